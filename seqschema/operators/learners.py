"""Learners over all models at once: strings to a summary in one shuffle, then one small task per model."""

from __future__ import annotations

from collections.abc import Iterable, Mapping

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from seqschema.functions import counting, solver
from seqschema.functions.solver import LEARNERS, Summary
from seqschema.operators import strings as st
from seqschema.operators.stored import stored

GROUPS = "array<struct<chains:array<array<struct<sym:string,op:string>>>,opt:boolean>>"
MODELS = f"model_key string, learner string, expr string, groups {GROUPS}, n_symbols int, n_strings bigint, n_distinct bigint, n_groups int, n_repairs int"


def summary_of(facts: pd.DataFrame, min_support: int = 0) -> Summary:
    """One model's facts as a Summary; facts seen in fewer than min_support strings are ignored."""
    out = Summary()
    rows = list(zip(facts["kind"], facts["a"], facts["b"], facts["n"], facts["w"], facts["hi"], strict=True))
    weak = {a for kind, a, _, _, w, _ in rows if kind == st.SYMBOL and w < min_support}
    for kind, a, b, n, w, hi in rows:
        if kind == st.TOTAL:
            out.strings, out.weight = int(n), int(w)
        elif kind == st.SYMBOL and a not in weak:
            out.present[a], out.most[a] = int(n), int(hi)
        elif kind == st.PAIR and w >= min_support and not {a, b} & weak:
            out.before.add((a, b))
        elif kind == st.EDGE and w >= min_support and not {a, b} & weak:
            out.follows.add((a, b))
    if weak or min_support:  # every symbol stays on a path from source to sink
        out.follows |= {(solver.SOURCE, a) for a in out.present if all(y != a for _, y in out.follows)}
        out.follows |= {(a, solver.SINK) for a in out.present if all(x != a for x, _ in out.follows)}
    return out


def learn(summary: DataFrame, learners: Mapping[str, dict] | Iterable[str] = ("level_chain",), min_support: int = 0) -> DataFrame:
    """A row for each model and learner. learners: names, or names with options; a name may carry a label after a colon,
    such as outer_shuffle:exact."""
    asked = learners if isinstance(learners, Mapping) else dict.fromkeys(learners, {})

    def solve(facts: pd.DataFrame) -> pd.DataFrame:
        key, s, rows = facts["model_key"].iloc[0], summary_of(facts, min_support), []
        for name, options in asked.items():
            if not s.present:
                continue
            got = LEARNERS[name.partition(":")[0]](s, **options)
            groups = None if got["groups"] is None else [{"chains": [[{"sym": a, "op": op} for a, op in c] for c in chains], "opt": opt} for chains, opt in got["groups"]]
            rows.append((key, name, got["expr"], groups, len(s.present), s.weight, s.strings, got["n_groups"], got["n_repairs"]))
        return pd.DataFrame(rows, columns=[c.split()[0] for c in ("model_key", "learner", "expr", "groups", "n_symbols", "n_strings", "n_distinct", "n_groups", "n_repairs")])

    return summary.where(F.col("kind") != st.LENGTH).groupBy("model_key").applyInPandas(solve, MODELS)


def _infer(name: str):
    def infer(strings: DataFrame, min_support: int = 0, **options) -> DataFrame:
        return learn(st.summarise(strings), {name: options}, min_support)

    infer.__name__ = f"infer_{name}"
    infer.__doc__ = f"strings (model_key, string_id, seq) to models by the {name.replace('_', ' ')} learner."
    return infer


infer_level_chain = _infer("level_chain")
infer_outer_shuffle = _infer("outer_shuffle")
infer_disjunctive_bag = _infer("disjunctive_bag")
infer_all_shuffle = _infer("all_shuffle")
infer_chain_factor = _infer("chain_factor")
infer_single_occurrence = _infer("single_occurrence")
infer_universal = _infer("universal")


def learn_by_sampling(strings: DataFrame, percent: int, checked, rounds: int = 10) -> DataFrame:
    """Learn on a hashed share of the strings, test all, add the rejected ones, until none is left: cheap scans instead
    of a heavy one; ends because summaries only grow. checked(strings, models) gives strings with a column ok."""
    share = F.pmod(F.xxhash64("model_key", "seq"), F.lit(100)) < percent
    summary = stored(st.summarise(strings.where(share)), "summary")
    for _ in range(rounds):
        models = stored(learn(summary), "models")
        rejected = checked(strings, models).where("NOT ok").select("model_key", "string_id", "seq")
        if rejected.isEmpty():
            return models
        summary = stored(st.merge_summaries(summary, st.summarise(rejected)), "summary")
    return learn(st.summarise(strings))


MEASURES = "model_key string, learner string, expr string, ls decimal(38,0), ls_log2 double, data_cost double, shuffle_count decimal(38,0)"


def measure(models: DataFrame, summary: DataFrame) -> DataFrame:
    """language size, its log2, data cost and shuffle count of each model; sizes beyond 38 digits are null but for log2."""
    import decimal
    import math

    def work(key, left: pd.DataFrame, right: pd.DataFrame) -> pd.DataFrame:
        lengths = {int(a): int(n) for a, n in zip(right["a"], right["n"], strict=True)}
        rows = []
        for learner, text in zip(left["learner"], left["expr"], strict=True):
            try:
                size, cost = counting.language_size(text), counting.data_cost(text, lengths)
            except ValueError:
                size = cost = None
            shuffles = counting.shuffle_count(text)
            small = lambda x: decimal.Decimal(x) if x is not None and x < 10**38 else None
            rows.append((key[0], learner, text, small(size), math.log2(size) if size else None, cost, small(shuffles)))
        return pd.DataFrame(rows, columns=["model_key", "learner", "expr", "ls", "ls_log2", "data_cost", "shuffle_count"])

    return models.select("model_key", "learner", "expr").groupBy("model_key").cogroup(summary.where(F.col("kind") == st.LENGTH).groupBy("model_key")).applyInPandas(work, MEASURES)


def compare_learners(strings: DataFrame, learners=("level_chain", "outer_shuffle", "disjunctive_bag", "all_shuffle")) -> DataFrame:
    """All learners on one summary, with measures, rank by language size and the ratio to the smallest in log2."""
    from pyspark.sql import Window as W

    summary = stored(st.summarise(strings), "summary")  # read by the learners and by the measures
    got = measure(learn(summary, learners), summary)
    own = W.partitionBy("model_key")
    return got.withColumn("rank", F.rank().over(own.orderBy("ls_log2"))).withColumn("log2_ratio", F.col("ls_log2") - F.min("ls_log2").over(own))
