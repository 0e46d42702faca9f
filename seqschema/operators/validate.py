"""Membership of strings in models, and reports on what does not fit.

Level-chain models (those with groups) are tested by SQL expressions on first and last positions. Models of other
classes have an expression only: its derivatives are tested in Arrow batches, once for each distinct string."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from seqschema.functions.expr import parse_expr, symbols
from seqschema.functions.registry import matches_udf
from seqschema.operators.learners import GROUPS, learn
from seqschema.operators.stored import stored
from seqschema.operators.strings import spans, summarise

#: Models are broadcast up to this many rows, else joined by key.
BROADCAST_MODELS = 10_000


def places(groups: Column) -> Column:
    """Per symbol of a model: numbers of its group and chain, position in the chain, operator."""
    numbered = F.transform(groups, lambda g, i: F.struct(i.alias("g"), g["chains"].alias("chains")))
    chains = F.flatten(F.transform(numbered, lambda x: F.transform(x["chains"], lambda c, k: F.struct(x["g"].alias("g"), k.alias("c"), c.alias("items")))))
    return F.flatten(F.transform(chains, lambda x: F.transform(x["items"], lambda s, p: F.struct(s["sym"].alias("sym"), x["g"].alias("g"), x["c"].alias("c"), p.alias("p"), s["op"].alias("op")))))


def reason(seq: Column, place: Column) -> Column:
    """Why a string does not fit, or null: unknown symbol, count, or order. A string fits if its counts fit and no symbol
    stands after one that belongs later: in a later group, or later in the same chain."""
    own = spans(F.filter(seq, lambda s: s.isNotNull()))
    at = F.transform(own, lambda x: F.struct(x["first"].alias("first"), x["last"].alias("last"), x["cnt"].alias("cnt"), F.element_at(F.filter(place, lambda q: q["sym"] == x["sym"]), 1).alias("q")))
    unknown = F.exists(own, lambda x: ~F.exists(place, lambda q: q["sym"] == x["sym"]))
    many = F.exists(own, lambda x: (x["cnt"] > 1) & F.exists(place, lambda q: (q["sym"] == x["sym"]) & q["op"].isin("1", "?")))
    missing = F.exists(place, lambda q: q["op"].isin("1", "+") & ~F.exists(own, lambda x: x["sym"] == q["sym"]))
    later = lambda x, y: (x["q"]["g"] < y["q"]["g"]) | ((x["q"]["g"] == y["q"]["g"]) & (x["q"]["c"] == y["q"]["c"]) & (x["q"]["p"] < y["q"]["p"]))
    order = F.exists(at, lambda x: F.exists(at, lambda y: later(x, y) & (x["last"] > y["first"])))
    return F.when(unknown, "unknown").when(many | missing, "count").when(F.try_element_at(F.array(order), F.lit(1)), "order")


def validate(strings: DataFrame, models: DataFrame) -> DataFrame:
    """strings with ok and reason, once for each model of their key (with the model's learner, where models name one).
    The reason is unknown, count or order for level-chain models, unknown or "no match" for others, and "no model" for
    strings of a key without one. Null symbols are left out of a string."""
    named = ["learner"] if "learner" in models.columns else []
    groups = F.col("groups") if "groups" in models.columns else F.lit(None).cast(GROUPS)
    known = stored(models.select("model_key", *named, "expr", groups.alias("_groups")), "models")
    n_models, n_other = known.agg(F.count("*"), F.count(F.when(F.col("_groups").isNull(), 1))).first()
    few = F.broadcast if n_models <= BROADCAST_MODELS else lambda df: df
    seq = F.filter(F.col("seq").cast("array<string>"), lambda x: x.isNotNull())
    told = known.select("model_key", *named, F.when(F.col("_groups").isNotNull(), places(F.col("_groups"))).alias("_place"), "expr").withColumnRenamed("expr", "_expr")
    met = strings.join(few(told), "model_key", "left")
    why = F.when(F.col("_expr").isNull(), "no model").when(F.col("_place").isNotNull(), reason(F.col("seq").cast("array<string>"), F.col("_place")))
    if n_other:
        plain = strings.select("model_key", seq.alias("_seq")).distinct()
        other = few(known.where("_groups IS NULL").select("model_key", F.col("expr").alias("_expr")).distinct())
        judged = plain.join(other, "model_key").select("model_key", "_seq", "_expr", F.when(has_unknown(F.col("_seq"), F.col("_expr")), "unknown").when(~matches_udf()("_seq", "_expr"), "no match").alias("_why"))
        met = met.withColumn("_seq", seq).join(judged, ["model_key", "_seq", "_expr"], "left")
        why = F.coalesce(why, "_why")
    return met.withColumn("reason", why).withColumn("ok", F.col("reason").isNull()).drop("_place", "_expr", "_seq", "_why")


def has_unknown(seq: Column, text: Column) -> Column:
    @F.pandas_udf("boolean")
    def unknown(seqs: pd.Series, texts: pd.Series) -> pd.Series:
        return pd.Series([not set(s) <= set(symbols(parse_expr(t))) for s, t in zip(seqs, texts, strict=True)])

    return unknown(seq, text)


def coverage(strings: DataFrame, models: DataFrame) -> DataFrame:
    """(model_key, learner where models name one, coverage, n_strings)."""
    own = ["model_key", *(["learner"] if "learner" in models.columns else [])]
    return validate(strings, models).groupBy(*own).agg(F.avg(F.col("ok").cast("double")).alias("coverage"), F.count("*").alias("n_strings"))


def holdout(strings: DataFrame, percent: int) -> DataFrame:
    """Learn on the strings whose numeric id falls into the first percents, accept on the rest."""
    chosen = F.pmod(F.col("string_id"), F.lit(100)) < percent
    return coverage(strings.where(~chosen), learn(summarise(strings.where(chosen)))).withColumn("percent", F.lit(percent))
