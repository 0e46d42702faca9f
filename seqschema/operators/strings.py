"""Statistics of strings, all declared on DataFrames: strings (model_key, string_id, seq) in, facts out.

Everything a learner needs is a union or sum over strings, so one pass of tagged facts and one aggregate make the
summary of all models at once, and summaries merge. Python takes part in levels(), on one small graph per model, and in
summarise_batches(), which sums the facts of many different strings by arrays before the same aggregate.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from seqschema.functions.solver import SINK, SOURCE, skipped_levels
from seqschema.functions.solver import levels as graph_levels
from seqschema.operators.stored import stored

#: Tags of facts: totals, symbols, pairs (a somewhere before b), edges (b directly after a), strings by length.
TOTAL, SYMBOL, PAIR, EDGE, LENGTH = "T", "S", "P", "E", "L"


def distinct_strings(strings: DataFrame) -> DataFrame:
    """(model_key, seq, n): duplicates carry nothing but their number. Null symbols are dropped before."""
    return strings.select("model_key", F.filter("seq", lambda s: s.isNotNull()).alias("seq")).groupBy("model_key", "seq").agg(F.count("*").alias("n"))


def dropped_symbols(strings: DataFrame) -> DataFrame:
    """(model_key, n): null symbols that distinct_strings leaves out."""
    return strings.groupBy("model_key").agg(F.sum(F.size(F.filter("seq", lambda s: s.isNull()))).cast("bigint").alias("n"))


def spans(seq: Column) -> Column:
    """Per symbol of a string: first and last position and number of occurrences."""
    back, size = F.reverse(seq), F.size(seq)
    return F.transform(
        F.array_distinct(seq),
        lambda s: F.struct(
            s.alias("sym"), F.array_position(seq, s).alias("first"), (size + 1 - F.array_position(back, s)).alias("last"),
            F.size(F.filter(seq, lambda x: x == s)).alias("cnt"),
        ),
    )


def alphabet(strings: DataFrame) -> DataFrame:
    return strings.select("model_key", F.explode(F.array_distinct("seq")).alias("sym")).where("sym IS NOT NULL").distinct()


def multiplicities(distinct: DataFrame) -> DataFrame:
    """(model_key, sym, present, min_cnt, max_cnt, op); min_cnt counts the strings that lack the symbol as zero."""
    totals = distinct.groupBy("model_key").agg(F.count("*").alias("d"))
    found = distinct.select("model_key", F.explode(spans(F.col("seq"))).alias("s")).groupBy("model_key", F.col("s.sym").alias("sym"))
    rows = found.agg(F.count("*").alias("present"), F.min("s.cnt").alias("low"), F.max("s.cnt").alias("max_cnt")).join(totals, "model_key")
    absent, many = F.col("present") < F.col("d"), F.col("max_cnt") > 1
    op = F.when(absent & many, "*").when(absent, "?").when(many, "+").otherwise("1")
    return rows.select("model_key", "sym", "present", F.when(absent, 0).otherwise(F.col("low")).alias("min_cnt"), "max_cnt", op.alias("op"))


def order_pairs(distinct: DataFrame) -> DataFrame:
    """(model_key, a, b, n_strings): a stands somewhere before b, from first and last positions."""
    pairs = distinct.select("model_key", "n", F.explode(_pairs(F.col("spans"))).alias("p")) if "spans" in distinct.columns else order_rows(distinct)
    return pairs.groupBy("model_key", F.col("p.a").alias("a"), F.col("p.b").alias("b")).agg(F.sum("n").alias("n_strings"))


def order_rows(distinct: DataFrame) -> DataFrame:
    return distinct.select("model_key", "n", F.explode(_pairs(spans(F.col("seq")))).alias("p"))


def _pairs(own: Column) -> Column:
    return F.flatten(F.transform(own, lambda x: F.transform(F.filter(own, lambda y: (x["first"] < y["last"]) & (x["sym"] != y["sym"])), lambda y: F.struct(x["sym"].alias("a"), y["sym"].alias("b")))))


def order_masks(distinct: DataFrame) -> DataFrame:
    """(model_key, a, word, mask): the successors of a as bits, 63 symbols to a word, in the order of the alphabet."""
    numbered = alphabet(distinct).withColumn("id", F.row_number().over(W.partitionBy("model_key").orderBy("sym")) - 1)
    rows = order_rows(distinct).select("model_key", "p.a", "p.b").distinct()
    met = rows.join(numbered.withColumnRenamed("sym", "b"), ["model_key", "b"])
    bit = F.call_function("shiftleft", F.lit(1).cast("bigint"), (F.col("id") % 63).cast("int"))
    return met.groupBy("model_key", "a", F.floor(F.col("id") / 63).cast("int").alias("word")).agg(F.bit_or(bit).alias("mask"))


def conflicts(pairs: DataFrame) -> DataFrame:
    """Pairs seen in both orders."""
    back = pairs.select("model_key", F.col("b").alias("a"), F.col("a").alias("b"))
    return pairs.select("model_key", "a", "b").join(back, ["model_key", "a", "b"], "left_semi")


def one_way(pairs: DataFrame) -> DataFrame:
    back = pairs.select("model_key", F.col("b").alias("a"), F.col("a").alias("b"))
    return pairs.select("model_key", "a", "b").join(back, ["model_key", "a", "b"], "left_anti")


def restrict(pairs: DataFrame, members: DataFrame) -> DataFrame:
    """Pairs with both ends in a set (model_key, sym)."""
    ends = [members.select("model_key", F.col("sym").alias(c)) for c in "ab"]
    return pairs.join(ends[0], ["model_key", "a"], "left_semi").join(ends[1], ["model_key", "b"], "left_semi").select(*pairs.columns)


def cooccurrence(distinct: DataFrame) -> DataFrame:
    """(model_key, a, b, n) for a < b: strings that hold both."""
    own = F.array_sort(F.array_distinct("seq"))
    pairs = F.flatten(F.transform(own, lambda x: F.transform(F.filter(own, lambda y: x < y), lambda y: F.struct(x.alias("a"), y.alias("b")))))
    return distinct.select("model_key", "n", F.explode(pairs).alias("p")).groupBy("model_key", "p.a", "p.b").agg(F.sum("n").alias("n"))


def never_together(distinct: DataFrame) -> DataFrame:
    """Pairs of a model's symbols that no string holds both of. The alphabet is small, each side is one model's."""
    own = alphabet(distinct)
    every = own.withColumnRenamed("sym", "a").join(own.withColumnRenamed("sym", "b"), "model_key").where("a < b")
    return every.join(cooccurrence(distinct), ["model_key", "a", "b"], "left_anti")


def symbol_automaton(distinct: DataFrame) -> DataFrame:
    """(model_key, src, dst, n): neighbours in strings, with marks for both ends."""
    return distinct.select("model_key", "n", F.explode(_edges(F.col("seq"))).alias("e")).groupBy("model_key", F.col("e.a").alias("src"), F.col("e.b").alias("dst")).agg(F.sum("n").alias("n"))


def _edges(seq: Column) -> Column:
    seq = seq.cast("array<string>")
    return F.zip_with(F.concat(F.array(F.lit(SOURCE)), seq), F.concat(seq, F.array(F.lit(SINK))), lambda a, b: F.struct(a.alias("a"), b.alias("b")))


def components(symbols: DataFrame, pairs: DataFrame, written=lambda df: stored(df, "components")) -> DataFrame:
    """(model_key, sym, comp): the least symbol of each component of the conflict graph, by rounds of taking the least
    label of the neighbours. For alphabets too large for the per-model solver. written(df) stores a round's table."""
    now = written(symbols.withColumn("comp", F.col("sym")))
    while True:
        seen = pairs.join(now.select("model_key", F.col("sym").alias("b"), "comp"), ["model_key", "b"]).groupBy("model_key", F.col("a").alias("sym")).agg(F.min("comp").alias("near"))
        new = written(now.join(seen, ["model_key", "sym"], "left").select("model_key", "sym", F.least("comp", F.coalesce("near", "comp")).alias("comp")))
        if new.join(now, ["model_key", "sym", "comp"], "left_anti").isEmpty():
            return new
        now = new


def contract(edges: DataFrame, comp: DataFrame) -> DataFrame:
    """(model_key, src, dst) between components; edges inside one are dropped."""
    ends = comp.select("model_key", "sym", "comp")
    out = edges
    for c in ("src", "dst"):
        out = out.join(ends.select("model_key", F.col("sym").alias(c), F.col("comp").alias(f"_{c}")), ["model_key", c], "left").withColumn(c, F.coalesce(f"_{c}", c)).drop(f"_{c}")
    return out.where("src <> dst").select("model_key", "src", "dst").distinct()


def levels(edges: DataFrame) -> DataFrame:
    """(model_key, node, level, skip): longest path from the source in a model's acyclic graph, however deep, and
    whether an edge skips that level. A contracted graph is small, so each model's is one task."""

    def solve(own: pd.DataFrame) -> pd.DataFrame:
        pairs = set(zip(own["src"], own["dst"], strict=True))
        level = graph_levels(pairs)
        skipped = skipped_levels(pairs, level)
        return pd.DataFrame([(own["model_key"].iloc[0], node, n, n in skipped) for node, n in level.items()], columns=["model_key", "node", "level", "skip"])

    return edges.groupBy("model_key").applyInPandas(solve, "model_key string, node string, level int, skip boolean")


def _facts(kind: str, a, bs, hi) -> Column:
    """Facts that differ in b only, as one struct."""
    return F.struct(F.lit(kind).alias("kind"), a.alias("a"), bs.alias("bs"), hi.cast("int").alias("hi"))


def _edge_codes(seq: Column) -> Column:
    """The distinct edges of a string, each as the bytes of its first end, a colon and both ends: equal codes are equal
    edges, and strings are told apart by hashing where structs are compared in pairs."""
    code = lambda a, b: F.concat(F.octet_length(a).cast("string"), F.lit(":"), a, b)
    return F.array_distinct(F.zip_with(F.concat(F.array(F.lit(SOURCE)), seq), F.concat(seq, F.array(F.lit(SINK))), code))


def _edge_ends(facts: DataFrame) -> DataFrame:
    """Facts with the ends of their edges read back from the codes, by bytes."""
    digits = F.substring_index("b", ":", 1)
    size, body = digits.cast("int"), F.substring(F.col("b").cast("binary"), F.length(digits) + 2, F.octet_length("b"))
    ends = F.substring(body, F.lit(1), size).cast("string"), F.substring(body, size + 1, F.octet_length("b")).cast("string")
    edge = F.col("kind") == EDGE
    return facts.withColumns({"a": F.when(edge, ends[0]).otherwise(F.col("a")), "b": F.when(edge, ends[1]).otherwise(F.col("b"))})


def summarise(strings: DataFrame, need_distinct: bool = True) -> DataFrame:
    """The summary of every model as tagged facts (model_key, kind, a, b, n, w, hi), in one aggregate.

    n counts distinct strings, w strings, hi the most occurrences of a symbol in one string. Without need_distinct the
    strings are not shuffled: operators, pairs and edges are the same, n counts duplicates, and lengths are left out.
    """
    if need_distinct:
        return summarise_distinct(distinct_strings(strings))
    return summarise_distinct(strings.select("model_key", F.filter("seq", lambda s: s.isNotNull()).alias("seq"), F.lit(1).cast("bigint").alias("n")), lengths=False)


def summarise_distinct(rows: DataFrame, lengths: bool = True) -> DataFrame:
    """The same of (model_key, seq, n): strings without null symbols and the number of each.

    What stands behind a symbol's first place, itself left out, is what it stands before. Each symbol is one struct with
    all of these, and they become rows by a second explode, so that no lambda runs for a pair."""
    rows = rows.select("model_key", "n", F.col("seq").cast("array<string>").alias("seq")).withColumn("size", F.size("seq"))
    none, nil = F.lit(""), F.lit(0)
    own, single = F.array_distinct("seq"), F.array(none)
    behind = lambda x: F.array_remove(F.array_distinct(F.slice("seq", F.array_position("seq", x).cast("int") + 1, F.col("size"))), x)
    parts = [
        F.array(_facts(TOTAL, none, single, nil), _facts(EDGE, none, _edge_codes(F.col("seq")), nil)),
        F.transform(own, lambda x: _facts(SYMBOL, x, single, F.col("size") - F.size(F.array_remove("seq", x)))),
        F.transform(own, lambda x: _facts(PAIR, x, behind(x), nil)),
    ]
    if lengths:
        parts.append(F.array(_facts(LENGTH, F.col("size").cast("string"), single, nil)))
    facts = rows.select("model_key", "n", F.explode_outer(F.concat(*parts)).alias("f")).select("model_key", "n", "f.kind", "f.a", "f.hi", F.explode_outer("f.bs").alias("b")).where("b IS NOT NULL")
    summed = facts.groupBy("model_key", "kind", "a", "b").agg(F.count("*").alias("n"), F.sum("n").alias("w"), F.max("hi").alias("hi"))
    return _edge_ends(summed)


#: Columns of a summary; facts that a worker sums before it hands them on, candidates for pairs it looks at in one step.
FACTS = "model_key string, kind string, a string, b string, n bigint, w bigint, hi int"
HELD, LOOKED = 200_000, 4_000_000


def _summed(kind: str, a: pa.Array, b: pa.Array, code: np.ndarray, weight: np.ndarray, hi: np.ndarray | None = None) -> pa.Table:
    """Facts by number: a and b give the ends of each of the sorted different codes found, weight what each stands for."""
    order = np.argsort(code, kind="stable")
    found, start = np.unique(code[order], return_index=True)
    n = np.diff(start, append=len(code))
    w = np.add.reduceat(weight[order], start) if len(start) else np.zeros(0, np.int64)
    most = np.maximum.reduceat(hi[order], start) if hi is not None and len(start) else np.zeros(len(found), np.int64)
    ends = [x(found) for x in (a, b)]
    return pa.table({"kind": pa.array([kind] * len(found), pa.string()), "a": ends[0], "b": ends[1], "n": pa.array(n, pa.int64()), "w": pa.array(w, pa.int64()), "hi": pa.array(most.astype(np.int32))})


def batch_facts(seqs: pa.ListArray, weights: np.ndarray) -> pa.Table:
    """(kind, a, b, n, w, hi): the facts of one model's strings, which hold no nulls."""
    size = np.diff(seqs.offsets.to_numpy())
    coded = pa.concat_arrays([seqs.flatten().cast(pa.string()), pa.array([SOURCE, SINK, ""])]).dictionary_encode()  # a symbol may be a mark
    code, names, k = coded.indices.to_numpy().astype(np.int64), coded.dictionary, len(coded.dictionary)
    code, (source, sink, none) = code[:-3], code[-3:]
    row, start = np.repeat(np.arange(len(size)), size), np.cumsum(size) - size
    place = np.arange(len(code)) - np.repeat(start, size)
    first_end, second_end = (lambda x: names.take(pa.array(x // k))), (lambda x: names.take(pa.array(x % k)))
    length = lambda x: pa.array(x.astype(str).tolist(), pa.string())
    whole = np.full(len(size), none * k + none)
    out = [_summed(TOTAL, first_end, second_end, whole, weights), _summed(LENGTH, length, lambda x: pa.array([""] * len(x), pa.string()), size, weights)]
    # each symbol of a string once, by string: its first and last place and its number
    order = np.argsort(row * k + code, kind="stable")
    at = row[order] * k + code[order]
    begin = np.flatnonzero(np.diff(at, prepend=-1))
    count = np.diff(begin, append=len(at))
    own, sym, first, last = row[order][begin], code[order][begin], place[order][begin], place[order][begin + count - 1]
    out.append(_summed(SYMBOL, first_end, second_end, sym * k + none, weights[own], count))
    edges = np.unique(np.concatenate([
        np.stack([row, np.where(place == 0, source, np.roll(code, 1)), code], 1), np.stack([np.arange(len(size)), np.where(size > 0, code[np.minimum(start + size, len(code)) - 1] if len(code) else source, source), np.full(len(size), sink)], 1),
    ]) @ np.array([k * k, k, 1]))
    out.append(_summed(EDGE, first_end, second_end, edges % (k * k), weights[edges // (k * k)]))
    many, head = np.unique(own, return_counts=True)[1], np.flatnonzero(np.diff(own, prepend=-1))
    for m in np.unique(many[many > 1]):
        heads = head[many == m]
        step = max(1, LOOKED // int(m * m))
        for j in range(0, len(heads), step):
            block = heads[j : j + step, None] + np.arange(m)
            ahead = first[block][:, :, None] < last[block][:, None, :]
            ahead[:, np.arange(m), np.arange(m)] = False
            which, x, y = np.nonzero(ahead)
            out.append(_summed(PAIR, first_end, second_end, sym[block[which, x]] * k + sym[block[which, y]], weights[own[block[which, 0]]]))
    return pa.concat_tables(out)


def summarise_batches(distinct: DataFrame) -> DataFrame:
    """summarise_distinct() for many different short strings: workers sum the facts of whole batches by arrays, and only
    sums are shuffled. Which strings stand in one batch makes no difference."""
    keys, sums = ["model_key", "kind", "a", "b"], [("n", "sum"), ("w", "sum"), ("hi", "max")]

    def fold(tables: list[pa.Table]) -> pa.Table:
        t = pa.concat_tables(tables).group_by(keys).aggregate(sums)
        return t.select([*keys, *(f"{c}_{how}" for c, how in sums)]).rename_columns([*keys, "n", "w", "hi"])

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, rows = [], 0
        for b in batches:
            model, weights = b.column(0).dictionary_encode(), b.column(2).to_numpy(zero_copy_only=False)
            of = model.indices.fill_null(-1).to_numpy(zero_copy_only=False)
            for i in np.unique(of).tolist():
                mine = np.flatnonzero(of == i)
                t = batch_facts(b.column(1).take(pa.array(mine)), weights[mine])
                held.append(t.add_column(0, "model_key", pa.array([model.dictionary[i].as_py() if i >= 0 else None] * len(t), pa.string())))
                rows += len(t)
            if rows > HELD:
                held = [fold(held)]
                rows = len(held[0])
                if 2 * rows > HELD:
                    yield from held[0].combine_chunks().to_batches(20_000)
                    held, rows = [], 0
        if held:
            yield from fold(held).combine_chunks().to_batches(20_000)

    rows = distinct.select("model_key", F.col("seq").cast("array<string>").alias("seq"), F.col("n").cast("bigint").alias("n"))
    return rows.mapInArrow(work, FACTS).groupBy(*keys).agg(F.sum("n").alias("n"), F.sum("w").alias("w"), F.max("hi").alias("hi"))


def merge_summaries(*summaries: DataFrame) -> DataFrame:
    """The summary of all inputs together. Counts add up: strings present in two inputs count in both, consistently."""
    both = reduce(lambda x, y: x.unionByName(y), summaries)
    return both.groupBy("model_key", "kind", "a", "b").agg(F.sum("n").alias("n"), F.sum("w").alias("w"), F.max("hi").alias("hi"))


def summarise_chunks(chunks: DataFrame) -> DataFrame:
    """The summary of strings too long for one row: (model_key, string_id, chunk_no, seq). Positions are offset by the
    chunks before, counts add up over chunks, and an edge joins the end of each chunk to the start of the next."""
    rows = chunks.select("model_key", "string_id", "chunk_no", F.filter("seq", lambda s: s.isNotNull()).cast("array<string>").alias("seq")).where(F.size("seq") > 0)
    order = W.partitionBy("model_key", "string_id").orderBy("chunk_no")
    placed = rows.withColumn("base", F.coalesce(F.sum(F.size("seq")).over(order.rowsBetween(W.unboundedPreceding, -1)), F.lit(0))).withColumn("next", F.lead(F.col("seq")[0], 1, SINK).over(order)).withColumn("nth", F.row_number().over(order))
    one = placed.select("model_key", "string_id", "base", F.explode(spans(F.col("seq"))).alias("s")).groupBy("model_key", "string_id", F.col("s.sym").alias("sym"))
    whole = one.agg(F.min(F.col("base") + F.col("s.first")).alias("first"), F.max(F.col("base") + F.col("s.last")).alias("last"), F.sum("s.cnt").cast("int").alias("cnt"))
    own = whole.groupBy("model_key", "string_id").agg(F.array_sort(F.collect_list(F.struct("sym", "first", "last", "cnt"))).alias("own"))
    totals = chunks.select("model_key", "string_id").distinct().select("model_key", F.lit(TOTAL).alias("kind"), F.lit("").alias("a"), F.lit("").alias("b"), F.lit(0).alias("hi"))
    symbols = whole.select("model_key", F.lit(SYMBOL).alias("kind"), F.col("sym").alias("a"), F.lit("").alias("b"), F.col("cnt").alias("hi"))
    pairs = own.select("model_key", F.lit(PAIR).alias("kind"), F.explode(_pairs(F.col("own"))).alias("p")).select("model_key", "kind", "p.a", "p.b", F.lit(0).alias("hi"))
    inner = F.zip_with(F.col("seq"), F.concat(F.slice("seq", 2, F.size("seq")), F.array("next")), lambda a, b: F.struct(a.alias("a"), b.alias("b")))
    start = F.when(F.col("nth") == 1, F.array(F.struct(F.lit(SOURCE).alias("a"), F.col("seq")[0].alias("b")))).otherwise(F.array().cast("array<struct<a:string,b:string>>"))
    edges = placed.select("model_key", "string_id", F.explode(F.array_distinct(F.concat(start, inner))).alias("e")).select("model_key", "string_id", "e.a", "e.b").distinct()
    void = chunks.groupBy("model_key", "string_id").agg(F.sum(F.size(F.filter("seq", lambda s: s.isNotNull()))).alias("len")).where("len = 0").select("model_key", "string_id", F.lit(SOURCE).alias("a"), F.lit(SINK).alias("b"))
    edges = edges.unionByName(void).select("model_key", F.lit(EDGE).alias("kind"), "a", "b", F.lit(0).alias("hi"))
    every = reduce(lambda x, y: x.unionByName(y), [totals, symbols, pairs, edges])
    return every.groupBy("model_key", "kind", "a", "b").agg(F.count("*").alias("n"), F.count("*").alias("w"), F.max("hi").alias("hi"))


def length_hist(distinct: DataFrame) -> DataFrame:
    return distinct.groupBy("model_key", F.size("seq").alias("len")).agg(F.count("*").alias("n_distinct"), F.sum("n").alias("n_strings"))
