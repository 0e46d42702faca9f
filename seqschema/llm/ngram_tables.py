"""Hashed n-gram counts over a whole corpus, and their fixed-size totals on every executor.

Words are hashed to numbers below a power of two, n-grams to buckets below another. Each task adds up arrays over all
its rows and hands on only slices of them, packed; the slices are summed by number in a second pass. What moves grows
with the number of tasks, never with the number of words in a task, and what reaches the driver has the size of the
tables, which is a parameter.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator, Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from seqschema.llm.common import bound_batches, written

SLICES = 64


IS_SPACE = np.zeros(256, bool)
IS_SPACE[[9, 10, 11, 12, 13, 32]] = True
FACTORS = np.random.default_rng(20).integers(0, 2**64, 64, np.uint64) | np.uint64(1)


def word_numbers(data: bytes, part: int = 1 << 21) -> Iterator[np.ndarray]:
    """64-bit numbers of the words (split at ASCII white space) of a text, some words at a time: a multilinear hash of
    the bytes, worked out for all words of a part at once. A part ends at white space."""
    at = 0
    while at < len(data):
        end = at + part
        while end < len(data) and not IS_SPACE[data[end]]:
            end += 1
        b = np.frombuffer(data, np.uint8, min(end, len(data)) - at, at)
        at = end
        word = ~IS_SPACE[b]
        edges = np.flatnonzero(np.diff(word, prepend=False, append=False))
        size = edges[1::2] - edges[0::2]
        if not len(size):
            continue
        first = np.cumsum(size) - size
        letters = b[word].astype(np.uint64) + np.uint64(1)
        place = np.arange(len(letters)) - np.repeat(first, size)
        factors = FACTORS[place & 63]
        with np.errstate(over="ignore"):
            if size.max() > 64:  # letters 64 apart get factors of their own
                factors = factors + (place >> 6).astype(np.uint64) * np.uint64(0x9E3779B97F4A7C16)
            n = np.add.reduceat(letters * factors, first) + size.astype(np.uint64)
            n = (n ^ (n >> np.uint64(31))) * np.uint64(0xD6E8FEB86659FD93)
        yield n ^ (n >> np.uint64(32))


def mix(a: np.ndarray, b: np.ndarray, bits: int) -> np.ndarray:
    """A bucket below 2**bits for each pair of numbers."""
    with np.errstate(over="ignore"):
        return ((a * np.uint64(0x9E3779B97F4A7C15) + b) * np.uint64(0xD6E8FEB86659FD93)) >> np.uint64(64 - bits)


def total_tables(
    rows: DataFrame, columns: Sequence[str], names: Sequence[str], sizes: Sequence[int],
    add: Callable[[], Callable[[pa.RecordBatch, list[np.ndarray]], None]],
) -> dict[str, np.ndarray]:
    """Tables of 64-bit counts, summed over all rows. add() gives a function that adds a batch to a task's tables."""
    bound_batches(rows.sparkSession)
    src = rows.select(*columns)

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tables, work, some = [np.zeros(n, np.int64) for n in sizes], add(), False
        for b in batches:
            if b.num_rows:
                work(b, tables)
                some = True
        if some:
            for k, table in enumerate(tables):
                for i, part in enumerate(np.array_split(table, min(SLICES, len(table)))):
                    if part.any():
                        data = part.astype(np.uint32) if part.min() >= 0 and part.max() < 2**32 else part
                        yield pa.RecordBatch.from_arrays([pa.array([k * SLICES + i], pa.int32()), pa.array([data.tobytes()], pa.binary()), pa.array([data.itemsize], pa.int32())], names=["slice", "data", "width"])

    def add_up(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        totals: dict[int, np.ndarray] = {}
        for b in batches:
            for i, data, width in zip(*(c.to_pylist() for c in b.columns), strict=True):
                part = np.frombuffer(data, np.uint32 if width == 4 else np.int64).astype(np.int64)
                totals[i] = totals[i] + part if i in totals else part
        if totals:
            yield pa.RecordBatch.from_arrays([pa.array(list(totals), pa.int32()), pa.array([x.tobytes() for x in totals.values()], pa.binary())], names=["slice", "data"])

    parts = src.mapInArrow(count, "slice int, data binary, width int")
    # a slice's partial counts meet in two steps: first by slice and salt, so that no task gets them all
    salted = parts.withColumn("salt", F.spark_partition_id() % 16).repartition("slice", "salt").select("slice", "data", "width")
    half = salted.mapInArrow(lambda it: (pa.RecordBatch.from_arrays([*x.columns, pa.array([8] * x.num_rows, pa.int32())], names=["slice", "data", "width"]) for x in add_up(it)), "slice int, data binary, width int")
    summed = half.repartition("slice").mapInArrow(add_up, "slice int, data binary").collect()
    out = {}
    for k, (name, size) in enumerate(zip(names, sizes, strict=True)):
        pieces = np.array_split(np.zeros(size, np.int64), min(SLICES, size))
        for r in summed:
            if r["slice"] // SLICES == k:
                pieces[r["slice"] % SLICES] = np.frombuffer(bytes(r["data"]), np.int64)
        out[name] = np.concatenate(pieces)
    return out


def trusted_flag(docs: DataFrame, labels: DataFrame, name: str = "_trusted", bound: int = 1_000_000) -> DataFrame:
    """Documents with a flag: labelled of good quality and not toxic by any of their labels.

    Labels without a doc_id count for nothing. Up to `bound` such documents the list of their ids is broadcast (8 MB at
    most), and the texts need not move. A longer list is joined by a shuffle on the ids, and the flagged documents are
    written, so that they move once; documents without a doc_id stay out of it. Every labelled document counts.
    """
    good = labels.where("doc_id IS NOT NULL").groupBy("doc_id").agg(F.max(F.coalesce(F.col("quality"), F.lit(0))).alias("_q"), F.max(F.coalesce(F.col("toxic"), F.lit(0))).alias("_t"))
    good = good.where("_q = 1 AND _t = 0").select(F.col("doc_id").alias("_good_id"))
    met = F.col("doc_id") == F.col("_good_id")
    if good.count() <= bound:
        return docs.join(F.broadcast(good), met, "left").withColumn(name, F.col("_good_id").isNotNull()).drop("_good_id")
    flagged = docs.where("doc_id IS NOT NULL").join(good.hint("shuffle_merge"), met, "left").withColumn(name, F.col("_good_id").isNotNull()).drop("_good_id")
    return written(flagged.unionByName(docs.where("doc_id IS NULL").withColumn(name, F.lit(False))), "flagged")
