"""What the text operators share: Arrow passes over whole rows, shared folders, written intermediate tables."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Callable, Iterator, Sequence

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

UPPER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
LOWER = "abcdefghijklmnopqrstuvwxyz"

#: Rows and bytes of an Arrow batch: long texts must not add up to more than a worker can hold.
BATCH_ROWS, BATCH_BYTES = 512, 16 << 20


def bound_batches(spark: SparkSession) -> None:
    """Lower the session's Arrow batch size (a runtime setting) so that long texts come in small batches."""
    for key, most in (("spark.sql.execution.arrow.maxRecordsPerBatch", BATCH_ROWS), ("spark.sql.execution.arrow.maxBytesPerBatch", BATCH_BYTES)):
        now = str(spark.conf.get(key)).lower().rstrip("b")
        if not (now.isdigit() and 0 < int(now) <= most):  # not set, no bound, or written with a unit
            spark.conf.set(key, str(most))


def spare(columns: Sequence[str], *names: str) -> list[str]:
    """The names, with underscores behind them until no column has them (in any case)."""
    taken, out = {c.lower() for c in columns}, []
    for name in names:
        while name.lower() in taken:
            name += "_"
        taken.add(name.lower())
        out.append(name)
    return out


def row_order(df: DataFrame, *first: str):
    """What rows are ordered by where any order would do but must always be the same: hashes of the first columns, then
    of the whole row."""
    part = {f.name: F.to_json(F.col(f"`{f.name}`")) if "map<" in f.dataType.simpleString() or f.dataType.simpleString() == "variant" else F.col(f"`{f.name}`") for f in df.schema}
    return [*(F.xxhash64(part[c]) for c in first), F.xxhash64(*part.values())]


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: the session's spark.checkpoint.dir; only a local master may go without."""
    named = spark.sparkContext.getConf().get("spark.checkpoint.dir") or spark.conf.get("spark.checkpoint.dir", None)
    if not named:
        at = spark.sparkContext._jsc.sc().getCheckpointDir()
        named = at.get() if at.isDefined() else None
    if not named:
        if not spark.sparkContext.master.startswith("local["):
            raise ValueError("spark.checkpoint.dir is not set: a cluster needs a folder that all executors share")
        named = tempfile.mkdtemp(prefix="shared-")
        spark.sparkContext.setCheckpointDir(named)
    return named.rstrip("/")


def fresh_dir(spark: SparkSession, name: str) -> str:
    return f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"


def written(df: DataFrame, name: str) -> DataFrame:
    """Write a table to the shared folder and read it again: cuts the lineage, survives lost executors, computes once."""
    spark = df.sparkSession
    path = fresh_dir(spark, name)
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


#: Rows of a class that make it hot, at least; the share of all rows that makes it hot, so that few classes can be.
HOT_ROWS, HOT_SHARE = 100_000, 10_000


def join_classes(rows: DataFrame, classes: DataFrame, keys: Sequence[str], size: str, hot_rows: int = HOT_ROWS) -> DataFrame:
    """rows with the columns of their class, without size. Keys are not null and name each class once; size says how
    many rows it has. Hot classes, at most HOT_SHARE of them by their size, are broadcast; the others are shuffled and
    none is larger than a task can hold. Both tables should be written ones: they are read twice where a class is hot."""
    total, most = classes.agg(F.sum(size), F.max(size)).first()
    least = max(hot_rows, (total or 0) // HOT_SHARE)
    plain = classes.drop(size)
    if (most or 0) <= least:
        return rows.join(plain, list(keys))
    hot = F.broadcast(classes.where(F.col(size) > least).drop(size))
    cold = rows.join(hot, list(keys), "left_anti").join(classes.where(F.col(size) <= least).drop(size), list(keys))
    return rows.join(hot, list(keys)).unionByName(cold)


def lower_ascii(text):
    """A-Z to a-z and nothing else; the cheap built-in is right where the text holds ASCII only."""
    return F.when(F.octet_length(text) == F.char_length(text), F.lower(text)).otherwise(F.translate(text, UPPER, LOWER))


def append_columns(
    df: DataFrame,
    text_col: str,
    kernel: Callable[[], Callable[[list[str], pa.RecordBatch], Sequence[pa.Array]]],
    fields: Sequence[tuple[str, T.DataType]],
    keep: Sequence[str] | None = None,
    also: Sequence[str] = (),
) -> DataFrame:
    """One Arrow pass: rows keep the columns named in keep (all by default) and get the kernel's columns.

    kernel() is called once for each partition and gives a function from (texts, batch) to arrays; a null text is the
    empty text. Columns of df with the name of a new one give way to it. also: columns the kernel reads beside the text.
    """
    bound_batches(df.sparkSession)
    new = {name for name, _ in fields}
    kept = [c for c in (df.columns if keep is None else keep) if c not in new]
    sent = list(dict.fromkeys([*kept, text_col, *also]))
    src = df.select(*[F.col(f"`{c}`") for c in sent])
    schema = T.StructType([src.schema[c] for c in kept] + [T.StructField(n, t) for n, t in fields])
    names = [*kept, *(n for n, _ in fields)]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        work = kernel()
        at = sent.index(text_col)
        for batch in batches:
            if batch.num_rows:
                texts = [x or "" for x in batch.column(at).to_pylist()]
                yield pa.RecordBatch.from_arrays([batch.column(sent.index(c)) for c in kept] + list(work(texts, batch)), names=names)

    return src.mapInArrow(run, schema)


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")
