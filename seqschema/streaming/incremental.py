"""Incremental inference: each micro-batch is summarised and merged into the summary so far; strings are not kept.

Versions are named by batch id, so a batch that runs again writes the same version again. A late string is merged like
any other. Windows go into the model key.
"""

from __future__ import annotations

import json
from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from seqschema.operators.learners import learn
from seqschema.operators.strings import PAIR, merge_summaries, summarise


def _versions(spark, folder: str) -> list[int]:
    path = spark._jvm.org.apache.hadoop.fs.Path(folder)
    fs = path.getFileSystem(spark._jsc.hadoopConfiguration())
    done = [s.getPath() for s in fs.listStatus(path)] if fs.exists(path) else []
    return sorted(int(p.getName().split("=")[1]) for p in done if p.getName().startswith("version=") and fs.exists(spark._jvm.org.apache.hadoop.fs.Path(p, "_SUCCESS")))


def merge_batch(folder: str, changed: Callable[[DataFrame, int], None] | None = None, need_distinct: bool = False):
    """A foreachBatch function. folder gets summary/version=N and models/version=N; changed(models, N) sees the models
    whose expression differs from the version before."""

    def merge(batch: DataFrame, number: int) -> None:
        spark = batch.sparkSession
        before = [v for v in _versions(spark, f"{folder}/summary") if v < number]
        facts = summarise(batch, need_distinct)
        old = spark.read.parquet(f"{folder}/summary/version={before[-1]}") if before else None
        new = facts if old is None else merge_summaries(old, facts)
        new.write.mode("overwrite").parquet(f"{folder}/summary/version={number}")
        models = learn(spark.read.parquet(f"{folder}/summary/version={number}"))
        models.write.mode("overwrite").parquet(f"{folder}/models/version={number}")
        if changed is not None:
            models = spark.read.parquet(f"{folder}/models/version={number}")
            if old is not None:
                models = models.join(spark.read.parquet(f"{folder}/models/version={before[-1]}").select("model_key", "expr"), ["model_key", "expr"], "left_anti")
            changed(models, number)

    return merge


def infer_stream(strings: DataFrame, folder: str, checkpoint: str, changed=None):
    """Start the query: a stream of (model_key, string_id, seq) to versioned models in folder."""
    return strings.writeStream.foreachBatch(merge_batch(folder, changed)).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def latest(spark, folder: str, what: str = "models") -> DataFrame:
    return spark.read.parquet(f"{folder}/{what}/version={_versions(spark, f'{folder}/{what}')[-1]}")


def session_strings(events: DataFrame, gap: str = "30 minutes", delay: str = "1 hour") -> DataFrame:
    """Strings from a stream of events: a string ends with a gap; complete ones are emitted as the watermark passes."""
    rows = events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", delay).dropDuplicatesWithinWatermark(["event_id"])
    grouped = rows.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.collect_list(F.struct("ts", "event_id", "event_type")).alias("i"))
    seq = F.transform(F.array_sort("i"), lambda x: x["event_type"])
    return grouped.select(F.lit("session").alias("model_key"), F.concat_ws(":", "user_id", F.col("w.start").cast("string")).alias("string_id"), seq.alias("seq"))


def windowed_strings(events: DataFrame, length: str, slide: str | None = None) -> DataFrame:
    """User strings by tumbling or sliding windows; the window's start is the model key."""
    rows = events.withColumn("ts", F.col("ts").cast("timestamp"))
    grouped = rows.groupBy(F.window("ts", length, slide or length).alias("w"), "user_id").agg(F.collect_list(F.struct("ts", "event_id", "event_type")).alias("i"))
    return grouped.select(F.date_format(F.col("w.start"), "yyyy-MM-dd").alias("model_key"), F.col("user_id").alias("string_id"), F.transform(F.array_sort("i"), lambda x: x["event_type"]).alias("seq"))


def new_conflicts(old: DataFrame, new: DataFrame) -> DataFrame:
    """Pairs that were one-way in the old summary and are seen in both orders in the new one: a drift alert."""
    pairs = lambda s: s.where(F.col("kind") == PAIR).select("model_key", "a", "b")
    back = lambda p: p.select("model_key", F.col("b").alias("a"), F.col("a").alias("b"))
    was, now = pairs(old), pairs(new)
    return was.join(back(was), ["model_key", "a", "b"], "left_anti").join(back(now), ["model_key", "a", "b"], "left_semi")


def progress(query) -> dict:
    """Rows, seconds and late rows dropped of the last batch."""
    last = json.loads(query.lastProgress.json) if query.lastProgress else {}
    return {"rows": last.get("numInputRows"), "dropped": sum(s.get("numRowsDroppedByWatermark", 0) for s in last.get("stateOperators", []))}
