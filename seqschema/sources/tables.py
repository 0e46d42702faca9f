"""Strings of symbols from ordered rows, and the workloads on the given tables."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F


def strings_from_rows(df: DataFrame, model_key: Column, string_id: Column, order_by: Sequence[str], symbol: Column) -> DataFrame:
    """(model_key, string_id, seq): the symbols of each string in order. For strings that fit a row; longer ones go to
    chunks_from_rows. Only the named columns are read."""
    item = F.struct(*[F.col(c) for c in order_by], symbol.cast("string").alias("_symbol"))
    rows = df.select(model_key.cast("string").alias("model_key"), string_id.alias("string_id"), item.alias("i"))
    return rows.groupBy("model_key", "string_id").agg(F.transform(F.array_sort(F.collect_list("i")), lambda x: x["_symbol"]).alias("seq"))


def chunks_from_rows(df: DataFrame, model_key: Column, string_id: Column, position: Column, symbol: Column, size: int = 10_000) -> DataFrame:
    """(model_key, string_id, chunk_no, seq): pieces of long strings by ranges of an integer position, each a group of
    bounded size."""
    rows = df.select(model_key.cast("string").alias("model_key"), string_id.alias("string_id"), position.alias("p"), symbol.cast("string").alias("s"))
    grouped = rows.groupBy("model_key", "string_id", F.floor(F.col("p") / size).alias("chunk_no"))
    return grouped.agg(F.transform(F.array_sort(F.collect_list(F.struct("p", "s"))), lambda x: x["s"]).alias("seq"))


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


LINE_COLUMNS = ("l_partkey", "l_suppkey", "l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_returnflag", "l_linestatus", "l_shipdate")


def roles(spark, sf):
    return strings_from_rows(table(spark, sf, "conversations"), F.lit("conversation"), F.col("conv_id"), ["turn", "role"], F.col("role"))


def user_days(spark, sf):
    t = table(spark, sf, "events")
    return strings_from_rows(t, F.lit("userday"), F.concat_ws(":", "user_id", F.date_format("ts", "yyyy-MM-dd")), ["ts", "event_id"], F.col("event_type"))


def sessions(spark, sf, minutes: int = 30):
    own = W.partitionBy("user_id").orderBy("ts", "event_id")
    t = table(spark, sf, "events").select("user_id", "ts", "event_id", "event_type").withColumn("gap", F.unix_micros(F.col("ts").cast("timestamp")) - F.lag(F.unix_micros(F.col("ts").cast("timestamp"))).over(own))
    t = t.withColumn("session", F.sum((F.coalesce("gap", F.lit(0)) >= minutes * 60_000_000).cast("int")).over(own.rowsBetween(W.unboundedPreceding, 0)))
    return strings_from_rows(t, F.lit("session"), F.concat_ws(":", "user_id", "session"), ["ts", "event_id"], F.col("event_type"))


def users(spark, sf):
    return strings_from_rows(table(spark, sf, "events"), F.lit("user"), F.col("user_id"), ["ts", "event_id"], F.col("event_type"))


def flags(spark, sf):
    t = table(spark, sf, "lineitem")
    return strings_from_rows(t, F.lit("order"), F.col("l_orderkey"), ["l_linenumber", *LINE_COLUMNS], F.concat("l_returnflag", "l_linestatus"))


def sorted_flags(spark, sf):
    t = table(spark, sf, "lineitem")
    return strings_from_rows(t, F.lit("order_sorted"), F.col("l_orderkey"), ["l_returnflag", "l_linenumber", "l_linestatus"], F.concat("l_returnflag", "l_linestatus"))


def quantities(spark, sf):
    """Low and high quantities of an order's lines, by return flag."""
    t = table(spark, sf, "lineitem")
    return strings_from_rows(t, F.lit("quantities"), F.col("l_orderkey"), ["l_returnflag", "l_linenumber", "l_quantity"], F.concat("l_returnflag", F.when(F.col("l_quantity") < 25, "L").otherwise("H")))


def statuses(spark, sf):
    return strings_from_rows(table(spark, sf, "orders"), F.lit("status"), F.col("o_custkey"), ["o_orderdate", "o_orderkey"], F.col("o_orderstatus"))


def priorities(spark, sf):
    return strings_from_rows(table(spark, sf, "orders"), F.lit("priority"), F.col("o_custkey"), ["o_orderdate", "o_orderkey"], F.col("o_orderpriority"))


#: Fixed line kinds, in the order they are tried.
LINE_KINDS = [("blank", "^[ \t]*$"), ("license", "[Ll]icense|CC BY"), ("email", "[A-Za-z0-9._]+@[A-Za-z0-9]"), ("open", "^[^.!?]*$"), ("short", "^.{0,60}$")]


def line_kinds(spark, sf):
    kind = F.coalesce(*[F.when(F.col("line").rlike(p), k) for k, p in LINE_KINDS], F.lit("prose"))
    t = table(spark, sf, "documents").select("doc_id", F.posexplode(F.split(F.coalesce("text", F.lit("")), "\n")).alias("pos", "line"))
    return strings_from_rows(t, F.lit("lines"), F.col("doc_id"), ["pos"], kind)


def record_fields(spark, sf):
    """The names of a document record's fields that are present, labels joined, in fixed order."""
    docs, labels = table(spark, sf, "documents").select("doc_id", "lang", "source", "text"), table(spark, sf, "labels")
    t = docs.join(labels, "doc_id", "left")
    names = ("lang", "source", "text", "quality", "toxic")
    seq = F.filter(F.array(*[F.when(F.col(c).isNotNull(), c) for c in names]), lambda x: x.isNotNull())
    return t.select(F.lit("document").alias("model_key"), F.col("doc_id").alias("string_id"), seq.alias("seq"))


def bucket_labels(spark, sf):
    return strings_from_rows(table(spark, sf, "embeddings"), F.lit("bucket"), F.floor(F.col("vec_id") / 8), ["vec_id"], F.col("label"))


def json_keys(spark, sf):
    """The keys of each event's JSON object in their order in the text; without an object there is no string."""
    keys = table(spark, sf, "events").select("event_id", F.json_object_keys("props").alias("seq")).where("seq IS NOT NULL")
    return keys.select(F.lit("props").alias("model_key"), F.col("event_id").alias("string_id"), "seq")


WORKLOADS = {
    "roles": roles, "userday": user_days, "session": sessions, "events": users, "flags": flags, "sorted_flags": sorted_flags, "status": statuses,
    "priority": priorities, "line_kind": line_kinds, "record_field": record_fields, "bucket_label": bucket_labels, "json_keys": json_keys,
}
