"""URL block and allow lists at scale, by hashed expressions.

A rule is a host, a path prefix and a verdict; it fits its host and all subdomains where the url's path starts with the
rule's. Each url is expanded into the host suffixes at label borders times the path prefixes whose lengths occur among
the rules. Expressions and rules meet in an equi-join on a short hash prefix; the full digest then confirms, and the
longest rule decides (longer host first on a tie, then block before allow). Nothing but built-in functions is used.

Defined results: a null url, or one without ://, has an empty host and path and no rule; repeated rows are judged once
and come back as often as they came; rules with a null part are ignored; a repeated rule counts once, with block
before allow. A url without a rule gets the default verdict, allow.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from seqschema.llm.common import LOWER, UPPER

#: Rules are broadcast up to this many; beyond it both sides are shuffled, the urls salted because hosts are skewed.
BROADCAST_RULES, SALTS = 200_000, 32

#: The rules of the query.
RULES = [("net", "/", "block"), ("example.net", "/en/", "allow"), ("example.com", "/de/", "block"), ("org", "/fr/", "allow")]


def host_and_path(url: Column) -> tuple[Column, Column]:
    """The parts as written: no decoding, ports and user names stay in the host; A-Z of the host are lower-cased."""
    at = F.locate("://", url)
    rest = F.when(at > 0, F.substr(url, at + F.lit(3)))
    host = F.translate(F.regexp_extract(rest, r"\A([^/?#]*)", 1), UPPER, LOWER)
    path = F.regexp_extract(rest, r"\A[^/?#]*([^?#]*)", 1)
    return F.coalesce(host, F.lit("")), F.coalesce(path, F.lit(""))


def host_suffixes(host: Column) -> Column:
    labels = F.split(host, r"\.")
    return F.transform(F.sequence(F.lit(1), F.size(labels)), lambda i: F.array_join(F.slice(labels, i, F.size(labels)), "."))


def rule_table(spark: SparkSession, rules: Sequence[tuple[str, str, str]]) -> DataFrame:
    return spark.createDataFrame(list(rules), "host string, path string, verdict string")


def _digest(host: Column, path: Column) -> Column:
    return F.sha2(F.concat(host, F.lit("\n"), path), 256)


def judge_urls(pages: DataFrame, rules: DataFrame, id_col: str = "page_id", url_col: str = "url", default: str = "allow") -> DataFrame:
    """One row for each page: id, url, host, path, rule (host and path together, or null), verdict."""
    rules = (
        rules.where(F.col("host").isNotNull() & F.col("path").isNotNull() & F.col("verdict").isin("allow", "block"))
        .select(F.translate("host", UPPER, LOWER).alias("r_host"), F.col("path").alias("r_path"), "verdict")
        .groupBy("r_host", "r_path")
        .agg(F.max("verdict").alias("r_verdict"))
        .withColumn("r_digest", _digest(F.col("r_host"), F.col("r_path")))
        .withColumn("r_key", F.substring("r_digest", 1, 8))
    )
    summary = rules.agg(F.count("*").alias("n"), F.sort_array(F.collect_set(F.length("r_path"))).alias("sizes")).first()
    host, path = host_and_path(F.col("url"))
    urls = (
        pages.select(F.col(id_col).alias("id"), F.col(url_col).alias("url"))
        .groupBy("id", "url")
        .agg(F.count("*").alias("times"))
        .withColumn("host", host)
        .withColumn("path", path)
    )
    sizes = F.array(*[F.lit(int(x)) for x in summary["sizes"]]).cast("array<int>")
    prefixes = F.transform(F.filter(sizes, lambda n: n <= F.length("path")), lambda n: F.substr(F.col("path"), F.lit(1), n))
    hosts = F.when(F.col("host") != "", host_suffixes(F.col("host"))).otherwise(F.array().cast("array<string>"))
    pairs = F.flatten(F.transform(hosts, lambda h: F.transform(prefixes, lambda p: F.struct(h.alias("h"), p.alias("p")))))
    asked = (
        urls.select("id", "url", F.explode(pairs).alias("e"))
        .withColumn("digest", _digest(F.col("e.h"), F.col("e.p")))
        .select("id", "url", "digest", F.substring("digest", 1, 8).alias("key"))
    )
    if summary["n"] <= BROADCAST_RULES:
        met = asked.join(F.broadcast(rules), F.col("key") == F.col("r_key"))
    else:
        asked = asked.withColumn("salt", F.pmod(F.xxhash64("id", "url"), F.lit(SALTS)).cast("bigint"))
        spread = rules.withColumn("r_salt", F.explode(F.sequence(F.lit(0).cast("bigint"), F.lit(SALTS - 1).cast("bigint"))))
        met = asked.join(spread, (F.col("key") == F.col("r_key")) & (F.col("salt") == F.col("r_salt")))
    rank = F.struct(
        (F.length("r_host") + F.length("r_path")).alias("size"), F.length("r_host").alias("host_size"),
        F.concat("r_host", "r_path").alias("rule"), F.col("r_verdict").alias("verdict"),
    )
    best = met.where(F.col("digest") == F.col("r_digest")).groupBy("id", "url").agg(F.max(rank).alias("best"))
    return (
        urls.alias("u")
        .join(best.alias("b"), F.col("u.id").eqNullSafe(F.col("b.id")) & (F.col("u.url") == F.col("b.url")), "left")
        .select(
            F.col("u.id").alias(id_col), F.col("u.url").alias(url_col), "host", "path", F.col("best.rule").alias("rule"),
            F.coalesce(F.col("best.verdict"), F.lit(default)).alias("verdict"), F.explode(F.sequence(F.lit(1), F.col("times").cast("int"))).alias("_n"),
        )
        .drop("_n")
    )
