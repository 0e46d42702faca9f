"""A corpus pipeline: quality rules, exact dedup, near dedup, mixing, encoding.

Each stage takes (spark, docs, sf_dir), works on every row of docs, and returns a DataFrame; run() writes each as
Parquet in the shared folder and reads it again as the next one's input. All stages but the last return the columns of
documents. Empty tables give empty tables; rows with nulls follow the operators' own rules.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from seqschema.llm import bpe, exact_dedup, mixing, ngram_tables, quality_rules, simhash
from seqschema.llm.common import written


def keep_good(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet").select("doc_id", "quality", "toxic")
    judged = quality_rules.judge(ngram_tables.trusted_flag(docs, labels, "_trusted"), "_trusted", keep=docs.columns, prefix="_rule_")
    return judged.where("_rule_kept").select(*[F.col(f"`{c}`") for c in docs.columns])


def keep_distinct(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return exact_dedup.drop_exact_copies(docs)


def keep_unlike(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return simhash.keep_first(docs)


def draw_mixture(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    mixed = mixing.mix_documents(docs.withColumnsRenamed({c: f"_in_{c}" for c in docs.columns if c in ("topic", "n_tokens", "probability", "kept")}))
    return mixed.where("kept").select(*[F.col(f"`_in_{c}`").alias(c) if c in ("topic", "n_tokens", "probability", "kept") else F.col(f"`{c}`") for c in docs.columns])


def encode_texts(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return bpe.round_trip(docs)


STAGES = [
    ("quality_rules", keep_good),
    ("exact_dedup", keep_distinct),
    ("simhash_near_dedup", keep_unlike),
    ("mixing", draw_mixture),
    ("bpe_encoding", encode_texts),
]

#: SQL can express neither the likelihood ratio's tables, nor XXH64 fingerprints, nor byte-pair merges.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES[:-1]:
        docs = written(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
