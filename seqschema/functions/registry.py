"""Expression functions for SQL and DataFrames, as Arrow UDFs over whole batches."""

from __future__ import annotations

import math

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from seqschema.functions import classes, counting, expr

FLAGS = ", ".join(f"{c} boolean" for c in classes.CLASSES)


def flags_udf():
    @F.pandas_udf(FLAGS)
    def expr_class(texts: pd.Series) -> pd.DataFrame:
        return pd.DataFrame([classes.class_flags(expr.parse_expr(t)) for t in texts], columns=list(classes.CLASSES))

    return expr_class


def _text_udf(kind: str, f):
    @F.pandas_udf(kind)
    def apply(texts: pd.Series) -> pd.Series:
        return pd.Series([None if t is None else f(t) for t in texts])

    return apply


def log2_size(text: str) -> float:
    return math.log2(counting.language_size(text))


def recovered_udf():
    @F.pandas_udf("boolean")
    def recovered(found: pd.Series, planted: pd.Series) -> pd.Series:
        return pd.Series([expr.canonical(expr.parse_expr(a)) == expr.canonical(expr.parse_expr(b)) for a, b in zip(found, planted, strict=True)])

    return recovered


def matches_udf():
    @F.pandas_udf("boolean")
    def matches(seqs: pd.Series, texts: pd.Series) -> pd.Series:
        return pd.Series([expr.matches_general(list(s), expr.parse_expr(t)) for s, t in zip(seqs, texts, strict=True)])

    return matches


def register(spark: SparkSession) -> None:
    """SQL names: expr_class, language_size (log2), shuffle_count, expr_length, simplify, matches, word_counts."""
    from pyspark.sql.functions import udtf

    spark.udf.register("expr_class", flags_udf())
    spark.udf.register("language_size", _text_udf("double", log2_size))
    spark.udf.register("shuffle_count", _text_udf("double", lambda t: float(counting.shuffle_count(t))))
    spark.udf.register("expr_length", _text_udf("int", lambda t: expr.expr_length(expr.parse_expr(t))))
    spark.udf.register("simplify", _text_udf("string", lambda t: expr.to_text(expr.simplify(expr.parse_expr(t)))))
    spark.udf.register("matches", matches_udf())

    @udtf(returnType="len int, words double")
    class WordCounts:
        def eval(self, text: str):
            for k, n in enumerate(counting.word_counts(text)):
                yield k, float(n)

    spark.udtf.register("word_counts", WordCounts)


def with_flags(corpus: DataFrame) -> DataFrame:
    """corpus (expr_id, source, expr) with one column for each class; each text is parsed once."""
    return corpus.withColumn("_f", flags_udf()(F.col("expr"))).select(*corpus.columns, "_f.*")


def usage_proportions(corpus: DataFrame, by: tuple[str, ...] = ()) -> DataFrame:
    """Shares of the classes over distinct (source, expr), in all and by the named columns (cube)."""
    flagged = with_flags(corpus)
    shares = [F.avg(F.col(c).cast("double")).alias(c) for c in classes.CLASSES]
    return (flagged.cube(*by) if by else flagged.groupBy()).agg(F.count("*").alias("n"), *shares)
