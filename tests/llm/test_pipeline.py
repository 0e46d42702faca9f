"""The pipeline as a whole: what each stage keeps, and odd tables."""

import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from seqschema.llm.queries import QUERIES

from .test_operators import SCHEMA, corpus

TABLES = {
    "documents": (corpus(), SCHEMA), "labels": ([(i, 1, 0) for i in range(0, 60, 2)], "doc_id bigint, quality int, toxic int"),
    "pages": ([(1, "http://a.net/", "<p>"), (2, None, None)], "page_id bigint, url string, html string"),
}


@pytest.fixture(scope="module")
def tables(spark, tmp_path_factory):
    top = tmp_path_factory.mktemp("tables")
    for name, (rows, schema) in TABLES.items():
        df = spark.createDataFrame(rows, schema)
        df.repartition(3).write.parquet(f"{top}/full/{name}.parquet")
        df.limit(0).write.parquet(f"{top}/empty/{name}.parquet")
        df.select([F.lit(None).cast(t).alias(c) for c, t in df.dtypes]).write.parquet(f"{top}/nulls/{name}.parquet")
    return top


def test_stages_keep_columns_and_shrink(spark, tables):
    docs = spark.read.parquet(f"{tables}/full/documents.parquet").withColumn("kept", F.lit("mine")).withColumn("topic", F.lit(3))
    before = docs.count()
    for name, stage in corpus_pipeline.STAGES[:-1]:
        docs, columns = stage(spark, docs, str(tables / "full")), docs.columns
        assert docs.columns == columns, name
        rows = docs.collect()
        assert 0 < len(rows) <= before and len({r["doc_id"] for r in rows}) == len(rows)
        docs, before = spark.createDataFrame(rows, docs.schema), len(rows)
    last = corpus_pipeline.STAGES[-1][1](spark, docs, str(tables / "full")).collect()
    assert len(last) == before and all(r["n_tokens"] > 0 for r in last)


@pytest.mark.parametrize("kind", ["empty", "nulls"])
@pytest.mark.parametrize("name", [*QUERIES, "pipeline"])
def test_odd_tables(spark, tables, kind, name):
    query = QUERIES.get(name, corpus_pipeline.run)
    rows = query(spark, str(tables / kind)).collect()
    assert len(rows) == 0 if kind == "empty" or name == "pipeline" else len(rows) >= 1
