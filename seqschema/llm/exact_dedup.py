"""Exact duplicates by content-defined chunk recipes.

A normalised text is cut into chunks where its content says so, between a least and a greatest size, so that equal
passages give equal chunks wherever they stand. A chunk's number is a 64-bit hash; the table of chunks is checked for
numbers that stand for more than one content (by SHA-256). A text's recipe is the ordered list of its chunks' numbers and,
where a number has several contents, of those chunks' digests. Equal texts are equal recipes: rows are grouped and joined
by their recipes, and only these lists move, never texts. The whole text's SHA-256 is not part of the key; a group whose
rows had two of them would stop the job. Built-in functions only.

Defined results: null counts as the empty text, whose list is empty. Of equal texts the row with the largest doc_id
stays; a null doc_id is the smallest. Rows equal in doc_id and text are judged alike, returned as often as they occur, and
count each in group_size. A text without a place to cut is cut after 4,096 characters. Rows with the same doc_id and different texts are judged apart.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from seqschema.llm.common import join_classes, lower_ascii, row_order, spare, written

#: Chunk sizes in characters, and where a chunk may end: after a space or line end that follows one of these word ends;
#: where there is none up to the greatest size (text without spaces), after one of some rarer letters.
LEAST, MOST, BORDER = 512, 4096, r"(?<=[aeinst][dnrsty.])[ \n]"
UNSPACED = r"(?:[\x{4E00}-\x{4E1F}\x{AC00}-\x{AC1F}]|[bjqxzJQXZ57][aeiouAEIOU02468])"


def chunks(text: Column, least: int = LEAST, most: int = MOST, border: str = BORDER) -> Column:
    """The text's chunks in order; concatenated they are the text."""
    pattern = rf"(?s).{{{least},{most - 1}}}?{border}|.{{{least},{most - 2}}}?{UNSPACED}|.{{1,{most}}}"
    return F.regexp_extract_all(text, F.lit(pattern), F.lit(0))


def recipes(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", **sizes) -> DataFrame:
    """doc_id, text_sha256 and the chunks' numbers and digests, in order. One pass over the texts, no shuffle."""
    text = lower_ascii(F.coalesce(F.col(text_col), F.lit("")))
    return (
        docs.select(F.col(id_col).alias("doc_id"), text.alias("t"))
        .withColumn("text_sha256", F.sha2("t", 256))
        .withColumn("parts", F.transform(chunks(F.col("t"), **sizes), lambda c: F.struct(F.xxhash64(c).alias("number"), F.unhex(F.sha2(c, 256)).alias("digest"))))
        .select("doc_id", "text_sha256", F.col("parts.number").alias("numbers"), F.col("parts.digest").alias("digests"))
    )


def clashing_numbers(rec: DataFrame) -> DataFrame:
    """Numbers that stand for more than one content."""
    found = rec.select(F.explode(F.arrays_zip("numbers", "digests")).alias("c")).groupBy(F.col("c.numbers").alias("number"))
    return found.agg(F.min("c.digests").alias("least"), F.max("c.digests").alias("most")).where("least <> most").select("number")


def verified(rec: DataFrame) -> DataFrame:
    """doc_id, text_sha256 and the recipe: numbers, and told, the digests of those whose number has several contents."""
    none = F.array().cast("array<binary>")
    clashing = written(clashing_numbers(rec), "clashing-numbers")
    if clashing.isEmpty():
        return rec.select("doc_id", "text_sha256", "numbers", none.alias("told"))
    chunk = rec.select("doc_id", "text_sha256", F.posexplode(F.arrays_zip("numbers", "digests")).alias("at", "c"))
    odd = chunk.join(clashing, F.col("c.numbers") == F.col("number"), "left_semi").groupBy("doc_id", "text_sha256")
    odd = odd.agg(F.transform(F.array_sort(F.collect_set(F.struct("at", F.col("c.digests").alias("digest")))), lambda x: x["digest"]).alias("told"))
    met = F.col("r.doc_id").eqNullSafe(F.col("o.doc_id")) & (F.col("r.text_sha256") == F.col("o.text_sha256"))
    return written(rec.alias("r").join(odd.alias("o"), met, "left").select("r.doc_id", "r.text_sha256", "r.numbers", F.coalesce("o.told", none).alias("told")), "verified-recipes")


def exact_groups(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", **sizes) -> DataFrame:
    """doc_id, keep_id, group_size, kept, text_sha256 for every document."""
    lists = verified(written(recipes(docs, id_col, text_col, **sizes), "recipes"))
    of = lists.groupBy("numbers", "told").agg(F.max("doc_id").alias("keep_id"), F.count("*").alias("group_size"), F.min("text_sha256").alias("least"), F.max("text_sha256").alias("most"))
    same = F.assert_true(F.col("least") == F.col("most"), F.lit("texts of one recipe differ")).isNull()
    groups = written(of.where(same).select("numbers", "told", "keep_id", "group_size", F.col("group_size").alias("members")), "groups")
    named = join_classes(lists, groups, ["numbers", "told"], "members")
    return named.select(F.col("doc_id").alias(id_col), "keep_id", "group_size", F.col("doc_id").eqNullSafe(F.col("keep_id")).alias("kept"), "text_sha256")


def drop_exact_copies(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The documents that stay, one row each, with the columns of docs. Rows with the same doc_id and kept twice, by
    their different texts, both stay. Of rows equal in doc_id and text but for case or other columns, the one whose text
    has the least hash stays, then the one whose row has."""
    key = lambda ident, sha: F.concat_ws(":", F.coalesce(F.col(f"`{ident}`").cast("string"), F.lit("null")), sha)
    name, nth = spare(docs.columns, "_key", "_nth")
    keep = exact_groups(docs.select(id_col, text_col), id_col, text_col).where("kept").select(key(id_col, F.col("text_sha256")).alias(name)).distinct()
    sha = F.sha2(lower_ascii(F.coalesce(F.col(f"`{text_col}`"), F.lit(""))), 256)
    rows = docs.withColumn(name, key(id_col, sha)).join(keep, name, "left_semi")
    first = W.partitionBy(name).orderBy(*row_order(docs, text_col))
    return rows.withColumn(nth, F.row_number().over(first)).where(F.col(nth) == 1).select(*[F.col(f"`{c}`") for c in docs.columns])
