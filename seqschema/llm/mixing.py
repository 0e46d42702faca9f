"""Mixing sources to target weights by iterative proportional fitting.

Token weights are added up by cell (source, language, topic). Each round rescales the cells so that one margin meets its
target shares, margin after margin, until all margins fit. The calibrated weight of a cell over its token count gives
the probability with which its documents are drawn, scaled so that the largest is one and the expected amount drawn is at
least `share` of all tokens. No probability is above one: what a cell lacks is spread over the others in proportion, so a rare value takes no more than
its own tokens from the amount. A document is drawn where a hash of its doc_id, taken as a uniform number, is below its
probability. Built-in functions only; only the cells go through the rounds.

Targets are shares by margin value; where none are given a margin's own shares are flattened by its exponent in
`flatten` (one leaves them as they are). Values without a target share, and target values without tokens, drop out of the fit: the former get
probability zero if `strict`, else keep their own share.

Defined results: null values are a category of their own (the empty string); null, empty and blank texts have one
token's weight, so that they can be drawn; a null doc_id is drawn by the hash of its whole row's text; repeated rows are
drawn together.
"""

from __future__ import annotations

from collections.abc import Mapping, Sequence
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from seqschema.llm.common import spare, written

MARGINS = ("source", "lang", "topic")
SPACE = r"[ \t\n\x0b\f\r]"
#: Cells that are broadcast to the documents, salts of the join beyond.
BROADCAST_CELLS, SALTS = 500_000, 64
#: The share of all tokens that is drawn in expectation, at least: more where all margins can be met with more.
SHARE = 0.7
FLATTEN, ROUNDS, TOLERANCE, SEED = {"source": 0.7, "lang": 0.7, "topic": 1.0}, 25, 1e-6, 17


def count_words(text: Column) -> Column:
    """Words between ASCII white space: the pieces of a split there, without the empty ones at both ends."""
    t = F.coalesce(text, F.lit(""))
    ends = F.when(t.rlike(rf"^{SPACE}"), 1).otherwise(0) + F.when(t.rlike(rf"{SPACE}\z"), 1).otherwise(0)
    return F.when(t == "", 0).otherwise(F.size(F.split(t, f"{SPACE}+")) - ends).cast("bigint")


def topic_of(text: Column, n_words: Column) -> Column:
    """A coarse topic by form: the table has none. Fixed rules on the whole text."""
    t = F.coalesce(text, F.lit(""))
    return (
        F.when(n_words < 50, "snippet")
        .when(t.contains("@") | t.contains("password") | t.contains("token ="), "contact")
        .when(F.length(t) - F.length(F.regexp_replace(t, "[#*$%&|<>]+", "")) > n_words, "markup")
        .when(n_words >= 1000, "long")
        .otherwise("prose")
    )


def describe(docs: DataFrame, text_col: str = "text", topic_col: str | None = None) -> Column:
    """The cell of a row and its tokens: a struct of source, lang, topic and tokens."""
    words = F.greatest(count_words(F.col(f"`{text_col}`")), F.lit(1).cast("bigint"))
    value = lambda c: F.coalesce(F.col(f"`{c}`").cast("string"), F.lit(""))
    topic = value(topic_col) if topic_col else topic_of(F.col(f"`{text_col}`"), words)
    return F.struct(value("source").alias("source"), value("lang").alias("lang"), topic.alias("topic"), words.alias("tokens"))


def fit_cells(cells: DataFrame, targets: Mapping[str, Mapping[str, float]] | None = None, flatten: Mapping[str, float] = FLATTEN, rounds: int = ROUNDS, tolerance: float = TOLERANCE, strict: bool = False) -> DataFrame:
    """cells (_source, _lang, _topic, tokens) with weight: a share of the whole that fits all margins."""
    spark, targets = cells.sparkSession, targets or {}
    goals = {}
    for m in MARGINS:
        own = cells.groupBy(f"_{m}").agg(F.sum("tokens").alias("t"))
        if m in targets:
            given = spark.createDataFrame([(str(k), float(v)) for k, v in targets[m].items()], f"_{m} string, g double")
            tokens = own.agg(F.sum("t")).first()[0] or 1
            own = own.withColumn("own", F.col("t") / F.lit(float(tokens))).join(given, f"_{m}", "left").withColumn("g", F.coalesce("g", F.lit(0.0) if strict else F.col("own")))
        else:
            own = own.withColumn("g", F.pow(F.col("t").cast("double"), F.lit(float(flatten[m]))))
        total = own.agg(F.sum("g")).first()[0] or 1.0
        goals[m] = written(own.select(f"_{m}", (F.col("g") / F.lit(float(total))).alias("goal")), f"goal-{m}")
    now = cells.withColumn("weight", F.col("tokens").cast("double"))
    for _ in range(rounds):
        for m in MARGINS:
            have = now.groupBy(f"_{m}").agg(F.sum("weight").alias("have")).join(goals[m], f"_{m}")
            scale = have.select(f"_{m}", F.when(F.col("have") > 0, F.col("goal") / F.col("have")).otherwise(0.0).alias("scale"))
            now = now.join(scale, f"_{m}").withColumn("weight", F.col("weight") * F.col("scale")).select(*cells.columns, "weight")
        now = written(now, "cells")  # each margin reads the table twice, so rounds are cut here
        # the last margin has just been met; the others may have moved
        gaps = [now.groupBy(f"_{m}").agg(F.sum("weight").alias("have")).join(goals[m], f"_{m}").agg(F.max(F.abs(F.col("have") - F.col("goal"))).alias("gap")) for m in MARGINS[:-1]]
        if max(r["gap"] or 0.0 for r in reduce(DataFrame.unionByName, gaps).collect()) <= tolerance:
            break
    return now


def scale_to(fitted: DataFrame, amount: float) -> DataFrame:
    """fitted with _chance: the least of one and weight over tokens times a factor, so that the tokens drawn add up to
    the amount at least, or to all tokens of cells with weight if these are fewer; the largest is one. Each round the cells that reach one leave the
    rest; it ends when no further cell does."""
    cells = fitted.withColumn("_ratio", F.when(F.col("tokens") > 0, F.col("weight") / F.col("tokens")).otherwise(0.0))
    most = cells.agg(F.max("_ratio")).first()[0]
    factor = 1.0 / most if most else 0.0
    while True:
        full = F.col("_ratio") * F.lit(factor) >= 1
        taken, free, cut = cells.agg(F.sum(F.when(full, F.col("tokens"))), F.sum(F.when(~full, F.col("weight"))), F.max(F.when(~full, F.col("_ratio")))).first()
        if not free:
            break
        # cells that are full stay full, for the factor never falls
        factor = max(factor, (amount - (taken or 0)) / free)
        if cut * factor < 1:
            break
    return cells.withColumn("_chance", F.round(F.least(F.col("_ratio") * F.lit(factor), F.lit(1.0)), 9))


def mix_documents(
    docs: DataFrame, text_col: str = "text", id_col: str = "doc_id", topic_col: str | None = None, targets=None, seed: int = SEED, share: float = SHARE, keep: Sequence[str] | None = None, **options
) -> DataFrame:
    """docs with topic, n_tokens, probability and kept. keep: the columns to return beside these, all by default. Without
    the text among them texts are read once: what is told of them is written. With it they are read twice and never move."""
    taken = {"topic", "n_tokens", "probability", "kept"}
    back = [c for c in (docs.columns if keep is None else keep) if c not in taken]
    key = F.coalesce(F.col(f"`{id_col}`").cast("string"), F.col(f"`{text_col}`"), F.lit(""))
    at, draw, chance, salt = spare(docs.columns, "_cell", "_draw", "_chance", "_salt")
    named = docs.select(*[F.col(f"`{c}`") for c in back], describe(docs, text_col, topic_col).alias(at), F.pmod(F.xxhash64(F.lit(seed), key), F.lit(1 << 40)).alias(draw))
    if text_col not in back:
        named = written(named, "described")
    cells = written(named.groupBy(*(F.col(at)[m].alias(f"_{m}") for m in MARGINS)).agg(F.sum(F.col(at)["tokens"]).alias("tokens")), "cells")
    n_cells, tokens = cells.agg(F.count("*"), F.sum("tokens")).first()
    fitted = scale_to(fit_cells(cells, targets, **options), share * (tokens or 0)).select(F.struct(*(F.col(f"_{m}").alias(m) for m in MARGINS)).alias("_margins"), F.col("_chance").alias(chance))
    own = F.struct(*(F.col(at)[m].alias(m) for m in MARGINS))
    if n_cells <= BROADCAST_CELLS:
        met = named.join(F.broadcast(fitted), own == F.col("_margins"), "left")
    else:  # a cell may hold a third of all rows: each is joined in many parts
        spread = fitted.withColumn("_part", F.explode(F.sequence(F.lit(0).cast("bigint"), F.lit(SALTS - 1).cast("bigint"))))
        met = named.withColumn(salt, F.col(draw) % SALTS).join(spread, (own == F.col("_margins")) & (F.col(salt) == F.col("_part")), "left")
    return met.select(
        *[F.col(f"`{c}`") for c in back], F.col(at)["topic"].alias("topic"), F.col(at)["tokens"].alias("n_tokens"),
        F.col(chance).alias("probability"), (F.col(draw).cast("double") / F.lit(float(1 << 40)) < F.col(chance)).alias("kept"),
    )
