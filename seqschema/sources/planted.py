"""Planted corpora: strings drawn from known shapes by plain integer arithmetic on keys, and an expression corpus."""

from __future__ import annotations

import functools

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from seqschema.functions.expr import parse_expr, to_groups

#: Ground-truth shapes by corpus, for the level-chain, outer-shuffle and bag learners.
SHAPES = {
    "astro": "a1 a2+ a3 a4+ a5 a6* (a10* & a7*) a8 a9",
    "doc": "a1 a2 (a3? & a4* & a5*) a7* a6* a8?",
    "web": "a1* a6? (a14* a5* & a15* & a2* a10* a3? a7? a17?)",
    "thesis": "a2+ a14 (a19* & a13? a20? & a17+ a16? a11? & a21* a10* & a12* a9? a15? a7*)",
}
OUTER = {
    "astro": "a1 a2+ a3 a4+ a5 a6* a7* a8 a9 & a10*",
    "doc": "a3? & a4* & a1 a2 a5* a7* a6* a8?",
    "web": "a6? a1* a14* a5* a3? a7? a17? & a15* & a2* a10*",
    "thesis": "a13? a20? & a12* a7* & a17+ a16? & a2+ a14 a9? a21* a15? & a11? a19* a10*",
}
BAGS = {
    "astro": "a1 & a2+ & a3 & a4+ & a5 & a6* & a7* & a8 & a9 & a10*",
    "doc": "(a6* | a7*) & a5* & a4* & a1 & a2 & a3? & a8?",
    "web": "(a10* | a17? | a6?) & (a5* | a3? | a7?) & (a2* | a1*) & a14* & a15*",
    "thesis": "(a11? | a9? | a19*) & (a10* | a20? | a15?) & a7* & a16? & a12* & a13? & a2+ & a14 & a21* & a17+",
}
MODULUS = 2147483647


def draw(key: int, p: int) -> int:
    """Draw number p of a key."""
    x = (key * 48271 + p * 69621 + 1) % MODULUS
    x = x * (x % 65536 + p) % MODULUS
    x = x * (x % 65521 + 17) % MODULUS
    return x // 1024


def draw_column(key, p):
    """The same in SQL arithmetic."""
    m = F.lit(MODULUS).cast("bigint")
    x = (key * 48271 + p * 69621 + 1) % m
    x = x * (x % 65536 + p) % m
    x = x * (x % 65521 + 17) % m
    return F.floor(x / 1024).cast("bigint")


#: Strings of the corpora.
SIZES = {"astro": 2_435, "thesis": 63_420, "doc": 1_719_728, "web": 2_000_226}


@functools.lru_cache(maxsize=256)
def _chains(shape: str) -> list:
    return [[[(sym, *{"1": (1, 1), "?": (0, 1), "*": (0, 2), "+": (1, 2)}[op]) for sym, op in chain] for chain in chains] for chains, _ in to_groups(parse_expr(shape))]


def planted(key: int, shape: str) -> list[str]:
    """The string of a key: counts for every symbol by group and chain, then chains interleaved by draws."""
    at, out = 0, []

    def next_draw(n: int) -> int:
        nonlocal at
        at += 1
        return draw(key, at - 1) % n

    for chains in _chains(shape):
        rows = []
        for chain in chains:
            row: list[str] = []
            for sym, low, high in chain:
                row += [sym] * (low if low == high else low + next_draw(high - low + 1))
            rows.append(row)
        while any(rows):
            live = [r for r in rows if r]
            out.append(live[next_draw(len(live)) if len(live) > 1 else 0].pop(0))
    return out


def planted_strings(keys: DataFrame, key_col: str, shapes: dict[str, str] | None = None, sizes: dict[str, int] | None = None, least: int = 300) -> DataFrame:
    """(model_key, string_id, seq) for each key and shape. sizes: strings of the corpora; the largest gets all keys, the
    others their share of them by a draw, but about `least` strings where there are as many keys."""
    shapes = shapes or SHAPES

    @F.pandas_udf("array<string>")
    def make(key: pd.Series, shape: pd.Series) -> pd.Series:
        return pd.Series([planted(int(k), s) for k, s in zip(key, shape, strict=True)])

    pairs = F.array(*[F.struct(F.lit(n).alias("name"), F.lit(s).alias("shape")) for n, s in shapes.items()])
    rows = keys.select(F.col(key_col).cast("bigint").alias("string_id"), F.explode(pairs).alias("s"))
    if sizes:
        most, n_keys = max(sizes.values()), max(1, keys.count())
        part = F.create_map(*[F.lit(x) for n in shapes for x in (n, max(sizes[n], most * least // n_keys))])
        # a draw is below MODULUS / 1024
        rows = rows.where(draw_column(F.col("string_id"), F.lit(999).cast("bigint")) * most < part[F.col("s.name")].cast("bigint") * (MODULUS // 1024))
    return rows.select(F.col("s.name").alias("model_key"), "string_id", make("string_id", "s.shape").alias("seq"))


def corpus_from_parts(parts: DataFrame) -> DataFrame:
    """(expr_id, source, expr, family): expressions of known families drawn by part key; the brand is the site."""
    k = F.col("p_partkey")
    name = lambda i: F.concat(F.lit("x"), ((k * 7 + i) % 50 + 50 * i).cast("string"))
    a, b, c, d = (name(i) for i in range(4))
    families = [
        ("chain_factor", F.concat(F.lit("("), a, F.lit(" | "), b, F.lit(")+ "), c, F.lit("?"))),
        ("single", F.concat(F.lit("(("), a, F.lit(" "), b, F.lit(")* | "), c, F.lit(") "), d)),
        ("bag", F.concat(F.lit("("), a, F.lit("* | "), b, F.lit("?) & "), c)),
        ("outer", F.concat(a, F.lit(" "), b, F.lit("* & "), c, F.lit(" "), d, F.lit("?"))),
        ("level", F.concat(a, F.lit(" ("), b, F.lit("* & "), c, F.lit("+) "), d, F.lit("?"))),
        ("level", F.concat(a, F.lit("* ("), b, F.lit(" & "), c, F.lit(") "), d)),
        ("general", F.concat(F.lit("("), a, F.lit(" & "), b, F.lit(" "), a, F.lit(")* "), c)),
    ]
    family = k % len(families)
    pick = lambda j: F.coalesce(*[F.when(family == i, f[j] if j else F.lit(f[j])) for i, f in enumerate(families)])
    return parts.select(k.alias("expr_id"), F.col("p_brand").alias("source"), pick(1).alias("expr"), pick(0).alias("family"))
