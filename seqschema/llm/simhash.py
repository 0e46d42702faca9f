"""Near duplicates by SimHash fingerprints and vantage-point trees.

A fingerprint has 64 bits, each the majority of that bit among the hashes of a text's word shingles. Two fingerprints
are linked at a Hamming distance of `radius` or less; classes are the connected components of the links.

Distances between unlike fingerprints crowd around 32, so one vantage-point tree over all 64 bits prunes next to nothing
at radius 4. The bits are therefore cut into blocks with a Hamming distance of their own, never more than the whole
distance, and a tree is grown for each block: linked fingerprints are within radius // blocks in at least one block.
A tree's levels are vantage points with rings of distance around them; the rings a fingerprint falls into, level by
level, name its shard. By the triangle bound a neighbour lies in the same or an overlapping ring, so a fingerprint
asks all shards that its ball touches. With blocks = radius + 1 the ball has radius zero and touches its own shard only.
A shard that holds more than `shard` fingerprints is split again, by a tree for each block of the bits that did not name
it: two of its fingerprints within the radius agree in one of these blocks too, so no link is lost, and the number of
shards grows with the input. What is still larger after SPLITS rounds is a clump of close fingerprints, which the next
step takes out at once. Inside a shard, a tree over the full distance finds the exact neighbours; it grows one component
at a time, and a shard hands on one link per fingerprint to its component's least one, never all pairs. Components
across shards come from rounds of star contraction over written tables.

Equal fingerprints are merged before all this, so a hot group of copies is one point; documents get their class back
without gathering a hot group in one task. Defined results: null, empty and
blank texts have fingerprint zero, linked as any other; a text shorter than a shingle is one shingle; rows repeated with
the same doc_id each get a row with the same class. A null doc_id is never the least of a class unless alone.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import repeat

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from seqschema.llm.common import append_columns, bound_batches, join_classes, row_order, spare, written

SHINGLE, RADIUS, SEED, BITS = 4, 4, 42, 64
#: Vantage points of a block's tree, fingerprints of a leaf that are compared directly, shingles hashed at a time.
LEVELS, LEAF, PART = 8, 1024, 1 << 16
#: Fingerprints that a shard holds before it is split, rounds of splitting, marks of such shards that are broadcast, salts beyond.
SHARD, SPLITS, BROADCAST_MARKS, SALTS = 20_000, 2, 200_000, 32


def fingerprint(text: str, shingle: int = SHINGLE) -> int:
    words = text.encode().lower().split()
    if not words:
        return 0
    joined = b" ".join(words)
    if len(words) <= shingle:
        return xxhash.xxh64_intdigest(joined, SEED)
    ends = np.cumsum(np.fromiter(map(len, words), np.int64, len(words)) + 1)
    starts = np.concatenate(([0], ends[:-1]))[: len(words) - shingle + 1].tolist()
    ends = (ends[shingle - 1 :] - 1).tolist()
    ones, n = np.zeros(BITS, np.int64), len(starts)
    for k in range(0, n, PART):
        pieces = [joined[a:b] for a, b in zip(starts[k : k + PART], ends[k : k + PART], strict=True)]
        h = np.fromiter(map(xxhash.xxh64_intdigest, pieces, repeat(SEED)), ">u8", len(pieces))
        ones += np.unpackbits(h.view(np.uint8).reshape(-1, 8), axis=1).sum(axis=0, dtype=np.int64)
    return int.from_bytes(np.packbits(2 * ones > n).tobytes(), "big")


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", shingle: int = SHINGLE) -> DataFrame:
    """doc_id and fp, the fingerprint as a signed long."""

    def kernel():
        return lambda texts, _: [pa.array(np.array([fingerprint(t, shingle) for t in texts], np.uint64).view(np.int64))]

    return append_columns(docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("text")), "text", kernel, [("fp", T.LongType())], ["doc_id"])


def block_masks(blocks: int, within: int = (1 << BITS) - 1) -> list[int]:
    """The bits of within, cut into blocks of nearly equal size."""
    bits = [b for b in range(BITS) if within >> b & 1]
    cuts = [round(len(bits) * k / blocks) for k in range(blocks + 1)]
    return [sum(1 << b for b in bits[cuts[k] : cuts[k + 1]]) for k in range(blocks)]


def _signed(x: int) -> int:
    return x - (1 << 64) if x >> 63 else x


def _then(rings: Column):
    return lambda name: F.transform(rings, lambda ring: name * 64 + ring)


def _of_tree(k: int):
    return lambda name: F.struct(F.lit(k).alias("tree"), name.alias("shard"))


def shard_names(fp: Column, mask: Column, width: int, points: list[int], radius: int) -> tuple[Column, Column]:
    """The shard a fingerprint lies in, and all shards its ball touches, as numbers. width: of a ring."""
    home, asked = F.lit(0).cast("bigint"), F.array(F.lit(0).cast("bigint"))
    for point in points:
        d = F.bit_count(fp.bitwiseXOR(F.lit(_signed(point))).bitwiseAND(mask)).cast("bigint")
        home = home * 64 + F.floor(d / width)
        if radius:
            rings = F.sequence(F.floor(F.greatest(d - radius, F.lit(0)) / width), F.floor((d + radius) / width))
            asked = F.flatten(F.transform(asked, _then(rings)))
    return home, asked if radius else F.array(home)


class VantageTree:
    """A vantage-point tree over 64-bit fingerprints under the full Hamming distance, with removal of found points."""

    def __init__(self, points: np.ndarray) -> None:
        self.points = points
        self.left = np.ones(len(points), bool)
        self.root = self._grow(np.arange(len(points)))

    def _grow(self, own: np.ndarray):
        if len(own) <= LEAF:
            return own
        vantage = self.points[own[len(own) // 2]]
        d = np.bitwise_count(self.points[own] ^ vantage)
        middle = int(np.median(d))
        near = d <= middle
        if near.all():
            near = d < middle
        if near.all() or not near.any():
            return own
        return vantage, int(d[near].max()), int(d[~near].min()), self._grow(own[near]), self._grow(own[~near])

    def take(self, centre: np.uint64, radius: int) -> np.ndarray:
        """Indexes of the points within radius that nobody has taken yet; they are taken now."""
        found, todo = [], [self.root]
        while todo:
            node = todo.pop()
            if isinstance(node, np.ndarray):
                hit = node[(np.bitwise_count(self.points[node] ^ centre) <= radius) & self.left[node]]
                if len(hit):
                    self.left[hit] = False
                    found.append(hit)
                continue
            vantage, inner, outer, near, far = node
            d = int(np.bitwise_count(centre ^ vantage))
            if d - radius <= inner:
                todo.append(near)
            if d + radius >= outer:
                todo.append(far)
        return np.concatenate(found) if found else np.zeros(0, np.int64)


def links(points: np.ndarray, radius: int) -> tuple[np.ndarray, np.ndarray]:
    """A link from each point to the first of its component, for components of two or more. Points are distinct."""
    n = len(points)
    if n <= 64:
        near = np.bitwise_count(points[:, None] ^ points[None, :]) <= radius
        if near.sum() == n:
            return points[:0], points[:0]
    tree, a, b = VantageTree(points), [], []
    for seed in range(n):
        if not tree.left[seed]:
            continue
        tree.left[seed] = False
        front, members = [seed], []
        while front:
            new = tree.take(points[front.pop()], radius)
            members.append(new)
            front.extend(new.tolist())
        grown = np.concatenate(members)
        if len(grown):
            a.append(points[grown])
            b.append(np.full(len(grown), points[seed]))
    return (np.concatenate(a), np.concatenate(b)) if a else (points[:0], points[:0])


def _vantage_points(rng: np.random.Generator) -> list[int]:
    return [int(x) for x in rng.integers(0, 2**64, LEVELS, np.uint64)]


def shard_rows(distinct: DataFrame, radius: int, blocks: int, shard: int = SHARD) -> DataFrame:
    """(tree, shard, fp): every shard with the fingerprints that lie in it or touch it."""
    ball, rng = radius // blocks, np.random.default_rng(11)
    used = block_masks(blocks)
    sides = []
    for k, mask in enumerate(used):
        width = 1 if ball == 0 else max(4 * ball, mask.bit_count() // 4)
        _, asked = shard_names(F.col("fp"), F.lit(_signed(mask)), width, _vantage_points(rng), ball)
        sides.append(F.transform(asked, _of_tree(k)))
    now = distinct.select(F.explode(F.concat(*sides)).alias("at"), "fp").select("at.tree", "at.shard", "fp")
    settled, first = None, 0
    for _ in range(SPLITS):
        large = written(now.groupBy("tree", "shard").agg(F.count("*").alias("n")).where(F.col("n") > shard).select("tree", "shard", F.lit(True).alias("large")), "large-shards")
        n = large.count()
        if not n:
            break
        if n <= BROADCAST_MARKS:
            marked = now.join(F.broadcast(large), ["tree", "shard"], "left")
        else:
            salted = large.withColumn("salt", F.explode(F.sequence(F.lit(0).cast("bigint"), F.lit(SALTS - 1).cast("bigint"))))
            marked = now.withColumn("salt", F.pmod(F.xxhash64("fp"), F.lit(SALTS)).cast("bigint")).join(salted, ["tree", "shard", "salt"], "left")
        marked = written(marked.select("tree", "shard", "fp", "large"), "marked-shards")
        calm = marked.where("large IS NULL").select("tree", "shard", "fp")
        settled = calm if settled is None else settled.unionByName(calm)
        # tree numbers go on: the trees of split shards follow all earlier ones
        after, parts = first + len(used), radius + 1
        below = [block_masks(parts, ((1 << BITS) - 1) & ~mask) for mask in used]
        sides = []
        for j in range(parts):
            mask = F.element_at(F.array(*[F.lit(_signed(x[j])) for x in below]), F.col("tree") - first + 1)
            home, _ = shard_names(F.col("fp"), mask, 1, _vantage_points(rng), 0)
            sides.append(F.struct((F.lit(after + j) + (F.col("tree") - first) * parts).cast("int").alias("tree"), F.xxhash64("shard", home).alias("shard")))
        now = marked.where("large").select(F.explode(F.array(*sides)).alias("at"), "fp").select("at.tree", "at.shard", "fp")
        used, first = [mask | x for mask, own in zip(used, below, strict=True) for x in own], after
    return now if settled is None else settled.unionByName(now)


def linked_pairs(distinct: DataFrame, radius: int = RADIUS, blocks: int | None = None, shard: int = SHARD) -> DataFrame:
    """Links (a, b) between distinct fingerprints that connect exactly what the radius connects."""
    rows = shard_rows(distinct, radius, blocks or radius + 1, shard).repartition("tree", "shard").sortWithinPartitions("tree", "shard", "fp")
    bound_batches(distinct.sparkSession)

    def find(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def out(a, b):
            return pa.RecordBatch.from_arrays([pa.array(a.view(np.int64)), pa.array(b.view(np.int64))], names=["a", "b"])

        held: list[np.ndarray] = []
        key = None
        for batch in batches:
            if not batch.num_rows:
                continue
            tree, shard, fp = (c.to_numpy() for c in batch.columns)
            cuts = np.flatnonzero((np.diff(tree) != 0) | (np.diff(shard) != 0)) + 1
            for part in np.split(np.arange(len(fp)), cuts):
                now = (tree[part[0]], shard[part[0]])
                if now != key and held:
                    a, b = links(np.concatenate(held).view(np.uint64), radius)
                    if len(a):
                        yield out(a, b)
                    held = []
                key = now
                held.append(fp[part])
        if held:
            a, b = links(np.concatenate(held).view(np.uint64), radius)
            if len(a):
                yield out(a, b)

    return rows.mapInArrow(find, "a bigint, b bigint")


def components(pairs: DataFrame) -> DataFrame:
    """(node, root): the least node of each component, by alternating large-star and small-star rounds. Each round is
    written; it ends when a round changes nothing, after a number of rounds logarithmic in the component size."""
    both = lambda p: p.select("a", "b").unionByName(p.select(F.col("b").alias("a"), F.col("a").alias("b")))
    edges = written(pairs.where("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct(), "links")
    mark = None
    while True:
        near = both(edges)
        least = near.groupBy("a").agg(F.least(F.min("b"), F.col("a")).alias("m"))
        large = near.where("b > a").join(least, "a").select(F.col("b").alias("a"), F.col("m").alias("b")).distinct()
        least = large.groupBy("a").agg(F.min("b").alias("m"))
        small = large.join(least, "a").select(F.when(F.col("b") == F.col("m"), F.col("a")).otherwise(F.col("b")).alias("a"), F.col("m").alias("b")).where("a <> b").distinct()
        edges = written(small, "links")
        now = edges.agg(F.count("*"), F.bit_xor(F.xxhash64("a", "b")), F.sum(F.pmod(F.xxhash64("b", "a"), F.lit(1 << 31)))).first()
        if now == mark:
            return edges.select(F.col("a").alias("node"), F.col("b").alias("root"))
        mark = now


def near_groups(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", shingle: int = SHINGLE, radius: int = RADIUS, blocks: int | None = None) -> DataFrame:
    """doc_id, fingerprint (16 hex digits), component_id: the smallest doc_id that links can reach."""
    fps = written(fingerprints(docs, id_col, text_col, shingle), "fingerprints")
    distinct = written(fps.groupBy("fp").agg(F.min("doc_id").alias("first"), F.count("*").alias("n")), "distinct-fingerprints")
    roots = components(linked_pairs(distinct, radius, blocks))
    named = distinct.join(roots, F.col("fp") == F.col("node"), "left").withColumn("root", F.coalesce("root", "fp")).select("fp", "root", "first", "n")
    named = written(named, "roots")
    least = written(named.groupBy("root").agg(F.min("first").alias("component_id"), F.count("*").alias("members")), "components")
    classes = written(join_classes(named, least, ["root"], "members").select("fp", "component_id", "n"), "classes")
    return join_classes(fps, classes, ["fp"], "n").select(F.col("doc_id").alias(id_col), F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def keep_first(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", **options) -> DataFrame:
    """One document of each class, with the columns of docs: the one with the smallest doc_id, of several the one with
    the smallest SHA-256 of its text. Documents without a doc_id stay only where their class has no other; rows that
    repeat the kept document's doc_id and text go, all but the one with the least hash of its row."""
    from pyspark.sql import Window as W

    name, nth = spare(docs.columns, "_key", "_nth")
    sha = F.sha2(F.coalesce(F.col(f"`{text_col}`"), F.lit("")), 256)
    key = lambda ident, digest: F.concat_ws(":", F.coalesce(ident.cast("string"), F.lit("null")), digest)
    ident = F.struct(F.col(f"`{id_col}`").isNull().alias("none"), F.col(f"`{id_col}`").alias("id"), sha.alias("digest"))
    named = near_groups(docs.select(ident.alias("_row"), F.col(f"`{text_col}`").alias("_text")), "_row", "_text", **options)
    keep = named.select(key(F.col("component_id.id"), F.col("component_id.digest")).alias(name)).distinct()
    rows = docs.withColumn(name, key(F.col(f"`{id_col}`"), sha)).join(keep, name, "left_semi")
    first = W.partitionBy(name).orderBy(*row_order(docs))
    return rows.withColumn(nth, F.row_number().over(first)).where(F.col(nth) == 1).select(*[F.col(f"`{c}`") for c in docs.columns])
