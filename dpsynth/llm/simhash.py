"""SimHash near-duplicates by vantage-point trees over Hamming distances.

A vantage-point tree splits fingerprints by their distance to a point at a radius; a ball of the
search radius that reaches over the sphere must be looked for on both sides.  Distances between
unrelated 64-bit fingerprints crowd around 32 +- 4, so at radius 3 each split still sends three
in ten points to both sides: good inside a shard, but far too much as the only way to deal
billions of fingerprints.  So the trees stand on top of each other:

* Dealing.  The distances over blocks of a fingerprint add up to that of the whole: if two
  fingerprints differ in at most r bits, at least ``blocks - r`` of the blocks have distance zero.
  One tree for each such set of blocks sends a fingerprint to one shard only, as a ball of radius
  zero never reaches over a sphere.  Up to SHARD fingerprints there is one shard and no dealing.
* Cutting.  Shards beyond SHARD_LIMIT are cut by distributed vantage points while that saves work: the
  points outside the sphere but within the radius of it go to the inner shard as well.
* Searching.  In each shard a vantage-point tree over whole fingerprints is searched as a
  self-join; pairs on different sides of a sphere are compared only near it.

Distinct fingerprints are compared only, so groups of copies cost nothing.  A shard returns a
spanning forest of its links, never all pairs.  Components are then found by alternating star
contraction over the forest edges, with a checkpoint each round.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from dpsynth.llm.common import columns_of, cut, fresh, map_batches, slices

SHINGLE, RADIUS = 3, 3
#: Distinct fingerprints that a shard should hold, and beyond which it is cut.
SHARD, SHARD_LIMIT = 4096, 1 << 16
#: So many fingerprints, a leaf of a tree, are compared pair by pair.
LEAF = 64
LOWER = bytes(c + 32 if 65 <= c <= 90 else c for c in range(256))


def bits_over_half(hashes: np.ndarray, counts: np.ndarray) -> np.ndarray:
    """Fingerprints of consecutive groups of 64-bit hashes: a bit is set if it is in over half of a group."""
    out = np.zeros(len(counts), np.uint64)
    some = np.flatnonzero(counts)
    if not len(some):
        return out
    starts = (np.cumsum(counts) - counts)[some]
    for bit in range(64):
        ones = np.add.reduceat((hashes >> np.uint64(bit) & np.uint64(1)).astype(np.uint8), starts, dtype=np.int64)
        out[some] |= (2 * ones > counts[some]).astype(np.uint64) << np.uint64(bit)
    return out


def fingerprints_of(texts: list[str | None], shingle: int = SHINGLE) -> np.ndarray:
    """64-bit fingerprints: bit set if set in over half of the shingles' XXH64 hashes, repeats included."""
    digest, hashes, counts = xxhash.xxh64_intdigest, [], []
    for text in texts:
        words = (text or "").encode("utf-8", "surrogatepass").translate(LOWER).split()
        if len(words) > shingle:
            hashes += [digest(x, 42) for x in map(b" ".join, zip(*[words[i:] for i in range(shingle)], strict=False))]
            counts.append(len(words) - shingle + 1)
        else:
            counts.append(bool(words))
            if words:
                hashes.append(digest(b" ".join(words), 42))
    return bits_over_half(np.array(hashes, np.uint64), np.array(counts, np.int64))


def fingerprint(docs: DataFrame, shingle: int = SHINGLE) -> DataFrame:
    """doc_id, row_hash (of the text) and fp (the fingerprint as a signed long) per row of ``docs``."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in slices(batches):
            texts, found, size, first = b.column(2).to_pylist(), [], 0, 0
            for i, t in enumerate(texts):
                size += len(t or "")
                if size > 4 << 20 or i + 1 == len(texts):  # hashes of some million characters at a time
                    found.append(fingerprints_of(texts[first : i + 1], shingle))
                    size, first = 0, i + 1
            fp = np.concatenate(found).view(np.int64) if found else np.zeros(0, np.int64)
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(fp)], ["doc_id", "row_hash", "fp"])

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64(F.col("text").cast("string")).alias("row_hash"), F.col("text").cast("string").alias("text"))
    return map_batches(rows, run, "doc_id long, row_hash long, fp long")


def hamming(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    return np.bitwise_count(a ^ b)


class Forest:
    """Union-find over the members of one shard."""

    def __init__(self, n: int):
        self.parent = list(range(n))

    def find(self, x: int) -> int:
        while self.parent[x] != x:
            self.parent[x] = x = self.parent[self.parent[x]]
        return x

    def join(self, xs: np.ndarray, ys: np.ndarray) -> None:
        for x, y in zip(xs.tolist(), ys.tolist(), strict=True):
            a, b = self.find(x), self.find(y)
            if a != b:
                self.parent[max(a, b)] = min(a, b)


def link_across(fp: np.ndarray, a: np.ndarray, b: np.ndarray, radius: int, forest: Forest, tally: Counter) -> None:
    """Join the members of a and b within the radius; both sides are cut at spheres until small."""
    todo = [(a, b)]
    while todo:
        a, b = todo.pop()
        if not len(a) or not len(b):
            continue
        pairs = len(a) * len(b)
        if pairs > LEAF * LEAF:
            point = fp[(a if len(a) >= len(b) else b)[0]]
            da, db = hamming(fp[a], point).astype(np.int64), hamming(fp[b], point).astype(np.int64)
            mid = int(np.median(da if len(a) >= len(b) else db))
            # a pair within the radius lies on one side, or right beside the sphere
            parts = [(a[da <= mid], b[db <= mid + radius]), (a[da > mid], b[db > mid - radius])]
            left = sum(len(x) * len(y) for x, y in parts)
            if left <= 0.9 * pairs:
                tally["pruned"] += pairs - left
                todo += parts
                continue
        tally["compared"] += pairs
        for k in range(0, len(a), 256):
            for m in range(0, len(b), 4096):
                i, j = np.nonzero(hamming(fp[a[k : k + 256]][:, None], fp[b[m : m + 4096]][None, :]) <= radius)
                forest.join(a[k : k + 256][i], b[m : m + 4096][j])


def link_within(fp: np.ndarray, members: np.ndarray, radius: int, forest: Forest, tally: Counter) -> None:
    """Join all members within the radius: a vantage-point tree over them, searched as a self-join.

    tally counts the nodes of the tree, the pairs that were compared and those pruned.
    """
    todo = [members]
    while todo:
        m = todo.pop()
        if len(m) <= LEAF:
            tally["compared"] += len(m) * (len(m) - 1) // 2
            i, j = np.nonzero(np.triu(hamming(fp[m][:, None], fp[m][None, :]) <= radius, 1))
            forest.join(m[i], m[j])
            continue
        d = hamming(fp[m], fp[m[0]]).astype(np.int64)
        mid = int(np.median(d))
        if mid == d.max():
            mid -= 1
        inside, outside = d <= mid, d > mid
        near, far = m[inside & (d > mid - radius)], m[outside & (d <= mid + radius)]
        tally["nodes"] += 1
        tally["pruned"] += int(inside.sum()) * int(outside.sum()) - len(near) * len(far)
        todo += [m[inside], m[outside]]
        link_across(fp, near, far, radius, forest, tally)


def shard_edges(key: np.ndarray, fp: np.ndarray, radius: int, tally: Counter | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Spanning forest of the links of every shard in rows sorted by key: (fingerprint, root)."""
    forest, tally = Forest(len(fp)), Counter() if tally is None else tally
    border = np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1]]))
    for a, z in zip(border.tolist(), np.append(border[1:], len(fp)).tolist(), strict=True):
        link_within(fp, np.arange(a, z), radius, forest, tally)
    root = np.array([forest.find(x) for x in range(len(fp))], np.int64)
    moved = np.flatnonzero(root != np.arange(len(fp)))
    return fp[moved], fp[root[moved]]


def block_sets(radius: int, blocks: int) -> list[list[tuple[int, int]]]:
    """Bit ranges (shift, width) of every set of blocks that a pair within the radius may agree on."""
    at = [64 * i // blocks for i in range(blocks + 1)]
    ranges = [(at[i], at[i + 1] - at[i]) for i in range(blocks)]
    return [list(x) for x in combinations(ranges, blocks - radius)]


def cut_large(homes: DataFrame, radius: int, limit: int) -> DataFrame:
    """``homes`` (shard, fp) with the shards of more than ``limit`` rows cut at spheres.

    A round cuts all such shards at once.  The vantage point of a shard is one of its members.
    Points outside its sphere, but not by more than the radius, are dealt to both sides, so
    any two within the radius are together in one of them.  The sphere lies so that both sides
    have about two thirds.  A shard stays whole where that would not save a twentieth of its pairs,
    as its members are all about as far from each other; its task then holds all of it.
    """
    homes = homes.withColumn("whole", F.lit(False))
    while True:
        large = homes.where(~F.col("whole")).groupBy("shard").agg(F.count("*").alias("n"), F.min_by("fp", F.xxhash64("fp", F.lit("vantage"))).alias("point")).where(F.col("n") > limit)
        large = cut(large)  # at most rows / limit rows
        if large.isEmpty():
            return homes.select("shard", "fp")
        away = F.bit_count(F.col("fp").bitwiseXOR(F.col("point")))
        mids = homes.join(large, "shard").groupBy("shard", "n", "point").agg((F.percentile_approx(away, 0.5) - (radius + 1) // 2).alias("mid"))
        sides = homes.join(mids, "shard").groupBy("shard").agg(F.count_if(away <= F.col("mid") + radius).alias("inner"), F.count_if(away > F.col("mid")).alias("outer"))
        plan = cut(mids.join(sides, "shard").select("shard", "point", "mid", (F.col("inner") ** 2 + F.col("outer") ** 2 > 0.95 * F.col("n") ** 2).alias("stays")))
        side = lambda k, c: F.when(c, F.xxhash64("shard", F.lit(k)))
        halves = F.array_compact(F.array(side(0, away <= F.col("mid") + radius), side(1, away > F.col("mid"))))
        dealt = F.explode(F.when(F.coalesce("stays", F.lit(True)), F.array("shard")).otherwise(halves))
        homes = cut(homes.join(plan, "shard", "left").select(dealt.alias("shard"), "fp", (F.col("whole") | F.coalesce("stays", F.lit(False))).alias("whole")))


def links(prints: DataFrame, radius: int = RADIUS, blocks: int | None = None, shard: int = SHARD, shard_limit: int = SHARD_LIMIT) -> DataFrame:
    """Forest edges (a, b) between distinct fingerprints in ``prints`` (column fp) within the radius.

    blocks: how many blocks the trees for dealing have; by default radius + 1, one more for each
    factor of 1000 in the number of fingerprints beyond a million, so that shards stay small.
    """
    if not 0 <= radius < 16:
        raise ValueError("the radius must be 0 to 15")
    n = prints.count()
    shards = -(-n // shard)
    if blocks is None:
        many, blocks = n, radius + 1
        while many > 1 << 20 and blocks < 2 * (radius + 1):
            many, blocks = many // 1000, blocks + 1
    sets = block_sets(radius, blocks)

    def leaf(part: list[tuple[int, int]]):
        bits = [F.shiftrightunsigned("fp", s).bitwiseAND((1 << w) - 1) if w < 64 else F.col("fp") for s, w in part]
        return F.pmod(F.xxhash64(*bits), F.lit(shards))

    if shards <= 1:
        homes = prints.select(F.lit(0).cast("long").alias("shard"), "fp")
    else:
        homes = prints.select("fp", F.posexplode(F.array(*[leaf(p) for p in sets])).alias("tree", "leaf")).select(F.xxhash64("tree", "leaf").alias("shard"), "fp")
    homes = cut_large(homes, radius, shard_limit)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def done(parts: list[pa.RecordBatch]) -> pa.RecordBatch:
            t = pa.Table.from_batches(parts)
            a, b = shard_edges(t.column("shard").to_numpy(), t.column("fp").to_numpy().view(np.uint64), radius)
            return pa.RecordBatch.from_arrays([pa.array(a.view(np.int64)), pa.array(b.view(np.int64))], ["a", "b"])

        held: list[pa.RecordBatch] = []
        for batch in batches:
            if not batch.num_rows:
                continue
            key = batch.column("shard").to_numpy(zero_copy_only=False)
            last = int(np.searchsorted(key, key[-1])) if key[0] <= key[-1] else 0
            if held and last > 0 or held and held[-1].column("shard")[-1].as_py() != key[0]:
                yield done([*held, batch.slice(0, last)])
                held = []
            elif last > 0:
                yield done([batch.slice(0, last)])
            held.append(batch.slice(last))
        if held:
            yield done(held)

    # two shards of one number by chance only cost time: pairs are compared whole
    dealt = homes.repartition("shard").sortWithinPartitions("shard", "fp")
    return dealt.mapInArrow(run, "a long, b long")


def components(edges: DataFrame) -> DataFrame:
    """(node, root) for every node of ``edges`` (a, b): root is the smallest node of its component.

    Alternating star contraction: each round links larger neighbours, then smaller ones, to the
    smallest.  Both steps are an aggregate and a join on the node, so no group is ever gathered.
    Rounds end when one changes nothing; each makes the sum of the ends smaller, so they do end.
    """
    state = lambda e: e.agg(F.count("*"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first()
    star = cut(edges.where("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct())
    before, now = None, state(star)
    while before != now:
        both = star.union(star.select(F.col("b").alias("a"), F.col("a").alias("b")))
        least = both.groupBy("a").agg(F.min("b").alias("m")).select("a", F.least("a", "m").alias("m"))
        large = both.where("b > a").join(least, "a").select(F.col("b").alias("a"), F.col("m").alias("b")).where("a <> b").distinct()
        down = large.groupBy("a").agg(F.min("b").alias("m"))
        small = large.join(down, "a").select(F.col("b").alias("a"), F.col("m").alias("b")).where("a <> b").union(down.select("a", F.col("m").alias("b"))).distinct()
        star = cut(small)
        before, now = now, state(star)
    return star.select(F.col("a").alias("node"), F.col("b").alias("root")).union(star.select(F.col("b").alias("node"), F.col("b").alias("root")).distinct())


def near_duplicates(docs: DataFrame, shingle: int = SHINGLE, radius: int = RADIUS) -> tuple[DataFrame, DataFrame]:
    """Rows (doc_id, row_hash, fp) of ``docs``, and (fp, root) of every distinct fingerprint, where
    root is the fingerprint that stands for its component.  Both are cut: joins on fp then have
    plain exchanges on both sides, so AQE can split a fingerprint that many copies share."""
    rows = cut(fingerprint(docs, shingle))
    prints = cut(rows.select("fp").distinct())
    found = components(links(prints, radius)).withColumnRenamed("node", "fp")
    return rows, cut(prints.join(found, "fp", "left").select("fp", F.coalesce("root", "fp").alias("root")))


def component_digests(docs: DataFrame, shingle: int = SHINGLE, radius: int = RADIUS) -> DataFrame:
    """Per row of ``docs``: doc_id, fingerprint (16 hex digits), component_id (smallest doc_id).

    Null and empty texts have the fingerprint zero and are linked like any other.  Null doc_ids
    belong to components but are never their smallest; repeated rows each give a row.
    """
    rows, roots = near_duplicates(docs, shingle, radius)
    # smallest ids of fingerprints, then of components: one row a fingerprint, however many copies
    least = rows.groupBy("fp").agg(F.min("doc_id").alias("least")).join(roots, "fp")
    of = least.groupBy("root").agg(F.min("least").alias("component_id"))
    named = cut(roots.join(of, "root").select("fp", "component_id"))
    return rows.join(named, "fp").select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def keep_first(docs: DataFrame, first: DataFrame) -> DataFrame:
    """The rows of ``docs`` whose doc_id and text hash are in ``first`` (doc_id, row_hash), each once.

    Columns stay as they are, whatever their names.  Null doc_ids are equal.
    """
    # plain keys without nulls: the join and the dropping of repeated rows then share one exchange of texts
    key = lambda c, row: [F.coalesce(c, F.lit(0).cast("long")).alias("key"), c.isNull().alias("none"), row.alias("row")]
    first = first.select(*key(F.col("doc_id"), F.col("row_hash"))).distinct()
    (every,) = fresh(docs, "llm_row")
    rows = docs.select(F.struct(*columns_of(docs)).alias(every), *key(F.col("doc_id").cast("long"), F.xxhash64(F.col("text").cast("string"))))
    met = rows.join(first.hint("shuffle_hash"), ["key", "none", "row"], "left_semi")
    return met.dropDuplicates(["key", "none", "row"]).select(f"{every}.*")


def keep_one(docs: DataFrame, shingle: int = SHINGLE, radius: int = RADIUS) -> DataFrame:
    """``docs`` with one row of each component: that of the smallest doc_id, then text hash.

    Null, empty and blank texts have the fingerprint zero.  Repeated rows leave one, whatever
    their other columns; null doc_ids are the smallest.  An empty table stays empty.
    """
    rows, roots = near_duplicates(docs, shingle, radius)
    least = rows.groupBy("fp").agg(F.min(F.struct("doc_id", "row_hash")).alias("k")).join(roots, "fp")
    return keep_first(docs, least.groupBy("root").agg(F.min("k").alias("k")).select("k.doc_id", "k.row_hash"))
