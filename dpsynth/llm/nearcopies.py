"""SimHash near-dedup with the reach of a pipeline stage: documents whose sets of five-word shingles
have a Jaccard similarity of 0.8 or more are linked, and one of each component of links stays.

At that similarity two 64-bit fingerprints lie some 10 +- 3 bits apart, and no tree over Hamming
distances prunes at such radii.  So the links of the fingerprints (simhash.links) are candidates,
and so are documents that agree in one of BANDS small samples of their shingles, each the minima of
BAND hash orders.  A pair at the threshold agrees in no sample with probability
(1 - 0.8^4)^32 = 5e-8, a closer pair less.  Each sample's documents are tied to the smallest of
them, never pair by pair, and the components of all these ties hold all candidate pairs.  Inside
such a component every pair of sets is counted exactly; a component too large for a task is dealt
as pairs of blocks.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from dpsynth.llm import simhash
from dpsynth.llm.backoff import mix
from dpsynth.llm.common import cut, map_batches, slices
from dpsynth.llm.simhash import LOWER, Forest, bits_over_half, components, keep_first

SHINGLE, BANDS, BAND = 5, 32, 4
#: Documents and shingles of a block; a task compares two blocks at a time.
BLOCK_DOCS, BLOCK_SHINGLES = 1000, 500_000
#: Shingles in more documents of a task than this are counted by matrix products, COLUMNS at a time.
COMMON, COLUMNS = 32, 2048
_RNG = np.random.default_rng(20)
FACTORS = _RNG.integers(0, 1 << 63, BANDS * BAND, np.uint64) * np.uint64(2) + np.uint64(1)


def shingle_set(text: str | None, shingle: int = SHINGLE) -> np.ndarray:
    """Sorted distinct XXH64 hashes of the shingles (A-Z lowered); a shorter text is one shingle."""
    words = (text or "").encode("utf-8", "surrogatepass").translate(LOWER).split()
    digest = xxhash.xxh64_intdigest
    if len(words) > shingle:
        return np.unique(np.array([digest(x, 42) for x in map(b" ".join, zip(*[words[i:] for i in range(shingle)], strict=False))], np.uint64))
    return np.array([digest(b" ".join(words), 42)] if words else [], np.uint64)


def band_keys(sets: list[np.ndarray]) -> np.ndarray:
    """One row of BANDS keys for each of the sets, none of which is empty."""
    h, starts = np.concatenate(sets), np.cumsum([0, *map(len, sets[:-1])])
    keys = np.zeros((len(sets), BANDS), np.uint64)
    for k, a in enumerate(FACTORS):
        keys[:, k // BAND] = mix(keys[:, k // BAND] + np.minimum.reduceat(h * a, starts) + np.uint64(k))
    return keys


def signatures(docs: DataFrame) -> DataFrame:
    """doc_id, row_hash, sid (hash of the shingle set), n (its size), fp (its fingerprint) and bands per row of ``docs``."""

    def run(batches):
        for b in slices(batches):
            sids, sizes, prints, bands, held, size = [], [], [], [], [], 0

            def flush(held=held, bands=bands, prints=prints):
                some = [s for s in held if len(s)]
                keys = iter(band_keys(some).view(np.int64).tolist() if some else [])
                bands += [next(keys) if len(s) else [] for s in held]
                prints.append(bits_over_half(np.concatenate([np.zeros(0, np.uint64), *some]), np.array([len(s) for s in held], np.int64)))
                held.clear()

            for t in b.column(2).to_pylist():
                s = shingle_set(t)
                sids.append(xxhash.xxh64_intdigest(s.tobytes(), 7))
                sizes.append(len(s))
                held.append(s)
                size += len(s)
                if size > 1 << 15:  # so many hashes stay in the processor's cache
                    flush()
                    size = 0
            flush()
            longs = [pa.array(np.array(sids, np.uint64).view(np.int64)), pa.array(sizes, pa.int64()), pa.array(np.concatenate(prints).view(np.int64))]
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), *longs, pa.array(bands, pa.list_(pa.int64()))], ["doc_id", "row_hash", "sid", "n", "fp", "bands"])

    return map_batches(keyed(docs).select("doc_id", "row_hash", "text"), run, "doc_id long, row_hash long, sid long, n long, fp long, bands array<long>")


def keyed(docs: DataFrame) -> DataFrame:
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64(F.col("text").cast("string")).alias("row_hash"), F.col("text").cast("string").alias("text"))


def intersections(sets: list[np.ndarray]) -> np.ndarray:
    """Sizes of the intersections of all pairs (i < j) of the sets, exactly."""
    m = len(sets)
    owner = np.repeat(np.arange(m), [len(s) for s in sets])
    _, at, found = np.unique(np.concatenate(sets), return_inverse=True, return_counts=True)
    order = np.lexsort((owner, at))
    owner, at = owner[order], at[order]
    out = np.zeros((m, m), np.float32)
    few = (found[at] > 1) & (found[at] <= COMMON)
    o, g = owner[few], at[few]
    for shift in range(1, min(COMMON, len(o))):
        i = np.flatnonzero(g[:-shift] == g[shift:])
        if not len(i):
            break
        np.add.at(out, (o[i], o[i + shift]), 1)
    many = np.flatnonzero(found > COMMON)
    for k in range(0, len(many), COLUMNS):
        column = np.full(len(found), -1)
        column[many[k : k + COLUMNS]] = np.arange(len(many[k : k + COLUMNS]))
        hit = column[at] >= 0
        table = np.zeros((m, COLUMNS), np.float32)
        table[owner[hit], column[at[hit]]] = 1
        out += table @ table.T
    return np.triu(out, 1)


def similar(sets: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    """Pairs (i < j) of non-empty sets with a Jaccard similarity of 0.8 or more."""
    n = np.array([len(s) for s in sets], np.int64)
    both = intersections(sets)
    # x / (a + b - x) >= 4 / 5 is 9 x >= 4 (a + b)
    return np.nonzero((both > 0) & (9 * both >= 4 * (n[:, None] + n[None, :])))


def candidates(rows: DataFrame) -> DataFrame:
    """Ties (a, b) between the sids in ``rows`` (sid, fp, bands): the links of their fingerprints, and the
    smallest sid of each band key with all others."""
    ties = rows.select("sid", F.explode("bands").alias("key"))
    least = cut(ties.groupBy("key").agg(F.min("sid").alias("b"), F.count("*").alias("n")).where("n > 1").select("key", "b"))
    banded = ties.join(least, "key").where("sid <> b").select(F.col("sid").alias("a"), "b")
    prints = rows.where(F.size("bands") > 0)
    heads = cut(prints.groupBy("fp").agg(F.min("sid").alias("head")))
    equal = prints.join(heads, "fp").where("sid <> head").select(F.col("sid").alias("a"), F.col("head").alias("b"))
    at = lambda c: heads.select(F.col("fp").alias(c), F.col("head").alias(f"head_{c}"))
    near = simhash.links(heads.select("fp")).join(at("a"), "a").join(at("b"), "b").select(F.col("head_a").alias("a"), F.col("head_b").alias("b"))
    return banded.union(equal).union(near)


def links(rows: DataFrame, docs: DataFrame) -> DataFrame:
    """Forest edges (a, b) between the sids in ``rows`` (sid, k: a row with this set, n, fp, bands)."""
    near = components(candidates(rows))
    members = cut(rows.select("sid", "k", "n").join(near.select(F.col("node").alias("sid"), "root"), "sid"))
    blocks = members.groupBy("root").agg(F.ceil(F.greatest(F.count("*") / BLOCK_DOCS, F.sum("n") / BLOCK_SHINGLES)).cast("int").alias("blocks"))
    own = F.pmod(F.xxhash64("sid"), F.col("blocks")).cast("int")
    dealt = members.join(blocks, "root").withColumn("own", own).select("sid", "root", "own", "blocks", F.col("k.doc_id").alias("llm_doc"), F.col("k.row_hash").alias("llm_hash"))
    texts = keyed(docs).join(dealt.hint("shuffle_hash"), F.col("doc_id").eqNullSafe(F.col("llm_doc")) & (F.col("row_hash") == F.col("llm_hash"))).select("sid", "root", "own", "blocks", "text")

    def read(batches):
        for b in slices(batches):
            yield pa.RecordBatch.from_arrays([*b.columns[:4], pa.array([shingle_set(t).tobytes() for t in b.column(4).to_pylist()], pa.binary())], ["sid", "root", "own", "blocks", "grams"])

    def compare(t: pa.Table) -> pa.Table:
        of = dict(zip(t.column("sid").to_pylist(), t.column("grams").to_pylist(), strict=True))  # a repeated row once
        sids = sorted(of)
        i, j = similar([np.frombuffer(of[s], np.uint64) for s in sids])
        forest = Forest(len(sids))
        forest.join(i, j)
        edges = [(sids[x], sids[r]) for x in range(len(sids)) if (r := forest.find(x)) != x]
        return pa.table({"a": pa.array([a for a, _ in edges], pa.int64()), "b": pa.array([b for _, b in edges], pa.int64())})

    sets = map_batches(texts, read, "sid long, root long, own int, blocks int, grams binary")
    # a block meets each block, itself among them, in one task: with one block there is one task, with more a task for each two
    other = F.expr("case when blocks = 1 then array(0) else filter(sequence(0, blocks - 1), x -> x <> own) end")
    pairs = sets.withColumn("other", F.explode(other)).select("sid", "grams", "root", F.least("own", "other").alias("lo"), F.greatest("own", "other").alias("hi"))
    return pairs.groupBy("root", "lo", "hi").applyInArrow(compare, "a long, b long")


def keep_one(docs: DataFrame) -> DataFrame:
    """``docs`` with one row of each component: that of the smallest doc_id, then text hash.

    Texts with the same shingles are one set; null, empty and blank texts have none and are alike.
    A text of fewer than five words is one shingle.  Repeated rows leave one, whatever their
    other columns; null doc_ids are the smallest.  All columns stay as they are, whatever
    their names; an empty table stays empty.
    """
    rows = cut(signatures(docs))
    sets = cut(rows.groupBy("sid").agg(F.min(F.struct("doc_id", "row_hash")).alias("k"), *(F.first(c).alias(c) for c in ("n", "fp", "bands"))))
    found = components(links(sets, docs)).withColumnRenamed("node", "sid")
    first = sets.join(found, "sid", "left").groupBy(F.coalesce("root", "sid").alias("root")).agg(F.min("k").alias("k"))
    return keep_first(docs, cut(first.select("k.doc_id", "k.row_hash")))
