"""Stupid-backoff scores against n-gram counts of the whole corpus.

The count tables and the exploded n-grams meet as in a hash join, but travel in blocks: a chunk
of documents sends the distinct keys of its uni-, bi- and trigrams, sorted and delta-coded, to
the partitions that own their hash range; an owner adds up what all chunks sent, which is its
part of the count tables, and returns the totals in the order of each request; the chunk looks
its n-grams up and sums per document.  Every n-gram of a chunk travels once, whatever its
frequency, so frequent words make no skew.  Rows of plain 64-bit keys would need some 30 bytes
for each n-gram; a block needs about four.

Chunks and owners both grow with the input, and so would the blocks between them with its square.
So a node never sends more than 2^FAN_BITS blocks: beyond that many owners requests go by way of
relays, each for the chunks of one group and one range of keys, which add up before they pass on,
and totals come back the same way.  The number of blocks is then in proportion to the input: one
hop up to some 100 GB, two up to some 1,000 TB.

Keys are hashes of 64 bits at every size: at 10^10 n-grams one in 10^9 shares its key with another.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from dpsynth.llm.common import cut, shuffle_width, slices

ALPHA, MIN_COUNT = 0.4, 2
#: Compressed input bytes for which one chunk and one owner is made.
CHUNK_BYTES = 6 << 20
KEY_BITS = 64
#: A node sends at most 2^FAN_BITS blocks; chunks of which one task reads several, beyond the session's partitions.
FAN_BITS, TASK_CHUNKS = 14, 32

LOWER = bytes(c + 32 if 65 <= c <= 90 else c for c in range(256))
SPACE = np.isin(np.arange(256), [32, *range(9, 14)])
_M1, _M2, _M3 = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xBF58476D1CE4E5B9), np.uint64(0x94D049BB133111EB)


def mix(x: np.ndarray) -> np.ndarray:
    """A bijective scramble of 64-bit numbers."""
    x = (x ^ (x >> np.uint64(30))) * _M2
    x = (x ^ (x >> np.uint64(27))) * _M3
    return x ^ (x >> np.uint64(31))


def powers(n: int) -> np.ndarray:
    """Powers of an odd multiplier modulo 2^64."""
    out = np.ones(n, np.uint64)
    np.multiply.accumulate(np.full(n - 1, _M1), out=out[1:]) if n > 1 else None
    return out


def word_hashes(texts: list[str | bytes | None]) -> tuple[np.ndarray, np.ndarray]:
    """64-bit hash of every white-space word (A-Z lowered), and the number of words per text."""
    raw = [(t if isinstance(t, bytes) else (t or "").encode("utf-8", "surrogatepass")).translate(LOWER) for t in texts]
    size = np.array([len(r) + 1 for r in raw], np.int64)
    data = np.frombuffer(b"\n".join([*raw, b""]) if raw else b"", np.uint8)
    inside = ~SPACE[data]
    edge = np.diff(np.concatenate([[False], inside, [False]]).astype(np.int8))
    start, stop = np.flatnonzero(edge == 1), np.flatnonzero(edge == -1)
    counts = np.diff(np.searchsorted(start, np.concatenate([[0], np.cumsum(size)])))
    if not len(start):
        return np.zeros(0, np.uint64), counts
    length = stop - start
    letters = data[inside].astype(np.uint64) + np.uint64(1)
    first = np.cumsum(length) - length
    place = np.arange(len(letters)) - np.repeat(first, length)
    return mix(np.add.reduceat(letters * powers(int(length.max()))[place], first) + length.astype(np.uint64)), counts


def gram_keys(words: np.ndarray, counts: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Keys of the uni-, bi- and trigram that end at each word, and the word's place in its text.

    Bi- and trigrams that would begin before the text are left 0 and must not be used.
    """
    place = np.arange(len(words)) - np.repeat(np.cumsum(counts) - counts, counts)
    one = mix(words + np.uint64(1))
    two, three = np.zeros_like(words), np.zeros_like(words)
    two[1:] = mix(words[:-1] * _M1 + words[1:] + np.uint64(2))
    three[2:] = mix((words[:-2] * _M1 + words[1:-1]) * _M2 + words[2:] + np.uint64(3))
    return one, two, three, place


def pack(numbers: np.ndarray) -> bytes:
    """Unsigned numbers, compressed byte plane by byte plane."""
    planes = np.ascontiguousarray(numbers.astype("<u8").view(np.uint8).reshape(-1, 8).T)
    return pa.compress(planes.tobytes(), codec="zstd", asbytes=True) if len(numbers) else b""


def unpack(block: bytes, n: int) -> np.ndarray:
    if not n:
        return np.zeros(0, np.uint64)
    planes = np.frombuffer(pa.decompress(block, 8 * n, codec="zstd", asbytes=True), np.uint8).reshape(8, n)
    return np.ascontiguousarray(planes.T).view("<u8").reshape(-1)


def distinct_grams(texts: list[str | bytes | None]) -> tuple[np.ndarray, np.ndarray]:
    words, counts = word_hashes(texts)
    one, two, three, place = gram_keys(words, counts)
    return np.unique(np.concatenate([one, two[place >= 1], three[place >= 2]]), return_counts=True)


def hops(owners: int, fan_bits: int = FAN_BITS) -> tuple[int, int]:
    """Number of hops to at least so many owners, and bits of the key that each decides by."""
    need = max(1, (owners - 1).bit_length())
    n = -(-need // fan_bits)
    return n, -(-need // n)


MESSAGE = "grp long, prefix long, from_grp long, from_prefix long, size long, keys binary, counts binary"
REPLY = "grp long, prefix long, part long, size long, totals binary"


def messages(keys: np.ndarray, counts: np.ndarray, grp: int, prefix: int, hop: int, width: int) -> pa.Table:
    """Blocks of a node's sorted keys, which all begin with the bits ``prefix``, for the nodes of the
    next hop: each has one more digit of ``width`` bits, and the senders of 2^width groups."""
    digits = np.arange(1 << width, dtype=np.uint64)
    starts = (np.uint64(prefix) << np.uint64(width) | digits) << np.uint64(KEY_BITS - width * (hop + 1))
    edge = np.append(np.searchsorted(keys, starts), len(keys))
    sent = np.flatnonzero(edge[1:] > edge[:-1])
    pieces = [(edge[d], edge[d + 1]) for d in sent]
    same = lambda x: pa.array(np.full(len(sent), x, np.int64))
    return pa.table({
        "grp": same(grp >> width), "prefix": pa.array((prefix << width) + sent), "from_grp": same(grp), "from_prefix": same(prefix), "size": pa.array([z - a for a, z in pieces], pa.int64()),
        "keys": pa.array([pack(np.diff(keys[a:z], prepend=np.uint64(0))) for a, z in pieces], pa.binary()), "counts": pa.array([pack(counts[a:z]) for a, z in pieces], pa.binary()),
    })


def merged(t: pa.Table) -> tuple[np.ndarray, np.ndarray, np.ndarray, list[int]]:
    """Distinct keys of some messages, their counts, each message's keys as places among them, and sizes."""
    sizes = t.column("size").to_pylist()
    keys = [np.cumsum(unpack(k, m), dtype=np.uint64) for k, m in zip(t.column("keys").to_pylist(), sizes, strict=True)]
    counts = np.concatenate([unpack(c, m) for c, m in zip(t.column("counts").to_pylist(), sizes, strict=True)])
    found, back = np.unique(np.concatenate(keys), return_inverse=True)
    return found, np.bincount(back, counts).astype(np.uint64), back, sizes


def replies(t: pa.Table, totals: np.ndarray, back: np.ndarray, sizes: list[int]) -> pa.Table:
    """The totals of each message's keys, for its sender."""
    ends = np.cumsum(sizes)
    told = [pack(totals[back[z - m : z]]) for z, m in zip(ends.tolist(), sizes, strict=True)]
    return pa.table({"grp": t.column("from_grp"), "prefix": t.column("from_prefix"), "part": t.column("prefix"), "size": t.column("size"), "totals": pa.array(told, pa.binary())})


def totals_of(told: pa.Table) -> np.ndarray:
    """What all parts of a node's request were answered, in the order of its keys."""
    rows = sorted(zip(told.column("part").to_pylist(), told.column("size").to_pylist(), told.column("totals").to_pylist(), strict=True))
    return np.concatenate([np.zeros(0, np.uint64), *(unpack(b, m) for _, m, b in rows)])


def block_scores(texts: list[str | bytes | None], totals: np.ndarray, alpha: float, min_count: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Per text: words, sum of log10 scores without the corpus size, words scored as unigrams.

    totals: corpus counts in the order of the sorted distinct keys of these texts.
    """
    words, counts = word_hashes(texts)
    one, two, three, place = gram_keys(words, counts)
    some = [place >= 0, place >= 1, place >= 2]
    _, back = np.unique(np.concatenate([k[s] for k, s in zip((one, two, three), some, strict=True)]), return_inverse=True)
    found = totals[back].astype(np.float64)
    c, at = [], 0
    for s in some:
        full = np.zeros(len(words))
        full[s] = found[at : at + int(s.sum())]
        at += int(s.sum())
        c.append(full)
    before = [np.concatenate([[0.0], x[:-1]]) for x in c[:2]]
    by3 = some[2] & (c[2] >= min_count)
    by2 = ~by3 & some[1] & (c[1] >= min_count)
    by1 = ~by3 & ~by2
    backed = np.where(by1, np.minimum(place, 2), np.where(by2, np.minimum(place, 2) - 1, 0))
    with np.errstate(divide="ignore", invalid="ignore"):
        score = np.log10(np.where(by3, c[2] / before[1], np.where(by2, c[1] / before[0], c[0]))) + backed * math.log10(alpha)
    owner = np.repeat(np.arange(len(texts)), counts)
    return counts, np.bincount(owner, score, len(texts)), np.bincount(owner, by1, len(texts)).astype(np.int64)


def packed_texts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """doc_id, text, chunk to doc_id, chunk, size, packed: each text's UTF-8 bytes in zstd, which travel lighter."""
    codec = pa.Codec("zstd", 3)
    for b in slices(batches):
        raw = [(t or "").encode("utf-8", "surrogatepass") for t in b.column("text").to_pylist()]
        columns = [b.column("doc_id"), b.column("chunk"), pa.array([len(r) for r in raw], pa.int64()), pa.array([codec.compress(r, asbytes=True) for r in raw], pa.binary())]
        yield pa.RecordBatch.from_arrays(columns, ["doc_id", "chunk", "size", "packed"])


def texts_of(t: pa.Table) -> list[bytes]:
    codec = pa.Codec("zstd")
    return [codec.decompress(p, n, asbytes=True) for p, n in zip(t.column("packed").to_pylist(), t.column("size").to_pylist(), strict=True)]


def input_bytes(docs: DataFrame) -> int:
    """Spark's estimate of the input's size; where it has none, the bytes of the texts."""
    size = int(docs._jdf.queryExecution().optimizedPlan().stats().sizeInBytes())
    return size if size < 1 << 60 else int(docs.agg(F.sum(F.octet_length(F.col("text").cast("string")))).first()[0] or 0)


def score_documents(docs: DataFrame, alpha: float = ALPHA, min_count: int = MIN_COUNT, chunks: int | None = None, fan_bits: int = FAN_BITS) -> DataFrame:
    """Per row of ``docs``: doc_id, n_tokens, log10_score and mean_log10 (null without words).

    A word scores count(trigram) / count(its first two words) if the trigram occurs at least
    min_count times in the corpus, else alpha times the same one order down; unigrams score
    count / size of the corpus.  The first words of a text start at the order that they have.
    Null and empty texts have no words.  Repeated rows count and score each.  Other columns
    are not read.  An empty table gives an empty result.
    """
    width_of = shuffle_width(docs.sparkSession)
    n = chunks or max(width_of, math.ceil(input_bytes(docs) / CHUNK_BYTES))
    n_hops, width = hops(n, fan_bits)
    tasks = max(width_of, n // TASK_CHUNKS)
    base = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    dealt = base.withColumn("chunk", F.pmod(F.xxhash64("doc_id", "text"), F.lit(n)))
    rows = dealt.mapInArrow(packed_texts, "doc_id long, chunk long, size long, packed binary").repartition(tasks, "chunk")
    node = ["grp", "prefix"]

    def request(t: pa.Table) -> pa.Table:
        return messages(*distinct_grams(texts_of(t)), t.column("chunk")[0].as_py(), 0, 0, width)

    def pass_on(hop: int):
        def run(t: pa.Table) -> pa.Table:
            keys, counts, _, _ = merged(t)
            return messages(keys, counts, t.column("grp")[0].as_py(), t.column("prefix")[0].as_py(), hop, width)

        return run

    def answer(t: pa.Table) -> pa.Table:
        _, counts, back, sizes = merged(t)
        return replies(t, counts, back, sizes)

    def pass_back(t: pa.Table, told: pa.Table) -> pa.Table:
        _, _, back, sizes = merged(t)
        return replies(t, totals_of(told), back, sizes)

    def score(t: pa.Table, told: pa.Table) -> pa.Table:
        counts, sums, singles = block_scores(texts_of(t), totals_of(told), alpha, min_count)
        return pa.table({"doc_id": t.column("doc_id"), "n_tokens": pa.array(counts, pa.int64()), "part": pa.array(sums, pa.float64()), "singles": pa.array(singles, pa.int64())})

    sent = [rows.groupBy("chunk").applyInArrow(request, MESSAGE).repartition(tasks, *node)]
    for hop in range(1, n_hops):  # relays: what they got is read again on the way back
        sent[-1] = cut(sent[-1])
        sent.append(sent[-1].repartition(tasks, *node).groupBy(*node).applyInArrow(pass_on(hop), MESSAGE).repartition(tasks, *node))
    told = sent.pop().groupBy(*node).applyInArrow(answer, REPLY)
    while sent:
        told = sent.pop().groupBy(*node).cogroup(told.groupBy(*node)).applyInArrow(pass_back, REPLY)
    told = told.withColumnRenamed("grp", "chunk").repartition(tasks, "chunk")
    parts = cut(rows.groupBy("chunk").cogroup(told.groupBy("chunk")).applyInArrow(score, "doc_id long, n_tokens long, part double, singles long"))
    corpus = parts.agg(F.sum("n_tokens")).first()[0] or 1
    total = F.col("part") - F.col("singles") * math.log10(corpus)
    return parts.select("doc_id", "n_tokens", F.round(total, 6).alias("log10_score"), F.when(F.col("n_tokens") > 0, F.round(total / F.col("n_tokens"), 6)).alias("mean_log10"))


#: DuckDB twin of score_documents with the production parameters.
ORACLE = r"""
with d as (select row_number() over () as rid, doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') as w from documents),
t as (select rid, i, w[i] as c, case when i > 1 then w[i - 1] end as b, case when i > 2 then w[i - 2] end as a from (select rid, w, unnest(range(1, len(w) + 1)) as i from d)),
n1 as (select c, count(*) as n from t group by c),
n2 as (select b, c, count(*) as n from t where b is not null group by b, c),
n3 as (select a, b, c, count(*) as n from t where a is not null group by a, b, c),
s as (select t.rid, case when n3.n >= 2 then log10(n3.n / ctx2.n)
             when n2.n >= 2 then log10(n2.n / ctx1.n) + log10(0.4) * (t.a is not null)::int
             else log10(n1.n / (select count(*) from t)) + log10(0.4) * ((t.a is not null)::int + (t.b is not null)::int) end as s
      from t join n1 on t.c = n1.c left join n2 on t.b = n2.b and t.c = n2.c left join n3 on t.a = n3.a and t.b = n3.b and t.c = n3.c
      left join n1 ctx1 on t.b = ctx1.c left join n2 ctx2 on t.a = ctx2.b and t.b = ctx2.c),
g as (select rid, sum(s) as s from s group by rid)
select doc_id, len(w)::bigint as n_tokens, round(coalesce(s, 0), 6) as log10_score, case when len(w) > 0 then round(s / len(w), 6) end as mean_log10
from d left join g using (rid)
"""
