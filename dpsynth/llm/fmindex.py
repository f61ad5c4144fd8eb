"""Benchmark decontamination with an FM-index per shard of training texts.

The words of a shard become one sequence over the benchmark's vocabulary.  A word outside it
cannot be part of any occurrence, so it ends a run, and runs shorter than the shortest window
are left out: the index holds what can match at all, and nothing is lost.  The Burrows-Wheeler
transform of the runs lies in a wavelet matrix; all windows of the benchmark are searched
backward at once, each step two ranks; occurrences are located by walking to sampled suffix
positions.  Hit words merge to removal spans.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from dpsynth.llm.common import Shipped, columns_of, fresh, map_batches, named

WINDOW = 10
#: Texts of one index, in bytes.
SHARD_BYTES = 32 << 20
#: Bytes of benchmark text that are broadcast at a time; a larger benchmark is met in blocks.
BLOCK_BYTES = 16 << 20
#: One position in so many is sampled.
SAMPLE = 8

#: A-Z lowered; bytes that end a word become blanks.  Bytes of 128 and more belong to words.
WORDS = bytes(c + 32 if 65 <= c <= 90 else c if 48 <= c <= 57 or 97 <= c <= 122 or c >= 128 else 32 for c in range(256))


def words_of(text: str | None) -> list[bytes]:
    return (text or "").encode("utf-8", "surrogatepass").translate(WORDS).split()


class WaveletMatrix:
    """Rank over a sequence of small integers: one bit level each, with counts of ones before."""

    def __init__(self, seq: np.ndarray, levels: int):
        self.levels, self.ones, self.zeros = levels, [], []
        for level in range(levels - 1, -1, -1):
            bit = (seq >> level & 1).astype(bool)
            self.ones.append(np.concatenate([[0], np.cumsum(bit, dtype=np.int32)]))
            self.zeros.append(len(seq) - int(self.ones[-1][-1]))
            seq = np.concatenate([seq[~bit], seq[bit]])

    def rank(self, symbol: np.ndarray, at: np.ndarray) -> np.ndarray:
        """How often each symbol occurs before its position."""
        start = np.zeros_like(at)
        for depth, (ones, zeros) in enumerate(zip(self.ones, self.zeros, strict=True)):
            bit = (symbol >> (self.levels - 1 - depth) & 1).astype(bool)
            start, at = (np.where(bit, zeros + ones[x], x - ones[x]) for x in (start, at))
        return at - start

    def access(self, at: np.ndarray) -> np.ndarray:
        """The symbols at the positions."""
        symbol = np.zeros_like(at)
        for ones, zeros in zip(self.ones, self.zeros, strict=True):
            bit = ones[at + 1] > ones[at]
            symbol = symbol << 1 | bit
            at = np.where(bit, zeros + ones[at], at - ones[at])
        return symbol


class FMIndex:
    """Over a sequence in which 0 ends each run (and the whole)."""

    def __init__(self, seq: np.ndarray, n_symbols: int):
        seq = np.asarray(seq, np.int64)
        order = self._suffixes(seq)
        before = seq[order - 1]  # of position 0 the last symbol, a 0
        self.bwt = WaveletMatrix(before, max(1, int(n_symbols).bit_length()))
        self.starts = np.concatenate([[0], np.cumsum(np.bincount(seq, minlength=n_symbols + 1))])
        # sampled: every SAMPLE-th position, and the heads of runs, so that no walk crosses a 0
        sampled = (order % SAMPLE == 0) | (before == 0)
        self.place = np.concatenate([[0], np.cumsum(sampled, dtype=np.int64)])
        self.sampled, self.position = sampled, order[sampled]

    @staticmethod
    def _suffixes(seq: np.ndarray) -> np.ndarray:
        """Suffix array by prefix doubling; each 0 counts as a symbol of its own, in text order."""
        n = len(seq)
        ends = seq == 0
        rank = np.where(ends, np.cumsum(ends) - 1, seq + int(ends.sum()))
        step = 1
        while True:
            after = np.zeros(n, np.int64)
            after[: n - step] = rank[step:] + 1
            key = rank * (int(rank.max()) + 2) + np.minimum(after, int(rank.max()) + 1)
            order = np.argsort(key, kind="stable")
            new = np.cumsum(np.concatenate([[0], key[order][1:] != key[order][:-1]]))
            rank = np.empty(n, np.int64)
            rank[order] = new
            step *= 2
            if new[-1] == n - 1 or step >= n:
                return order

    def search(self, patterns: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Suffix intervals [low, high) of patterns of one length, a row each, last symbol first."""
        low = np.zeros(len(patterns), np.int64)
        high = np.full(len(patterns), self.starts[-1], np.int64)
        live = np.arange(len(patterns))
        for column in range(patterns.shape[1] - 1, -1, -1):
            symbol = patterns[live, column]
            low[live] = self.starts[symbol] + self.bwt.rank(symbol, low[live])
            high[live] = self.starts[symbol] + self.bwt.rank(symbol, high[live])
            live = live[low[live] < high[live]]
        low[low >= high] = high[low >= high]
        return low, high

    def locate(self, low: np.ndarray, high: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(pattern, position) of every occurrence in the intervals."""
        size = high - low
        owner = np.repeat(np.arange(len(low)), size)
        at = np.arange(size.sum()) - np.repeat(np.cumsum(size) - size, size) + np.repeat(low, size)
        walked = np.zeros(len(at), np.int64)
        far = np.flatnonzero(~self.sampled[at])
        while len(far):
            symbol = self.bwt.access(at[far])
            at[far] = self.starts[symbol] + self.bwt.rank(symbol, at[far])
            walked[far] += 1
            far = far[~self.sampled[at[far]]]
        return owner, self.position[self.place[at]] + walked


class Phrases:
    """The windows of some benchmark items: distinct word sequences, and the items of each."""

    def __init__(self, items: list[tuple[int | None, str | None]], window: int):
        self.window, self.vocabulary = window, {}
        groups: dict[int, dict[tuple[int, ...], set]] = {}
        for item, text in items:
            w = [self.vocabulary.setdefault(x, len(self.vocabulary) + 1) for x in words_of(text)]
            n = min(window, len(w))
            for i in range(len(w) - n + 1 if n else 0):
                groups.setdefault(n, {}).setdefault(tuple(w[i : i + n]), set()).add(item)
        self.groups = {n: (np.array(list(g), np.int64), [sorted(x, key=str) for x in g.values()]) for n, g in groups.items()}
        self.shortest = min(groups, default=0)

    def hits(self, texts: list[str | None]) -> tuple[list[int], list[list[tuple[int, int]]], list[set]]:
        """Per text: number of words, merged spans of hit words (end exclusive), items found."""
        n_words, spans, items = [0] * len(texts), [[] for _ in texts], [set() for _ in texts]
        parts, heads, owners, bases = [], [], [], []
        total, get = 0, self.vocabulary.get
        for t, text in enumerate(texts):
            words = words_of(text)
            n_words[t] = len(words)
            if not self.shortest:
                continue
            ids = np.array([get(w, 0) for w in words], np.int64)
            border = np.flatnonzero(np.concatenate([[True], ids[1:] == 0, [True]]) | np.concatenate([[True], ids[:-1] == 0, [True]])) if len(ids) else []
            for a, b in zip(border[:-1], border[1:], strict=True):
                if b - a >= self.shortest and ids[a]:
                    parts += [ids[a:b], [0]]
                    heads.append(total)
                    owners.append(t)
                    bases.append(a)
                    total += b - a + 1
        if not parts:
            return n_words, spans, items
        index = FMIndex(np.concatenate(parts), len(self.vocabulary))
        heads, owners, bases = np.array(heads), np.array(owners), np.array(bases)
        edge = np.zeros(total + 1, np.int64)  # +1 where an occurrence starts, -1 behind its end
        for n, (patterns, of) in self.groups.items():
            which, at = index.locate(*index.search(patterns))
            np.add.at(edge, at, 1)
            np.add.at(edge, at + n, -1)
            met = np.unique(owners[np.searchsorted(heads, at, "right") - 1] * len(of) + which)
            for t, p in zip((met // len(of)).tolist(), (met % len(of)).tolist(), strict=True):
                items[t].update(of[p])
        cover = np.concatenate([[0], (np.cumsum(edge) > 0).astype(np.int8)])
        turn = np.diff(cover)  # runs end in an uncovered 0, so each covered stretch lies in one
        first, last = np.flatnonzero(turn == 1), np.flatnonzero(turn == -1)
        run = np.searchsorted(heads, first, "right") - 1
        moved = bases[run] - heads[run]
        for t, a, b in zip(owners[run].tolist(), (first + moved).tolist(), (last + moved).tolist(), strict=True):
            spans[t].append((a, b))
        return n_words, spans, items


def merge_spans(spans: list[tuple[int, int]]) -> list[tuple[int, int]]:
    """Sorted spans, joined where they touch or overlap."""
    out: list[tuple[int, int]] = []
    for a, b in sorted(spans):
        if out and a <= out[-1][1]:
            out[-1] = (out[-1][0], max(b, out[-1][1]))
        else:
            out.append((a, b))
    return out


def remove_spans(text: str, spans: list[tuple[int, int]]) -> str:
    """The text without the words of the spans and what stands between them."""
    import re

    if not spans:
        return text
    places = [m.span() for m in re.finditer("[^\\x00-\\x2F\\x3A-\\x40\\x5B-\\x60\\x7B-\\x7F]+", text)]
    out, at = [], 0
    for a, b in spans:
        out.append(text[at : places[a][0]])
        at = places[b - 1][1]
    return "".join([*out, text[at:]])


def benchmark_blocks(benchmark: DataFrame, block_bytes: int = BLOCK_BYTES) -> Iterator[list[tuple[int | None, str | None]]]:
    """The items of the benchmark, a block of bounded size at a time."""
    block, size = [], 0
    for row in benchmark.select(F.col("item_id").cast("long"), F.col("text").cast("string")).distinct().toLocalIterator():
        block.append(tuple(row))
        size += len(row[1] or "")
        if size > block_bytes:
            yield block
            block, size = [], 0
    if block:
        yield block


HIT_COLUMNS = ("llm_words", "llm_spans", "llm_items")
HIT_TYPES = (T.LongType(), T.ArrayType(T.ArrayType(T.LongType())), T.ArrayType(T.LongType()))


def mark(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW, block_bytes: int = BLOCK_BYTES, shard_bytes: int = SHARD_BYTES, names: tuple[str, ...] = HIT_COLUMNS) -> DataFrame:
    """``docs`` with llm_words (number of words), llm_spans (merged [start, end) in words) and
    llm_items (ids of the items with an occurring window), or columns of other ``names``, which
    no column of ``docs`` may have.  No shuffle: one Arrow pass per block of the benchmark, in
    which each pass adds to what the ones before have found.
    """
    spark, out = docs.sparkSession, docs
    fields = [T.StructField(n, t) for n, t in zip(names, HIT_TYPES, strict=True)]
    schema = T.StructType([*docs.schema.fields, *fields])
    kinds = [pa.int64(), pa.list_(pa.list_(pa.int64())), pa.list_(pa.int64())]

    def scan(phrases):
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            def done(held: list[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
                n, spans, items = phrases.value.hits([x for b in held for x in b.column("text").to_pylist()])
                at = 0
                for b in held:
                    to = at + b.num_rows
                    new = [n[at:to], spans[at:to], [sorted(i for i in x if i is not None) for x in items[at:to]]]
                    if names[1] in b.schema.names:
                        new[1] = [merge_spans([*map(tuple, x), *y]) for x, y in zip(b.column(names[1]).to_pylist(), new[1], strict=True)]
                        new[2] = [sorted({*x, *y}) for x, y in zip(b.column(names[2]).to_pylist(), new[2], strict=True)]
                        b = b.select(b.schema.names[:-3])
                    new[1] = [[list(s) for s in x] for x in new[1]]
                    for name, kind, values in zip(names, kinds, new, strict=True):
                        b = b.append_column(name, pa.array(values, kind))
                    yield b
                    at = to

            held, size = [], 0
            for b in batches:
                held.append(b)
                size += b.column("text").nbytes
                if size > shard_bytes:
                    yield from done(held)
                    held, size = [], 0
            if held:
                yield from done(held)

        return run

    some = False
    for block in benchmark_blocks(benchmark, block_bytes):
        out, some = map_batches(out, scan(Shipped(spark, Phrases(block, window))), schema), True
    return out if some else map_batches(out, scan(Shipped(spark, Phrases([], window))), schema)


def contamination_digests(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW) -> DataFrame:
    """Per row of ``docs``: doc_id, n_words, n_hit, n_items, items_sha256, contaminated.

    Null texts have no words.  Items without words have no windows; an item of null id marks
    words but is not listed.  An empty benchmark hits nothing.
    """
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    hit = F.aggregate("llm_spans", F.lit(0).cast("long"), lambda n, s: n + s[1] - s[0])
    listed = F.array_join(F.array_sort(F.transform("llm_items", lambda i: i.cast("string"))), ",")
    return mark(rows, benchmark, window).select("doc_id", F.col("llm_words").alias("n_words"), hit.alias("n_hit"), F.size("llm_items").cast("long").alias("n_items"), F.sha2(listed, 256).alias("items_sha256"), (hit > 0).alias("contaminated"))


def clean_documents(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW) -> DataFrame:
    """``docs`` without the documents in which a window of the benchmark occurs.

    Null, empty and word-less texts stay, as do repeated rows of a clean text; all columns
    stay as they are, whatever their names.  An empty benchmark keeps everything, an empty
    table stays empty.
    """
    names = fresh(docs, *HIT_COLUMNS)
    marked = mark(docs.withColumn("text", F.col("text").cast("string")), benchmark, window, names=tuple(names))
    return marked.where(F.size(named(names[1])) == 0).select(*columns_of(docs))


#: DuckDB twin of contamination_digests.
ORACLE = r"""
with words as (select row_number() over () as rid, doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') as w from documents),
bench as (select item_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') as w from benchmark),
win as (select distinct item_id, least(10, len(w)) as n, array_to_string(w[i:i + least(10, len(w)) - 1], ' ') as phrase
        from (select item_id, w, unnest(range(1, len(w) - least(10, len(w)) + 2)) as i from bench where len(w) > 0)),
sizes as (select distinct n from win),
dwin as (select rid, n, i, array_to_string(w[i:i + n - 1], ' ') as phrase
         from (select rid, w, n, unnest(range(1, len(w) - n + 2)) as i from words, sizes where len(w) >= n)),
hits as (select d.rid, d.i, d.n, b.item_id from dwin d join win b on d.n = b.n and d.phrase = b.phrase),
hw as (select rid, count(distinct p) as n_hit from (select rid, unnest(range(i, i + n)) as p from (select distinct rid, i, n from hits)) group by rid),
hi as (select rid, count(*) as n_items, string_agg(item_id::varchar, ',' order by item_id::varchar) as items from (select distinct rid, item_id from hits) group by rid)
select doc_id, len(w)::bigint as n_words, coalesce(n_hit, 0)::bigint as n_hit, coalesce(n_items, 0)::bigint as n_items,
       sha256(coalesce(items, '')) as items_sha256, coalesce(n_hit, 0) > 0 as contaminated
from words left join hw using (rid) left join hi using (rid)
"""
