"""Language identification: multinomial naive Bayes over hashed character n-grams.

Letters are lower-cased, everything else counts as a blank; bigrams and trigrams go to a fixed
number of buckets.  The model is one log-probability matrix, buckets x languages, broadcast to
the workers in blocks of languages of at most BROADCAST_BYTES: 256 languages at the default
number of buckets, so one block as a rule.  Each block is one Arrow pass, which adds its best
language and its sum of evidence to those of the passes before.  A batch is scored in numpy from
its sparse bucket indices: rows of the matrix are gathered and summed per text.  Whole texts are
scored; long ones in segments, whose sums add up.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from dpsynth.llm.common import Shipped, fresh, map_batches, named, slices

#: At most about so many labelled documents of each language are learned from, dealt by a hash of doc_id.
TRAIN_DOCS_PER_LANG = 2_000
BUCKET_BITS = 16
BROADCAST_BYTES = 64 << 20
#: Up to so many languages the shares of their samples are broadcast; beyond, Spark chooses the join.
BROADCAST_LANGS = 100_000
SEGMENT = 1 << 19
#: Grams that count as independent evidence for the score; neighbouring ones overlap.
EVIDENCE = 64.0
UNDETERMINED = "und"
PREDICTION_SCHEMA = "doc_id long, held_out boolean, lang_pred string, score double"


def letter_table() -> np.ndarray:
    """Whether each code point below 65536 is a letter."""
    return np.fromiter((chr(c).isalpha() for c in range(1 << 16)), bool, 1 << 16)


class GramIndex:
    """Turns texts into bucket indices.  The bucket past the last stands for "no gram"."""

    def __init__(self, bits: int):
        self.bits, self.none, self.letters = bits, 1 << bits, letter_table()

    def _segments(self, texts: list[str]) -> Iterator[list[tuple[int, bool, bool, str]]]:
        """Blocks of (owning text, whether it went on before, goes on behind, characters).

        A segment begins with the last two characters of the one before it.
        """
        block: list[tuple[int, bool, bool, str]] = []
        room = SEGMENT
        for i, text in enumerate(texts):
            low = text.lower()
            for start in range(0, max(1, len(low)), SEGMENT):
                part = low[max(0, start - 2) : start + SEGMENT]
                if block and len(part) > room:
                    yield block
                    block, room = [], SEGMENT
                block.append((i, start > 0, start + SEGMENT < len(low), part))
                room -= len(part)
        if block:
            yield block

    def batches(self, texts: list[str]) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]]:
        """Per block of segments: owning text, segment starts, letters per segment, bucket indices (2 x n)."""
        for block in self._segments(texts):
            # two blanks end each segment; grams that begin in them are none
            code = np.frombuffer("".join([p + "\0\0" for _, _, _, p in block]).encode("utf-32-le", "surrogatepass"), np.uint32)
            ends = np.cumsum([len(p) + 2 for _, _, _, p in block]) - 2
            starts = np.concatenate([[0], ends[:-1] + 2])
            letter = self.letters[np.minimum(code, 0xFFFF)]
            if len(wide := np.flatnonzero(code > 0xFFFF)):
                letter[wide] = [chr(c).isalpha() for c in code[wide]]
            c = np.where(letter, code, np.uint32(32))
            index = np.full((2, len(c)), self.none, np.int64)
            mixed = c * np.uint32(0x9E3779B1)
            two = mixed[:-1] ^ (c[1:] * np.uint32(0x85EBCA6B))
            three = two[:-1] ^ (c[2:] * np.uint32(0xC2B2AE35)) ^ np.uint32(0x27D4EB2F)
            for row, hashed, n in ((0, two, 2), (1, three, 3)):
                hashed = (hashed ^ (hashed >> np.uint32(15))) * np.uint32(0x2C1B3C6D)
                some = letter[: len(c) - n + 1].copy()
                for k in range(1, n):
                    some |= letter[k : len(c) - n + 1 + k]
                index[row, : len(hashed)] = np.where(some, (hashed >> np.uint32(32 - self.bits)).astype(np.int64), self.none)
            index[:, ends] = index[:, ends + 1] = self.none
            # each gram of a text counts in one segment: in the last one that has all of it
            again, on = (np.array([x[k] for x in block], bool) for k in (1, 2))
            index[0, starts[again]] = index[0, ends[on] - 1] = index[1, ends[on] - 1] = index[1, ends[on] - 2] = self.none
            yield np.array([x[0] for x in block]), starts, np.add.reduceat(letter.astype(np.int64), starts), index


class NaiveBayes:
    """langs: the learned values; weights: (buckets + 1) x languages, the last row zero."""

    def __init__(self, langs: list[str], weights: np.ndarray, prior: np.ndarray, bits: int):
        self.langs, self.weights, self.prior, self.bits = langs, weights, prior, bits
        self.index: GramIndex | None = None

    @classmethod
    def of_counts(cls, counts: pd.DataFrame, docs: dict[str, int], bits: int, smooth: float = 0.5) -> NaiveBayes:
        """counts: lang, bucket, cnt."""
        langs = sorted(docs)
        dense = np.full((1 << bits, len(langs)), smooth)
        place = {x: i for i, x in enumerate(langs)}
        dense[counts["bucket"].to_numpy(), counts["lang"].map(place).to_numpy(np.int64)] += counts["cnt"].to_numpy()
        total = np.array([docs[x] for x in langs], float)
        weights = np.vstack([np.log(dense / dense.sum(0)), np.zeros((1, len(langs)))]).astype(np.float32)
        return cls(langs, weights, np.log(total / total.sum()), bits)

    def block(self, start: int, stop: int) -> NaiveBayes:
        """The model of some of the languages; priors stay those of the whole."""
        return NaiveBayes(self.langs[start:stop], self.weights[:, start:stop], self.prior[start:stop], self.bits)

    def blocks(self, size: int = BROADCAST_BYTES) -> list[NaiveBayes]:
        """The model in blocks of languages whose matrices have at most about ``size`` bytes."""
        step = max(1, size // (4 << self.bits))
        return [self.block(k, k + step) for k in range(0, len(self.langs), step)]

    def joint(self, texts: list[str | None]) -> tuple[np.ndarray, np.ndarray]:
        """Log of prior and likelihood (texts x languages), and the grams of each text, 0 without a letter."""
        if self.index is None:
            self.index = GramIndex(self.bits)
        n = len(texts)
        sums, grams, letters = np.zeros((n, len(self.langs))), np.zeros(n), np.zeros(n, np.int64)
        for owner, starts, has, index in self.index.batches([t or "" for t in texts]):
            np.add.at(letters, owner, has)
            for row in index:
                np.add.at(sums, owner, np.add.reduceat(self.weights[row], starts, axis=0, dtype=np.float64))
                np.add.at(grams, owner, np.add.reduceat((row != self.index.none).astype(np.int64), starts))
        return sums + self.prior, np.where(letters > 0, grams, 0)

    def best(self, texts: list[str | None]) -> tuple[list[str | None], np.ndarray, np.ndarray]:
        """Per text: the likeliest language (None without a gram), its tempered log probability,
        and the log of the sum of those of all languages.  The evidence of a text is limited to
        that of EVIDENCE grams."""
        joint, grams = self.joint(texts)
        tempered = joint * np.minimum(1.0, EVIDENCE / np.maximum(grams, 1))[:, None]
        at = joint.argmax(1)
        top = tempered.max(1)
        total = top + np.log(np.exp(tempered - top[:, None]).sum(1))
        return [self.langs[i] if g > 0 else None for i, g in zip(at, grams, strict=True)], top, total


def held_out(docs: DataFrame):
    """Whether a document is kept from learning: crc32(doc_id as text) mod 3 is 1."""
    return F.coalesce(F.crc32(docs["doc_id"].cast("string")) % 3 == 1, F.lit(False))


def train(docs: DataFrame, per_lang: int = TRAIN_DOCS_PER_LANG, bits: int = BUCKET_BITS) -> NaiveBayes:
    """Learn from documents that are not held out and have doc_id, lang and text.

    The sample of each language is every such document where it has at most ``per_lang``; else
    those whose hashed doc_id falls below per_lang / count.  Gram counts are summed in Spark;
    the driver gets one number per language, and the gram counts of the bounded samples.
    """
    spark = docs.sparkSession
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("lang").cast("string").alias("lang"), F.col("text").cast("string").alias("text"))
    rows = rows.where(F.col("lang").isNotNull() & F.col("doc_id").isNotNull() & ~held_out(rows))
    found = {r["lang"]: r["n"] for r in rows.groupBy("lang").agg(F.count("*").alias("n")).collect()}
    if not found:
        return NaiveBayes([], np.zeros(((1 << bits) + 1, 0), np.float32), np.zeros(0), bits)
    shares = spark.createDataFrame([(k, per_lang / n) for k, n in found.items()], "lang string, share double")
    if len(found) <= BROADCAST_LANGS:
        shares = F.broadcast(shares)
    dealt = F.pmod(F.xxhash64("doc_id", F.lit("langid")), F.lit(1_000_003)) / 1_000_003.0
    sample = rows.withColumn("dealt", dealt).join(shares, "lang").where("dealt < share").select("lang", "text")

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        index, sums = GramIndex(bits), {}
        for b in slices(batches):
            groups: dict[str, list[str]] = {}
            for lang, text in zip(b.column("lang").to_pylist(), b.column("text").to_pylist(), strict=True):
                groups.setdefault(lang, []).append(text or "")
            for lang, texts in groups.items():
                into = sums.setdefault(lang, np.zeros((1 << bits) + 1, np.int64))
                for _, _, _, found_in in index.batches(texts):
                    for row in found_in:
                        into += np.bincount(row, minlength=len(into))
        for lang, into in sums.items():
            some = np.flatnonzero(into[:-1])
            yield pa.RecordBatch.from_arrays([pa.array([lang] * len(some), pa.string()), pa.array(some), pa.array(into[some])], ["lang", "bucket", "cnt"])

    counts = map_batches(sample, count, "lang string, bucket long, cnt long").groupBy("lang", "bucket").agg(F.sum("cnt").alias("cnt")).toPandas()
    return NaiveBayes.of_counts(counts, found, bits)


def identify(docs: DataFrame, model: NaiveBayes, names: tuple[str, str] = ("lang_pred", "score"), block_bytes: int = BROADCAST_BYTES) -> DataFrame:
    """``docs`` with the predicted language and its posterior share in two new columns ``names``.

    All columns stay; one that has such a name is replaced, so give others to keep it (see
    common.fresh).  Texts that are null or have no letter, and all texts under a model without
    languages, get ``und`` and 0.  Repeated rows get equal results, an empty table stays empty.
    No shuffle: one Arrow pass for each block of the model.
    """
    kept = docs.drop(*names)
    at_lang, at_top, at_total = fresh(kept, "llm_best", "llm_top", "llm_total")
    found = [(at_lang, T.StringType()), (at_top, T.DoubleType()), (at_total, T.DoubleType())]
    schema = T.StructType([*kept.schema.fields, *(T.StructField(n, t) for n, t in found)])

    def scan(shared):
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in slices(batches):
                langs, top, total = shared.value.best(b.column("text").to_pylist())
                if at_lang in b.schema.names:
                    old, old_top, old_total = b.column(at_lang).to_pylist(), *(b.column(c).to_numpy(zero_copy_only=False) for c in (at_top, at_total))
                    langs = [x if p > q else y for x, y, p, q in zip(langs, old, top, old_top, strict=True)]
                    top, total = np.maximum(top, old_top), np.logaddexp(total, old_total)
                    b = b.select(b.schema.names[:-3])
                yield b.append_column(at_lang, pa.array(langs, pa.string())).append_column(at_top, pa.array(top, pa.float64())).append_column(at_total, pa.array(total, pa.float64()))

        return run

    out = kept
    for part in model.blocks(block_bytes):
        out = map_batches(out, scan(Shipped(docs.sparkSession, part)), schema)
    if not model.langs:
        out = out.withColumns({at_lang: F.lit(None).cast("string"), at_top: F.lit(0.0), at_total: F.lit(0.0)})
    sure = F.when(F.col(at_lang).isNull(), F.lit(0.0)).otherwise(F.least(F.exp(F.col(at_top) - F.col(at_total)), F.lit(1.0)))
    return out.select(*[named(c) for c in kept.columns], F.coalesce(at_lang, F.lit(UNDETERMINED)).alias(names[0]), sure.alias(names[1]))


def predict_languages(docs: DataFrame, per_lang: int = TRAIN_DOCS_PER_LANG, bits: int = BUCKET_BITS) -> DataFrame:
    """Per row of ``docs``: doc_id, held_out, lang_pred, score.

    Texts that are null or have no letter get ``und`` and score 0, as does everything if there is
    nothing to learn from.  lang, source and doc_id are no inputs of a prediction.  Repeated
    rows each give a row; an empty table gives an empty result.
    """
    model = train(docs, per_lang, bits)
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    out = identify(rows, model)
    return out.select("doc_id", held_out(out).alias("held_out"), "lang_pred", "score")
