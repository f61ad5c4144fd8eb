"""Byte-level BPE by prefix dynamic programming.

For every prefix of a piece there is exactly one last token with which a valid BPE encoding of
that prefix can end.  A table of those last tokens, one entry per byte, is all that is needed:
walking back from any position yields the encoding of that prefix.  Appending bytes extends the
table; editing bytes at position p keeps the table below p and recomputes from p on, until the
table meets the old one again.

Two adjacent tokens are valid if the merges of BPE would not have joined across their border.
"""

from __future__ import annotations

import base64
import hashlib
from collections.abc import Iterator

import ahocorasick
import pyarrow as pa
import public_tokenizers
import regex
from pyspark.sql import DataFrame

from dpsynth.llm.common import Shipped, map_batches, slices

#: Pieces that a worker keeps for digests, where no other stage's memory is in its process.
DIGEST_CACHE = 400_000
DIGEST_SCHEMA = "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string"


def load_ranks(path: str) -> dict[bytes, int]:
    """The vocabulary of a rank file: one base64 token and its rank a line."""
    with open(path, "rb") as lines:
        return {base64.b64decode(token): int(rank) for token, rank in (x.split() for x in lines if x.strip())}


def last_merges(ranks: dict[bytes, int]) -> dict[int, tuple[int, int]]:
    """For each token the pair of tokens whose merge made it; a single byte is its own pair."""
    made: dict[int, tuple[int, int]] = {}
    for token, rank in ranks.items():
        parts = [token[i : i + 1] for i in range(len(token))]
        while len(parts) > 2:
            best, at = rank, -1
            for i in range(len(parts) - 1):
                r = ranks.get(parts[i] + parts[i + 1], rank)
                if r < best:
                    best, at = r, i
            if at < 0:
                break
            parts[at : at + 2] = [parts[at] + parts[at + 1]]
        made[rank] = (ranks[parts[0]], ranks[parts[1]]) if len(parts) == 2 else (rank, rank)
    return made


class PrefixTable:
    """The last tokens of all prefixes of one piece of bytes; grows and can be edited."""

    def __init__(self, coder: PrefixCoder, piece: bytes = b""):
        self.coder, self.piece, self.last = coder, b"", []
        self.append(piece)

    def append(self, more: bytes) -> PrefixTable:
        """Add bytes at the end; costs only their share."""
        start = len(self.piece)
        self.piece += more
        self.coder.extend(self.piece, self.last, start)
        return self

    def replace(self, start: int, end: int, by: bytes) -> PrefixTable:
        """Put ``by`` in place of bytes start..end; entries before start stay.

        Behind the edit the table is computed anew only until as many entries in a row as the
        longest token has bytes equal the old ones: from there on both tables agree.
        """
        old, shift = self.last[end:], len(by) - (end - start)
        self.piece = self.piece[:start] + by + self.piece[end:]
        del self.last[start:]
        edited, same = start + len(by), 0
        for i in range(start, len(self.piece)):
            self.coder.extend(self.piece[: i + 1], self.last, i)
            if i >= edited:
                same = same + 1 if self.last[i] == old[i - shift - end] else 0
                if same > self.coder.longest:
                    self.last += old[i - shift - end + 1 :]
                    break
        return self

    def ids(self, length: int | None = None) -> list[int]:
        """The encoding of the first ``length`` bytes (all of them by default)."""
        return self.coder.walk(self.last, len(self.piece) if length is None else length)


class PrefixCoder:
    """Encoder and decoder over one vocabulary.  Pieces met before are kept in two generations of at
    most ``cache`` pieces: when the younger one is full it replaces the older one, and what is
    met again moves back.  They change the speed only."""

    def __init__(self, ranks: dict[bytes, int], pattern: str, cache: int = 150_000):
        self.ranks, self.pattern, self.room = ranks, pattern, cache
        self.merges = last_merges(ranks)
        self._ready()

    def __getstate__(self):
        return {k: self.__dict__[k] for k in ("ranks", "pattern", "room", "merges")}

    def __setstate__(self, state):
        self.__dict__.update(state)
        self._ready()

    def _ready(self) -> None:
        self.tokens = {rank: token for token, rank in self.ranks.items()}
        self.sizes = {rank: len(token) for token, rank in self.ranks.items()}
        self.longest = max(map(len, self.ranks))
        self.joined = {pair: rank for rank, pair in self.merges.items() if pair[0] != rank}
        self.ends = ahocorasick.Automaton()
        for token, rank in self.ranks.items():
            self.ends.add_word(token.decode("latin-1"), (len(token), rank))
        self.ends.make_automaton()
        self.split = regex.compile(self.pattern)
        self.fits: dict[int, bool] = {}
        self.edges: tuple[dict, dict] = {}, {}  # of tokens, so no more than the vocabulary
        self.known: dict[str, list[int]] = {}
        self.known_before: dict[str, list[int]] = {}
        self.seen: dict[str, tuple[int, bytes, bytes]] = {}
        self.seen_before: dict[str, tuple[int, bytes, bytes]] = {}

    def edge(self, token: int, side: int) -> list[tuple[int, int]]:
        """The tokens that stand at one end of ``token`` while BPE builds it (side 0: its left end,
        1: its right end), each with the rank of the merge that takes it away."""
        out = self.edges[side].get(token)
        if out is None:
            out, at = [(token, 1 << 30)], token
            while (inner := self.merges[at][side]) != at:
                out.append((inner, at))
                at = inner
            self.edges[side][token] = out
        return out

    def compatible(self, left: int, right: int) -> bool:
        """Whether BPE leaves the border between the two tokens alone.

        Merges happen in rank order, since what a merge makes only enters merges of higher rank.
        So each token x at the border is there from its own rank on until the merge that takes
        it away, of rank gone(x).  A merge m of a token x left of the border with a token y right
        of it crosses the border if both are still there when its turn comes: m < gone(x), and
        m <= gone(y), for of equal merges the leftmost is first: x's own one starts further
        left, y's further right.  Both have come by then, as m is above the ranks of x and y.
        """
        key = left << 24 | right
        known = self.fits.get(key)
        if known is None:
            known = self._border_stays(left, right)
            if len(self.fits) >= 4 * self.room:
                self.fits.clear()
            self.fits[key] = known
        return known

    def _border_stays(self, left: int, right: int) -> bool:
        joined, starts = self.joined.get, self.edge(right, 0)
        for x, gone in self.edge(left, 1):
            for y, lost in starts:
                merge = joined((x, y))
                if merge is not None and merge < gone and merge <= lost:
                    return False
        return True

    def extend(self, piece: bytes, last: list[int], start: int) -> None:
        """Append to ``last`` the last tokens of the prefixes longer than ``start``.

        An Aho-Corasick automaton lists the tokens that end at each byte; the one that begins
        the piece, or fits behind the last token of the prefix before it, is the entry.
        """
        base, known, fits, n = max(0, start - self.longest + 1), self.fits.get, self.compatible, len(last)
        for at, (size, token) in self.ends.iter(piece[base:].decode("latin-1") if base else piece.decode("latin-1")):
            if base + at == n:
                if size > n:
                    last.append(token)
                    n += 1
                else:
                    before = last[n - size]
                    fit = known(before << 24 | token)
                    if fit or fit is None and fits(before, token):
                        last.append(token)
                        n += 1
        if n != len(piece):
            raise ValueError("a byte has no token in this vocabulary")

    def walk(self, last: list[int], at: int) -> list[int]:
        """The encoding of the first ``at`` bytes, read off their last tokens from the end."""
        out, sizes = [], self.sizes
        while at > 0:
            token = last[at - 1]
            out.append(token)
            at -= sizes[token]
        out.reverse()
        return out

    def encode_piece(self, piece: bytes) -> list[int]:
        whole = self.ranks.get(piece)
        if whole is not None:
            return [whole]
        last: list[int] = []
        self.extend(piece, last, 0)
        return self.walk(last, len(last))

    def _learned(self, piece: str) -> list[int]:
        ids = self.known_before.get(piece) or self.encode_piece(piece.encode("utf-8", "surrogatepass"))
        if len(piece) <= 64:
            if len(self.known) >= self.room:
                self.known_before, self.known = self.known, {}
            self.known[piece] = ids
        return ids

    def encode(self, text: str) -> list[int]:
        known, learned = self.known.get, self._learned
        return [i for p in self.split.findall(text) for i in known(p) or learned(p)]

    def decode(self, ids: list[int]) -> bytes:
        return b"".join(map(self.tokens.__getitem__, ids))

    def _written(self, piece: str) -> tuple[int, bytes, bytes]:
        """Number of tokens, their decimals joined by blanks, and the bytes they decode to."""
        out = self.seen_before.get(piece)
        if out is None:
            ids = self.encode_piece(piece.encode("utf-8", "surrogatepass"))
            out = len(ids), " ".join(map(str, ids)).encode(), self.decode(ids)
        if len(piece) <= 64:
            if len(self.seen) >= self.room:
                self.seen_before, self.seen = self.seen, {}
            self.seen[piece] = out
        return out

    def digest(self, text: str | None) -> tuple[int, str, str]:
        """Number of tokens and the two digests of one text."""
        seen, written = self.seen.get, self._written
        found = [seen(p) or written(p) for p in self.split.findall(text or "")]
        ids = hashlib.sha256(b" ".join([x[1] for x in found])).hexdigest()
        return sum([x[0] for x in found]), ids, hashlib.sha256(b"".join([x[2] for x in found])).hexdigest()


def coder(path: str | None = None, pattern: str = public_tokenizers.PATTERN, cache: int = 150_000) -> PrefixCoder:
    return PrefixCoder(load_ranks(path or public_tokenizers.path("byte_bpe_50k.tiktoken")), pattern, cache)


def encode_documents(docs: DataFrame, path: str | None = None, pattern: str = public_tokenizers.PATTERN, text_col: str = "text", out: str = "token_ids") -> DataFrame:
    """``docs`` with the token ids of each whole text in a new column ``out`` (null text: no ids).

    All columns stay; a column of that name is replaced.  Repeated rows get equal ids, an empty
    table stays empty.  No shuffle: one Arrow pass, the vocabulary (a file of fixed size) is
    broadcast.
    """
    from pyspark.sql import types as T

    model = Shipped(docs.sparkSession, coder(path, pattern))
    kept = docs.drop(out)
    schema = T.StructType([*kept.schema.fields, T.StructField(out, T.ArrayType(T.IntegerType()))])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in slices(batches):
            ids = [model.value.encode(t or "") for t in b.column(text_col).to_pylist()]
            yield b.append_column(out, pa.array(ids, pa.list_(pa.int32())))

    return map_batches(kept, run, schema)


def encode_digests(docs: DataFrame, path: str | None = None, pattern: str = public_tokenizers.PATTERN) -> DataFrame:
    """Per row of ``docs``: doc_id, n_tokens, ids_sha256, decoded_sha256.

    Null and empty texts have no tokens (digests of nothing).  Repeated rows each give a row.  An
    empty table gives an empty result.  Other columns are not read.
    """
    model = Shipped(docs.sparkSession, coder(path, pattern, DIGEST_CACHE))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in slices(batches):
            rows = [model.value.digest(t) for t in b.column(1).to_pylist()]
            n, ids, back = zip(*rows) if rows else ((), (), ())
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(n, pa.int64()), pa.array(ids, pa.string()), pa.array(back, pa.string())], ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])

    return map_batches(docs.selectExpr("cast(doc_id as bigint) as doc_id", "cast(text as string) as text"), run, DIGEST_SCHEMA)
