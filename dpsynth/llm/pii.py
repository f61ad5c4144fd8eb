"""Personal data: fixed patterns, and a character-level bidirectional LSTM with a CRF on top.

The tagger is trained in numpy from labelled spans: data of every kind, in many more forms than
the patterns know, are written by ``Forge`` into passages of the corpus that have none, among
look-alikes that are no personal data (dates, versions, prices).  So each label is known by
construction, and held-out passages and forms give precision and recall (``evaluate``).  What the
tagger adds must also be plausible for its kind (digits, checksum).  Texts are cut into overlapping
windows; every kind has a digit or an @ in it, so only windows near one are decoded, all others are
"outside" by definition.  Each character takes its label from the window in whose middle it
stands, and the labels are put together over the whole text before spans are read off.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from dpsynth.llm.common import Shipped, map_batches, slices

#: The kinds of the patterns, and two that only the tagger finds.
BASE_KINDS = ["email", "ip", "card", "phone"]
KINDS = [*BASE_KINDS, "secret", "account"]
EMAIL, IP, CARD, PHONE, SECRET, ACCOUNT = range(len(KINDS))
#: Passages that are learned from at most, their characters, and buckets of the hash that deals them.
TRAIN_PASSAGES, PASSAGE, BUCKETS = 300, 400, 1024
WINDOW, STRIDE, HIDDEN, EMBED = 96, 64, 24, 8
EPOCHS, BATCH, RATE, SEED = 24, 16, 0.01, 7
#: Mean posterior of a span's labels, and its length, from which on the tagger's word counts.
MIN_POSTERIOR, MIN_LENGTH = 0.9, 7
SCHEMA = "doc_id long, n_email long, n_ip long, n_card long, n_phone long, base_sha256 string, spans string, n_spans long"

TRIGGER = re.compile("[0-9@]")
_LOCAL = re.compile("[A-Za-z0-9._%+-]*\\Z")
_DOMAIN = re.compile("[A-Za-z0-9-]++(?:\\.[A-Za-z0-9-]+)++")
_IP = re.compile("(?<![0-9])[0-9]++(?:\\.[0-9]++){3}")
_CARD = re.compile("[0-9](?:[\\x20-]?[0-9])++")
_PHONE = re.compile("\\+[0-9][\\x20().0-9-]+[0-9]")
#: Character classes of the tagger: printable ASCII each, line ends, letters beyond, anything else.
N_CLASSES = 98
_CLASS = np.full(256, 97, np.uint8)
_CLASS[32:127] = np.arange(95)
_CLASS[9:14] = 95
TAGS = 1 + 2 * len(KINDS)
#: Transitions into the inside of a kind from anything but that kind are ruled out.
RULED_OUT = np.array([[to > 0 and to % 2 == 0 and source not in (to - 1, to) for to in range(TAGS)] for source in range(TAGS)])


def luhn(digits: str) -> bool:
    total = 0
    for i, d in enumerate(reversed(digits)):
        x = int(d) * (1 + i % 2)
        total += x - 9 * (x > 9)
    return total % 10 == 0


def base_spans(text: str) -> list[tuple[int, int, int]]:
    """(kind index, start, end) of the fixed patterns, by kind, then start.  Linear in the text."""
    out, free, at = [], 0, text.find("@")
    while at >= 0:
        start = at
        while start > free and (c := text[start - 1]) < "\x80" and (c.isalnum() or c in "._%+-"):
            start -= 1
        if start < at and (m := _DOMAIN.match(text, at + 1)):
            out.append((0, start, m.end()))
            free = m.end()
        at = text.find("@", max(at + 1, free))
    out += [(1, *m.span()) for m in _IP.finditer(text) if all(len(p.lstrip("0")) <= 3 and int(p[-4:]) <= 255 for p in m[0].split("."))]
    for m in _CARD.finditer(text):
        digits = m[0].replace(" ", "").replace("-", "")
        if 13 <= len(digits) <= 19 and luhn(digits):
            out.append((2, *m.span()))
    out += [(3, *m.span()) for m in _PHONE.finditer(text) if 9 <= sum(c.isdigit() for c in m[0]) <= 15]
    return out


def classes(text: str) -> np.ndarray:
    code = np.frombuffer(text.encode("utf-32-le", "surrogatepass"), np.uint32)
    return np.where(code < 128, _CLASS[np.minimum(code, 127)], np.uint8(96)).astype(np.uint8)


def window_starts(text: str) -> list[int]:
    """Starts of the windows that have a digit or an @ in them or in the window beside them."""
    near = {k for m in TRIGGER.finditer(text) for k in range(m.start() // STRIDE - 2, m.start() // STRIDE + 2)}
    last = max(0, -(-(len(text) - WINDOW) // STRIDE))
    return [k * STRIDE for k in sorted(near) if 0 <= k <= last]


def sigmoid(x: np.ndarray) -> np.ndarray:
    return 0.5 * np.tanh(0.5 * x) + 0.5


class Tagger:
    """Embedding, one LSTM in each direction, emissions, CRF transitions; float32 arrays only.

    Both directions run side by side, on the sequence and on its reverse.
    """

    def __init__(self, seed: int = SEED):
        rng = np.random.default_rng(seed)
        w = lambda *s: (rng.standard_normal(s) / np.sqrt(s[-2])).astype(np.float32)
        self.p = {"embed": w(N_CLASSES, EMBED), "w": w(2, EMBED, 4 * HIDDEN), "u": w(2, HIDDEN, 4 * HIDDEN), "z": np.zeros((2, 4 * HIDDEN), np.float32)}
        self.p |= {"out": w(2 * HIDDEN, TAGS), "bias": np.zeros(TAGS, np.float32), "trans": np.zeros((TAGS, TAGS), np.float32), "start": np.zeros(TAGS, np.float32)}
        self.p["z"][:, HIDDEN : 2 * HIDDEN] = 1.0
        self.p["trans"][RULED_OUT] = -1e3

    def _lstm(self, codes: np.ndarray, keep: dict | None = None) -> np.ndarray:
        """codes: time x batch.  Hidden states, time x batch x 2 HIDDEN; keep gets what the way back needs."""
        steps, n = codes.shape
        table = self.p["embed"] @ self.p["w"] + self.p["z"][:, None, :]
        both = np.stack([codes, codes[::-1]])
        given = table[np.arange(2)[:, None, None], both]
        h = c = np.zeros((2, n, HIDDEN), table.dtype)
        out = np.empty((2, steps, n, HIDDEN), table.dtype)
        if keep is not None:
            shape = (steps, 2, n, HIDDEN)
            keep |= {"codes": both, "gates": np.empty((steps, 2, n, 4 * HIDDEN), table.dtype), "c": np.empty(shape, table.dtype), "s": np.empty(shape, table.dtype), "out": out}
        for t in range(steps):
            z = given[:, t] + h @ self.p["u"]
            z[..., : 3 * HIDDEN] = sigmoid(z[..., : 3 * HIDDEN])
            z[..., 3 * HIDDEN :] = np.tanh(z[..., 3 * HIDDEN :])
            c = z[..., HIDDEN : 2 * HIDDEN] * c + z[..., :HIDDEN] * z[..., 3 * HIDDEN :]
            s = np.tanh(c)
            h = z[..., 2 * HIDDEN : 3 * HIDDEN] * s
            out[:, t] = h
            if keep is not None:
                keep["gates"][t], keep["c"][t], keep["s"][t] = z, c, s
        return np.concatenate([out[0], out[1, ::-1]], 2)

    def emissions(self, codes: np.ndarray) -> np.ndarray:
        return self._lstm(codes) @ self.p["out"] + self.p["bias"]

    def _crf(self, e: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Posteriors (time x batch x tags), expected transitions, and the log partition (batch), by
        forward and backward sums that are scaled to one at each step."""
        trans, steps = np.exp(self.p["trans"]), len(e)
        e = e.copy()
        e[0] += self.p["start"]
        top = e.max(2, keepdims=True)
        x = np.exp(e - top)
        a, b, scale = np.empty_like(x), np.ones_like(x), np.empty_like(top)
        for t in range(steps):
            a[t] = x[t] if t == 0 else (a[t - 1] @ trans) * x[t]
            scale[t] = a[t].sum(1, keepdims=True)
            a[t] /= scale[t]
        x /= scale
        for t in range(steps - 2, -1, -1):
            b[t] = (x[t + 1] * b[t + 1]) @ trans.T
        pairs = trans * (a[:-1].reshape(-1, TAGS).T @ (x * b)[1:].reshape(-1, TAGS))
        return a * b, pairs, (np.log(scale) + top).sum((0, 2))

    def gradients(self, codes: np.ndarray, tags: np.ndarray) -> tuple[float, dict[str, np.ndarray]]:
        """Mean negative log-likelihood of the tags (time x batch) and its gradients."""
        p, (steps, n) = self.p, codes.shape
        kept: dict = {}
        h = self._lstm(codes, kept)
        e = h @ p["out"] + p["bias"]
        de, pairs, z = self._crf(e)
        time, rows = np.arange(steps)[:, None], np.arange(n)
        gold = p["start"][tags[0]] + e[time, rows, tags].sum(0) + p["trans"][tags[:-1], tags[1:]].sum(0)
        de[time, rows, tags] -= 1
        np.subtract.at(pairs, (tags[:-1], tags[1:]), 1)
        pairs[RULED_OUT] = 0
        g = {"start": de[0].sum(0), "trans": pairs, "out": h.reshape(-1, 2 * HIDDEN).T @ de.reshape(-1, TAGS), "bias": de.sum((0, 1))}
        dh = de @ p["out"].T
        dh = np.stack([dh[..., :HIDDEN], dh[::-1, :, HIDDEN:]], 1)
        gates, c, s = kept["gates"], kept["c"], kept["s"]
        dz = np.empty_like(gates)
        later_h = later_c = np.zeros_like(c[0])
        back = p["u"].transpose(0, 2, 1)
        for t in range(steps - 1, -1, -1):
            i, f, o, new = (gates[t][..., k * HIDDEN : (k + 1) * HIDDEN] for k in range(4))
            down = dh[t] + later_h
            dc = down * o * (1 - s[t] * s[t]) + later_c
            dz[t][..., :HIDDEN] = dc * new * i * (1 - i)
            dz[t][..., HIDDEN : 2 * HIDDEN] = dc * c[t - 1] * f * (1 - f) if t else 0
            dz[t][..., 2 * HIDDEN : 3 * HIDDEN] = down * s[t] * o * (1 - o)
            dz[t][..., 3 * HIDDEN :] = dc * i * (1 - new * new)
            later_h, later_c = dz[t] @ back, dc * f
        flat = lambda x: x.reshape(2, -1, x.shape[-1])
        dz = dz.transpose(1, 0, 2, 3)
        g["u"] = flat(np.ascontiguousarray(kept["out"][:, :-1])).transpose(0, 2, 1) @ flat(np.ascontiguousarray(dz[:, 1:]))
        one = np.zeros((2, N_CLASSES, steps * n), dz.dtype)
        one[np.arange(2)[:, None], kept["codes"].reshape(2, -1), np.arange(steps * n)] = 1
        per_class = one @ flat(np.ascontiguousarray(dz))
        g["z"], g["w"] = per_class.sum(1), p["embed"].T @ per_class
        g["embed"] = (per_class @ p["w"].transpose(0, 2, 1)).sum(0)
        return float((z - gold).mean()), {k: v / n for k, v in g.items()}

    def fit(self, codes: np.ndarray, tags: np.ndarray, epochs: int = EPOCHS) -> list[float]:
        """Adam over shuffled batches of windows (windows x time); mean losses by epoch."""
        rng, losses, step = np.random.default_rng(SEED), [], 0
        m, v = ({k: np.zeros_like(x) for k, x in self.p.items()} for _ in range(2))
        for epoch in range(epochs):
            order, sums = rng.permutation(len(codes)), []
            for k in range(0, len(order), BATCH):
                at = order[k : k + BATCH]
                loss, g = self.gradients(codes[at].T, tags[at].T)
                sums.append(loss)
                step += 1
                size = np.sqrt(sum(float((x * x).sum()) for x in g.values()))
                rate = RATE * (1 - epoch / epochs) * min(1.0, 5.0 / max(size, 1e-9))
                for name, x in g.items():
                    m[name] = 0.9 * m[name] + 0.1 * x
                    v[name] = 0.99 * v[name] + 0.01 * x * x
                    self.p[name] -= (rate * (m[name] / (1 - 0.9**step)) / (np.sqrt(v[name] / (1 - 0.99**step)) + 1e-8)).astype(np.float32)
            losses.append(float(np.mean(sums)))
        return losses

    def decode(self, codes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Best tags of windows (windows x time) and their posteriors."""
        e = self.emissions(codes.T)
        steps, n = e.shape[:2]
        back, best = np.zeros((steps, n, TAGS), np.int8), self.p["start"] + e[0]
        for t in range(1, steps):
            x = best[:, :, None] + self.p["trans"]
            back[t] = x.argmax(1)
            best = x.max(1) + e[t]
        tags, rows = np.zeros((steps, n), np.int8), np.arange(n)
        tags[-1] = best.argmax(1)
        for t in range(steps - 1, 0, -1):
            tags[t - 1] = back[t, rows, tags[t]]
        sure = np.ones((steps, n), np.float32)
        some = np.flatnonzero(tags.any(0))
        if len(some):
            sure[:, some] = np.take_along_axis(self._crf(e[:, some])[0], tags[:, some, None].astype(np.int64), 2)[:, :, 0]
        return tags.T, sure.T


def labels_of(length: int, spans: list[tuple[int, int, int]]) -> np.ndarray:
    """Tags per character: 0 outside, 1 + 2 kind at a span's head, 2 + 2 kind in it; earlier kinds win."""
    out = np.zeros(length, np.int8)
    for kind, a, b in spans:
        if not out[a:b].any():
            out[a:b] = 2 + 2 * kind
            out[a] = 1 + 2 * kind
    return out


def windows_of(text: str, tags: np.ndarray | None = None) -> tuple[list[int], np.ndarray, np.ndarray | None]:
    """Starts, classes and tags of a text's windows, padded behind its end."""
    starts = window_starts(text)
    if not starts:
        return starts, np.zeros((0, WINDOW), np.uint8), None if tags is None else np.zeros((0, WINDOW), np.int8)
    code = np.concatenate([classes(text), np.full(WINDOW, 95, np.uint8)])
    at = np.array(starts)[:, None] + np.arange(WINDOW)
    return starts, code[at], None if tags is None else np.concatenate([tags, np.zeros(WINDOW, np.int8)])[at]


def read_spans(n: int, starts: list[int], tags: np.ndarray, sure: np.ndarray) -> list[tuple[int, int, int, float]]:
    """(kind, start, end, mean posterior) of a text of n characters from its decoded windows."""
    half, pieces = (WINDOW - STRIDE) // 2, []
    for k, s in enumerate(starts):
        a = 0 if s == 0 else half
        b = WINDOW if s + WINDOW >= n else half + STRIDE
        for x in np.flatnonzero(tags[k, a:b]):
            pieces.append((s + a + int(x), int(tags[k, a + x]), float(sure[k, a + x])))
    out: list[list] = []
    for at, tag, p in pieces:
        kind, head = (tag - 1) // 2, tag % 2 == 1
        if out and not head and out[-1][0] == kind and out[-1][2] == at:
            out[-1][2] = at + 1
            out[-1][3].append(p)
        elif at < n:
            out.append([kind, at, at + 1, [p]])
    return [(k, a, b, sum(p) / len(p)) for k, a, b, p in out]


def all_spans(texts: list[str], tagger: Tagger | None, batch: int = 512) -> list[tuple[list[tuple[int, int, int]], list[tuple[int, int, int]]]]:
    """Per text: the base spans, and base and added spans together."""
    base = [base_spans(t) if TRIGGER.search(t) else [] for t in texts]
    every = [list(b) for b in base]
    held: list[tuple[int, list[int], np.ndarray]] = []

    def flush() -> None:
        codes = np.concatenate([c for _, _, c in held])
        done = [tagger.decode(codes[k : k + batch]) for k in range(0, len(codes), batch)]
        tags, sure = (np.concatenate(x) for x in zip(*done, strict=True))
        at = 0
        for i, starts, _ in held:
            text, taken = texts[i], labels_of(len(texts[i]), base[i])
            for kind, a, b, p in read_spans(len(text), starts, tags[at : at + len(starts)], sure[at : at + len(starts)]):
                if b - a >= MIN_LENGTH and p >= MIN_POSTERIOR and plausible(kind, text[a:b]) and not taken[a:b].any():
                    every[i].append((kind, a, b))
            every[i].sort()
            at += len(starts)
        held.clear()

    if tagger is not None:
        waiting = 0
        for i, text in enumerate(texts):
            starts, codes, _ = windows_of(text)
            if starts:
                held.append((i, starts, codes))
                waiting += len(starts)
                if waiting >= batch:
                    flush()
                    waiting = 0
        if held:
            flush()
    return list(zip(base, every, strict=True))


def plausible(kind: int, found: str) -> bool:
    """Whether a span can be of its kind at all: what the tagger adds must be."""
    digits = re.sub("[^0-9]", "", found)
    if kind == EMAIL:
        return "@" in found
    if kind == IP:
        parts = found.split(".")
        return ":" in found or len(parts) == 4 and all(p.isdigit() and p.isascii() and len(p) <= 3 and int(p) <= 255 for p in parts)
    if kind == CARD:
        return 13 <= len(digits) <= 19 and luhn(digits)
    return 7 <= len(digits) <= 15 if kind == PHONE else len(digits) >= (2 if kind == SECRET else 9)


class Forge:
    """Writes labelled personal data and look-alikes, in forms drawn from a seed."""

    LETTERS, HEX, CODE = "abcdefghijklmnopqrstuvwxyz", "0123456789abcdef", "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789"

    def __init__(self, seed: int):
        self.rng = np.random.default_rng(seed)

    def of(self, letters: str, least: int, most: int | None = None) -> str:
        return "".join(self.rng.choice(list(letters), int(self.rng.integers(least, (most or least) + 1))))

    def pick(self, *choices):
        return choices[int(self.rng.integers(len(choices)))]

    def number(self, low: int, high: int) -> str:
        return str(int(self.rng.integers(low, high)))

    def digits(self, n: int, first: str = "123456789") -> str:
        return self.pick(*first) + self.of("0123456789", n - 1)

    def email(self) -> str:
        host = ".".join([self.of(self.LETTERS, 2, 8) + self.pick("", self.number(0, 30)) for _ in range(int(self.rng.integers(1, 3)))])
        return self.pick("", self.of(self.LETTERS, 1, 7) + self.pick(".", "_", "-")) + self.of(self.LETTERS, 2, 9) + self.pick("", self.number(0, 999)) + self.pick("@", "@", " @ ", "(at)@") + host + "." + self.pick("com", "org", "net", "de", "fr", "es", "io")

    def ip(self) -> str:
        if self.rng.random() < 0.75:
            return ".".join(self.number(0, 256) for _ in range(4))
        return ":".join(self.of(self.HEX, 1, 4) for _ in range(8)) if self.rng.random() < 0.5 else "2001:db8::" + self.of(self.HEX, 2, 4) + ":" + self.of(self.HEX, 2, 4)

    def card(self) -> str:
        body = self.digits(15, "3456")
        body += next(d for d in "0123456789" if luhn(body + d))
        return self.pick("", "", " ", "-", ".", "/", "  ").join(body[k : k + 4] for k in range(0, 16, 4))

    def phone(self) -> str:
        a, b, c = self.number(200, 999), self.number(200, 999), self.digits(4)
        return self.pick(f"+1 ({a}) {b}-{c}", f"({a}) {b}-{c}", f"{a}-{b}-{c}", f"{a}.{b}.{c}", f"+{self.number(30, 99)} {self.number(10, 99)} {self.digits(7)}", f"0{self.number(100, 999)} {self.digits(7)}", f"00{self.number(30, 99)} {a} {b} {self.number(10, 99)}")

    def secret(self) -> str:
        return self.pick(self.of(self.HEX, 40), self.of(self.HEX, 32), self.of(self.HEX, 64), self.of(self.CODE, 20, 44), "sk-" + self.of(self.CODE, 24, 48), "AKIA" + self.of(self.CODE[:26] + "0123456789", 16))

    def account(self) -> str:
        return self.pick(self.digits(16), self.digits(int(self.rng.integers(12, 20))), self.pick("DE", "FR", "ES", "GB") + self.digits(2) + " " + " ".join(self.digits(4, "0123456789") for _ in range(4)) + " " + self.digits(2), f"{self.digits(3)}-{self.digits(2)}-{self.digits(4)}")

    def harmless(self) -> str:
        return self.pick(
            self.number(0, 10), self.number(10, 100), self.number(100, 2100), self.digits(int(self.rng.integers(3, 7))), f"{self.number(1900, 2030)}-{self.number(10, 13)}-{self.number(10, 29)}", f"{self.number(1, 29)}/{self.number(1, 13)}/{self.number(1990, 2030)}",
            f"version {self.number(0, 9)}.{self.number(0, 20)}", f"Version {self.number(0, 9)}.0.", f"v{self.number(0, 9)}.{self.number(0, 9)}.{self.number(0, 9)}", f"${self.number(1, 999)},{self.digits(3)}.{self.digits(2)}", f"{self.number(0, 100)}%", f"{self.number(10, 24)}:{self.number(10, 60)}",
            f"{self.number(1, 50)}-{self.number(50, 99)}", f"{self.number(1, 20)}.{self.number(1, 20)}.{self.number(1, 9)}", f"{self.number(1, 99)},{self.digits(3)},{self.digits(3)}", f"{self.of(self.LETTERS, 3, 8)}{self.number(1, 99)}", f"@{self.of(self.LETTERS, 3, 9)}", "@", f"({self.number(1, 30)})", f"#{self.number(1, 9999)}",
        )

    def item(self) -> tuple[str, str, int | None, str]:
        """What stands before a datum, the datum, its kind (None: no personal data), and what stands behind."""
        behind = self.pick("", "", "", ",", ".", ";", ")", "!!", "###", "%%%", "$$$", "***", "&&&", "?")
        if self.rng.random() < 0.4:
            return "", self.harmless(), None, behind
        kind = int(self.rng.integers(len(KINDS)))
        if kind == CARD and self.rng.random() < 0.5:
            kind = ACCOUNT  # cards are known by their checksum; the tagger learns numbers of their look as accounts
        datum = [self.email, self.ip, self.card, self.phone, self.secret, self.account][kind]()
        if kind == SECRET:
            quote = self.pick('"', "'", "")
            return self.pick("token", "api_key", "key", "secret", "password", "Authorization", "access token") + self.pick(" = ", "=", ": ") + quote, datum, kind, quote + behind
        cue = {EMAIL: ["mail ", "<"], IP: ["host ", "from "], CARD: ["card "], PHONE: ["tel ", "call "], ACCOUNT: ["account ", "no. ", "IBAN "]}[kind]
        return self.pick("", "", "", *cue), datum, kind, behind

    def write(self, passage: str, every: int = 70) -> tuple[str, list[tuple[int, int, int]]]:
        """A passage with items between its words, one in about ``every`` characters, and the labelled spans."""
        out, spans, at, due = [], [], 0, int(self.rng.integers(1, every))
        for word in re.findall("\\S+\\s*|\\s+", passage) or [""]:
            out.append(word)
            at += len(word)
            if at >= due:
                before, datum, kind, behind = self.item()
                lead = "" if not out[-1] or out[-1][-1].isspace() else " "
                start = at + len(lead) + len(before)
                if kind is not None:
                    spans.append((kind, start, start + len(datum)))
                out.append(f"{lead}{before}{datum}{behind} ")
                at += len(out[-1])
                due = at + int(self.rng.integers(every // 2, 2 * every))
        return "".join(out), spans


def passages_of(docs: DataFrame, most: int = TRAIN_PASSAGES) -> list[str]:
    """At most ``most`` passages of PASSAGE characters without a digit or an @, one pass over the texts.

    A text gives the passage at a place that its hash tells; of the passages whose hashes fall
    into one of BUCKETS buckets the smallest is taken.  So the driver gets BUCKETS passages at
    most, whatever the number of documents, their lengths and repetitions.
    """
    text = F.col("text").cast("string")
    at = F.pmod(F.xxhash64(text), F.greatest(F.length(text) - PASSAGE, F.lit(1)))
    some = docs.select(F.substring(text, at.cast("int") + 1, F.lit(PASSAGE)).alias("x")).where(~F.col("x").rlike("[0-9@]") & F.col("x").rlike("\\S"))
    dealt = some.groupBy(F.pmod(F.xxhash64("x", F.lit("pii")), F.lit(BUCKETS)).alias("bucket")).agg(F.min("x").alias("x"))
    return [r["x"] for r in sorted(dealt.collect(), key=lambda r: r["bucket"])][:most]


def train(docs: DataFrame, most: int = TRAIN_PASSAGES, seed: int = SEED) -> Tagger | None:
    """A tagger learned from spans written into at most ``most`` passages; None without a passage."""
    passages = passages_of(docs, most)
    return trained(passages, seed) if passages else None


def trained(passages: list[str], seed: int = SEED) -> Tagger:
    """Few passages are used several times, with other items in them."""
    forge = Forge(seed)
    texts = [forge.write(passages[k % len(passages)]) for k in range(max(TRAIN_PASSAGES, len(passages)))]
    made = [windows_of(t, labels_of(len(t), spans))[1:] for t, spans in texts]
    tagger = Tagger(seed)
    tagger.fit(*balanced(np.concatenate([c for c, _ in made]), np.concatenate([t for _, t in made])))
    return tagger


def evaluate(tagger: Tagger | None, passages: list[str], seed: int) -> dict[str, tuple[int, int, int]]:
    """Per kind: labelled spans written into the passages, those found exactly, and spans found.
    Without a tagger: what the patterns alone find."""
    forge = Forge(seed)
    texts, spans = zip(*[forge.write(x) for x in passages], strict=True)
    out = {k: [0, 0, 0] for k in KINDS}
    for truth, (_, found) in zip(spans, all_spans(list(texts), tagger), strict=True):
        for kind, *_ in truth:
            out[KINDS[kind]][0] += 1
        for span in found:
            out[KINDS[span[0]]][1] += span in truth
            out[KINDS[span[0]]][2] += 1
    return {k: tuple(v) for k, v in out.items()}


def balanced(codes: np.ndarray, tags: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The windows with labels, and as many evenly taken ones without."""
    some, none = np.flatnonzero(tags.any(1)), np.flatnonzero(~tags.any(1))
    none = none[:: max(1, len(none) // max(1, len(some)))]
    at = np.concatenate([some, none])
    return codes[at], tags[at]


def written(spans: list[tuple[int, int, int]]) -> str:
    return ",".join(f"{KINDS[k]}:{a}:{b}" for k, a, b in spans)


def find(docs: DataFrame, most: int = TRAIN_PASSAGES) -> DataFrame:
    """Per row of ``docs``: doc_id, n_email, n_ip, n_card, n_phone (of the patterns), base_sha256,
    spans, n_spans (of both).

    Null and empty texts have no spans; without anything to learn from only the patterns
    count.  Repeated rows each give a row, an empty table an empty result; other columns are
    not read.
    """
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"))
    model = Shipped(docs.sparkSession, train(rows, most))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in slices(batches, 16 << 20):
            found = all_spans(b.column(1).to_pylist(), model.value)
            counts = [pa.array([sum(s[0] == k for s in base) for base, _ in found], pa.int64()) for k in range(len(BASE_KINDS))]
            digest = pa.array([hashlib.sha256(written(base).encode()).hexdigest() for base, _ in found], pa.string())
            every = [pa.array([written(x) for _, x in found], pa.string()), pa.array([len(x) for _, x in found], pa.int64())]
            yield pa.RecordBatch.from_arrays([b.column(0), *counts, digest, *every], ["doc_id", *(f"n_{k}" for k in BASE_KINDS), "base_sha256", "spans", "n_spans"])

    return map_batches(rows, run, SCHEMA)


def redact(text: str, spans: list[tuple[int, int, int]]) -> str:
    """The text with every span replaced by its kind in brackets."""
    out, at = [], 0
    for kind, a, b in sorted(spans, key=lambda s: (s[1], -s[2])):
        if a >= at:
            out += [text[at:a], f"[{KINDS[kind]}]"]
            at = b
    return "".join([*out, text[at:]])
