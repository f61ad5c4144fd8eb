"""Quality rules: robust multivariate outliers by minimum covariance determinant.

Word statistics of every text are turned into a vector of logarithmic ratios.  For each language
and source the mean and covariance of the SUPPORT share of documents with the smallest
determinant are sought.  All documents count, but a group comes to one task as a table of at most
CELLS grid cells, each with its exact moments: the grid is as fine as that bound allows, so a
group of any size takes bounded memory and the shuffle carries few rows for it.  On the cells the
estimate is sought from several starts (medians and quartile ranges, and small random
subsets) by concentration steps until the determinant stays; the smallest determinant wins.  It
is then made consistent for normal data and reweighted once, as usual.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator
from math import factorial

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from dpsynth.llm.common import cut, map_batches, slices

#: Share of a group that an estimate rests on, smallest group with an estimate of its own.
SUPPORT, MIN_GROUP = 0.75, 20
#: Random starts, those of all starts that are followed to the end, and steps at most.
STARTS, FOLLOWED, STEPS = 60, 8, 100
#: Cells of one group at most.  Cells are 2^-4 to 2^-1 wide; at that width, with component 0 up to
#: TOP, there are 2 TOP + 1 times 10 times 15 times 8 of them at most, but far fewer have a text.
CELLS, WIDTHS, TOP = 20_000, (16, 8, 4, 2), 8
#: Standard deviations that count as the least possible: ratios that are zero in most texts have none of their own.
#: For repeated lines and words half the step that one repeated line of eight words makes in 300: log1p(1000 / 300) / 2, log1p(1600 / 300) / 2.
FLOORS = (0.1, 0.38, 0.73, 0.92)
#: Chi-square with four degrees of freedom: the median, the quantile that reweighting keeps, and that beyond which one in a thousand lies.
MEDIAN, INLIER, CUTOFF = 3.3567, 11.1433, 18.4668
BASE_WORDS, BASE_REPEATS = 50, 50

SPACES, SYMBOLS = b" \t\n\x0b\x0c\r", b"#*$%&|<>"
P = len(FLOORS)
PAIRS = [(i, j) for i in range(P) for j in range(i, P)]
COUNTS = ["n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words"]


def word_statistics(text: str | None) -> tuple[int, int, int, int, int]:
    """n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words of one whole text."""
    text = text or ""
    raw = text.encode("utf-8", "surrogatepass")
    words = raw.split()
    blanks = len(raw) - len(raw.translate(None, SPACES))
    lines = [x for x in raw.split(b"\n") if x.strip()]
    repeated = 0
    grams = list(zip(words, words[1:], words[2:], strict=False))
    if len(set(grams)) < len(grams):
        seen, reach = Counter(grams), 0
        for i, g in enumerate(grams):
            if seen[g] > 1:
                repeated += i + 3 - max(i, reach)
                reach = i + 3
    return len(words), len(text) - blanks, len(raw) - len(raw.translate(None, SYMBOLS)), len(lines) - len(set(lines)), repeated


def statistics(docs: DataFrame) -> DataFrame:
    """doc_id, lang, source and the word statistics per row of ``docs``; one Arrow pass over the texts."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in slices(batches):
            found = np.array([word_statistics(t) for t in b.column(3).to_pylist()], np.int64).reshape(-1, 5)
            yield pa.RecordBatch.from_arrays([*b.columns[:3], *(pa.array(found[:, k]) for k in range(5))], ["doc_id", "lang", "source", *COUNTS])

    text = lambda c: F.coalesce(F.col(c).cast("string"), F.lit("")).alias(c)
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), text("lang"), text("source"), text("text"))
    return map_batches(rows, run, "doc_id long, lang string, source string, " + ", ".join(f"{c} long" for c in COUNTS))


def with_vectors(stats: DataFrame) -> DataFrame:
    """Adds base_failed and the components v0..v3: word length, symbols, repeated lines, repeated words."""
    words = F.greatest("n_words", F.lit(1))
    failed = (F.col("n_words") < BASE_WORDS) | (100 * F.col("n_repeat_words") > BASE_REPEATS * F.col("n_words"))
    vector = [F.log(F.greatest("word_chars", F.lit(1)) / words), F.log1p(100 * F.col("n_symbols") / F.greatest("word_chars", F.lit(1))), F.log1p(1000 * F.col("n_dup_lines") / words), F.log1p(100 * F.col("n_repeat_words") / words)]
    return stats.withColumn("base_failed", failed).withColumns({f"v{i}": v for i, v in enumerate(vector)})


def with_groups(rows: DataFrame, min_group: int) -> DataFrame:
    """Adds ``grp``: language and source, or for small groups the language, or else everything.
    Only texts that pass the base rules count and are learned from."""
    key = lambda *c: F.to_json(F.array(*c))
    good = rows.where(~F.col("base_failed"))
    fine = good.groupBy("lang", "source").agg(F.count("*").alias("n"))
    small = fine.where(F.col("n") < min_group).groupBy("lang").agg(F.sum("n").alias("n_small"))
    names = fine.join(small, "lang", "left").select("lang", "source", F.when(F.col("n") >= min_group, key("lang", "source")).when(F.col("n_small") >= min_group, key("lang")).otherwise(F.lit("[]")).alias("grp"))
    return rows.join(names, ["lang", "source"], "left").withColumn("grp", F.coalesce("grp", F.lit("[]")))


def cells_of(rows: DataFrame, limit: int = CELLS) -> DataFrame:
    """grp, m, s0.., q0..: counts and moments of the cells of each group, on the finest grid of WIDTHS
    on which the group has at most ``limit`` cells (or on the widest)."""
    v = [F.col(f"v{i}") for i in range(P)]
    at = lambda k: [F.floor((F.least(x, F.lit(TOP)) if i == 0 else x) * k).alias(f"c{i}") for i, x in enumerate(v)]
    key = [f"c{i}" for i in range(P)]
    sums = [F.count("*").alias("m"), *[F.sum(x).alias(f"s{i}") for i, x in enumerate(v)], *[F.sum(v[i] * v[j]).alias(f"q{k}") for k, (i, j) in enumerate(PAIRS)]]
    fine = cut(rows.select("grp", *at(WIDTHS[0]), *v).groupBy("grp", *key).agg(*sums))
    names = ["m", *[f"s{i}" for i in range(P)], *[f"q{k}" for k in range(len(PAIRS))]]
    # coarser grids are unions of finer cells, so they are counted on the cells, not on the texts
    coarser = lambda k: [F.shiftright(c, k).alias(c) for c in key]
    counts = [F.approx_count_distinct(F.struct(*coarser(k)), 0.02).alias(f"n{k}") for k in range(len(WIDTHS))]
    step = F.lit(len(WIDTHS) - 1)
    for k in reversed(range(len(WIDTHS) - 1)):
        step = F.when(F.col(f"n{k}") <= 0.9 * limit, F.lit(k)).otherwise(step)
    steps = fine.groupBy("grp").agg(*counts).select("grp", step.alias("step"))
    moved = fine.join(steps, "grp").select("grp", *[F.call_function("shiftright", c, "step").alias(c) for c in key], *names)
    return moved.groupBy("grp", *key).agg(*[F.sum(n).alias(n) for n in names]).select("grp", *names)


def floored(cov: np.ndarray) -> np.ndarray:
    """Covariances (.. x P x P) whose variances are at least those of FLOORS; never singular."""
    out, d = cov.copy(), np.arange(P)
    least = np.square(FLOORS)
    out[..., d, d] = np.maximum(out[..., d, d], least) + 1e-6 * least
    return out


class Moments:
    """Weighted points or cells of one group: counts, sums and sums of products."""

    def __init__(self, m: np.ndarray, s: np.ndarray, q: np.ndarray):
        self.m, self.s, self.q = m, s, q
        self.mid = s / m[:, None]

    @classmethod
    def of_points(cls, v: np.ndarray) -> Moments:
        return cls(np.ones(len(v)), v, v[:, :, None] * v[:, None, :])

    def estimate(self, share: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Mean and covariance of the given shares (0 to 1) of the cells."""
        w = (share * self.m).sum()
        mean = share @ self.s / w
        return mean, np.tensordot(share, self.q, 1) / w - np.outer(mean, mean)

    def distances(self, mean: np.ndarray, cov: np.ndarray) -> np.ndarray:
        d = self.mid - mean
        return np.einsum("ij,ij->i", d @ np.linalg.inv(floored(cov)), d)

    def nearest(self, far: np.ndarray, h: float) -> np.ndarray:
        """Shares of the cells that make up the h nearest documents; of the last cell only a part."""
        order = np.argsort(far, kind="stable")
        before = np.cumsum(self.m[order]) - self.m[order]
        out = np.empty(len(far))
        out[order] = np.clip((h - before) / self.m[order], 0.0, 1.0)
        return out


def consistency(share: float) -> float:
    """Factor that makes the covariance of the nearest ``share`` of normal data that of all of them:
    share / P(chi-square with P + 2 degrees <= its quantile at P degrees)."""
    if share >= 1:
        return 1.0
    within = lambda x, k: 1 - np.exp(-x / 2) * sum((x / 2) ** i / factorial(i) for i in range(k // 2))
    low, high = 0.0, 200.0
    while high - low > 1e-9:
        mid = (low + high) / 2
        low, high = (mid, high) if within(mid, P) < share else (low, mid)
    return float(share / within(low, P + 2))


def objective(cov: np.ndarray) -> float:
    return float(np.linalg.slogdet(floored(cov))[1])


def starting_points(cells: Moments, rng: np.random.Generator) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Medians and quartile ranges; then random subsets of P + 1 documents."""
    mid, dev = np.empty(P), np.empty(P)
    for i in range(P):
        order = np.argsort(cells.mid[:, i], kind="stable")
        upto = np.cumsum(cells.m[order])
        low, mid[i], high = (cells.mid[order[np.searchsorted(upto, q * upto[-1])], i] for q in (0.25, 0.5, 0.75))
        dev[i] = (high - low) / 1.349
    yield mid, np.diag(dev * dev)
    odds = cells.m / cells.m.sum()
    for _ in range(STARTS):
        some = cells.mid[rng.choice(len(odds), P + 1, p=odds)]
        yield some.mean(0), np.cov(some.T, bias=True)


def least_determinant(cells: Moments, support: float = SUPPORT, seed: int = 0) -> tuple[float, np.ndarray, np.ndarray]:
    """Log determinant, mean and covariance of the support with the smallest determinant that
    concentration steps find: two from every start, then on to the end from the best ones."""
    h = np.ceil(support * cells.m.sum())

    def step(mean: np.ndarray, cov: np.ndarray) -> tuple[float, np.ndarray, np.ndarray]:
        mean, cov = cells.estimate(cells.nearest(cells.distances(mean, cov), h))
        return objective(cov), mean, cov

    tried = [step(*step(*start)[1:]) for start in starting_points(cells, np.random.default_rng(seed))]
    best = None
    for now in sorted(tried, key=lambda x: x[0])[:FOLLOWED]:
        for _ in range(STEPS):
            after = step(*now[1:])
            done = after[0] >= now[0] - 1e-12
            now = min(now, after, key=lambda x: x[0])
            if done:
                break
        best = now if best is None else min(best, now, key=lambda x: x[0])
    return best


def robust_estimate(cells: Moments, support: float = SUPPORT) -> tuple[np.ndarray, np.ndarray, float]:
    """Mean, inverse covariance and scale of a group: the smallest determinant, reweighted.

    scale puts the median distance of the group at that of the chi-square law, where it is larger.
    """
    _, mean, cov = least_determinant(cells, support)
    near = cells.distances(mean, cov * consistency(support)) <= INLIER
    mean, cov = cells.estimate(near.astype(float))
    cov = cov * consistency(0.975)
    far = cells.distances(mean, cov)
    order = np.argsort(far, kind="stable")
    upto = np.cumsum(cells.m[order])
    return mean, np.linalg.inv(floored(cov)), max(1.0, float(far[order[np.searchsorted(upto, 0.5 * upto[-1])]]) / MEDIAN)


SOLVED = "grp string, n long, mean array<double>, inv array<double>, scale double"


def distance() -> F.Column:
    """Squared Mahalanobis distance of v0..v3 under the columns mean and inv."""
    d = [F.col(f"v{i}") - F.get("mean", F.lit(i)) for i in range(P)]
    terms = [(1.0 if i == j else 2.0) * F.get("inv", F.lit(k)) * d[i] * d[j] for k, (i, j) in enumerate(PAIRS)]
    return F.greatest(sum(terms[1:], terms[0]), F.lit(0.0))


def estimates(rows: DataFrame, min_group: int = MIN_GROUP, support: float = SUPPORT, limit: int = CELLS) -> DataFrame:
    """grp, n, mean, inv, scale: the estimate of each group of at least ``min_group`` rows."""

    def solve(f: pd.DataFrame) -> pd.DataFrame:
        f = f.sort_values([f"s{i}" for i in range(P)])  # whatever way the cells came
        q = np.empty((len(f), P, P))
        for k, (i, j) in enumerate(PAIRS):
            q[:, i, j] = q[:, j, i] = f[f"q{k}"]
        cells = Moments(f["m"].to_numpy(float), f[[f"s{i}" for i in range(P)]].to_numpy(float), q)
        if cells.m.sum() < min_group:
            return pd.DataFrame({"grp": [], "n": [], "mean": [], "inv": [], "scale": []})
        mean, inverse, scale = robust_estimate(cells, support)
        return pd.DataFrame({"grp": [f["grp"].iloc[0]], "n": [int(cells.m.sum())], "mean": [mean.tolist()], "inv": [[float(inverse[i, j]) for i, j in PAIRS]], "scale": [scale]})

    return cut(cells_of(rows, limit).groupBy("grp").applyInPandas(solve, SOLVED))


def judge(docs: DataFrame, min_group: int = MIN_GROUP, cutoff: float = CUTOFF, support: float = SUPPORT) -> DataFrame:
    """Per row of ``docs``: doc_id, the word statistics, base_failed, kept, distance and grp.

    Null texts, languages and sources are empty strings.  A text that fails the base rules is
    rejected; of the others those are whose distance exceeds the cutoff.  A language and source
    with fewer than ``min_group`` texts to learn from is judged with the others like it of its
    language, or of all languages; where that is too small too, nothing else is rejected
    (distance null).  Repeated rows each give a row, an empty table an empty result.
    """
    rows = cut(with_vectors(statistics(docs)))
    rows = cut(with_groups(rows, min_group))
    learned = estimates(rows.where(~F.col("base_failed")), min_group, support)
    met = rows.join(learned.select("grp", "mean", "inv", "scale"), "grp", "left").withColumn("distance", distance() / F.col("scale"))
    met = met.withColumn("distance", F.when(F.col("scale").isNotNull(), F.col("distance")))
    kept = ~F.col("base_failed") & F.coalesce(F.col("distance") <= cutoff, F.lit(True))
    return met.select("doc_id", *COUNTS, "base_failed", kept.alias("kept"), "distance", "grp")
