"""Noise sources and the two mechanisms: noisy marginals, noisy choice."""

from __future__ import annotations

import math
import secrets
from collections.abc import Iterator, Sequence

import numpy as np
import pandas as pd
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from dpsynth.functions import gauss, gumbel, laplace


class NoiseSource:
    """Driver-side draws.  ``seed`` None takes entropy from the system; only such a source may
    serve a release.  discrete rounds Gaussian draws to integers by exact rejection."""

    def __init__(self, seed: int | None = None, discrete: bool = False):
        self.secure, self.discrete = seed is None, discrete
        self.rng = np.random.default_rng(secrets.randbits(128) if seed is None else seed)

    def check(self, release: bool) -> None:
        if release and not self.secure:
            raise ValueError("a release needs noise from system entropy, not from a seed")

    def gaussian(self, sigma: float, n: int) -> np.ndarray:
        return self._discrete(sigma, n) if self.discrete else self.rng.normal(0.0, sigma, n)

    def laplace(self, scale: float, n: int) -> np.ndarray:
        return self.rng.laplace(0.0, scale, n)

    def gumbel(self, n: int) -> np.ndarray:
        return self.rng.gumbel(size=n)

    def _discrete(self, sigma: float, n: int) -> np.ndarray:
        """Discrete Gaussian from two-sided geometric proposals."""
        t, out = math.floor(sigma) + 1, np.empty(0)
        while len(out) < n:
            m = 2 * (n - len(out)) + 16
            x = (self.rng.geometric(1 - math.exp(-1 / t), m) - 1) * np.where(self.rng.random(m) < 0.5, -1, 1)
            fair = ~((x == 0) & (self.rng.random(m) < 0.5))  # zero is proposed by both signs
            keep = self.rng.random(m) < np.exp(-((np.abs(x) - sigma * sigma / t) ** 2) / (2 * sigma * sigma))
            out = np.concatenate([out, x[keep & fair]])
        return out[:n].astype(float)


def gaussian_release(values: np.ndarray, sigma: float, noise: NoiseSource) -> np.ndarray:
    """All cells of a dense marginal plus noise: empty cells are as secret as full ones."""
    return values + noise.gaussian(sigma, len(values))


def laplace_release(values: np.ndarray, scale: float, noise: NoiseSource) -> np.ndarray:
    return values + noise.laplace(scale, len(values))


def spread_release(dense: DataFrame, sigma: float, seed: int | None = None) -> DataFrame:
    """``dense`` (with a column cnt) with value, cnt plus Gaussian noise drawn where the rows are.

    For tables too large for the driver.  Each task draws from system entropy; with a seed
    (tests only) from it and the task's number.  A task that is run again draws anew, so write the
    result once and publish only what was written.
    """
    names = [*dense.columns, "value"]

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        rng = np.random.default_rng(secrets.randbits(128) if seed is None else [seed, TaskContext.get().partitionId()])
        for f in frames:
            yield f.assign(value=f["cnt"] + rng.normal(0.0, sigma, len(f)))[names]

    schema = T.StructType([*dense.schema.fields, T.StructField("value", T.DoubleType())])
    return dense.mapInPandas(run, schema)


def exp_select(scores: Sequence[float], eps: float, sensitivity: float, noise: NoiseSource) -> int:
    """Index drawn in proportion to exp(eps * score / (2 * sensitivity)), by the largest Gumbel sum."""
    return int(np.argmax(np.asarray(scores) * (eps / (2 * sensitivity)) + noise.gumbel(len(scores))))


def hash_release(dense: DataFrame, sigma: float, seed: int, kind: str = "gauss") -> DataFrame:
    """Dense store plus noise that is a hash of seed, marginal and cell: a retried task draws the
    same again.  For tests and benchmarks; never a release."""
    draw = {"gauss": gauss, "laplace": laplace}[kind](seed, F.col("marginal_id"), F.col("cell"))
    return dense.select("marginal_id", "cell", (F.col("cnt") + sigma * draw).alias("value"))


def hash_select(scores: DataFrame, eps: float, sensitivity: float, seed: int, n: int = 1) -> DataFrame:
    """The first ``n`` candidates (marginal_id, score) by score plus hashed Gumbel noise."""
    key = F.col("score") * (eps / (2 * sensitivity)) + gumbel(seed, F.col("marginal_id"), F.lit("pick"))
    return scores.withColumn("key", key).orderBy(F.desc("key"), "marginal_id").limit(n)


def bound_contributions(df: DataFrame, unit: str, m: int, seed: int = 0) -> DataFrame:
    """At most m records of each unit (person), in the order of a hash of the whole record.

    Noise must then be scaled by m.  A unit's records meet in one task; the window ranks them
    by a streamed sort, so a unit of any size needs no memory of its own.
    """
    order = F.xxhash64(F.lit(seed), *[c for c in df.columns])
    return df.withColumn("_rank", F.row_number().over(Window.partitionBy(unit).orderBy(order))).where(F.col("_rank") <= m).drop("_rank")
