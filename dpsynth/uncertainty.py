"""Error bounds after the fact, from the public transcript alone.

For a marginal inside a measured set: an estimator from all sets that contain it, and a bound on
its error.  For any other one: a bound from the last round in which it was a candidate and lost.
No function here takes the sensitive table.
"""

from __future__ import annotations

import math
from collections.abc import Iterable

import numpy as np
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from dpsynth.domain import DomainSpec, marginal_id
from dpsynth.model.graphical import Measurement
from dpsynth.synth.base import Transcript

Subset = tuple[int, ...]
HALF_NORMAL = math.sqrt(2 / math.pi)
#: Default levels: one tail for supported, two for unsupported marginals.
LAMBDA, LAMBDA_1, LAMBDA_2 = 1.7, 2.7, 3.7


def lambda_for(level: float) -> float:
    """The value at which 1 - exp(-x^2) is the level."""
    return math.sqrt(-math.log(1 - level))


def simultaneous(level: float, k: int) -> float:
    """Level of each of k bounds for all to hold together at ``level`` (union bound)."""
    return 1 - (1 - level) / k


def confidence(lam: float) -> float:
    return 1 - math.exp(-lam * lam)


def confidence_unsupported(l1: float, l2: float) -> float:
    return 1 - math.exp(-l1 * l1 / 2) - math.exp(-l2)


def is_supported(r: Subset, measured: Iterable[Subset]) -> bool:
    return any(set(r) <= set(s) for s in measured)


def weighted_average(r: Subset, measured: Iterable[Measurement], spec: DomainSpec) -> tuple[np.ndarray, float] | None:
    """Inverse-variance mean of the marginal over all measurements that contain it, and the
    variance of each of its cells."""
    top, bottom, n = np.zeros(spec.size(r)), 0.0, spec.size(r)
    for m in measured:
        if set(r) <= set(m.subset):
            table = m.values.reshape(spec.shape(m.subset))
            down = table.sum(tuple(k for k, i in enumerate(m.subset) if i not in r)).ravel()
            weight = n / (len(m.values) * m.sigma**2)
            top, bottom = top + weight * down, bottom + weight
    return (top / bottom, 1 / bottom) if bottom else None


def bound_supported(cells: int, sd: float, lam: float = LAMBDA) -> float:
    """On the estimator's L1 error: expectation and deviation of a Gaussian vector's norm."""
    return math.sqrt(2 * math.log(2)) * sd * cells + lam * sd * math.sqrt(2 * cells)


def bound_supported_synth(estimate: np.ndarray, sd: float, synth: np.ndarray, lam: float = LAMBDA) -> float:
    """On the synthetic table's error: its distance from the estimate, and the estimate's bound."""
    return float(np.abs(synth - estimate).sum()) + bound_supported(len(estimate), sd, lam)


def bound_unsupported(t: Transcript, r: Subset, l1: float = LAMBDA_1, l2: float = LAMBDA_2, lambda1_weighting: str = "derived") -> tuple[float, int] | None:
    """On the error of the model before the round that is used, and the round's number.

    A candidate that lost scored at most so much more than the winner; the winner's error is known
    up to noise.  derived: the noise term carries the winner's weight; printed: it does not.
    """
    if r not in t.seen or not t.weights.get(r):
        return None
    number = t.seen[r][0]
    now = next(x for x in t.rounds if x.number == number)
    y, shown = t.answers[number]
    s, n_r, n_s = now.selected, t.spec.size(r), t.spec.size(now.selected)
    w_r, w_s = t.weights[r], t.weights[s]
    noise = l1 * now.sigma * math.sqrt(n_s) * (w_s if lambda1_weighting == "derived" else 1.0)
    won = w_s * float(np.abs(y - shown).sum()) + noise
    sizes = HALF_NORMAL * now.sigma * (w_r * n_r - w_s * n_s)
    choice = 2 * now.sensitivity / now.eps * (math.log(len(now.candidates)) + l2)
    return (won + sizes + choice) / w_r, number


def bound_unsupported_synth(t: Transcript, r: Subset, synth: np.ndarray, l1: float = LAMBDA_1, l2: float = LAMBDA_2, lambda1_weighting: str = "derived") -> float:
    """On the synthetic table's error: its distance from that model, and the model's bound."""
    found = bound_unsupported(t, r, l1, l2, lambda1_weighting)
    if found is None:
        return math.inf
    return float(np.abs(synth - t.seen[r][1].marginal(r)).sum()) + found[0]


def bound_rows(t: Transcript, synth: dict[Subset, np.ndarray], subsets: Iterable[Subset], lam: float = LAMBDA, l1: float = LAMBDA_1, l2: float = LAMBDA_2) -> list[tuple[Subset, str, float]]:
    """(subset, kind, bound) for each subset; synth: marginals of the synthetic table."""
    measured, out = [m.subset for m in t.measured], []
    for r in subsets:
        if is_supported(r, measured):
            mean, var = weighted_average(r, t.measured, t.spec)
            out.append((r, "supported", bound_supported_synth(mean, math.sqrt(var), synth[r], lam)))
        else:
            out.append((r, "unsupported", bound_unsupported_synth(t, r, synth[r], l1, l2)))
    return out


def uncertainty_report(spark: SparkSession, t: Transcript, synth: dict[Subset, np.ndarray], subsets: Iterable[Subset], n: float, lam: float = LAMBDA, l1: float = LAMBDA_1, l2: float = LAMBDA_2) -> DataFrame:
    """marginal_id, kind, bound, bound per record of the (noisy) total."""
    rows = [(marginal_id(r), kind, float(b), float(b) / max(1.0, n)) for r, kind, b in bound_rows(t, synth, subsets, lam, l1, l2)]
    return spark.createDataFrame(rows, "marginal_id long, kind string, bound double, normalized double")


# -- the same on tables ------------------------------------------------------------------------
def supported_df(closure: DataFrame, measured: DataFrame) -> DataFrame:
    """marginal_id of the closure's sets that some measured set contains (bit masks)."""
    inside = F.col("marginal_id").bitwiseAND(F.col("s")) == F.col("marginal_id")
    return closure.join(F.broadcast(measured.select(F.col("marginal_id").alias("s")).distinct()), inside, "left_semi")


def pick_round_df(round_candidates: DataFrame) -> DataFrame:
    """The last round in which each marginal was a candidate; never the best over rounds."""
    last = F.row_number().over(Window.partitionBy("marginal_id").orderBy(F.desc("round")))
    return round_candidates.withColumn("k", last).where("k = 1").drop("k")


def variance_df(measured: DataFrame, targets: DataFrame) -> DataFrame:
    """marginal_id, var of the weighted average, from (marginal_id, n_r, sigma) of measurements and
    (marginal_id, n_r) of targets.  Releases of one set add up first: what is broadcast has a row a set."""
    m = measured.groupBy(F.col("marginal_id").alias("s"), F.col("n_r").alias("n_s")).agg(F.sum(1 / (F.col("sigma") * F.col("sigma"))).alias("precision"))
    inside = F.col("marginal_id").bitwiseAND(F.col("s")) == F.col("marginal_id")
    return targets.join(F.broadcast(m), inside).groupBy("marginal_id").agg((1 / F.sum(F.col("n_r") / F.col("n_s") * F.col("precision"))).alias("var"))
