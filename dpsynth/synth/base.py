"""What all mechanisms share: configuration, public transcript, result."""

from __future__ import annotations

import time
from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import DataFrame, SparkSession

from dpsynth.domain import DomainSpec, marginal_id
from dpsynth.model.generate import generate, generate_rows
from dpsynth.model.graphical import GraphicalModel, Measurement
from dpsynth.privacy.accountant import Ledger, Neighbor

Subset = tuple[int, ...]


@dataclass(frozen=True)
class AdaptiveConfig:
    """Switches of the round loop; the defaults are the main method."""

    alpha: float = 0.9
    rounds_factor: int = 16
    cap_mb: float = 80.0
    cap_schedule: str = "fixed"  # or proportional to the budget spent
    fit_iters: int = 40
    final_iters: int = 400
    seed: int | None = None
    neighbor: Neighbor = Neighbor.UNBOUNDED
    noise: str = "gauss"  # or laplace, discrete
    start: str = "independent"  # or uniform
    score: str = "new"  # or old
    candidates: str = "closure"  # or workload
    rounds: str = "adaptive"  # or fixed
    n_rounds: int | None = None
    estimator: str = "gme"  # or relaxed
    residual_weight: str = "inv_sigma"
    rows_per_unit: int = 1

    def __post_init__(self):
        if not 0 < self.alpha < 1 or self.rounds_factor < 1:
            raise ValueError("alpha lies between 0 and 1, and there are at least d rounds")


@dataclass
class Round:
    """One round as the public sees it."""

    number: int
    sigma: float
    eps: float
    sensitivity: float
    selected: Subset
    candidates: list[Subset]
    rho_spent: float
    rho_left: float
    annealed: bool = False
    final: bool = False
    size_mb: float = 0.0
    seconds: float = 0.0
    fit_seconds: float = 0.0


@dataclass
class Transcript:
    """Everything that error bounds need; no sensitive table is in it."""

    spec: DomainSpec
    weights: dict[Subset, float]
    measured: list[Measurement] = field(default_factory=list)
    rounds: list[Round] = field(default_factory=list)
    #: per candidate: the last round it was one in, and the model before that round (a model fits the capacity limit)
    seen: dict[Subset, tuple[int, GraphicalModel]] = field(default_factory=dict)
    #: per round: the noisy values minus nothing, and the selected set's marginal before the round
    answers: dict[int, tuple[np.ndarray, np.ndarray]] = field(default_factory=dict)

    def to_dfs(self, spark: SparkSession) -> dict[str, DataFrame]:
        ids = marginal_id
        rounds = [(r.number, r.sigma, r.eps, r.sensitivity, ids(r.selected), len(r.candidates), r.rho_spent, r.rho_left, r.annealed, r.final, r.size_mb) for r in self.rounds]
        every = [(r.number, ids(c), float(self.weights.get(c, 0.0)), self.spec.size(c)) for r in self.rounds for c in r.candidates]
        noisy = [(k, ids(m.subset), float(m.sigma), c, float(v)) for k, m in enumerate(self.measured) for c, v in enumerate(m.values)]
        return {
            "rounds": spark.createDataFrame(rounds, "round int, sigma double, eps double, delta_sens double, selected long, n_cand int, rho_spent double, rho_left double, annealed boolean, final boolean, jt_mb double"),
            "round_candidates": spark.createDataFrame(every, "round int, marginal_id long, w_r double, n_r long"),
            "measurement": spark.createDataFrame(noisy, "no int, marginal_id long, sigma double, cell long, value double"),
        }


@dataclass
class SynthesisResult:
    model: GraphicalModel
    transcript: Transcript
    ledger: Ledger
    stats: dict[str, float] = field(default_factory=dict)

    def generate(self, spark: SparkSession, n: int | None = None, seed: int = 0, method: str = "round") -> DataFrame:
        return generate(spark, self.model, n, seed, method)

    def error(self, store, workload, norm: str = "l1") -> float:
        """Workload error of the model's own marginals, scaled to the size of the table that it makes."""
        total = 0.0
        for r, c in workload.merged().items():
            gap = np.abs(store.dense(r) - self.model.marginal(r))
            total += c * float({"l1": gap.sum(), "l2": np.sqrt((gap**2).sum()), "linf": gap.max()}[norm])
        return total / (workload.k * max(1, store.n))


def table_error(result: SynthesisResult, store, workload, seed: int = 0) -> float:
    """Workload error of a generated table, one that fits the memory of a task."""
    made = generate_rows(result.model, None, seed).astype(np.int64)
    spec, total = store.spec, 0.0
    for r, c in workload.merged().items():
        at = sum(made[:, i] * k for i, k in zip(r, spec.strides(r), strict=True))
        total += c * float(np.abs(store.dense(r) - np.bincount(at, minlength=spec.size(r))).sum())
    return total / (workload.k * max(1, store.n))


class Clock:
    def __init__(self):
        self.began = time.perf_counter()

    def lap(self) -> float:
        now = time.perf_counter()
        out, self.began = now - self.began, now
        return out
