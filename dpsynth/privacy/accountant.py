"""Zero-concentrated differential privacy: costs, conversion, ledger with a filter."""

from __future__ import annotations

import math
from dataclasses import dataclass, field
from enum import Enum


class Neighbor(Enum):
    """Which tables must look alike: one record more or less, or one record replaced."""

    UNBOUNDED = "add or remove"
    BOUNDED = "replace"


def l2_sensitivity(neighbor: Neighbor = Neighbor.UNBOUNDED, rows_per_unit: int = 1) -> float:
    """Of a marginal: one cell moves by one per record; a replacement moves two cells."""
    return rows_per_unit * (1.0 if neighbor is Neighbor.UNBOUNDED else math.sqrt(2.0))


def score_sensitivity(weight: float, neighbor: Neighbor = Neighbor.UNBOUNDED, rows_per_unit: int = 1) -> float:
    """Of a weighted L1 distance to a fixed table."""
    return weight * rows_per_unit * (1 if neighbor is Neighbor.UNBOUNDED else 2)


def rho_gauss(sigma: float) -> float:
    return 1 / (2 * sigma * sigma)


def rho_exp(eps: float) -> float:
    return eps * eps / 8


def rho_laplace(b: float) -> float:
    """Of Laplace noise with scale b in units of the L1 sensitivity (pure privacy 1/b)."""
    return 1 / (2 * b * b)


def compose(rhos: list[float]) -> float:
    return math.fsum(rhos)


def delta_of(rho: float, eps: float) -> float:
    """The smallest delta for which rho-zCDP gives (eps, delta): a search over the order, in logs."""
    if rho <= 0:
        return 0.0

    def log_delta(order: float) -> float:
        return (order - 1) * (order * rho - eps) + order * math.log1p(-1 / order) - math.log(order - 1)

    lo, hi = math.log(1e-9), math.log(max(1e-3, (eps + rho) / rho * 4 + 10))
    for _ in range(200):  # unimodal in the logarithm of order - 1
        a, b = lo + (hi - lo) * 0.382, lo + (hi - lo) * 0.618
        if log_delta(1 + math.exp(a)) < log_delta(1 + math.exp(b)):
            hi = b
        else:
            lo = a
    return min(1.0, math.exp(log_delta(1 + math.exp((lo + hi) / 2))))


def rho_of(eps: float, delta: float) -> float:
    """The largest rho whose guarantee implies (eps, delta), by bisection."""
    lo, hi = 0.0, eps + 1.0
    while delta_of(hi, eps) <= delta:
        hi *= 2
    for _ in range(200):
        mid = (lo + hi) / 2
        lo, hi = (mid, hi) if delta_of(mid, eps) <= delta else (lo, mid)
    return lo


@dataclass(frozen=True)
class ApproxDP:
    eps: float
    delta: float = 1e-9

    @property
    def rho(self) -> float:
        return rho_of(self.eps, self.delta)


class BudgetExceeded(RuntimeError):
    """A charge would pass the budget; nothing was released."""


@dataclass
class Ledger:
    """Charges before data are touched, so a crash never counts too little."""

    rho: float
    spent: list[tuple[str, float]] = field(default_factory=list)

    @property
    def used(self) -> float:
        return math.fsum(r for _, r in self.spent)

    @property
    def left(self) -> float:
        return self.rho - self.used

    def can_afford(self, cost: float, rounds: float = 1) -> bool:
        return cost * rounds <= self.left * (1 + 1e-12)

    def charge(self, cost: float, what: str = "") -> None:
        if cost > self.left + 1e-12 * self.rho:
            raise BudgetExceeded(f"{what}: {cost} asked, {self.left} left")
        self.spent.append((what, cost))


def initial_rates(rho: float, d: int, alpha: float = 0.9, factor: int = 16) -> tuple[float, float]:
    """Noise scale and selection parameter at which factor * d rounds would spend all of rho."""
    rounds = factor * d
    return math.sqrt(rounds / (2 * alpha * rho)), math.sqrt(8 * (1 - alpha) * rho / rounds)


def last_rates(left: float, alpha: float = 0.9) -> tuple[float, float]:
    """Rates of a round that spends exactly what is left."""
    return math.sqrt(1 / (2 * alpha * left)), math.sqrt(8 * (1 - alpha) * left)


def round_cost(sigma: float, eps: float) -> float:
    return rho_gauss(sigma) + rho_exp(eps)
