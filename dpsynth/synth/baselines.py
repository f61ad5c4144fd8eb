"""The rivals.  All share ledger, noise, store, estimator and generator with the main method and
differ in what they choose and how they fit.  These are formulations of published ideas.
"""

from __future__ import annotations

import math
from itertools import combinations

import numpy as np

from dpsynth.domain import DomainSpec
from dpsynth.model.graphical import Measurement, estimate_total, fit, independent_model
from dpsynth.model.junction import elimination_cliques
from dpsynth.model.mixture import Generator, fit_relaxed
from dpsynth.operators.marginals import MarginalStore
from dpsynth.privacy.accountant import Ledger
from dpsynth.privacy.mechanisms import NoiseSource, exp_select, gaussian_release
from dpsynth.synth.base import Clock, Round, SynthesisResult, Transcript
from dpsynth.workload import Workload

Subset = tuple[int, ...]
HALF_NORMAL = math.sqrt(2 / math.pi)


class _Run:
    """Ledger, noise and transcript of one run."""

    def __init__(self, store: MarginalStore, rho: float, seed: int | None):
        self.store, self.spec, self.clock = store, store.spec, Clock()
        self.ledger, self.noise = Ledger(rho), NoiseSource(seed)
        self.transcript = Transcript(store.spec, {})

    def measure(self, subset: Subset, rho: float) -> Measurement:
        self.ledger.charge(min(rho, self.ledger.left), f"table {subset}")
        sigma = math.sqrt(1 / (2 * rho))
        m = Measurement(subset, gaussian_release(self.store.dense(subset), sigma, self.noise), sigma)
        self.transcript.measured.append(m)
        return m

    def choose(self, scores: list[float], rho: float, sensitivity: float) -> int:
        self.ledger.charge(rho, "choice")
        return exp_select(scores, math.sqrt(8 * rho), sensitivity, self.noise)

    def noted(self, number: int, chosen: Subset, pool: list[Subset], sigma: float, eps: float) -> None:
        self.transcript.rounds.append(Round(number, sigma, eps, 1.0, chosen, pool, self.ledger.used, self.ledger.left))

    def result(self, model, **stats: float) -> SynthesisResult:
        base = {"rounds": len(self.transcript.rounds), "seconds": self.clock.lap(), "rho_spent": self.ledger.used, "size_mb": getattr(model, "size_mb", 0.0), "scans": 1}
        return SynthesisResult(model, self.transcript, self.ledger, base | stats)


def pair_sets(spec: DomainSpec, k: int) -> list[Subset]:
    """All subsets of up to k attributes: what the workload-agnostic rivals may look at."""
    return [r for n in range(1, k + 1) for r in combinations(range(spec.d), n)]


def synthesize_independent(store: MarginalStore, workload: Workload | None, rho: float, seed: int | None = None) -> SynthesisResult:
    """One-way tables with equal shares, product model."""
    run = _Run(store, rho, seed)
    for i in range(run.spec.d):
        run.measure((i,), rho / run.spec.d)
    return run.result(independent_model(run.spec, run.transcript.measured))


def gaussian_shares(workload: Workload, spec: DomainSpec, split: str = "optimal") -> dict[Subset, float]:
    """Budget share of each workload set; optimal minimizes the expected weighted L1 error,
    which by Lagrange is in proportion to (weight * cells)^(2/3)."""
    raw = {r: (c * spec.size(r)) ** (2 / 3) if split == "optimal" else 1.0 for r, c in workload.merged().items()}
    total = sum(raw.values())
    return {r: x / total for r, x in raw.items()}


def answer_gaussian(store: MarginalStore, workload: Workload, rho: float, seed: int | None = None, split: str = "optimal") -> tuple[dict[Subset, Measurement], Ledger]:
    """Noisy answers to every set of the workload, and nothing else: no records come of it."""
    run = _Run(store, rho, seed)
    return {r: run.measure(r, share * rho) for r, share in gaussian_shares(workload, run.spec, split).items() if share > 0}, run.ledger


def answer_error(answers: dict[Subset, Measurement], store: MarginalStore, workload: Workload) -> float:
    return sum(c * float(np.abs(answers[r].values - store.dense(r)).sum()) for r, c in workload.merged().items() if r in answers) / (workload.k * max(1, store.n))


def expected_gaussian_error(workload: Workload, spec: DomainSpec, rho: float, n: int) -> float:
    """Closed form of the optimal split's expected error."""
    s = sum((c * spec.size(r)) ** (2 / 3) for r, c in workload.merged().items())
    return HALF_NORMAL * s**1.5 / (workload.k * n * math.sqrt(2 * rho))


def _gap_to_product(store: MarginalStore, child: int, parents: Subset) -> float:
    """L1 distance of a family's table from the product of its two sides.  One record more or less
    moves it by less than 4 (family, both sides and the total each move by one at most)."""
    spec, family = store.spec, tuple(sorted((child, *parents)))
    table = store.dense(family).reshape(spec.shape(family))
    at = family.index(child)
    a = table.sum(tuple(k for k in range(len(family)) if k != at))
    b = table.sum(at)
    return float(np.abs(np.moveaxis(table, at, 0) - np.multiply.outer(a, b) / max(1.0, table.sum())).sum())


def synthesize_bayes_net(store: MarginalStore, workload: Workload | None, rho: float, seed: int | None = None, degree: int = 2, theta: float = 4.0, iters: int = 200) -> SynthesisResult:
    """Attributes one after the other, each with the parents that it depends on most."""
    run = _Run(store, rho, seed)
    spec, d = run.spec, run.spec.d
    order = [int(run.noise.rng.integers(d))]
    families: list[Subset] = [(order[0],)]
    total = estimate_total([run.measure((min(range(d), key=lambda i: (spec.attrs[i].size, i)),), 0.02 * rho)])  # the number of records is secret
    each = rho / 2 / max(1, d - 1)
    limit = max(4.0, total * math.sqrt(rho / d) / theta)  # families whose noise would drown them are left out
    while len(order) < d:
        pool = [(c, p) for c in range(d) if c not in order for n in range(1, min(degree, len(order)) + 1) for p in combinations(sorted(order), n) if n == 1 or spec.size((c, *p)) <= limit]
        c, p = pool[run.choose([_gap_to_product(store, c, p) for c, p in pool], each, 4.0)]
        order.append(c)
        families.append(tuple(sorted((c, *p))))
        run.noted(len(order) - 1, families[-1], [tuple(sorted((a, *b))) for a, b in pool], 0.0, math.sqrt(8 * each))
    rest = run.ledger.left / d
    for r in families:
        run.measure(r, rest)
    return run.result(fit(run.transcript.measured, spec, iters))


def synthesize_span_tree(store: MarginalStore, workload: Workload | None, rho: float, seed: int | None = None, iters: int = 200) -> SynthesisResult:
    """One-way tables, a spanning tree of strongly dependent pairs, the pairs' tables: a third each."""
    run = _Run(store, rho, seed)
    spec, d = run.spec, run.spec.d
    for i in range(d):
        run.measure((i,), rho / 3 / d)
    product = independent_model(spec, run.transcript.measured)
    score = {e: float(np.abs(store.dense(e) - product.marginal(e)).sum()) for e in combinations(range(d), 2)}
    part, chosen = list(range(d)), []
    for k in range(d - 1):
        pool = [e for e in score if part[e[0]] != part[e[1]]]
        e = pool[run.choose([score[x] for x in pool], rho / 3 / (d - 1), 1.0)]
        chosen.append(e)
        run.noted(k + 1, e, pool, 0.0, math.sqrt(8 * rho / 3 / (d - 1)))
        old, new = part[e[0]], part[e[1]]
        part = [new if x == old else x for x in part]
    rest = run.ledger.left / max(1, d - 1)
    for e in chosen:
        run.measure(e, rest)
    return run.result(fit(run.transcript.measured, spec, iters))


def synthesize_rand_field(store: MarginalStore, workload: Workload | None, rho: float, seed: int | None = None, max_cells: int = 20_000, rounds: int | None = None, iters: int = 60) -> SynthesisResult:
    """A sparse triangulated graph from noisy pair dependences, then sets inside its cliques by
    how far the model is from them beyond the noise."""
    run = _Run(store, rho, seed)
    spec, d = run.spec, run.spec.d
    for i in range(d):
        run.measure((i,), 0.1 * rho / d)
    product = independent_model(spec, run.transcript.measured)
    pairs = list(combinations(range(d), 2))
    run.ledger.charge(0.1 * rho, "dependences")
    sigma = math.sqrt(len(pairs)) * math.sqrt(1 / (0.2 * rho))
    noisy = [float(np.abs(store.dense(e) - product.marginal(e)).sum()) + z for e, z in zip(pairs, run.noise.gaussian(sigma, len(pairs)), strict=True)]
    edges: list[Subset] = []
    for v, e in sorted(zip(noisy, pairs, strict=True), reverse=True):
        if v > 0 and max(spec.size(c) for c in elimination_cliques([*edges, e], spec.sizes)) <= max_cells:
            edges.append(e)
    known = set(store.subsets)
    inside = sorted({r for c in elimination_cliques(edges, spec.sizes) for n in (2, 3) for r in combinations(c, n) if r in known})
    model, n = fit(run.transcript.measured, spec, iters), min(rounds or d, len(inside))
    share = run.ledger.left / max(1, n)
    for k in range(n):
        sd = math.sqrt(1 / (2 * 0.8 * share))
        scores = [float(np.abs(store.dense(r) - model.marginal(r)).sum()) - HALF_NORMAL * sd * spec.size(r) for r in inside]
        r = inside[run.choose(scores, 0.2 * share, 1.0)]
        run.measure(r, 0.8 * share)
        run.noted(k + 1, r, inside, sd, math.sqrt(8 * 0.2 * share))
        model = fit(run.transcript.measured, spec, iters * (4 if k == n - 1 else 1), model)
    return run.result(model)


def synthesize_relaxed_proj(store: MarginalStore, workload: Workload, rho: float, seed: int | None = None, rounds: int = 5, per_round: int = 4, rows: int = 200, steps: int = 150, rate: float = 0.1) -> SynthesisResult:
    """T rounds of K choices among the workload's sets without repeats; a relaxed table is fitted."""
    run = _Run(store, rho, seed)
    spec, left = run.spec, list(workload.merged())
    first = min(left, key=lambda r: (spec.size(r), r))
    total_m = run.measure(first, 0.02 * rho)
    total = estimate_total([total_m])
    model = fit_relaxed([total_m], spec, rows, 20, rate, total)
    n = min(rounds * per_round, len(left))
    share = run.ledger.left / n
    done = 0
    while done < n:
        for _ in range(min(per_round, n - done)):
            r = left[run.choose([float(np.abs(store.dense(x) - model.marginal(x)).sum()) for x in left], share / 2, 1.0)]
            left.remove(r)
            run.measure(r, share / 2)
            done += 1
            run.noted(done, r, list(left), math.sqrt(1 / share), math.sqrt(4 * share))
        model = fit_relaxed(run.transcript.measured, spec, rows, steps, rate, total, model)
    return run.result(model)


def synthesize_gen_mix(store: MarginalStore, workload: Workload, rho: float, seed: int | None = None, rounds: int | None = None, variant: str = "marginal", components: int = 128, steps: int = 80) -> SynthesisResult:
    """A generator of product mixtures; each round adds the worst answered set (or, in the query
    variant, one cell of a set) to what it is trained on."""
    run = _Run(store, rho, seed)
    spec, pool = run.spec, list(workload.merged())
    first = min(pool, key=lambda r: (spec.size(r), r))
    total = estimate_total([run.measure(first, 0.02 * rho)])
    net = Generator(spec, components, seed=0 if seed is None else seed)
    model = net.fit(run.transcript.measured, total, steps)
    n = min(rounds or 2 * spec.d, 10_000)
    share = run.ledger.left / n
    for k in range(n):
        gaps = [np.abs(store.dense(r) - model.marginal(r)) for r in pool]
        if variant == "marginal":
            r = pool[run.choose([float(g.sum()) for g in gaps], share / 2, 1.0)]
            run.measure(r, share / 2)
        else:  # one counting query: the other cells keep the model's own values
            flat = np.concatenate(gaps)
            at = run.choose(list(flat), share / 2, 1.0)
            ends = np.cumsum([len(g) for g in gaps])
            i = int(np.searchsorted(ends, at, "right"))
            r, c = pool[i], at - (ends[i] - len(gaps[i]))
            run.ledger.charge(min(share / 2, run.ledger.left), f"cell {r}")
            values = model.marginal(r).copy()
            values[c] = store.dense(r)[c] + run.noise.gaussian(math.sqrt(1 / share), 1)[0]
            run.transcript.measured.append(Measurement(r, values, math.sqrt(1 / share)))
        run.noted(k + 1, r, pool, math.sqrt(1 / share), math.sqrt(4 * share))
        model = net.fit(run.transcript.measured, total, steps)
    return run.result(model)

