"""Mechanisms by name."""

from __future__ import annotations

from itertools import combinations

from pyspark.sql import DataFrame

from dpsynth.domain import DomainSpec
from dpsynth.operators.marginals import MarginalStore
from dpsynth.privacy.accountant import ApproxDP
from dpsynth.privacy.mechanisms import NoiseSource
from dpsynth.synth import baselines
from dpsynth.synth.base import AdaptiveConfig, SynthesisResult
from dpsynth.synth.rounds import ABLATIONS, ablation, synthesize_adaptive, synthesize_fixed_round
from dpsynth.workload import Workload

RIVALS = {
    "independent": baselines.synthesize_independent, "bayes_net": baselines.synthesize_bayes_net, "span_tree": baselines.synthesize_span_tree,
    "rand_field": baselines.synthesize_rand_field, "relaxed_proj": baselines.synthesize_relaxed_proj, "gen_mix": baselines.synthesize_gen_mix,
}
MECHANISMS = ["adaptive", "fixed_round", *RIVALS]


def needed_subsets(spec: DomainSpec, workload: Workload) -> list[tuple[int, ...]]:
    """Marginals that any of the mechanisms may ask for: the closure, all pairs and all triples."""
    return sorted({*workload.closure(), *(r for k in (1, 2, 3) for r in combinations(range(spec.d), k))}, key=lambda r: (len(r), r))


def synthesize_from(store: MarginalStore, workload: Workload, budget: ApproxDP | float, mechanism: str = "adaptive", cfg: AdaptiveConfig | None = None, **kw) -> SynthesisResult:
    """Run a mechanism on an exact store.  budget: (eps, delta), or rho as a number."""
    rho = budget.rho if isinstance(budget, ApproxDP) else float(budget)
    cfg = cfg or AdaptiveConfig()
    if mechanism == "adaptive":
        return synthesize_adaptive(store, workload, rho, cfg)
    if mechanism == "fixed_round":
        return synthesize_fixed_round(store, workload, rho, cfg)
    if mechanism in ABLATIONS:
        return synthesize_adaptive(store, workload, rho, ablation(mechanism, cfg))
    if mechanism == "gen_mix_query":
        return baselines.synthesize_gen_mix(store, workload, rho, cfg.seed, variant="query", **kw)
    return RIVALS[mechanism](store, workload, rho, cfg.seed, **kw)


def synthesize(codes: DataFrame, spec: DomainSpec, workload: Workload, budget: ApproxDP | float, mechanism: str = "adaptive", cfg: AdaptiveConfig | None = None, release: bool = False, **kw) -> SynthesisResult:
    """Encoded records to a fitted model: one scan for the store, then the mechanism.

    release=True refuses a seeded configuration: what leaves the trusted side needs system entropy.
    """
    NoiseSource((cfg or AdaptiveConfig()).seed).check(release)
    subsets = workload.closure() if mechanism in ("adaptive", "fixed_round") or mechanism in ABLATIONS else needed_subsets(spec, workload)
    store = MarginalStore.build(codes, spec, subsets)
    try:
        return synthesize_from(store, workload, budget, mechanism, cfg, **kw)
    finally:
        store.close()
