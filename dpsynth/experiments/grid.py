"""Experiment grids: datasets x workloads x budgets x mechanisms x trials, as a table of errors.

A dataset's exact store is built once; the runs of a grid are independent and small, so they may
be spread over executors (one task a run) with the store's dense marginals broadcast.
"""

from __future__ import annotations

from collections.abc import Iterator, Sequence
from dataclasses import replace

import numpy as np
import pandas as pd
from pyspark.errors import AnalysisException
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from dpsynth import fixtures
from dpsynth import workload as wl
from dpsynth.domain import DomainSpec
from dpsynth.experiments.stats import t_pvalue
from dpsynth.operators.marginals import MarginalStore
from dpsynth.privacy.accountant import rho_of
from dpsynth.synth import needed_subsets, synthesize_from
from dpsynth.synth.base import AdaptiveConfig, table_error
from dpsynth.uncertainty import bound_rows

#: The nine budgets, log-spaced.
EPSILONS = [10 ** (k / 2) for k in range(-4, 5)]
DELTA = 1e-9
RESULTS = "dataset string, workload string, epsilon double, mechanism string, trial int, error double, table_error double, error_l2 double, error_linf double, rounds int, seconds double, size_mb double"


class DenseStore:
    """The dense marginals of a store, detached from Spark: what a run on an executor needs."""

    def __init__(self, spec: DomainSpec, n: int, tables: dict[tuple[int, ...], np.ndarray]):
        self.spec, self.n, self.tables, self.subsets = spec, n, tables, list(tables)

    @classmethod
    def of(cls, store: MarginalStore) -> DenseStore:
        if store.cells > store.DRIVER_CELLS:
            raise ValueError("this store is too large to be copied; run its mechanisms from the driver")
        return cls(store.spec, store.n, {r: store.dense(r) for r in store.subsets})

    def dense(self, subset: tuple[int, ...]) -> np.ndarray:
        return self.tables[subset]


def workload_of(spec: DomainSpec, name: str, target: int = 0, seed: int = 42) -> wl.Workload:
    return {"all3": lambda: wl.all_kway(spec, 3), "all2": lambda: wl.all_kway(spec, 2), "target": lambda: wl.target_workload(spec, target), "skewed": lambda: wl.skewed_workload(spec, seed=seed)}[name]()


#: Attributes to be predicted, where a table has one; others are drawn with a fixed seed.
TARGETS = {"F1": "returnflag", "F5": "quality"}


def target_of(name: str, spec: DomainSpec) -> int:
    return spec.index(TARGETS[name]) if name in TARGETS else wl.pick_target(spec)


def run_grid(spark: SparkSession, sf_dir: str, datasets: Sequence[str] = ("F7",), workloads: Sequence[str] = ("all3",), epsilons: Sequence[float] = EPSILONS, mechanisms: Sequence[str] = ("adaptive", "independent"), trials: int = 5, cfg: AdaptiveConfig | None = None, folder: str | None = None, at_once: int = 400) -> DataFrame:
    """Errors of every run (columns RESULTS); trial k uses seed k.

    error is that of the model's marginals, table_error that of a generated table.  folder:
    results are written there, ``at_once`` runs a job, and runs found there are not made again, so
    a grid that was stopped goes on where it was.
    """
    cfg = cfg or AdaptiveConfig()
    if folder is not None:
        return _stored_grid(spark, folder, at_once, sf_dir, datasets, workloads, epsilons, mechanisms, trials, cfg)
    return _run(spark, sf_dir, cfg, [(d, w, float(e), m, k) for d in datasets for w in workloads for e in epsilons for m in mechanisms for k in range(trials)])


KEYS = ["dataset", "workload", "epsilon", "mechanism", "trial"]


def _stored_grid(spark: SparkSession, folder: str, at_once: int, sf_dir: str, datasets, workloads, epsilons, mechanisms, trials: int, cfg: AdaptiveConfig) -> DataFrame:
    def found() -> DataFrame | None:
        try:
            return spark.read.schema(RESULTS).parquet(folder)
        except AnalysisException as e:
            if e.getCondition() != "PATH_NOT_FOUND":
                raise
            return None

    for d in datasets:
        for w in workloads:
            runs = [(d, w, float(e), m, k) for e in epsilons for m in mechanisms for k in range(trials)]
            old = found()
            done = set() if old is None else {tuple(r) for r in old.where((F.col("dataset") == d) & (F.col("workload") == w)).select(*KEYS).collect()}
            left = [r for r in runs if r not in done]
            for k in range(0, len(left), at_once):
                _run(spark, sf_dir, cfg, left[k : k + at_once]).write.mode("append").parquet(folder)
    asked = (F.col(c).isin(list(v)) for c, v in (("dataset", datasets), ("workload", workloads), ("epsilon", map(float, epsilons)), ("mechanism", mechanisms)))
    out = found().where(F.col("trial") < trials)
    for c in asked:
        out = out.where(c)
    return out


def _run(spark: SparkSession, sf_dir: str, cfg: AdaptiveConfig, runs: list[tuple]) -> DataFrame:
    datasets, epsilons = dict.fromkeys(r[0] for r in runs), dict.fromkeys(r[2] for r in runs)
    stores: dict[str, DenseStore] = {}
    for name in datasets:
        codes, spec = fixtures.load(spark, sf_dir, name)
        store = MarginalStore.build(codes, spec, needed_subsets(spec, wl.all_kway(spec, min(3, spec.d))))
        stores[name] = DenseStore.of(store)
        store.close()
    shared = spark.sparkContext.broadcast((stores, cfg, {e: rho_of(e, DELTA) for e in epsilons}))
    todo = spark.createDataFrame(runs, "dataset string, workload string, epsilon double, mechanism string, trial int").repartition(max(1, min(len(runs), 2_000)), *KEYS)

    def work(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        by_name, base, rho = shared.value
        for f in frames:
            for row in f.itertuples():
                store = by_name[row.dataset]
                w = workload_of(store.spec, row.workload, target_of(row.dataset, store.spec))
                r = synthesize_from(store, w, rho[row.epsilon], row.mechanism, replace(base, seed=int(row.trial)))
                l1, l2, linf = (r.error(store, w, norm) for norm in ("l1", "l2", "linf"))
                yield pd.DataFrame([(row.dataset, row.workload, row.epsilon, row.mechanism, row.trial, l1, table_error(r, store, w, int(row.trial)), l2, linf, int(r.stats["rounds"]), r.stats["seconds"], r.stats["size_mb"])], columns=[c.split()[0] for c in RESULTS.split(", ")])

    # a task has one core, and so have the matrix products in it; the worker reads this when it starts
    environment = spark.sparkContext.environment
    before = environment.get("OMP_NUM_THREADS")
    environment["OMP_NUM_THREADS"] = "1"
    out = todo.mapInPandas(work, RESULTS)
    if before is None:
        del environment["OMP_NUM_THREADS"]
    else:
        environment["OMP_NUM_THREADS"] = before
    return out


def ablation_table(results: DataFrame, main: str = "adaptive") -> DataFrame:
    """variant, settings, geometric mean of error ratios, per-setting one-sided p values combined."""
    from dpsynth.experiments.stats import stouffer

    keys = ["dataset", "workload", "epsilon"]
    base = results.where(F.col("mechanism") == main).groupBy(*keys).agg(F.collect_list("error").alias("base"))
    other = results.where(F.col("mechanism") != main).groupBy(*keys, "mechanism").agg(F.collect_list("error").alias("other"))
    rows = {}
    for r in other.join(base, keys).collect():  # one row a setting
        rows.setdefault(r["mechanism"], []).append((np.mean(r["other"]) / np.mean(r["base"]), t_pvalue(r["base"], r["other"]) if len(r["base"]) > 1 else 0.5))
    made = [(m, len(x), float(np.exp(np.mean(np.log([a for a, _ in x])))), *map(float, stouffer([p for _, p in x]))) for m, x in rows.items()]
    return results.sparkSession.createDataFrame(made, "mechanism string, settings int, geo_ratio double, z double, log_p double")


def bound_experiment(spark: SparkSession, sf_dir: str, dataset: str = "F5", eps: float = 10.0, cfg: AdaptiveConfig | None = None) -> DataFrame:
    """marginal_id, kind, bound, err for every 3-way set: are the bounds above the errors, and how far?"""
    from dpsynth.domain import marginal_id

    codes, spec = fixtures.load(spark, sf_dir, dataset)
    w = wl.all_kway(spec, 3)
    store = MarginalStore.build(codes, spec, w.closure())
    r = synthesize_from(store, w, rho_of(eps, DELTA), "adaptive", cfg or AdaptiveConfig(seed=0))
    synth = MarginalStore.build(r.generate(spark), spec, w.closure())
    rows = [(marginal_id(s), kind, float(b), float(np.abs(store.dense(s) - synth.dense(s)).sum())) for s, kind, b in bound_rows(r.transcript, {s: synth.dense(s) for s in w.merged()}, w.merged())]
    for s in (store, synth):
        s.close()
    return spark.createDataFrame(rows, "marginal_id long, kind string, bound double, err double")


def fixture_summary(spark: SparkSession, sf_dir: str, names: Sequence[str] = tuple(fixtures.SPECS)) -> DataFrame:
    """Records, attributes, least and greatest size, size of the full domain (as text: it exceeds 64 bits)."""
    rows = [(n, fixtures.load(spark, sf_dir, n)[0].count(), s.d, min(s.sizes), max(s.sizes), str(s.size())) for n, s in fixtures.SPECS.items() if n in names]
    return spark.createDataFrame(rows, "fixture string, records long, d int, min_size int, max_size int, domain string")
