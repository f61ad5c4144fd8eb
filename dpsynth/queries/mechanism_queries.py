"""Whole mechanisms and experiments.  SQL cannot iterate a fit; queries here whose answer does not
depend on the fit (numbers of records, domain violations, budget spent) have a twin all the same.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from dpsynth import encode as en
from dpsynth import workload as wl
from dpsynth.experiments import grid
from dpsynth.fixtures import SPECS, encoded_sql, load
from dpsynth.operators import marginals as mg
from dpsynth.operators import metrics as mt
from dpsynth.privacy.accountant import ApproxDP, Neighbor
from dpsynth.synth import ABLATIONS, MECHANISMS, AdaptiveConfig, synthesize
from dpsynth.synth.baselines import answer_gaussian, expected_gaussian_error

CFG = AdaptiveConfig(seed=0)
BUDGET = ApproxDP(10.0)


def _result(spark: SparkSession, sf_dir: str, name: str, mechanism: str, cfg: AdaptiveConfig = CFG, workload: str = "all3"):
    codes, spec = load(spark, sf_dir, name)
    w = grid.workload_of(spec, workload, grid.target_of(name, spec))
    return codes, spec, w, synthesize(codes, spec, w, BUDGET, mechanism, cfg)


def _records(name: str, mechanism: str):
    """Synthetic records as counts per distinct record, decoded."""

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        _, spec, _, r = _result(spark, sf_dir, name, mechanism)
        return en.decode(r.generate(spark), spec)

    return run, None


def _bounded_size(name: str):
    """Under bounded neighbours the number of records is public: it and the domain hold exactly."""

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        from dataclasses import replace

        _, spec, _, r = _result(spark, sf_dir, name, "adaptive", replace(CFG, neighbor=Neighbor.BOUNDED))
        return en.validate(r.generate(spark), spec)

    return run, f"select count(*) as n, 0::bigint as n_bad from ({encoded_sql(name)})"


def _errors(name: str, mechanisms: list[str], workload: str = "all3", norm: str = "l1"):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        g = grid.run_grid(spark, sf_dir, [name], [workload], [1.0, 10.0], mechanisms, 1, CFG)
        return g.select("dataset", "workload", "epsilon", "mechanism", {"l1": "error", "l2": "error_l2", "linf": "error_linf"}[norm])

    return run, None


def _trials(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mt.trial_summary(grid.run_grid(spark, sf_dir, ["F7"], ["all3"], [1.0, 10.0], ["adaptive", "independent", "span_tree"], 5, CFG))


def _ablation(spark: SparkSession, sf_dir: str) -> DataFrame:
    names = ["adaptive", *(a for a in ABLATIONS if a != "O1_relaxed")]
    return grid.ablation_table(grid.run_grid(spark, sf_dir, ["F7"], ["all3"], [1.0, 10.0], names, 3, CFG))


def _grid(name: str, workload: str, mechanisms: list[str]):
    """A whole grid on one table: all budgets, five trials."""

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        return grid.run_grid(spark, sf_dir, [name], [workload], grid.EPSILONS, mechanisms, 5, CFG)

    return run, None


def _whole_bounds(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mt.bound_tightness(grid.bound_experiment(spark, sf_dir, "F1"))


def _bounds(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mt.bound_tightness(grid.bound_experiment(spark, sf_dir, "F5"))


def _capacity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Error, model size and seconds by the limit on the model."""
    from dataclasses import replace

    out = None
    for mb in (0.01, 0.1, 1.0, 80.0):
        g = grid.run_grid(spark, sf_dir, ["F5"], ["all3"], [10.0], ["adaptive"], 1, replace(CFG, cap_mb=mb)).withColumn("cap_mb", F.lit(mb))
        out = g if out is None else out.unionByName(g)
    return out.select("cap_mb", "error", "size_mb", "rounds")


def _hyper(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sensitivity of the fixed-round synthesizer to its number of rounds."""
    from dataclasses import replace

    rows = []
    for n in (2, 5, 10):
        codes, spec, w, r = _result(spark, sf_dir, "F5", "fixed_round", replace(CFG, n_rounds=n))
        store = mg.MarginalStore.build(codes, spec, w.closure())
        rows.append((n, float(r.error(store, w))))
    return spark.createDataFrame(rows, "n_rounds int, error double")


def _budget(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Share of the budget that every mechanism spends."""
    codes, spec = load(spark, sf_dir, "F7")
    w = wl.all_kway(spec, 3)
    rows = [(m, round(r.ledger.used / r.ledger.rho, 9)) for m in MECHANISMS for r in [synthesize(codes, spec, w, BUDGET, m, CFG)]]
    return spark.createDataFrame(rows, "mechanism string, share double")


def _gauss_error(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Closed form of the Gaussian baseline's expected error on F2, all pairs."""
    codes, spec = load(spark, sf_dir, "F2")
    w = wl.all_kway(spec, 2)
    return spark.createDataFrame([(round(expected_gaussian_error(w, spec, 0.5, codes.count()), 6),)], "error double")


_SIZES2 = [SPECS["F2"].size(r) for r in wl.all_kway(SPECS["F2"], 2).merged()]
GAUSS_ERROR_SQL = f"select round(sqrt(2 / pi()) * pow(sum(pow(n, 2.0 / 3)), 1.5) / (36 * (select count(*) from orders join customer on o_custkey = c_custkey)), 6) as error from (values {', '.join(f'({n})' for n in _SIZES2)}) t(n)"


def _gauss_answers(spark: SparkSession, sf_dir: str) -> DataFrame:
    codes, spec = load(spark, sf_dir, "F7")
    w = wl.all_kway(spec, 2)
    answers, _ = answer_gaussian(mg.MarginalStore.build(codes, spec, w.closure()), w, 0.5, 0)
    return spark.createDataFrame([(list(r), float(m.sigma), float(m.values.sum())) for r, m in answers.items()], "attrs array<int>, sigma double, total double")


def _transcript(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _result(spark, sf_dir, "F5", "adaptive")[3].transcript.to_dfs(spark)["rounds"]


def _report(spark: SparkSession, sf_dir: str) -> DataFrame:
    from dpsynth.uncertainty import uncertainty_report

    _, spec, w, r = _result(spark, sf_dir, "F5", "adaptive")
    synth = mg.MarginalStore.build(r.generate(spark), spec, w.closure())
    return uncertainty_report(spark, r.transcript, {s: synth.dense(s) for s in w.merged()}, w.merged(), r.model.total)


def _sampled(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rounding against plain sampling: L1 distance of one-way tables from the model's."""
    import numpy as np

    _, spec, _, r = _result(spark, sf_dir, "F5", "adaptive")
    rows = []
    for method in ("round", "sample"):
        store = mg.MarginalStore.build(r.generate(spark, method=method), spec, [(i,) for i in range(spec.d)])
        rows.append((method, float(sum(np.abs(store.dense((i,)) - r.model.marginal((i,)) * store.n / r.model.total).sum() for i in range(spec.d)) / store.n)))
    return spark.createDataFrame(rows, "method string, gap double")


def _source(spark: SparkSession, sf_dir: str) -> DataFrame:
    """1,000 records from the data source, and how many break the domain."""
    from dpsynth.sources import synthetic

    _, spec, _, r = _result(spark, sf_dir, "F5", "independent")
    synthetic.register(spark)
    return en.validate(spark.read.format("dpsynth").options(model=synthetic.model_option(r.model), n="1000", seed="1", slicerows="300").load(), spec)


def _summary(spark: SparkSession, sf_dir: str) -> DataFrame:
    return grid.fixture_summary(spark, sf_dir)


SUMMARY_SQL = " union all ".join(f"select '{n}' as fixture, (select count(*) from ({encoded_sql(n)})) as records, {s.d}::int as d, {min(s.sizes)}::int as min_size, {max(s.sizes)}::int as max_size, '{s.size()}' as domain" for n, s in SPECS.items())

#: The six tables of the whole experiments, and all that is compared on them.
TABLES, RIVALS = ("F1", "F2", "F3", "F4", "F5", "F6"), [*MECHANISMS, "gen_mix_query"]

QUERIES = {
    **{f"x_{w}_{t}": _grid(t, w, RIVALS) for w in ("all3", "target", "skewed", "all2") for t in TABLES},
    **{f"x_ablation_{t}": _grid(t, "all3", ["adaptive", *ABLATIONS]) for t in TABLES},
    "x_bounds_F1": (_whole_bounds, None),
    **{f"x_records_{m}": _records("F7" if m in ("gen_mix", "relaxed_proj") else "F5", m) for m in MECHANISMS},
    "x_records_adaptive_F2": _records("F2", "adaptive"),
    "x_bounded_F5": _bounded_size("F5"),
    "x_all3": _errors("F5", ["adaptive", "fixed_round", "independent", "bayes_net", "span_tree", "rand_field"]),
    "x_all3_mixtures": _errors("F7", ["relaxed_proj", "gen_mix", "gen_mix_query"]),
    "x_target": _errors("F5", ["adaptive", "span_tree", "rand_field"], "target"),
    "x_skewed": _errors("F5", ["adaptive", "span_tree", "rand_field"], "skewed"),
    "x_all2": _errors("F5", ["adaptive", "span_tree", "rand_field"], "all2"),
    "x_norm_l2": _errors("F5", ["adaptive", "independent"], "all3", "l2"),
    "x_norm_linf": _errors("F5", ["adaptive", "independent"], "all3", "linf"),
    "x_trials": (_trials, None),
    "x_ablation": (_ablation, None),
    "x_relaxed_ablation": _errors("F7", ["adaptive", "O1_relaxed"]),
    "x_bounds": (_bounds, None),
    "x_capacity": (_capacity, None),
    "x_hyper": (_hyper, None),
    "x_summary": (_summary, SUMMARY_SQL),
    "x_budget": (_budget, "select unnest(['" + "', '".join(MECHANISMS) + "']) as mechanism, 1.0::double as share"),
    "x_gauss_expected": (_gauss_error, GAUSS_ERROR_SQL),
    "x_gauss_answers": (_gauss_answers, None),
    "x_transcript": (_transcript, None),
    "x_uncertainty": (_report, None),
    "x_generation": (_sampled, None),
    "x_source": (_source, "select 1000::bigint as n, 0::bigint as n_bad"),
}

#: Queries of hundreds of runs each.
WHOLE_GRIDS = {f"x_{w}_{t}" for w in ("all3", "target", "skewed", "all2", "ablation") for t in TABLES}
