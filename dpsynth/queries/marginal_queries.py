"""Encoders, marginals, workloads and accuracy measures."""

from __future__ import annotations

from itertools import combinations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from dpsynth import encode as en
from dpsynth import workload as wl
from dpsynth.domain import marginal_id
from dpsynth.fixtures import SPECS, encoded_sql, load
from dpsynth.functions import cell_sql, uncell_sql
from dpsynth.operators import marginals as mg
from dpsynth.operators import metrics as mt
from dpsynth.sources.tables import read_table

Subset = tuple[int, ...]


def kway(name: str, k: int) -> list[Subset]:
    return list(combinations(range(SPECS[name].d), k))


def marginals_sql(name: str, subsets: list[Subset], source: str | None = None) -> str:
    """Counts of each subset by a GROUP BY of its own."""
    spec = SPECS[name]
    parts = [f"select cast({marginal_id(r)} as bigint) as marginal_id, {cell_sql(spec, r)} as cell, count(*) as cnt from e group by all" for r in subsets]
    return f"with e as ({source or encoded_sql(name)}) " + " union all ".join(parts)


def _encoded(name: str):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        codes, spec = load(spark, sf_dir, name)
        return codes.groupBy(*spec.names).agg(F.count("*").alias("cnt"))

    return run, f"select {', '.join(SPECS[name].names)}, count(*) as cnt from ({encoded_sql(name)}) group by all"


def _marginals(name: str, subsets: list[Subset], plan: str = "inline"):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        codes, spec = load(spark, sf_dir, name)
        return mg.marginals(codes, spec, subsets, plan)

    return run, marginals_sql(name, subsets)


def _store(name: str, k: int, plan: str = "auto"):
    subsets = wl.all_kway(SPECS[name], k).closure()

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        codes, spec = load(spark, sf_dir, name)
        return mg.MarginalStore.build(codes, spec, subsets, plan=plan).table

    return run, marginals_sql(name, subsets)


def _dense(spark: SparkSession, sf_dir: str) -> DataFrame:
    codes, spec = load(spark, sf_dir, "F7")
    return mg.marginal(codes, spec, (0, 1, 2), dense=True)


DENSE_SQL = f"with e as ({encoded_sql('F7')}), c as (select {cell_sql(SPECS['F7'], (0, 1, 2))} as cell, count(*) as cnt from e group by all) select r.range as cell, coalesce(c.cnt, 0) as cnt from range({SPECS['F7'].size()}) r left join c on r.range = c.cell"


def _weighted(spark: SparkSession, sf_dir: str) -> DataFrame:
    codes, spec = load(spark, sf_dir, "F2")
    counted = codes.groupBy("priority", "segment", "orderstatus").agg(F.count("*").alias("n"))
    return mg.marginal(counted, spec, (spec.index("priority"), spec.index("segment")), weight="n")


def _normalized(spark: SparkSession, sf_dir: str) -> DataFrame:
    codes, spec = load(spark, sf_dir, "F2")
    return mg.normalize(mg.marginals(codes, spec, kway("F2", 1))).select("marginal_id", "cell", F.round("freq", 9).alias("freq"))


def _merged(spark: SparkSession, sf_dir: str) -> DataFrame:
    codes, spec = load(spark, sf_dir, "F2")
    one, two = codes.where("order_month < 6"), codes.where("order_month >= 6")
    return mg.merge_store(mg.marginals(one, spec, kway("F2", 1)), mg.marginals(two, spec, kway("F2", 1)))


def _uncell(spark: SparkSession, sf_dir: str) -> DataFrame:
    codes, spec = load(spark, sf_dir, "F2")
    r = (1, 5, 7)
    one = mg.marginal(codes, spec, r)
    return one.select("cell", *[F.expr(uncell_sql(spec, r, i)).cast("int").alias(spec.attrs[i].name) for i in r], "cnt")


def _roundtrip(spark: SparkSession, sf_dir: str) -> DataFrame:
    codes, spec = load(spark, sf_dir, "F2")
    return en.recode(en.decode(codes, spec), spec).groupBy(*spec.names).agg(F.count("*").alias("cnt"))


def _decoded(spark: SparkSession, sf_dir: str) -> DataFrame:
    codes, spec = load(spark, sf_dir, "F2")
    return en.decode(codes, spec).groupBy("orderstatus", "priority", "segment").agg(F.count("*").alias("cnt"))


def _valid(spark: SparkSession, sf_dir: str) -> DataFrame:
    return en.validate(*load(spark, sf_dir, "F1"))


def _met(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """attr, met: how many values of each attribute the records hold, from the one-way marginals."""
    codes, spec = load(spark, sf_dir, name)
    ones = mg.marginals(codes, spec, kway(name, 1)).groupBy("marginal_id").agg(F.count("*").alias("met"))
    return ones.select(F.bit_count(F.col("marginal_id") - 1).alias("attr"), "met")


def _met_sql(name: str) -> str:
    """One row: v0, v1, ... in the order of the attributes."""
    return "select " + ", ".join(f"count(distinct {a}) as v{i}" for i, a in enumerate(SPECS[name].names)) + f" from ({encoded_sql(name)})"


def _domain(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sizes of all closure sets of F1, as declared and by the values that the records hold:
    products by higher-order functions."""
    spec = SPECS["F1"]
    met = _met(spark, sf_dir, "F1").agg(F.map_from_entries(F.collect_list(F.struct("attr", "met"))).alias("met"))
    sizes = F.array(*[F.lit(n).cast("long") for n in spec.sizes])
    sets = wl.closure_df(wl.all_kway(spec, 3).to_df(spark))
    chosen = F.filter(F.transform(sizes, lambda n, i: F.when(F.expr("1") == 1, F.struct(n.alias("n"), i.alias("i")))), lambda x: F.getbit("marginal_id", x["i"]) == 1)
    times = lambda n: F.aggregate(chosen, F.lit(1).cast("long"), lambda a, x: a * n(x))
    return sets.crossJoin(F.broadcast(met)).select("marginal_id", times(lambda x: x["n"]).alias("n_r"), times(lambda x: F.coalesce(F.element_at("met", x["i"]), F.lit(0).cast("long"))).alias("n_met"))


def _sizes_sql() -> str:
    spec = SPECS["F1"]
    cases = lambda of: " * ".join(f"case when (marginal_id >> {i}) & 1 = 1 then {n} else 1 end" for i, n in enumerate(of))
    met = cases(f"v{i}" for i in range(spec.d))
    return f"with s as (select distinct m.marginal_id from ({_closure_sql(15, 3)}) m), v as ({_met_sql('F1')}) select marginal_id, cast({cases(spec.sizes)} as bigint) as n_r, cast({met} as bigint) as n_met from s, v"


def _closure_sql(d: int, k: int) -> str:
    """Masks of all sets of one to k of d attributes."""
    one = f"select 1::bigint << range as m, range as i from range({d})"
    parts = []
    for n in range(1, k + 1):
        tables = ", ".join(f"({one}) t{j}" for j in range(n))
        less = " and ".join([f"t{j}.i < t{j + 1}.i" for j in range(n - 1)] or ["true"])
        parts.append(f"select {' | '.join(f't{j}.m' for j in range(n))} as marginal_id from {tables} where {less}")
    return " union all ".join(parts)


def _exact_sql(d: int, k: int) -> str:
    return f"select marginal_id from ({_closure_sql(d, k)}) where bit_count(marginal_id) = {k}"


def _kway_table(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All 3-sets of the attributes of F1 that vary in the records."""
    return wl.kway_of(_met(spark, sf_dir, "F1").where("met > 1").select("attr"), 3).select("marginal_id")


def _vary_sql() -> str:
    vary = " and ".join(f"(marginal_id & {1 << i} = 0 or v{i} > 1)" for i in range(15))
    return f"select marginal_id from ({_exact_sql(15, 3)}), ({_met_sql('F1')}) where {vary}"


def _target(spark: SparkSession, sf_dir: str) -> DataFrame:
    return wl.kway_df(spark, 15, 3).where(F.array_contains("attrs", 0)).select("marginal_id")


def _closure(spark: SparkSession, sf_dir: str) -> DataFrame:
    return wl.closure_df(wl.kway_df(spark, 15, 3))


def _weights(spark: SparkSession, sf_dir: str) -> DataFrame:
    w = wl.kway_df(spark, 15, 3).withColumn("weight", F.lit(1.0))
    return wl.weights_df(w, wl.closure_df(w))


def _merged_workload(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Copies of sets, made from pairs of line attributes, merged with summed weights."""
    lines = read_table(spark, sf_dir, "lineitem", ["l_linenumber", "l_quantity"])
    sets = lines.select(F.expr("shiftleft(1L, l_linenumber % 8) | 256").alias("marginal_id"), (F.col("l_quantity") / 10).alias("weight"))
    return sets.groupBy("marginal_id").agg(F.round(F.sum("weight"), 6).alias("weight"))


def _perturbed(codes: DataFrame) -> DataFrame:
    """The synthetic side of the measures: one column shifted by another, as SQL can say too."""
    return codes.withColumn("toxic", ((F.col("toxic") + F.col("chars")) % 3).cast("int"))


PERTURBED_SQL = f"select * replace (cast((toxic + chars) % 3 as int) as toxic) from ({encoded_sql('F5')})"


def _errors(norm: str):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        codes, spec = load(spark, sf_dir, "F5")
        pairs = kway("F5", 2)
        e = mt.per_query_error(mg.marginals(codes, spec, pairs), mg.marginals(_perturbed(codes), spec, pairs), norm)
        return e.select("marginal_id", F.round("err", 6).alias("err"))

    total = {"l1": "sum(g)", "l2": "sqrt(sum(g * g))", "linf": "max(g)"}[norm]
    a, b = marginals_sql("F5", kway("F5", 2)), marginals_sql("F5", kway("F5", 2), PERTURBED_SQL)
    return run, f"select marginal_id, round(cast({total} as double), 6) as err from (select coalesce(a.marginal_id, b.marginal_id) as marginal_id, abs(coalesce(a.cnt, 0) - coalesce(b.cnt, 0)) as g from ({a}) a full join ({b}) b on a.marginal_id = b.marginal_id and a.cell = b.cell) group by marginal_id"


def _workload_error(spark: SparkSession, sf_dir: str) -> DataFrame:
    codes, spec = load(spark, sf_dir, "F5")
    w = wl.all_kway(spec, 2)
    return spark.createDataFrame([(round(mt.workload_error(codes, _perturbed(codes), spec, w), 9),)], "error double")


def _results(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A table of trials in the shape of a grid's results, drawn from line items."""
    m = F.element_at(F.array(*[F.lit(x) for x in ("adaptive", "independent", "span_tree")]), (F.col("l_quantity") % 3).cast("int") + 1)
    lines = read_table(spark, sf_dir, "lineitem", ["l_returnflag", "l_linestatus", "l_linenumber", "l_quantity", "l_extendedprice"])
    return lines.select(F.col("l_returnflag").alias("dataset"), F.col("l_linestatus").alias("workload"), F.col("l_linenumber").cast("double").alias("epsilon"), m.alias("mechanism"), (F.col("l_extendedprice") / 1000).alias("error"))


RESULTS_SQL = "(select l_returnflag as dataset, l_linestatus as workload, cast(l_linenumber as double) as epsilon, case cast(l_quantity as int) % 3 when 0 then 'adaptive' when 1 then 'independent' else 'span_tree' end as mechanism, l_extendedprice / 1000 as error from lineitem)"
SUMMARY_SQL = f"(select dataset, workload, epsilon, mechanism, avg(error) as mean_error, min(error) as min_error, max(error) as max_error, count(*) as trials from {RESULTS_SQL} group by all)"
RATIO_SQL = f"(select a.dataset, a.workload, a.epsilon, a.mechanism, a.mean_error / b.mean_error as ratio from {SUMMARY_SQL} a join {SUMMARY_SQL} b on a.dataset = b.dataset and a.workload = b.workload and a.epsilon = b.epsilon and b.mechanism = 'adaptive' where a.mechanism <> 'adaptive')"


def _rounded(df: DataFrame, places: int = 6) -> DataFrame:
    return df.select(*[F.round(c, places).alias(c) if k == "double" else c for c, k in df.dtypes])


def _trials(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _rounded(mt.trial_summary(_results(spark, sf_dir)))


def _ratios(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _rounded(mt.ratio_table(mt.trial_summary(_results(spark, sf_dir))))


def _ratio_summary(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = mt.ratio_summary(mt.ratio_table(mt.trial_summary(_results(spark, sf_dir))))
    return _rounded(s.select("mechanism", "avg_ratio", "max_ratio", "geo_ratio", *[F.col("box")[i].alias(f"q{i}") for i in range(5)]))


def _wins(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _rounded(mt.win_share(mt.trial_summary(_results(spark, sf_dir))))


def _tightness(spark: SparkSession, sf_dir: str) -> DataFrame:
    lines = read_table(spark, sf_dir, "lineitem", ["l_returnflag", "l_quantity", "l_extendedprice"])
    return _rounded(mt.bound_tightness(lines.select(F.col("l_returnflag").alias("kind"), F.col("l_extendedprice").alias("bound"), (F.col("l_quantity") * 900).alias("err"))))


QUERIES = {
    **{f"enc_{n}": _encoded(n) for n in SPECS},
    **{f"m_1way_{n}": _marginals(n, kway(n, 1)) for n in SPECS},
    "m_2way_F2": _marginals("F2", kway("F2", 2)),
    "m_2way_F4": _marginals("F4", kway("F4", 2)),
    "m_3way_F6": _marginals("F6", kway("F6", 3)),
    "m_sets": _marginals("F2", kway("F2", 2), "grouping_sets"),
    "m_arrow": _marginals("F2", kway("F2", 2), "arrow"),
    "m_store_F5": _store("F5", 3),
    "m_store_F1": _store("F1", 2),
    "m_rollup": _store("F5", 3, "cover"),
    "m_dense_zero_cells": (_dense, DENSE_SQL),
    "m_weighted": (_weighted, f"select {cell_sql(SPECS['F2'], (1, 5))} as cell, count(*) as cnt from ({encoded_sql('F2')}) group by all"),
    "m_normalized": (_normalized, f"select marginal_id, cell, round(cnt / sum(cnt) over (partition by marginal_id), 9) as freq from ({marginals_sql('F2', kway('F2', 1))})"),
    "m_merged": (_merged, marginals_sql("F2", kway("F2", 1))),
    "d_cells": (_uncell, f"select {cell_sql(SPECS['F2'], (1, 5, 7))} as cell, priority, segment, region, count(*) as cnt from ({encoded_sql('F2')}) group by all"),
    "d_roundtrip": (_roundtrip, f"select *, count(*) as cnt from ({encoded_sql('F2')}) group by all"),
    "d_decoded": (_decoded, "select o_orderstatus as orderstatus, o_orderpriority as priority, c_mktsegment as segment, count(*) as cnt from orders join customer on o_custkey = c_custkey group by all"),
    "d_valid": (_valid, f"select count(*) as n, 0::bigint as n_bad from ({encoded_sql('F1')})"),
    "d_sizes": (_domain, _sizes_sql()),
    "w_all3": (_kway_table, _vary_sql()),
    "w_target": (_target, f"select marginal_id from ({_exact_sql(15, 3)}) where marginal_id & 1 = 1"),
    "w_closure": (_closure, _closure_sql(15, 3)),
    "w_weights": (_weights, f"select r.marginal_id, cast(sum(bit_count(r.marginal_id & s.marginal_id)) as double) as w_r from ({_closure_sql(15, 3)}) r, ({_exact_sql(15, 3)}) s group by r.marginal_id"),
    "w_merged": (_merged_workload, "select (1::bigint << cast(l_linenumber % 8 as int)) | 256 as marginal_id, round(sum(l_quantity / 10), 6) as weight from lineitem group by all"),
    "c_l1": _errors("l1"),
    "c_l2": _errors("l2"),
    "c_linf": _errors("linf"),
    "c_workload_error": (_workload_error, f"select round(sum(err) / (36 * (select count(*) from ({encoded_sql('F5')}))), 9) as error from ({_errors('l1')[1]})"),
    "c_trials": (_trials, f"select dataset, workload, epsilon, mechanism, round(mean_error, 6) as mean_error, round(min_error, 6) as min_error, round(max_error, 6) as max_error, trials from {SUMMARY_SQL}"),
    "c_ratios": (_ratios, f"select dataset, workload, epsilon, mechanism, round(ratio, 6) as ratio from {RATIO_SQL}"),
    "c_ratio_summary": (_ratio_summary, "select mechanism, round(avg(ratio), 6) as avg_ratio, round(max(ratio), 6) as max_ratio, round(exp(avg(ln(ratio))), 6) as geo_ratio, " + ", ".join(f"round(quantile_cont(ratio, {q}), 6) as q{i}" for i, q in enumerate((0.0, 0.25, 0.5, 0.75, 1.0))) + f" from {RATIO_SQL} group by mechanism"),
    "c_wins": (_wins, f"select mechanism, round(avg(case when best = 1 then 1.0 else 0.0 end), 6) as share from (select mechanism, rank() over (partition by dataset, workload, epsilon order by mean_error) as best from {SUMMARY_SQL}) group by mechanism"),
    "c_tightness": (_tightness, "select l_returnflag as kind, count(*) as n, count(*) filter (where l_extendedprice < l_quantity * 900) as failures, round(quantile_cont(l_extendedprice / (l_quantity * 900), 0.5) filter (where l_quantity > 0), 6) as median_ratio from lineitem group by all"),
}
