"""Noise, choice, ledger, scores and bounds, with noise from hashes so that SQL can repeat them."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from dpsynth import uncertainty as un
from dpsynth import workload as wl
from dpsynth.domain import marginal_id
from dpsynth.fixtures import SPECS, load
from dpsynth.functions import udtfs
from dpsynth.functions import gauss, gauss_duck, gumbel_duck, laplace_duck, register, uncell_sql
from dpsynth.operators import marginals as mg
from dpsynth.privacy import mechanisms as me
from dpsynth.queries.marginal_queries import DENSE_SQL, _closure_sql, kway, marginals_sql
from dpsynth.sources.tables import read_table
from dpsynth.synth.baselines import gaussian_shares
from dpsynth.synth.rounds import HALF_NORMAL, score_cogroups, score_table

SEED, SIGMA = 42, 3.0


def _dense_store(spark: SparkSession, sf_dir: str, name: str, subsets) -> DataFrame:
    codes, spec = load(spark, sf_dir, name)
    return mg.densify(mg.marginals(codes, spec, subsets), spec, subsets)


def dense_sql(name: str, subsets) -> str:
    spec = SPECS[name]
    every = " union all ".join(f"select cast({marginal_id(r)} as bigint) as marginal_id, range as cell from range({spec.size(r)})" for r in subsets)
    return f"select e.marginal_id, e.cell, coalesce(c.cnt, 0) as cnt from ({every}) e left join ({marginals_sql(name, subsets)}) c on e.marginal_id = c.marginal_id and e.cell = c.cell"


def _release(kind: str):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        out = me.hash_release(_dense_store(spark, sf_dir, "F7", [(0, 1, 2)]), SIGMA, SEED, kind)
        return out.select("marginal_id", "cell", F.round("value", 6).alias("value"))

    draw = {"gauss": gauss_duck, "laplace": laplace_duck}[kind](SEED, "7", "cell")
    return run, f"select cast(7 as bigint) as marginal_id, cell, round(cnt + {SIGMA} * {draw}, 6) as value from ({DENSE_SQL})"


def _total(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Mass from noisy one-way tables: sums weighted by inverse variance."""
    subsets = kway("F7", 1)
    noisy = me.hash_release(_dense_store(spark, sf_dir, "F7", subsets), SIGMA, SEED)
    each = noisy.groupBy("marginal_id").agg(F.sum("value").alias("s"), F.count("*").alias("n"))
    return each.agg(F.round(F.sum(F.col("s") / F.col("n")) / F.sum(1 / F.col("n")), 6).alias("total"))


TOTAL_SQL = f"with v as (select marginal_id, sum(cnt + {SIGMA} * {gauss_duck(SEED, 'marginal_id', 'cell')}) as s, count(*) as n from ({dense_sql('F7', kway('F7', 1))}) group by marginal_id) select round(sum(s / n) / sum(1 / n), 6) as total from v"


def _measure_independent(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The measurements of the independent baseline at rho = 0.5: equal shares."""
    sigma = math.sqrt(1 / (2 * 0.5 / SPECS["F2"].d))
    out = me.hash_release(_dense_store(spark, sf_dir, "F2", kway("F2", 1)), sigma, SEED)
    return out.select("marginal_id", "cell", F.round("value", 6).alias("value"))


INDEPENDENT_SQL = f"select marginal_id, cell, round(cnt + {math.sqrt(1 / (2 * 0.5 / SPECS['F2'].d))!r} * {gauss_duck(SEED, 'marginal_id', 'cell')}, 6) as value from ({dense_sql('F2', kway('F2', 1))})"


def _query_gauss(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Answers of the Gaussian baseline to all pairs of F7 at rho = 0.5, optimal shares."""
    spec, w = SPECS["F7"], wl.all_kway(SPECS["F7"], 2)
    sd = spark.createDataFrame([(marginal_id(r), math.sqrt(1 / (2 * 0.5 * s))) for r, s in gaussian_shares(w, spec).items()], "marginal_id long, sigma double")
    dense = _dense_store(spark, sf_dir, "F7", list(w.merged())).join(F.broadcast(sd), "marginal_id")
    return dense.select("marginal_id", "cell", F.round(F.col("cnt") + F.col("sigma") * gauss(SEED, F.col("marginal_id"), F.col("cell")), 6).alias("value"))


QUERY_GAUSS_SQL = f"with d as ({dense_sql('F7', kway('F7', 2))}), n as (select marginal_id, count(*) as n from d group by marginal_id), s as (select marginal_id, sqrt(1 / (2 * 0.5 * pow(n, 2.0 / 3) / sum(pow(n, 2.0 / 3)) over ())) as sigma from n) select d.marginal_id, d.cell, round(cnt + sigma * {gauss_duck(SEED, 'd.marginal_id', 'd.cell')}, 6) as value from d join s on d.marginal_id = s.marginal_id"


def _weights(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame([(marginal_id(r), w) for r, w in wl.all_kway(SPECS["F7"], 3).weights().items()], "marginal_id long, w_r double")


CLOSURE7 = wl.all_kway(SPECS["F7"], 3).closure()


def _scores(kind: str):
    """New scores of all closure sets of F7 under the uniform model, or the product of exact one-way tables."""
    spec = SPECS["F7"]

    def frame(spark: SparkSession, sf_dir: str) -> DataFrame:
        dense = _dense_store(spark, sf_dir, "F7", CLOSURE7)
        n = F.sum("cnt").over(Window.partitionBy("marginal_id"))
        if kind == "uniform":
            cells = F.count("*").over(Window.partitionBy("marginal_id"))
            modelled = dense.select("marginal_id", "cell", (n / cells).alias("value"))
        else:
            ones = {i: dense.where(F.col("marginal_id") == marginal_id((i,))).select(F.col("cell").alias(f"c{i}"), (F.col("cnt") / n).alias(f"p{i}")) for i in range(spec.d)}
            modelled = None
            for r in CLOSURE7:
                part = dense.where(F.col("marginal_id") == marginal_id(r)).withColumn("n", n)
                value = F.col("n")
                for i in r:
                    part = part.withColumn(f"c{i}", F.expr(uncell_sql(spec, r, i))).join(F.broadcast(ones[i]), f"c{i}")
                    value = value * F.col(f"p{i}")
                one = part.select("marginal_id", "cell", value.alias("value"))
                modelled = one if modelled is None else modelled.unionByName(one)
        return score_table(dense, modelled, _weights(spark), SIGMA)

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        return frame(spark, sf_dir).select("marginal_id", F.round("l1", 6).alias("l1"), "n_r", "w_r", F.round("score", 6).alias("score"))

    return frame, run, f"select marginal_id, round(l1, 6) as l1, n_r, w_r, round(score, 6) as score from ({score_sql(kind)})"


def score_sql(kind: str) -> str:
    spec = SPECS["F7"]
    w = wl.all_kway(spec, 3).weights()
    weights = ", ".join(f"({marginal_id(r)}, {x!r}::double)" for r, x in w.items())
    if kind == "uniform":
        model = "select marginal_id, cell, cnt, sum(cnt) over (partition by marginal_id) / count(*) over (partition by marginal_id) as value from d"
    else:
        parts = []
        for r in CLOSURE7:
            joins = " ".join(f"join p p{i} on p{i}.i = {i} and p{i}.code = {uncell_sql(spec, r, i, 'd.cell')}" for i in r)
            parts.append(f"select d.marginal_id, d.cell, d.cnt, {' * '.join(f'p{i}.share' for i in r)} * (select sum(cnt) from d where marginal_id = 1) as value from d {joins} where d.marginal_id = {marginal_id(r)}")
        model = " union all ".join(parts)
    singles = " union all ".join(f"select {i} as i, cell as code, cnt / (select sum(cnt) from d where marginal_id = 1) as share from d where marginal_id = {1 << i}" for i in range(spec.d))
    return f"with d as ({dense_sql('F7', CLOSURE7)}), p as ({singles}), m as ({model}), w as (select * from (values {weights}) t(marginal_id, w_r)), l as (select marginal_id, sum(abs(cnt - value)) as l1, count(*) as n_r from m group by marginal_id) select cast(l.marginal_id as bigint) as marginal_id, cast(l1 as double) as l1, n_r, w_r, w_r * (l1 - {HALF_NORMAL * SIGMA!r} * n_r) as score from l join w on l.marginal_id = w.marginal_id"


_UNIFORM, _INDEPENDENT = _scores("uniform"), _scores("independent")


def _cogrouped(spark: SparkSession, sf_dir: str) -> DataFrame:
    """L1 distance of each closure set of F7 from the uniform model, by a cogrouped map."""
    dense = _dense_store(spark, sf_dir, "F7", CLOSURE7)
    w = Window.partitionBy("marginal_id")
    modelled = _dense_store(spark, sf_dir, "F7", CLOSURE7).select("marginal_id", "cell", (F.sum("cnt").over(w) / F.count("*").over(w)).alias("value"))
    return score_cogroups(dense, modelled).select("marginal_id", F.round("l1", 6).alias("l1"))


def _combined(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Combined z of the balances of each segment's customers: Arrow aggregate and built-in twin."""
    z = read_table(spark, sf_dir, "customer", ["c_mktsegment", "c_acctbal"]).select("c_mktsegment", (F.col("c_acctbal") / 5000 - 1).alias("z"))
    a = z.groupBy("c_mktsegment").agg(F.round(udtfs.stouffer_arrow("z"), 6).alias("arrow"))
    return a.join(z.groupBy("c_mktsegment").agg(F.round(udtfs.stouffer_sql("z"), 6).alias("built_in")), "c_mktsegment")


MOST = max(wl.all_kway(SPECS["F7"], 3).weights().values())


def _first_pick(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The main method's first choice under the product model, by hashed Gumbel noise."""
    return me.hash_select(_INDEPENDENT[0](spark, sf_dir).select("marginal_id", "score"), 0.5, MOST, SEED).select("marginal_id", F.round("key", 5).alias("key"))


def _fixed_pick(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The fixed-round synthesizer's first choice: pairs of F7, uniform model, older score."""
    s = _UNIFORM[0](spark, sf_dir).where(F.bit_count("marginal_id") == 2).select("marginal_id", (F.col("l1") - F.col("n_r")).alias("score"))
    return me.hash_select(s, 0.5, 1.0, SEED).select("marginal_id", F.round("key", 5).alias("key"))


def _select_all(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Choice among nations by the number of their customers."""
    scores = read_table(spark, sf_dir, "customer", ["c_nationkey"]).groupBy(F.col("c_nationkey").cast("long").alias("marginal_id")).agg(F.count("*").cast("double").alias("score"))
    return me.hash_select(scores, 0.1, 1.0, SEED).select("marginal_id", F.round("key", 6).alias("key"))


def _ledger(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Running cost of a sequence of releases, one for each supplier: 1/(2 sigma^2) + eps^2/8."""
    rows = read_table(spark, sf_dir, "supplier", ["s_suppkey", "s_nationkey"]).select(F.col("s_suppkey").alias("round"), "s_nationkey", (F.lit(10.0) + F.col("s_nationkey")).alias("sigma"), (F.col("s_nationkey") / 100).alias("eps"))
    register(spark)
    cost = F.expr("dp_rho_gauss(sigma) + dp_rho_exp(eps)")
    spent = F.sum("rho").over(Window.partitionBy("s_nationkey").orderBy("round").rowsBetween(Window.unboundedPreceding, 0))
    return rows.withColumn("rho", cost).select("round", F.round("rho", 9).alias("rho"), F.round(spent, 9).alias("spent"))


def _supported(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Closure sets of F1 inside one of the measured pairs: those whose records fill half of the cells."""
    codes, spec = load(spark, sf_dir, "F1")
    sizes = spark.createDataFrame([(marginal_id(r), spec.size(r)) for r in kway("F1", 2)], "marginal_id long, n_r long")
    filled = mg.marginals(codes, spec, kway("F1", 2)).groupBy("marginal_id").agg(F.count("*").alias("met"))
    measured = filled.join(F.broadcast(sizes), "marginal_id").where("2 * met >= n_r").select("marginal_id")
    return un.supported_df(wl.closure_df(wl.kway_df(spark, 15, 3)), measured)


_PAIRS = ", ".join(f"({marginal_id(r)}, {SPECS['F1'].size(r)})" for r in kway("F1", 2))
SUPPORTED_SQL = f"with f as (select marginal_id as s, count(*) as met from ({marginals_sql('F1', kway('F1', 2))}) group by marginal_id), m as (select f.s from f join (values {_PAIRS}) t(s, n_r) on f.s = t.s where 2 * met >= n_r) select marginal_id from ({_closure_sql(15, 3)}) c where exists (select 1 from m where c.marginal_id & s = c.marginal_id)"


_RELEASED = "shiftleft(1L, cast((l_linenumber - 1) % 7 as int)) | shiftleft(1L, cast(7 + l_suppkey % 8 as int))"


def _variance(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Line items as releases of a pair each, by line number and supplier, with a noise of their own."""
    lines = read_table(spark, sf_dir, "lineitem", ["l_linenumber", "l_suppkey", "l_quantity"])
    measured = lines.select(F.expr(_RELEASED).alias("marginal_id"), F.lit(6).cast("long").alias("n_r"), (F.lit(1.0) + F.col("l_quantity")).alias("sigma"))
    targets = wl.kway_df(spark, 15, 1).select("marginal_id", F.lit(2).cast("long").alias("n_r"))
    return un.variance_df(measured, targets).select("marginal_id", F.round("var", 9).alias("var"))


VARIANCE_SQL = "with m as (select (1::bigint << ((l_linenumber - 1) % 7)::int) | (1::bigint << (7 + l_suppkey % 8)::int) as s, 1.0 + l_quantity as sigma from lineitem), t as (select 1::bigint << range as marginal_id from range(15)) select marginal_id, round(1 / sum(2 / (6 * sigma * sigma)), 9) as var from t join m on marginal_id & s = marginal_id group by marginal_id"


def _round_pick(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rounds as orders of a customer: the last one of each."""
    rounds = read_table(spark, sf_dir, "orders", ["o_custkey", "o_orderkey"]).select(F.col("o_custkey").alias("marginal_id"), F.col("o_orderkey").alias("round"))
    return un.pick_round_df(rounds)


def _wavg(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Attribute 1 of F7 from noisy tables over {1}, {0,1} and {1,2}."""
    spec, sets = SPECS["F7"], [(1,), (0, 1), (1, 2)]
    noisy = me.hash_release(_dense_store(spark, sf_dir, "F7", sets), SIGMA, SEED)
    down = None
    for r in sets:
        one = noisy.where(F.col("marginal_id") == marginal_id(r)).groupBy(F.expr(uncell_sql(spec, r, 1)).alias("cell")).agg((F.sum("value") / spec.size(r)).alias("v"), (F.lit(1.0) / spec.size(r)).alias("w"))
        down = one if down is None else down.unionByName(one)
    return down.groupBy("cell").agg(F.round(F.sum("v") / F.sum("w"), 6).alias("value"))


def _wavg_sql() -> str:
    spec, sets = SPECS["F7"], [(1,), (0, 1), (1, 2)]
    parts = [f"select {uncell_sql(spec, r, 1)} as cell, sum(value) / {spec.size(r)} as v, 1.0::double / {spec.size(r)} as w from n where marginal_id = {marginal_id(r)} group by 1" for r in sets]
    return f"with n as (select marginal_id, cell, cnt + {SIGMA} * {gauss_duck(SEED, 'marginal_id', 'cell')} as value from ({dense_sql('F7', sets)})) select cell, round(sum(v) / sum(w), 6) as value from ({' union all '.join(parts)}) group by cell"


def _bounded(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events with at most five for each user: how many stay."""
    events = read_table(spark, sf_dir, "events", ["user_id", "event_id"])
    return me.bound_contributions(events, "user_id", 5).groupBy("user_id").agg(F.count("*").alias("n"))


QUERIES = {
    "p_gauss_release": _release("gauss"),
    "p_laplace_release": _release("laplace"),
    "p_exp_select": (_select_all, f"select marginal_id, round(score * 0.05 + {gumbel_duck(SEED, 'marginal_id', chr(39) + 'pick' + chr(39))}, 6) as key from (select cast(c_nationkey as bigint) as marginal_id, count(*) as score from customer group by all) order by key desc limit 1"),
    "p_ledger": (_ledger, "with r as (select s_suppkey as round, s_nationkey, 1 / (2 * pow(10.0 + s_nationkey, 2)) + pow(s_nationkey / 100, 2) / 8 as rho from supplier) select round, round(rho, 9) as rho, round(sum(rho) over (partition by s_nationkey order by round rows unbounded preceding), 9) as spent from r"),
    "p_bound_contributions": (_bounded, "select user_id, least(count(*), 5) as n from events group by user_id"),
    "e_total": (_total, TOTAL_SQL),
    "bl_independent_measure": (_measure_independent, INDEPENDENT_SQL),
    "bl_query_gauss": (_query_gauss, QUERY_GAUSS_SQL),
    "a_score_uniform": _UNIFORM[1:],
    "a_score_independent": _INDEPENDENT[1:],
    "a_first_pick": (_first_pick, f"select marginal_id, round(score * {0.5 / (2 * MOST)!r} + {gumbel_duck(SEED, 'marginal_id', chr(39) + 'pick' + chr(39))}, 5) as key from ({score_sql('independent')}) order by key desc limit 1"),
    "bl_fixed_first_pick": (_fixed_pick, f"select marginal_id, round((l1 - n_r) * 0.25 + {gumbel_duck(SEED, 'marginal_id', chr(39) + 'pick' + chr(39))}, 5) as key from ({score_sql('uniform')}) where bit_count(marginal_id) = 2 order by key desc limit 1"),
    "a_score_cogroup": (_cogrouped, f"select marginal_id, round(l1, 6) as l1 from ({score_sql('uniform')})"),
    "c_combined_z": (_combined, "select c_mktsegment, round(sum(c_acctbal / 5000 - 1) / sqrt(count(*)), 6) as arrow, round(sum(c_acctbal / 5000 - 1) / sqrt(count(*)), 6) as built_in from customer group by all"),
    "u_supported": (_supported, SUPPORTED_SQL),
    "u_variance": (_variance, VARIANCE_SQL),
    "u_round_pick": (_round_pick, "select o_custkey as marginal_id, max(o_orderkey) as round from orders group by o_custkey"),
    "u_weighted_average": (_wavg, _wavg_sql()),
}
