"""Scans, joins, aggregations, windows, functions and streams as the methods use them."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from dpsynth import streaming as st
from dpsynth.domain import DomainSpec
from dpsynth.encode import encode
from dpsynth.fixtures import SPECS, encoded_sql, load
from dpsynth.functions import cell_sql, gauss, gauss_duck, udtfs
from dpsynth.operators import relational as rel
from dpsynth.operators.marginals import marginal, marginals
from dpsynth.queries.marginal_queries import kway, marginals_sql
from dpsynth.sources import tables as tb

Run = Callable[[SparkSession, str], DataFrame]


class Tables:
    """The given tables by name, scanned with the columns that are asked for."""

    def __init__(self, spark: SparkSession, sf_dir: str):
        self.spark, self.sf_dir = spark, sf_dir

    def __call__(self, name: str, *cols: str) -> DataFrame:
        return tb.read_table(self.spark, self.sf_dir, name, list(cols) or None)


def of(f: Callable[[Tables], DataFrame]) -> Run:
    return lambda spark, sf_dir: f(Tables(spark, sf_dir))


def rounded(df: DataFrame, places: int = 4) -> DataFrame:
    return df.select(*[F.round(c, places).alias(c) if k == "double" else F.col(c) for c, k in df.dtypes])


def agg(df: DataFrame, by: list[str], **cols) -> DataFrame:
    return rounded(df.groupBy(*by).agg(*[c.alias(n) for n, c in cols.items()]))


def rows() -> Column:
    return F.count("*")



# -- scans, sources, sinks -----------------------------------------------------------------------
def _round_trip(kind: str) -> Run:
    """customer written and read back under an explicit schema, in the folder that executors share."""

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        df = tb.read_table(spark, sf_dir, "customer", ["c_custkey", "c_mktsegment", "c_acctbal"])
        path = tb.shared_folder(spark, f"dpsynth-{kind}")
        tb.write_as(df, path, kind, "overwrite")
        back = tb.read_as(spark, path, kind, "c_custkey long, c_mktsegment string, c_acctbal double")
        return agg(back, ["c_mktsegment"], n=rows(), balance=F.sum("c_acctbal"))

    return run


def _store_sink(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A store written by bucket of its id and read back for one marginal: one folder is scanned."""
    codes, spec = load(spark, sf_dir, "F2")
    path = tb.shared_folder(spark, "dpsynth-store")
    tb.write_store(marginals(codes, spec, kway("F2", 1)), path, 8, "overwrite")
    return spark.read.parquet(path).where("marginal_id = 2 and bucket = pmod(hash(cast(2 as bigint)), 8)").select("marginal_id", "cell", "cnt")


def _views(spark: SparkSession, sf_dir: str) -> DataFrame:
    tb.read_table(spark, sf_dir, "nation").createOrReplaceTempView("dp_nation")
    tb.read_table(spark, sf_dir, "region").createOrReplaceTempView("dp_region")
    return spark.sql("select r_name, count(*) as n from dp_nation join dp_region on n_regionkey = r_regionkey group by r_name")


# -- joins -----------------------------------------------------------------------------------------
def _bands(t: Tables) -> DataFrame:
    bands = t.spark.createDataFrame([(i, 2000.0 * i, 2000.0 * (i + 1)) for i in range(-1, 6)], "band int, lo double, hi double")
    return agg(rel.range_join(t("customer", "c_acctbal"), "c_acctbal", bands, width=2000.0), ["band"], n=rows(), balance=F.sum("c_acctbal"))


def _as_of(t: Tables) -> DataFrame:
    e = t("events", "event_id", "user_id", "ts", "event_type")
    bought, seen = e.where("event_type = 'purchase'").select("event_id", "user_id", "ts"), e.where("event_type = 'view'")
    return rel.as_of(bought, seen, "user_id", "ts", {"event_id": "view_id"}).select("event_id", F.coalesce("view_id", F.lit(-1)).alias("view_id"))


def _salted(t: Tables) -> DataFrame:
    return agg(rel.salted_join(t("lineitem", "l_suppkey", "l_quantity", "l_linenumber"), t("supplier", "s_suppkey", "s_nationkey").withColumnRenamed("s_suppkey", "l_suppkey"), "l_suppkey"), ["s_nationkey"], n=rows(), quantity=F.sum("l_quantity"))


def _theta(t: Tables) -> DataFrame:
    a, b = (t("nation", "n_nationkey", "n_regionkey").select(F.col("n_nationkey").alias(f"k{s}"), F.col("n_regionkey").alias(f"r{s}")) for s in "ab")
    return a.join(b, (F.col("ra") == F.col("rb")) & (F.col("ka") < F.col("kb"))).groupBy("ra").agg(rows().alias("n"))


def _self_join(t: Tables) -> DataFrame:
    o = t("orders", "o_custkey", "o_orderpriority", "o_totalprice").groupBy("o_orderpriority", (F.col("o_custkey") % 5).alias("trial")).agg(F.avg("o_totalprice").alias("v"))
    a, b = o.where("trial = 0"), o.where("trial = 1")
    return rounded(a.alias("a").join(b.alias("b"), "o_orderpriority").select("o_orderpriority", (F.col("a.v") / F.col("b.v")).alias("ratio")))


# -- windows ---------------------------------------------------------------------------------------
def _ranks(t: Tables) -> DataFrame:
    w = Window.partitionBy("c_nationkey").orderBy("c_acctbal", "c_custkey")
    cols = {"rn": F.row_number(), "rk": F.rank(), "dr": F.dense_rank(), "q": F.ntile(4), "pr": F.percent_rank(), "cd": F.cume_dist()}
    return rounded(t("customer", "c_custkey", "c_nationkey", "c_acctbal").select("c_custkey", *[f.over(w).alias(k) for k, f in cols.items()]), 9)


def _offsets(t: Tables) -> DataFrame:
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    e = t("events", "event_id", "user_id", "ts", "event_type")
    return e.select("event_id", F.lag("event_type").over(w).alias("before"), F.lead("event_type").over(w).alias("after"), F.first_value("event_type").over(w).alias("first"))


def _running(t: Tables) -> DataFrame:
    w = Window.partitionBy("o_custkey").orderBy("o_orderkey").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return rounded(t("orders", "o_custkey", "o_orderkey", "o_totalprice").select("o_orderkey", F.sum("o_totalprice").over(w).alias("running")), 2)


def _hour_before(t: Tables) -> DataFrame:
    w = Window.partitionBy("user_id").orderBy("s").rangeBetween(-3600, 0)
    e = t("events", "event_id", "user_id", "ts").withColumn("s", F.unix_timestamp(F.col("ts").cast("timestamp")))
    return e.select("event_id", F.count("*").over(w).alias("n"))


# -- streams ---------------------------------------------------------------------------------------
def _stream(make: Callable[[DataFrame], DataFrame], mode: str = "append") -> Run:
    """Events replayed as files in the order of time through a query, to its end.

    Last files far in the future move the watermark past everything, so all windows close.
    """

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        base = tb.shared_folder(spark, "dpsynth-stream")
        events = tb.read_table(spark, sf_dir, "events")
        schema = events.select("event_id", "ts", "user_id", "event_type", "value", "props").schema
        last = spark.sql("select -1L as event_id, timestamp_ntz'2999-01-01' as ts, -1L as user_id, 'end' as event_type, 0.0D as value, '{}' as props")
        events.orderBy("ts").select(*schema.names).coalesce(1).write.mode("append").parquet(f"{base}/in")
        for days in range(2):  # the second one is met under the watermark that the first one sets
            last.withColumn("ts", F.expr(f"ts + interval {days} days")).select(*schema.names).coalesce(1).write.mode("append").parquet(f"{base}/in")
        writer = make(st.read_events(spark, f"{base}/in")).writeStream.outputMode(mode).option("checkpointLocation", f"{base}/state").trigger(availableNow=True)
        if mode == "append":
            writer = writer.format("parquet").option("path", f"{base}/out")
        else:  # each batch brings the whole result, or what has changed of it
            writer = writer.foreachBatch(lambda df, k: df.withColumn("batch", F.lit(k)).write.mode("append").parquet(f"{base}/out"))
        writer.start().awaitTermination()
        return spark.read.parquet(f"{base}/out")

    return run


_F6 = SPECS["F6"]


def _tumbling(e: DataFrame) -> DataFrame:
    codes = st.coded(st.encode_events(e, _F6), _F6)
    return st.window_marginals(codes, _F6, (0,)).where("start < timestamp'2900-01-01'").select(F.date_format("start", "yyyy-MM-dd").alias("day"), "cell", "cnt")


def _sliding(e: DataFrame) -> DataFrame:
    codes = st.coded(st.encode_events(e, _F6), _F6)
    return st.window_marginals(codes, _F6, (0,), "1 day", "12 hours").where("start < timestamp'2900-01-01'").select(F.date_format("start", "yyyy-MM-dd HH").alias("start"), "cell", "cnt")


def _sessions(e: DataFrame) -> DataFrame:
    # a filter on the user would be pushed below the watermark, which the last files then never move
    return st.session_lengths(e).where("start < timestamp'2900-01-01'").select("user_id", F.unix_timestamp("start").alias("start"), "n")


def _deduped(e: DataFrame) -> DataFrame:
    return st.first_events(e).where("user_id >= 0").select("event_id", "user_id")


def _capped(e: DataFrame) -> DataFrame:
    return st.capped(e.where("user_id >= 0"), 5).select("user_id", "nth")


def _latest(mode: str) -> Run:
    """Running counts by event type: every batch's rows are kept, the last one of each type counts."""

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        out = _stream(lambda e: e.where("user_id >= 0").groupBy("event_type").agg(rows().alias("n")), mode)(spark, sf_dir)
        return out.groupBy("event_type").agg(F.max_by("n", "batch").alias("n"))

    return run


#: The public grid of the releases: the days of January 2024, all due with the first batch that closes any.
_DAYS = [1_704_067_200.0 + 86_400 * k for k in range(31)]


class _HashNoise:
    """Noise that is a hash of window and cell, so that SQL can say it; for this query only."""

    def at(self, sigma: float, start: Column, at: Column) -> Column:
        return sigma * gauss(SEED, start.cast("long"), at)


SEED = 5


def _released(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Days of January by event type with Gaussian noise, empty days and types included."""
    base = tb.shared_folder(spark, "dpsynth-release")
    ledger, out = st.ReleaseLedger(spark, f"{base}/ledger", 10.0), f"{base}/out"
    codes = lambda e: st.coded(st.encode_events(e, _F6), _F6)
    tb.read_table(spark, sf_dir, "events").coalesce(1).write.mode("append").parquet(f"{base}/in")
    end = spark.sql("select -1L as event_id, timestamp_ntz'2999-01-01' as ts, -1L as user_id, 'end' as event_type, 0.0D as value, '{}' as props")
    for days in range(2):  # moves the watermark past January
        end.withColumn("ts", F.expr(f"ts + interval {days} days")).coalesce(1).write.mode("append").parquet(f"{base}/in")
    counts = st.window_marginals(codes(st.read_events(spark, f"{base}/in")), _F6, (0,))
    due = lambda batch: _DAYS if batch == 2 else []
    each = st.releasing(ledger, _F6, (0,), 1.0, _HashNoise(), lambda k, df: df.write.mode("overwrite").parquet(f"{out}/batch={k}"), due)
    counts.writeStream.outputMode("append").foreachBatch(each).option("checkpointLocation", f"{base}/state").trigger(availableNow=True).start().awaitTermination()
    return spark.read.parquet(out).select(F.col("start").cast("long").alias("start"), "cell", F.round("value", 6).alias("value"))


RELEASED_SQL = f"""with e as (select epoch(date_trunc('day', ts))::bigint as start, case event_type when 'click' then 0 when 'error' then 1 when 'purchase' then 2 when 'signup' then 3 else 4 end as cell from events),
c as (select start, cell, count(*) as cnt from e group by all),
g as (select 1704067200 + 86400 * d as start, cell::bigint as cell from range(31) a(d), range(5) b(cell))
select g.start::bigint as start, g.cell, round(coalesce(cnt, 0) + 1.0 * {gauss_duck(SEED, "g.start", "g.cell")}, 6) as value from g left join c on g.start = c.start and g.cell = c.cell"""


def _static_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Stream joined with a static vocabulary."""
    vocabulary = spark.createDataFrame([(c, i) for i, c in enumerate(("click", "error", "purchase", "signup", "view"))], "event_type string, code int")
    return _stream(lambda e: e.join(F.broadcast(vocabulary), "event_type").select("event_id", "code"))(spark, sf_dir)


# -- functions -------------------------------------------------------------------------------------
def _tabled_on(name: str, make: Callable[[Tables], DataFrame], sql: str) -> Run:
    """A table function beside rows of a given table, ``{rows}`` in the text."""

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        udtfs.register(spark)
        return spark.sql(sql, rows=make(Tables(spark, sf_dir)))

    run.__name__ = name
    return run


#: Two attributes of line items with three and four values.
_CELLS = DomainSpec.of(*(SPECS["F1"].attrs[SPECS["F1"].index(n)] for n in ("returnflag", "ship_quarter")))


def _cells_counted(t: Tables) -> DataFrame:
    return marginal(encode(t("lineitem", "l_returnflag", "l_shipdate"), _CELLS), _CELLS, (0, 1))


def _order_sizes(t: Tables) -> DataFrame:
    """Numbers of lines that an order has, and how many orders have each."""
    return t("lineitem", "l_orderkey").where("l_orderkey is not null").groupBy("l_orderkey").agg(rows().cast("int").alias("d")).groupBy("d").agg(rows().alias("n"))


_PRIORITY = SPECS["F2"].attrs[SPECS["F2"].index("priority")].rule


def _priority_sets(t: Tables) -> DataFrame:
    """Sets of priorities that a customer has ordered with, and how many customers have each."""
    sets = t("orders", "o_custkey", "o_orderpriority").groupBy("o_custkey").agg(F.sort_array(F.collect_set(F.expr(_PRIORITY))).alias("attrs"))
    return sets.groupBy("attrs").agg(rows().alias("n"))


_TAX = SPECS["F1"].attrs[SPECS["F1"].index("tax")].rule


def _accounting(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Line items ask for the nine budgets by their tax: rho of each budget by an Arrow function, and
    the delta that it implies again."""
    asked = tb.read_table(spark, sf_dir, "lineitem", ["l_tax"]).groupBy(F.expr(_TAX).alias("k")).agg(rows().alias("n"))
    eps = asked.select((F.pow(F.lit(10.0), (F.col("k") - 4) / 2)).alias("eps"), F.lit(1e-9).alias("delta"), "n")
    back = eps.withColumn("rho", udtfs.rho_for("eps", "delta")).withColumn("back", udtfs.delta_for("rho", "eps"))
    return back.select(F.round("eps", 6).alias("eps"), "n", (F.abs(F.col("back") / 1e-9 - 1) < 1e-6).alias("agrees"))


def _mutual(t: Tables) -> DataFrame:
    codes, spec = load(t.spark, t.sf_dir, "F2")
    return rounded(rel.mutual_information(marginals(codes, spec, [*kway("F2", 1), *kway("F2", 2)])), 6)


_M2 = marginals_sql("F2", [*kway("F2", 1), *kway("F2", 2)])
MUTUAL_SQL = f"with m as ({_M2}), h as (select marginal_id, sum(-p * log2(p)) as bits from (select marginal_id, cnt / sum(cnt) over (partition by marginal_id) as p from m) group by marginal_id), o as (select * from h where bit_count(marginal_id) = 1) select p.marginal_id as pair, round(sum(o.bits) - any_value(p.bits), 6) as bits from h p join o on p.marginal_id & o.marginal_id <> 0 where bit_count(p.marginal_id) = 2 group by p.marginal_id"

LINE = "l_orderkey", "l_linenumber", "l_quantity", "l_extendedprice", "l_discount", "l_returnflag", "l_linestatus", "l_shipdate"
DAY = "date_trunc('day', ts)"

QUERIES = {
    "o_scan_parquet": (of(lambda t: agg(t("lineitem", "l_returnflag", "l_quantity"), ["l_returnflag"], n=rows(), q=F.sum("l_quantity"))), "select l_returnflag, count(*) as n, round(sum(l_quantity), 4) as q from lineitem group by all"),
    **{f"o_roundtrip_{k}": (_round_trip(k), "select c_mktsegment, count(*) as n, round(sum(c_acctbal), 4) as balance from customer group by all") for k in ("csv", "json", "orc")},
    "o_store_sink": (_store_sink, f"select * from ({marginals_sql('F2', [(1,)])})"),
    "o_views": (_views, "select r_name, count(*) as n from nation join region on n_regionkey = r_regionkey group by r_name"),
    "o_text_features": (of(lambda t: t("documents", "doc_id", "text").select("doc_id", F.contains("text", F.lit("@")).alias("has_at"), F.length("text").cast("long").alias("chars"), F.regexp_count("text", F.lit("[0-9]")).cast("long").alias("digits"))), "select doc_id, contains(text, '@') as has_at, length(text) as chars, len(regexp_extract_all(text, '[0-9]'))::bigint as digits from documents"),
    "o_page_features": (of(lambda t: t("pages", "url", "html").groupBy(F.parse_url("url", F.lit("PROTOCOL")).alias("scheme")).agg(rows().alias("n"), F.sum(F.length("html")).alias("chars"))), "select regexp_extract(url, '^([a-z]+):', 1) as scheme, count(*) as n, sum(length(html))::bigint as chars from pages group by all"),
    "o_projection": (of(lambda t: rounded(t("lineitem", *LINE).select("l_orderkey", "l_linenumber", (F.col("l_extendedprice") * (1 - F.col("l_discount"))).alias("net")))), "select l_orderkey, l_linenumber, round(l_extendedprice * (1 - l_discount), 4) as net from lineitem"),
    "o_filters": (of(lambda t: t("lineitem", *LINE).where("l_discount between 0.02 and 0.08 and l_returnflag in ('A', 'R') and l_linestatus rlike '^[FO]$' and l_quantity < 30").groupBy("l_returnflag").agg(rows().alias("n"))), "select l_returnflag, count(*) as n from lineitem where l_discount between 0.02 and 0.08 and l_returnflag in ('A', 'R') and l_quantity < 30 group by all"),
    "o_conditional": (of(lambda t: t("documents", "doc_id").join(t("labels"), "doc_id", "left").select(F.coalesce(F.nullif("quality", F.lit(0)), F.lit(9)).alias("q"), F.when(F.col("toxic").isNull(), 2).otherwise(F.col("toxic")).alias("t")).groupBy("q", "t").agg(rows().alias("n"))), "select coalesce(nullif(quality, 0), 9) as q, case when toxic is null then 2 else toxic end as t, count(*) as n from documents d left join labels l on d.doc_id = l.doc_id group by all"),
    "o_sub_population": (lambda s, d: (lambda x: marginals(x[0].where("returnflag = 2"), x[1], [(1, 3), (4, 9)]))(load(s, d, "F1")), marginals_sql("F1", [(1, 3), (4, 9)], f"select * from ({encoded_sql('F1')}) where returnflag = 2")),
    # joins
    "o_star_join": (of(lambda t: agg(t("orders", "o_custkey", "o_totalprice").join(F.broadcast(t("customer", "c_custkey", "c_nationkey")), F.expr("o_custkey = c_custkey")).join(F.broadcast(t("nation", "n_nationkey", "n_name")), F.expr("c_nationkey = n_nationkey")), ["n_name"], n=rows(), total=F.sum("o_totalprice"))), "select n_name, count(*) as n, round(sum(o_totalprice), 4) as total from orders join customer on o_custkey = c_custkey join nation on c_nationkey = n_nationkey group by all"),
    "o_merge_join": (of(lambda t: agg(t("lineitem", "l_orderkey", "l_quantity").join(t("orders", "o_orderkey", "o_orderpriority").hint("merge"), F.expr("l_orderkey = o_orderkey")), ["o_orderpriority"], n=rows(), q=F.sum("l_quantity"))), "select o_orderpriority, count(*) as n, round(sum(l_quantity), 4) as q from lineitem join orders on l_orderkey = o_orderkey group by all"),
    "o_hash_join": (of(lambda t: agg(t("lineitem", "l_orderkey", "l_quantity").join(t("orders", "o_orderkey", "o_orderstatus").hint("shuffle_hash"), F.expr("l_orderkey = o_orderkey")), ["o_orderstatus"], n=rows(), q=F.avg("l_quantity"))), "select o_orderstatus, count(*) as n, round(avg(l_quantity), 4) as q from lineitem join orders on l_orderkey = o_orderkey group by all"),
    "o_left_join": (of(lambda t: t("documents", "doc_id", "lang").join(t("labels"), "doc_id", "left").groupBy("lang", F.coalesce("quality", F.lit(-1)).alias("quality")).agg(rows().alias("n"))), "select lang, coalesce(quality, -1) as quality, count(*) as n from documents d left join labels l on d.doc_id = l.doc_id group by all"),
    "o_full_join": (of(lambda t: t("supplier", "s_nationkey").groupBy("s_nationkey").agg(rows().alias("s")).join(t("customer", "c_nationkey").where("c_nationkey < 20").groupBy("c_nationkey").agg(rows().alias("c")), F.expr("s_nationkey = c_nationkey"), "full").select(F.coalesce("s_nationkey", "c_nationkey").alias("k"), F.coalesce("s", F.lit(0)).alias("s"), F.coalesce("c", F.lit(0)).alias("c"))), "select coalesce(s_nationkey, c_nationkey) as k, coalesce(s, 0) as s, coalesce(c, 0) as c from (select s_nationkey, count(*) as s from supplier group by all) full join (select c_nationkey, count(*) as c from customer where c_nationkey < 20 group by all) on s_nationkey = c_nationkey"),
    "o_semi_join": (of(lambda t: t("customer", "c_custkey", "c_mktsegment").join(t("orders", "o_custkey"), F.expr("c_custkey = o_custkey"), "left_semi").groupBy("c_mktsegment").agg(rows().alias("n"))), "select c_mktsegment, count(*) as n from customer where c_custkey in (select o_custkey from orders) group by all"),
    "o_anti_join": (of(lambda t: t("customer", "c_custkey").join(t("orders", "o_custkey").where("o_custkey % 3 <> 0"), F.expr("c_custkey = o_custkey"), "left_anti")), "select c_custkey from customer where not exists (select 1 from orders where o_custkey = c_custkey and o_custkey % 3 <> 0)"),
    "o_theta_join": (of(_theta), "select a.n_regionkey as ra, count(*) as n from nation a join nation b on a.n_regionkey = b.n_regionkey and a.n_nationkey < b.n_nationkey group by all"),
    "o_range_join": (of(_bands), "select range::int as band, count(*) as n, round(sum(c_acctbal), 4) as balance from customer join range(-1, 6) on c_acctbal >= 2000 * range and c_acctbal < 2000 * (range + 1) group by all"),
    "o_as_of_join": (of(_as_of), "with v as (select user_id, ts, max(event_id) as event_id, count(*) as m from events where event_type = 'view' group by all) select p.event_id, coalesce((select v.event_id from v where v.user_id = p.user_id and v.ts <= p.ts order by v.ts desc limit 1), -1) as view_id from events p where event_type = 'purchase'"),
    "o_null_safe_join": (of(lambda t: t("documents", "doc_id").join(t("labels"), "doc_id", "left").select("quality").alias("a").join(t.spark.createDataFrame([(0, "bad"), (1, "good"), (None, "none")], "q int, name string").alias("b"), F.expr("quality <=> q")).groupBy("name").agg(rows().alias("n"))), "select case quality when 0 then 'bad' when 1 then 'good' else 'none' end as name, count(*) as n from documents d left join labels l on d.doc_id = l.doc_id group by all"),
    "o_self_join": (of(_self_join), "with o as (select o_orderpriority, o_custkey % 5 as trial, avg(o_totalprice) as v from orders group by all) select o_orderpriority, round(a.v / b.v, 4) as ratio from o a join o b using (o_orderpriority) where a.trial = 0 and b.trial = 1"),
    "o_salted_join": (of(_salted), "select s_nationkey, count(*) as n, round(sum(l_quantity), 4) as quantity from lineitem join supplier on l_suppkey = s_suppkey group by all"),
    # aggregations
    "o_hash_agg": (of(lambda t: agg(t("lineitem", *LINE), ["l_returnflag", "l_linestatus"], n=rows(), q=F.sum("l_quantity"), p=F.avg("l_extendedprice"), m=F.max("l_shipdate"))), "select l_returnflag, l_linestatus, count(*) as n, round(sum(l_quantity), 4) as q, round(avg(l_extendedprice), 4) as p, max(l_shipdate) as m from lineitem group by all"),
    "o_sequences": (of(lambda t: t("events", "user_id", "event_id", "event_type").groupBy("user_id").agg(F.array_sort(F.collect_list(F.struct("event_id", "event_type"))).alias("e")).select("user_id", F.concat_ws(",", F.transform("e", lambda x: x["event_type"])).alias("types"))), "select user_id, string_agg(event_type, ',' order by event_id) as types from events group by user_id"),
    "o_count_distinct": (of(lambda t: t("lineitem", "l_returnflag", "l_partkey", "l_suppkey").groupBy("l_returnflag").agg(F.countDistinct("l_partkey").alias("parts"), F.countDistinct("l_partkey", "l_suppkey").alias("pairs"))), "select l_returnflag, count(distinct l_partkey) as parts, count(distinct (l_partkey, l_suppkey)) as pairs from lineitem group by all"),
    "o_approx_distinct": (of(lambda t: t("lineitem", "l_partkey").agg((F.abs(F.approx_count_distinct("l_partkey", 0.02) / F.countDistinct("l_partkey") - 1) < 0.1).alias("close"))), "select true as close"),
    "o_cube": (of(lambda t: t("lineitem", "l_returnflag", "l_linestatus").cube("l_returnflag", "l_linestatus").agg(rows().alias("n"), F.grouping_id().cast("int").alias("gid"))), "select l_returnflag, l_linestatus, count(*) as n, grouping_id(l_returnflag, l_linestatus)::int as gid from lineitem group by cube (l_returnflag, l_linestatus)"),
    "o_rollup": (of(lambda t: rounded(t("orders", "o_orderstatus", "o_orderpriority", "o_totalprice").rollup("o_orderstatus", "o_orderpriority").agg(F.sum("o_totalprice").alias("total")), 2)), "select o_orderstatus, o_orderpriority, round(sum(o_totalprice), 2) as total from orders group by rollup (o_orderstatus, o_orderpriority)"),
    "o_grouping_sets": (of(lambda t: t("orders", "o_orderstatus", "o_orderpriority").groupingSets([["o_orderstatus"], ["o_orderpriority"]], "o_orderstatus", "o_orderpriority").agg(rows().alias("n"))), "select o_orderstatus, o_orderpriority, count(*) as n from orders group by grouping sets ((o_orderstatus), (o_orderpriority))"),
    "o_pivot": (of(lambda t: t("lineitem", "l_returnflag", "l_linestatus").groupBy("l_returnflag").pivot("l_linestatus", ["F", "O"]).agg(F.count(F.lit(1))).na.fill(0)), "select l_returnflag, count(*) filter (where l_linestatus = 'F') as \"F\", count(*) filter (where l_linestatus = 'O') as \"O\" from lineitem group by all"),
    "o_unpivot": (of(lambda t: rounded(t("customer", "c_custkey", "c_acctbal").withColumn("half", F.col("c_acctbal") / 2).unpivot(["c_custkey"], ["c_acctbal", "half"], "what", "value"))), "select c_custkey, 'c_acctbal' as what, round(c_acctbal, 4) as value from customer union all select c_custkey, 'half', round(c_acctbal / 2, 4) from customer"),
    "o_moments": (of(lambda t: agg(t("lineitem", *LINE), ["l_linestatus"], sd=F.stddev_samp("l_quantity"), vp=F.var_pop("l_quantity"), r=F.corr("l_quantity", "l_extendedprice"), c=F.covar_samp("l_quantity", "l_discount"))), "select l_linestatus, round(stddev_samp(l_quantity), 4) as sd, round(var_pop(l_quantity), 4) as vp, round(corr(l_quantity, l_extendedprice), 4) as r, round(covar_samp(l_quantity, l_discount), 4) as c from lineitem group by all"),
    "o_percentiles": (of(lambda t: agg(t("orders", "o_orderstatus", "o_totalprice"), ["o_orderstatus"], lo=F.percentile("o_totalprice", F.lit(0.25)), mid=F.median("o_totalprice"), hi=F.percentile("o_totalprice", F.lit(0.9)))), "select o_orderstatus, round(quantile_cont(o_totalprice, 0.25), 4) as lo, round(median(o_totalprice), 4) as mid, round(quantile_cont(o_totalprice, 0.9), 4) as hi from orders group by all"),
    "o_filtered_agg": (of(lambda t: t("orders", "o_orderpriority", "o_totalprice").groupBy("o_orderpriority").agg(F.count_if(F.col("o_totalprice") > 100000).alias("large"), F.expr("cast(sum(1) filter (where o_totalprice <= 100000) as bigint)").alias("small"))), "select o_orderpriority, count(*) filter (where o_totalprice > 100000) as large, count(*) filter (where o_totalprice <= 100000) as small from orders group by all"),
    "o_arg_max": (of(lambda t: t("orders", "o_custkey", "o_orderkey", "o_totalprice").groupBy((F.col("o_custkey") % 50).alias("g")).agg(F.max_by("o_orderkey", F.struct("o_totalprice", "o_orderkey")).alias("top"), F.min_by("o_orderkey", F.struct("o_totalprice", "o_orderkey")).alias("low"))), "select o_custkey % 50 as g, arg_max(o_orderkey, (o_totalprice, o_orderkey)) as top, arg_min(o_orderkey, (o_totalprice, o_orderkey)) as low from orders group by all"),
    "o_mutual_information": (of(_mutual), MUTUAL_SQL),
    # windows, sorts, sets
    "o_ranks": (of(_ranks), "select c_custkey, row_number() over w::int as rn, rank() over w::int as rk, dense_rank() over w::int as dr, ntile(4) over w::int as q, round(percent_rank() over w, 9) as pr, round(cume_dist() over w, 9) as cd from customer window w as (partition by c_nationkey order by c_acctbal, c_custkey)".replace(" over w::int", " over w")),
    "o_offsets": (of(_offsets), "select event_id, lag(event_type) over w as before, lead(event_type) over w as after, first_value(event_type) over w as first from events window w as (partition by user_id order by ts, event_id)"),
    "o_running_sum": (of(_running), "select o_orderkey, round(sum(o_totalprice) over (partition by o_custkey order by o_orderkey rows unbounded preceding), 2) as running from orders"),
    "o_range_frame": (of(_hour_before), "select event_id, count(*) over (partition by user_id order by floor(epoch(ts)) range between 3600 preceding and current row) as n from events"),
    "o_share": (of(lambda t: rounded(t("customer", "c_mktsegment", "c_nationkey").groupBy("c_nationkey", "c_mktsegment").agg(rows().alias("n")).withColumn("share", F.col("n") / F.sum("n").over(Window.partitionBy("c_nationkey"))), 9)), "select c_nationkey, c_mktsegment, n, round(n / sum(n) over (partition by c_nationkey), 9) as share from (select c_nationkey, c_mktsegment, count(*) as n from customer group by all)"),
    "o_sorted": (of(lambda t: t("lineitem", "l_orderkey", "l_linenumber", "l_quantity").repartitionByRange(8, "l_orderkey").sortWithinPartitions("l_orderkey", "l_linenumber").where("l_quantity > 45")), "select l_orderkey, l_linenumber, l_quantity from lineitem where l_quantity > 45"),
    "o_top_k": (of(lambda t: t("orders", "o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").offset(5).limit(10)), "select o_orderkey, o_totalprice from orders order by o_totalprice desc, o_orderkey limit 10 offset 5"),
    "o_top_per_group": (of(lambda t: rel.top_per_group(t("customer", "c_custkey", "c_nationkey", "c_acctbal"), "c_nationkey", [F.desc("c_acctbal"), F.asc("c_custkey")], 3).select("c_custkey", "c_nationkey")), "select c_custkey, c_nationkey from (select *, row_number() over (partition by c_nationkey order by c_acctbal desc, c_custkey) as k from customer) where k <= 3"),
    "o_union": (of(lambda t: t("supplier", "s_nationkey").withColumnRenamed("s_nationkey", "k").unionByName(t("customer", "c_nationkey").withColumnRenamed("c_nationkey", "k")).groupBy("k").agg(rows().alias("n"))), "select k, count(*) as n from (select s_nationkey as k from supplier union all select c_nationkey from customer) group by k"),
    "o_intersect_all": (of(lambda t: t("supplier", "s_nationkey").withColumnRenamed("s_nationkey", "k").intersectAll(t("customer", "c_nationkey").withColumnRenamed("c_nationkey", "k"))), "select s_nationkey as k from supplier intersect all select c_nationkey from customer"),
    "o_except_all": (of(lambda t: t("customer", "c_nationkey").withColumnRenamed("c_nationkey", "k").exceptAll(t("supplier", "s_nationkey").withColumnRenamed("s_nationkey", "k"))), "select c_nationkey as k from customer except all select s_nationkey from supplier"),
    "o_distinct": (of(lambda t: t("lineitem", "l_returnflag", "l_linestatus", "l_linenumber").distinct()), "select distinct l_returnflag, l_linestatus, l_linenumber from lineitem"),
    # functions
    "o_math": (of(lambda t: rounded(t("customer", "c_custkey", "c_acctbal").select("c_custkey", F.ln(F.abs("c_acctbal") + 1).alias("l"), F.sqrt(F.abs("c_acctbal")).alias("r"), F.pow(F.col("c_acctbal") / 1000, 2).alias("p"), F.bit_count("c_custkey").alias("b"), F.shiftleft("c_custkey", 3).alias("s"), F.width_bucket("c_acctbal", F.lit(-1000.0), F.lit(10000.0), F.lit(11)).cast("long").alias("w")), 6)), "select c_custkey, round(ln(abs(c_acctbal) + 1), 6) as l, round(sqrt(abs(c_acctbal)), 6) as r, round(pow(c_acctbal / 1000, 2), 6) as p, bit_count(c_custkey)::int as b, c_custkey << 3 as s, least(greatest(floor((c_acctbal + 1000) / 1000) + 1, 0), 12)::bigint as w from customer"),
    "o_strings": (of(lambda t: t("nation", "n_nationkey", "n_name").select("n_nationkey", F.lower(F.trim("n_name")).alias("low"), F.concat_ws("-", F.substring("n_name", 1, 3), F.length("n_name").cast("string")).alias("tag"), F.md5("n_name").alias("h"), F.regexp_replace("n_name", "[AEIOU]", "_").alias("v"), F.sha2("n_name", 256).alias("s"))), "select n_nationkey, lower(trim(n_name)) as low, substr(n_name, 1, 3) || '-' || length(n_name) as tag, md5(n_name) as h, regexp_replace(n_name, '[AEIOU]', '_', 'g') as v, sha256(n_name) as s from nation"),
    "o_dates": (of(lambda t: t("orders", "o_orderkey", "o_orderdate").select("o_orderkey", F.year("o_orderdate").alias("y"), F.quarter("o_orderdate").alias("q"), F.month("o_orderdate").alias("m"), F.weekday("o_orderdate").alias("d"), F.datediff("o_orderdate", F.lit("1995-01-01")).alias("days"))), "select o_orderkey, year(o_orderdate)::int as y, quarter(o_orderdate)::int as q, month(o_orderdate)::int as m, (isodow(o_orderdate) - 1)::int as d, date_diff('day', date '1995-01-01', o_orderdate::date)::int as days from orders"),
    "o_arrays": (of(lambda t: rounded(t("embeddings", "vec_id", "embedding").select("vec_id", F.aggregate("embedding", F.lit(0.0), lambda a, x: a + x.cast("double")).alias("total"), F.size(F.filter("embedding", lambda x: x > 0)).cast("long").alias("positive"), F.element_at("embedding", 1).cast("double").alias("first"), F.array_max("embedding").cast("double").alias("most")), 3)), "select vec_id, round(list_sum(list_transform(embedding, lambda x: x::double)), 3) as total, len(list_filter(embedding, lambda x: x > 0)) as positive, round(embedding[1]::double, 3) as first, round(list_max(embedding)::double, 3) as most from embeddings"),
    "o_explode": (of(lambda t: rounded(t("embeddings", "vec_id", "embedding").select("vec_id", F.posexplode("embedding").alias("pos", "x")).groupBy("pos").agg(F.sum(F.col("x").cast("double")).alias("total")), 3)), "select (i - 1)::int as pos, round(sum(embedding[i]::double), 3) as total from embeddings, range(1, 65) r(i) group by all"),
    "o_maps": (of(lambda t: t("events", "event_type", "user_id").groupBy((F.col("user_id") % 20).alias("g")).pivot("event_type", ["click", "view"]).agg(F.count(F.lit(1))).select("g", F.map_from_arrays(F.array(F.lit("click"), F.lit("view")), F.array("click", "view")).alias("m")).select("g", F.coalesce(F.element_at("m", "click"), F.lit(0)).alias("c"), F.size(F.map_keys(F.map_filter("m", lambda k, v: v > 5))).cast("long").alias("many"))), "select user_id % 20 as g, count(*) filter (where event_type = 'click') as c, ((count(*) filter (where event_type = 'click') > 5)::int + (count(*) filter (where event_type = 'view') > 5)::int)::bigint as many from events group by all"),
    "o_json": (of(lambda t: t("events", "event_id", "props").select("event_id", F.get_json_object("props", "$.k").cast("int").alias("k"), F.element_at(F.from_json("props", "map<string,int>"), "k").alias("k2"))), "select event_id, json_extract(props, '$.k')::int as k, json_extract(props, '$.k')::int as k2 from events"),
    "o_structs": (of(lambda t: t("nation").select(F.struct("n_nationkey", "n_name").alias("s"), "n_regionkey").select(F.col("s").withField("r", F.col("n_regionkey")).alias("s")).select("s.n_nationkey", "s.r")), "select n_nationkey, n_regionkey as r from nation"),
    "o_udtf_subsets": (_tabled_on("subsets", _order_sizes, "select subset[0] as a, subset[1] as b, sum(n) as n from {rows}, lateral dp_subsets(d, 2) group by 1, 2"), "with o as (select count(*) as d from lineitem where l_orderkey is not null group by l_orderkey), p as (select d, unnest(range(d)) as a from o), q as (select d, a, unnest(range(a + 1, d)) as b from p) select a::int as a, b::int as b, count(*) as n from q group by all"),
    "o_udtf_cells": (_tabled_on("cells", _cells_counted, "select c.cell, c.codes[0] as a, c.codes[1] as b, coalesce(r.cnt, 0L) as cnt from dp_cells(array(3, 4)) c left join {rows} r on c.cell = r.cell"), f"select range as cell, (range // 4)::int as a, (range % 4)::int as b, count(x) as cnt from range(12) left join (select 1 as x, {cell_sql(_CELLS, (0, 1))} as cell from (select {_CELLS.attrs[0].rule} as returnflag, {_CELLS.attrs[1].rule} as ship_quarter from lineitem)) on range = cell group by range"),
    "o_udtf_closure": (_tabled_on("closure", _priority_sets, "select mask, sum(n) as n from {rows}, lateral dp_closure(attrs) group by mask"), f"with s as (select o_custkey, bit_or(1::bigint << ({_PRIORITY})) as m from orders group by o_custkey) select range as mask, count(*) as n from s, range(1, 32) where m & range = range group by range"),
    "o_accounting": (_accounting, f"select round(pow(10.0, (k - 4) / 2), 6) as eps, count(*) as n, true as agrees from (select {_TAX} as k from lineitem) group by k"),
    # streams
    "s_tumbling": (_stream(_tumbling), f"select strftime({DAY}, '%Y-%m-%d') as day, event_type as cell, count(*) as cnt from (select ts, cast(event_type as bigint) as event_type from (select e.ts, case e.event_type when 'click' then 0 when 'error' then 1 when 'purchase' then 2 when 'signup' then 3 else 4 end as event_type from events e)) group by all"),
    "s_sliding": (_stream(_sliding), "with e as (select ts, cast(case event_type when 'click' then 0 when 'error' then 1 when 'purchase' then 2 when 'signup' then 3 else 4 end as bigint) as cell from events), h as (select time_bucket(interval '12 hours', ts, timestamp '1970-01-01') as b, cell from e), w as (select b as start, cell from h union all select b - interval '12 hours', cell from h) select strftime(start, '%Y-%m-%d %H') as start, cell, count(*) as cnt from w group by all"),
    "s_sessions": (_stream(_sessions), "with g as (select user_id, ts, case when ts - lag(ts) over (partition by user_id order by ts) < interval '30 minutes' then 0 else 1 end as new from events), s as (select user_id, ts, sum(new) over (partition by user_id order by ts rows unbounded preceding) as k from g) select user_id, floor(epoch(min(ts)))::bigint as start, count(*) as n from s group by user_id, k"),
    "s_deduplicated": (_stream(_deduped), "select event_id, user_id from events"),
    "s_capped": (_stream(_capped), "select user_id, cast(k as int) as nth from (select user_id, unnest(range(1, least(n, 5) + 1)) as k from (select user_id, count(*) as n from events group by user_id))"),
    "s_complete": (_latest("complete"), "select event_type, count(*) as n from events group by all"),
    "s_update": (_latest("update"), "select event_type, count(*) as n from events group by all"),
    "s_release": (_released, RELEASED_SQL),
    "s_static_join": (_static_join, "select event_id, case event_type when 'click' then 0 when 'error' then 1 when 'purchase' then 2 when 'signup' then 3 else 4 end::int as code from events"),
}
