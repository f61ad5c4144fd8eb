"""The experiment tables: encoders over the given tables, and their sources as joins."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from dpsynth.domain import DomainSpec
from dpsynth.encode import bins, code, encode, flag, log_bins, nullable, vocab
from dpsynth.sources.tables import read_table

PRIORITIES = ["1-URGENT", "2-HIGH", "3-MEDIUM", "4-NOT SPECIFIED", "5-LOW"]
SEGMENTS = ["AUTOMOBILE", "BUILDING", "FURNITURE", "HOUSEHOLD", "MACHINERY"]
EVENT_TYPES = ["click", "error", "purchase", "signup", "view"]
SEQUENCE, BITS = 16, 16

_LINE = [
    vocab("returnflag", "l_returnflag", ["A", "N", "R"]), vocab("linestatus", "l_linestatus", ["F", "O"]), code("linenumber", "l_linenumber - 1", 7),
    code("discount", "round(l_discount * 100)", 11), code("tax", "round(l_tax * 100)", 9), code("quantity", "floor((l_quantity - 1) / 5)", 10),
    code("ship_year", "year(l_shipdate) - 1995", 7), code("ship_month", "month(l_shipdate) - 1", 12), bins("price", "l_extendedprice", 0, 105000, 16),
    vocab("orderstatus", "o_orderstatus", ["F", "O", "P"]), vocab("priority", "o_orderpriority", PRIORITIES), code("nation", "c_nationkey", 25),
    code("region", "n_regionkey", 5), code("part_type", "part_type_code", 6), code("ship_quarter", "quarter(l_shipdate) - 1", 4),
]
_ORDERS = [
    vocab("orderstatus", "o_orderstatus", ["F", "O", "P"]), vocab("priority", "o_orderpriority", PRIORITIES), code("order_year", "year(o_orderdate) - 1995", 7),
    code("order_month", "month(o_orderdate) - 1", 12), code("totalprice", "floor(o_totalprice / 1000)", 501), vocab("segment", "c_mktsegment", SEGMENTS),
    code("nation", "c_nationkey", 25), code("region", "n_regionkey", 5), bins("balance", "c_acctbal", -1000, 10000, 10),
]
_DOCS = [
    vocab("lang", "lang", ["de", "en", "es", "fr"]), vocab("source", "source", [f"src{i}" for i in range(20)], other=True), log_bins("chars", "n_chars", 16),
    nullable("quality", "quality", 2), nullable("toxic", "toxic", 2), flag("has_at", "text like '%@%'"), flag("has_digit", "text like '%0%' or text like '%1%'"),
    flag("has_license", "text like '%icense%'"), code("newlines", "length(text) - length(replace(text, chr(10), ''))", 10),
]

SPECS: dict[str, DomainSpec] = {
    "F1": DomainSpec.of(*_LINE),
    "F2": DomainSpec.of(*_ORDERS),
    "F3": DomainSpec.of(*(code(f"s{i}", f"s{i}", 6) for i in range(SEQUENCE))),
    "F4": DomainSpec.of(*(flag(f"b{i}", f"embedding[{i}] > 0") for i in range(BITS))),
    "F5": DomainSpec.of(*_DOCS),
    "F6": DomainSpec.of(vocab("event_type", "event_type", EVENT_TYPES), code("hour", "hour(ts)", 24), code("weekday", "weekday_code", 7), log_bins("value", "value", 10, 1), code("user_mod", "user_id % 10", 10), code("prop", "floor(k / 10)", 10)),
    "F7": DomainSpec.of(code("turn", "turn", 8), vocab("role", "role", ["assistant", "system", "user"]), log_bins("chars", "length(text)", 16)),
    "F8": DomainSpec.of(vocab("scheme", "scheme", ["http", "https"], other=True), log_bins("chars", "length(html)", 20), code("items", "(length(html) - length(replace(html, '<li', ''))) / 3", 10)),
}

_TYPES = ["ECONOMY", "LARGE", "MEDIUM", "PROMO", "SMALL", "STANDARD"]
_TYPE_CODE = "case " + " ".join(f"when p_type like '{t}%' then {i}" for i, t in enumerate(_TYPES)) + " else 0 end"

#: DuckDB sources of the fixtures; columns as source() gives them.
SQL_SOURCES = {
    "F1": f"(select *, {_TYPE_CODE} as part_type_code from lineitem join orders on l_orderkey = o_orderkey join customer on o_custkey = c_custkey join nation on c_nationkey = n_nationkey join part on l_partkey = p_partkey)",
    "F2": "(select * from orders join customer on o_custkey = c_custkey join nation on c_nationkey = n_nationkey)",
    "F3": "(select user_id, run, " + ", ".join(f"coalesce(max(c) filter (where pos = {i}), 5) as s{i}" for i in range(SEQUENCE)) + f" from (select user_id, rn // {SEQUENCE} as run, rn % {SEQUENCE} as pos, case event_type " + " ".join(f"when '{e}' then {i}" for i, e in enumerate(EVENT_TYPES)) + " else 5 end as c from (select *, row_number() over (partition by user_id order by ts, event_id) - 1 as rn from events)) group by user_id, run)",
    "F4": "(select list_prepend(0::float, embedding) as embedding from embeddings)",
    "F5": "(select d.*, l.quality, l.toxic from documents d left join labels l on d.doc_id = l.doc_id)",
    "F6": "(select *, isodow(ts) - 1 as weekday_code, cast(json_extract(props, '$.k') as int) as k from events)",
    "F7": "conversations",
    "F8": "(select *, regexp_extract(url, '^([a-z]+):', 1) as scheme from pages)",
}


def source(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """The raw rows of a fixture: dimension tables are joined by broadcast where Spark finds them
    small, else by shuffle; only the columns that the encoder reads are scanned."""
    t = lambda n, *c: read_table(spark, sf_dir, n, list(c) or None)
    if name in ("F1", "F2"):
        buyers = t("customer", "c_custkey", "c_nationkey", "c_mktsegment", "c_acctbal").join(t("nation", "n_nationkey", "n_regionkey"), F.expr("c_nationkey = n_nationkey"))
        orders = t("orders", "o_orderkey", "o_custkey", "o_orderstatus", "o_totalprice", "o_orderdate", "o_orderpriority").join(buyers, F.expr("o_custkey = c_custkey"))
        if name == "F2":
            return orders
        lines = t("lineitem", "l_orderkey", "l_partkey", "l_linenumber", "l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_returnflag", "l_linestatus", "l_shipdate")
        parts = t("part", "p_partkey", "p_type").select("p_partkey", F.expr(_TYPE_CODE).alias("part_type_code"))
        return lines.join(orders, F.expr("l_orderkey = o_orderkey")).join(parts, F.expr("l_partkey = p_partkey"))
    if name == "F3":
        return event_runs(t("events", "event_id", "ts", "user_id", "event_type"))
    if name == "F4":
        return t("embeddings", "embedding")
    if name == "F5":
        return t("documents", "doc_id", "text", "lang", "source", "n_chars").join(t("labels"), "doc_id", "left")
    if name == "F6":
        events = t("events").select("event_type", F.col("ts").cast("timestamp").alias("ts"), "value", "user_id", F.get_json_object("props", "$.k").cast("int").alias("k"))
        return events.withColumn("weekday_code", F.weekday("ts"))
    if name == "F7":
        return t("conversations", "turn", "role", "text")
    if name == "F8":
        return t("pages", "url", "html").withColumn("scheme", F.regexp_extract("url", "^([a-z]+):", 1))
    raise KeyError(name)


def event_runs(events: DataFrame) -> DataFrame:
    """Events of each user in time order, cut in runs of 16: user_id, run, s0..s15 (5 past the end)."""
    from pyspark.sql import Window

    nth = F.row_number().over(Window.partitionBy("user_id").orderBy("ts", "event_id")) - 1
    codes = F.expr("case event_type " + " ".join(f"when '{e}' then {i}" for i, e in enumerate(EVENT_TYPES)) + " else 5 end")
    at = events.select("user_id", nth.alias("rn"), codes.alias("c")).select("user_id", F.expr(f"rn div {SEQUENCE}").alias("run"), (F.col("rn") % SEQUENCE).alias("pos"), "c")
    return at.groupBy("user_id", "run").agg(*[F.coalesce(F.max(F.when(F.col("pos") == i, F.col("c"))), F.lit(5)).alias(f"s{i}") for i in range(SEQUENCE)])


def load(spark: SparkSession, sf_dir: str, name: str) -> tuple[DataFrame, DomainSpec]:
    """Encoded records of a fixture and their domain."""
    return encode(source(spark, sf_dir, name), SPECS[name]), SPECS[name]


def encoded_sql(name: str) -> str:
    """DuckDB text of the encoded fixture."""
    rule = lambda a: a.rule.replace("embedding[", "embedding[2 + ") if name == "F4" else a.rule
    return "select " + ", ".join(f"cast({rule(a)} as int) as {a.name}" for a in SPECS[name].attrs) + f" from {SQL_SOURCES[name]}"
