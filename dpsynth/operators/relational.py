"""Relational operators that the methods lean on, where Spark has no single call for them."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def range_join(df: DataFrame, value: str, ranges: DataFrame, lo: str = "lo", hi: str = "hi", width: float = 1.0) -> DataFrame:
    """Rows with lo <= value < hi.  Both sides are dealt to buckets of ``width``, which turns the
    theta join into an equi-join; each range goes to every bucket that it touches."""
    bucket = lambda c: F.floor(c / width)
    spread = ranges.withColumn("_b", F.explode(F.sequence(bucket(F.col(lo)), bucket(F.col(hi)))))
    met = df.withColumn("_b", bucket(F.col(value))).join(spread, "_b")
    return met.where((F.col(value) >= F.col(lo)) & (F.col(value) < F.col(hi))).drop("_b")


def as_of(left: DataFrame, right: DataFrame, key: str, at: str, take: dict[str, str]) -> DataFrame:
    """Each left row with the latest right row of its key at or before its time.

    One union and one window: no row meets more than its predecessor.  ``take`` maps columns of
    the right side to their new names.
    """
    a = left.withColumns({"_side": F.lit(1), **{f"_r_{c}": F.lit(None).cast(right.schema[c].dataType) for c in take}})
    b = right.select(key, at, F.lit(0).alias("_side"), *[F.col(c).alias(f"_r_{c}") for c in take])
    w = Window.partitionBy(key).orderBy(at, "_side").rowsBetween(Window.unboundedPreceding, 0)
    both = a.unionByName(b, allowMissingColumns=True)
    seen = both.withColumns({new: F.last(F.when(F.col("_side") == 0, F.struct(f"_r_{c}")), ignorenulls=True).over(w)[f"_r_{c}"] for c, new in take.items()})
    return seen.where("_side = 1").select(*left.columns, *take.values())


def salted_join(big: DataFrame, small: DataFrame, key: str, salts: int = 16) -> DataFrame:
    """An equi-join whose hot keys are spread: the big side draws a salt from its row, the small
    side is there once for each salt."""
    salt = F.pmod(F.xxhash64(*big.columns), F.lit(salts))
    spread = small.withColumn("_salt", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(salts - 1).cast("long"))))
    return big.withColumn("_salt", salt).join(spread, [key, "_salt"]).drop("_salt")


def salted_sum(df: DataFrame, key: str, value: Column, salts: int = 16) -> DataFrame:
    """key, total by two aggregations, for aggregates that have no partial form of their own."""
    part = df.groupBy(key, F.pmod(F.xxhash64(*df.columns), F.lit(salts)).alias("_salt")).agg(F.sum(value).alias("_part"))
    return part.groupBy(key).agg(F.sum("_part").alias("total"))


def top_per_group(df: DataFrame, group: str, order: list[Column], k: int) -> DataFrame:
    return df.withColumn("_k", F.row_number().over(Window.partitionBy(group).orderBy(*order))).where(F.col("_k") <= k).drop("_k")


def entropy(store: DataFrame) -> DataFrame:
    """marginal_id, bits: entropy of each marginal of a store."""
    p = F.col("cnt") / F.sum("cnt").over(Window.partitionBy("marginal_id"))
    return store.withColumn("p", p).groupBy("marginal_id").agg(F.sum(-F.col("p") * F.log2("p")).alias("bits"))


def mutual_information(store: DataFrame) -> DataFrame:
    """pair, bits: H(a) + H(b) - H(a, b) for every pair in a store that has the one-way tables too."""
    h = entropy(store)
    ones = h.where(F.bit_count("marginal_id") == 1).select(F.col("marginal_id").alias("one"), F.col("bits").alias("h"))
    pairs = h.where(F.bit_count("marginal_id") == 2)
    inside = F.col("marginal_id").bitwiseAND(F.col("one")) != 0
    return pairs.join(F.broadcast(ones), inside).groupBy(F.col("marginal_id").alias("pair")).agg((F.sum("h") - F.first("bits")).alias("bits"))
