"""Workloads: weighted lists of attribute subsets, their closure and relevance weights.

Each computation has a driver form (workloads are small) and a relational twin for tables of sets.
"""

from __future__ import annotations

import random
from collections import defaultdict
from collections.abc import Iterable
from dataclasses import dataclass
from itertools import combinations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from dpsynth.domain import DomainSpec, marginal_id

Subset = tuple[int, ...]


@dataclass(frozen=True)
class Workload:
    """The list keeps copies: the error divides by its length."""

    queries: tuple[tuple[Subset, float], ...]

    def __post_init__(self):
        if any(c < 0 for _, c in self.queries):
            raise ValueError("weights are not negative")

    @classmethod
    def of(cls, queries: Iterable[tuple[Iterable[int], float]]) -> Workload:
        return cls(tuple((tuple(sorted(set(r))), float(c)) for r, c in queries))

    @classmethod
    def from_df(cls, df: DataFrame) -> Workload:
        """From columns attrs (array of attribute numbers) and weight; a workload fits the driver."""
        return cls.of((r["attrs"], r["weight"]) for r in df.select("attrs", "weight").collect())

    @property
    def k(self) -> int:
        return len(self.queries)

    def merged(self) -> dict[Subset, float]:
        """Distinct subsets with the sums of their weights."""
        out: dict[Subset, float] = defaultdict(float)
        for r, c in self.queries:
            out[r] += c
        return dict(out)

    def closure(self) -> list[Subset]:
        """Every non-empty subset of a set in the workload, by size, then attributes."""
        every = {s for r, _ in self.queries for n in range(1, len(r) + 1) for s in combinations(r, n)}
        return sorted(every, key=lambda s: (len(s), s))

    def weights(self) -> dict[Subset, float]:
        """Relevance of each closure set: overlaps with the workload's sets, weighted."""
        once = self.merged()
        return {r: sum(c * len(set(r).intersection(s)) for s, c in once.items()) for r in self.closure()}

    def to_df(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame([(i, marginal_id(r), list(r), c) for i, (r, c) in enumerate(self.queries)], "query_no int, marginal_id long, attrs array<int>, weight double")


def all_kway(spec: DomainSpec, k: int) -> Workload:
    return Workload.of((r, 1.0) for r in combinations(range(spec.d), k))


def target_workload(spec: DomainSpec, attr: int, k: int = 3) -> Workload:
    return Workload.of((r, 1.0) for r in combinations(range(spec.d), k) if attr in r)


def skewed_workload(spec: DomainSpec, count: int = 256, k: int = 3, seed: int = 42) -> Workload:
    """``count`` draws, with replacement, of k-sets in proportion to products of attribute weights,
    which are squares of exponential draws."""
    rng = random.Random(seed)
    weight = [rng.expovariate(1.0) ** 2 for _ in range(spec.d)]
    sets = list(combinations(range(spec.d), k))
    mass = []
    for r in sets:
        m = 1.0
        for i in r:
            m *= weight[i]
        mass.append(m)
    return Workload.of((r, 1.0) for r in rng.choices(sets, mass, k=count))


def pick_target(spec: DomainSpec, seed: int = 42) -> int:
    return random.Random(seed).randrange(spec.d)


def kway_df(spark: SparkSession, d: int, k: int) -> DataFrame:
    """All k-sets of 0..d-1 as rows attrs, marginal_id: theta joins of a short range with itself."""
    out = spark.range(d).select(F.array(F.col("id").cast("int")).alias("attrs"))
    for _ in range(k - 1):
        nxt = spark.range(d).select(F.col("id").cast("int").alias("nxt"))
        out = out.join(nxt, F.element_at("attrs", -1) < F.col("nxt")).select(F.concat("attrs", F.array("nxt")).alias("attrs"))
    return out.select("attrs", mask("attrs").alias("marginal_id"))


def kway_of(attrs: DataFrame, k: int) -> DataFrame:
    """The same of the attributes in a short table (column attr, an int), which is read once: it may
    be the result of a scan, so it is not joined with itself."""
    out = attrs.agg(F.sort_array(F.collect_list("attr")).alias("every")).select("every", F.expr("cast(array() as array<int>)").alias("attrs"))
    for _ in range(k):
        later = F.filter("every", lambda x: F.coalesce(x > F.try_element_at("attrs", F.lit(-1)), F.lit(True)))
        out = out.select("every", "attrs", F.explode(later).alias("nxt")).select("every", F.concat("attrs", F.array("nxt")).alias("attrs"))
    return out.select("attrs", mask("attrs").alias("marginal_id"))


def mask(attrs: str) -> Column:
    return F.aggregate(attrs, F.lit(0).cast("long"), lambda m, i: m.bitwiseOR(F.expr("1L") * F.pow(F.lit(2), i).cast("long")))


def closure_df(workload: DataFrame) -> DataFrame:
    """marginal_id of all non-empty subsets of the sets in ``workload`` (column marginal_id, attrs)."""
    masks = F.aggregate("attrs", F.array(F.lit(0).cast("long")), lambda acc, i: F.concat(acc, F.transform(acc, lambda m: m.bitwiseOR(F.pow(F.lit(2), i).cast("long")))))
    return workload.select(F.explode(masks).alias("marginal_id")).where("marginal_id > 0").distinct()


def weights_df(workload: DataFrame, closure: DataFrame) -> DataFrame:
    """marginal_id, w_r.  Both sides are sets of attributes, a few hundred rows, not data."""
    once = workload.groupBy(F.col("marginal_id").alias("s")).agg(F.sum("weight").alias("c"))
    shared = F.bit_count(F.col("marginal_id").bitwiseAND(F.col("s")))
    return closure.join(F.broadcast(once), shared >= 0, "inner").groupBy("marginal_id").agg(F.sum(F.col("c") * shared).alias("w_r"))
