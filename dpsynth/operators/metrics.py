"""Accuracy measures between stores of marginals, and summaries over trials."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from dpsynth.domain import DomainSpec, marginal_id
from dpsynth.operators.marginals import marginals
from dpsynth.workload import Workload

NORMS = ("l1", "l2", "linf")


def per_query_error(real: DataFrame, synth: DataFrame, norm: str = "l1") -> DataFrame:
    """marginal_id, err: distance of two sparse stores, unnormalized; a missing cell is a zero."""
    a, b = real.select("marginal_id", "cell", F.col("cnt").alias("x")), synth.select("marginal_id", "cell", F.col("cnt").alias("y"))
    gap = F.abs(F.coalesce("x", F.lit(0)) - F.coalesce("y", F.lit(0)))
    total = {"l1": F.sum(gap), "l2": F.sqrt(F.sum(gap * gap)), "linf": F.max(gap)}[norm]
    return a.join(b, ["marginal_id", "cell"], "full").groupBy("marginal_id").agg(total.cast("double").alias("err"))


def workload_error(real: DataFrame, synth: DataFrame, spec: DomainSpec, w: Workload, norm: str = "l1") -> float:
    """Weighted error of all queries of the workload over encoded records, divided by the length of
    the list and the number of real records.  Each table is scanned once."""
    spark = real.sparkSession
    errors = per_query_error(marginals(real, spec, w.merged()), marginals(synth, spec, w.merged()), norm)
    return store_error(errors, spark, w, real.count())


def store_error(errors: DataFrame, spark: SparkSession, w: Workload, n: int) -> float:
    weight = spark.createDataFrame([(marginal_id(r), c) for r, c in w.merged().items()], "marginal_id long, c double")
    total = errors.join(F.broadcast(weight), "marginal_id").agg(F.sum(F.col("c") * F.col("err"))).first()[0] or 0.0
    return total / (w.k * max(1, n))


def expected_l1(sigma: float, cells: int) -> float:
    """Expected L1 norm of Gaussian noise: the mean of a half-normal, once a cell."""
    return math.sqrt(2 / math.pi) * sigma * cells


def trial_summary(results: DataFrame) -> DataFrame:
    """Mean, least and greatest error of the trials of each setting and mechanism."""
    return results.groupBy("dataset", "workload", "epsilon", "mechanism").agg(F.avg("error").alias("mean_error"), F.min("error").alias("min_error"), F.max("error").alias("max_error"), F.count("*").alias("trials"))


def ratio_table(summary: DataFrame, main: str = "adaptive") -> DataFrame:
    """Each rival's mean error over that of the main mechanism in the same setting."""
    keys = ["dataset", "workload", "epsilon"]
    base = summary.where(F.col("mechanism") == main).select(*keys, F.col("mean_error").alias("base"))
    return summary.where(F.col("mechanism") != main).join(base, keys).select(*keys, "mechanism", (F.col("mean_error") / F.col("base")).alias("ratio"))


def ratio_summary(ratios: DataFrame) -> DataFrame:
    """Average, greatest and geometric mean of the ratios per rival, and their quartiles."""
    box = F.percentile("ratio", F.array(*[F.lit(q) for q in (0.0, 0.25, 0.5, 0.75, 1.0)]))
    return ratios.groupBy("mechanism").agg(F.avg("ratio").alias("avg_ratio"), F.max("ratio").alias("max_ratio"), F.exp(F.avg(F.ln("ratio"))).alias("geo_ratio"), box.alias("box"))


def win_share(summary: DataFrame) -> DataFrame:
    """Share of the settings in which each mechanism has the least error."""
    best = F.rank().over(Window.partitionBy("dataset", "workload", "epsilon").orderBy("mean_error"))
    won = summary.withColumn("best", best).groupBy("mechanism").agg(F.avg((F.col("best") == 1).cast("double")).alias("share"))
    return won


def bound_tightness(report: DataFrame) -> DataFrame:
    """Per kind: bounds, failures, median of bound over true error."""
    return report.groupBy("kind").agg(F.count("*").alias("n"), F.count_if(F.col("bound") < F.col("err")).alias("failures"), F.percentile(F.expr("case when err > 0 then bound / err end"), F.lit(0.5)).alias("median_ratio"))
