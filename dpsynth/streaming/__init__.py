"""Streams of records: marginal counts by event time, and private releases of closed windows.

Counts add up over disjoint inputs, so a stream can keep a store.  Every release costs budget:
tumbling windows hold each record once; sliding ones hold it width / slide times.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator, Sequence

import pandas as pd
from pyspark.errors import AnalysisException
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from dpsynth.domain import DomainSpec, marginal_id
from dpsynth.functions import cell
from dpsynth.privacy.accountant import rho_gauss
from dpsynth.privacy.mechanisms import spread_release

EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def read_events(spark: SparkSession, folder: str, files_per_trigger: int = 1) -> DataFrame:
    """A stream of event files; ts becomes a timestamp, as watermarks need one."""
    stream = spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", files_per_trigger).parquet(folder)
    return stream.withColumn("ts", F.col("ts").cast("timestamp"))


def encode_events(events: DataFrame, spec: DomainSpec) -> DataFrame:
    """event_id, ts, user_id and the codes of a flat event (stream or table)."""
    ready = events.withColumns({"k": F.get_json_object("props", "$.k").cast("int"), "weekday_code": F.weekday("ts")})
    return ready.select("event_id", "ts", "user_id", *[F.expr(a.rule).cast("int").alias(f"{a.name}_code") for a in spec.attrs])


def coded(events: DataFrame, spec: DomainSpec) -> DataFrame:
    return events.select("event_id", "ts", "user_id", *[F.col(f"{a.name}_code").alias(a.name) for a in spec.attrs])


def window_marginals(codes: DataFrame, spec: DomainSpec, subset: tuple[int, ...], width: str = "1 day", slide: str | None = None, late: str = "1 hour") -> DataFrame:
    """start, marginal_id, cell, cnt per tumbling or sliding window; later rows than the watermark are dropped."""
    w = F.window("ts", width, slide) if slide else F.window("ts", width)
    counted = codes.withWatermark("ts", late).groupBy(w, cell(spec, subset).alias("cell")).agg(F.count("*").alias("cnt"))
    return counted.select(F.col("window.start").alias("start"), F.lit(marginal_id(subset)).cast("long").alias("marginal_id"), "cell", "cnt")


def session_lengths(events: DataFrame, gap: str = "30 minutes", late: str = "1 hour") -> DataFrame:
    """user_id, start, n: events of each session of a user."""
    return events.withWatermark("ts", late).groupBy("user_id", F.session_window("ts", gap)).agg(F.count("*").alias("n")).select("user_id", F.col("session_window.start").alias("start"), "n")


def first_events(events: DataFrame, late: str = "1 hour") -> DataFrame:
    """Repeated deliveries of an event within the watermark are dropped."""
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def capped(events: DataFrame, m: int) -> DataFrame:
    """At most m events of each user over the life of the stream: event_id, user_id, nth.

    State is one number per user; noise on what is counted later must be scaled by m.
    """

    def count(key: tuple, frames: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        seen = state.get[0] if state.exists else 0
        for f in frames:
            take = f.sort_values(["ts", "event_id"]).head(max(0, m - seen))
            if len(take):
                yield pd.DataFrame({"event_id": take["event_id"], "user_id": key[0], "nth": range(seen + 1, seen + len(take) + 1)})
                seen += len(take)
        state.update((seen,))

    return events.groupBy("user_id").applyInPandasWithState(count, "event_id long, user_id long, nth int", "seen int", "append", "NoTimeout")


class ReleaseLedger:
    """Releases by batch in a shared folder: a batch that is retried after a crash gets back the
    numbers it released before, so it neither draws nor pays twice.

    A release is a table; what it cost stands beside it, written last.
    """

    def __init__(self, spark: SparkSession, folder: str, rho: float):
        self.spark, self.folder, self.rho = spark, folder, rho

    def _read(self, kind: str) -> DataFrame | None:
        try:
            return self.spark.read.parquet(f"{self.folder}/{kind}")
        except AnalysisException as e:
            if e.getCondition() != "PATH_NOT_FOUND":
                raise
            return None

    def costs(self) -> dict[int, float]:
        found = self._read("cost")
        return {} if found is None else {r["batch"]: r["rho"] for r in found.select("batch", "rho").collect()}

    @property
    def used(self) -> float:
        return sum(self.costs().values())

    def keep(self, batch: int, exact: DataFrame) -> None:
        """Closed windows with exact counts, for the release that they are due in.  Never published."""
        exact.write.mode("overwrite").parquet(f"{self.folder}/exact/batch={batch}")

    def kept(self) -> DataFrame | None:
        return self._read("exact")

    def release(self, batch: int, cost: float, draw: Callable[[], DataFrame]) -> DataFrame:
        costs, at = self.costs(), f"{self.folder}/noisy/batch={batch}"
        if batch not in costs:
            if sum(costs.values()) + cost > self.rho * (1 + 1e-12):
                raise RuntimeError(f"batch {batch} would pass the budget")
            draw().write.mode("overwrite").parquet(at)
            self.spark.createDataFrame([(float(cost),)], "rho double").coalesce(1).write.mode("overwrite").parquet(f"{self.folder}/cost/batch={batch}")
        return self.spark.read.parquet(at)


def releasing(ledger: ReleaseLedger, spec: DomainSpec, subset: tuple[int, ...], sigma: float, noise, sink: Callable[[int, DataFrame], None], schedule: Callable[[int], Sequence[float]], overlap: int = 1) -> Callable[[DataFrame, int], None]:
    """A foreachBatch function: windows get Gaussian noise on every cell and go to the sink.

    schedule: the windows (starts in seconds) that are released with a batch.  It must be public,
    made without the data: which windows have records is as secret as how many.  Windows due
    without records are noise around zero; closed windows that are not due yet are kept until
    they are.  overlap: windows that hold a record, width / slide of sliding ones; each of them
    is paid for.  noise: a NoiseSource, or anything with ``at`` (a column of noise).  Counts and
    noise stay on the executors; the driver sees the schedule only.
    """
    if overlap < 1:
        raise ValueError("a record is in one window at least")

    def run(batch: DataFrame, number: int) -> None:
        spark = batch.sparkSession
        ledger.keep(number, batch.select(F.col("start").cast("double").alias("start"), F.col("cell").cast("long").alias("cell"), "cnt"))
        due = sorted({float(x) for x in schedule(number)})
        if not due:
            return

        def draw() -> DataFrame:
            windows = spark.createDataFrame([(x,) for x in due], "start double")
            grid = windows.withColumn("cell", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(spec.size(subset) - 1).cast("long"))))
            counts = ledger.kept().groupBy("start", "cell").agg(F.sum("cnt").alias("cnt"))
            dense = grid.join(counts, ["start", "cell"], "left").withColumn("cnt", F.coalesce("cnt", F.lit(0).cast("long")))
            if hasattr(noise, "at"):
                return dense.select("start", "cell", (F.col("cnt") + noise.at(sigma, F.col("start"), F.col("cell"))).alias("value"))
            return spread_release(dense, sigma, None if noise.secure else 0).select("start", "cell", "value")

        sink(number, ledger.release(number, overlap * rho_gauss(sigma), draw))

    return run
