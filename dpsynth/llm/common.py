"""Helpers shared by the operators: tables, checkpoints, partition counts, row identity."""

from __future__ import annotations

import tempfile
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark import cloudpickle
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

#: ASCII white space as the contracts spell it: [\x20\x09-\x0D].
ASCII_SPACE = " \t\n\x0b\x0c\r"

#: The session's limit on the bytes of an Arrow batch, and what it is where nobody has set it.
BATCH_LIMIT = "spark.sql.execution.arrow.maxBytesPerBatch"
BATCH_BYTES = 4 << 20


def table(spark: SparkSession, sf_dir: str, name: str, *cols: str) -> DataFrame:
    """A given table, read with the columns that are asked for."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*cols) if cols else df


def cut(df: DataFrame) -> DataFrame:
    """Cut lineage with a reliable checkpoint in the folder that the cluster shares.

    ``spark.checkpoint.dir`` is read from the session.  Where neither it nor a checkpoint
    folder is set, a master on one machine gets a temporary folder; a cluster is an error, as
    its executors share no local folder.
    """
    sc = df.sparkSession.sparkContext
    if sc.getCheckpointDir() is None:
        shared = df.sparkSession.conf.get("spark.checkpoint.dir", None)
        if shared is None and not (sc.master or "").split("[")[0] == "local":
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        sc.setCheckpointDir(shared or tempfile.mkdtemp(prefix="dpsynth-checkpoint-"))
    return df.checkpoint(eager=True)


class Shipped:
    """A value that is broadcast with its classes, so that workers need no copy of this package.

    Broadcasts pickle classes by reference; so the bytes are made here, by value.  Each worker
    process opens them once and keeps the value beside its broadcast.
    """

    def __init__(self, spark: SparkSession, value: object):
        self.held = spark.sparkContext.broadcast(cloudpickle.dumps(value))

    @property
    def value(self):
        if not hasattr(self.held, "opened"):
            self.held.opened = cloudpickle.loads(self.held.value)
        return self.held.opened


def slices(batches: Iterator[pa.RecordBatch], most: int = BATCH_BYTES) -> Iterator[pa.RecordBatch]:
    """The batches in pieces of about ``most`` bytes: the objects made of a piece take several times
    that.  What Arrow holds of earlier batches goes back to the system, as workers outlive a stage."""
    pool = pa.default_memory_pool()
    for b in batches:
        step = max(1, b.num_rows * most // max(1, b.nbytes))
        for k in range(0, b.num_rows, step):
            yield b.slice(k, step)
        pool.release_unused()
    pool.release_unused()


def map_batches(df: DataFrame, run: Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]], schema: str | StructType) -> DataFrame:
    """``mapInArrow`` with batches bounded in bytes: texts differ in length, and the JVM, the pipe
    and the worker each hold a batch.  A limit that the session has set itself stays."""
    conf = df.sparkSession.conf
    if conf.get(BATCH_LIMIT, None) is None:
        conf.set(BATCH_LIMIT, str(BATCH_BYTES))
    return df.mapInArrow(run, schema)


def fresh(df: DataFrame, *names: str) -> list[str]:
    """The names, with underscores behind them until no column of ``df`` has one (case aside)."""
    taken, out = {c.lower() for c in df.columns}, []
    for name in names:
        while name.lower() in taken:
            name += "_"
        taken.add(name.lower())
        out.append(name)
    return out


def named(name: str) -> Column:
    """The top-level column of this very name, dots and backticks included."""
    return F.col("`" + name.replace("`", "``") + "`")


def columns_of(df: DataFrame) -> list[Column]:
    """All columns, as they are."""
    return [named(c) for c in df.columns]


def shuffle_width(spark: SparkSession) -> int:
    """The session's number of shuffle partitions."""
    return int(spark.conf.get("spark.sql.shuffle.partitions", "200"))


def byte_text(text: Column) -> Column:
    """The UTF-8 bytes of a text as one character each, ASCII and Latin capitals lowered.

    Valid UTF-8 stays injective but for the case of A-Z: the bytes C3..DE become E3..FE, and the
    number of continuation bytes after a lead byte still tells which of both it was.  So this
    is "lower-case A-Z only" for comparing, hashing and ASCII patterns, at the speed of lower().
    """
    return F.lower(F.decode(text.cast("binary"), "ISO-8859-1"))
