"""Scans and sinks."""

from __future__ import annotations

import tempfile
import uuid

import json

from pyspark.sql import DataFrame, SparkSession

from dpsynth.domain import AttrSpec, DomainSpec


def read_table(spark: SparkSession, sf_dir: str, name: str, cols: list[str] | None = None) -> DataFrame:
    """A given table; naming columns lets the scan read those only."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*cols) if cols else df


def read_as(spark: SparkSession, path: str, kind: str, schema: str) -> DataFrame:
    """csv, json or orc under an explicit schema: inference would read the data twice."""
    reader = spark.read.schema(schema)
    return reader.option("header", True).csv(path) if kind == "csv" else getattr(reader, kind)(path)


def write_as(df: DataFrame, path: str, kind: str = "parquet", mode: str = "errorifexists", by: list[str] | None = None) -> None:
    writer = df.write.mode(mode)
    if by:
        writer = writer.partitionBy(*by)
    (writer.option("header", True) if kind == "csv" else writer).format(kind).save(path)


def write_store(store: DataFrame, path: str, buckets: int = 64, mode: str = "errorifexists") -> None:
    """A store of marginals by bucket of its id: a query for one marginal reads one folder."""
    write_as(store.selectExpr("*", f"pmod(hash(marginal_id), {buckets}) as bucket"), path, mode=mode, by=["bucket"])


def domain_from_json(text: str) -> DomainSpec:
    """A domain from a JSON array of objects with name, size, rule and, optionally, labels."""
    return DomainSpec.of(*(AttrSpec(a["name"], int(a["size"]), a.get("rule", a["name"]), a.get("kind", "code"), tuple(a.get("labels", ()))) for a in json.loads(text)))


def domain_to_json(spec: DomainSpec) -> str:
    return json.dumps([{"name": a.name, "size": a.size, "rule": a.rule, "kind": a.kind, "labels": list(a.labels)} for a in spec.attrs])


def shared_folder(spark: SparkSession, name: str) -> str:
    """A new folder of this name beside the checkpoints, where all executors can read and write.

    ``spark.checkpoint.dir`` is read from the session; only a master on one machine may go
    without, and then gets a temporary folder.
    """
    base = spark.sparkContext.getCheckpointDir() or spark.conf.get("spark.checkpoint.dir", None)
    if base is None:
        if not (spark.sparkContext.master or "").startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        base = tempfile.mkdtemp(prefix="dpsynth-")
    return f"{base}/{name}-{uuid.uuid4().hex}"
