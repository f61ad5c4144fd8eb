"""A fitted model as a data source: spark.read.format("dpsynth").load()."""

from __future__ import annotations

import base64
import pickle
from collections.abc import Iterator

import numpy as np
from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from dpsynth.model.generate import make_slice, plan_columns
from dpsynth.model.graphical import GraphicalModel


class _Slice(InputPartition):
    def __init__(self, number: int, rows: int):
        self.number, self.rows = number, rows


class _Reader(DataSourceReader):
    def __init__(self, options: dict[str, str]):
        self.spec, self.columns = pickle.loads(base64.b64decode(options["model"]))
        self.n, self.seed, self.slice = int(options["n"]), int(options.get("seed", "0")), int(options.get("slicerows", str(1 << 16)))

    def partitions(self) -> list[_Slice]:
        return [_Slice(k, min(self.slice, self.n - at)) for k, at in enumerate(range(0, self.n, self.slice))]

    def read(self, partition: _Slice) -> Iterator[tuple]:
        yield from map(tuple, make_slice(self.columns, self.spec, partition.rows, np.random.default_rng([self.seed, partition.number])).tolist())


class SyntheticSource(DataSource):
    """Each partition makes its slice from (seed, number): reading twice gives the same records."""

    @classmethod
    def name(cls) -> str:
        return "dpsynth"

    def schema(self) -> str:
        spec, _ = pickle.loads(base64.b64decode(self.options["model"]))
        return ", ".join(f"{x} int" for x in spec.names)

    def reader(self, schema) -> DataSourceReader:
        return _Reader(dict(self.options))


def model_option(model: GraphicalModel) -> str:
    """The value of the option ``model``."""
    return base64.b64encode(pickle.dumps((model.spec, plan_columns(model)))).decode()


def register(spark: SparkSession) -> None:
    spark.dataSource.register(SyntheticSource)
