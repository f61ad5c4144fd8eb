"""Table functions over attribute sets, and Arrow functions for accounting on tables.

Spark binds such functions to a session, so they are made on demand.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations, product

import pandas as pd
from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F

from dpsynth.privacy.accountant import delta_of, rho_of


class Subsets:
    """All k-subsets of 0..d-1."""

    def eval(self, d: int, k: int) -> Iterator[tuple]:
        for r in combinations(range(d), k):
            yield (list(r),)


class Cells:
    """Every cell of a domain with its codes."""

    def eval(self, sizes: list) -> Iterator[tuple]:
        for cell, codes in enumerate(product(*(range(n) for n in sizes))):
            yield cell, list(codes)


class Closure:
    """Masks of the non-empty subsets of one set."""

    def eval(self, attrs: list) -> Iterator[tuple]:
        for n in range(1, len(attrs) + 1):
            for r in combinations(attrs, n):
                yield (sum(1 << i for i in r),)


def rho_for(eps: Column | str, delta: Column | str) -> Column:
    """rho of each budget in a column."""
    run = lambda e, d: pd.Series([rho_of(x, y) for x, y in zip(e, d, strict=True)])
    return F.pandas_udf(run, "double", F.PandasUDFType.SCALAR)(eps, delta)


def delta_for(rho: Column | str, eps: Column | str) -> Column:
    run = lambda r, e: pd.Series([delta_of(x, y) for x, y in zip(r, e, strict=True)])
    return F.pandas_udf(run, "double", F.PandasUDFType.SCALAR)(rho, eps)


def stouffer_arrow(z: Column | str) -> Column:
    """Combined z of a group, as a grouped-aggregate Arrow function."""
    return F.pandas_udf(lambda v: float(v.sum() / len(v) ** 0.5), "double", F.PandasUDFType.GROUPED_AGG)(z)


def stouffer_sql(z: str) -> Column:
    """The same from built-in aggregates, which have partial forms: the one to use at scale."""
    return F.sum(z) / F.sqrt(F.count(z))


def register(spark: SparkSession) -> None:
    """dp_subsets(d, k), dp_cells(sizes) and dp_closure(attrs) for SQL."""
    for name, cls, kind in (("dp_subsets", Subsets, "subset array<int>"), ("dp_cells", Cells, "cell bigint, codes array<int>"), ("dp_closure", Closure, "mask bigint")):
        spark.udtf.register(name, F.udtf(cls, returnType=kind))
