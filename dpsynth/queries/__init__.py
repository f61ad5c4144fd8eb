"""Named queries of the engine over the given tables, and their DuckDB twins.

Each module has QUERIES: name -> (function of session and folder, SQL or None).
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

Query = tuple[Callable[[SparkSession, str], DataFrame], str | None]


def registered() -> dict[str, Query]:
    from dpsynth.queries import marginal_queries, mechanism_queries, privacy_queries, relational_queries

    out: dict[str, Query] = {}
    for module in (marginal_queries, privacy_queries, mechanism_queries, relational_queries):
        if clash := out.keys() & module.QUERIES.keys():
            raise ValueError(f"two queries of one name: {clash}")
        out |= module.QUERIES
    return out
