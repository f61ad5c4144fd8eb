import sys
from pathlib import Path

import pytest

sys.path.insert(0, str(Path(__file__).resolve().parent.parent))

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="session")
def spark(tmp_path_factory):
    from pyspark.sql import SparkSession

    s = (
        SparkSession.builder.master("local[4]")
        .config("spark.sql.shuffle.partitions", "4")
        .config("spark.ui.enabled", "false")
        .config("spark.driver.memory", "4g")
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.checkpoint.dir", str(tmp_path_factory.mktemp("checkpoints")))
        .getOrCreate()
    )
    s.sparkContext.setLogLevel("ERROR")
    yield s


@pytest.fixture(scope="session")
def duck():
    """Run DuckDB SQL over the given tables."""
    import duckdb

    c = duckdb.connect()
    for t in Path(SF).glob("*.parquet"):
        c.execute(f"create view {t.stem} as select * from read_parquet('{t}')")
    return lambda sql: c.execute(sql).df()


def same(a, b) -> None:
    """Two frames hold the same rows, in any order."""
    import pandas as pd

    assert sorted(a.columns) == sorted(b.columns)
    cols = sorted(a.columns)

    def cell(v):
        if v is None or v is pd.NA or v is pd.NaT or v != v:
            return "null"
        return str(round(float(v), 6) + 0.0) if isinstance(v, (int, float)) and not isinstance(v, bool) else str(v)

    rows = lambda d: sorted(tuple(map(cell, r)) for r in d[cols].astype(object).itertuples(index=False, name=None))
    assert rows(a) == rows(b)
