"""Every query with a twin in SQL gives the twin's rows; every other one runs."""

import pytest
from conftest import SF, same

from dpsynth.queries import registered

QUICK = {n: q for n, q in registered().items() if not n.startswith("x_") or n in ("x_summary", "x_budget", "x_gauss_expected", "x_bounded_F5", "x_source", "x_ablation", "x_bounds", "x_generation", "x_transcript", "x_uncertainty")}


@pytest.mark.parametrize("name", list(QUICK))
def test_query(spark, duck, name):
    run, sql = QUICK[name]
    found = run(spark, SF).toPandas()
    if sql:
        same(found, duck(sql))
    else:
        assert len(found) > 0


def test_entry(spark):
    import __spark_entry__ as e

    assert e.entry(spark).count() > 0
    assert e.oracle_sql().keys() <= e.queries().keys()
