"""Queries that once made up their data read given tables, and their rows follow these."""

import shutil
from pathlib import Path

import duckdb
import pytest
from conftest import SF, same

from dpsynth.queries import registered


@pytest.fixture(scope="module")
def odd(tmp_path_factory):
    """sf0.001 with lines of one flag and two line numbers, a null tax, and orders of one priority."""
    folder = tmp_path_factory.mktemp("odd")
    for f in Path(SF).glob("*.parquet"):
        shutil.copyfile(f, folder / f.name)
    c = duckdb.connect()
    lines = f"select * replace (case when l_linenumber = 2 then null else l_tax end as l_tax) from '{SF}/lineitem.parquet' where l_returnflag = 'A' and l_linenumber in (1, 2)"
    for name, rows in (("lineitem", lines), ("orders", f"select * from '{SF}/orders.parquet' where o_orderpriority = '2-HIGH' or o_custkey % 2 = 0")):
        c.execute(f"copy ({rows}) to '{folder / name}.parquet' (format parquet)")
    for f in folder.glob("*.parquet"):
        c.execute(f"create view {f.stem} as select * from read_parquet('{f}')")
    return str(folder), lambda sql: c.execute(sql).df()


def check(spark, odd, name):
    """The rows of the odd tables, which are those of SQL and not those of sf0.001."""
    run, sql = registered()[name]
    assert run(spark, SF).inputFiles()
    folder, duck = odd
    found = run(spark, folder).toPandas()
    same(found, duck(sql))
    with pytest.raises(AssertionError):
        same(found, run(spark, SF).toPandas())
    return found


def test_sizes_follow_the_records(spark, odd):
    found = check(spark, odd, "d_sizes").set_index("marginal_id")
    assert found["n_r"][1] == 3 and found["n_met"][1] == 1 and found["n_met"][4] == 2


def test_budgets_are_those_that_lines_ask_for(spark, odd):
    assert check(spark, odd, "o_accounting")["agrees"].all()


def test_cells_are_those_of_lines_empty_ones_too(spark, odd):
    found = check(spark, odd, "o_udtf_cells")
    assert len(found) == 12 and (found["cnt"][found["a"] > 0] == 0).all()


def test_closures_of_the_customers_sets(spark, odd):
    found = check(spark, odd, "o_udtf_closure").set_index("mask")["n"]
    assert found[2] > found[1] >= found[3]


def test_pairs_of_lines_of_an_order(spark, odd):
    found = check(spark, odd, "o_udtf_subsets").set_index(["a", "b"])["n"]
    assert found.idxmax() == (0, 1) and (found > 0).all()


def test_support_follows_the_filled_cells(spark, odd):
    found = set(check(spark, odd, "u_supported")["marginal_id"])
    assert 2 in found and 1 not in found


def test_variances_follow_the_releases(spark, odd):
    found = check(spark, odd, "u_variance")
    assert sorted(found["marginal_id"]) == [1, 2, *(1 << i for i in range(7, 15))]


def test_workload_of_the_attributes_that_vary(spark, odd):
    found = check(spark, odd, "w_all3")["marginal_id"]
    assert len(found) > 0 and not (found & 1).any()
