"""Queries that show the methods on small cases do so on given tables, with results that SQL gives too."""

import duckdb
import pytest

from localcomm.plans import catalogue as cat

DIR = "/root/testdata/sf0.001"


@pytest.mark.parametrize("name", ["math_params", "three_graphs", "toy_ratio_cut"])
def test_small_cases_come_from_given_tables(spark, name):
    con = duckdb.connect()
    for t in ("part", "lineitem", "orders"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{DIR}/{t}.parquet'")
    got = cat.QUERIES[name](spark, DIR)
    assert any(p.endswith((".parquet", ".parquet/")) or "parquet" in p for p in got.inputFiles())
    order = lambda rows: sorted(rows, key=repr)
    assert order(tuple(r) for r in got.collect()) == order(con.execute(cat.ORACLES[name]).fetchall())
