"""Queries that once made their rows up: they now run over the given customers, so more customers give other results."""

import duckdb
import pytest

from relmix import catalogue


@pytest.fixture(scope="module")
def folder(spark, sf, tmp_path_factory):
    """The customers with keys shifted by one and one balance of the tie's thousand."""
    path = str(tmp_path_factory.mktemp("customers"))
    spark.read.parquet(f"{sf}/customer.parquet").selectExpr("c_custkey + 1 AS c_custkey", "CASE WHEN c_custkey = 5 THEN 4500D ELSE c_acctbal END AS c_acctbal").coalesce(1).write.parquet(f"file://{path}/customer.parquet")
    return path


@pytest.mark.parametrize("name", ["assign_all_ties", "counter_capped", "source_planted", "udtf_components"])
def test_equal_to_sql_over_customers(spark, folder, name):
    frame = catalogue.queries()[name](spark, f"file://{folder}")
    con = duckdb.connect()
    con.execute(f"CREATE VIEW customer AS SELECT * FROM read_parquet('{folder}/customer.parquet/*.parquet')")
    want = con.execute(catalogue.oracle_sql()[name])
    names = [c[0] for c in want.description]
    got = sorted(map(tuple, frame.select(*names).collect()))
    assert got and got == sorted(want.fetchall())


def test_a_draw_for_every_customer(spark, sf):
    got = sorted(map(tuple, catalogue.queries()["udtf_sample"](spark, sf).collect()))
    assert sum(r[1] for r in got) == spark.read.parquet(f"{sf}/customer.parquet").count()
    assert [round(r[2]) for r in got] == [1, 4] or [round(r[2]) for r in got] == [1, 5]
    assert got == sorted(map(tuple, catalogue.queries()["udtf_sample"](spark, sf).collect()))
