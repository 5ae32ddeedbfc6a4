import duckdb
import pytest

from relmix import catalogue
from relmix.workloads import planted, sweeps

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def test_every_sql_has_a_query():
    assert set(catalogue.oracle_sql()) <= set(catalogue.queries()) and len(catalogue.queries()) > 120


@pytest.fixture(scope="module")
def duck(sf):
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{sf}/{t}.parquet')")
    return con


@pytest.mark.parametrize("name", ["gmm1d_fused", "gmm1d_text", "gmm_full_rfm", "mlr_round3", "moe_round3", "params_from_stats", "suff_stats", "closure_loop", "segment_cube", "join_asof_model", "stream_tumbling"])
def test_queries_equal_sql(spark, sf, duck, name):
    got = catalogue.queries()[name](spark, sf).toPandas()
    want = duck.execute(catalogue.oracle_sql()[name]).df()
    assert sorted(got.columns) == sorted(want.columns)
    cols = sorted(got.columns)
    a, b = (f[cols].astype(object).where(f[cols].notna(), None).map(lambda v: round(float(v), 5) if isinstance(v, (int, float)) and not isinstance(v, bool) else str(v)) for f in (got, want))
    key = lambda f: sorted(map(tuple, f.to_numpy().tolist()), key=str)
    assert key(a) == key(b)


def test_planted_noise_is_standard_normal(spark):
    x = planted.gauss(spark, "/root/testdata/sf0.01", 4, 10).selectExpr("x2 - 8 * cos(2 * pi() * label * 2 / 10) AS z").agg({"z": "avg"}).head()[0]
    assert abs(x) < 0.02


def test_hybrid_round_and_modes_report_costs(spark, sf):
    rows = {r.plan: r for r in sweeps.hybrid_round(spark, sf, 500, 2, 3).collect()}
    assert rows["hybrid"].jobs > rows["fused"].jobs
    assert len({round(r.loglik, 5) for r in rows.values()}) == 1
