import itertools
import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from relmix.evaluate import clustering as C
from relmix.evaluate.meter import Meter, model_gap, scaling_slope
from relmix.functions.udfs import mvn_logpdf, register_npdf
from relmix.models.families import ExpertMixture, Gaussian, LinearMixture, gaussian1d
from relmix.operators import joins as J
from relmix.operators.features import minmax, zscore
from relmix.view.model_view import ModelView, information_criteria, versions

VIEW = ModelView(Gaussian(1), gaussian1d([0.3, 0.7], [0.0, 4.0], [1.0, 2.0]))


@pytest.fixture(scope="module")
def points(spark):
    return spark.createDataFrame([(i, i / 7 - 3) for i in range(60)], "tid bigint, x0 double")


def test_posterior_density_and_entropy(points):
    sums = VIEW.posterior(points).groupBy("tid").agg(F.sum("p").alias("s")).collect()
    assert all(abs(r.s - 1) < 1e-12 for r in sums)
    for r in VIEW.density(points).collect():
        x = r.tid / 7 - 3
        want = 0.3 * math.exp(-x * x / 2) / math.sqrt(2 * math.pi) + 0.7 * math.exp(-((x - 4) ** 2) / 8) / (2 * math.sqrt(2 * math.pi))
        assert abs(r.density - want) < 1e-12
    assert all(0 <= r.entropy <= math.log(2) + 1e-12 for r in VIEW.uncertainty(points).collect())
    even = ModelView(Gaussian(1), gaussian1d([0.25] * 4, [1.0] * 4, [1.0] * 4))
    assert abs(even.uncertainty(points).head().entropy - math.log(4)) < 1e-12


def test_mahalanobis_with_identity_is_distance(spark):
    view = ModelView(Gaussian(2), {"weight": np.array([1.0]), "mu": np.zeros((1, 2)), "sigma": np.eye(2)[None]})
    row = view.uncertainty(spark.createDataFrame([(1, 3.0, 4.0)], "tid int, x0 double, x1 double")).head()
    assert abs(row.min_mahalanobis - 5) < 1e-12


def test_far_rows_do_not_underflow(spark):
    far = spark.createDataFrame([(1, 1e4), (2, -1e4)], "tid bigint, x0 double")
    assert [round(sum(r.p), 9) for r in VIEW.scored(far).collect()] == [1.0, 1.0]


def test_inference_plan_has_no_exchange_and_pushes_filters(spark, sf):
    from relmix.catalogue.common import customers

    scored = VIEW.posterior(customers(spark, sf)).filter("tid = 7")
    plan = scored._jdf.queryExecution().executedPlan().toString()
    assert "Exchange" not in plan and "EqualTo(c_custkey,7)" in plan


def test_versions_round_trip(spark, tmp_path):
    path = f"file://{tmp_path}/m"
    linear = ModelView(LinearMixture(1), {"weight": np.array([0.4, 0.6]), "beta": np.array([[1.0, 2.0], [3.0, 4.0]]), "var": np.array([0.25, 1.0])})
    expert = ModelView(ExpertMixture(1), {"theta": np.array([[1.0, 0.0], [-1.0, 0.0]]), "beta": np.array([[1.0, 2.0], [3.0, 4.0]]), "var": np.array([0.25, 1.0])})
    for n, view in enumerate((VIEW, linear, expert), 1):
        assert view.save(spark, path) == n
        back = ModelView.load(spark, path)
        assert type(back.family) is type(view.family) and all(np.allclose(back.params[k], view.params[k]) for k in view.params)
    assert versions(spark, path) == [1, 2, 3] and ModelView.load(spark, path, 1).k() == 2


def test_predictions(spark):
    rows = spark.createDataFrame([(1, 2.0)], "tid int, x0 double")
    mlr = ModelView(LinearMixture(1), {"weight": np.array([0.4, 0.6]), "beta": np.array([[1.0, 2.0], [3.0, 4.0]]), "var": np.ones(2)})
    assert abs(mlr.predict(rows).head().prediction - (0.4 * 4 + 0.6 * 10)) < 1e-12
    moe = ModelView(ExpertMixture(1), {"theta": np.array([[0.5, 0.1], [-0.5, 0.2]]), "beta": np.array([[1.0, 2.0], [3.0, 4.0]]), "var": np.ones(2)})
    g = np.exp([1.1, -0.8])
    g /= g.sum()
    assert abs(moe.predict(rows).head().prediction - (g[0] * 4 + g[1] * 10)) < 1e-12
    assert np.allclose([r.g for r in sorted(moe.gates(rows).collect(), key=lambda r: r.comp)], g)


def test_information_criteria():
    aic, bic = information_criteria(VIEW, -100.0, 50)
    assert aic == 210 and abs(bic - (5 * math.log(50) + 200)) < 1e-9


def pairs(a, b):
    n = list(itertools.combinations(range(len(a)), 2))
    return sum((a[i] == a[j]) == (b[i] == b[j]) for i, j in n) / len(n)


def test_measures_against_brute_force(spark):
    rng = np.random.default_rng(1)
    a, b = rng.integers(0, 3, 40).tolist(), rng.integers(0, 4, 40).tolist()
    c = C.contingency(spark.createDataFrame(list(zip(a, b, strict=True)), "a int, b int"), "a", "b")
    assert abs(C.rand_index(c).head()[0] - pairs(a, b)) < 1e-12
    top = sum(max(sum(1 for x, y in zip(a, b, strict=True) if (x, y) == (k, v)) for v in range(4)) for k in range(3))
    assert abs(C.purity(c).head()[0] - top / 40) < 1e-12
    assert 0 <= C.nmi(c, "max").head()[0] <= C.nmi(c).head()[0] <= C.nmi(c, "min").head()[0] <= 1
    assert abs(C.rand_index(c, True).head()[0]) < 0.3


def test_identical_and_relabelled_partitions(spark):
    df = spark.createDataFrame([(i % 3, "xyz"[i % 3]) for i in range(30)], "a int, b string")
    assert all(abs(r.value - 1) < 1e-12 for r in C.report(df, "a", "b").collect())
    one = spark.createDataFrame([(1, 1)] * 5, "a int, b int")
    assert C.nmi(C.contingency(one, "a", "b")).head()[0] == 1.0


def test_meter_and_gaps(spark):
    assert abs(scaling_slope([(1, 2.0), (2, 4.0), (4, 8.0)]) - 1) < 1e-12
    _, cost = Meter(spark).counted(lambda: spark.range(10).count())
    assert cost["jobs"] >= 1
    p = gaussian1d([0.3, 0.7], [0.0, 4.0], [1.0, 2.0])
    q = gaussian1d([0.7, 0.3], [4.1, 0.0], [2.0, 1.0])
    assert abs(model_gap(Gaussian(1), p, q)[0] - 0.1) < 1e-12


def test_functions(spark):
    register_npdf(spark)
    assert abs(spark.sql("SELECT npdf(0D, 0D, 1D)").head()[0] - 1 / math.sqrt(2 * math.pi)) < 1e-12
    f = mvn_logpdf(np.zeros(2), np.eye(2))
    got = spark.createDataFrame([([0.0, 0.0],)], "x array<double>").select(f("x")).head()[0]
    assert abs(got + math.log(2 * math.pi)) < 1e-12


def test_scaling(spark):
    df = spark.createDataFrame([(1, 1.0), (2, 3.0)], "tid int, v double")
    assert sorted(r.v for r in zscore(df, ["v"]).collect()) == [-1.0, 1.0]
    assert sorted(r.v for r in minmax(df, ["v"]).collect()) == [0.0, 1.0]


def test_joins_against_brute_force(spark):
    a = spark.createDataFrame([(i, float(i % 13) - 2) for i in range(50)], "id int, x0 double")
    m = spark.createDataFrame([(1, 0.0), (2, 7.5)], "comp int, mu double")
    got = {(r.id, r.comp) for r in J.within_radius(a, m, 1.5).collect()}
    assert got == {(i, c) for i in range(50) for c, mu in ((1, 0.0), (2, 7.5)) if abs(i % 13 - 2 - mu) <= 1.5}
    big = spark.createDataFrame([(i % 2, i) for i in range(40)], "k int, v int")
    small = spark.createDataFrame([(0, "z")], "k int, w string")
    assert J.salted_join(big, small, ["k"], 4).count() == 20 and J.salted_join(big, small, ["k"], 4, "left").count() == 40
    with pytest.raises(ValueError):
        J.salted_join(big, small, ["k"], 4, "full")
