import numpy as np
import pytest
from pyspark.sql import functions as F

from relmix.maintain import select as S
from relmix.maintain.stats import stats_of, stats_of_rows
from relmix.maintain.table import MaintainedTable, preferred
from relmix.maintain.update import parallel_sweep, sweep
from relmix.models.em import fit
from relmix.models.families import Gaussian, gaussian1d
from relmix.streaming import events as E
from relmix.view.model_view import ModelView
from relmix.workloads import planted

FAMILY = Gaussian(1)
START = gaussian1d([0.5, 0.5], [-2.0, 2.0], [1.5, 1.5])


@pytest.fixture(scope="module")
def data(spark):
    return planted.ranged(spark, 3000).select("tid", "x0").cache()


@pytest.fixture(scope="module")
def trained(data):
    return fit(data, FAMILY, START, 10).params


def close(a, b, tol=1e-9):
    return all(np.allclose(a[k], b[k], atol=tol) for k in a)


def test_statistics_are_additive_and_give_parameters(data, trained):
    whole = stats_of(data, FAMILY, trained)
    parts = stats_of(data.filter("tid % 3 = 0"), FAMILY, trained) + stats_of(data.filter("tid % 3 <> 0"), FAMILY, trained)
    assert np.allclose(whole.s2, parts.s2) and whole.n == parts.n and np.isclose(whole.s0.sum(), whole.n)
    assert close(whole.params(FAMILY, trained), fit(data, FAMILY, trained, 1).params)
    about = stats_of(data, FAMILY, trained, np.array([50.0]))
    assert close(about.params(FAMILY, trained), whole.params(FAMILY, trained), 1e-6)
    rows = np.array([[r.x0] for r in data.collect()])
    assert np.allclose(stats_of_rows(rows, FAMILY, trained, np.zeros(1)).s1, whole.s1)


def test_insert_then_delete_restores_statistics(data, trained):
    base = stats_of(data, FAMILY, trained)
    extra = stats_of_rows(np.array([[0.3], [4.0]]), FAMILY, trained, base.centre)
    back = base + extra - extra
    assert np.allclose(back.s1, base.s1) and back.n == base.n


def test_full_sweeps_equal_warm_rounds(data, trained):
    rows = np.array([[r.x0] for r in data.collect()])
    _, got = sweep(stats_of(data, FAMILY, START), rows, FAMILY, START, 3, None, len(rows))
    assert close(got, fit(data, FAMILY, START, 4).params, 1e-8)


def test_sweep_without_rows_or_rounds(data, trained):
    s = stats_of(data, FAMILY, trained)
    for rows, rounds in ((np.zeros((0, 1)), 3), (np.array([[1.0]]), 0)):
        moved, params = sweep(s, rows, FAMILY, trained, rounds)
        assert np.allclose(moved.s0, s.s0) and close(params, s.params(FAMILY, trained))


def test_parallel_sweep_is_near_the_sequential_one(data, trained):
    s = stats_of(data, FAMILY, START)
    rows = data.filter("tid % 20 = 0")
    x = np.array([[r.x0] for r in rows.collect()])
    _, one = sweep(s, x, FAMILY, START, 2, 0, 16)
    _, many = parallel_sweep(s, rows, FAMILY, START, 2, 0, 16)
    assert close(one, many, 5e-2)


def test_selection(data, trained):
    view = ModelView(FAMILY, trained)
    top = S.select_entropy(data, view, budget=20).collect()
    rest = {r.tid for r in top}
    least = min(r.entropy for r in top)
    assert len(rest) == 20 and all(r.entropy <= least + 1e-12 for r in S.select_entropy(data, view).collect() if r.tid not in rest)
    outside = S.select_distance(data, view, radius=1.5).collect()
    assert all(r.min_mahalanobis > 1.5 for r in outside)
    assert S.select_distance(data, view, budget=5).count() == 5
    assert S.select_random(data, 7, 1).count() == 7 and S.select_none(data).count() == 0 and S.select_all(data).count() == 3000
    bar = S.budget_threshold(data, view, 100, 3000)
    assert 60 <= S.select_entropy(data, view, threshold=bar).count() <= 140


def table(spark, tmp_path, data, params, **options):
    return MaintainedTable.create(spark, f"file://{tmp_path}/t", data, FAMILY, params, **options)


def test_insert_moves_towards_retraining(spark, tmp_path, data):
    old, new = data.filter("tid % 50 <> 7"), data.filter("tid % 50 = 7")
    base = fit(old, FAMILY, START, 25).params
    whole = fit(data, FAMILY, base, 25).params
    t = table(spark, tmp_path, old, base, budget=200, sweeps=3)
    timing = t.insert(new)
    assert timing.inserted == 60 and timing.budget == 200 and timing.tuples == 260
    gap = lambda p: max(np.abs(p[k] - whole[k]).max() for k in p)
    assert gap(t.params) < gap(base)
    assert np.isclose(t.stats.s0.sum(), 3000) and t.data().count() == 3000


def test_statements_are_whole_and_idempotent(spark, tmp_path, data, trained):
    t = table(spark, tmp_path, data.filter("tid < 2900"), trained, budget=10, sweeps=1)
    t.insert(data.filter("tid >= 2900 AND tid < 2950"), "b1")
    version = t.version
    t.insert(data.filter("tid >= 2900 AND tid < 2950"), "b1")
    assert t.version == version
    with pytest.raises(ValueError):
        t.insert(data.filter("tid = 5"))
    with pytest.raises(ValueError):
        t.insert(spark.createDataFrame([(9999, None)], "tid bigint, x0 double"))
    again = MaintainedTable.open(spark, t.path, FAMILY)
    assert again.version == version and again.batches == ["b1"] and close(again.params, t.params) and again.data().count() == 2950
    again.delete(data.filter("tid < 20").select("tid"))
    assert again.data().count() == 2930 and np.isclose(again.stats.s0.sum(), 2930)
    again.update(spark.createDataFrame([(100, 9.0)], "tid bigint, x0 double"))
    assert again.data().filter("tid = 100").head().x0 == 9.0 and again.data().count() == 2930
    assert again.refresh("warm", 2) == "warm"
    again.refresh("batch", 2, start=START)


def test_strategies_and_late_statistics(spark, tmp_path, data, trained):
    for i, strategy in enumerate(("distance", "random", "entropy")):
        t = MaintainedTable.create(spark, f"file://{tmp_path}/{i}", data.filter("tid < 2990"), FAMILY, trained, precompute=False, strategy=strategy, budget=15, sweeps=1)
        timing = t.insert(data.filter("tid >= 2990"))
        assert timing.budget == 15 and timing.stats_s > 0
    zero = MaintainedTable.create(spark, f"file://{tmp_path}/zero", data.filter("tid < 2990"), FAMILY, trained, budget=0)
    assert zero.insert(data.filter("tid >= 2990")).budget == 0


@pytest.mark.parametrize("kind", ["linear", "expert"])
def test_regression_families_are_maintained_too(spark, kind):
    from relmix.maintain import regression as R
    from relmix.models.families import ExpertMixture, LinearMixture

    rng = np.random.default_rng(4)
    x = rng.uniform(-1, 1, 400)
    y = np.where(np.arange(400) % 2 == 0, 2 * x + 1, -x - 1) + rng.normal(0, 0.1, 400)
    rows = spark.createDataFrame([(i, float(a), float(b)) for i, (a, b) in enumerate(zip(x, y, strict=True))], "tid bigint, x0 double, y double").cache()
    start = {"beta": np.array([[1.0, 0.5], [-0.5, -0.5]]), "var": np.array([0.5, 0.5])}
    family = LinearMixture(1) if kind == "linear" else ExpertMixture(1)
    start |= {"weight": np.array([0.5, 0.5])} if kind == "linear" else {"theta": np.array([[0.1, 0.0], [-0.1, 0.0]])}
    stats = R.stats_of(rows, family, start)
    assert close(stats.params(family, start), fit(rows, family, start, 1).params, 1e-8)
    matrix = np.column_stack([x, y])
    _, got = R.sweep(stats, matrix, family, start, 2, None, len(matrix))
    assert close(got, fit(rows, family, start, 3).params, 1e-7)
    part = R.stats_of(rows.filter("tid < 100"), family, start) + R.stats_of(rows.filter("tid >= 100"), family, start)
    assert np.allclose(part.s2, stats.s2) and np.allclose((part - part).s0, 0)
    _, moved = R.sweep(stats, matrix[:50], family, start, 1)
    assert np.isfinite(moved["beta"]).all()


def test_policy():
    assert preferred(1e6, 10, 1000, 3, 15) == "incremental" and preferred(1e3, 10, 10**6, 3, 15) == "batch"


def stream_rows(spark):
    return spark.sql("SELECT id AS event_id, timestamp_seconds(1704067200 + id * 600) AS ts, id % 3 AS user_id, 'click' AS event_type, double(id % 7) AS value, '{}' AS props FROM range(60)")


def test_windows_sessions_and_state(spark):
    rows = stream_rows(spark)
    out = E.finished(spark, E.windowed_components(E.replay(spark, rows, 3), "1 hour"), "complete", "t_windows")
    assert out.agg(F.sum("n")).head()[0] == 60 and out.count() == 10
    stats = E.finished(spark, E.running_stats(E.replay(spark, rows, 2)), "update", "t_stats")
    assert stats.groupBy("user_id").agg(F.max("n").alias("n")).filter("n = 20").count() == 3
    sessions = E.finished(spark, E.sessions(E.replay(spark, rows, 2), "20 minutes"), "complete", "t_sessions")
    assert sessions.agg(F.sum("n")).head()[0] == 60


def test_rows_later_than_the_watermark_are_left_out(spark, tmp_path):
    from relmix.sources.readers import read_stream

    late = stream_rows(spark).limit(1).withColumn("event_id", F.lit(99).cast("bigint"))
    path = str(tmp_path / "in")
    stream_rows(spark).filter("event_id < 58").coalesce(1).write.mode("append").parquet(path)
    # a batch filters by the watermark that the batch before it knew
    stream_rows(spark).filter("event_id >= 58").coalesce(1).write.mode("append").parquet(path)
    late.coalesce(1).write.mode("append").parquet(path)
    counted = E.windowed_components(read_stream(spark, path, E.EVENTS), "1 hour", watermark="30 minutes")
    out = E.finished(spark, counted, "append", "t_late")
    assert out.agg(F.max("n")).head()[0] <= 6


def test_stream_maintains_the_model_across_restarts(spark, tmp_path):
    rows = stream_rows(spark)
    base = rows.filter("event_id < 20").select(F.col("event_id").alias("tid"), F.col("value").alias("x0"))
    t = MaintainedTable.create(spark, f"file://{tmp_path}/t", base, FAMILY, gaussian1d([0.5, 0.5], [1.0, 5.0], [1.0, 1.0]), budget=5, sweeps=1)
    stream = E.replay(spark, rows.filter("event_id >= 20"), 2)
    check = f"file://{tmp_path}/check"
    E.maintain_stream(stream, t, check).awaitTermination()
    E.maintain_stream(stream, t, check).awaitTermination()
    assert t.data().count() == 60 and np.isclose(t.stats.n, 60)
