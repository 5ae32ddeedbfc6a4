import numpy as np
import pytest
from pyspark.sql import functions as F

from relmix.maintain import regression, update
from relmix.maintain.stats import stats_of
from relmix.maintain.table import MaintainedTable, preferred
from relmix.models.em import fit
from relmix.models.families import ExpertMixture, Gaussian, LinearMixture, gaussian1d

FAMILY = Gaussian(1)
START = gaussian1d([0.5, 0.5], [1.0, 5.0], [1.0, 1.0])


@pytest.fixture(scope="module")
def rows(spark):
    rng = np.random.default_rng(4)
    x = np.where(np.arange(600) % 3 == 0, rng.normal(1, 1, 600), rng.normal(6, 1, 600))
    return spark.createDataFrame([(i, float(v)) for i, v in enumerate(x)], "tid bigint, x0 double").cache()


def made(spark, tmp_path, data, **options):
    return MaintainedTable.create(spark, f"file://{tmp_path}/t", data, FAMILY, START, **({"budget": 20, "sweeps": 1} | options))


def values(t):
    return {r.tid: r.x0 for r in t.data().collect()}


def test_deletes_write_tombstones_and_compacting_removes_them(spark, tmp_path, rows):
    t = made(spark, tmp_path, rows.filter("tid < 500"))
    parts = [p["name"] for p in t.parts]
    t.delete(rows.filter("tid IN (3, 4, 700)").select("tid"))
    assert [p["name"] for p in t.parts] == parts and len(t.tombstones) == 1
    version = t.version
    t.delete(rows.filter("tid = 3").select("tid"))  # not there any more
    assert t.version == version
    t.insert(spark.createDataFrame([(3, 7.5)], "tid bigint, x0 double"))
    t.update(spark.createDataFrame([(3, 8.5), (5, 9.5), (999, 1.0)], "tid bigint, x0 double"))
    want = {r.tid: r.x0 for r in rows.filter("tid < 500 AND tid <> 4").collect()} | {3: 8.5, 5: 9.5, 999: 1.0}
    assert values(t) == want and np.isclose(t.stats.n, len(want)) and np.isclose(t.stats.s0.sum(), len(want))
    t.compact()
    again = MaintainedTable.open(spark, t.path, FAMILY)
    assert not again.tombstones and len(again.parts) == 1 and values(again) == want
    with pytest.raises(ValueError):
        again.insert(spark.createDataFrame([(5, 0.0)], "tid bigint, x0 double"))


def test_an_insert_reads_only_parts_whose_ids_meet_it(spark, tmp_path, rows):
    t = made(spark, tmp_path, rows.filter("tid < 500"))
    read = []
    known = t._read
    t._read = lambda names: read.append(list(names)) or known(names)
    t.insert(rows.filter("tid >= 550"))
    first = t.parts[0]["name"]
    assert all(first not in names for names in read)
    with pytest.raises(ValueError):
        t.insert(rows.filter("tid = 7"))


def test_updates_are_one_statement_and_failures_leave_no_trace(spark, tmp_path, rows, monkeypatch):
    t = made(spark, tmp_path, rows.filter("tid < 100"))
    version, before = t.version, values(t)
    t.update(rows.filter("tid < 100").select("tid", (F.col("x0") + 1).alias("x0")))  # every row
    assert t.version == version + 1 and values(t) == {k: v + 1 for k, v in before.items()}
    state = (t.version, list(t.parts), t.stats.n)
    monkeypatch.setattr(t, "_append", lambda *_: (_ for _ in ()).throw(RuntimeError("lost")))
    with pytest.raises(RuntimeError):
        t.update(spark.createDataFrame([(1, 0.0)], "tid bigint, x0 double"))
    assert (t.version, list(t.parts), t.stats.n) == state and len(values(t)) == 100


def test_an_emptied_table_keeps_its_parameters(spark, tmp_path, rows):
    t = made(spark, tmp_path, rows.filter("tid < 60"))
    params = t.params
    t.delete(rows.select("tid"))
    assert t.data().count() == 0 and t.stats is None and all(np.array_equal(t.params[k], params[k]) for k in params)
    t.insert(rows.filter("tid >= 60 AND tid < 160"))
    assert t.data().count() == 100 and np.isclose(t.stats.n, 100)


def test_large_batches_take_the_distributed_way(spark, tmp_path, rows, monkeypatch):
    base = rows.filter("tid % 2 = 0")
    t = made(spark, tmp_path, base, sweeps=2)
    monkeypatch.setattr(update, "MOST_STAGED", 50)
    timing = t.insert(rows.filter("tid % 2 = 1"))
    assert timing.inserted == 300 and t.data().count() == 600 and np.isclose(t.stats.s0.sum(), 600)
    whole = fit(rows, FAMILY, START, 10).params
    assert abs(t.params["mu"] - whole["mu"]).max() < 0.2
    t.delete(rows.filter("tid % 2 = 1").select("tid"))
    assert t.data().count() == 300 and np.isclose(t.stats.s0.sum(), 300)
    many = update.full_sweep(rows, FAMILY, START, 2)
    three = fit(rows, FAMILY, START, 3).params
    assert all(np.allclose(many[k], three[k]) for k in three)


def test_held_shares_keep_the_statistics_exact_over_many_inserts(spark, tmp_path, rows):
    """What the statistics hold is the sum of the selected rows' held shares and the others' entering shares."""
    t = made(spark, tmp_path, rows.filter("tid < 300"), budget=40, sweeps=2)
    for a in range(300, 600, 60):
        t.insert(rows.filter(f"tid >= {a} AND tid < {a + 60}"))
    assert len(t.held) == 40
    picked = {r.tid: r.x0 for r in t.before_statement().collect()}
    now = update._responsibilities(np.array([[picked[i]] for i, _ in t.held]), FAMILY, t.params)
    assert np.abs(np.array([p for _, p in t.held]) - now).max() < 0.05  # swept lately, so nearly present
    exact = stats_of(rows, FAMILY, t.params, t.stats.centre)
    assert np.isclose(t.stats.s0.sum(), 600) and np.allclose(t.stats.s1.sum(0), exact.s1.sum(0)) and np.allclose(t.stats.s2.sum(0), exact.s2.sum(0))
    assert np.abs(t.stats.s0 - exact.s0).max() < 0.02 * 600  # bounded drift of the rows outside the selection


@pytest.mark.parametrize("family", [LinearMixture(1, floor=1e-3), ExpertMixture(1, floor=1e-3)])
def test_regression_tables(spark, tmp_path, family):
    rng = np.random.default_rng(2)
    x = rng.uniform(0, 10, 400)
    y = np.where(np.arange(400) % 2 == 0, 2 * x, 30 - x) + rng.normal(0, 0.3, 400)
    data = spark.createDataFrame([(i, float(a), float(b)) for i, (a, b) in enumerate(zip(x, y, strict=True))], "tid bigint, x0 double, y double")
    start = {"beta": np.array([[1.5, 1.0], [-0.5, 25.0]]), "var": np.array([4.0, 4.0])}
    start |= {"theta": np.zeros((2, 2))} if isinstance(family, ExpertMixture) else {"weight": np.array([0.5, 0.5])}
    base = fit(data.filter("tid < 380"), family, start, 8).params
    t = MaintainedTable.create(spark, f"file://{tmp_path}/r", data.filter("tid < 380"), family, base, budget=30, sweeps=2, batch_size=8)
    t.insert(data.filter("tid >= 380"), "b")
    again = MaintainedTable.open(spark, t.path, family)
    again.delete(data.filter("tid < 10").select("tid"))
    assert again.data().count() == 390 and np.isclose(again.stats.n, 390) and np.isclose(again.stats.s0.sum(), 390)
    assert np.abs(np.sort(again.params["beta"][:, 0]) - [-1, 2]).max() < 0.1
    stats = regression.stats_of(data, family, base)
    _, one = regression.sweep(stats, np.column_stack([x, y]), family, base, 1, 0, 16)
    _, many = regression.parallel_sweep(stats, data.repartition(3), family, base, 1, 0, 16)
    assert np.abs(one["beta"] - many["beta"]).max() < 0.1


def test_policy_knows_dimensions_and_components():
    assert preferred(10_000, 50_000, 0, 3, 15) == "batch"
    assert preferred(10_000, 50_000, 0, 3, 15) != preferred(100_000_000, 50_000, 0, 3, 15, d=20, k=8) == "incremental"
