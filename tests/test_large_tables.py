"""What larger tables and times of day with fractions showed."""

import math
from pathlib import Path

import pytest
from pyspark.sql import functions as F

from relmix import catalogue
from relmix.operators import iterate as it
from relmix.operators import joins as J
from relmix.operators import quantiles as Q
from relmix.operators import reports as R
from relmix.session import scratch
from relmix.streaming import events as E
from relmix.workloads import planted


def stream_rows(spark):
    return spark.sql("SELECT id AS event_id, timestamp_seconds(1704067200 + id * 600) AS ts, id % 3 AS user_id, 'click' AS event_type, double(id % 7) AS value, '{}' AS props FROM range(60)")


@pytest.mark.parametrize("mode", ["append", "complete", "update"])
def test_a_stream_writes_files_and_nothing_to_the_driver(spark, mode):
    stream = E.replay(spark, stream_rows(spark), 3)
    frame = E.score_stream(stream, catalogue.surrounding.fixed_view()).select("event_id", "comp") if mode == "append" else E.sessions(stream, "20 minutes")
    if mode == "update":
        frame = E.running_stats(stream)
    out = E.finished(spark, frame, mode, f"t_files_{mode}")
    assert out.inputFiles() and out.schema.names == frame.schema.names
    if mode == "append":
        assert sorted(r.event_id for r in out.collect()) == list(range(60))
    elif mode == "complete":
        assert out.agg(F.sum("n")).head()[0] == 60
    else:
        assert sorted(r[0] for r in out.groupBy("user_id").agg(F.max("n")).select("max(n)").collect()) == [20, 20, 20]


def test_sessions_keep_their_state_on_disk(spark, sf, monkeypatch):
    made = []
    monkeypatch.setattr(E, "scratch", lambda s, label: made.append(scratch(s, label)) or made[-1])
    before = {k: spark.conf.get(k, None) for k in E.ON_DISK}
    out = catalogue.queries()["stream_session"](spark, sf)
    assert out.agg(F.sum("n")).head()[0] == spark.read.parquet(f"{sf}/events.parquet").count()
    path = next(p for p in made if "/stream-" in p).removeprefix("file:")
    kinds = {f.suffix for f in Path(path, "state").rglob("*") if f.name[0].isdigit() and f.is_file()}
    assert kinds & {".changelog", ".zip"} and ".delta" not in kinds
    assert {k: spark.conf.get(k, None) for k in E.ON_DISK} == before


def odd_events(spark, tmp_path):
    times = ["01 00:00:00", "01 04:00:00", "01 07:59:59.999999", "01 11:59:59.999998", "02 00:00:00"]
    rows = [(i, f"2024-01-{t}", 1, "click", 2.0 if i else None, "{}") for i, t in enumerate(times)]
    made = spark.createDataFrame(rows, E.EVENTS.replace("timestamp", "string")).withColumn("ts", F.col("ts").cast("timestamp"))
    made.write.parquet(f"file://{tmp_path}/events.parquet")
    return f"file://{tmp_path}"


def test_events_a_whole_gap_apart_are_of_two_sessions(spark, tmp_path):
    got = catalogue.queries()["stream_session"](spark, odd_events(spark, tmp_path)).collect()
    assert sorted((str(r.start)[8:], r.n) for r in got) == [("01 00:00:00", 1), ("01 04:00:00", 3), ("02 00:00:00", 1)]


def test_events_without_a_value_are_of_no_component(spark, tmp_path):
    assert [tuple(r) for r in catalogue.queries()["stream_scored"](spark, odd_events(spark, tmp_path)).collect()] == [(1, 4)]


def test_a_stream_without_rows_gives_an_empty_frame(spark):
    for mode, frame in (("append", lambda s: s.select("event_id")), ("complete", lambda s: E.sessions(s, "20 minutes"))):
        assert E.finished(spark, frame(E.replay(spark, stream_rows(spark).limit(0), 1)), mode, f"t_none_{mode}").collect() == []


def test_sweep_rows_are_those_of_the_whole_table(spark, sf):
    lines = planted.first_lines(spark, sf, 200)
    assert lines.count() == 200
    for whole, few in ((planted.gauss(spark, sf, 3, 4), planted.gauss(spark, sf, 3, 4, lines=lines)), (planted.linear(spark, sf, 2, 4), planted.linear(spark, sf, 2, 4, lines=lines))):
        assert few.orderBy("tid").collect() == whole.orderBy("tid").limit(200).collect()


@pytest.mark.parametrize("name", ["closure_depth", "closure_loop"])
def test_closures_larger_than_the_loop_holds(spark, sf, monkeypatch, name):
    want = sorted(map(tuple, catalogue.queries()[name](spark, sf).collect()))
    monkeypatch.setattr(it, "MOST_STATE", 40)
    assert sorted(map(tuple, catalogue.queries()[name](spark, sf).collect())) == want


@pytest.mark.parametrize("kind", ["timestamp", "timestamp_ntz"])
def test_interval_join_counts_fractions_of_a_second(spark, kind):
    a = spark.sql(f"SELECT 1 AS i, CAST('2024-01-01 10:00:00.700000' AS {kind}) AS a_ts")
    times = ["09:50:00.699999", "09:50:00.700000", "10:05:00.700000", "10:05:00.700001", "10:05:00.900000"]
    b = spark.createDataFrame([(f"2024-01-01 {t}",) for t in times], "t string").selectExpr("t", f"CAST(t AS {kind}) AS b_ts")
    assert sorted(r.t[11:] for r in J.interval_join(a, b, "a_ts", "b_ts", 600, 300).collect()) == times[1:3]


@pytest.mark.parametrize("accuracy", [10_000, 4])
def test_order_statistics_are_exact(spark, monkeypatch, accuracy):
    monkeypatch.setattr(Q, "ACCURACY", accuracy)  # bounds of four ranks in all do not hold
    df = spark.range(30_000).selectExpr("CASE WHEN id % 10 > 0 THEN double((id * 7919) % 5003) END AS v")
    values = sorted(r.v for r in df.collect() if r.v is not None)
    steps = [0.02, 0.2, 0.5, 0.8, 0.95]
    want = [values[k - 1] if (k := math.ceil(30_000 * round(s * 100) / 100)) <= len(values) else None for s in steps]
    assert Q.order_statistics(df, "v", steps) == want
    assert Q.order_statistics(df.limit(0), "v", steps) == [None] * 5


def test_equal_prices_get_one_score_in_any_order(spark, tmp_path):
    prices = [0.1, 0.2, 0.3, 1000.7, 5.05]
    turns = [prices[i:] + prices[:i] for i in range(5)] + [[p * 9 for p in prices]] * 5
    rows = [(c, p) for c, t in enumerate(turns) for p in t]
    made = spark.createDataFrame(rows, "o_custkey bigint, o_totalprice double").withColumn("o_orderdate", F.lit("2000-01-01").cast("timestamp"))
    made.repartition(3).write.parquet(f"file://{tmp_path}/orders.parquet")
    score = {r.tid: r.m_score for r in catalogue.queries()["rfm_ntile"](spark, f"file://{tmp_path}").collect()}
    assert len({score[c] for c in range(5)}) == 1 and score[9] > score[0]


def test_ntiles_of_nulls_and_nothing(spark):
    rows = spark.createDataFrame([(1, 1.0), (2, None), (3, 3.0)], "tid int, m double")
    assert {r.tid: r.m_score for r in R.ntiles(rows, ["m"], 3).collect()} == {1: 1, 2: 1, 3: 2}
    assert R.ntiles(rows.limit(0), ["m"]).collect() == []
