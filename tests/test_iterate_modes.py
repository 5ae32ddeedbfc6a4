import pytest

from relmix.operators import iterate as it
from relmix.operators.iterate import IterationError, iterate, run

MODES = ["loop", "script", "dataframe", "client"]


def halving():
    return iterate("r", "k", "v").start("SELECT 1 AS k, 1.0D AS v UNION ALL SELECT 2, 0.5D").next("SELECT k, v / 2 AS v FROM r").replace_on("k")


SPECS = {
    "unchanged within a tolerance": halving().max_rounds(30).unchanged(0.1).build(),
    "unchanged exactly": iterate("r", "k", "v").start("SELECT 1 AS k, 5 AS v").next("SELECT k, greatest(v - 1, 2) AS v FROM r").replace_on("k").max_rounds(30).unchanged().build(),
    "until after a round": halving().max_rounds(30).until("v < 0.3").build(),
    "until true at the start": halving().max_rounds(30).until("v > 0").build(),
    "cap": halving().max_rounds(3).build(),
    "new keys": iterate("r", "k", "v").start("SELECT 1 AS k, 1 AS v").next("SELECT k + 1 AS k, v FROM r WHERE k < 5").replace_on("k").max_rounds(9).build(),
    "no new rows": iterate("r", "k", "v").start("SELECT 1 AS k, 1 AS v").next("SELECT k, v FROM r WHERE v > 1").replace_on("k").max_rounds(9).build(),
    "append to the cap": iterate("r", "n").start("SELECT 0 AS n").next("SELECT n + 1 AS n FROM r").append().max_rounds(4).build(),
    "append until empty": iterate("r", "n").start("SELECT 0 AS n").next("SELECT n + 1 AS n FROM r WHERE n < 3").append().max_rounds(40).build(),
    "append until": iterate("r", "n").start("SELECT 0 AS n").next("SELECT n + 1 AS n FROM r").append().max_rounds(40).until("n >= 3").build(),
}
ROUNDS = {"unchanged within a tolerance": 4, "unchanged exactly": 4, "until after a round": 1, "until true at the start": 1, "cap": 3, "new keys": 9, "no new rows": 1, "append to the cap": 4, "append until empty": 4, "append until": 3}


@pytest.mark.parametrize("name", SPECS)
def test_modes_agree_on_rows_and_rounds(spark, name):
    got = {}
    for mode in MODES:
        done = run(spark, SPECS[name], mode)
        got[mode] = (done.rounds, sorted(tuple(r) for r in done.result.collect()))
    assert got["loop"][0] == ROUNDS[name]
    assert all(got[m] == got["loop"] for m in MODES)


@pytest.mark.parametrize("mode", MODES)
def test_several_new_rows_for_a_key_are_refused(spark, mode):
    spec = iterate("r", "k", "v").start("SELECT 1 AS k, 1 AS v").next("SELECT k, explode(array(1, 2)) AS v FROM r").replace_on("k").max_rounds(2).build()
    with pytest.raises(Exception, match="several|one key|duplicate|DUPLICATE") as caught:
        run(spark, spec, mode).result.collect()
    if mode in ("loop", "script"):
        assert isinstance(caught.value, IterationError)


def test_plain_recursion_refuses_stop_rules(spark):
    for change in (lambda b: b.until("n > 2"), lambda b: b.unchanged()):
        spec = change(iterate("r", "n").start("SELECT 0 AS n").next("SELECT n + 1 AS n FROM r WHERE n < 3").append().max_rounds(9)).build()
        with pytest.raises(IterationError):
            run(spark, spec, "cte")


def test_states_are_bounded_before_they_are_collected(spark, monkeypatch):
    monkeypatch.setattr(it, "MOST_STATE", 10)
    spec = iterate("r", "n").start("SELECT id AS n FROM range(8)").next("SELECT n + 1 AS n FROM r").append().max_rounds(2).build()
    with pytest.raises(IterationError):
        run(spark, spec)
    big = iterate("r", "n").start("SELECT id AS n FROM range(11)").next("SELECT n FROM r WHERE n < 0").append().max_rounds(2).build()
    with pytest.raises(IterationError):
        run(spark, big)
    assert run(spark, spec, "dataframe").result.count() == 24


@pytest.mark.parametrize("merge", ["append", "distinct", "replace"])
def test_a_loop_that_outgrows_its_bound_goes_on_in_the_shared_folder(spark, monkeypatch, merge):
    b = iterate("r", "k", "v").start("SELECT id AS k, 0 AS v FROM range(3)").next("SELECT k + 2 AS k, v + 1 AS v FROM r WHERE k + 2 < 19")
    spec = (b.replace_on("k") if merge == "replace" else getattr(b, merge)()).max_rounds(30).build()
    want = run(spark, spec, "dataframe")
    for most in (2, 6, 1000):
        monkeypatch.setattr(it, "MOST_STATE", most)
        got = run(spark, spec, overflow="dataframe")
        assert sorted(map(tuple, got.result.collect())) == sorted(map(tuple, want.result.collect())) and got.rounds == want.rounds
