import pytest
from pyspark.errors import AnalysisException

from relmix.operators.iterate import IterationError, IterationSpec, compile_script, iterate, iterate_sql, parse, run, validate
from relmix.workloads import recursion


@pytest.fixture(scope="module")
def edges(spark):
    spark.createDataFrame([("a", "b"), ("b", "c"), ("c", "d"), ("a", "e")], "src string, dst string").createOrReplaceTempView("t_edges")
    return "t_edges"


@pytest.mark.parametrize("mode", ["loop", "script", "dataframe", "client", "cte"])
def test_closure_in_every_mode(spark, edges, mode):
    got = {(r.src, r.dst) for r in run(spark, recursion.closure(edges), mode).result.collect()}
    assert got == {("a", "b"), ("b", "c"), ("c", "d"), ("a", "e"), ("a", "c"), ("a", "d"), ("b", "d")}


@pytest.mark.parametrize("mode", ["loop", "script", "dataframe", "client"])
def test_overwriting_modes_agree(spark, edges, mode):
    got = {r.node: r.hops for r in run(spark, recursion.shortest_hops(edges, "a"), mode).result.collect()}
    assert got == {"a": 0, "b": 1, "c": 2, "d": 3, "e": 1}


def test_cap_until_unchanged_and_distinct(spark, edges):
    assert run(spark, recursion.counter(5)).result.count() == 6
    spec = iterate("r", "n").start("SELECT 0 AS n").next("SELECT n + 1 AS n FROM r").append().max_rounds(50).until("n >= 3").build()
    assert run(spark, spec).rounds == 3
    halving = iterate("r", "k", "v").start("SELECT 1 AS k, 1.0D AS v").next("SELECT k, v / 2 AS v FROM r").replace_on("k").max_rounds(50).unchanged(0.01).build()
    assert run(spark, halving).rounds == 7
    loop = iterate("r", "n").start("SELECT 0 AS n").next("SELECT (n + 1) % 3 AS n FROM r").distinct().max_rounds(50).build()
    for mode in ("loop", "dataframe"):
        assert sorted(r.n for r in run(spark, loop, mode).result.collect()) == [0, 1, 2]


def test_ill_formed_specifications():
    ok = dict(name="r", start="SELECT 1 AS k", next="SELECT k FROM r", merge="replace", keys=("k",))
    validate(IterationSpec(**ok))
    for change in (
        {"keys": ()},
        {"merge": "append", "keys": ("k",)},
        {"merge": "other"},
        {"start": "SELECT * FROM r"},
        {"next": "SELECT 1 AS k"},
        {"locals": (("a", "SELECT * FROM b"), ("b", "SELECT * FROM a"))},
        {"locals": (("a", "SELECT 1"), ("A", "SELECT 2"))},
        {"locals": (("r", "SELECT 1"),)},
    ):
        with pytest.raises(IterationError):
            validate(IterationSpec(**(ok | change)))
    with pytest.raises(IterationError):
        iterate("r").replace_on("k").replace_on("k")
    with pytest.raises(IterationError):
        iterate("r").replace_on("k").append()


def test_step_errors(spark):
    wide = iterate("r", "k").start("SELECT 1 AS k").next("SELECT k, k AS x FROM r").replace_on("k").max_rounds(2).build()
    with pytest.raises(IterationError):
        run(spark, wide)
    twice = iterate("r", "k", "v").start("SELECT 1 AS k, 1 AS v").next("SELECT k, explode(array(1, 2)) AS v FROM r").replace_on("k").max_rounds(2).build()
    with pytest.raises(IterationError):
        run(spark, twice)


def test_standard_recursion_cannot_aggregate(spark):
    with pytest.raises(AnalysisException):
        spark.sql("WITH RECURSIVE r(n) AS (SELECT 1 UNION ALL SELECT max(n) + 1 FROM r) SELECT * FROM r").collect()
    with pytest.raises(IterationError):
        run(spark, iterate("r", "k").start("SELECT 1 AS k").next("SELECT k FROM r").replace_on("k").build(), "cte")


def test_text_form(spark):
    got = iterate_sql(spark, "ITERATE r (k, v) START (SELECT 1 AS k, 1 AS v) NEXT (SELECT k, w AS v FROM a) LET a AS (SELECT k, v * 2 AS w FROM r) REPLACE ON (k) MAX ROUNDS 4 THEN (SELECT v FROM r)")
    assert [r.v for r in got.collect()] == [16]
    assert parse("iterate r start (select ')' as k) next (select k from r) append max rounds 2").stop.rounds == 2
    for bad in ("SELECT 1", "ITERATE r START SELECT 1", "ITERATE r START (SELECT 1) WHAT (x)", "ITERATE r START (SELECT 1"):
        with pytest.raises(IterationError):
            parse(bad)


def test_script_text_is_one_statement(spark):
    from pyspark.sql import types as T

    text = compile_script(recursion.counter(3), T.StructType().add("n", "integer"))
    assert text.startswith("BEGIN") and text.count("WHILE") == 2


def test_em_text_keeps_a_constant_plan(spark):
    spark.createDataFrame([(i, float(i % 7) + (8 if i % 2 else 0)) for i in range(60)], "tid int, x double").createOrReplaceTempView("t_points")
    spark.createDataFrame([(1, 0.5, 2.0, 3.0), (2, 0.5, 9.0, 3.0)], "comp int, weight double, mu double, sd double").createOrReplaceTempView("t_start")
    sizes = []
    run(spark, recursion.gmm1d_spec("t_points", "t_start", 4), "loop", lambda n, df: sizes.append(len(df._jdf.queryExecution().logical().toString())))
    assert max(sizes) - min(sizes) < 200
