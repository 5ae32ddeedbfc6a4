"""Layouts, semiring algebra, merges, recursion."""

from __future__ import annotations

from pyspark.sql import functions as F

from relmix.catalogue.common import r, table
from relmix.functions import vectors as V
from relmix.operators import algebra as A
from relmix.operators import layouts as L
from relmix.operators import merge as M
from relmix.operators.iterate import run
from relmix.workloads import recursion

QUERIES: dict = {}
SQL: dict = {}


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql:
            SQL[name] = sql
        return f

    return add


# layouts ---------------------------------------------------------------------------------

_LINE = ["l_quantity", "l_extendedprice", "l_discount", "l_tax"]


def _emb(spark, d, cols=4):
    e = table(spark, d, "embeddings")
    return e.select(F.col("vec_id").alias("tid"), *[F.element_at("embedding", i + 1).cast("double").alias(f"d{i + 1}") for i in range(cols)])


_EMB = "SELECT vec_id AS tid, " + ", ".join(f"CAST(embedding[{i}] AS DOUBLE) AS d{i}" for i in range(1, 5)) + " FROM embeddings"
_UNPIVOT = " UNION ALL ".join(f"SELECT tid, {i} AS c, d{i} AS x FROM e" for i in range(1, 5))


@query("repr_coordinate", f"WITH e AS ({_EMB}) {_UNPIVOT}")
def repr_coordinate(spark, d):
    return L.convert(_emb(spark, d), "wide", "coordinate", 4).withColumn("c", F.col("c").cast("int"))


@query("repr_wide", _EMB)
def repr_wide(spark, d):
    return L.convert(L.convert(_emb(spark, d), "wide", "coordinate", 4), "coordinate", "wide", 4)


@query("repr_vector_roundtrip", _EMB)
def repr_vector_roundtrip(spark, d):
    x = L.convert(_emb(spark, d), "wide", "vector", 4)
    x = L.convert(L.convert(x, "vector", "coordinate", 4), "coordinate", "vector", 4)
    return L.convert(x, "vector", "wide", 4)


def _resp(spark, d):
    e = _emb(spark, d)
    p1 = (F.col("tid") % 10 + 1) / 12.0
    return e.select("tid", F.lit(1).alias("comp"), p1.alias("p")).union(e.select("tid", F.lit(2).alias("comp"), (1 - p1).alias("p")))


_RESP = "r AS (SELECT tid, 1 AS comp, (tid % 10 + 1) / 12.0e0 AS p FROM e UNION ALL SELECT tid, 2, 1 - (tid % 10 + 1) / 12.0e0 FROM e)"


@query("mean_coordinate", f"WITH e AS ({_EMB}), x AS ({_UNPIVOT}), {_RESP} SELECT comp, c, round(sum(p * x) / sum(p), 6) + 0.0 AS mean FROM r JOIN x USING (tid) GROUP BY comp, c")
def mean_coordinate(spark, d):
    return L.mean_coordinate(_resp(spark, d), repr_coordinate(spark, d)).select("comp", "c", r("mean").alias("mean"))


_MEANS = ", ".join(f"round(sum(p * d{i}) / sum(p), 6) + 0.0 AS m{i}" for i in range(1, 5))


@query("mean_wide", f"WITH e AS ({_EMB}), {_RESP} SELECT comp, {_MEANS} FROM r JOIN e USING (tid) GROUP BY comp")
def mean_wide(spark, d):
    return L.mean_wide(_resp(spark, d), _emb(spark, d), 4).select("comp", *[r(f"m{i}").alias(f"m{i}") for i in range(1, 5)])


@query("mean_vector", SQL["mean_wide"])
def mean_vector(spark, d):
    m = L.mean_vector(_resp(spark, d), L.wide_to_vector(_emb(spark, d), 4), 4)
    return m.select("comp", *[r(F.element_at("mean", i)).alias(f"m{i}") for i in range(1, 5)])


# semirings -------------------------------------------------------------------------------


def _e(spark, d, a=20, b=30):
    li = table(spark, d, "lineitem")
    return li.groupBy((F.col("l_orderkey") % a).alias("r"), (F.col("l_partkey") % b).alias("c")).agg(F.sum("l_quantity").alias("v"))


_E = "SELECT l_orderkey % {a} AS r, l_partkey % {b} AS c, sum(l_quantity) AS v FROM lineitem GROUP BY 1, 2"
_EM, _FM = _E.format(a=20, b=30), _E.format(a=30, b=7)
_VEC = "SELECT c AS i, sum(v) AS v FROM e GROUP BY c"


def _v(spark, d):
    return _e(spark, d).groupBy(F.col("c").alias("i")).agg(F.sum("v").alias("v"))


@query("mv_sum", f"WITH e AS ({_EM}), w AS ({_VEC}) SELECT r AS i, round(sum(e.v * w.v), 4) AS v FROM e JOIN w ON e.c = w.i GROUP BY r")
def mv_sum(spark, d):
    return A.mv_join(_e(spark, d), _v(spark, d)).select("i", F.round("v", 4).alias("v"))


@query("mv_minplus", f"WITH e AS ({_EM}), w AS ({_VEC}) SELECT r AS i, round(min(e.v + w.v), 4) AS v FROM e JOIN w ON e.c = w.i GROUP BY r")
def mv_minplus(spark, d):
    return A.mv_join(_e(spark, d), _v(spark, d), A.MIN_PLUS).select("i", F.round("v", 4).alias("v"))


@query("mm_sum", f"WITH e AS ({_EM}), f AS ({_FM}) SELECT e.r, f.c, round(sum(e.v * f.v), 4) AS v FROM e JOIN f ON e.c = f.r GROUP BY e.r, f.c")
def mm_sum(spark, d):
    return A.mm_join(_e(spark, d), _e(spark, d, 30, 7)).select("r", "c", F.round("v", 4).alias("v"))


@query("mm_maxplus", f"WITH e AS ({_EM}), f AS ({_FM}) SELECT e.r, f.c, round(max(e.v + f.v), 4) AS v FROM e JOIN f ON e.c = f.r GROUP BY e.r, f.c")
def mm_maxplus(spark, d):
    return A.mm_join(_e(spark, d), _e(spark, d, 30, 7), A.MAX_PLUS).select("r", "c", F.round("v", 4).alias("v"))


@query("mm_maxmin", f"WITH e AS ({_EM}), f AS ({_FM}) SELECT e.r, f.c, round(max(least(e.v, f.v)), 4) AS v FROM e JOIN f ON e.c = f.r GROUP BY e.r, f.c")
def mm_maxmin(spark, d):
    return A.mm_join(_e(spark, d), _e(spark, d, 30, 7), A.MAX_MIN).select("r", "c", F.round("v", 4).alias("v"))


@query("mm_bool", f"WITH e AS ({_EM}), f AS ({_FM}) SELECT e.r, f.c, bool_or(e.v > 60 AND f.v > 400) AS v FROM e JOIN f ON e.c = f.r GROUP BY e.r, f.c")
def mm_bool(spark, d):
    return A.mm_join(_e(spark, d).withColumn("v", F.col("v") > 60), _e(spark, d, 30, 7).withColumn("v", F.col("v") > 400), A.OR_AND)


@query("hadamard_rowsum", f"WITH e AS ({_EM}), f AS ({_E.format(a=20, b=15)}) SELECT e.r AS i, round(sum(e.v * f.v), 4) AS v FROM e JOIN f ON e.r = f.r AND e.c = f.c GROUP BY e.r")
def hadamard_rowsum(spark, d):
    return A.hadamard_rowsum(_e(spark, d), _e(spark, d, 20, 15)).select("i", F.round("v", 4).alias("v"))


@query("hadamard_vectors", f"WITH e AS ({_EM}), f AS ({_E.format(a=20, b=15)}) SELECT e.r AS i, round(sum(e.v * f.v), 4) AS x1, round(sum(e.v * f.v * 2), 4) AS x2 FROM e JOIN f ON e.r = f.r AND e.c = f.c GROUP BY e.r")
def hadamard_vectors(spark, d):
    cells = _e(spark, d, 20, 15).select("r", "c", F.array("v", F.col("v") * 2).alias("x"))
    out = A.hadamard_vectors(_e(spark, d), cells, 2)
    return out.select("i", F.round(F.element_at("x", 1), 4).alias("x1"), F.round(F.element_at("x", 2), 4).alias("x2"))


@query("matrix_add", f"WITH e AS ({_EM}), f AS ({_FM}) SELECT r, c, round(sum(v), 4) AS v FROM (SELECT * FROM e UNION ALL SELECT * FROM f) u GROUP BY r, c")
def matrix_add(spark, d):
    return A.matrix_add(_e(spark, d), _e(spark, d, 30, 7)).select("r", "c", F.round("v", 4).alias("v"))


# vectors ---------------------------------------------------------------------------------


@query("vec_dot", f"WITH e AS ({_EMB}) SELECT tid, round(d1 * d1 + d2 * d2 + d3 * d3 + d4 * d4, 6) + 0.0 AS v FROM e")
def vec_dot(spark, d):
    x = L.wide_to_vector(_emb(spark, d), 4)
    return x.select("tid", r(V.dot(F.col("x"), F.col("x"))).alias("v"))


@query("vec_outer_sum", "WITH e AS (" + _EMB + ") SELECT tid % 5 AS g, " + ", ".join(f"round(sum(d{i} * d{j}), 6) + 0.0 AS o{i}{j}" for i in (1, 2) for j in (1, 2)) + " FROM e GROUP BY 1")
def vec_outer_sum(spark, d):
    x = L.wide_to_vector(_emb(spark, d, 2), 2).select((F.col("tid") % 5).alias("g"), V.outer(F.col("x"), F.col("x")).alias("o"))
    sums = V.vec_sum_long(x, ["g"], "o")
    return sums.select("g", *[r(F.element_at("total", 2 * i + j + 1)).alias(f"o{i + 1}{j + 1}") for i in (0, 1) for j in (0, 1)])


@query("vec_quadform", f"WITH e AS ({_EMB}) SELECT tid, round(2 * d1 * d1 + 2 * 0.5 * d1 * d2 + 3 * d2 * d2, 6) + 0.0 AS q FROM e")
def vec_quadform(spark, d):
    a = F.array(F.array(F.lit(2.0), F.lit(0.5)), F.array(F.lit(0.5), F.lit(3.0)))
    return L.wide_to_vector(_emb(spark, d, 2), 2).select("tid", r(V.quad(F.col("x"), a)).alias("q"))


# merges ----------------------------------------------------------------------------------


def _old(spark, d):
    return table(spark, d, "nation").select(F.col("n_nationkey").alias("k"), F.col("n_name").alias("v"))


_OLD = "old AS (SELECT n_nationkey AS k, n_name AS v FROM nation)"


@query("merge_overwrite", f"WITH {_OLD}, new AS (SELECT k, lower(v) AS v FROM old WHERE k % 3 = 0 UNION ALL SELECT k + 100, v FROM old WHERE k < 4) SELECT * FROM old WHERE k NOT IN (SELECT k FROM new) UNION ALL SELECT * FROM new")
def merge_overwrite(spark, d):
    old = _old(spark, d)
    new = old.filter("k % 3 = 0").select("k", F.lower("v").alias("v")).union(old.filter("k < 4").select((F.col("k") + 100).alias("k"), "v"))
    return M.overwrite_merge(old, new, ["k"])


@query("merge_partial", f"WITH {_OLD}, new AS (SELECT k, lower(v) AS v FROM old WHERE k % 3 = 0) SELECT * FROM old WHERE k NOT IN (SELECT k FROM new) UNION ALL SELECT * FROM new")
def merge_partial(spark, d):
    old = _old(spark, d)
    return M.overwrite_merge(old, old.filter("k % 3 = 0").select("k", F.lower("v").alias("v")), ["k"], how="full")


@query("merge_insert_only", f"WITH {_OLD} SELECT * FROM old UNION ALL SELECT k + 100, v FROM old")
def merge_insert_only(spark, d):
    old = _old(spark, d)
    return M.overwrite_merge(old, old.select((F.col("k") + 100).alias("k"), "v"), ["k"])


@query("merge_last", f"WITH {_OLD}, new AS (SELECT k % 5 AS k, max(v) AS v FROM old GROUP BY 1) SELECT * FROM old WHERE k NOT IN (SELECT k FROM new) UNION ALL SELECT * FROM new")
def merge_last(spark, d):
    old = _old(spark, d)
    return M.overwrite_merge(old, old.select((F.col("k") % 5).alias("k"), "v"), ["k"], on_duplicate="last", order="v")


@query("merge_append", f"WITH {_OLD} SELECT * FROM old UNION ALL SELECT * FROM old WHERE k < 5")
def merge_append(spark, d):
    old = _old(spark, d)
    return M.append_merge(old, old.filter("k < 5"))


@query("merge_distinct", f"WITH {_OLD} SELECT * FROM old")
def merge_distinct(spark, d):
    old = _old(spark, d)
    return M.distinct_merge(old, old.filter("k < 5"))


# recursion -------------------------------------------------------------------------------

_EDGES = "edges AS (SELECT 's' || s_suppkey AS src, 'n' || s_nationkey AS dst FROM supplier UNION ALL SELECT 'n' || n_nationkey, 'r' || n_regionkey FROM nation)"
_CLOSURE = f"WITH RECURSIVE {_EDGES}, reach(src, dst, hops) AS (SELECT src, dst, 1 FROM edges UNION ALL SELECT reach.src, e.dst, reach.hops + 1 FROM reach JOIN edges e ON reach.dst = e.src) SELECT src, dst, hops FROM reach"


def _closure(mode):
    def f(spark, d):
        recursion.containment_edges(spark, d).createOrReplaceTempView("relmix_edges")
        # a loop whose state outgrows the driver's bound goes on in the shared folder
        return run(spark, recursion.closure("relmix_edges"), mode, overflow="dataframe").result.select("src", "dst", F.col("hops").cast("int").alias("hops"))

    return f


for _name, _mode in (("closure_native", "cte"), ("closure_loop", "loop"), ("closure_stored", "dataframe"), ("closure_client", "client"), ("closure_script", "script")):
    query(_name, _CLOSURE)(_closure(_mode))


@query("closure_depth", _CLOSURE.replace("SELECT src, dst, hops FROM reach", "SELECT hops, count(*) AS n FROM reach GROUP BY hops"))
def closure_depth(spark, d):
    return _closure("loop")(spark, d).groupBy("hops").agg(F.count(F.lit(1)).alias("n"))


@query("counter_capped", "SELECT c_custkey AS n FROM (SELECT DISTINCT c_custkey FROM customer ORDER BY c_custkey LIMIT 13) t")
def counter_capped(spark, d):
    """Counts on from key to key; only the cap stops it before the table's end."""
    table(spark, d, "customer").createOrReplaceTempView("relmix_counted")
    return run(spark, recursion.key_counter("relmix_counted", "c_custkey", 12)).result


@query("reach_minplus", f"WITH RECURSIVE {_EDGES}, reach(node, hops) AS (SELECT 's1', 0 UNION ALL SELECT e.dst, reach.hops + 1 FROM reach JOIN edges e ON reach.node = e.src WHERE reach.hops < 9) SELECT node, min(hops) AS hops FROM reach GROUP BY node")
def reach_minplus(spark, d):
    recursion.containment_edges(spark, d).createOrReplaceTempView("relmix_edges")
    return run(spark, recursion.shortest_hops("relmix_edges", "s1")).result.select("node", F.col("hops").cast("int").alias("hops"))
