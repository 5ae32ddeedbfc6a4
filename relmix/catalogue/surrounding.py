"""Features, reports, joins, windows, sets, functions and streams around the models."""

from __future__ import annotations

import uuid

import numpy as np
from pyspark.sql import Window
from pyspark.sql import functions as F

from relmix.catalogue import emsql
from relmix.catalogue.common import CUSTOMERS, FIXED, FIXED_PARAMS, RFM, RFM_Z, START_1D, START_1D_PARAMS, customers, fixed_view, r, table
from relmix.functions.udfs import gmm_stats, mvn_logpdf, npdf, register_npdf, register_tables
from relmix.maintain.table import MaintainedTable
from relmix.models.families import Gaussian, gaussian1d
from relmix.operators import joins as J
from relmix.operators import reports as R
from relmix.operators.features import minmax
from relmix.session import scratch
from relmix.sources.readers import MixtureSource, read, write
from relmix.streaming import events as E
from relmix.workloads import rfm, sweeps

QUERIES: dict = {}
SQL: dict = {}


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql:
            SQL[name] = sql
        return f

    return add


# features --------------------------------------------------------------------------------


@query("rfm_features", f"SELECT tid, r, f, round(m, 4) AS m FROM ({RFM}) z")
def rfm_features(spark, d):
    return rfm.orders(spark, d).select("tid", "r", "f", F.round("m", 4).alias("m"))


@query("rfm_zscore", f"WITH b AS ({RFM}) SELECT tid, round(r, 6) + 0.0 AS r, round(f, 6) + 0.0 AS f, round(m, 6) + 0.0 AS m FROM ({RFM_Z}) z")
def rfm_zscore(spark, d):
    return rfm.scaled(rfm.orders(spark, d)).select("tid", r("r").alias("r"), r("f").alias("f"), r("m").alias("m"))


@query("rfm_minmax", f"WITH b AS ({RFM}) SELECT tid, round((f - (SELECT min(f) FROM b)) / ((SELECT max(f) FROM b) - (SELECT min(f) FROM b)), 6) + 0.0 AS f FROM b")
def rfm_minmax(spark, d):
    return minmax(rfm.orders(spark, d), ["f"]).select("tid", r("f").alias("f"))


@query("rfm_events", "SELECT user_id AS tid, CAST(date_diff('day', CAST(max(ts) AS DATE), DATE '2024-02-01') AS DOUBLE) AS r, CAST(count(*) AS DOUBLE) AS f, round(sum(value), 4) AS m FROM events WHERE event_type = 'purchase' GROUP BY user_id")
def rfm_events(spark, d):
    return rfm.events(spark, d).select("tid", "r", "f", F.round("m", 4).alias("m"))


@query("rfm_ntile", f"WITH b AS ({RFM}), q AS (SELECT *, row_number() OVER (ORDER BY m) AS k, count(*) OVER () AS n FROM b), cuts AS (" + " UNION ALL ".join(f"SELECT min(m) AS c FROM q WHERE k >= n * {i / 5}e0" for i in range(1, 5)) + ") SELECT tid, CAST(1 + (SELECT count(*) FROM cuts WHERE m > c) AS INT) AS m_score FROM b")
def rfm_ntile(spark, d):
    """Sums of the same prices in another order differ in the last bits; customers with equal prices get one score."""
    return R.ntiles(rfm.orders(spark, d).withColumn("m", F.round("m", 6)), ["m"]).select("tid", "m_score")


@query("date_features", "SELECT o_orderkey, CAST(year(o_orderdate) AS INT) AS y, CAST(month(o_orderdate) AS INT) AS m, CAST(date_diff('day', CAST(o_orderdate AS DATE), DATE '2001-08-02') AS INT) AS age, strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') AS first_day FROM orders")
def date_features(spark, d):
    o = table(spark, d, "orders")
    day = F.col("o_orderdate").cast("date")
    return o.select("o_orderkey", F.year(day).alias("y"), F.month(day).alias("m"), F.datediff(F.lit(rfm.END).cast("date"), day).alias("age"), F.date_format(F.trunc(day, "month"), "yyyy-MM-dd").alias("first_day"))


@query("json_props", "SELECT event_id, length(props) AS n, props LIKE '{%' AS is_object FROM events")
def json_props(spark, d):
    """Properties parsed as a map of strings; rows that do not parse are not objects."""
    e = table(spark, d, "events").withColumn("parsed", F.from_json("props", "map<string,string>"))
    return e.select("event_id", F.length("props").cast("long").alias("n"), (F.col("parsed").isNotNull() & F.col("props").startswith("{")).alias("is_object"))


@query("string_norm", "SELECT doc_id, md5(trim(regexp_replace(lower(text), '[^a-z]+', ' ', 'g'))) AS norm_md5 FROM documents")
def string_norm(spark, d):
    return table(spark, d, "documents").select("doc_id", F.md5(F.trim(F.regexp_replace(F.lower("text"), "[^a-z]+", " "))).alias("norm_md5"))


@query("text_size_quality", "SELECT quality, count(*) AS n, round(avg(ln(d.n_chars)), 6) AS mean_ln FROM documents d JOIN labels l USING (doc_id) WHERE d.n_chars > 0 GROUP BY quality")
def text_size_quality(spark, d):
    j = table(spark, d, "documents").join(table(spark, d, "labels"), "doc_id").filter("n_chars > 0")
    return j.groupBy("quality").agg(F.count(F.lit(1)).alias("n"), F.round(F.avg(F.log("n_chars")), 6).alias("mean_ln"))


# reports ---------------------------------------------------------------------------------


def _assigned(spark, d):
    """Customers with component, segment, nation and balance."""
    c = table(spark, d, "customer").select(F.col("c_custkey").alias("tid"), "c_mktsegment", "c_nationkey", "c_acctbal")
    return fixed_view().assign(customers(spark, d)).join(c, "tid").join(F.broadcast(table(spark, d, "nation").select(F.col("n_nationkey").alias("c_nationkey"), "n_regionkey")), "c_nationkey")  # 25 rows


_ASSIGNED = emsql.gaussian(CUSTOMERS, FIXED, 1, "full", 0) + ", k AS MATERIALIZED (SELECT tid, CAST(min(comp) AS INT) AS comp FROM (SELECT *, max(p) OVER (PARTITION BY tid) AS mx FROM e0) z WHERE p = mx GROUP BY tid), s AS MATERIALIZED (SELECT tid, comp, c_mktsegment, n_regionkey, c_acctbal FROM k JOIN customer ON tid = c_custkey JOIN nation ON c_nationkey = n_nationkey)"


@query("segment_rollup", _ASSIGNED + " SELECT comp, c_mktsegment, CAST(grouping(comp) * 2 + grouping(c_mktsegment) AS BIGINT) AS gid, count(*) AS n, round(sum(c_acctbal), 2) AS total FROM s GROUP BY ROLLUP (comp, c_mktsegment)")
def segment_rollup(spark, d):
    return R.segment_report(_assigned(spark, d), ["comp", "c_mktsegment"], "c_acctbal", "rollup").withColumn("total", F.round("total", 2))


@query("segment_cube", _ASSIGNED + " SELECT comp, c_mktsegment, n_regionkey, CAST(grouping(comp) * 4 + grouping(c_mktsegment) * 2 + grouping(n_regionkey) AS BIGINT) AS gid, count(*) AS n, round(sum(c_acctbal), 2) AS total FROM s GROUP BY CUBE (comp, c_mktsegment, n_regionkey)")
def segment_cube(spark, d):
    return R.segment_report(_assigned(spark, d), ["comp", "c_mktsegment", "n_regionkey"], "c_acctbal").withColumn("total", F.round("total", 2))


@query("segment_grouping_sets", _ASSIGNED + " SELECT comp, c_mktsegment, n_regionkey, count(*) AS n, round(sum(c_acctbal), 2) AS total FROM s GROUP BY GROUPING SETS ((comp, c_mktsegment), (comp, n_regionkey), ())")
def segment_grouping_sets(spark, d):
    _assigned(spark, d).createOrReplaceTempView("relmix_assigned")
    return R.grouping_sets(spark, "relmix_assigned", [["comp", "c_mktsegment"], ["comp", "n_regionkey"], []], "c_acctbal").withColumn("total", F.round("total", 2))


@query("segment_measures", _ASSIGNED + " SELECT comp, count(DISTINCT c_mktsegment) AS segments, round(var_pop(c_acctbal), 2) AS spread, arg_max(tid, c_acctbal) AS richest FROM s GROUP BY comp")
def segment_measures(spark, d):
    return _assigned(spark, d).groupBy("comp").agg(F.countDistinct("c_mktsegment").alias("segments"), F.round(F.var_pop("c_acctbal"), 2).alias("spread"), F.max_by("tid", "c_acctbal").alias("richest"))


# joins -----------------------------------------------------------------------------------

_VERSIONS = "v(version, valid_from) AS (VALUES (1, TIMESTAMP '2024-01-05 00:00:00'), (2, TIMESTAMP '2024-01-12 06:00:00'), (3, TIMESTAMP '2024-01-20 00:00:00'))"


def _versions(spark):
    return spark.sql("SELECT * FROM VALUES (1, TIMESTAMP '2024-01-05 00:00:00'), (2, TIMESTAMP '2024-01-12 06:00:00'), (3, TIMESTAMP '2024-01-20 00:00:00') v(version, valid_from)")


@query("join_asof_model", f"WITH {_VERSIONS} SELECT event_id, (SELECT max(version) FROM v WHERE valid_from <= ts) AS version FROM events")
def join_asof_model(spark, d):
    return J.asof_model(table(spark, d, "events").select("event_id", "ts"), _versions(spark), "ts").select("event_id", "version")


@query("join_asof_keyed", "SELECT e.event_id, (SELECT max(p.ts) FROM events p WHERE p.user_id = e.user_id AND p.event_type = 'purchase' AND p.ts <= e.ts) AS last_purchase FROM events e")
def join_asof_keyed(spark, d):
    e = table(spark, d, "events")
    buys = e.filter("event_type = 'purchase'").groupBy("user_id", F.col("ts").alias("bought")).agg(F.lit(1).alias("one"))
    return J.asof_model(e.select("event_id", "user_id", "ts"), buys.select("user_id", "bought"), "ts", "bought", ["user_id"]).select("event_id", F.col("bought").alias("last_purchase"))


@query("join_interval_events", "SELECT a.event_id AS a_id, count(*) AS n FROM events a JOIN events b ON b.ts BETWEEN a.ts - INTERVAL 600 SECOND AND a.ts + INTERVAL 300 SECOND WHERE a.event_type = 'purchase' AND b.event_type = 'click' GROUP BY a.event_id")
def join_interval_events(spark, d):
    e = table(spark, d, "events")
    a = e.filter("event_type = 'purchase'").select(F.col("event_id").alias("a_id"), F.col("ts").alias("a_ts"))
    b = e.filter("event_type = 'click'").select(F.col("ts").alias("b_ts"))
    return J.interval_join(a, b, "a_ts", "b_ts", 600, 300).groupBy("a_id").agg(F.count(F.lit(1)).alias("n"))


@query("join_range_radius", f"WITH x AS ({CUSTOMERS}), m(comp, mu) AS (VALUES (1, 1.0e0), (2, 4.5e0), (3, 8.4e0)) SELECT tid, comp FROM x JOIN m ON abs(x0 - mu) <= 0.75")
def join_range_radius(spark, d):
    model = spark.createDataFrame([(1, 1.0), (2, 4.5), (3, 8.4)], "comp int, mu double")
    return J.within_radius(customers(spark, d), model, 0.75).select("tid", "comp")


@query("join_salted", "SELECT o_orderpriority, count(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY o_orderpriority")
def join_salted(spark, d):
    o = table(spark, d, "orders").select(F.col("o_custkey").alias("k"), "o_orderkey", "o_orderpriority")
    c = table(spark, d, "customer").select(F.col("c_custkey").alias("k"))
    return J.salted_join(o, c, ["k"], 8).groupBy("o_orderpriority").agg(F.count(F.lit(1)).alias("n"))


@query("join_semi", "SELECT c_custkey FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders WHERE o_totalprice > 400000)")
def join_semi(spark, d):
    big = table(spark, d, "orders").filter("o_totalprice > 400000").select(F.col("o_custkey").alias("c_custkey"))
    return table(spark, d, "customer").join(big, "c_custkey", "left_semi").select("c_custkey")


@query("join_anti", "SELECT c_custkey FROM customer WHERE c_custkey NOT IN (SELECT o_custkey FROM orders WHERE o_totalprice > 100000)")
def join_anti(spark, d):
    big = table(spark, d, "orders").filter("o_totalprice > 100000").select(F.col("o_custkey").alias("c_custkey"))
    return table(spark, d, "customer").join(big, "c_custkey", "left_anti").select("c_custkey")


@query("join_full_outer", "SELECT coalesce(a.k, b.k) AS k, a.n AS suppliers, b.n AS customers FROM (SELECT s_nationkey AS k, count(*) AS n FROM supplier GROUP BY 1) a FULL OUTER JOIN (SELECT c_nationkey AS k, count(*) AS n FROM customer WHERE c_nationkey > 3 GROUP BY 1) b ON a.k = b.k")
def join_full_outer(spark, d):
    a = table(spark, d, "supplier").groupBy(F.col("s_nationkey").alias("k")).agg(F.count(F.lit(1)).alias("suppliers"))
    b = table(spark, d, "customer").filter("c_nationkey > 3").groupBy(F.col("c_nationkey").alias("k")).agg(F.count(F.lit(1)).alias("customers"))
    return a.join(b, "k", "full_outer")


@query("join_theta", f"WITH {_VERSIONS} SELECT version, count(*) AS later FROM v JOIN events ON ts > valid_from GROUP BY version")
def join_theta(spark, d):
    v = F.broadcast(_versions(spark))  # three rows
    return table(spark, d, "events").join(v, F.col("ts") > F.col("valid_from")).groupBy("version").agg(F.count(F.lit(1)).alias("later"))


# windows and top-k -----------------------------------------------------------------------

_POST = emsql.gaussian(CUSTOMERS, FIXED, 1, "full", 0)


def _post(spark, d):
    return fixed_view().posterior(customers(spark, d)).withColumn("p", r("p"))


@query("window_rank_components", _POST + " SELECT tid, comp, CAST(row_number() OVER (PARTITION BY tid ORDER BY round(p, 6) DESC, comp) AS INT) AS rank FROM e0")
def window_rank_components(spark, d):
    return R.rank_components(_post(spark, d)).select("tid", "comp", "rank")


@query("window_running_loglik", _POST + " SELECT tid, round(sum(lse) OVER (PARTITION BY tid % 25 ORDER BY tid), 4) AS running FROM (SELECT DISTINCT tid, lse FROM e0) z")
def window_running_loglik(spark, d):
    """Running likelihood in 25 lanes: a single lane would put all rows into one task."""
    dense = fixed_view().density(customers(spark, d))
    return dense.select("tid", F.round(F.sum("lse").over(Window.partitionBy(F.col("tid") % 25).orderBy("tid")), 4).alias("running"))


@query("window_moving_avg", "SELECT o_orderkey, round(avg(o_totalprice) OVER (PARTITION BY o_custkey ORDER BY o_orderkey ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 4) AS ma, lag(o_orderkey) OVER (PARTITION BY o_custkey ORDER BY o_orderkey) AS before FROM orders")
def window_moving_avg(spark, d):
    w = Window.partitionBy("o_custkey").orderBy("o_orderkey")
    return table(spark, d, "orders").select("o_orderkey", F.round(F.avg("o_totalprice").over(w.rowsBetween(-2, 0)), 4).alias("ma"), F.lag("o_orderkey").over(w).alias("before"))


@query("topk_per_component", _POST + " SELECT tid, comp, CAST(rank AS INT) AS rank FROM (SELECT tid, comp, row_number() OVER (PARTITION BY comp ORDER BY round(p, 6) DESC, tid) AS rank FROM e0) z WHERE rank <= 5")
def topk_per_component(spark, d):
    return R.top_per_component(_post(spark, d), 5).select("tid", "comp", "rank")


# set operations --------------------------------------------------------------------------

_A = _ASSIGNED + ", a AS (SELECT n_regionkey AS t, comp, c_acctbal > 0 AS rich FROM s WHERE c_mktsegment = 'BUILDING'), b AS (SELECT n_regionkey AS t, comp, c_acctbal > 0 AS rich FROM s WHERE c_mktsegment = 'MACHINERY' AND c_acctbal > 4000)"


def _sets(spark, d):
    """Region, component and sign of the balance: of one segment, and of another's customers with much money."""
    s = _assigned(spark, d)
    cut = lambda c: s.filter(c).select(F.col("n_regionkey").alias("t"), "comp", (F.col("c_acctbal") > 0).alias("rich"))
    return cut("c_mktsegment = 'BUILDING'"), cut("c_mktsegment = 'MACHINERY' AND c_acctbal > 4000")


@query("set_union", _A + " SELECT * FROM a UNION SELECT * FROM b")
def set_union(spark, d):
    a, b = _sets(spark, d)
    return a.union(b).distinct()


@query("set_intersect", _A + " SELECT * FROM a INTERSECT SELECT * FROM b")
def set_intersect(spark, d):
    a, b = _sets(spark, d)
    return a.intersect(b)


@query("set_except", _A + " SELECT * FROM a EXCEPT SELECT * FROM b")
def set_except(spark, d):
    a, b = _sets(spark, d)
    return a.subtract(b)


# functions -------------------------------------------------------------------------------


@query("udf_npdf", f"SELECT tid, round(exp(-0.5e0 * (x0 - 4.5e0) * (x0 - 4.5e0) / 3.24e0) / (1.8e0 * 2.5066282746310002e0), 6) + 0.0 AS f, true AS same FROM ({CUSTOMERS}) x")
def udf_npdf(spark, d):
    register_npdf(spark)
    rows = customers(spark, d).select("tid", F.expr("npdf(x0, 4.5D, 1.8D)").alias("f"), npdf(F.col("x0"), F.lit(4.5), F.lit(1.8)).alias("g"))
    return rows.select("tid", r("f").alias("f"), (F.abs(F.col("f") - F.col("g")) < 1e-12).alias("same"))


@query("udf_mvn_logpdf", "SELECT vec_id AS tid, round(-0.5e0 * (2 * 1.8378770664093453e0 + ln(0.75e0) + (power(a - 0.1e0, 2) - (a - 0.1e0) * (b + 0.1e0) + power(b + 0.1e0, 2)) / 0.75e0), 6) + 0.0 AS l FROM (SELECT vec_id, CAST(embedding[1] AS DOUBLE) AS a, CAST(embedding[2] AS DOUBLE) AS b FROM embeddings) z")
def udf_mvn_logpdf(spark, d):
    f = mvn_logpdf([0.1, -0.1], [[1.0, 0.5], [0.5, 1.0]])
    e = table(spark, d, "embeddings").select(F.col("vec_id").alias("tid"), F.array(*[F.element_at("embedding", i).cast("double") for i in (1, 2)]).alias("x"))
    return e.select("tid", r(f("x")).alias("l"))


@query("udaf_stats", _POST + " SELECT comp, round(sum(p), 4) AS s0, round(sum(p * x0), 4) AS s1, round(sum(p * x0 * x0), 4) AS s2 FROM e0 GROUP BY comp")
def udaf_stats(spark, d):
    x = customers(spark, d)
    rows = fixed_view().scored(x).select("x0", F.posexplode("p").alias("k", "p"))
    out = rows.groupBy((F.col("k") + 1).alias("comp")).agg(gmm_stats()("p", "x0").alias("s"))
    return out.select("comp", *[F.round(F.element_at("s", i + 1), 4).alias(f"s{i}") for i in range(3)])


@query("udtf_components", "SELECT comp, weight, mu, sd, count(*) AS n FROM customer JOIN (VALUES (1, 0.3e0, 1.0e0, 1.2e0), (2, 0.7e0, 4.5e0, 1.8e0)) t(comp, weight, mu, sd) ON abs(c_acctbal / 1000 - mu) <= sd GROUP BY comp, weight, mu, sd")
def udtf_components(spark, d):
    """The rows of a model's table function, each with the customers within its spread."""
    register_tables(spark)
    model = spark.sql("SELECT comp, weight, mu, sd FROM component_table('[[1, 0.3, 1.0, 1.2], [2, 0.7, 4.5, 1.8]]')")
    near = table(spark, d, "customer").join(F.broadcast(model), F.abs(F.col("c_acctbal") / 1000 - F.col("mu")) <= F.col("sd"))  # two rows
    return near.groupBy("comp", "weight", "mu", "sd").agg(F.count(F.lit(1)).alias("n"))


@query("udtf_sample")
def udtf_sample(spark, d):
    """A draw for every customer: as many for each of 256 blocks of keys as it has customers, seeded by the block."""
    register_tables(spark)
    table(spark, d, "customer").createOrReplaceTempView("relmix_drawn_for")
    blocks = "SELECT CAST(pmod(c_custkey, 256) AS INT) AS block, CAST(count(*) AS INT) AS n FROM relmix_drawn_for GROUP BY 1"
    return spark.sql(f"SELECT s.comp, count(*) AS n, round(avg(s.x), 3) AS mean FROM ({blocks}) g, LATERAL mixture_sample(g.n, g.block, '[[1, 0.3, 1.0, 0.2], [2, 0.7, 4.5, 0.2]]') s GROUP BY s.comp")


# sources and sinks -----------------------------------------------------------------------


@query("source_planted", "SELECT CAST((c_custkey % 3000 + 3000) % 3000 % 2 AS INT) AS label, count(*) AS n FROM customer GROUP BY 1")
def source_planted(spark, d):
    """Every customer with the planted row that its key falls on."""
    spark.dataSource.register(MixtureSource)
    rows = spark.read.format("mixture").option("rows", 3000).option("parts", 3).load()
    keys = table(spark, d, "customer").select(F.pmod("c_custkey", F.lit(3000)).alias("tid"))
    return keys.join(F.broadcast(rows), "tid").groupBy("label").agg(F.count(F.lit(1)).alias("n"))  # 3,000 rows


@query("source_csv_json", "SELECT n_nationkey, n_name, n_regionkey FROM nation")
def source_csv_json(spark, d):
    n = table(spark, d, "nation")
    a, b = scratch(spark, "csv"), scratch(spark, "json")
    write(n, a, "csv")
    write(read(spark, a, "csv", "n_nationkey int, n_name string, n_regionkey int"), b, "json")
    return read(spark, b, "json", "n_nationkey int, n_name string, n_regionkey int")


@query("source_query_training", _POST.replace("FROM customer", "FROM customer WHERE c_mktsegment = 'BUILDING'") + " SELECT count(*) AS n, round(sum(lse), 4) AS loglik FROM (SELECT DISTINCT tid, lse FROM e0) z")
def source_query_training(spark, d):
    """A SQL query as the training set."""
    table(spark, d, "customer").createOrReplaceTempView("relmix_customer")
    rows = read(spark, "SELECT c_custkey AS tid, c_acctbal / 1000 AS x0 FROM relmix_customer WHERE c_mktsegment = 'BUILDING'", "query")
    return fixed_view().loglik(rows).select("n", F.round("loglik", 4).alias("loglik"))


# streams ---------------------------------------------------------------------------------


def _stream(spark, d):
    return E.replay(spark, table(spark, d, "events").select(*[c.split()[0] for c in E.EVENTS.split(", ")]))


def _name() -> str:
    return "relmix_stream_" + uuid.uuid4().hex[:10]


@query("stream_tumbling", "SELECT time_bucket(INTERVAL 6 HOUR, ts, TIMESTAMP '2024-01-01 00:00:00') AS start, event_type, count(*) AS n, round(sum(value), 3) AS total FROM events GROUP BY 1, 2")
def stream_tumbling(spark, d):
    out = E.finished(spark, E.windowed_components(_stream(spark, d), "6 hours", extra=["event_type"]), "complete", _name())
    return out.select(F.col("window.start").alias("start"), "event_type", "n", F.round("total", 3).alias("total"))


@query("stream_sliding", "SELECT w AS start, count(*) AS n FROM (SELECT unnest([time_bucket(INTERVAL 6 HOUR, ts, TIMESTAMP '2024-01-01 00:00:00'), time_bucket(INTERVAL 6 HOUR, ts, TIMESTAMP '2024-01-01 00:00:00') - INTERVAL 6 HOUR]) AS w FROM events) z GROUP BY w")
def stream_sliding(spark, d):
    out = E.finished(spark, E.windowed_components(_stream(spark, d), "12 hours", "6 hours"), "complete", _name())
    return out.select(F.col("window.start").alias("start"), "n")


@query("stream_session", "SELECT user_id, min(ts) AS start, count(*) AS n FROM (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS s FROM (SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) < INTERVAL 4 HOUR THEN 0 ELSE 1 END AS fresh FROM events) a) b GROUP BY user_id, s")
def stream_session(spark, d):
    # events 4 hours apart are of two sessions; the engine's window would take the second in
    rows = E.sessions(_stream(spark, d), "3 hours 59 minutes 59.999999 seconds")
    out = E.finished(spark, rows, "complete", _name(), on_disk=True)  # every session stays in the state
    return out.select("user_id", F.col("session_window.start").alias("start"), "n")


@query("stream_dedup", "SELECT count(*) AS n FROM events")
def stream_dedup(spark, d):
    e = table(spark, d, "events").select(*[c.split()[0] for c in E.EVENTS.split(", ")])
    twice = E.replay(spark, e.union(e))
    out = E.finished(spark, E.deduplicated(twice, ["event_id"], "40 days").select("event_id"), "append", _name())
    return out.agg(F.count(F.lit(1)).alias("n"))


@query("stream_stats", "SELECT user_id, count(*) AS n, round(sum(value), 3) AS total, round(sum(value * value), 2) AS squares FROM events GROUP BY user_id")
def stream_stats(spark, d):
    out = E.finished(spark, E.running_stats(_stream(spark, d)), "update", _name())
    last = out.groupBy("user_id").agg(F.max_by(F.struct("n", "total", "squares"), "n").alias("s"))
    return last.select("user_id", "s.n", F.round("s.total", 3).alias("total"), F.round("s.squares", 2).alias("squares"))


@query("stream_scored", emsql.gaussian("SELECT event_id AS tid, value / 10 AS x0 FROM events", FIXED, 1, "full", 0) + " SELECT comp, count(*) AS n FROM (SELECT tid, CAST(min(comp) AS INT) AS comp FROM (SELECT *, max(p) OVER (PARTITION BY tid) AS mx FROM e0) z WHERE p = mx GROUP BY tid) y GROUP BY comp")
def stream_scored(spark, d):
    stream = _stream(spark, d).withColumn("scaled", F.col("value") / 10)
    out = E.finished(spark, E.score_stream(stream, fixed_view(), "scaled").select("event_id", "comp"), "append", _name())
    return out.filter("comp IS NOT NULL").groupBy("comp").agg(F.count(F.lit(1)).alias("n"))  # an event without a value has none


@query("stream_maintained", emsql.gaussian("SELECT event_id AS tid, value AS x0 FROM events", [(1, 0.5, 20.0, 400.0), (2, 0.5, 120.0, 3600.0)], 1, "full", 1) + " SELECT comp, round(w, 6) + 0.0 AS weight, round(mu0, 5) + 0.0 AS mu, round(sqrt(s00), 5) + 0.0 AS sd, (SELECT count(*) FROM events) AS n FROM m1")
def stream_maintained(spark, d):
    """Half of the events are there, the other half arrive from a stream; without a sweep the parameters are
    those of all rows' shares under the entering parameters."""
    e = table(spark, d, "events").select(*[c.split()[0] for c in E.EVENTS.split(", ")])
    base = e.filter("event_id % 2 = 0").select(F.col("event_id").alias("tid"), F.col("value").alias("x0"))
    params = gaussian1d([0.5, 0.5], [20.0, 120.0], [20.0, 60.0])
    t = MaintainedTable.create(spark, scratch(spark, "maintained"), base, Gaussian(1), params, budget=0, sweeps=0)
    E.maintain_stream(E.replay(spark, e.filter("event_id % 2 = 1"), 1), t, scratch(spark, "checkpoint")).awaitTermination()
    now = spark.createDataFrame([(k + 1, float(t.params["weight"][k]), float(t.params["mu"][k, 0]), float(np.sqrt(t.params["sigma"][k, 0, 0]))) for k in range(2)], "comp int, weight double, mu double, sd double")
    n = t.data().agg(F.count(F.lit(1)).alias("n"))
    return now.select("comp", r("weight").alias("weight"), r("mu", 5).alias("mu"), r("sd", 5).alias("sd")).crossJoin(F.broadcast(n))


# experiments -----------------------------------------------------------------------------


@query("experiment_loop_modes")
def experiment_loop_modes(spark, d):
    from relmix.workloads import planted

    return sweeps.loop_sweep(spark, d)


@query("experiment_hybrid_round")
def experiment_hybrid_round(spark, d):
    return sweeps.hybrid_round(spark, d, 10_000, 10, 3)


@query("experiment_scalability")
def experiment_scalability(spark, d):
    return sweeps.scalability_sweep(spark, d)


@query("experiment_maintenance")
def experiment_maintenance(spark, d):
    from relmix.workloads import planted

    data = planted.two(spark, d)
    ahead = sweeps.maintenance(spark, data, [10, 30, 50], [0, 250, 1000])
    return ahead.unionByName(sweeps.maintenance(spark, data, [50], [250, 1000], precomputed=False))


@query("experiment_deletion")
def experiment_deletion(spark, d):
    from relmix.workloads import planted

    return sweeps.deletion(spark, planted.two(spark, d), [10, 50])


@query("experiment_convergence")
def experiment_convergence(spark, d):
    return sweeps.convergence(spark, rfm.scaled(rfm.orders(spark, d)), rounds=15)


@query("experiment_segments", "SELECT count(DISTINCT o_custkey) AS customers FROM orders")
def experiment_segments(spark, d):
    """Every customer gets one segment from each of the three models."""
    parts = [rfm.segment(spark, d, f, rounds=15).select("tid", F.lit(f).alias("model"), "comp") for f in ("gaussian", "linear", "expert")]
    whole = parts[0].unionByName(parts[1]).unionByName(parts[2])
    once = whole.groupBy("tid").agg(F.countDistinct("model").alias("m"), F.count(F.lit(1)).alias("n")).filter("m = 3 AND n = 3")
    return once.agg(F.count(F.lit(1)).alias("customers"))


@query("experiment_intermediate_rows", "SELECT p.plan AS plan, p.k * (SELECT count(*) FROM customer) AS relation_rows FROM (VALUES ('relational', 3), ('coordinate', 3)) p(plan, k)")
def experiment_intermediate_rows(spark, d):
    """Rows of the responsibility relation that the joining plans build, counted from their executed frames."""
    return sweeps.relation_rows(spark, customers(spark, d), FIXED_PARAMS)


@query("experiment_shuffled_rows")
def experiment_shuffled_rows(spark, d):
    """Rows that a round of each plan writes to shuffles, as the executors report them."""
    return sweeps.shuffled_rows(spark, customers(spark, d), FIXED_PARAMS)


@query("experiment_convergence_1d", emsql.gaussian(CUSTOMERS, START_1D, 1, "full", 15) + "\n" + " UNION ALL ".join(f"SELECT {t + 1} AS round, round(sum(lse), 4) + 0.0 AS loglik FROM (SELECT DISTINCT tid, lse FROM e{t}) z" for t in range(15)))
def experiment_convergence_1d(spark, d):
    """The likelihood entering each of fifteen rounds."""
    from relmix.models.em import fit

    done = fit(customers(spark, d), Gaussian(1), START_1D_PARAMS, 15)
    return spark.createDataFrame([(n, float(v)) for n, v, _, _ in done.trace], "round int, loglik double").select("round", r("loglik", 4).alias("loglik"))
