"""Inference, evaluation, statistics, selection and maintenance queries."""

from __future__ import annotations

import numpy as np
from pyspark.sql import functions as F

from relmix.catalogue import emsql
from relmix.catalogue.common import CUSTOMERS, FIXED, FIXED_PARAMS, RFM_REG, START_1D_PARAMS, customers, fixed_view, planted_start, r, table
from relmix.catalogue.models import MLR_PARAMS, MLR_START, MOE_PARAMS, MOE_START, _frame_1d, money
from relmix.evaluate import clustering as C
from relmix.evaluate.meter import model_gap
from relmix.maintain import regression as reg
from relmix.maintain import select as S
from relmix.maintain.stats import stats_of
from relmix.maintain.table import MaintainedTable, preferred
from relmix.maintain.update import parallel_sweep, sweep
from relmix.models.em import fit
from relmix.models.families import ExpertMixture, Gaussian, LinearMixture, gaussian1d
from relmix.models.init import init_quantile, init_spread, init_uniform
from relmix.session import scratch
from relmix.view.model_view import ModelView, information_criteria
from relmix.workloads import planted

QUERIES: dict = {}
SQL: dict = {}


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql:
            SQL[name] = sql
        return f

    return add


def _fixed(select: str, data: str = CUSTOMERS) -> str:
    return emsql.gaussian(data, FIXED, 1, "full", 0) + "\n" + select


# inference -------------------------------------------------------------------------------


@query("posterior", _fixed("SELECT tid, comp, round(p, 6) + 0.0 AS p FROM e0"))
def posterior(spark, d):
    return fixed_view().posterior(customers(spark, d)).select("tid", "comp", r("p").alias("p"))


@query("posterior_sql_function", _fixed("SELECT tid, comp, round(p, 6) + 0.0 AS p FROM e0"))
def posterior_sql_function(spark, d):
    fixed_view().create_view(spark, "relmix_fixed")
    customers(spark, d).createOrReplaceTempView("relmix_points")
    return spark.sql("SELECT tid, CAST(pos + 1 AS INT) AS comp, round(p, 6) + 0.0D AS p FROM (SELECT tid, relmix_fixed_posterior(x0) AS ps FROM relmix_points) LATERAL VIEW posexplode(ps) t AS pos, p")


@query("map_posterior", _fixed("SELECT tid, max(CASE WHEN comp = 1 THEN round(p, 6) + 0.0 END) AS p1, max(CASE WHEN comp = 3 THEN round(p, 6) + 0.0 END) AS p3 FROM e0 GROUP BY tid"))
def map_posterior(spark, d):
    m = fixed_view().posterior_map(customers(spark, d))
    return m.select("tid", r(F.element_at("posterior", 1)).alias("p1"), r(F.element_at("posterior", 3)).alias("p3"))


_ASSIGN = "SELECT tid, CAST(min(comp) AS INT) AS comp FROM (SELECT *, max(p) OVER (PARTITION BY tid) AS mx FROM e0) z WHERE p = mx GROUP BY tid"


@query("assign_first", _fixed(_ASSIGN))
def assign_first(spark, d):
    return fixed_view().assign(customers(spark, d))


@query("assign_all_ties", "WITH t AS (SELECT c_custkey AS tid, floor(c_acctbal / 1000) - 4 AS x0 FROM customer) SELECT tid, 1 AS comp FROM t WHERE x0 <= 0 UNION ALL SELECT tid, 2 FROM t WHERE x0 >= 0")
def assign_all_ties(spark, d):
    """Between two equal components a customer in the middle, at whole thousands of the balance, belongs to both."""
    view = ModelView(Gaussian(1), gaussian1d([0.5, 0.5], [-1.0, 1.0], [1.0, 1.0]))
    rows = table(spark, d, "customer").select(F.col("c_custkey").alias("tid"), (F.floor(F.col("c_acctbal") / 1000) - 4).cast("double").alias("x0"))
    return view.assign(rows, ties="all")


@query("density_rows", _fixed("SELECT DISTINCT tid, round(lse, 6) + 0.0 AS lse, round(exp(lse), 6) + 0.0 AS density FROM e0"))
def density_rows(spark, d):
    return fixed_view().density(customers(spark, d)).select("tid", r("lse").alias("lse"), r("density").alias("density"))


@query("on_the_fly_filter", _fixed("SELECT tid, comp, round(p, 6) + 0.0 AS p FROM e0 WHERE tid BETWEEN 100 AND 120"))
def on_the_fly_filter(spark, d):
    return fixed_view().posterior(customers(spark, d)).filter("tid BETWEEN 100 AND 120").select("tid", "comp", r("p").alias("p"))


@query("component_summary", _fixed(f"SELECT a.comp, count(*) AS n, round(avg(x0), 6) + 0.0 AS mean_x0, round(stddev_pop(x0), 6) + 0.0 AS sd_x0, round(count(*) * 1.0e0 / (SELECT count(*) FROM x), 6) + 0.0 AS share FROM ({_ASSIGN}) a JOIN x USING (tid) GROUP BY a.comp"))
def component_summary(spark, d):
    s = fixed_view().summary(customers(spark, d), ["x0"])
    return s.select("comp", "n", r("mean_x0").alias("mean_x0"), r("sd_x0").alias("sd_x0"), r("share").alias("share"))


@query("uncertainty", _fixed("SELECT tid, round(-sum(CASE WHEN p > 0 THEN p * ln(p) ELSE 0 END), 6) + 0.0 AS entropy, round(min(abs(x0 - mu0) / sqrt(s00)), 6) + 0.0 AS min_mahalanobis FROM e0 GROUP BY tid"))
def uncertainty(spark, d):
    u = fixed_view().uncertainty(customers(spark, d))
    return u.select("tid", r("entropy").alias("entropy"), r("min_mahalanobis").alias("min_mahalanobis"))


@query("outliers_lowdensity", _fixed("SELECT tid, round(lse, 6) + 0.0 AS lse FROM (SELECT DISTINCT tid, lse FROM e0) z WHERE lse < (SELECT min(lse) FROM (SELECT lse, row_number() OVER (ORDER BY lse) AS k, count(*) OVER () AS n FROM (SELECT DISTINCT tid, lse FROM e0) q) w WHERE k >= n * 0.02)"))
def outliers_lowdensity(spark, d):
    return fixed_view().outliers(customers(spark, d), 0.02).select("tid", r("lse").alias("lse"))


@query("loglik_total", _fixed("SELECT count(*) AS n, round(sum(lse), 4) AS loglik FROM (SELECT DISTINCT tid, lse FROM e0) z"))
def loglik_total(spark, d):
    return fixed_view().loglik(customers(spark, d)).select("n", F.round("loglik", 4).alias("loglik"))


@query("bic", _fixed("SELECT round(16 - 2 * sum(lse), 4) AS aic, round(8 * ln(count(*)) - 2 * sum(lse), 4) AS bic FROM (SELECT DISTINCT tid, lse FROM e0) z"))
def bic(spark, d):
    row = fixed_view().loglik(customers(spark, d)).head()
    aic, b = information_criteria(fixed_view(), row["loglik"], row["n"])
    return spark.createDataFrame([(aic, b)], "aic double, bic double").select(F.round("aic", 4).alias("aic"), F.round("bic", 4).alias("bic"))


@query("label_components", _fixed(f"SELECT comp, label, n FROM (SELECT comp, label, n, row_number() OVER (PARTITION BY comp ORDER BY n DESC, label) AS k FROM (SELECT a.comp, c_mktsegment AS label, count(*) AS n FROM ({_ASSIGN}) a JOIN customer ON tid = c_custkey GROUP BY 1, 2) q) z WHERE k = 1"))
def label_components(spark, d):
    data = customers(spark, d).join(table(spark, d, "customer").select(F.col("c_custkey").alias("tid"), "c_mktsegment"), "tid")
    return fixed_view().label_components(data, "c_mktsegment")


@query("model_versions")
def model_versions(spark, d):
    """Two versions are written; the first is read back and scored."""
    path = scratch(spark, "model")
    view = fixed_view()
    view.save(spark, path)
    ModelView(Gaussian(1), START_1D_PARAMS).save(spark, path)
    return ModelView.load(spark, path, 1).loglik(customers(spark, d)).select("n", F.round("loglik", 4).alias("loglik"))


SQL["model_versions"] = SQL["loglik_total"]


# evaluation ------------------------------------------------------------------------------


def _clusters(spark, d):
    """Planted rows with the component that near-true parameters give them."""
    view = ModelView(Gaussian(2), planted_start()[1])
    return view.clustered(planted.gauss(spark, d)).select("tid", "label", "comp")


_CLUSTERS = emsql.gaussian(planted.gauss_sql(2), planted_start()[0], 2, "full", 0) + ", k AS MATERIALIZED (SELECT tid, max(label) AS label, CAST(min(comp) AS INT) AS comp FROM (SELECT *, max(p) OVER (PARTITION BY tid) AS mx FROM e0) z WHERE p = mx GROUP BY tid), c AS MATERIALIZED (SELECT comp AS a, label AS b, count(*) AS n FROM k GROUP BY 1, 2), ra AS (SELECT a, sum(n) AS na FROM c GROUP BY a), rb AS (SELECT b, sum(n) AS nb FROM c GROUP BY b), t AS (SELECT CAST(sum(n) AS DOUBLE) AS n FROM c)"


@query("contingency", _CLUSTERS + " SELECT a, b, n FROM c")
def contingency(spark, d):
    return C.contingency(_clusters(spark, d), "comp", "label")


@query("purity", _CLUSTERS + " SELECT round(sum(top) / (SELECT n FROM t), 6) AS purity FROM (SELECT max(n) AS top FROM c GROUP BY a) z")
def purity(spark, d):
    return C.purity(contingency(spark, d)).select(F.round("purity", 6).alias("purity"))


_ENT = "(SELECT -sum(na / t.n * ln(na / t.n)) FROM ra, t)", "(SELECT -sum(nb / t.n * ln(nb / t.n)) FROM rb, t)"


@query("nmi", _CLUSTERS + f" SELECT round((SELECT sum(c.n / t.n * ln(c.n * t.n / (na * nb))) FROM c JOIN ra USING (a) JOIN rb USING (b), t) / (({_ENT[0]} + {_ENT[1]}) / 2), 6) AS nmi")
def nmi(spark, d):
    return C.nmi(contingency(spark, d)).select(F.round("nmi", 6).alias("nmi"))


@query("nmi_sqrt", _CLUSTERS + f" SELECT round((SELECT sum(c.n / t.n * ln(c.n * t.n / (na * nb))) FROM c JOIN ra USING (a) JOIN rb USING (b), t) / sqrt({_ENT[0]} * {_ENT[1]}), 6) AS nmi")
def nmi_sqrt(spark, d):
    return C.nmi(contingency(spark, d), "sqrt").select(F.round("nmi", 6).alias("nmi"))


_PAIR = "(SELECT sum(n * (n - 1) / 2.0e0) FROM c)", "(SELECT sum(na * (na - 1) / 2.0e0) FROM ra)", "(SELECT sum(nb * (nb - 1) / 2.0e0) FROM rb)", "(SELECT n * (n - 1) / 2 FROM t)"


@query("rand_index", _CLUSTERS + f" SELECT round(({_PAIR[3]} + 2 * {_PAIR[0]} - {_PAIR[1]} - {_PAIR[2]}) / {_PAIR[3]}, 6) AS rand_index")
def rand_index(spark, d):
    return C.rand_index(contingency(spark, d)).select(F.round("rand_index", 6).alias("rand_index"))


@query("adjusted_rand", _CLUSTERS + f" SELECT round(({_PAIR[0]} - {_PAIR[1]} * {_PAIR[2]} / {_PAIR[3]}) / (({_PAIR[1]} + {_PAIR[2]}) / 2 - {_PAIR[1]} * {_PAIR[2]} / {_PAIR[3]}), 6) AS adjusted_rand")
def adjusted_rand(spark, d):
    return C.rand_index(contingency(spark, d), True).select(F.round("adjusted_rand", 6).alias("adjusted_rand"))


@query("evaluation_report")
def evaluation_report(spark, d):
    return C.report(_clusters(spark, d), "comp", "label").select("measure", F.round("value", 6).alias("value"))


SQL["evaluation_report"] = _CLUSTERS + " " + " UNION ALL ".join(f"SELECT '{m}' AS measure, ({SQL[q].replace(_CLUSTERS, '', 1)}) AS value" for m, q in (("purity", "purity"), ("nmi", "nmi"), ("rand_index", "rand_index"), ("adjusted_rand", "adjusted_rand")))


# statistics ------------------------------------------------------------------------------

_STAT = "SELECT comp, round(sum(p), 4) AS s0, round(sum(p * x0), 4) AS s1, round(sum(p * x0 * x0), 4) AS s2 FROM e0 {where} GROUP BY comp"


def _stat_frame(spark, s):
    return s.frame(spark).select("comp", F.round("s0", 4).alias("s0"), F.round(F.element_at("s1", 1), 4).alias("s1"), F.round(F.element_at("s2", 1), 4).alias("s2"))


@query("suff_stats", _fixed(_STAT.format(where="")))
def suff_stats(spark, d):
    return _stat_frame(spark, stats_of(customers(spark, d), Gaussian(1), FIXED_PARAMS))


@query("params_from_stats", _fixed("SELECT comp, round(sum(p) / (SELECT count(*) FROM x), 6) + 0.0 AS weight, round(sum(p * x0) / sum(p), 6) + 0.0 AS mu, round(sqrt(sum(p * x0 * x0) / sum(p) - power(sum(p * x0) / sum(p), 2)), 6) + 0.0 AS sd FROM e0 GROUP BY comp"))
def params_from_stats(spark, d):
    return _frame_1d(spark, stats_of(customers(spark, d), Gaussian(1), FIXED_PARAMS).params(Gaussian(1), FIXED_PARAMS))


@query("stats_insert_delta", _fixed(_STAT.format(where="")))
def stats_insert_delta(spark, d):
    """Statistics of 90 % of the rows plus those of the inserted rest, under the old parameters."""
    x = customers(spark, d)
    old, new = stats_of(x.filter("tid % 10 <> 3"), Gaussian(1), FIXED_PARAMS), stats_of(x.filter("tid % 10 = 3"), Gaussian(1), FIXED_PARAMS)
    return _stat_frame(spark, old + new)


@query("stats_delete_delta", _fixed(_STAT.format(where="WHERE tid % 10 <> 3")))
def stats_delete_delta(spark, d):
    x = customers(spark, d)
    return _stat_frame(spark, stats_of(x, Gaussian(1), FIXED_PARAMS) - stats_of(x.filter("tid % 10 = 3"), Gaussian(1), FIXED_PARAMS))


# selection -------------------------------------------------------------------------------

_MEASURES = "SELECT tid, -sum(CASE WHEN p > 0 THEN p * ln(p) ELSE 0 END) AS en, min(abs(x0 - mu0) / sqrt(s00)) AS di FROM e0 GROUP BY tid"


@query("select_distance_radius", _fixed(f"SELECT tid, round(di, 6) + 0.0 AS distance FROM ({_MEASURES}) z WHERE di > 1.1"))
def select_distance_radius(spark, d):
    return S.select_distance(customers(spark, d), fixed_view(), radius=1.1).select("tid", r("min_mahalanobis").alias("distance"))


@query("select_distance_topb", _fixed(f"SELECT tid, round(di, 6) + 0.0 AS distance FROM ({_MEASURES}) z ORDER BY di DESC, tid LIMIT 50"))
def select_distance_topb(spark, d):
    return S.select_distance(customers(spark, d), fixed_view(), budget=50).select("tid", r("min_mahalanobis").alias("distance"))


@query("select_entropy_topb", _fixed(f"SELECT tid, round(en, 6) + 0.0 AS entropy FROM ({_MEASURES}) z ORDER BY en DESC, tid LIMIT 50"))
def select_entropy_topb(spark, d):
    return S.select_entropy(customers(spark, d), fixed_view(), budget=50).select("tid", r("entropy").alias("entropy"))


@query("select_entropy_threshold", _fixed(f"SELECT tid, round(en, 6) + 0.0 AS entropy FROM ({_MEASURES}) z WHERE en >= 0.5"))
def select_entropy_threshold(spark, d):
    return S.select_entropy(customers(spark, d), fixed_view(), threshold=0.5).select("tid", r("entropy").alias("entropy"))


@query("select_random", "SELECT c_custkey AS tid FROM customer ORDER BY md5(c_custkey || ':7'), c_custkey LIMIT 40")
def select_random(spark, d):
    return S.select_random(customers(spark, d), 40, seed=7).select("tid")


# maintenance -----------------------------------------------------------------------------


@query("warm_refresh", emsql.gaussian(CUSTOMERS, FIXED, 1, "full", 3) + "\nSELECT comp, round(w, 6) + 0.0 AS weight, round(mu0, 6) + 0.0 AS mu, round(sqrt(s00), 6) + 0.0 AS sd FROM m3")
def warm_refresh(spark, d):
    return _frame_1d(spark, fit(customers(spark, d), Gaussian(1), FIXED_PARAMS, 3).params)


@query("full_sweep", emsql.gaussian(CUSTOMERS, FIXED, 1, "full", 3) + "\nSELECT comp, round(w, 6) + 0.0 AS weight, round(mu0, 6) + 0.0 AS mu, round(sqrt(s00), 6) + 0.0 AS sd FROM m3")
def full_sweep(spark, d):
    """All rows staged, one batch a sweep: two sweeps after the statistics equal three warm rounds."""
    from relmix.maintain.update import full_sweep as whole

    return _frame_1d(spark, whole(customers(spark, d), Gaussian(1), FIXED_PARAMS, 2))


def _two(spark, d):
    return planted.two(spark, d).select("tid", "x0")


_TWO_PARAMS = gaussian1d([0.5, 0.5], [-2.0, 2.0], [1.5, 1.5])


@query("incremental_update")
def incremental_update(spark, d):
    """Insert a tenth of a percent of the rows with and without a budget; gap of the parameters to retraining."""
    x, family = _two(spark, d), Gaussian(1)
    old, new = x.filter("tid % 1000 <> 1"), x.filter("tid % 1000 = 1")
    base = fit(old, family, _TWO_PARAMS, 15).params
    whole = fit(x, family, base, 15).params
    rows = [("untouched", 0, model_gap(family, base, whole)[0])]
    for b in (0, 200):
        t = MaintainedTable.create(spark, scratch(spark, "maintained"), old, family, base, budget=b, sweeps=3)
        t.insert(new)
        rows.append(("incremental", b, model_gap(family, t.params, whole)[0]))
    return spark.createDataFrame(rows, "method string, budget int, gap double")


_PARAMS_OF_P = "SELECT comp, round(s0 / n, 6) + 0.0 AS weight, round(s1 / s0, 6) + 0.0 AS mu, round(sqrt(s2 / s0 - (s1 / s0) * (s1 / s0)), 6) + 0.0 AS sd FROM"
_TWO_START = [(1, 0.5, -2.0, 2.25), (2, 0.5, 2.0, 2.25)]


@query("incremental_delete")
def incremental_delete(spark, d):
    """Parameters and row count after a delete without a sweep: the statistics of the rows that are left."""
    x, family = _two(spark, d), Gaussian(1)
    t = MaintainedTable.create(spark, scratch(spark, "maintained"), x, family, _TWO_PARAMS, budget=0)
    t.delete(x.filter("tid % 1000 = 1").select("tid"))
    return _frame_1d(spark, t.params).crossJoin(F.broadcast(t.data().agg(F.count(F.lit(1)).alias("n"))))


SQL["incremental_delete"] = (
    emsql.gaussian(f"SELECT tid, x0 FROM ({planted.gauss_sql(1, two=3.0)}) g", _TWO_START, 1, "full", 0)
    + f" {_PARAMS_OF_P.replace(' FROM', ', n FROM')} (SELECT comp, count(*) AS n, sum(p) AS s0, sum(p * x0) AS s1, sum(p * x0 * x0) AS s2 FROM e0 WHERE tid % 1000 <> 1 GROUP BY comp) z"
)

#: The update row by row in a fixed order, unrolled as a recursion over the steps; lists hold the components.
_STEPS, _STAGED = 16, 8
_EACH = "list_transform(range(1, 4), lambda k: {})".format
SQL["incremental_fixed_order"] = (
    emsql.gaussian(CUSTOMERS, FIXED, 1, "full", 0).replace("WITH ", "WITH RECURSIVE ", 1)
    + f""",
staged AS (SELECT tid, row_number() OVER (ORDER BY tid) AS i FROM x ORDER BY tid LIMIT {_STAGED}),
shares AS (SELECT i, max(x0) AS v, list(p ORDER BY comp) AS p FROM e0 JOIN staged USING (tid) GROUP BY i),
rows8 AS (SELECT list(v ORDER BY i) AS xs, list(p ORDER BY i) AS ps FROM shares),
sums AS (SELECT comp, sum(p) AS a, sum(p * x0) AS b, sum(p * x0 * x0) AS c FROM e0 GROUP BY comp),
steps(step, xs, ps, a, b, c) AS (
  SELECT 0, xs, ps, (SELECT list(a ORDER BY comp) FROM sums), (SELECT list(b ORDER BY comp) FROM sums), (SELECT list(c ORDER BY comp) FROM sums) FROM rows8
  UNION ALL
  SELECT step + 1, xs, {_EACH("k").replace("range(1, 4)", f"range(1, {_STAGED + 1})").replace(": k)", ": CASE WHEN k = i THEN q ELSE ps[k] END)")},
         {_EACH("a[k] + q[k] - ps[i][k]")}, {_EACH("b[k] + (q[k] - ps[i][k]) * v")}, {_EACH("c[k] + (q[k] - ps[i][k]) * v * v")}
  FROM (SELECT *, {_EACH("f[k] / list_sum(f)")} AS q
    FROM (SELECT *, {_EACH("a[k] / sqrt(c[k] / a[k] - (b[k] / a[k]) * (b[k] / a[k])) * exp(-0.5e0 * (v - b[k] / a[k]) * (v - b[k] / a[k]) / (c[k] / a[k] - (b[k] / a[k]) * (b[k] / a[k])))")} AS f
      FROM (SELECT *, step % {_STAGED} + 1 AS i, xs[step % {_STAGED} + 1] AS v FROM steps WHERE step < {_STEPS}) s1) s2) s3),
done AS (SELECT CAST(k AS INT) AS comp, a[k] AS s0, b[k] AS s1, c[k] AS s2, (SELECT count(*) FROM x) AS n FROM steps, range(1, 4) r(k) WHERE step = {_STEPS})
{_PARAMS_OF_P} done"""
)


@query("incremental_fixed_order", SQL["incremental_fixed_order"])
def incremental_fixed_order(spark, d):
    """Eight staged rows, two sweeps in the order of ids, parameters derived after each row."""
    x, family = customers(spark, d), Gaussian(1)
    staged = np.array([[r["x0"]] for r in x.orderBy("tid").limit(_STAGED).collect()])
    _, params = sweep(stats_of(x, family, FIXED_PARAMS), staged, family, FIXED_PARAMS, _STEPS // _STAGED, None, 1)
    return _frame_1d(spark, params)


@query("incremental_parallel")
def incremental_parallel(spark, d):
    """Partitions sweep their own rows; gap to one sequential sweep."""
    from relmix.maintain.update import collected

    x, family = _two(spark, d), Gaussian(1)
    base = fit(x, family, _TWO_PARAMS, 5).params
    staged = S.select_entropy(x, ModelView(family, base), budget=1000).repartition(4, "tid")
    stats = stats_of(x, family, base)
    _, one = sweep(stats, collected(staged, family), family, base, 2, 0, 64)
    _, many = parallel_sweep(stats, staged, family, base, 2)
    return spark.createDataFrame([(model_gap(family, many, one)[0] < 1e-2,)], "close boolean")


_POLICY = [(budget, dims, comps) for budget in (0, 1_000, 20_000, 500_000) for dims, comps in ((1, 2), (20, 8))]


@query(
    "refresh_policy",
    "SELECT n, b AS budget, d, k, CASE WHEN (b + 10) * 3 * (1e-4 + 1e-6 * m) <= 15 * (0.3e0 + n * m * 4e-8) THEN 'incremental' ELSE 'batch' END AS mode "
    f"FROM (SELECT *, k * (1 + d + d * (d + 1) / 2.0e0) AS m, (SELECT count(*) FROM lineitem) AS n FROM (VALUES {', '.join(map(str, _POLICY))}) t(b, d, k)) z",
)
def refresh_policy(spark, d):
    """The choice for a table as long as lineitem, by budget, dimensions and components."""
    n = spark.read.parquet(f"{d}/lineitem.parquet").count()
    rows = [(n, b, dims, comps, preferred(n, 10, b, 3, 15, d=dims, k=comps)) for b, dims, comps in _POLICY]
    return spark.createDataFrame(rows, "n bigint, budget int, d int, k int, mode string")


@query("regression_stats", emsql.regression(RFM_REG, MLR_START, 1, False) + "\nSELECT comp, round(w, 6) + 0.0 AS w, round(b0, 6) + 0.0 AS b0, round(b1, 6) + 0.0 AS b1, round(v, 6) + 0.0 AS v FROM m1")
def regression_stats(spark, d):
    """Parameters from the statistics of nine tenths of the rows plus those of the inserted rest."""
    x, family = money(spark, d), LinearMixture(1)
    stats = reg.stats_of(x.filter("tid % 10 <> 3"), family, MLR_PARAMS) + reg.stats_of(x.filter("tid % 10 = 3"), family, MLR_PARAMS)
    p = stats.params(family, MLR_PARAMS)
    df = spark.createDataFrame([(k + 1, float(p["weight"][k]), *map(float, p["beta"][k]), float(p["var"][k])) for k in range(2)], "comp int, w double, b0 double, b1 double, v double")
    return df.select("comp", *[r(n).alias(n) for n in df.columns[1:]])


@query("expert_stats", emsql.regression(RFM_REG, MOE_START, 1, True) + "\nSELECT comp, " + ", ".join(f"round({n}, 5) + 0.0 AS {n}" for n in ("g0", "g1", "b0", "b1", "v")) + " FROM m1")
def expert_stats(spark, d):
    p = reg.stats_of(money(spark, d), ExpertMixture(1), MOE_PARAMS).params(ExpertMixture(1), MOE_PARAMS)
    df = spark.createDataFrame([(k + 1, *map(float, p["theta"][k]), *map(float, p["beta"][k]), float(p["var"][k])) for k in range(2)], "comp int, g0 double, g1 double, b0 double, b1 double, v double")
    return df.select("comp", *[r(n, 5).alias(n) for n in df.columns[1:]])


@query("initialisers")
def initialisers(spark, d):
    """Likelihood after three rounds from each way to start."""
    x, family = planted.gauss(spark, d).select("tid", "x0", "x1"), Gaussian(2)
    starts = {"uniform": init_uniform(x, family, 10, 1), "quantile": init_quantile(x, family, 10), "spread": init_spread(x, family, 10, 1), "near truth": planted_start()[1]}
    return spark.createDataFrame([(k, float(np.round(fit(x, family, p, 3).trace[-1][1], 3))) for k, p in starts.items()], "start string, loglik double")

