"""Training queries: every family, plan and execution mode."""

from __future__ import annotations

import numpy as np
from pyspark.sql import functions as F

from relmix.catalogue import emsql
from relmix.catalogue.common import CUSTOMERS, RFM_GAUSS, RFM_REG, START_1D, START_1D_PARAMS, customers, planted_start, r, rfm_start, rfm_z, table
from relmix.models.em import fit
from relmix.models.families import ExpertMixture, Gaussian, LinearMixture
from relmix.operators.features import bind_features, bind_vector
from relmix.operators.iterate import iterate_sql, run
from relmix.view.model_view import ModelView
from relmix.workloads import planted, recursion, rfm

QUERIES: dict = {}
SQL: dict = {}

_ROUND_1D = "SELECT comp, round(w, 6) + 0.0 AS weight, round(mu0, 6) + 0.0 AS mu, round(sqrt(s00), 6) + 0.0 AS sd FROM m{t}"


def _sql_1d(rounds: int, select: str) -> str:
    return emsql.gaussian(CUSTOMERS, START_1D, 1, "full", rounds) + "\n" + select


def _frame_1d(spark, params):
    rows = [(k + 1, float(w), float(m[0]), float(np.sqrt(s[0, 0]))) for k, (w, m, s) in enumerate(zip(params["weight"], params["mu"], params["sigma"], strict=True))]
    df = spark.createDataFrame(rows, "comp int, weight double, mu double, sd double")
    return df.select("comp", r("weight").alias("weight"), r("mu").alias("mu"), r("sd").alias("sd"))


def _gmm1d(rounds: int, plan: str):
    return lambda spark, d: _frame_1d(spark, fit(customers(spark, d), Gaussian(1), START_1D_PARAMS, rounds, plan=plan).params)


_FIVE = _sql_1d(5, _ROUND_1D.format(t=5))
for _name, _rounds, _plan in (("gmm1d_round1", 1, "relational"), ("gmm1d_round5", 5, "relational"), ("gmm1d_fused", 5, "fused"), ("gmm1d_explode", 5, "explode"), ("gmm1d_arrow", 5, "arrow")):
    QUERIES[_name] = _gmm1d(_rounds, _plan)
    SQL[_name] = _FIVE if _rounds == 5 else _sql_1d(1, _ROUND_1D.format(t=1))


def _gmm1d_iterated(mode: str):
    def f(spark, d):
        customers(spark, d).select("tid", F.col("x0").alias("x")).createOrReplaceTempView("relmix_points")
        spark.createDataFrame([(c, w, m, v**0.5) for c, w, m, v in START_1D], "comp int, weight double, mu double, sd double").createOrReplaceTempView("relmix_start")
        out = run(spark, recursion.gmm1d_spec("relmix_points", "relmix_start", 5), mode).result
        return out.select("comp", r("weight").alias("weight"), r("mu").alias("mu"), r("sd").alias("sd"))

    return f


for _name, _mode in (("gmm1d_loop", "loop"), ("gmm1d_script", "script"), ("gmm1d_client", "client"), ("gmm1d_dataframe", "dataframe")):
    QUERIES[_name] = _gmm1d_iterated(_mode)
    SQL[_name] = _FIVE

TEXT = """
ITERATE model (comp, weight, mu, sd)
START (SELECT comp, weight, mu, sd FROM relmix_start)
NEXT (SELECT a.comp, a.s / n.n AS weight, a.m AS mu, sqrt(b.v / a.s) AS sd FROM mass a JOIN spread b ON a.comp = b.comp CROSS JOIN size n)
LET joint AS (SELECT p.tid, p.x, model.comp, model.weight * npdf(p.x, model.mu, model.sd) AS f FROM relmix_points p CROSS JOIN model)
LET resp AS (SELECT tid, x, comp, f / sum(f) OVER (PARTITION BY tid) AS p FROM joint)
LET mass AS (SELECT comp, sum(p) AS s, sum(p * x) / sum(p) AS m FROM resp GROUP BY comp)
LET spread AS (SELECT q.comp, sum(q.p * (q.x - m.m) * (q.x - m.m)) AS v FROM resp q JOIN mass m ON q.comp = m.comp GROUP BY q.comp)
LET size AS (SELECT count(*) AS n FROM relmix_points)
REPLACE ON (comp)
MAX ROUNDS 5
THEN (SELECT comp, weight, mu, sd FROM model ORDER BY comp)
"""


def gmm1d_text(spark, d):
    from relmix.functions.udfs import register_npdf

    register_npdf(spark)
    customers(spark, d).select("tid", F.col("x0").alias("x")).createOrReplaceTempView("relmix_points")
    spark.createDataFrame([(c, w, m, v**0.5) for c, w, m, v in START_1D], "comp int, weight double, mu double, sd double").createOrReplaceTempView("relmix_start")
    out = iterate_sql(spark, TEXT)
    return out.select("comp", r("weight").alias("weight"), r("mu").alias("mu"), r("sd").alias("sd"))


QUERIES["gmm1d_text"] = gmm1d_text
SQL["gmm1d_text"] = _FIVE


def gmm1d_estep(spark, d):
    view = ModelView(Gaussian(1), START_1D_PARAMS)
    return view.posterior(customers(spark, d)).select("tid", "comp", r("p").alias("p"))


QUERIES["gmm1d_estep"] = gmm1d_estep
SQL["gmm1d_estep"] = _sql_1d(0, "SELECT tid, comp, round(p, 6) + 0.0 AS p FROM e0")

_LL = "(SELECT sum(lse) FROM (SELECT DISTINCT tid, lse FROM e{t}) z)"


def gmm1d_loglik_trace(spark, d):
    view = ModelView.of(fit(customers(spark, d), Gaussian(1), START_1D_PARAMS, 5))
    return view.trace(spark).select("round", F.round("loglik", 4).alias("loglik"))


QUERIES["gmm1d_loglik_trace"] = gmm1d_loglik_trace
SQL["gmm1d_loglik_trace"] = _sql_1d(5, " UNION ALL ".join(f"SELECT {t + 1} AS round, round({_LL.format(t=t)}, 4) AS loglik" for t in range(5)))


def gmm1d_until(spark, d):
    """Stops when the likelihood gains less than 2: after the fifth look at the data."""
    done = fit(customers(spark, d), Gaussian(1), START_1D_PARAMS, 8, eps=2.0)
    return spark.createDataFrame([(done.rounds(), done.converged)], "rounds int, converged boolean")


QUERIES["gmm1d_until"] = gmm1d_until
_GAINS = " UNION ALL ".join(f"SELECT {t + 1} AS t, {_LL.format(t=t)} - {_LL.format(t=t - 1)} AS gain" for t in range(1, 8))
SQL["gmm1d_until"] = _sql_1d(8, f"SELECT CAST(coalesce(min(CASE WHEN abs(gain) <= 2 THEN t END), 8) AS INT) AS rounds, coalesce(bool_or(abs(gain) <= 2), false) AS converged FROM ({_GAINS}) g")


def gmm1d_resume(spark, d):
    view = ModelView.of(fit(customers(spark, d), Gaussian(1), START_1D_PARAMS, 2))
    return _frame_1d(spark, view.resume(customers(spark, d), 3).params)


QUERIES["gmm1d_resume"] = gmm1d_resume
SQL["gmm1d_resume"] = _FIVE


# three dimensions -------------------------------------------------------------------------


def _frame_3d(spark, params, cov):
    names = emsql.names_of(3, cov)
    rows = [(k + 1, float(w), *map(float, m), *[float(s[int(n[1]), int(n[2])]) for n in names if n[0] == "s"]) for k, (w, m, s) in enumerate(zip(params["weight"], params["mu"], params["sigma"], strict=True))]
    df = spark.createDataFrame(rows, "comp int, w double, " + ", ".join(f"{n} double" for n in names))
    return df.select("comp", r("w").alias("weight"), *[r(n).alias(n) for n in names])


def _rfm(cov: str, plan: str, rounds: int = 4):
    def f(spark, d):
        data = rfm.gaussian_rows(rfm_z(spark, d))
        return _frame_3d(spark, fit(data, Gaussian(3, cov=cov), rfm_start(cov)[1], rounds, plan=plan).params, cov)

    return f


def _rfm_sql(cov: str, rounds: int = 4) -> str:
    names = emsql.names_of(3, cov)
    return emsql.gaussian(RFM_GAUSS, rfm_start(cov)[0], 3, cov, rounds) + f"\nSELECT comp, round(w, 6) + 0.0 AS weight, {', '.join(f'round({n}, 6) + 0.0 AS {n}' for n in names)} FROM m{rounds}"


for _name, _cov, _plan in (
    ("gmm_diag_rfm", "diag", "fused"),
    ("gmm_diag_wide", "diag", "wide"),
    ("gmm_diag_coordinate", "diag", "coordinate"),
    ("gmm_diag_hybrid", "diag", "hybrid"),
    ("gmm_full_rfm", "full", "fused"),
    ("gmm_full_rfm_arrow", "full", "arrow"),
    ("gmm_full_rfm_relational", "full", "relational"),
):
    QUERIES[_name] = _rfm(_cov, _plan)
    SQL[_name] = _rfm_sql(_cov)


def gmm_spherical_rfm(spark, d):
    data = rfm.gaussian_rows(rfm_z(spark, d))
    done = fit(data, Gaussian(3, cov="spherical"), rfm_start("diag")[1], 3)
    rows = [(k + 1, float(w), *map(float, m), float(s[0, 0])) for k, (w, m, s) in enumerate(zip(done.params["weight"], done.params["mu"], done.params["sigma"], strict=True))]
    df = spark.createDataFrame(rows, "comp int, w double, mu0 double, mu1 double, mu2 double, v double")
    return df.select("comp", r("w").alias("weight"), *[r(n).alias(n) for n in ("mu0", "mu1", "mu2", "v")])


def _shared(sql: str, tied: bool) -> str:
    """Spread the covariance of every M-step: over dimensions (spherical) or components (tied)."""
    for t in range(1, 4):
        if tied:
            body = ", ".join(f"sum(w * s{i}{j}) OVER () / sum(w) OVER () AS s{i}{j}" for i in range(3) for j in range(i, 3))
        else:
            body = ", ".join(f"(s00 + s11 + s22) / 3 AS s{i}{i}" for i in range(3))
        sql = sql.replace(f"m{t} AS MATERIALIZED (", f"raw{t} AS MATERIALIZED (", 1)
        at = sql.index(f"l{t} AS MATERIALIZED (")
        sql = sql[:at] + f"m{t} AS MATERIALIZED (SELECT comp, w, mu0, mu1, mu2, {body} FROM raw{t}),\n" + sql[at:]
    return sql


QUERIES["gmm_spherical_rfm"] = gmm_spherical_rfm
SQL["gmm_spherical_rfm"] = _shared(emsql.gaussian(RFM_GAUSS, rfm_start("diag")[0], 3, "diag", 3), False) + "\nSELECT comp, round(w, 6) + 0.0 AS weight, round(mu0, 6) + 0.0 AS mu0, round(mu1, 6) + 0.0 AS mu1, round(mu2, 6) + 0.0 AS mu2, round(s00, 6) + 0.0 AS v FROM m3"


def gmm_tied_rfm(spark, d):
    data = rfm.gaussian_rows(rfm_z(spark, d))
    return _frame_3d(spark, fit(data, Gaussian(3, cov="tied"), rfm_start("full")[1], 3).params, "full")


QUERIES["gmm_tied_rfm"] = gmm_tied_rfm
SQL["gmm_tied_rfm"] = _shared(emsql.gaussian(RFM_GAUSS, rfm_start("full")[0], 3, "full", 3), True) + "\nSELECT comp, round(w, 6) + 0.0 AS weight, " + ", ".join(f"round({n}, 6) + 0.0 AS {n}" for n in emsql.names_of(3, "full")) + " FROM m3"


def gmm_full_2d(spark, d):
    done = fit(planted.gauss(spark, d), Gaussian(2), planted_start()[1], 3)
    rows = [(k + 1, float(w), float(m[0]), float(m[1]), float(s[0, 0]), float(s[0, 1]), float(s[1, 1])) for k, (w, m, s) in enumerate(zip(done.params["weight"], done.params["mu"], done.params["sigma"], strict=True))]
    df = spark.createDataFrame(rows, "comp int, w double, mu0 double, mu1 double, s00 double, s01 double, s11 double")
    return df.select("comp", *[r(n).alias(n) for n in df.columns[1:]])


QUERIES["gmm_full_2d"] = gmm_full_2d
SQL["gmm_full_2d"] = emsql.gaussian(planted.gauss_sql(2), planted_start()[0], 2, "full", 3) + "\nSELECT comp, " + ", ".join(f"round({n}, 6) + 0.0 AS {n}" for n in ("w", "mu0", "mu1", "s00", "s01", "s11")) + " FROM m3"


# regression mixtures ----------------------------------------------------------------------

MLR_START = [(1, 0.4, 0.8, -0.5, 0.5), (2, 0.6, 0.8, 0.5, 0.5)]
MOE_START = [(1, 0.1, 0.0, 0.8, -0.5, 0.5), (2, -0.1, 0.0, 0.8, 0.5, 0.5)]
MLR_PARAMS = {"weight": np.array([0.4, 0.6]), "beta": np.array([[0.8, -0.5], [0.8, 0.5]]), "var": np.array([0.5, 0.5])}
MOE_PARAMS = {"theta": np.array([[0.1, 0.0], [-0.1, 0.0]]), "beta": np.array([[0.8, -0.5], [0.8, 0.5]]), "var": np.array([0.5, 0.5])}


def money(spark, d):
    """Frequency as the feature, money as the target."""
    return rfm_z(spark, d).select("tid", F.col("f").alias("x0"), F.col("m").alias("y"))


def _mlr(plan):
    def f(spark, d):
        p = fit(money(spark, d), LinearMixture(1), MLR_PARAMS, 3, plan=plan).params
        df = spark.createDataFrame([(k + 1, float(p["weight"][k]), *map(float, p["beta"][k]), float(p["var"][k])) for k in range(2)], "comp int, w double, b0 double, b1 double, v double")
        return df.select("comp", *[r(n).alias(n) for n in df.columns[1:]])

    return f


def _moe(plan):
    def f(spark, d):
        p = fit(money(spark, d), ExpertMixture(1), MOE_PARAMS, 3, plan=plan).params
        df = spark.createDataFrame([(k + 1, *map(float, p["theta"][k]), *map(float, p["beta"][k]), float(p["var"][k])) for k in range(2)], "comp int, g0 double, g1 double, b0 double, b1 double, v double")
        return df.select("comp", *[r(n, 5).alias(n) for n in df.columns[1:]])

    return f


_MLR_SQL = emsql.regression(RFM_REG, MLR_START, 3, False) + "\nSELECT comp, " + ", ".join(f"round({n}, 6) + 0.0 AS {n}" for n in ("w", "b0", "b1", "v")) + " FROM m3"
_MOE_SQL = emsql.regression(RFM_REG, MOE_START, 3, True) + "\nSELECT comp, " + ", ".join(f"round({n}, 5) + 0.0 AS {n}" for n in ("g0", "g1", "b0", "b1", "v")) + " FROM m3"
for _plan in ("fused", "arrow"):
    _tail = "" if _plan == "fused" else "_arrow"
    QUERIES[f"mlr_round3{_tail}"], SQL[f"mlr_round3{_tail}"] = _mlr(_plan), _MLR_SQL
    QUERIES[f"moe_round3{_tail}"], SQL[f"moe_round3{_tail}"] = _moe(_plan), _MOE_SQL


def mlr_predict(spark, d):
    return ModelView(LinearMixture(1), MLR_PARAMS).predict(money(spark, d)).select("tid", r("prediction").alias("prediction"))


def moe_gate(spark, d):
    return ModelView(ExpertMixture(1), MOE_PARAMS).gates(money(spark, d)).select("tid", "comp", r("g").alias("g"))


def moe_predict(spark, d):
    return ModelView(ExpertMixture(1), MOE_PARAMS).predict(money(spark, d)).select("tid", r("prediction").alias("prediction"))


QUERIES |= {"mlr_predict": mlr_predict, "moe_gate": moe_gate, "moe_predict": moe_predict}
SQL["mlr_predict"] = f"SELECT tid, round(0.4e0 * (0.8e0 * x0 - 0.5e0) + 0.6e0 * (0.8e0 * x0 + 0.5e0), 6) + 0.0 AS prediction FROM ({RFM_REG}) z"
SQL["moe_gate"] = f"WITH z AS ({RFM_REG}) SELECT tid, 1 AS comp, round(exp(0.1e0 * x0) / (exp(0.1e0 * x0) + exp(-0.1e0 * x0)), 6) + 0.0 AS g FROM z UNION ALL SELECT tid, 2, round(exp(-0.1e0 * x0) / (exp(0.1e0 * x0) + exp(-0.1e0 * x0)), 6) + 0.0 FROM z"
SQL["moe_predict"] = f"WITH z AS ({RFM_REG}), g AS (SELECT *, exp(0.1e0 * x0) / (exp(0.1e0 * x0) + exp(-0.1e0 * x0)) AS a FROM z) SELECT tid, round(a * (0.8e0 * x0 - 0.5e0) + (1 - a) * (0.8e0 * x0 + 0.5e0), 6) + 0.0 AS prediction FROM g"


def moe_gate_variants(spark, d):
    """Likelihood after three rounds by gate: least squares, one Newton step, inner Newton loop."""
    rows = []
    for gate, steps in (("ls", 1), ("newton1", 1), ("irls", 4)):
        done = fit(money(spark, d), ExpertMixture(1, gate=gate), MOE_PARAMS, 4, gate_steps=steps)
        rows.append((gate, done.trace[-1][1], done.trace[-1][1] > done.trace[0][1]))
    return spark.createDataFrame(rows, "gate string, loglik double, improved boolean")


def gmm_high_dimension(spark, d):
    """64 dimensions, diagonal: the Arrow plan by choice of the planner."""
    emb = bind_vector(table(spark, d, "embeddings"), "embedding", 64, "vec_id")
    from relmix.models.init import init_spread

    family = Gaussian(64, cov="diag", floor=1e-4)
    done = fit(emb, family, init_spread(emb, family, 5, 3), 3)
    return ModelView.of(done).trace(spark).select("round", "loglik")


def descent_regression(spark, d):
    bind_features(table(spark, d, "lineitem"), ["l_discount"], y="l_tax").select(F.col("x0").alias("x"), "y").createOrReplaceTempView("relmix_descent")
    out = run(spark, recursion.descent_spec("relmix_descent", 0.5, 4)).result
    return out.select(r("a").alias("a"), r("b").alias("b"))


QUERIES |= {"moe_gate_variants": moe_gate_variants, "gmm_high_dimension": gmm_high_dimension, "descent_regression": descent_regression}
_D = ["WITH d AS (SELECT l_discount AS x, l_tax AS y FROM lineitem)", "w0 AS (SELECT 0.0e0 AS a, 0.0e0 AS b)"]
for _t in range(4):
    _D.append(f"w{_t + 1} AS (SELECT max(a) - 0.5e0 * avg(a + b * x - y) AS a, max(b) - 0.5e0 * avg((a + b * x - y) * x) AS b FROM d CROSS JOIN w{_t})")
SQL["descent_regression"] = ", ".join(_D) + " SELECT round(a, 6) + 0.0 AS a, round(b, 6) + 0.0 AS b FROM w4"
