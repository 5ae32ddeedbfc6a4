"""Baseline plans over the older layouts, for diagonal Gaussian mixtures.

``coordinate``: rows (tid, c, x); the exponent is a join with the model in the same layout and a sum
by (tid, comp); means and variances are sums by (comp, c).
``wide``: one expression per dimension, sums per component and dimension.
``hybrid``: both copies; the E-step reads the wide one, the M-step sends one statement per component
for its mean and one for its variance, 2K in all, each scanning the data.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from relmix.models.families import LOG_2PI, Gaussian, Params
from relmix.operators.layouts import vector_to_coordinate
from relmix.plans.base import Round
from relmix.plans.fused import posterior_columns


def _model(data: DataFrame, family: Gaussian, params: Params) -> DataFrame:
    """The model in coordinate layout: K * d rows."""
    rows = [(k, j + 1, float(params["mu"][k, j]), float(params["sigma"][k, j, j])) for k in range(family.k(params)) for j in range(family.d)]
    return data.sparkSession.createDataFrame(rows, "comp int, c int, mu double, var double")


def _weights(data: DataFrame, params: Params) -> DataFrame:
    return data.sparkSession.createDataFrame([(k, float(w)) for k, w in enumerate(params["weight"])], "comp int, weight double")


def _back(family: Gaussian, params: Params, n: float, loglik: float, parts: dict[int, tuple[float, np.ndarray, np.ndarray]]) -> Round:
    """(mass, mean, variance) by component as statistics about the entering means."""
    flat = []
    for k in range(family.k(params)):
        s0, mean, var = parts[k]
        shift = mean - params["mu"][k]
        flat += [s0, *(s0 * shift), *(s0 * (var + shift**2))]
    return Round(n, loglik, np.array(flat))


def coordinate_round(data: DataFrame, family: Gaussian, params: Params, groups: int = 0) -> Round:
    """``data`` has tid and x0..; it is turned into n * d rows first."""
    cells = vector_to_coordinate(data.select("tid", F.array(*family.columns).alias("x")))
    joined = cells.join(F.broadcast(_model(data, family, params)), "c")  # K * d rows
    part = -0.5 * (F.log("var") + LOG_2PI + F.pow(F.col("x") - F.col("mu"), 2) / F.col("var"))
    logs = joined.groupBy("tid", "comp").agg(F.sum(part).alias("q")).join(F.broadcast(_weights(data, params)), "comp")
    by_row = Window.partitionBy("tid")
    logs = logs.withColumn("l", F.log("weight") + F.col("q")).withColumn("top", F.max("l").over(by_row))
    logs = logs.withColumn("lse", F.col("top") + F.log(F.sum(F.exp(F.col("l") - F.col("top"))).over(by_row)))
    r = logs.select("tid", "comp", F.exp(F.col("l") - F.col("lse")).alias("p"), "lse")
    means = r.join(cells, "tid").groupBy("comp", "c").agg(F.sum("p").alias("s"), (F.sum(F.col("p") * F.col("x")) / F.sum("p")).alias("mean"))
    spread = r.join(cells, "tid").join(F.broadcast(means), ["comp", "c"]).groupBy("comp", "c").agg(F.first("s").alias("s"), F.first("mean").alias("mean"), (F.sum(F.col("p") * F.pow(F.col("x") - F.col("mean"), 2)) / F.sum("p")).alias("var"))
    totals = r.filter("comp = 0").agg(F.count(F.lit(1)).alias("n"), F.sum("lse").alias("l")).head()
    rows = sorted(spread.collect(), key=lambda x: (x["comp"], x["c"]))
    parts = {}
    for k in range(family.k(params)):
        own = [x for x in rows if x["comp"] == k]
        parts[k] = (own[0]["s"], np.array([x["mean"] for x in own]), np.array([x["var"] for x in own]))
    return _back(family, params, float(totals["n"]), float(totals["l"]), parts)


def wide_round(data: DataFrame, family: Gaussian, params: Params, groups: int = 0) -> Round:
    """Two scans: masses and means per dimension, then variances about the new means."""
    rows = posterior_columns(data.select(*family.columns), family, params)
    n_comp, d = family.k(params), family.d
    first = [F.count(F.lit(1)), F.sum("lse")] + [F.sum(f"p{k}") for k in range(n_comp)] + [F.sum(F.col(f"p{k}") * F.col(f"x{j}")) for k in range(n_comp) for j in range(d)]
    got = np.array([float(v) for v in rows.agg(*first).head()])
    mass, means = got[2 : 2 + n_comp], got[2 + n_comp :].reshape(n_comp, d) / got[2 : 2 + n_comp, None]
    second = [F.sum(F.col(f"p{k}") * F.pow(F.col(f"x{j}") - F.lit(float(means[k, j])), 2)) for k in range(n_comp) for j in range(d)]
    var = np.array([float(v) for v in rows.agg(*second).head()]).reshape(n_comp, d) / mass[:, None]
    return _back(family, params, got[0], got[1], {k: (mass[k], means[k], var[k]) for k in range(n_comp)})


def hybrid_round(data: DataFrame, family: Gaussian, params: Params, groups: int = 0) -> Round:
    """E-step on the wide copy, then 2K statements over the long copy."""
    x = data.select("tid", *family.columns)
    posts = posterior_columns(x, family, params)
    n_comp = family.k(params)
    totals = posts.agg(F.count(F.lit(1)).alias("n"), F.sum("lse").alias("l")).head()
    cells = vector_to_coordinate(x.select("tid", F.array(*family.columns).alias("x")))
    r = posts.select("tid", F.posexplode(F.array(*[f"p{k}" for k in range(n_comp)])).alias("comp", "p"))
    parts = {}
    for k in range(n_comp):
        own = r.filter(F.col("comp") == k).join(cells, "tid")
        mean = {row["c"]: (row["s"], row["m"]) for row in own.groupBy("c").agg(F.sum("p").alias("s"), (F.sum(F.col("p") * F.col("x")) / F.sum("p")).alias("m")).collect()}
        centre = F.element_at(F.array(*[F.lit(float(mean[j + 1][1])) for j in range(family.d)]), F.col("c"))
        var = {row["c"]: row["v"] for row in own.groupBy("c").agg((F.sum(F.col("p") * F.pow(F.col("x") - centre, 2)) / F.sum("p")).alias("v")).collect()}
        parts[k] = (mean[1][0], np.array([mean[j + 1][1] for j in range(family.d)]), np.array([var[j + 1] for j in range(family.d)]))
    return _back(family, params, float(totals["n"]), float(totals["l"]), parts)
