"""Relational plan: the readable join-and-window form of a round for Gaussian mixtures.

R: every row with every component, density times weight, normalised by a window over the row's id;
N: responsibilities joined back to the rows, weights and means by component; C: squared deviations
from the new means, joined to responsibilities, summed by component; then N and C are joined into
the new model relation. The cost is n * K rows through shuffles, so this plan is for reading, for
text-defined iterations and for moderate data; the fused plan gives the same numbers in one scan.

The model relation has K rows, which bounds its broadcast.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from relmix.functions.vectors import dot, outer, scale, subtract, vec_sum
from relmix.models.families import LOG_2PI, Gaussian, Params
from relmix.plans.base import Round


def model_relation(data: DataFrame, family: Gaussian, params: Params) -> DataFrame:
    """(comp, weight, mu, white, shift): white = inverse Cholesky factor by rows, shift = log normaliser."""
    rows = []
    for k in range(family.k(params)):
        low = np.linalg.inv(np.linalg.cholesky(params["sigma"][k]))
        shift = float(np.log(np.diag(low)).sum()) - 0.5 * family.d * LOG_2PI
        rows.append((k, float(params["weight"][k]), params["mu"][k].tolist(), low.tolist(), shift))
    return data.sparkSession.createDataFrame(rows, "comp int, weight double, mu array<double>, white array<array<double>>, shift double")


def responsibilities(x: DataFrame, model: DataFrame, raw: bool = False) -> DataFrame:
    """(tid, comp, p). ``raw`` divides densities directly, which underflows to 0 / 0 far from all means."""
    pairs = x.crossJoin(F.broadcast(model))
    z = F.transform("white", lambda row: dot(row, subtract(F.col("x"), F.col("mu"))))
    logs = F.log("weight") + F.col("shift") - 0.5 * dot(z, z)
    by_row = Window.partitionBy("tid")
    if raw:
        dense = pairs.withColumn("f", F.exp(logs))
        return dense.select("tid", "comp", (F.col("f") / F.sum("f").over(by_row)).alias("p"))
    lifted = pairs.withColumn("l", logs).withColumn("top", F.max("l").over(by_row))
    return lifted.withColumn("f", F.exp(F.col("l") - F.col("top"))).select("tid", "comp", (F.col("f") / F.sum("f").over(by_row)).alias("p"), "l", "top", "f")


def step(x: DataFrame, family: Gaussian, params: Params) -> tuple[DataFrame, DataFrame]:
    """(new model relation (comp, weight, mu, sigma flat), responsibilities) of one round; ``x`` is (tid, x ARRAY)."""
    d = family.d
    r = responsibilities(x, model_relation(x, family, params))
    joined = r.join(x, "tid")
    n = joined.groupBy("comp").agg(F.sum("p").alias("s"), vec_sum(scale(F.col("p"), F.col("x")), d).alias("v"))
    n = n.select("comp", "s", scale(1 / F.col("s"), F.col("v")).alias("mean"))
    # the new means have K rows
    t = x.crossJoin(F.broadcast(n.select("comp", "mean"))).select("tid", "comp", outer(subtract(F.col("x"), F.col("mean")), subtract(F.col("x"), F.col("mean"))).alias("t"))
    c = r.join(t, ["tid", "comp"]).groupBy("comp").agg(vec_sum(scale(F.col("p"), F.col("t")), d * d).alias("cov"))
    size = x.agg(F.count(F.lit(1)).alias("n"))
    model = n.join(c, "comp").crossJoin(F.broadcast(size)).select("comp", (F.col("s") / F.col("n")).alias("weight"), F.col("mean").alias("mu"), scale(1 / F.col("s"), F.col("cov")).alias("sigma"), "s", "n")
    return model, r


def run_round(data: DataFrame, family: Gaussian, params: Params, groups: int = 0) -> Round:
    """The same statistics as the other plans, from the relational step; ``data`` must have ``tid``."""
    x = data.select("tid", F.array(*[F.col(c) for c in family.columns]).alias("x"))
    model, r = step(x, family, params)
    rows = {row["comp"]: row for row in model.collect()}
    loglik = r.groupBy("tid").agg((F.max("top") + F.log(F.sum("f"))).alias("lse")).agg(F.sum("lse")).head()[0]
    flat = []
    for k in range(family.k(params)):
        s0 = rows[k]["s"]
        shift = np.array(rows[k]["mu"]) - params["mu"][k]
        cov = np.array(rows[k]["sigma"]).reshape(family.d, family.d) + np.outer(shift, shift)
        flat += [s0, *(s0 * shift), *[s0 * cov[i, j] for i, j in family.pairs()]]
    return Round(float(rows[0]["n"]), float(loglik), np.array(flat))
