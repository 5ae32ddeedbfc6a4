"""Frames, fixed models and SQL texts that several queries share."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from relmix.models.families import Gaussian, Params, gaussian1d
from relmix.operators.features import bind_features
from relmix.view.model_view import ModelView
from relmix.workloads import planted, rfm


def r(c: Column | str, digits: int = 6) -> Column:
    return F.round(F.col(c) if isinstance(c, str) else c, digits) + F.lit(0.0)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def customers(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bind_features(table(spark, sf_dir, "customer").withColumn("x", F.col("c_acctbal") / 1000), ["x"], tid="c_custkey")


CUSTOMERS = "SELECT c_custkey AS tid, c_acctbal / 1000 AS x0 FROM customer"
START_1D = [(1, 0.34, 0.0, 4.0), (2, 0.33, 5.0, 4.0), (3, 0.33, 9.0, 4.0)]
START_1D_PARAMS = gaussian1d([0.34, 0.33, 0.33], [0.0, 5.0, 9.0], [2.0, 2.0, 2.0])

#: A fixed trained model for inference queries: comp, weight, mean, variance.
FIXED = [(1, 0.3, 1.0, 1.44), (2, 0.4, 4.5, 3.24), (3, 0.3, 8.4, 1.1025)]
FIXED_PARAMS = gaussian1d([0.3, 0.4, 0.3], [1.0, 4.5, 8.4], [1.2, 1.8, 1.05])


def fixed_view() -> ModelView:
    return ModelView(Gaussian(1), FIXED_PARAMS)


def rfm_z(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rfm.scaled(rfm.orders(spark, sf_dir))


RFM = "SELECT o_custkey AS tid, CAST(date_diff('day', CAST(max(o_orderdate) AS DATE), DATE '2001-08-02') AS DOUBLE) AS r, CAST(count(*) AS DOUBLE) AS f, sum(o_totalprice) AS m FROM orders GROUP BY o_custkey"
RFM_Z = f"SELECT tid, (r - (SELECT avg(r) FROM b)) / (SELECT stddev_pop(r) FROM b) AS r, (f - (SELECT avg(f) FROM b)) / (SELECT stddev_pop(f) FROM b) AS f, (m - (SELECT avg(m) FROM b)) / (SELECT stddev_pop(m) FROM b) AS m FROM b"
RFM_GAUSS = f"WITH b AS ({RFM}) SELECT tid, r AS x0, f AS x1, m AS x2 FROM ({RFM_Z}) z"
RFM_REG = f"WITH b AS ({RFM}) SELECT tid, f AS x0, m AS y FROM ({RFM_Z}) z"

RFM_MU = [(-0.5, 0.8, 0.8), (-0.3, -0.2, -0.3), (1.5, -1.0, -1.0), (0.2, 0.3, 0.1)]


def rfm_start(cov: str) -> tuple[list[tuple], Params]:
    rows = []
    for k, mu in enumerate(RFM_MU):
        s = [1.0, 1.0, 1.0] if cov == "diag" else [1.0, 0.0, 0.0, 1.0, 0.0, 1.0]
        rows.append((k + 1, 0.25, *mu, *s))
    return rows, {"weight": np.full(4, 0.25), "mu": np.array(RFM_MU), "sigma": np.repeat(np.eye(3)[None], 4, 0)}


def planted_start(k: int = 10) -> tuple[list[tuple], Params]:
    p = planted.true_start(2, k)
    return [(i + 1, 1 / k, float(m[0]), float(m[1]), 1.0, 0.0, 1.0) for i, m in enumerate(p["mu"])], p
