"""SQL and Python function surface: densities, a grouped-statistics aggregate and table functions.

``npdf`` is a SQL function, which Catalyst inlines into the projection; ``mvn_logpdf`` is an Arrow
function for high dimensions; ``gmm_stats`` is a grouped aggregate in pandas for groups of bounded
size (the fused plan is the scalable way); the table functions serve small relations.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F

LOG_2PI = float(np.log(2 * np.pi))


def register_npdf(spark: SparkSession) -> None:
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION npdf(x DOUBLE, mu DOUBLE, sd DOUBLE) RETURNS DOUBLE RETURN exp(-0.5D * (x - mu) / sd * (x - mu) / sd) / (sd * 2.5066282746310002D)")


def npdf(x: Column, mu: Column, sd: Column) -> Column:
    """Normal density with the standard deviation as the third argument."""
    z = (x - mu) / sd
    return F.exp(-0.5 * z * z) / (sd * F.lit(2.5066282746310002))


def mvn_logpdf(mu: np.ndarray, sigma: np.ndarray):
    """An Arrow function of an ARRAY<DOUBLE> column: ln N(x; mu, sigma), a whole batch at a time."""
    low = np.linalg.inv(np.linalg.cholesky(np.asarray(sigma, float)))
    shift = float(np.log(np.diag(low)).sum()) - 0.5 * len(low) * LOG_2PI
    centre = np.asarray(mu, float)

    @F.pandas_udf("double")
    def logpdf(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        for x in batches:
            z = (np.stack(x.to_numpy()) - centre) @ low.T if len(x) else np.zeros((0, len(centre)))
            yield pd.Series(shift - 0.5 * (z * z).sum(1))

    return logpdf


def gmm_stats():
    """Grouped aggregate: packed (sum p, sum p x, sum p x^2) of a weighted scalar group as an array."""

    @F.pandas_udf("array<double>")
    def stats(p: pd.Series, x: pd.Series) -> list:
        return [float(p.sum()), float((p * x).sum()), float((p * x * x).sum())]

    return stats


def register_tables(spark: SparkSession) -> None:
    """Table functions: ``component_table(json)`` lists a model's rows, ``mixture_sample(n, seed, json)`` draws from it."""
    from pyspark.sql.functions import udtf

    @udtf(returnType="comp int, weight double, mu double, sd double")
    class ComponentTable:
        def eval(self, model: str):
            import json

            for row in json.loads(model):
                yield int(row[0]), float(row[1]), float(row[2]), float(row[3])

    @udtf(returnType="tid bigint, comp int, x double")
    class MixtureSample:
        def eval(self, n: int, seed: int, model: str):
            import json

            rows = json.loads(model)
            rng = np.random.default_rng(seed)
            pick = rng.choice(len(rows), n, p=np.array([r[1] for r in rows]) / sum(r[1] for r in rows))
            for i, k in enumerate(pick):
                yield i, int(rows[k][0]), float(rng.normal(rows[k][2], rows[k][3]))

    spark.udtf.register("component_table", ComponentTable)
    spark.udtf.register("mixture_sample", MixtureSample)
