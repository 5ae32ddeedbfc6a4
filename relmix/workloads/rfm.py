"""Market segmentation: recency, frequency and money of customers."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from relmix.operators.features import zscore

END = "2001-08-02"


def orders(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(tid, r, f, m): days from the last order to END, orders, total price; one shuffle by customer."""
    o = spark.read.parquet(f"{sf_dir}/orders.parquet")
    days = F.datediff(F.lit(END).cast("date"), F.max(F.col("o_orderdate").cast("date")))
    return o.groupBy(F.col("o_custkey").alias("tid")).agg(days.cast("double").alias("r"), F.count(F.lit(1)).cast("double").alias("f"), F.sum("o_totalprice").alias("m"))


def events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same from purchase events by user."""
    e = spark.read.parquet(f"{sf_dir}/events.parquet").filter("event_type = 'purchase'")
    days = F.datediff(F.lit("2024-02-01").cast("date"), F.max(F.col("ts").cast("date")))
    return e.groupBy(F.col("user_id").alias("tid")).agg(days.cast("double").alias("r"), F.count(F.lit(1)).cast("double").alias("f"), F.sum("value").alias("m"))


def scaled(df: DataFrame) -> DataFrame:
    return zscore(df, ["r", "f", "m"])


def gaussian_rows(df: DataFrame) -> DataFrame:
    return df.select("tid", F.col("r").alias("x0"), F.col("f").alias("x1"), F.col("m").alias("x2"))


def regression_rows(df: DataFrame) -> DataFrame:
    """Features R and F, target M."""
    return df.select("tid", F.col("r").alias("x0"), F.col("f").alias("x1"), F.col("m").alias("y"))


def segment(spark: SparkSession, sf_dir: str, family: str = "gaussian", k: int = 4, rounds: int = 15, seed: int = 1) -> DataFrame:
    """(tid, r, f, m, comp): customers with the segment that a fitted model gives them."""
    import numpy as np

    from relmix.models.em import fit
    from relmix.models.families import ExpertMixture, Gaussian, LinearMixture
    from relmix.models.init import init_spread
    from relmix.session import stored
    from relmix.view.model_view import ModelView

    rows = stored(scaled(orders(spark, sf_dir)), "rfm")
    rng = np.random.default_rng(seed)
    if family == "gaussian":
        data, model = gaussian_rows(rows), Gaussian(3, ridge=1e-4)
        start = init_spread(data, model, k, seed)
    else:
        data = regression_rows(rows)
        start = {"beta": rng.uniform(-1, 1, (k, 3)), "var": np.full(k, 1.0)}
        if family == "linear":
            model, start = LinearMixture(2, floor=1e-4), start | {"weight": np.full(k, 1 / k)}
        else:
            model, start = ExpertMixture(2, floor=1e-4), start | {"theta": rng.uniform(-0.1, 0.1, (k, 3))}
    view = ModelView.of(fit(data, model, start, rounds))
    return rows.join(view.assign(data), "tid")
