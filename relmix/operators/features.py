"""Feature frames: binding, scaling and the policy for invalid numbers."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


class InvalidRowsError(ValueError):
    """A feature is null, NaN or infinite and the policy is ``error``."""


def bind_features(data: DataFrame | str, x: list[str], y: str | None = None, tid: str | None = None, on_invalid: str = "drop", spark: SparkSession | None = None) -> DataFrame:
    """(tid?, x0.., y?) as doubles from a frame or a SQL query.

    One NaN would poison every component's sums: ``drop`` filters such rows, ``error`` raises if one
    exists (one extra scan).
    """
    df = spark.sql(data) if isinstance(data, str) else data
    picked = [F.col(tid).alias("tid")] if tid else []
    picked += [F.col(c).cast("double").alias(f"x{j}") for j, c in enumerate(x)]
    picked += [F.col(y).cast("double").alias("y")] if y else []
    out = df.select(*picked)
    names = [c for c in out.columns if c != "tid"]
    good = F.lit(True)
    for c in names:
        good = good & F.col(c).isNotNull() & ~F.isnan(c) & (F.abs(F.col(c)) != F.lit(float("inf")))
    if on_invalid == "error":
        bad = out.filter(~good | good.isNull()).limit(1).count()
        if bad:
            raise InvalidRowsError("a feature is null, NaN or infinite")
        return out
    return out.filter(good)


def bind_vector(df: DataFrame, vector: str, d: int, tid: str | None = None) -> DataFrame:
    """(tid?, x0..) from an array column."""
    picked = [F.col(tid).alias("tid")] if tid else []
    return df.select(*picked, *[F.element_at(vector, j + 1).cast("double").alias(f"x{j}") for j in range(d)])


def zscore(df: DataFrame, cols: list[str], scale: str = "sd") -> DataFrame:
    """(x - mean) / sd (population), or / variance; the one-row moments are joined, not collected."""
    stats = df.agg(*[F.avg(c).alias(f"__m_{c}") for c in cols], *[(F.stddev_pop(c) if scale == "sd" else F.var_pop(c)).alias(f"__s_{c}") for c in cols])
    joined = df.crossJoin(F.broadcast(stats))  # one row
    return joined.select(*[((F.col(c) - F.col(f"__m_{c}")) / F.col(f"__s_{c}")).alias(c) if c in cols else F.col(c) for c in df.columns])


def minmax(df: DataFrame, cols: list[str]) -> DataFrame:
    stats = df.agg(*[F.min(c).alias(f"__a_{c}") for c in cols], *[F.max(c).alias(f"__b_{c}") for c in cols])
    joined = df.crossJoin(F.broadcast(stats))  # one row
    return joined.select(*[((F.col(c) - F.col(f"__a_{c}")) / F.nullif(F.col(f"__b_{c}") - F.col(f"__a_{c}"), F.lit(0.0))).alias(c) if c in cols else F.col(c) for c in df.columns])
