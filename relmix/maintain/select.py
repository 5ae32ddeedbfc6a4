"""Choosing the old rows that take part in an incremental update."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from relmix.view.model_view import ModelView


def select_distance(df: DataFrame, view: ModelView, radius: float | None = None, budget: int | None = None, tid: str = "tid") -> DataFrame:
    """Rows outside ``radius`` of every component, and/or the ``budget`` farthest; ties by tid."""
    rows = _measured(df, view, tid)
    if radius is not None:
        rows = rows.filter(F.col("min_mahalanobis") > radius)
    if budget is not None:
        rows = rows.orderBy(F.col("min_mahalanobis").desc(), tid).limit(budget)
    return rows


def select_entropy(df: DataFrame, view: ModelView, budget: int | None = None, threshold: float | None = None, tid: str = "tid") -> DataFrame:
    """Rows of the greatest posterior entropy (at most ln K): the ones whose membership is least settled."""
    rows = _measured(df, view, tid)
    if threshold is not None:
        rows = rows.filter(F.col("entropy") >= threshold)
    if budget is not None:
        rows = rows.orderBy(F.col("entropy").desc(), tid).limit(budget)
    return rows


def _measured(df: DataFrame, view: ModelView, tid: str) -> DataFrame:
    """The rows with both measures, row-local."""
    from relmix.models.families import Gaussian
    from relmix.view.model_view import entropy, mahalanobis

    scored = view.scored(df).withColumn("entropy", entropy(F.col("p")))
    distance = mahalanobis(view.family, view.params) if isinstance(view.family, Gaussian) else F.lit(None).cast("double")
    return scored.withColumn("min_mahalanobis", distance).select(*df.columns, "entropy", "min_mahalanobis")


def select_none(df: DataFrame) -> DataFrame:
    return df.limit(0)


def select_all(df: DataFrame) -> DataFrame:
    return df


def select_random(df: DataFrame, budget: int, seed: int = 0, tid: str = "tid") -> DataFrame:
    """The rows of smallest seeded hash of the id."""
    return df.orderBy(F.md5(F.concat(F.col(tid).cast("string"), F.lit(f":{seed}"))), tid).limit(budget)


def budget_threshold(df: DataFrame, view: ModelView, budget: int, n: int, tid: str = "tid") -> float:
    """For budgets too large for a top-k: the entropy above which about ``budget`` rows lie."""
    q = max(0.0, 1 - budget / max(n, 1))
    return float(_measured(df, view, tid).agg(F.percentile_approx("entropy", q, 100_000)).head()[0])
