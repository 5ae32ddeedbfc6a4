"""Linear algebra as joins and aggregates over a semiring.

Vector: (i, v). Matrix: (r, c, v), absent cells being the semiring's zero. The aggregate combines
before the shuffle. A side is broadcast only if the caller has proven its size (``small=True``).
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Semiring:
    name: str
    plus: Callable[[Column], Column]  # an aggregate
    times: Callable[[Column, Column], Column]
    zero: float | bool


SUM_TIMES = Semiring("sum_times", F.sum, lambda a, b: a * b, 0.0)
MIN_PLUS = Semiring("min_plus", F.min, lambda a, b: a + b, float("inf"))
MAX_PLUS = Semiring("max_plus", F.max, lambda a, b: a + b, float("-inf"))
MAX_TIMES = Semiring("max_times", F.max, lambda a, b: a * b, 0.0)
MAX_MIN = Semiring("max_min", F.max, lambda a, b: F.least(a, b), float("-inf"))
OR_AND = Semiring("or_and", F.bool_or, lambda a, b: a & b, False)
SEMIRINGS = {s.name: s for s in (SUM_TIMES, MIN_PLUS, MAX_PLUS, MAX_TIMES, MAX_MIN, OR_AND)}


def _side(df: DataFrame, small: bool) -> DataFrame:
    return F.broadcast(df) if small else df


def mv_join(e: DataFrame, v: DataFrame, semiring: Semiring = SUM_TIMES, small: bool = False) -> DataFrame:
    """Matrix times vector -> (i, v)."""
    right = _side(v.select(F.col("i").alias("c"), F.col("v").alias("w")), small)
    return e.join(right, "c").groupBy(F.col("r").alias("i")).agg(semiring.plus(semiring.times(F.col("v"), F.col("w"))).alias("v"))


def mm_join(e: DataFrame, e2: DataFrame, semiring: Semiring = SUM_TIMES, small: bool = False) -> DataFrame:
    """Matrix times matrix -> (r, c, v)."""
    left = e.select("r", F.col("c").alias("k"), F.col("v").alias("a"))
    right = _side(e2.select(F.col("r").alias("k"), "c", F.col("v").alias("b")), small)
    return left.join(right, "k").groupBy("r", "c").agg(semiring.plus(semiring.times(F.col("a"), F.col("b"))).alias("v"))


def hadamard_rowsum(e: DataFrame, e2: DataFrame, semiring: Semiring = SUM_TIMES) -> DataFrame:
    """Element-wise product folded per row -> (i, v)."""
    both = e.select("r", "c", F.col("v").alias("a")).join(e2.select("r", "c", F.col("v").alias("b")), ["r", "c"])
    return both.groupBy(F.col("r").alias("i")).agg(semiring.plus(semiring.times(F.col("a"), F.col("b"))).alias("v"))


def hadamard_vectors(weights: DataFrame, vectors: DataFrame, d: int) -> DataFrame:
    """The tensor variant: scalar cells (r, c, v) times vector cells (r, c, x), vectors summed per row -> (i, x)."""
    from relmix.functions.vectors import scale, vec_sum

    both = weights.join(vectors, ["r", "c"])
    return both.groupBy(F.col("r").alias("i")).agg(vec_sum(scale(F.col("v"), F.col("x")), d).alias("x"))


def matrix_add(e: DataFrame, e2: DataFrame, semiring: Semiring = SUM_TIMES) -> DataFrame:
    return e.select("r", "c", "v").unionByName(e2.select("r", "c", "v")).groupBy("r", "c").agg(semiring.plus(F.col("v")).alias("v"))


def transpose(e: DataFrame) -> DataFrame:
    return e.select(F.col("c").alias("r"), F.col("r").alias("c"), "v")
