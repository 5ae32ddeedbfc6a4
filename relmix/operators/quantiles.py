"""Exact order statistics without a global sort: approximate bounds, exact counts, a small rest."""

from __future__ import annotations

import math
from collections.abc import Sequence
from decimal import Decimal

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

ACCURACY = 10_000
MARGIN = 5 / ACCURACY  # five times the error of the bounds, as a share of the rows


def rank_of(step: float, n: int) -> int:
    """The least rank (from 1) that is not below ``step`` of ``n`` rows."""
    return max(1, math.ceil(Decimal(repr(step)) * n))


def order_statistics(df: DataFrame, col: str, steps: Sequence[float]) -> list:
    """For each step the least value whose rank among all rows (nulls last) is not below that share of them.

    Approximate quantiles on both sides bound each value. One pass counts the rows below, one groups those between by
    value, a thousandth of the rows and their equals. A bound that did not hold is replaced by the column's end.
    """
    column = df.select(F.col(f"`{col}`").alias("v"))
    edges = [min(max(s + m, 0.0), 1.0) for s in steps for m in (-MARGIN, MARGIN)]
    n, got = column.agg(F.count(F.lit(1)), F.percentile_approx("v", edges, ACCURACY)).head()
    if got is None:
        return [None] * len(steps)
    ranks = [rank_of(s, n) for s in steps]
    values = _between(column, ranks, got[::2], got[1::2])
    if None in values:
        values = _between(column, ranks, [None] * len(steps), [None] * len(steps))
    return values


def _between(column: DataFrame, ranks: list[int], low: list, high: list) -> list:
    """The value of each rank if it lies between its bounds (null: none); else null."""
    kind = column.schema["v"].dataType
    under = [F.col("v") < F.lit(b).cast(kind) if b is not None else F.lit(False) for b in low]
    over = [F.col("v") > F.lit(b).cast(kind) if b is not None else F.lit(False) for b in high]
    below = column.agg(*[F.count_if(u).alias(f"b{i}") for i, u in enumerate(under)]).head()
    inside = F.array_compact(F.array(*[F.when(~u & ~o, i) for i, (u, o) in enumerate(zip(under, over, strict=True))]))
    counts = column.filter("v IS NOT NULL").select("v", F.explode(inside).alias("i")).groupBy("i", "v").agg(F.count(F.lit(1)).alias("c"))
    upto = counts.withColumn("upto", F.sum("c").over(Window.partitionBy("i").orderBy("v").rowsBetween(Window.unboundedPreceding, 0)))
    wanted = F.element_at(F.array(*[F.lit(r - b).cast("long") for r, b in zip(ranks, below, strict=True)]), F.col("i") + 1)
    found = {r["i"]: r["v"] for r in upto.filter(F.col("upto") >= wanted).groupBy("i").agg(F.min("v").alias("v")).collect()}  # one row a step
    return [found.get(i) if b < r else None for i, (r, b) in enumerate(zip(ranks, below, strict=True))]
