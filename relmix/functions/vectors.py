"""Vectors as ARRAY<DOUBLE> columns: row-local operations and the vector-sum aggregate.

Row-local operations are higher-order built-ins. The aggregate over a group comes in two forms:
``vec_sum`` for a known dimension (one scalar sum per place, code-generated, combines before the
shuffle) and ``vec_sum_long`` for a dimension known only from the data (explode, sum, collect).
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def scale(a: Column, v: Column) -> Column:
    return F.transform(v, lambda e: a * e)


def add(v: Column, w: Column) -> Column:
    return F.zip_with(v, w, lambda a, b: a + b)


def subtract(v: Column, w: Column) -> Column:
    return F.zip_with(v, w, lambda a, b: a - b)


def dot(v: Column, w: Column) -> Column:
    return F.aggregate(F.zip_with(v, w, lambda a, b: a * b), F.lit(0.0), lambda s, e: s + e)


def norm(v: Column) -> Column:
    return F.sqrt(dot(v, v))


def outer(v: Column, w: Column) -> Column:
    """Row-major flattened outer product."""
    return F.flatten(F.transform(v, lambda a: F.transform(w, lambda b: a * b)))


def quad(v: Column, rows: Column) -> Column:
    """v' A v with A as an array of rows."""
    return dot(v, F.transform(rows, lambda r: dot(r, v)))


def vec_sum(v: Column, d: int) -> Column:
    return F.array(*[F.sum(F.element_at(v, i + 1)) for i in range(d)])


def vec_sum_long(df: DataFrame, keys: list[str], vector: str, out: str = "total") -> DataFrame:
    places = df.select(*keys, F.posexplode(vector).alias("__i", "__e"))
    sums = places.groupBy(*keys, "__i").agg(F.sum("__e").alias("__s"))
    # one row per place: a group never holds more than the dimension
    ordered = F.transform(F.array_sort(F.collect_list(F.struct("__i", "__s"))), lambda r: r["__s"])
    return sums.groupBy(*keys).agg(ordered.alias(out))
