"""Three encodings of high-dimensional rows and the conversions between them.

coordinate: (tid, c, x), one row per place, c from 1; wide: (tid, d1..dd); vector: (tid, x ARRAY<DOUBLE>).
Leaving the coordinate encoding costs one shuffle by tid; every other conversion is row-local.
Also the component means that each encoding leads to, from responsibilities (tid, comp, p).
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from relmix.functions.vectors import scale, vec_sum


def to_vector(df: DataFrame, tid: str, cols: list[str]) -> DataFrame:
    return df.select(F.col(tid).alias("tid"), F.array(*[F.col(c).cast("double") for c in cols]).alias("x"))


def to_wide(df: DataFrame, tid: str, cols: list[str]) -> DataFrame:
    return df.select(F.col(tid).alias("tid"), *[F.col(c).cast("double").alias(f"d{i + 1}") for i, c in enumerate(cols)])


def to_coordinate(df: DataFrame, tid: str, cols: list[str]) -> DataFrame:
    return vector_to_coordinate(to_vector(df, tid, cols))


def vector_to_coordinate(df: DataFrame) -> DataFrame:
    return df.select("tid", F.posexplode("x").alias("c", "x")).withColumn("c", F.col("c") + 1)


def vector_to_wide(df: DataFrame, d: int) -> DataFrame:
    return df.select("tid", *[F.element_at("x", i + 1).alias(f"d{i + 1}") for i in range(d)])


def wide_to_vector(df: DataFrame, d: int) -> DataFrame:
    return df.select("tid", F.array(*[F.col(f"d{i + 1}") for i in range(d)]).alias("x"))


def coordinate_to_vector(df: DataFrame) -> DataFrame:
    """One row per tid; a tid has as many rows as dimensions, so the collected list is bounded by d."""
    places = F.array_sort(F.collect_list(F.struct("c", "x")))
    return df.groupBy("tid").agg(F.transform(places, lambda r: r["x"]).alias("x"))


def coordinate_to_wide(df: DataFrame, d: int) -> DataFrame:
    return df.groupBy("tid").agg(*[F.max(F.when(F.col("c") == i + 1, F.col("x"))).alias(f"d{i + 1}") for i in range(d)])


def convert(df: DataFrame, source: str, target: str, d: int) -> DataFrame:
    """Any encoding to any other."""
    if source == target:
        return df
    as_vector = {"vector": lambda x: x, "wide": lambda x: wide_to_vector(x, d), "coordinate": coordinate_to_vector}[source]
    if (source, target) == ("coordinate", "wide"):
        return coordinate_to_wide(df, d)
    return {"vector": lambda x: x, "wide": lambda x: vector_to_wide(x, d), "coordinate": vector_to_coordinate}[target](as_vector(df))


def mean_coordinate(r: DataFrame, x: DataFrame) -> DataFrame:
    return r.join(x, "tid").groupBy("comp", "c").agg((F.sum(F.col("p") * F.col("x")) / F.sum("p")).alias("mean"))


def mean_wide(r: DataFrame, x: DataFrame, d: int) -> DataFrame:
    means = [(F.sum(F.col("p") * F.col(f"d{i + 1}")) / F.sum("p")).alias(f"m{i + 1}") for i in range(d)]
    return r.join(x, "tid").groupBy("comp").agg(*means)


def mean_vector(r: DataFrame, x: DataFrame, d: int) -> DataFrame:
    sums = r.join(x, "tid").groupBy("comp").agg(F.sum("p").alias("s"), vec_sum(scale(F.col("p"), F.col("x")), d).alias("v"))
    return sums.select("comp", scale(1 / F.col("s"), F.col("v")).alias("mean"))
