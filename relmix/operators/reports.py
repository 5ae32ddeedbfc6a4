"""Reports over cluster assignments."""

from __future__ import annotations

from functools import reduce
from operator import add

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from relmix.operators.quantiles import order_statistics
from relmix.session import stored


def segment_report(assigned: DataFrame, dims: list[str], measure: str, how: str = "cube") -> DataFrame:
    """Counts and sums over ``cube`` or ``rollup`` of the dimensions, with the grouping id."""
    grouped = assigned.cube(*dims) if how == "cube" else assigned.rollup(*dims)
    return grouped.agg(F.grouping_id().cast("bigint").alias("gid"), F.count(F.lit(1)).alias("n"), F.sum(measure).alias("total"))


def grouping_sets(spark, view: str, sets: list[list[str]], measure: str) -> DataFrame:
    names = list(dict.fromkeys(c for s in sets for c in s))
    text = ", ".join("(" + ", ".join(s) + ")" for s in sets)
    return spark.sql(f"SELECT {', '.join(names)}, count(*) AS n, sum({measure}) AS total FROM {view} GROUP BY GROUPING SETS ({text})")


def top_per_component(rows: DataFrame, n: int, by: str = "p", tid: str = "tid") -> DataFrame:
    """The ``n`` rows of greatest ``by`` in each component; a group limit runs before the shuffle."""
    order = Window.partitionBy("comp").orderBy(F.col(by).desc(), F.col(tid))
    return rows.withColumn("rank", F.row_number().over(order)).filter(F.col("rank") <= n)


def rank_components(r: DataFrame) -> DataFrame:
    """Rank of the components of each row by responsibility; ties by component."""
    order = Window.partitionBy("tid").orderBy(F.col("p").desc(), "comp")
    return r.withColumn("rank", F.row_number().over(order))


def ntiles(df: DataFrame, cols: list[str], buckets: int = 5) -> DataFrame:
    """Quantile scores of each column by exact bounds: 1 and the number of bounds below the value; null has no bound below.

    The rows are written once, because counting and scoring read them several times."""
    rows = stored(df, "ntiles")
    steps = [i / buckets for i in range(1, buckets)]
    bounds = {c: [b for b in order_statistics(rows, c, steps) if b is not None] for c in cols}
    score = lambda c: reduce(add, [F.when(F.col(c) > F.lit(b).cast(rows.schema[c].dataType), 1).otherwise(0) for b in bounds[c]], F.lit(1))
    return rows.select(*df.columns, *[score(c).alias(f"{c}_score") for c in cols])
