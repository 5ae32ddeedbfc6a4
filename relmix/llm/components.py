"""Connected components of an edge table by alternating large-star and small-star steps.

Every step is two aggregates that combine before the shuffle and equi-joins, so a node with very
many neighbours never has to fit in one task: the minima are written before they are joined, so both sides
of a join are plain exchanges that adaptive execution can split. Each step's edges are written to the shared folder:
a lost executor costs a reread, not the iteration.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from relmix.session import remove, scratch


def _stored(df: DataFrame) -> tuple[DataFrame, str]:
    path = scratch(df.sparkSession, "cc-edges")
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path), path


def _large_star(edges: DataFrame, done: list[str]) -> DataFrame:
    both = edges.select("u", "v").union(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
    least, path = _stored(both.groupBy("u").agg(F.least(F.min("v"), F.first("u")).alias("m")))
    done.append(path)
    return both.filter("v > u").join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v"))


def _small_star(edges: DataFrame, done: list[str]) -> DataFrame:
    least, path = _stored(edges.groupBy("u").agg(F.min("v").alias("m")))
    done.append(path)
    moved = edges.join(least, "u").filter("v != m").select(F.col("v").alias("u"), F.col("m").alias("v"))
    return moved.union(least.select("u", F.col("m").alias("v"))).distinct()


def components(edges: DataFrame) -> DataFrame:
    """(u, v) bigint -> (node, root): root is the smallest node reachable. Nodes without an edge do not occur."""
    spark = edges.sparkSession
    start = edges.filter("u != v").select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct()
    now, path = _stored(start)
    known = None
    while True:
        marks = now.agg(F.count(F.lit(1)), F.sum(F.hash("u", "v").cast("decimal(20,0)")), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).head()
        if tuple(marks) == known or not marks[0]:
            break
        known = tuple(marks)
        done = [path]
        wide, wide_path = _stored(_large_star(now, done))
        after, new_path = _stored(_small_star(wide, done))
        for old in [*done, wide_path]:
            remove(spark, old)
        now, path = after, new_path
    return now.select(F.col("u").alias("node"), F.col("v").alias("root")).union(now.select(F.col("v").alias("node"), F.col("v").alias("root")).distinct())
