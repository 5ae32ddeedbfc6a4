"""Key-overwriting merge and its inflationary relatives.

``overwrite_merge(old, new, keys)``: rows of ``new`` replace rows of ``old`` with the same key, other
rows of both stay. Null keys never match. Duplicate keys in ``new`` raise, or the row greatest by
``order`` wins.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


class MergeError(ValueError):
    """Ill-formed merge input."""


def overwrite_merge(old: DataFrame, new: DataFrame, keys: list[str], on_duplicate: str = "error", order: str | None = None, how: str = "anti") -> DataFrame:
    """``how``: ``anti`` (anti-join and union) or ``full`` (one full outer join, one shuffle of each side)."""
    if [f.name for f in old.schema] != [f.name for f in new.schema]:
        raise MergeError(f"columns differ: {old.columns} and {new.columns}")
    if on_duplicate == "last":
        rank = Window.partitionBy(*keys).orderBy(F.col(order or keys[0]).desc())
        new = new.withColumn("__n", F.row_number().over(rank)).filter("__n = 1").drop("__n")
    elif new.groupBy(*keys).count().filter("count > 1").limit(1).count():
        raise MergeError(f"several new rows for one key of {keys}")
    if how == "anti":
        return old.join(new, keys, "left_anti").unionByName(new)
    a, b = old.withColumn("__old", F.lit(True)).alias("a"), new.withColumn("__new", F.lit(True)).alias("b")
    on = [F.col(f"a.{k}") == F.col(f"b.{k}") for k in keys]
    picked = [F.when(F.col("b.__new"), F.col(f"b.{c}")).otherwise(F.col(f"a.{c}")).alias(c) for c in old.columns]
    return a.join(b, on, "full_outer").select(*picked)


def append_merge(old: DataFrame, new: DataFrame) -> DataFrame:
    return old.unionByName(new)


def distinct_merge(old: DataFrame, new: DataFrame) -> DataFrame:
    return old.unionByName(new).distinct()
