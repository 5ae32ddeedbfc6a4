"""Joins around models: versions in force, intervals, radii."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.types import TimestampNTZType


def asof_model(df: DataFrame, versions: DataFrame, ts: str, valid_from: str = "valid_from", keys: list[str] | None = None) -> DataFrame:
    """Each row with the latest version at or before its time (left: none before gives nulls).

    Without keys the version history is a short list: its ranges [valid_from, next) are range-joined,
    and the history's size bounds the broadcast (one row a version). With keys, both sides are sorted
    once by key and time and the last version is carried forward.
    """
    if not keys:
        ordered = Window.orderBy(valid_from)
        ranges = versions.withColumn("__to", F.lead(valid_from).over(ordered))
        on = (F.col(ts) >= F.col(valid_from)) & (F.col("__to").isNull() | (F.col(ts) < F.col("__to")))
        return df.join(F.broadcast(ranges), on, "left").drop("__to")
    extra = [c for c in versions.columns if c not in keys]
    left = df.select(*[F.col(c) for c in df.columns], F.col(ts).alias("__t"), F.lit(1).alias("__side"), *[F.lit(None).cast(versions.schema[c].dataType).alias(f"__v_{c}") for c in extra])
    right = versions.select(*[F.col(c) if c in keys else F.lit(None).cast(df.schema[c].dataType).alias(c) for c in df.columns], F.col(valid_from).alias("__t"), F.lit(0).alias("__side"), *[F.col(c).alias(f"__v_{c}") for c in extra])
    carried = Window.partitionBy(*keys).orderBy("__t", "__side").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    both = left.unionByName(right)
    both = both.select(*df.columns, "__side", *[F.last(f"__v_{c}", ignorenulls=True).over(carried).alias(c) for c in extra if c not in df.columns])
    return both.filter("__side = 1").drop("__side")


def interval_join(a: DataFrame, b: DataFrame, a_ts: str, b_ts: str, before_s: int, after_s: int, bucket_s: int | None = None) -> DataFrame:
    """Pairs with b_ts in [a_ts - before, a_ts + after] to the microsecond, as an equi-join on time buckets and a residual filter."""
    size = (bucket_s or max(before_s + after_s, 1)) * 1_000_000
    before, after = before_s * 1_000_000, after_s * 1_000_000
    a_at, b_at = micros(a, a_ts), micros(b, b_ts)
    left = a.withColumn("__a", a_at).withColumn("__b", F.explode(F.sequence(F.floor((F.col("__a") - before) / size), F.floor((F.col("__a") + after) / size))))
    right = b.withColumn("__at", b_at).withColumn("__b", F.floor(F.col("__at") / size))
    near = (F.col("__at") >= F.col("__a") - before) & (F.col("__at") <= F.col("__a") + after)
    return left.join(right, "__b").filter(near).drop("__a", "__at", "__b")


def micros(df: DataFrame, ts: str) -> Column:
    """Microseconds since 1970 of a time column; local times are counted as such, without any zone's clock changes."""
    if isinstance(df.schema[ts].dataType, TimestampNTZType):
        return F.timestamp_diff("MICROSECOND", F.lit("1970-01-01").cast("timestamp_ntz"), F.col(ts))
    return F.unix_micros(F.col(ts).cast("timestamp"))


def within_radius(df: DataFrame, model: DataFrame, radius: float, x: str = "x0", mu: str = "mu") -> DataFrame:
    """One-dimensional range join of rows with components: cells of the radius's width, then the exact test."""
    left = df.withColumn("__c", F.floor(F.col(x) / radius))
    right = model.withColumn("__c", F.explode(F.sequence(F.floor(F.col(mu) / radius) - 1, F.floor(F.col(mu) / radius) + 1)))
    return left.join(right, "__c").filter(F.abs(F.col(x) - F.col(mu)) <= radius).drop("__c")


def salted_join(big: DataFrame, small: DataFrame, keys: list[str], salts: int = 16, how: str = "inner") -> DataFrame:
    """Equi-join whose hot keys are spread: the big side gets a random salt, the small side every salt."""
    if how not in ("inner", "left"):
        raise ValueError("salting keeps inner and left joins only")
    left = big.withColumn("__s", F.pmod(F.xxhash64(*big.columns), F.lit(salts)))
    right = small.withColumn("__s", F.explode(F.sequence(F.lit(0).cast("bigint"), F.lit(salts - 1).cast("bigint"))))
    return left.join(right, [*keys, "__s"], how).drop("__s")
