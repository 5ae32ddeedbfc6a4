"""A bounded Bloom filter as a table: rows that cannot join are left out before their texts move.

The filter is a table of 64-bit words, one hash, at most ``MOST_BITS`` bits, so its broadcast has a proven
bound (half a million rows of 16 bytes) whatever the number of keys. Where keys are many it fills up and
lets more rows pass; the join behind it decides, so results never depend on it.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

MOST_BITS = 1 << 25


def bit_of(key: Column, bits: int) -> Column:
    return F.pmod(F.xxhash64(key), F.lit(bits).cast("bigint"))


class Filter:
    """``keys``: a frame with one column, of the type of the columns that are tested. It is read twice, so it should be stored."""

    def __init__(self, keys: DataFrame):
        self.bits = min(1 << max(10, (8 * keys.count()).bit_length()), MOST_BITS)
        at = bit_of(F.col(keys.columns[0]), self.bits)
        mark = F.call_function("shiftleft", F.lit(1).cast("bigint"), (at % 64).cast("int"))
        self.words = keys.select(F.shiftright(at, 6).alias("__word"), mark.alias("m")).groupBy("__word").agg(F.bit_or("m").alias("__bits"))

    def _matched(self, rows: DataFrame, key: Column, how: str) -> DataFrame:
        at = bit_of(key, self.bits)
        hit = F.call_function("shiftrightunsigned", F.col("__bits"), (at % 64).cast("int")).bitwiseAND(F.lit(1)) == 1
        return rows.join(F.broadcast(self.words), (F.shiftright(at, 6) == F.col("__word")) & hit, how)

    def possible(self, rows: DataFrame, key: Column) -> DataFrame:
        """Rows whose key is among the keys, and perhaps others."""
        return self._matched(rows, key, "left_semi")

    def impossible(self, rows: DataFrame, key: Column) -> DataFrame:
        """The other rows: their keys are surely not among the keys."""
        return self._matched(rows, key, "left_anti")
