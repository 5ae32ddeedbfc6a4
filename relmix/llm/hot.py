"""An equi-join of rows with one row a group, where one group may hold any share of the rows.

Groups with more than a ``PARTS``-th of all rows are broadcast: their sizes add up to at most the number of
rows, so there are fewer than ``PARTS`` of them whatever the data. The others are joined by key, and no key
of those can fill a task. Every row meets its group in exactly one of the two ways.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

PARTS = 1000


def with_group(rows: DataFrame, groups: DataFrame, key: str, n: str = "n") -> DataFrame:
    """``rows`` joined with ``groups`` (one row a key, ``n`` its number of rows). Both are read more than once: store them."""
    total = groups.agg(F.sum(n)).head()[0] or 0
    large = F.col(n) * PARTS > total
    spread = rows.join(F.broadcast(groups.filter(large)), key)
    others = rows.join(F.broadcast(groups.filter(large).select(key)), key, "left_anti").join(groups.filter(~large), key)
    return spread.unionByName(others)
