"""Agreement of two labellings, from their contingency table only (no pairs of rows).

The table is counted once and written; it has at most K x L rows, and every measure reads it.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window
from pyspark.sql import functions as F

from relmix.session import stored


def contingency(df: DataFrame, a: str, b: str) -> DataFrame:
    """(a, b, n): one small row per occurring combination."""
    return stored(df.groupBy(F.col(a).alias("a"), F.col(b).alias("b")).agg(F.count(F.lit(1)).alias("n")), "contingency")


def purity(c: DataFrame) -> DataFrame:
    best = c.groupBy("a").agg(F.max("n").alias("top"), F.sum("n").alias("size"))
    return best.agg((F.sum("top") / F.sum("size")).alias("purity"))


def _with_margins(c: DataFrame) -> DataFrame:
    """The cells with na, nb and total; windows over K x L rows."""
    margin = lambda *by: F.sum("n").over(Window.partitionBy(*by))
    return c.select("*", margin("a").alias("na"), margin("b").alias("nb"), margin(F.lit(0)).alias("total"))


def nmi(c: DataFrame, norm: str = "mean") -> DataFrame:
    """Normalised mutual information; ``norm``: mean, sqrt, max or min of the two entropies. 1 if both are constant."""
    m = _with_margins(c)
    n, na, nb, total = (F.col(x).cast("double") for x in ("n", "na", "nb", "total"))
    mutual = F.sum(n / total * F.log(n * total / (na * nb)))
    # a cell's share of its margin spreads the margin's entropy over the cells
    ha = -F.sum(n / total * F.log(na / total))
    hb = -F.sum(n / total * F.log(nb / total))
    parts = m.agg(mutual.alias("i"), ha.alias("ha"), hb.alias("hb"))
    scale = {"mean": (F.col("ha") + F.col("hb")) / 2, "sqrt": F.sqrt(F.col("ha") * F.col("hb")), "max": F.greatest("ha", "hb"), "min": F.least("ha", "hb")}[norm]
    return parts.select(F.when(scale > 0, F.col("i") / scale).otherwise(F.lit(1.0)).alias("nmi"))


def _pairs(x: str):
    v = F.col(x).cast("decimal(38,0)")
    return v * (v - 1) / 2


def rand_index(c: DataFrame, adjusted: bool = False) -> DataFrame:
    """Share of row pairs on which the labellings agree; ``adjusted`` for chance. Pair counts are decimals: 10^12 rows make 10^24 pairs."""
    # cells, row margins and column margins in one pass
    margins = c.cube("a", "b").agg(F.sum("n").alias("m"), F.grouping("a").alias("no_a"), F.grouping("b").alias("no_b"))
    of = lambda a, b: F.sum(F.when((F.col("no_a") == a) & (F.col("no_b") == b), _pairs("m"))).cast("double")
    whole = F.sum(F.when((F.col("no_a") == 1) & (F.col("no_b") == 1), F.col("m")))
    one = margins.agg(of(0, 0).alias("both"), of(0, 1).alias("pa"), of(1, 0).alias("pb"), whole.alias("total"))
    all_pairs = _pairs("total").cast("double")
    if not adjusted:
        return one.select(((all_pairs + 2 * F.col("both") - F.col("pa") - F.col("pb")) / all_pairs).alias("rand_index"))
    expected = F.col("pa") * F.col("pb") / all_pairs
    most = (F.col("pa") + F.col("pb")) / 2
    return one.select(F.when(most == expected, F.lit(1.0)).otherwise((F.col("both") - expected) / (most - expected)).alias("adjusted_rand"))


def report(assigned: DataFrame, cluster: str, label: str) -> DataFrame:
    """(measure, value) of all measures."""
    c = contingency(assigned, cluster, label)
    parts = {"purity": purity(c), "nmi": nmi(c), "rand_index": rand_index(c), "adjusted_rand": rand_index(c, True)}
    frames = [f.select(F.lit(name).alias("measure"), F.col(f.columns[0]).alias("value")) for name, f in parts.items()]
    out = frames[0]
    for f in frames[1:]:
        out = out.unionByName(f)
    return out
