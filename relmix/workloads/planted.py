"""Planted data, reproducible in any SQL engine from the given tables by integer arithmetic.

Noise: u1, u2 from the part and supplier keys give a standard normal pair; further pairs come from
key hashes modulo 2^31 - 1, squared once. Each column has a text form that both engines accept.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from relmix.session import stored

PRIME = 2147483647


def tid_sql(parts: str = "np", suppliers: str = "ns") -> str:
    return f"((l_orderkey * {parts} + l_partkey) * {suppliers} + l_suppkey) * 8 + l_linenumber"


def normal_sql(j: int) -> str:
    """The j-th standard normal column (0 and 1 from the keys themselves)."""
    pair, which = divmod(j, 2)
    turn = "cos" if which == 0 else "sin"
    if pair == 0:
        u1, u2 = "((l_partkey % np) + 0.5e0) / np", "((l_suppkey % ns) + 0.5e0) / ns"
    else:
        u1, u2 = uniform_sql(2 * pair), uniform_sql(2 * pair + 1)
    return f"sqrt(-2 * ln({u1})) * {turn}(6.283185307179586e0 * ({u2}))"


def uniform_sql(i: int) -> str:
    h = f"((l_orderkey * {7919 + 104 * i} + l_partkey * {15485 + 62 * i} + l_suppkey * {32452 + 88 * i} + l_linenumber * {49979 + 686 * i} + {i * 611953}) % {PRIME})"
    return f"(((({h} * {h}) % {PRIME}) + 0.5e0) / {PRIME})"


def centre_sql(j: int, k: int, radius: float) -> str:
    """Coordinate j of component ``label``'s centre: a circle in each pair of dimensions, turning faster in later pairs."""
    turn = "cos" if j % 2 == 0 else "sin"
    return f"{float(radius)}e0 * {turn}(6.283185307179586e0 * (label * {j // 2 + 1}) / {k}.0e0)"


def gauss_sql(d: int, k: int = 10, radius: float = 8.0, two: float | None = None) -> str:
    """SELECT of (tid, label, x0..) over lineitem; with ``two`` one dimension and centres at minus and plus ``two``."""
    base = f"SELECT {tid_sql()} AS tid, CAST(l_orderkey % {2 if two else k} AS INT) AS label, {', '.join(f'{normal_sql(j)} AS z{j}' for j in range(d))} FROM (SELECT * FROM lineitem CROSS JOIN (SELECT count(*) AS np FROM part) a CROSS JOIN (SELECT count(*) AS ns FROM supplier) b) t"
    if two:
        return f"SELECT tid, label, CASE WHEN label = 0 THEN {-float(two)}e0 ELSE {float(two)}e0 END + z0 AS x0 FROM ({base}) q"
    return f"SELECT tid, label, {', '.join(f'{centre_sql(j, k, radius)} + z{j} AS x{j}' for j in range(d))} FROM ({base}) q"


def linear_sql(d: int = 1, k: int = 10, noise: float = 0.3) -> str:
    """SELECT of (tid, label, x0.., y): y = a_label + b_label x + noise, x in [0, 1)."""
    xs = ", ".join(f"{uniform_sql(20 + j)} AS x{j}" for j in range(d))
    base = f"SELECT {tid_sql()} AS tid, CAST(l_orderkey % {k} AS INT) AS label, {xs}, {normal_sql(0)} AS z FROM (SELECT * FROM lineitem CROSS JOIN (SELECT count(*) AS np FROM part) a CROSS JOIN (SELECT count(*) AS ns FROM supplier) b) t"
    slope = " + ".join(f"((label * {3 + j}) % {k} - {k / 2}e0) * x{j}" for j in range(d))
    return f"SELECT tid, label, {', '.join(f'x{j}' for j in range(d))}, label * 4.0e0 + {slope} + {noise}e0 * z AS y FROM ({base}) q"


def _run(spark: SparkSession, sf_dir: str, text: str, lines: DataFrame | None = None) -> DataFrame:
    for t in ("lineitem", "part", "supplier"):
        rows = lines if t == "lineitem" and lines is not None else spark.read.parquet(f"{sf_dir}/{t}.parquet")
        rows.createOrReplaceTempView(f"__planted_{t}")
        text = text.replace(f"FROM {t}", f"FROM __planted_{t}")
    return spark.sql(text)


def first_lines(spark: SparkSession, sf_dir: str, n: int) -> DataFrame:
    """The keys of the ``n`` lineitem rows of least tid, found in one scan and written once: planted columns are made for
    these rows only."""
    keys = "l_orderkey, l_partkey, l_suppkey, l_linenumber"
    base = f"SELECT {keys}, {tid_sql()} AS tid FROM (SELECT {keys}, np, ns FROM lineitem CROSS JOIN (SELECT count(*) AS np FROM part) a CROSS JOIN (SELECT count(*) AS ns FROM supplier) b) t"
    return stored(_run(spark, sf_dir, base).orderBy("tid").limit(n).drop("tid"), "planted-lines")


def gauss(spark: SparkSession, sf_dir: str, d: int = 2, k: int = 10, radius: float = 8.0, lines: DataFrame | None = None) -> DataFrame:
    """``lines``: lineitem rows to use instead of the whole table."""
    return _run(spark, sf_dir, gauss_sql(d, k, radius), lines)


def two(spark: SparkSession, sf_dir: str, separation: float = 3.0) -> DataFrame:
    return _run(spark, sf_dir, gauss_sql(1, two=separation))


def linear(spark: SparkSession, sf_dir: str, d: int = 1, k: int = 10, noise: float = 0.3, lines: DataFrame | None = None) -> DataFrame:
    return _run(spark, sf_dir, linear_sql(d, k, noise), lines)


def ranged(spark: SparkSession, n: int, separation: float = 3.0) -> DataFrame:
    """The two-component data over a range of any length, for timing."""
    ids = spark.range(n)
    h1 = F.expr(f"((id * 7919 + 13) % {PRIME}) * ((id * 7919 + 13) % {PRIME}) % {PRIME}")
    h2 = F.expr(f"((id * 15485 + 7) % {PRIME}) * ((id * 15485 + 7) % {PRIME}) % {PRIME}")
    z = F.sqrt(-2 * F.log((h1 + 0.5e0) / PRIME)) * F.cos(6.283185307179586e0 * (h2 + 0.5e0) / PRIME)
    label = (F.col("id") % 2).cast("int")
    return ids.select(F.col("id").alias("tid"), label.alias("label"), (F.when(label == 0, -separation).otherwise(separation) + z).alias("x0"))


def true_start(d: int, k: int = 10, radius: float = 8.0, jitter: float = 0.5):
    """Gaussian parameters near the planted centres."""
    import numpy as np

    label = np.arange(k)
    mu = np.stack([radius * (np.cos if j % 2 == 0 else np.sin)(2 * np.pi * label * (j // 2 + 1) / k) for j in range(d)], 1)
    return {"weight": np.full(k, 1 / k), "mu": mu + jitter, "sigma": np.repeat(np.eye(d)[None], k, 0)}
