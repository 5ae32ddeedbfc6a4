"""Starting parameters: from a relation, uniform, quantiles, hashed sample rows, spread-out rows, and restarts."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from relmix.models.families import ExpertMixture, Family, Gaussian, LinearMixture, Params


def init_from(df: DataFrame, family: Family) -> Params:
    """From an initial-parameter relation with the family's schema (K rows)."""
    return family.from_rows(df.collect())


def moments(data: DataFrame, family: Family) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(mean, variance, least, greatest) of every column, in one pass."""
    aggs = []
    for c in family.columns:
        aggs += [F.avg(c), F.var_pop(c), F.min(c), F.max(c)]
    row = np.array(data.agg(*aggs).head(), float).reshape(-1, 4).T
    return row[0], row[1], row[2], row[3]


def around(means: np.ndarray, family: Gaussian, variance: np.ndarray) -> Params:
    """Gaussian start at given means; covariance = global variance / K^(2/d), which keeps components apart."""
    k = len(means)
    sigma = np.diag(np.maximum(variance[: family.d], family.floor) / k ** (2 / family.d))
    return {"weight": np.full(k, 1 / k), "mu": np.asarray(means, float), "sigma": np.repeat(sigma[None], k, 0)}


def regression_start(family: LinearMixture, k: int, rng: np.random.Generator, low: float, high: float, variance: float) -> Params:
    beta = rng.uniform(low, high, (k, family.m()))
    if isinstance(family, ExpertMixture):
        return {"theta": rng.uniform(low, high, (k, family.m())) * 0.1, "beta": beta, "var": np.full(k, variance)}
    return {"weight": np.full(k, 1 / k), "beta": beta, "var": np.full(k, variance)}


def init_uniform(data: DataFrame, family: Family, k: int, seed: int, low: float | None = None, high: float | None = None) -> Params:
    rng = np.random.default_rng(seed)
    _, variance, least, greatest = moments(data, family)
    if isinstance(family, LinearMixture):
        return regression_start(family, k, rng, -1.0 if low is None else low, 1.0 if high is None else high, max(variance[family.d], family.floor))
    lo = least[: family.d] if low is None else low
    hi = greatest[: family.d] if high is None else high
    return around(rng.uniform(lo, hi, (k, family.d)), family, variance)


def init_quantile(data: DataFrame, family: Gaussian, k: int) -> Params:
    """Means at the (j + 1/2) / k quantiles of each column."""
    _, variance, _, _ = moments(data, family)
    steps = [(j + 0.5) / k for j in range(k)]
    rows = data.agg(*[F.percentile_approx(c, steps, 10_000) for c in family.columns]).head()
    return around(np.array(rows, float).T, family, variance)


def sample_rows(data: DataFrame, family: Family, n: int, seed: int) -> np.ndarray:
    """``n`` distinct rows by smallest seeded hash of their values: deterministic, no full sort, no shuffle of the rows.

    Every task sends its smallest; equal rows have equal hashes, so they stand together and are removed
    after. Where that leaves too few, more are taken."""
    rows = data.select(*family.columns)
    by = [F.xxhash64(*family.columns, F.lit(seed)), *family.columns]
    take = n
    while True:
        picked = [tuple(r) for r in rows.orderBy(*by).limit(take).collect()]
        distinct = list(dict.fromkeys(picked))[:n]
        if len(distinct) == n or len(picked) < take:
            return np.array(distinct, float)
        if take >= 64 * n:  # rows repeat very often: remove the copies first
            return np.array([list(r) for r in rows.dropDuplicates().orderBy(*by).limit(n).collect()], float)
        take *= 4


def init_sample(data: DataFrame, family: Gaussian, k: int, seed: int) -> Params:
    _, variance, _, _ = moments(data, family)
    return around(sample_rows(data, family, k, seed)[:, : family.d], family, variance)


def init_spread(data: DataFrame, family: Gaussian, k: int, seed: int, pool: int = 2000) -> Params:
    """Means drawn from a bounded pool of rows, each far from the ones before (probability by squared distance)."""
    _, variance, _, _ = moments(data, family)
    rows = sample_rows(data, family, pool, seed)[:, : family.d]
    rng = np.random.default_rng(seed)
    scaled = rows / np.sqrt(np.maximum(variance[: family.d], family.floor))
    chosen = [int(rng.integers(len(rows)))]
    while len(chosen) < k:
        gap = np.min([((scaled - scaled[c]) ** 2).sum(1) for c in chosen], 0)
        chosen.append(int(rng.choice(len(rows), p=gap / gap.sum())) if gap.sum() > 0 else int(rng.integers(len(rows))))
    return around(rows[chosen], family, variance)
