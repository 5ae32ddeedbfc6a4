"""Sufficient statistics of a Gaussian mixture about a fixed centre: additive under inserts and deletes.

s0 = sum p, s1 = sum p (x - c), s2 = sum p (x - c)(x - c)'. With s0 kept, parameters are
weight = s0 / n, mean = c + s1 / s0, covariance = s2 / s0 - (s1 / s0)(s1 / s0)'. A centre near the data
keeps the subtraction harmless; c = 0 gives the raw moments.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame, SparkSession

from relmix.models.families import Gaussian, Params
from relmix.plans.base import choose
from relmix.plans.arrow import run_round as arrow_round
from relmix.plans.fused import run_round as fused_round


@dataclass
class SuffStats:
    n: float
    centre: np.ndarray
    s0: np.ndarray
    s1: np.ndarray
    s2: np.ndarray

    def __add__(self, other: SuffStats) -> SuffStats:
        return SuffStats(self.n + other.n, self.centre, self.s0 + other.s0, self.s1 + other.s1, self.s2 + other.s2)

    def __sub__(self, other: SuffStats) -> SuffStats:
        return SuffStats(self.n - other.n, self.centre, self.s0 - other.s0, self.s1 - other.s1, self.s2 - other.s2)

    def params(self, family: Gaussian, before: Params) -> Params:
        """Parameters; a component without mass keeps its former mean and covariance."""
        held = {"weight": before["weight"], "mu": np.repeat(self.centre[None], len(self.s0), 0), "sigma": before["sigma"]}
        got = family.from_stats(self.n, [(float(a), b, c) for a, b, c in zip(self.s0, self.s1, self.s2, strict=True)], held)
        empty = self.s0 <= 1e-12 * max(self.n, 1)
        got["mu"][empty] = before["mu"][empty]
        return got

    def frame(self, spark: SparkSession) -> DataFrame:
        upper = np.triu_indices(self.s1.shape[1])
        rows = [(k + 1, float(a), (b).tolist(), c[upper].tolist()) for k, (a, b, c) in enumerate(zip(self.s0, self.s1, self.s2, strict=True))]
        return spark.createDataFrame(rows, "comp int, s0 double, s1 array<double>, s2 array<double>")

    def to_json(self) -> dict:
        return {"n": self.n, "centre": self.centre.tolist(), "s0": self.s0.tolist(), "s1": self.s1.tolist(), "s2": self.s2.tolist()}

    @classmethod
    def from_json(cls, d: dict) -> SuffStats:
        return cls(d["n"], *(np.array(d[k]) for k in ("centre", "s0", "s1", "s2")))


def _about(n: float, flat: np.ndarray, family: Gaussian, params: Params, centre: np.ndarray) -> SuffStats:
    """Statistics about the component means, moved to the common centre."""
    width = family.width()
    s0, s1, s2 = [], [], []
    for k in range(family.k(params)):
        a, b, c = family.unpack(flat[k * width : (k + 1) * width])
        shift = params["mu"][k] - centre
        s0.append(a)
        s1.append(b + a * shift)
        s2.append(c + np.outer(b, shift) + np.outer(shift, b) + a * np.outer(shift, shift))
    return SuffStats(n, centre, np.array(s0), np.array(s1), np.array(s2))


def stats_of(data: DataFrame, family: Gaussian, params: Params, centre: np.ndarray | None = None) -> SuffStats:
    """One fused pass over the rows."""
    run = fused_round if choose(family, params) == "fused" else arrow_round
    got = run(data, family, params)
    stats = got.stats if len(got.stats) else np.zeros(family.k(params) * family.width())
    return _about(got.n, stats, family, params, np.zeros(family.d) if centre is None else centre)


def stats_of_rows(x: np.ndarray, family: Gaussian, params: Params, centre: np.ndarray) -> SuffStats:
    n, _, flat = family.np_stats(x, params)
    return _about(n, flat, family, params, centre)
