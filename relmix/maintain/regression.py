"""Sufficient statistics of the regression families, with the same delta rules as for Gaussian mixtures.

With v = (design, y), component k keeps s0 = sum p and s2 = sum p v v'; that gives its coefficients by
least squares and its variance by the residual sum of squares. Experts also keep the moments of the
least-squares gate: sum x x' over all rows and sum x t_k, t being the centred log responsibilities.
Everything is a sum over rows, so inserts add, deletes subtract, and a sweep replaces contributions.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from relmix.maintain.update import _responsibilities
from relmix.models.families import ExpertMixture, LinearMixture, Params


@dataclass
class RegressionStats:
    n: float
    s0: np.ndarray
    s2: np.ndarray
    gate_xx: np.ndarray
    gate_xt: np.ndarray

    def to_json(self) -> dict:
        return {"n": self.n} | {f: getattr(self, f).tolist() for f in ("s0", "s2", "gate_xx", "gate_xt")}

    @classmethod
    def from_json(cls, d: dict) -> RegressionStats:
        return cls(d["n"], *(np.array(d[f]) for f in ("s0", "s2", "gate_xx", "gate_xt")))

    def _with(self, other: RegressionStats, sign: int) -> RegressionStats:
        return RegressionStats(*(getattr(self, f) + sign * getattr(other, f) for f in ("n", "s0", "s2", "gate_xx", "gate_xt")))

    def __add__(self, other: RegressionStats) -> RegressionStats:
        return self._with(other, 1)

    def __sub__(self, other: RegressionStats) -> RegressionStats:
        return self._with(other, -1)

    def params(self, family: LinearMixture, before: Params) -> Params:
        m = family.m()
        beta, var = before["beta"].copy(), before["var"].copy()
        for k, (mass, s) in enumerate(zip(self.s0, self.s2, strict=True)):
            if mass > 1e-12 * max(self.n, 1):
                beta[k] = np.linalg.lstsq(s[:m, :m] + family.ridge * np.eye(m), s[:m, m], rcond=None)[0]
                var[k] = max((s[m, m] - 2 * beta[k] @ s[:m, m] + beta[k] @ s[:m, :m] @ beta[k]) / mass, family.floor)
        if isinstance(family, ExpertMixture):
            theta = np.linalg.lstsq(self.gate_xx + family.ridge * np.eye(m), self.gate_xt.T, rcond=None)[0].T
            return {"theta": theta - theta.mean(0), "beta": beta, "var": var}
        return {"weight": np.maximum(self.s0 / max(self.n, 1), 1e-300), "beta": beta, "var": var}


def contribution(x: np.ndarray, p: np.ndarray, family: LinearMixture, rows: float) -> RegressionStats:
    """What rows add under responsibilities p; ``rows`` is how many new rows that is (0 for a replacement)."""
    design = family.design(x)
    v = np.column_stack([design, x[:, family.d]])
    s2 = np.einsum("nk,ni,nj->kij", p, v, v)
    if isinstance(family, ExpertMixture):
        logs = np.log(np.maximum(p, family.gate_floor))
        xt = (logs - logs.mean(1, keepdims=True)).T @ design
    else:
        xt = np.zeros((p.shape[1], family.m()))
    return RegressionStats(rows, p.sum(0), s2, design.T @ design, xt)


def stats_of(data: DataFrame, family: LinearMixture, params: Params) -> RegressionStats:
    """One Arrow pass; every task sends one vector, summed on executors."""
    k, m = family.k(params), family.m()
    shapes = [(), (k,), (k, m + 1, m + 1), (m, m), (k, m)]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = None
        for b in batches:
            if b.num_rows:
                x = np.column_stack([b.column(i).to_numpy(zero_copy_only=False) for i in range(b.num_columns)])
                c = contribution(x, _responsibilities(x, family, params), family, float(len(x)))
                total = c if total is None else total + c
        if total is not None:
            flat = np.concatenate([np.ravel(getattr(total, f)) for f in ("n", "s0", "s2", "gate_xx", "gate_xt")])
            yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(flat))), pa.array(flat)], names=["i", "v"])

    sizes = [int(np.prod(s)) for s in shapes]
    flat = np.zeros(sum(sizes))
    for r in data.select(*family.columns).mapInArrow(run, "i bigint, v double").groupBy("i").sum("v").collect():
        flat[r[0]] = r[1]
    parts = np.split(flat, np.cumsum(sizes)[:-1])
    return RegressionStats(float(parts[0][0]), *(p.reshape(s) for p, s in zip(parts[1:], shapes[1:], strict=True)))


def parallel_sweep(stats: RegressionStats, rows: DataFrame, family: LinearMixture, start: Params, rounds: int, seed: int = 0, batch_size: int = 64) -> tuple[RegressionStats, Params]:
    """Every partition sweeps its own rows against its own copy of the statistics; the deltas are added up."""
    first = stats.params(family, start)
    names = ("s0", "s2", "gate_xx", "gate_xt")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        blocks = [np.column_stack([b.column(i).to_numpy(zero_copy_only=False) for i in range(b.num_columns)]) for b in batches if b.num_rows]
        if blocks:
            moved, _ = sweep(stats, np.concatenate(blocks), family, start, rounds, seed, batch_size, first)
            flat = np.concatenate([np.ravel(getattr(moved, f) - getattr(stats, f)) for f in names])
            yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(flat))), pa.array(flat)], names=["i", "v"])

    flat = np.concatenate([np.ravel(getattr(stats, f)) for f in names])
    for r in rows.select(*family.columns).mapInArrow(run, "i bigint, v double").groupBy("i").sum("v").collect():
        flat[r[0]] += r[1]
    shapes = [getattr(stats, f).shape for f in names]
    parts = np.split(flat, np.cumsum([int(np.prod(s)) for s in shapes])[:-1])
    moved = RegressionStats(stats.n, *(p.reshape(s) for p, s in zip(parts, shapes, strict=True)))
    return moved, moved.params(family, start)


def sweep(stats: RegressionStats, x: np.ndarray, family: LinearMixture, start: Params, rounds: int, seed: int | None = 0, batch_size: int = 1, params: Params | None = None, before: np.ndarray | None = None) -> tuple[RegressionStats, Params]:
    """As for Gaussian mixtures: contributions under ``start`` (or the shares ``before``) are replaced row by row (or batch by batch)."""
    now = params or stats.params(family, start)
    if not len(x):
        return stats, now
    before = _responsibilities(x, family, start) if before is None else before
    rng = np.random.default_rng(seed)
    for _ in range(rounds):
        order = np.arange(len(x)) if seed is None else rng.permutation(len(x))
        for a in range(0, len(order), batch_size):
            pick = order[a : a + batch_size]
            p = _responsibilities(x[pick], family, now)
            stats = stats + contribution(x[pick], p, family, 0.0) - contribution(x[pick], before[pick], family, 0.0)
            before[pick] = p
            now = stats.params(family, now)
    return stats, now
