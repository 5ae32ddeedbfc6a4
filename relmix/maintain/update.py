"""The incremental update: statistics follow the new rows and a few old ones, row by row.

Inserted rows enter the statistics with their responsibilities under the old parameters; then for T
sweeps over the staged rows in random order each row's contribution is replaced by the one under the
current parameters, which are derived anew after every ``batch_size`` rows (1: after each row; the
number of staged rows: one batch step per sweep). Rows outside the staged set keep their old
contribution. The sweep is sequential by nature and runs in one process on a bounded set; for very
large batches ``parallel_sweep`` lets every partition sweep its own rows and adds the deltas.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from relmix.maintain.stats import SuffStats
from relmix.models.families import Gaussian, Params

#: Staged rows that one process may hold.
MOST_STAGED = 200_000


def _responsibilities(x: np.ndarray, family: Gaussian, params: Params) -> np.ndarray:
    joint = family.np_log_joint(x, params)
    top = joint.max(1, keepdims=True)
    e = np.exp(joint - top)
    return e / e.sum(1, keepdims=True)


def sweep(stats: SuffStats, x: np.ndarray, family: Gaussian, start: Params, rounds: int, seed: int | None = 0, batch_size: int = 1, params: Params | None = None, before: np.ndarray | None = None) -> tuple[SuffStats, Params]:
    """``start``: the parameters under which the rows' present contributions were computed. ``seed`` None keeps the given order.

    ``before``: the rows' present shares, where they are not those under ``start``; it is left holding the new ones."""
    s = SuffStats(stats.n, stats.centre, stats.s0.copy(), stats.s1.copy(), stats.s2.copy())
    now = params or s.params(family, start)
    if not len(x):
        return s, now
    before = _responsibilities(x, family, start) if before is None else before
    rng = np.random.default_rng(seed)
    centred = x - stats.centre
    for _ in range(rounds):
        order = np.arange(len(x)) if seed is None else rng.permutation(len(x))
        for a in range(0, len(order), batch_size):
            pick = order[a : a + batch_size]
            p = _responsibilities(x[pick], family, now)
            change = p - before[pick]
            u = centred[pick]
            s.s0 += change.sum(0)
            s.s1 += change.T @ u
            s.s2 += np.einsum("nk,ni,nj->kij", change, u, u)
            before[pick] = p
            now = s.params(family, now)
    return s, now


def full_sweep(data: DataFrame, family: Gaussian, start: Params, sweeps: int) -> Params:
    """All rows staged, one batch a sweep: every contribution is replaced at once, by one pass on the executors."""
    from relmix.maintain.stats import stats_of

    now = stats_of(data, family, start).params(family, start)
    for _ in range(sweeps):
        now = stats_of(data, family, now).params(family, now)
    return now


def parallel_sweep(stats: SuffStats, rows: DataFrame, family: Gaussian, start: Params, rounds: int, seed: int = 0, batch_size: int = 64) -> tuple[SuffStats, Params]:
    """Every partition sweeps its own rows against its own copy of the statistics; the deltas are added up."""
    first = stats.params(family, start)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        blocks = [np.column_stack([b.column(i).to_numpy(zero_copy_only=False) for i in range(b.num_columns)]) for b in batches if b.num_rows]
        if blocks:
            s, _ = sweep(stats, np.concatenate(blocks), family, start, rounds, seed, batch_size, first)
            d = s - stats
            flat = np.concatenate([d.s0.ravel(), d.s1.ravel(), d.s2.ravel()])
            yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(flat))), pa.array(flat)], names=["i", "v"])

    delta = rows.select(*family.columns).mapInArrow(run, "i bigint, v double").groupBy("i").sum("v").collect()
    k, d = stats.s1.shape
    flat = np.zeros(k + k * d + k * d * d)
    for r in delta:
        flat[r[0]] = r[1]
    moved = SuffStats(stats.n, stats.centre, stats.s0 + flat[:k], stats.s1 + flat[k : k + k * d].reshape(k, d), stats.s2 + flat[k + k * d :].reshape(k, d, d))
    return moved, moved.params(family, start)


def collected(rows: DataFrame, family: Gaussian) -> np.ndarray:
    """Staged rows on the driver; their number is the selection budget plus the batch, checked against a bound."""
    got = rows.select(*family.columns).limit(MOST_STAGED + 1).toPandas().to_numpy(float)
    if len(got) > MOST_STAGED:
        raise ValueError(f"over {MOST_STAGED} staged rows: use parallel_sweep")
    return got.reshape(-1, family.d)
