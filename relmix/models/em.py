"""The EM driver: rounds until the log-likelihood stops growing or the cap is reached."""

from __future__ import annotations

import time
from collections.abc import Callable
from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import DataFrame

from relmix.models.families import ExpertMixture, Family, Params
from relmix.plans import arrow, fused, layered, relational
from relmix.plans.base import Round, choose

PLANS: dict[str, Callable[..., Round]] = {
    "fused": fused.run_round,
    "explode": fused.run_round_explode,
    "arrow": arrow.run_round,
    "relational": relational.run_round,
    "coordinate": layered.coordinate_round,
    "wide": layered.wide_round,
    "hybrid": layered.hybrid_round,
}


@dataclass
class Fit:
    """``trace`` has (round, loglik of the parameters entering the round, delta, seconds)."""

    family: Family
    params: Params
    trace: list[tuple[int, float, float | None, float]] = field(default_factory=list)
    n: float = 0.0
    converged: bool = False
    history: list[Params] = field(default_factory=list)

    def rounds(self) -> int:
        return len(self.trace)


def fit(
    data: DataFrame,
    family: Family,
    params: Params,
    rounds: int = 10,
    eps: float | None = None,
    relative: bool = False,
    plan: str = "auto",
    groups: int = 0,
    gate_steps: int = 1,
    keep_history: bool = False,
    start: Fit | None = None,
    on_round: Callable[[int, Params], None] | None = None,
) -> Fit:
    """Train from ``params``; ``start`` continues an earlier fit's trace.

    Stops before applying a round whose entering likelihood gained no more than ``eps`` (both limits
    hold: the tolerance and the cap). Per round one pass over the data and one vector to the driver;
    the state is K rows, so the lineage never grows.
    """
    done = Fit(family, params, list(start.trace) if start else [])
    run = PLANS[choose(family, params) if plan == "auto" else plan]
    before = done.trace[-1][1] if done.trace else None
    for _ in range(rounds):
        began = time.perf_counter()
        got = run(data, family, done.params, groups)
        if not got.n:
            break
        delta = None if before is None else got.loglik - before
        done.n = got.n
        if eps is not None and delta is not None and abs(delta) <= eps * (abs(before) if relative else 1.0):
            done.trace.append((len(done.trace) + 1, got.loglik, delta, time.perf_counter() - began))
            done.converged = True
            break
        if keep_history:
            done.history.append(done.params)
        entered = done.params
        done.params = family.solve(got.n, got.stats, entered)
        if isinstance(family, ExpertMixture) and family.gate == "irls":
            done.params = _inner_gate(data, family, entered, done.params, gate_steps)
        before = got.loglik
        done.trace.append((len(done.trace) + 1, got.loglik, delta, time.perf_counter() - began))
        if on_round:
            on_round(len(done.trace), done.params)
    return done


def _inner_gate(data: DataFrame, family: ExpertMixture, entered: Params, solved: Params, steps: int) -> Params:
    """Further Newton steps of the gate with the responsibilities of the entering parameters held."""
    from pyspark.sql import functions as F

    params = dict(solved)
    base = family.width() * family.k(entered)
    for _ in range(max(steps - 1, 0)):
        rows = fused.posterior_columns(data, family, entered)
        sums = [F.sum(F.expr(s)) for s in family.extra_sql(params)]
        values = np.array([float(v) for v in rows.agg(F.count(F.lit(1)), *sums).head()])
        held = {"theta": params["theta"], "beta": solved["beta"], "var": solved["var"]}
        zero = np.zeros(base)
        params["theta"] = family.solve(values[0], np.concatenate([zero, values[1:]]), held)["theta"]
    return params


def best_of(data: DataFrame, family: Family, starts: list[Params], rounds: int, **options) -> Fit:
    """Restarts: the fit whose last likelihood is greatest."""
    return max((fit(data, family, p, rounds, **options) for p in starts), key=lambda f: f.trace[-1][1])


def rounds_to(trace: list[tuple], tolerance: float) -> int | None:
    """First round whose relative gain is below the tolerance."""
    for i in range(1, len(trace)):
        if abs(trace[i][1] - trace[i - 1][1]) <= tolerance * abs(trace[i - 1][1]):
            return trace[i][0]
    return None
