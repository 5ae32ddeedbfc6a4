"""Cost measures: seconds per round and in all, counters of jobs and statements, growth slopes, model gaps."""

from __future__ import annotations

import time
import uuid
from collections.abc import Callable

import numpy as np
from pyspark.sql import DataFrame, SparkSession

from relmix.models.em import Fit
from relmix.models.families import Family, Params


class Meter:
    """Times only execution: sessions, loading and starting values are the caller's, before ``fit_timing``."""

    def __init__(self, spark: SparkSession):
        self.spark = spark
        self.rows: list[tuple] = []

    def fit_timing(self, run: Callable[[], Fit], mode: str, plan: str, n: int, d: int, k: int) -> Fit:
        done = run()
        for round_, _, _, seconds in done.trace:
            self.rows.append((mode, plan, n, d, k, round_, seconds))
        return done

    def total_seconds(self) -> float:
        return sum(r[-1] for r in self.rows)

    def frame(self) -> DataFrame:
        return self.spark.createDataFrame(self.rows, "mode string, plan string, n bigint, d int, k int, round int, seconds double")

    def counted(self, run: Callable[[], object]) -> tuple[object, dict[str, float]]:
        """Result and (jobs, stages, seconds) of a call."""
        group = uuid.uuid4().hex
        self.spark.sparkContext.setJobGroup(group, "metered")
        began = time.perf_counter()
        out = run()
        seconds = time.perf_counter() - began
        tracker = self.spark.sparkContext.statusTracker()
        jobs = tracker.getJobIdsForGroup(group)
        stages = sum(len(info.stageIds) for j in jobs if (info := tracker.getJobInfo(j)))
        self.spark.sparkContext.setLocalProperty("spark.jobGroup.id", None)
        return out, {"jobs": len(jobs), "stages": stages, "seconds": seconds}


def scaling_slope(points: list[tuple[float, float]]) -> float:
    """Slope of ln seconds on ln axis."""
    x, y = np.log(np.array(points, float)).T
    return float(np.polyfit(x, y, 1)[0])


def matched(a: Params, b: Params) -> list[int]:
    """For each component of a its nearest unused one of b, closest pairs first."""
    key = "mu" if "mu" in a else "beta"
    gap = ((a[key][:, None] - b[key][None]) ** 2).sum(-1)
    out = [-1] * len(gap)
    while -1 in out:
        i, j = np.unravel_index(np.argmin(gap), gap.shape)
        out[i] = int(j)
        gap[i], gap[:, j] = np.inf, np.inf
    return out


def model_gap(family: Family, a: Params, b: Params, data: DataFrame | None = None) -> tuple[float, float | None]:
    """(greatest absolute parameter gap of matched components, log-likelihood of a minus that of b)."""
    order = matched(a, b)
    gap = max(float(np.abs(a[name] - b[name][order]).max()) for name in a)
    if data is None:
        return gap, None
    from relmix.plans.fused import run_round

    return gap, run_round(data, family, a).loglik - run_round(data, family, b).loglik
