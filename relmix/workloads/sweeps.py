"""Experiment workloads: loop modes, scalability, convergence, maintenance; each returns a measured frame."""

from __future__ import annotations

import time

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from relmix.evaluate.meter import Meter, model_gap, scaling_slope
from relmix.maintain.table import MaintainedTable
from relmix.models.em import fit
from relmix.models.families import ExpertMixture, Gaussian, LinearMixture, gaussian1d
from relmix.operators.iterate import run
from relmix.session import scratch, stored
from relmix.workloads import planted, recursion


def loop_modes(spark: SparkSession, data: DataFrame, k: int, rounds: int, modes: tuple[str, ...] = ("loop", "script", "dataframe", "client"), d: int = 1, n: int | None = None) -> DataFrame:
    """The text-defined mixture in every mode: seconds, jobs, stages, statements, tables written, weight of the first component."""
    data.createOrReplaceTempView("__sweep_data")
    means = planted.true_start(d, k)["mu"] if d > 1 else np.linspace(-4, 4, k)[:, None]
    start = [(i + 1, 1 / k, *map(float, means[i]), *[4.0] * d) for i in range(k)]
    columns = "comp int, weight double, " + ", ".join([*(f"mu{j} double" for j in range(d)), *(f"v{j} double" for j in range(d))])
    spark.createDataFrame(start, columns).createOrReplaceTempView("__sweep_start")
    size = data.count() if n is None else n
    rows = []
    for mode in modes:
        spec = recursion.gmm_diag_spec("__sweep_data", "__sweep_start", d, rounds)

        def once(spec=spec, mode=mode):
            out = run(spark, spec, mode)
            return out, out.result.collect()

        (out, model), cost = Meter(spark).counted(once)
        rows.append((mode, d, size, k, out.rounds, cost["seconds"], int(cost["jobs"]), int(cost["stages"]), out.statements, out.materialised, round(min(model)["weight"], 6)))
    return spark.createDataFrame(rows, "mode string, d int, n bigint, k int, rounds int, seconds double, jobs int, stages int, statements int, materialised int, first_weight double")


def loop_sweep(spark: SparkSession, sf_dir: str, modes: tuple[str, ...] = ("loop", "script", "client"), base: tuple[int, int, int, int] = (2, 10_000, 10, 2)) -> DataFrame:
    """d, n, K and rounds varied one at a time around ten Gaussians."""
    d, n, k, rounds = base
    points = [("d", 1, n, k, rounds), ("base", d, n, k, rounds), ("d", 5, n, k, rounds), ("n", d, 2 * n, k, rounds), ("k", d, n, 2, rounds), ("rounds", d, n, k, 1), ("rounds", d, n, k, 5)]
    out = None
    for axis, dims, size, comps, r in points:
        rows = planted.gauss(spark, sf_dir, dims, comps).select("tid", *[f"x{j}" for j in range(dims)])
        data = stored(rows.orderBy("tid").limit(size), "sweep-loop")
        part = loop_modes(spark, data, comps, r, modes, dims).withColumn("axis", F.lit(axis))
        out = part if out is None else out.unionByName(part)
    return out


def hybrid_round(spark: SparkSession, sf_dir: str, n: int = 10_000, d: int = 10, k: int = 10) -> DataFrame:
    """One round over n rows of d dimensions: the hybrid layout's 2K statements against the fused pass."""
    data = stored(planted.gauss(spark, sf_dir, d, k).orderBy("tid").limit(n), "hybrid-data")
    family, start = Gaussian(d, cov="diag"), planted.true_start(d, k)
    rows = []
    for plan in ("hybrid", "wide", "coordinate", "fused", "arrow"):
        done, cost = Meter(spark).counted(lambda plan=plan: fit(data, family, start, 1, plan=plan))
        rows.append((plan, n, d, k, cost["seconds"], int(cost["jobs"]), float(done.trace[0][1])))
    return spark.createDataFrame(rows, "plan string, n bigint, d int, k int, seconds double, jobs int, loglik double")


def scalability(spark: SparkSession, sf_dir: str, family: str, axis: str, values: list[int], d: int = 5, k: int = 8, n: int = 10_000, rounds: int = 2, plan: str = "auto", lines: DataFrame | None = None) -> DataFrame:
    """Seconds per round along d, n or k for ``gaussian``, ``linear`` or ``expert``; ``lines`` as ``planted.first_lines`` gives them."""
    meter = Meter(spark)
    lines = planted.first_lines(spark, sf_dir, max(values) if axis == "n" else n) if lines is None else lines
    for v in values:
        dims, comps, size = (v if axis == "d" else d), (v if axis == "k" else k), (v if axis == "n" else n)
        if family == "gaussian":
            rows, model, start = planted.gauss(spark, sf_dir, dims, comps, lines=lines), Gaussian(dims, ridge=1e-6), planted.true_start(dims, comps)
        else:
            rows = planted.linear(spark, sf_dir, dims, comps, lines=lines)
            model = LinearMixture(dims, ridge=1e-6) if family == "linear" else ExpertMixture(dims, ridge=1e-6)
            rng = np.random.default_rng(1)
            beta = rng.uniform(0, 10, (comps, dims + 1))
            start = {"beta": beta, "var": np.full(comps, 4.0)}
            start |= {"weight": np.full(comps, 1 / comps)} if family == "linear" else {"theta": np.zeros((comps, dims + 1))}
        data = stored(rows.select("tid", *model.columns).orderBy("tid").limit(size), "sweep-data")
        meter.fit_timing(lambda data=data, model=model, start=start: fit(data, model, start, rounds, plan=plan), family, plan, size, dims, comps)
    return meter.frame()


def maintenance(spark: SparkSession, data: DataFrame, inserts: list[int], budgets: list[int], sweeps: int = 3, train_rounds: int = 15, precomputed: bool = True) -> DataFrame:
    """Insert latency and its parts by batch size and budget, with the gap to retraining on all rows."""
    family, start = Gaussian(1), gaussian1d([0.5, 0.5], [-2.0, 2.0], [1.5, 1.5])
    rows = []
    base_n = data.count()
    most = max(inserts)
    last = stored(data.orderBy(F.col("tid").desc()).limit(most), "sweep-new")
    old = stored(data.join(last.select("tid"), "tid", "left_anti").select("tid", "x0"), "sweep-old")
    began = time.perf_counter()
    trained = fit(old, family, start, train_rounds)
    batch_s = time.perf_counter() - began
    for m in inserts:
        new = last.orderBy("tid").limit(m).select("tid", "x0")
        whole = fit(old.unionByName(new), family, trained.params, train_rounds)
        for b in budgets:
            table = MaintainedTable.create(spark, scratch(spark, "maintained"), old, family, trained.params, precompute=precomputed, budget=b, sweeps=sweeps)
            t = table.insert(new)
            gap, _ = model_gap(family, table.params, whole.params)
            rows.append((base_n, m, b, t.select_s, t.stats_s, t.sweep_s, t.total_s, t.tuples, batch_s, gap))
    return spark.createDataFrame(rows, "n bigint, inserted int, budget int, select_s double, stats_s double, sweep_s double, total_s double, tuples int, batch_s double, gap double")


def deletion(spark: SparkSession, data: DataFrame, deletes: list[int], budget: int = 250, sweeps: int = 3) -> DataFrame:
    family, start = Gaussian(1), gaussian1d([0.5, 0.5], [-2.0, 2.0], [1.5, 1.5])
    base = stored(data.select("tid", "x0"), "sweep-base")
    trained = fit(base, family, start, 15)
    rows = []
    for m in deletes:
        table = MaintainedTable.create(spark, scratch(spark, "maintained"), base, family, trained.params, budget=budget, sweeps=sweeps)
        gone = base.orderBy(F.col("tid").desc()).limit(m).select("tid")
        t = table.delete(gone)
        whole = fit(table.data(), family, trained.params, 15)
        rows.append((m, budget, t.total_s, model_gap(family, table.params, whole.params)[0]))
    return spark.createDataFrame(rows, "deleted int, budget int, total_s double, gap double")


def convergence(spark: SparkSession, rows: DataFrame, k: int = 4, rounds: int = 15, seed: int = 1) -> DataFrame:
    """(model, round, loglik, delta) of the three families on RFM rows (r, f, m), regressions of m on r and f."""
    from relmix.workloads import rfm

    rng = np.random.default_rng(seed)
    gauss, reg = rfm.gaussian_rows(rows), rfm.regression_rows(rows)
    beta, var = rng.uniform(-1, 1, (k, 3)), np.full(k, 1.0)
    runs = {
        "gaussian": (gauss, Gaussian(3, ridge=1e-6), {"weight": np.full(k, 1 / k), "mu": rng.uniform(-1, 1, (k, 3)), "sigma": np.repeat(np.eye(3)[None], k, 0)}),
        "linear": (reg, LinearMixture(2, floor=1e-4), {"weight": np.full(k, 1 / k), "beta": beta, "var": var}),
        "expert": (reg, ExpertMixture(2, floor=1e-4), {"theta": rng.uniform(-0.1, 0.1, (k, 3)), "beta": beta, "var": var}),
    }
    out = []
    for name, (data, family, start) in runs.items():
        out += [(name, n, loglik, delta) for n, loglik, delta, _ in fit(data, family, start, rounds).trace]
    return spark.createDataFrame(out, "model string, round int, loglik double, delta double")


def relation_rows(spark: SparkSession, data: DataFrame, params) -> DataFrame:
    """Rows of the responsibility relations that the joining plans build, counted."""
    from relmix.plans import fused, relational

    family = Gaussian(1)
    x = data.select("tid", F.array(*[F.col(c) for c in family.columns]).alias("x"))
    joined = relational.responsibilities(x, relational.model_relation(x, family, params)).count()
    k = family.k(params)
    posts = fused.posterior_columns(data.select("tid", *family.columns), family, params)
    long = posts.select("tid", F.posexplode(F.array(*[F.col(f"p{i}") for i in range(k)])).alias("comp", "p")).count()
    return spark.createDataFrame([("relational", joined), ("coordinate", long)], "plan string, relation_rows bigint")


def shuffled_rows(spark: SparkSession, data: DataFrame, params, plans: tuple[str, ...] = ("relational", "coordinate", "wide", "hybrid", "fused", "explode", "arrow")) -> DataFrame:
    """(plan, tasks, shuffled rows) of one round, from the stages' own counters."""
    rows, family = [], Gaussian(1, cov="diag")
    store = spark.sparkContext._jsc.sc().statusStore()
    for plan in plans:
        group = f"shuffled-{plan}"
        spark.sparkContext.setJobGroup(group, plan)
        fit(data, family, params, 1, plan=plan)
        tracker = spark.sparkContext.statusTracker()
        stages = {i for j in tracker.getJobIdsForGroup(group) if (info := tracker.getJobInfo(j)) for i in info.stageIds}
        seen = [store.lastStageAttempt(i) for i in stages if tracker.getStageInfo(i)]
        rows.append((plan, sum(s.numCompleteTasks() for s in seen), sum(s.shuffleWriteRecords() for s in seen)))
    spark.sparkContext.setLocalProperty("spark.jobGroup.id", None)
    return spark.createDataFrame(rows, "plan string, tasks int, shuffled_rows bigint")


def scalability_sweep(spark: SparkSession, sf_dir: str, d: int = 20, k: int = 8, n: int = 10_000) -> DataFrame:
    """Seconds per round of the three models along d, n and K around d=20, K=8, n=10,000, with the axis' log-log slope."""
    out, lines = [], planted.first_lines(spark, sf_dir, n)
    for family in ("gaussian", "linear", "expert"):
        for axis, values in (("d", [5, 10, d]), ("k", [2, 4, k]), ("n", [n // 4, n // 2, n])):
            got = scalability(spark, sf_dir, family, axis, values, d, k, n, rounds=2, plan="arrow", lines=lines).collect()
            # the second round: the first one warms up
            points = [(float(r[axis]), r["seconds"]) for r in got if r["round"] == 2]
            slope = scaling_slope(points)
            out += [(family, axis, r["n"], r["d"], r["k"], r["round"], r["seconds"], slope) for r in got]
    return spark.createDataFrame(out, "model string, axis string, n bigint, d int, k int, round int, seconds double, slope double")
