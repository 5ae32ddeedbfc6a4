"""Headline timings. Prints one JSON line; BENCH_SF_DIR and BENCH_CPUS choose data and cores.

Data is written before a timing begins (the published figures time execution only). ``per_round``
separates the fixed cost of a round (planning and scheduling, from a thousand rows) from its scan.
"""

from __future__ import annotations

import json
import os
import time

SF_DIR = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", str(os.cpu_count() or 8))


def main() -> None:
    from pyspark.sql import SparkSession
    from pyspark.sql import functions as F

    spark = (
        SparkSession.builder.master(f"local[{CPUS}]").appName("bench").config("spark.sql.shuffle.partitions", CPUS).config("spark.driver.memory", "16g")
        .config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    from relmix import catalogue
    from relmix.maintain.select import select_entropy
    from relmix.maintain.stats import stats_of
    from relmix.maintain.table import MaintainedTable
    from relmix.models.em import fit
    from relmix.models.families import ExpertMixture, Gaussian, LinearMixture, gaussian1d
    from relmix.session import ready, scratch, stored
    from relmix.view.model_view import ModelView
    from relmix.workloads import planted

    ready(spark)
    seconds: dict[str, float] = {}

    def timed(name: str, run):
        began = time.perf_counter()
        out = run()
        seconds[name] = round(time.perf_counter() - began, 3)
        return out

    two, start = Gaussian(1), gaussian1d([0.5, 0.5], [-2.0, 2.0], [1.5, 1.5])
    sizes = {"1k": 1_000, "100k": 100_000, "1m": 1_000_000, "10m": 10_000_000}
    data = {name: stored(planted.ranged(spark, n).select("tid", "x0"), f"bench-{name}") for name, n in sizes.items()}
    fit(data["1k"], two, start, 3)  # warm-up
    for name in sizes:
        timed(f"train_1d_{name}_15_rounds", lambda name=name: fit(data[name], two, start, 15, plan="fused"))
    for name in ("100k", "1m", "10m"):
        trained = fit(data[name], two, start, 2).params
        timed(f"selection_and_statistics_{name}", lambda name=name, trained=trained: (select_entropy(data[name], ModelView(two, trained), budget=1000).count(), stats_of(data[name], two, trained)))
    trained = fit(data["1m"], two, start, 5).params
    new = spark.createDataFrame([(10**9 + i, float(i % 5) - 2) for i in range(50)], "tid bigint, x0 double")
    table = MaintainedTable.create(spark, scratch(spark, "bench-table"), data["1m"], two, trained, budget=1000, sweeps=3)
    timed("insert_50_budget_1000_1m", lambda: table.insert(new))

    gauss10 = stored(planted.gauss(spark, SF_DIR, 10, 10).orderBy("tid").limit(10_000), "bench-gauss10")
    near, diag = planted.true_start(10, 10), Gaussian(10, cov="diag")
    for plan in ("hybrid", "fused", "arrow"):
        timed(f"one_round_d10_n10k_{plan}", lambda plan=plan: fit(gauss10, diag, near, 1, plan=plan))
    wide = stored(planted.gauss(spark, SF_DIR, 20, 8), "bench-gauss20")
    timed("gaussian_d20_k8_3_rounds", lambda: fit(wide, Gaussian(20, ridge=1e-6), planted.true_start(20, 8), 3))
    import numpy as np

    lines = stored(planted.linear(spark, SF_DIR, 5, 8), "bench-linear")
    beta = np.random.default_rng(1).uniform(0, 10, (8, 6))
    timed("linear_d5_k8_3_rounds", lambda: fit(lines, LinearMixture(5, ridge=1e-6), {"weight": np.full(8, 1 / 8), "beta": beta, "var": np.full(8, 4.0)}, 3))
    timed("expert_d5_k8_3_rounds", lambda: fit(lines, ExpertMixture(5, ridge=1e-6), {"theta": np.zeros((8, 6)), "beta": beta, "var": np.full(8, 4.0)}, 3))
    points = stored(planted.gauss(spark, SF_DIR, 2, 10), "bench-gauss2")
    view = ModelView(Gaussian(2), planted.true_start(2, 10))
    timed("assign_d2_k10", lambda: view.assign(points).groupBy("comp").agg(F.count(F.lit(1))).collect())
    queries = catalogue.queries()
    for name in ("gmm1d_relational", "gmm1d_loop", "gmm1d_script", "gmm1d_client", "gmm_full_rfm", "mlr_round3", "moe_round3", "segment_cube", "nmi", "closure_native", "mm_sum", "join_interval_events", "window_moving_avg"):
        run = queries["gmm1d_round5" if name == "gmm1d_relational" else name]
        timed(name, lambda run=run: run(spark, SF_DIR).collect())
    total = round(sum(seconds.values()), 3)
    fixed = seconds["train_1d_1k_15_rounds"] / 15
    per_round = {k: {"fixed_s": round(fixed, 4), "scan_s": round(max(seconds[f"train_1d_{k}_15_rounds"] / 15 - fixed, 0), 4)} for k in ("100k", "1m", "10m")}
    print(json.dumps({"metric": "total_seconds", "value": total, "unit": "sec", "queries": seconds, "per_round": per_round, "sf": SF_DIR, "cpus": CPUS}))


if __name__ == "__main__":
    main()
