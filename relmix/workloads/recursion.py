"""Recursion examples: closure of containment edges, shortest hops, a capped counter."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from relmix.operators.iterate import IterationSpec, iterate


def containment_edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(src, dst): supplier in nation, nation in region."""
    s, n, r = (spark.read.parquet(f"{sf_dir}/{t}.parquet") for t in ("supplier", "nation", "region"))
    low = s.select(F.concat(F.lit("s"), "s_suppkey").alias("src"), F.concat(F.lit("n"), "s_nationkey").alias("dst"))
    high = n.select(F.concat(F.lit("n"), "n_nationkey").alias("src"), F.concat(F.lit("r"), "n_regionkey").alias("dst"))
    return low.union(high)


def closure(edges_view: str, depth: int = 20) -> IterationSpec:
    """Monotone: pairs reachable, found edge by edge; ``edges_view`` has (src, dst)."""
    return (
        iterate("reach", "src", "dst", "hops")
        .start(f"SELECT src, dst, 1 AS hops FROM {edges_view}")
        .next(f"SELECT reach.src, e.dst, reach.hops + 1 AS hops FROM reach JOIN {edges_view} e ON reach.dst = e.src")
        .append()
        .max_rounds(depth)
        .build()
    )


def shortest_hops(edges_view: str, source: str, depth: int = 20) -> IterationSpec:
    """Non-monotone: hop counts overwritten by better ones, over the (min, +) semiring."""
    return (
        iterate("dist", "node", "hops")
        .start(f"SELECT '{source}' AS node, 0 AS hops")
        .let("step", f"SELECT e.dst AS node, min(dist.hops + 1) AS hops FROM dist JOIN {edges_view} e ON dist.node = e.src GROUP BY e.dst")
        .next("SELECT step.node, step.hops FROM step LEFT JOIN dist ON step.node = dist.node WHERE dist.hops IS NULL OR step.hops < dist.hops")
        .replace_on("node")
        .max_rounds(depth)
        .build()
    )


def counter(cap: int) -> IterationSpec:
    """Endless without the cap."""
    return iterate("r", "n").start("SELECT 0 AS n").next("SELECT n + 1 AS n FROM r").append().max_rounds(cap).build()


def key_counter(view: str, key: str, cap: int) -> IterationSpec:
    """The least keys of a table, one a round, each the next one above the last."""
    return (
        iterate("at", "n")
        .start(f"SELECT min({key}) AS n FROM {view} HAVING min({key}) IS NOT NULL")
        .next(f"SELECT min(t.{key}) AS n FROM at JOIN {view} t ON t.{key} > at.n HAVING min(t.{key}) IS NOT NULL")
        .append()
        .max_rounds(cap)
        .build()
    )


def gmm1d_spec(data_view: str, start_view: str, rounds: int) -> IterationSpec:
    """A one-dimensional Gaussian mixture as an iterative query; ``data_view`` has (tid, x), ``start_view`` (comp, weight, mu, sd)."""
    dense = "model.weight * exp(-0.5D * (d.x - model.mu) * (d.x - model.mu) / (model.sd * model.sd)) / (model.sd * 2.5066282746310002D)"
    return (
        iterate("model", "comp", "weight", "mu", "sd")
        .start(f"SELECT comp, weight, mu, sd FROM {start_view}")
        .let("resp", f"SELECT d.tid, model.comp, d.x, {dense} / sum({dense}) OVER (PARTITION BY d.tid) AS p FROM model CROSS JOIN {data_view} d")
        .let("mass", "SELECT comp, sum(p) AS s, sum(p * x) / sum(p) AS m FROM resp GROUP BY comp")
        .let("spread", "SELECT resp.comp, sum(resp.p * power(resp.x - mass.m, 2)) AS v FROM resp JOIN mass ON resp.comp = mass.comp GROUP BY resp.comp")
        .next(f"SELECT mass.comp, mass.s / (SELECT count(*) FROM {data_view}) AS weight, mass.m AS mu, sqrt(spread.v / mass.s) AS sd FROM mass JOIN spread ON mass.comp = spread.comp")
        .replace_on("comp")
        .max_rounds(rounds)
        .build()
    )


def gmm_diag_spec(data_view: str, start_view: str, d: int, rounds: int) -> IterationSpec:
    """A diagonal Gaussian mixture over x0..x{d-1} as an iterative query; ``start_view`` has (comp, weight, mu0.., v0..)."""
    dims = range(d)
    names = ["comp", "weight", *(f"mu{j}" for j in dims), *(f"v{j}" for j in dims)]
    log = "ln(model.weight) - 0.5D * (" + " + ".join(f"ln(model.v{j}) + (d.x{j} - model.mu{j}) * (d.x{j} - model.mu{j}) / model.v{j}" for j in dims) + ")"
    xs = ", ".join(f"x{j}" for j in dims)
    means, spreads = ", ".join(f"sum(p * x{j}) / sum(p) AS m{j}" for j in dims), ", ".join(f"sum(resp.p * power(resp.x{j} - mass.m{j}, 2)) AS q{j}" for j in dims)
    return (
        iterate("model", *names)
        .start(f"SELECT {', '.join(names)} FROM {start_view}")
        .let("joint", f"SELECT d.tid, model.comp, {', '.join(f'd.x{j}' for j in dims)}, {log} AS l FROM model CROSS JOIN {data_view} d")
        .let("lifted", f"SELECT tid, comp, {xs}, exp(l - max(l) OVER (PARTITION BY tid)) AS f FROM joint")
        .let("resp", f"SELECT tid, comp, {xs}, f / sum(f) OVER (PARTITION BY tid) AS p FROM lifted")
        .let("mass", f"SELECT comp, sum(p) AS s, {means} FROM resp GROUP BY comp")
        .let("spread", f"SELECT resp.comp, {spreads} FROM resp JOIN mass ON resp.comp = mass.comp GROUP BY resp.comp")
        .next(
            f"SELECT mass.comp, mass.s / (SELECT count(*) FROM {data_view}) AS weight, {', '.join(f'mass.m{j} AS mu{j}' for j in dims)}, "
            f"{', '.join(f'greatest(spread.q{j} / mass.s, 1e-9D) AS v{j}' for j in dims)} FROM mass JOIN spread ON mass.comp = spread.comp"
        )
        .replace_on("comp")
        .max_rounds(rounds)
        .build()
    )


def descent_spec(data_view: str, rate: float, rounds: int) -> IterationSpec:
    """Supervised use of the same recursion: gradient descent for y = a + b x; ``data_view`` has (x, y)."""
    return (
        iterate("w", "id", "a", "b")
        .start("SELECT 1 AS id, 0D AS a, 0D AS b")
        .let("grad", f"SELECT avg(w.a + w.b * d.x - d.y) AS ga, avg((w.a + w.b * d.x - d.y) * d.x) AS gb FROM {data_view} d CROSS JOIN w")
        .next(f"SELECT w.id, w.a - {rate}D * grad.ga AS a, w.b - {rate}D * grad.gb AS b FROM w CROSS JOIN grad")
        .replace_on("id")
        .max_rounds(rounds)
        .build()
    )
