"""Fused plan: E-step and statistics in one scan and one shuffle of a few doubles per task.

The parameters are literals in the row expressions; every row computes its K log joint densities,
the log-sum-exp, its responsibilities and the additive statistics, which are summed at once. No
join, no window, no row of responsibilities is ever materialised. ``explode`` is the second shape:
one array of structs a row, exploded and grouped by component, a smaller plan when K is large.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from relmix.models.families import Family, Params
from relmix.plans.base import Round


def joint_columns(data: DataFrame, family: Family, params: Params) -> DataFrame:
    """The rows with l0..l{K-1}: log joint densities."""
    return data.select("*", *[F.expr(family.log_joint_sql(params, k)).alias(f"l{k}") for k in range(family.k(params))])


def posterior_columns(data: DataFrame, family: Family, params: Params) -> DataFrame:
    """The rows with l0.., lse (log density) and p0.. (responsibilities), row-local, in the log domain."""
    n_comp = family.k(params)
    joint = joint_columns(data, family, params)
    names = [f"l{k}" for k in range(n_comp)]
    top = F.greatest(*names) if n_comp > 1 else F.col("l0")
    with_top = joint.select("*", top.alias("__top"))
    total = sum((F.exp(F.col(c) - F.col("__top")) for c in names[1:]), F.exp(F.col("l0") - F.col("__top")))
    with_lse = with_top.select("*", (F.col("__top") + F.log(total)).alias("lse"))
    return with_lse.select("*", *[F.exp(F.col(f"l{k}") - F.col("lse")).alias(f"p{k}") for k in range(n_comp)]).drop("__top")


def statistics(family: Family, params: Params) -> list[str]:
    """SQL of every statistic, in the flat layout."""
    out = []
    for k in range(family.k(params)):
        u = family.u_sql(params, k)
        out.append(f"p{k}")
        out += [f"p{k} * {u[j]}" for j in range(family.q())]
        out += [f"p{k} * {u[i]} * {u[j]}" for i, j in family.pairs()]
    return out + family.extra_sql(params)


def round_frame(data: DataFrame, family: Family, params: Params, groups: int = 0) -> DataFrame:
    """One row: n, loglik, s0... With ``groups`` the sums go through that many intermediate groups,
    so that no single task merges the partials of 100,000 scan tasks.

    The round is one SQL text, parsed and analysed once: on small data planning is most of a round, and
    every DataFrame call would analyse the plan again.
    """
    n_comp = family.k(params)
    names = [f"l{k}" for k in range(n_comp)]
    joint = ", ".join(f"{family.log_joint_sql(params, k)} AS l{k}" for k in range(n_comp))
    rows = f"SELECT {', '.join(family.columns)}, {joint} FROM {{rows}}"
    rows = f"SELECT *, {'greatest(' + ', '.join(names) + ')' if n_comp > 1 else 'l0'} AS top FROM ({rows})"
    rows = f"SELECT *, top + ln({' + '.join(f'exp({c} - top)' for c in names)}) AS lse FROM ({rows})"
    rows = f"SELECT *, {', '.join(f'exp(l{k} - lse) AS p{k}' for k in range(n_comp))} FROM ({rows})"
    sums = ["count(1) AS n", "sum(lse) AS loglik", *[f"sum({sql}) AS s{i}" for i, sql in enumerate(statistics(family, params))]]
    if groups:
        merged = ", ".join(f"sum({c}) AS {c}" for c in ("n", "loglik", *[f"s{i}" for i in range(len(sums) - 2)]))
        text = f"SELECT {merged} FROM (SELECT {', '.join(sums)} FROM (SELECT *, pmod(spark_partition_id(), {groups}) AS g FROM ({rows})) GROUP BY g)"
    else:
        text = f"SELECT {', '.join(sums)} FROM ({rows})"
    return data.sparkSession.sql(text, rows=data)


def run_round(data: DataFrame, family: Family, params: Params, groups: int = 0) -> Round:
    row = round_frame(data, family, params, groups).collect()[0]  # an aggregate of all rows is one row
    values = np.array([0.0 if v is None else float(v) for v in row])
    return Round(values[0], values[1], values[2:])


def run_round_explode(data: DataFrame, family: Family, params: Params, groups: int = 0) -> Round:
    """The exploded shape: group by component instead of one column per component."""
    n_comp, width = family.k(params), family.width()
    rows = posterior_columns(data, family, params)
    sql = statistics(family, params)
    parts = F.array(*[F.struct(F.lit(k).alias("k"), *[F.expr(sql[k * width + i]).alias(f"v{i}") for i in range(width)]) for k in range(n_comp)])
    extra = [F.sum(F.expr(s)).alias(f"e{i}") for i, s in enumerate(sql[n_comp * width :])]
    spread = rows.select("lse", F.explode(parts).alias("c"))
    by_comp = spread.groupBy("c.k").agg(F.count(F.lit(1)).alias("n"), F.sum("lse").alias("loglik"), *[F.sum(f"c.v{i}").alias(f"v{i}") for i in range(width)])
    got = sorted(by_comp.collect(), key=lambda r: r["k"])
    flat = [float(r[f"v{i}"]) for r in got for i in range(width)]
    if extra:
        flat += [float(v) for v in rows.agg(*extra).head()]
    if not got:
        return Round(0.0, 0.0, np.zeros(n_comp * width + len(extra)))
    return Round(float(got[0]["n"]), float(got[0]["loglik"]), np.array(flat))
