"""Arrow plan: for many dimensions or components, numpy on column batches.

Every task reduces its batches to one vector of statistics (K blocks of 1 + q + q(q+1)/2 doubles);
the vectors are summed place by place on executors, so the driver receives one vector whatever the
number of tasks.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from relmix.models.families import Family, Params
from relmix.plans.base import Round


def _block_stats(family: Family, params: Params):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = None
        for batch in batches:
            if not batch.num_rows:
                continue
            x = np.column_stack([batch.column(i).to_numpy(zero_copy_only=False) for i in range(batch.num_columns)])
            n, loglik, flat = family.np_stats(x, params)
            part = np.concatenate([[n, loglik], flat])
            total = part if total is None else total + part
        if total is not None:
            yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(total))), pa.array(total)], names=["i", "v"])

    return run


def run_round(data: DataFrame, family: Family, params: Params, groups: int = 0) -> Round:
    parts = data.select(*family.columns).mapInArrow(_block_stats(family, params), "i bigint, v double")
    values = np.zeros(2 + family.k(params) * family.width() + len(family.extra_sql(params)))
    for r in parts.groupBy("i").agg(F.sum("v").alias("v")).collect():
        values[r["i"]] = r["v"]
    return Round(values[0], values[1], values[2:])
