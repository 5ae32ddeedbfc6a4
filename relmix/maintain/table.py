"""A maintained table: inserts, deletes and updates that keep a mixture model current.

One insert statement runs three hooks: ``before_statement`` selects old rows, ``for_rows`` checks and
stages the new ones, ``after_statement`` updates statistics and parameters. Data parts, tombstones,
parameters, statistics, the persisted selection with its present shares, and the ids of applied batches
are committed together by one manifest that appears by rename: a reader sees the state before or after
a statement, and a batch id that is in the manifest is not applied again. A statement that fails leaves
the object as it was.

Statements touch little old data: a part keeps its range of ids, so an insert looks for its ids only in
parts whose range meets them (the range is pushed to the Parquet scan), and a delete writes the removed
ids as a tombstone instead of rewriting parts. ``compact`` merges parts and tombstones when it suits.

Gaussian, linear and expert mixtures are maintained alike. Batches of more than ``MOST_STAGED`` rows
take the distributed way: statistics by one pass on the executors, then a sweep in every partition.

Defined cases: rows with a missing id or number are refused; ids are unique; deleting ids that are not
there changes nothing; a table without rows keeps its parameters, has no statistics and takes inserts.
"""

from __future__ import annotations

import copy
import json
import time
from contextlib import contextmanager
from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from relmix.maintain import regression
from relmix.maintain import select as selection
from relmix.maintain import stats as gaussian
from relmix.maintain import update
from relmix.models.em import fit
from relmix.models.families import Family, Gaussian, Params
from relmix.view.model_view import ModelView, _fs, _read_text, _write_text


@dataclass
class Timing:
    n: float = 0
    inserted: int = 0
    budget: int = 0
    select_s: float = 0.0
    stats_s: float = 0.0
    sweep_s: float = 0.0
    total_s: float = 0.0

    @property
    def tuples(self) -> int:
        return self.inserted + self.budget


@dataclass
class MaintainedTable:
    spark: SparkSession
    path: str
    family: Family
    budget: int = 100
    sweeps: int = 3
    batch_size: int = 1
    strategy: str = "entropy"
    seed: int = 0
    version: int = 0
    parts: list[dict] = field(default_factory=list)  # name, seq, least and greatest id, rows
    tombstones: list[dict] = field(default_factory=list)  # name, seq: hides the ids in parts of a lower seq
    batches: list[str] = field(default_factory=list)
    params: Params | None = None
    stats: gaussian.SuffStats | regression.RegressionStats | None = None
    picked: str | None = None
    held: list | None = None  # shares of the persisted selection's rows in the statistics, by id
    seq: int = 0

    # life cycle ------------------------------------------------------------------------

    @classmethod
    def create(cls, spark: SparkSession, path: str, data: DataFrame, family: Family, params: Params, precompute: bool = True, **options) -> MaintainedTable:
        """``data`` has tid and the family's columns; ``params`` are trained parameters."""
        table = cls(spark, path, family, **options)
        table.params = params
        table._append(data.select("tid", *family.columns))
        if precompute:
            table.persist_stats()
            table.persist_selection()
        table._commit()
        return table

    @classmethod
    def open(cls, spark: SparkSession, path: str, family: Family, **options) -> MaintainedTable:
        at, fs = _fs(spark, path)
        numbers = [int(n[6:-5]) for e in fs.listStatus(at) if (n := e.getPath().getName()).startswith("state-") and n.endswith(".json")]
        state = json.loads(_read_text(spark, f"{path}/state-{max(numbers)}.json"))
        table = cls(spark, path, family, **options)
        table.version = max(numbers)
        for name in ("parts", "tombstones", "batches", "picked", "held", "seq"):
            setattr(table, name, state[name])
        table.params = {k: np.array(v) for k, v in state["params"].items()}
        table.stats = table._kind().from_json(state["stats"]) if state["stats"] else None
        return table

    def _commit(self) -> None:
        self.version += 1
        state = {name: getattr(self, name) for name in ("parts", "tombstones", "batches", "picked", "held", "seq")}
        state |= {"params": {k: v.tolist() for k, v in self.params.items()}, "stats": self.stats.to_json() if self.stats else None}
        _write_text(self.spark, f"{self.path}/state-{self.version}.json", json.dumps(state))

    @contextmanager
    def _statement(self):
        """All of a statement is committed, or the object is as before."""
        names = ("version", "parts", "tombstones", "batches", "params", "stats", "picked", "held", "seq")
        before = {n: copy.deepcopy(getattr(self, n)) for n in names}
        try:
            yield
            self._commit()
        except BaseException:
            for n, v in before.items():
                setattr(self, n, v)
            raise

    def _kind(self):
        return gaussian.SuffStats if isinstance(self.family, Gaussian) else regression.RegressionStats

    def _schema(self, extra: str = "") -> str:
        return "tid bigint, " + ", ".join(f"{c} double" for c in self.family.columns) + extra

    def _append(self, rows: DataFrame) -> None:
        """Parts are sorted by id, so that a range of ids reads few row groups."""
        self.seq += 1
        name = f"part-{self.version + 1}-{self.seq}"
        rows.withColumn("seq", F.lit(self.seq).cast("bigint")).sortWithinPartitions("tid").write.mode("overwrite").parquet(f"{self.path}/{name}")
        least, most, n = self._read([name]).agg(F.min("tid"), F.max("tid"), F.count(F.lit(1))).head()
        if n:
            self.parts.append({"name": name, "seq": self.seq, "least": least, "most": most, "rows": n})

    def _read(self, names: list[str]) -> DataFrame:
        schema = self._schema(", seq bigint")
        return self.spark.read.schema(schema).parquet(*[f"{self.path}/{n}" for n in names]) if names else self.spark.createDataFrame([], schema)

    def _rows(self, least: int | None = None, most: int | None = None) -> DataFrame:
        """Present rows, of a range of ids if one is given: only parts that meet it are read."""
        inside = [p for p in self.parts if least is None or (p["least"] <= most and p["most"] >= least)]
        rows = self._read([p["name"] for p in inside])
        if least is not None:
            rows = rows.filter(F.col("tid").between(least, most))
        older = min((p["seq"] for p in inside), default=0)
        graves = [t["name"] for t in self.tombstones if t["seq"] > older]
        if graves:
            gone = self.spark.read.schema("tid bigint, seq bigint").parquet(*[f"{self.path}/{g}" for g in graves])
            gone = gone.groupBy(F.col("tid").alias("gone_tid")).agg(F.max("seq").alias("gone_seq"))
            rows = rows.join(gone, (F.col("tid") == F.col("gone_tid")) & (F.col("seq") < F.col("gone_seq")), "left_anti")
        return rows.drop("seq")

    def data(self) -> DataFrame:
        return self._rows()

    def compact(self) -> None:
        """One part instead of many, without tombstones."""
        rows = self.data()
        with self._statement():
            self.parts, self.tombstones = [], []
            self._append(rows)

    def view(self) -> ModelView:
        return ModelView(self.family, self.params, self.version)

    # precomputation --------------------------------------------------------------------

    def _stats_of(self, rows: DataFrame, centre: np.ndarray | None = None):
        if not isinstance(self.family, Gaussian):
            return regression.stats_of(rows, self.family, self.params)
        if centre is None:
            centre = (self.params["weight"][:, None] * self.params["mu"]).sum(0) / self.params["weight"].sum()
        return gaussian.stats_of(rows, self.family, self.params, centre)

    def _stats_of_matrix(self, x: np.ndarray):
        if isinstance(self.family, Gaussian):
            return gaussian.stats_of_rows(x, self.family, self.params, self.stats.centre)
        return regression.contribution(x, update._responsibilities(x, self.family, self.params), self.family, float(len(x)))

    def persist_stats(self) -> None:
        self.stats = self._stats_of(self.data())

    def persist_selection(self) -> None:
        """Ahead of time, for a fixed budget; its rows' shares in the statistics are kept beside it."""
        picked = f"selection-{self.version + 1}"
        self._select().write.mode("overwrite").parquet(f"{self.path}/{picked}")
        self.picked, self.held = picked, None

    def _select(self) -> DataFrame:
        data, view = self.data(), self.view()
        names = ["tid", *self.family.columns]
        if self.budget <= 0:
            return selection.select_none(data)
        if self.strategy == "entropy":
            return selection.select_entropy(data, view, self.budget).select(*names)
        if self.strategy == "distance":
            return selection.select_distance(data, view, budget=self.budget).select(*names)
        return selection.select_random(data, self.budget, self.seed)

    # hooks -----------------------------------------------------------------------------

    def before_statement(self) -> DataFrame:
        return self.spark.read.schema(self._schema()).parquet(f"{self.path}/{self.picked}") if self.picked else self._select()

    def for_rows(self, rows: DataFrame, replaced: DataFrame | None = None) -> DataFrame:
        """Checked new rows: numbers are finite and no tid is already there (but those of ``replaced``)."""
        good = F.col("tid").isNotNull()
        for c in self.family.columns:
            good = good & F.col(c).isNotNull() & ~F.isnan(c)
        faulty, least, most = rows.agg(F.max((~good).cast("int")), F.min("tid").cast("bigint"), F.max("tid").cast("bigint")).head()
        if faulty:
            raise ValueError("a new row has a missing id or number")
        if rows.groupBy("tid").count().filter("count > 1").limit(1).count():
            raise ValueError("a new row's id exists already")
        if least is not None and any(p["least"] <= most and p["most"] >= least for p in self.parts):
            there = self._rows(least, most).join(rows.select("tid"), "tid", "left_semi")
            if replaced is not None:
                there = there.join(replaced.select("tid"), "tid", "left_anti")
            if there.limit(1).count():
                raise ValueError("a new row's id exists already")
        return rows.select(F.col("tid").cast("bigint").alias("tid"), *[F.col(c).cast("double").alias(c) for c in self.family.columns])

    def _staged(self, rows: DataFrame) -> tuple[np.ndarray, np.ndarray] | None:
        """(ids, values) of a bounded set of rows, in the order of ids; None beyond ``MOST_STAGED``."""
        got = rows.select("tid", *self.family.columns).limit(update.MOST_STAGED + 1).toPandas()
        if len(got) > update.MOST_STAGED:
            return None
        got = got.sort_values("tid")
        return got["tid"].to_numpy(np.int64), got[self.family.columns].to_numpy(float).reshape(-1, len(self.family.columns))

    def after_statement(self, old: tuple[np.ndarray, np.ndarray], new: np.ndarray | None, removed: np.ndarray | None, timing: Timing) -> None:
        """Statistics follow the new and the removed rows, then the sweep runs over the old selected and the new rows.

        An old row's contribution is replaced by what it holds in the statistics: its share after the last
        statement that swept it, else that under the present parameters.
        """
        began = time.perf_counter()
        start, (ids, rows) = self.params, old
        if removed is not None and len(removed):
            self.stats = self.stats - self._stats_of_matrix(removed)
        if new is not None and len(new):
            self.stats = self.stats + self._stats_of_matrix(new)
        if self.stats.n < 0.5:
            self.stats = self.picked = self.held = None
            return
        staged = rows if new is None else np.concatenate([rows, new])
        shares = update._responsibilities(staged, self.family, start) if len(staged) else np.zeros((0, self.view().k()))
        known = {i: p for i, p in self.held or []}
        for at, i in enumerate(ids.tolist()):
            if i in known:
                shares[at] = known[i]
        sweep = update.sweep if isinstance(self.family, Gaussian) else regression.sweep
        self.stats, self.params = sweep(self.stats, staged, self.family, start, self.sweeps, self.seed, self.batch_size, before=shares)
        self.held = [[i, p] for i, p in zip(ids.tolist(), shares[: len(ids)].tolist(), strict=True)] if self.picked else None
        timing.sweep_s = time.perf_counter() - began

    def _after_large(self, old: DataFrame, new: DataFrame | None, removed: DataFrame | None, timing: Timing) -> None:
        """The same for batches that no process can hold: statistics by a pass, a sweep in every partition, deltas added."""
        began = time.perf_counter()
        centre = getattr(self.stats, "centre", None)
        for rows, sign in ((removed, -1), (new, 1)):
            if rows is not None:
                change = self._stats_of(rows, centre)
                self.stats = self.stats + change if sign > 0 else self.stats - change
        self.picked = self.held = None
        if self.stats.n < 0.5:
            self.stats = None
            return
        staged = old if new is None else old.unionByName(new)
        sweep = update.parallel_sweep if isinstance(self.family, Gaussian) else regression.parallel_sweep
        self.stats, self.params = sweep(self.stats, staged, self.family, self.params, self.sweeps, self.seed, max(self.batch_size, 64))
        timing.sweep_s = time.perf_counter() - began

    # statements ------------------------------------------------------------------------

    def insert(self, rows: DataFrame, batch_id: str | None = None) -> Timing:
        return self._change(rows, None, batch_id)

    def delete(self, keys: DataFrame) -> Timing:
        """Remove rows by tid: their contribution under the present parameters is subtracted, then the sweep runs."""
        return self._change(None, keys, None)

    def update(self, rows: DataFrame) -> Timing:
        """Delete and insert, as one statement."""
        return self._change(rows, rows.select("tid"), None)

    def _change(self, rows: DataFrame | None, keys: DataFrame | None, batch_id: str | None) -> Timing:
        timing = Timing(n=self.stats.n if self.stats else 0)
        if batch_id is not None and batch_id in self.batches:
            return timing
        began = time.perf_counter()
        gone = None
        if keys is not None:
            keys = keys.select(F.col("tid").cast("bigint").alias("tid")).distinct()
            least, most = keys.agg(F.min("tid"), F.max("tid")).head()
            gone = self._rows(least, most).join(keys, "tid", "left_semi") if least is not None else self.data().limit(0)
        fresh = self.for_rows(rows, keys) if rows is not None else None
        if rows is None and gone.isEmpty():
            timing.total_s = time.perf_counter() - began
            return timing
        chosen = self.before_statement()
        if keys is not None:
            chosen = chosen.join(keys, "tid", "left_anti")
        new = self._staged(fresh) if fresh is not None else None
        removed = self._staged(gone) if gone is not None else None
        large = (fresh is not None and new is None) or (gone is not None and removed is None)
        old = None if large else self._staged(chosen)
        large = large or old is None
        timing.select_s = time.perf_counter() - began
        with self._statement():
            at = time.perf_counter()
            if self.stats is None and self.parts:
                self.persist_stats()
            elif self.stats is None:
                self.stats = self._stats_of(self._read([]).drop("seq"))
            timing.stats_s = time.perf_counter() - at
            if not large:
                # read once: what enters the statistics is what is written
                timing.inserted, timing.budget = len((new or removed)[0]), len(old[0])
                fresh = self._frame(*new) if new is not None else None
                gone_ids = self._frame(removed[0]) if removed is not None else None
                self.after_statement(old, new[1] if new is not None else None, removed[1] if removed is not None else None, timing)
            else:
                counted = fresh if fresh is not None else gone
                timing.inserted, timing.budget = counted.count(), chosen.count()
                gone_ids = gone.select("tid") if gone is not None else None
                self._after_large(chosen, fresh, gone, timing)
            if gone_ids is not None:
                self.seq += 1
                name = f"gone-{self.version + 1}-{self.seq}"
                gone_ids.select("tid", F.lit(self.seq).cast("bigint").alias("seq")).write.mode("overwrite").parquet(f"{self.path}/{name}")
                self.tombstones.append({"name": name, "seq": self.seq})
                self._forget_selected(chosen, old)
            if fresh is not None:
                self._append(fresh)
            if batch_id is not None:
                self.batches.append(batch_id)
        timing.total_s = time.perf_counter() - began
        return timing

    def _frame(self, ids: np.ndarray, values: np.ndarray | None = None) -> DataFrame:
        import pandas as pd

        frame = pd.DataFrame({"tid": ids})
        for j, c in enumerate(self.family.columns if values is not None else []):
            frame[c] = values[:, j]
        schema = self._schema() if values is not None else "tid bigint"
        return self.spark.createDataFrame(frame, schema) if len(frame) else self.spark.createDataFrame([], schema)

    def _forget_selected(self, chosen: DataFrame, old: tuple[np.ndarray, np.ndarray] | None) -> None:
        """The persisted selection without the removed rows; the shares of the others stay."""
        if self.picked and old is not None:
            self.picked = f"selection-{self.version + 1}"
            self._frame(*old).write.mode("overwrite").parquet(f"{self.path}/{self.picked}")

    def refresh(self, mode: str = "auto", rounds: int = 15, start: Params | None = None, inserted: int = 0, **options) -> str:
        """``batch`` retrains from ``start``, ``warm`` from the present parameters, ``auto`` picks by the cost of a batch
        of ``inserted`` rows. Returns the mode used."""
        if mode == "auto":
            n = sum(p["rows"] for p in self.parts)
            mode = preferred(n, inserted, self.budget, self.sweeps, rounds, d=len(self.family.columns), k=self.view().k())
            if mode == "incremental":
                return mode
        with self._statement():
            done = fit(self.data(), self.family, start if mode == "batch" and start else self.params, rounds, **options)
            self.params = done.params
            self.persist_stats()
            self.picked = self.held = None
        return mode


#: Measured on one machine: seconds per swept row at one component and one number a component, and per scanned
#: row, number and round on eight cores; both grow with the numbers that a row adds to (K times the moments).
SWEEP_SECONDS, SWEEP_NUMBER, SCAN_NUMBER, ROUND_SECONDS = 1.0e-4, 1.0e-6, 4e-8, 0.3


def preferred(n: float, inserted: int, budget: int, sweeps: int, rounds: int, cores: int = 8, d: int = 1, k: int = 2) -> str:
    """Incremental unless its sequential sweep costs more than retraining's scans (small tables, large batches)."""
    numbers = k * (1 + d + d * (d + 1) / 2)
    incremental = (budget + inserted) * sweeps * (SWEEP_SECONDS + SWEEP_NUMBER * numbers)
    retrain = rounds * (ROUND_SECONDS + n * numbers * SCAN_NUMBER * 8 / cores)
    return "incremental" if incremental <= retrain else "batch"
