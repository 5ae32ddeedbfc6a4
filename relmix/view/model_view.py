"""Trained parameters as a view: inference, versions, resuming."""

from __future__ import annotations

import json
import math
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from relmix.models.em import Fit, fit
from relmix.models.families import ExpertMixture, Family, Gaussian, LinearMixture, Params, num
from relmix.operators.quantiles import order_statistics
from relmix.plans.fused import posterior_columns

FAMILIES = {"Gaussian": Gaussian, "LinearMixture": LinearMixture, "ExpertMixture": ExpertMixture}


@dataclass
class ModelView:
    """K parameter rows with their family. Inference is row-local: no shuffle, filters of the caller
    reach the scan. Components are numbered from 1."""

    family: Family
    params: Params
    version: int = 0
    trace_rows: list[tuple] = field(default_factory=list)
    n: float = 0.0

    @classmethod
    def of(cls, done: Fit) -> ModelView:
        return cls(done.family, done.params, 0, list(done.trace), done.n)

    def k(self) -> int:
        return self.family.k(self.params)

    def frame(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame(self.family.rows(self.params), self.family.schema)

    def create_view(self, spark: SparkSession, name: str) -> None:
        """``<name>_params`` as a temporary view and, for one dimension, ``<name>_posterior(x)`` as a SQL function."""
        self.frame(spark).createOrReplaceTempView(f"{name}_params")
        if isinstance(self.family, Gaussian) and self.family.d == 1:
            joint = [self.family.log_joint_sql(self.params, k).replace("x0", "x") for k in range(self.k())]
            top = f"greatest({', '.join(joint)})" if len(joint) > 1 else joint[0]
            total = " + ".join(f"exp({j} - {top})" for j in joint)
            parts = ", ".join(f"exp({j} - {top}) / ({total})" for j in joint)
            spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}_posterior(x DOUBLE) RETURNS ARRAY<DOUBLE> RETURN array({parts})")

    def trace(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame(self.trace_rows, "round int, loglik double, delta double, seconds double")

    # inference -------------------------------------------------------------------------

    def _joint(self, df: DataFrame) -> DataFrame:
        """The rows with ``__l``, the array of log joint densities."""
        parts = [F.expr(self.family.log_joint_sql(self.params, k)) for k in range(self.k())]
        return df.select("*", F.array(*parts).alias("__l"))

    def scored(self, df: DataFrame) -> DataFrame:
        """The rows with ``lse`` (log density) and ``p`` (array of responsibilities).

        Array functions keep the expressions linear in K: a filter or a join on an output is pushed below
        the projection with the whole expression written out, and K columns that refer to K columns
        would make that text grow with K squared and more.
        """
        top = F.array_max("__l")
        lse = top + F.log(F.aggregate("__l", F.lit(0.0), lambda s, v: s + F.exp(v - F.array_max("__l"))))
        rows = self._joint(df).withColumn("lse", lse)
        keep = [F.col(f"`{c}`") for c in df.columns]
        return rows.select(*keep, "lse", F.transform("__l", lambda v: F.exp(v - F.col("lse"))).alias("p"))

    def clustered(self, df: DataFrame) -> DataFrame:
        """The rows with ``comp``, the component of greatest posterior (the lowest of equals)."""
        keep = [F.col(f"`{c}`") for c in df.columns]
        return self._joint(df).select(*keep, F.array_position("__l", F.array_max("__l")).cast("int").alias("comp"))

    def posterior(self, df: DataFrame, tid: str = "tid") -> DataFrame:
        return self.scored(df).select(tid, F.posexplode("p").alias("comp", "p")).select(tid, (F.col("comp") + 1).alias("comp"), "p")

    def posterior_map(self, df: DataFrame, tid: str = "tid") -> DataFrame:
        keys = F.array(*[F.lit(k + 1) for k in range(self.k())])
        return self.scored(df).select(tid, F.map_from_arrays(keys, F.col("p")).alias("posterior"))

    def assign(self, df: DataFrame, ties: str = "first", tid: str = "tid") -> DataFrame:
        """(tid, comp): the component of greatest posterior; ``first`` takes the lowest of ties, ``all`` every one."""
        if ties == "first":
            return self.clustered(df).select(tid, "comp")
        rows = self.scored(df)
        places = F.filter(F.transform("p", lambda p, i: F.when(p == F.array_max("p"), (i + 1).cast("int"))), lambda c: c.isNotNull())
        return rows.select(tid, F.explode(places).alias("comp"))

    def density(self, df: DataFrame, tid: str = "tid") -> DataFrame:
        return self.scored(df).select(tid, "lse", F.exp("lse").alias("density"))

    def uncertainty(self, df: DataFrame, tid: str = "tid") -> DataFrame:
        """(tid, entropy of the posterior, least Mahalanobis distance to a component)."""
        rows = self.scored(df).withColumn("entropy", entropy(F.col("p")))
        distance = mahalanobis(self.family, self.params) if isinstance(self.family, Gaussian) else F.lit(None).cast("double")
        return rows.select(tid, "entropy", distance.alias("min_mahalanobis"))

    def predict(self, df: DataFrame, tid: str = "tid") -> DataFrame:
        """E[y | x] of the regression families."""
        return df.select(tid, F.expr(self.family.prediction_sql(self.params)).alias("prediction"))

    def gates(self, df: DataFrame, tid: str = "tid") -> DataFrame:
        parts = [F.exp(F.expr(self.family.log_weight_sql(self.params, k))) for k in range(self.k())]
        return df.select(tid, F.posexplode(F.array(*parts)).alias("comp", "g")).select(tid, (F.col("comp") + 1).alias("comp"), "g")

    def outliers(self, df: DataFrame, q: float, tid: str = "tid") -> DataFrame:
        """Rows whose log density is below the exact q-quantile."""
        dense = self.density(df, tid)
        bar = order_statistics(dense, "lse", [q])[0]
        return dense.filter(F.col("lse") < F.lit(bar).cast("double")).select(tid, "lse")

    def summary(self, df: DataFrame, columns: list[str], tid: str = "tid") -> DataFrame:
        """Size, share, means and spreads of each hard cluster."""
        rows = self.clustered(df)
        aggs = [F.count(F.lit(1)).alias("n")] + [F.avg(c).alias(f"mean_{c}") for c in columns] + [F.stddev_pop(c).alias(f"sd_{c}") for c in columns]
        total = Window.partitionBy()
        return rows.groupBy("comp").agg(*aggs).withColumn("share", F.col("n") / F.sum("n").over(total))

    def label_components(self, df: DataFrame, label: str, tid: str = "tid") -> DataFrame:
        """(comp, label): the majority label of each hard cluster, the smallest of equals."""
        rows = self.clustered(df).select(label, "comp")
        counts = rows.groupBy("comp", label).agg(F.count(F.lit(1)).alias("n"))
        best = Window.partitionBy("comp").orderBy(F.col("n").desc(), F.col(label))
        return counts.withColumn("__r", F.row_number().over(best)).filter("__r = 1").select("comp", F.col(label).alias("label"), "n")

    def loglik(self, df: DataFrame) -> DataFrame:
        return posterior_columns(df, self.family, self.params).agg(F.count(F.lit(1)).alias("n"), F.sum("lse").alias("loglik"))

    # training --------------------------------------------------------------------------

    def resume(self, data: DataFrame, rounds: int, **options) -> ModelView:
        done = fit(data, self.family, self.params, rounds, start=Fit(self.family, self.params, list(self.trace_rows)), **options)
        out = ModelView.of(done)
        out.version = self.version
        return out

    # versions --------------------------------------------------------------------------

    def save(self, spark: SparkSession, path: str) -> int:
        """Write a new version; its manifest appears by rename, so a reader sees a whole version or none."""
        version = max(versions(spark, path), default=0) + 1
        self.frame(spark).coalesce(1).write.parquet(f"{path}/v{version}")
        meta = {"family": type(self.family).__name__, "options": {k: v for k, v in vars(self.family).items()}, "trace": self.trace_rows, "n": self.n}
        _write_text(spark, f"{path}/manifest-{version}.json", json.dumps(meta))
        self.version = version
        return version

    @classmethod
    def load(cls, spark: SparkSession, path: str, version: int | None = None) -> ModelView:
        version = version or max(versions(spark, path))
        meta = json.loads(_read_text(spark, f"{path}/manifest-{version}.json"))
        family = FAMILIES[meta["family"]](**meta["options"])
        params = family.from_rows(spark.read.parquet(f"{path}/v{version}").collect())
        return cls(family, params, version, [tuple(t) for t in meta["trace"]], meta["n"])


def entropy(p: Column) -> Column:
    return -F.aggregate(p, F.lit(0.0), lambda s, v: s + F.when(v > 0, v * F.log(v)).otherwise(0.0))


def mahalanobis(family: Gaussian, params: Params) -> Column:
    """Least distance of a row to a component's mean in its covariance."""
    parts = []
    for k in range(family.k(params)):
        low, _ = family._whitening(params, k)
        u = family.u_sql(params, k)
        z = [" + ".join(f"{num(low[i, j])} * {u[j]}" for j in range(i + 1)) for i in range(family.d)]
        parts.append("sqrt(" + " + ".join(f"power({t}, 2)" for t in z) + ")")
    return F.expr(f"least({', '.join(parts)})" if len(parts) > 1 else parts[0])


def information_criteria(view: ModelView, loglik: float, n: float) -> tuple[float, float]:
    """(AIC, BIC)."""
    k, d = view.k(), view.family.d
    if isinstance(view.family, Gaussian):
        per = {"full": d * (d + 1) // 2, "diag": d, "spherical": 1, "tied": 0}[view.family.cov]
        free = k - 1 + k * d + k * per + (d * (d + 1) // 2 if view.family.cov == "tied" else 0)
    else:
        m = view.family.m()
        free = k * (m + 1) + ((k - 1) * m if isinstance(view.family, ExpertMixture) else k - 1)
    return 2 * free - 2 * loglik, free * math.log(n) - 2 * loglik


def _fs(spark: SparkSession, path: str):
    at = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return at, at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())


def versions(spark: SparkSession, path: str) -> list[int]:
    at, fs = _fs(spark, path)
    if not fs.exists(at):
        return []
    names = [e.getPath().getName() for e in fs.listStatus(at)]
    return sorted(int(n[9:-5]) for n in names if n.startswith("manifest-") and n.endswith(".json"))


def _write_text(spark: SparkSession, path: str, text: str) -> None:
    at, fs = _fs(spark, path)
    part = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path + ".part")
    stream = fs.create(part, True)
    stream.write(bytearray(text.encode()))
    stream.close()
    if not fs.rename(part, at):
        raise OSError(f"{path} could not be committed")


def _read_text(spark: SparkSession, path: str) -> str:
    return "\n".join(r[0] for r in spark.read.text(path, wholetext=True).collect())
