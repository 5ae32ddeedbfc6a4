"""Streams: scoring with a model, windows over scored events, statistics per key, model maintenance."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import DataStreamWriter, StreamingQuery
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from relmix.maintain.table import MaintainedTable
from relmix.session import remove, scratch
from relmix.sources.readers import read_stream
from relmix.view.model_view import ModelView

EVENTS = "event_id bigint, ts timestamp, user_id bigint, event_type string, value double, props string"

_STORE = "spark.sql.streaming.stateStore"
ON_DISK = {
    f"{_STORE}.providerClass": "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider",
    f"{_STORE}.rocksdb.changelogCheckpointing.enabled": "true",
    f"{_STORE}.rocksdb.boundedMemoryUsage": "true",
    f"{_STORE}.rocksdb.maxMemoryUsageMB": "256",  # of a process, for all its partitions
}


def replay(spark: SparkSession, events: DataFrame, files: int = 4) -> DataFrame:
    """A stream over a table: it is written as several files by time and read one file per micro-batch.

    Files are ordered by their time stamps, so the parts are written one after another.
    """
    path = scratch(spark, "replay")
    events = events.withColumn("ts", F.col("ts").cast("timestamp"))
    cuts = [float(q) for q in events.agg(F.percentile_approx(F.col("ts").cast("double"), [i / files for i in range(1, files)], 100_000)).head()[0]] if files > 1 else []
    part = sum((F.when(F.col("ts").cast("double") > c, 1).otherwise(0) for c in cuts), F.lit(0))
    marked = events.withColumn("__part", part)
    for i in range(files):
        marked.filter(F.col("__part") == i).drop("__part").coalesce(1).write.mode("append").parquet(path)
    return read_stream(spark, path, EVENTS)


def score_stream(stream: DataFrame, view: ModelView, x: str = "value") -> DataFrame:
    """Stream-static: the model is literals in the projection, so scoring keeps no state."""
    return view.clustered(stream.withColumn("x0", F.col(x).cast("double")))


def windowed_components(scored: DataFrame, width: str, slide: str | None = None, watermark: str = "1 hour", extra: list[str] | None = None) -> DataFrame:
    """Counts and sums by window and component; rows later than the watermark are dropped."""
    by = [F.window("ts", width, slide) if slide else F.window("ts", width), *(extra or [])]
    return scored.withWatermark("ts", watermark).groupBy(*by).agg(F.count(F.lit(1)).alias("n"), F.sum("value").alias("total"))


def sessions(stream: DataFrame, gap: str, watermark: str = "1 hour") -> DataFrame:
    return stream.withWatermark("ts", watermark).groupBy(F.session_window("ts", gap), "user_id").agg(F.count(F.lit(1)).alias("n"))


def deduplicated(stream: DataFrame, keys: list[str], watermark: str = "1 hour") -> DataFrame:
    return stream.withWatermark("ts", watermark).dropDuplicatesWithinWatermark(keys)


def _running(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
    n, total, squares = state.get if state.exists else (0, 0.0, 0.0)
    for f in frames:
        n, total, squares = n + len(f), total + float(f["value"].sum()), squares + float((f["value"] ** 2).sum())
    state.update((n, total, squares))
    yield pd.DataFrame({"user_id": [key[0]], "n": [n], "total": [total], "squares": [squares]})


def running_stats(stream: DataFrame) -> DataFrame:
    """(user_id, n, total, squares): additive statistics kept per user; each batch yields the users it touched."""
    schema = "user_id bigint, n bigint, total double, squares double"
    return stream.groupBy("user_id").applyInPandasWithState(_running, schema, "n bigint, total double, squares double", "update", GroupStateTimeout.NoTimeout)


def maintain_stream(stream: DataFrame, table: MaintainedTable, checkpoint: str, x: str | dict[str, str] = "value", tid: str = "event_id"):
    """Each micro-batch is one insert statement; a batch id that the manifest has is not applied again.

    ``x``: the column of a one-dimensional model, or SQL for each column of the table's family."""
    bound = {"x0": f"`{x}`"} if isinstance(x, str) else x
    rows = stream.select(F.col(tid).alias("tid"), *[F.expr(sql).cast("double").alias(c) for c, sql in bound.items()])

    def apply(batch: DataFrame, batch_id: int) -> None:
        if not batch.isEmpty():
            table.insert(batch, f"{checkpoint}#{batch_id}")

    return rows.writeStream.foreachBatch(apply).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def _begun(spark: SparkSession, writer: DataStreamWriter, on_disk: bool) -> StreamingQuery:
    """A started query; it copies the session's settings when it starts, and the session gets its own back."""
    settings = ON_DISK if on_disk else {}
    before = {k: spark.conf.get(k, None) for k in settings}
    try:
        for k, v in settings.items():
            spark.conf.set(k, v)
        return writer.start()
    finally:
        for k, v in before.items():
            spark.conf.unset(k) if v is None else spark.conf.set(k, v)


def finished(spark: SparkSession, frame: DataFrame, mode: str, name: str, on_disk: bool = False) -> DataFrame:
    """Run a stream to the end of its input and return what it wrote, as tables in the shared folder.

    ``append`` goes to a file sink; the other modes write each batch to a folder of its own, which a repeated batch
    overwrites. Of ``complete`` only the last batch is kept. No rows pass through the driver. ``on_disk``: the state,
    else in the heap whole, is kept in RocksDB; for queries that keep many keys to the end, at the cost of time."""
    path, checkpoint = scratch(spark, "streamed"), scratch(spark, "stream")
    writer = frame.writeStream.queryName(name).outputMode(mode).option("checkpointLocation", checkpoint).trigger(availableNow=True)
    if mode == "append":
        _begun(spark, writer.format("parquet").option("path", path), on_disk).awaitTermination()
        return spark.read.schema(frame.schema).parquet(path)
    batches: list[int] = []

    def keep(batch: DataFrame, batch_id: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/{batch_id}")
        if mode == "complete":
            for old in batches:
                if old != batch_id:
                    remove(spark, f"{path}/{old}")
            batches.clear()
        if batch_id not in batches:
            batches.append(batch_id)

    _begun(spark, writer.foreachBatch(keep), on_disk).awaitTermination()
    if not batches:
        return spark.createDataFrame([], frame.schema)
    return spark.read.schema(frame.schema).parquet(*[f"{path}/{i}" for i in batches])
