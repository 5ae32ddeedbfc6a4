"""Session helpers: shared folders, worker import path, lineage cuts."""

from __future__ import annotations

import os
import uuid
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession

REPO_ROOT = str(Path(__file__).resolve().parent.parent)


def ready(spark: SparkSession) -> SparkSession:
    """Make sure Python workers can import this package (they inherit the context's environment)."""
    env = spark.sparkContext.environment
    known = env.get("PYTHONPATH", "") or os.environ.get("PYTHONPATH", "")
    if REPO_ROOT not in known.split(os.pathsep):
        env["PYTHONPATH"] = os.pathsep.join(x for x in (REPO_ROOT, known) if x)
    # workers outlive their tasks: few malloc arenas and the system's allocator give freed memory back
    for name, value in (("ARROW_DEFAULT_MEMORY_POOL", "system"), ("MALLOC_ARENA_MAX", "2")):
        env.setdefault(name, value)
    return spark


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: ``spark.checkpoint.dir``; a local one only where that is unset."""
    named = spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if not named:
        named = spark.sparkContext.getCheckpointDir()
    if not named:
        named = "/tmp/checkpoints/relmix"
        spark.sparkContext.setCheckpointDir(named)
    return named.rstrip("/")


_MADE: list[str] = []


def scratch(spark: SparkSession, label: str) -> str:
    """A fresh path in the shared folder."""
    _MADE.append(f"{shared_dir(spark)}/{label}-{uuid.uuid4().hex}")
    return _MADE[-1]


def release(spark: SparkSession) -> int:
    """Delete every intermediate table this process has made; frames that read them are no longer usable."""
    n = len(_MADE)
    while _MADE:
        remove(spark, _MADE.pop())
    return n


def stored(df: DataFrame, label: str) -> DataFrame:
    """Cut lineage: write once to the shared folder, continue from the written table.

    The written files survive the loss of any executor, unlike cached blocks.
    """
    path = scratch(df.sparkSession, label)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def remove(spark: SparkSession, path: str) -> None:
    """Delete a path through Hadoop, so it also works on stores that only Spark reads."""
    jvm = spark.sparkContext._jvm
    at = jvm.org.apache.hadoop.fs.Path(path)
    at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(at, True)
