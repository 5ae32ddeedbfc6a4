"""Sources and sinks: training sets from files, views or queries; file and rate streams; model and report sinks."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


def read(spark: SparkSession, what: str, kind: str = "parquet", schema: str | None = None) -> DataFrame:
    """``kind``: parquet, csv, json, view or query."""
    if kind == "view":
        return spark.table(what)
    if kind == "query":
        return spark.sql(what)
    reader = spark.read.schema(schema) if schema else spark.read
    return reader.option("header", True).csv(what) if kind == "csv" else getattr(reader, kind)(what)


def read_stream(spark: SparkSession, path: str, schema: str, kind: str = "parquet", files_per_batch: int = 1) -> DataFrame:
    """Files of a folder as a stream, in order of their time stamps."""
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_batch).format(kind).load(path)


def rate_stream(spark: SparkSession, rows_per_second: int) -> DataFrame:
    return spark.readStream.format("rate").option("rowsPerSecond", rows_per_second).load()


def write(df: DataFrame, path: str, kind: str = "parquet", mode: str = "errorifexists", partition_by: list[str] | None = None) -> None:
    writer = df.write.mode(mode)
    if partition_by:
        writer = writer.partitionBy(*partition_by)
    writer.option("header", True).csv(path) if kind == "csv" else getattr(writer, kind)(path)


class _Slice(InputPartition):
    def __init__(self, start: int, stop: int):
        self.start, self.stop = start, stop


class MixtureSource(DataSource):
    """``spark.read.format("mixture").option("rows", n).option("separation", s).option("parts", p)``:
    two-component planted rows (tid, label, x0), each slice made where it is read."""

    @classmethod
    def name(cls) -> str:
        return "mixture"

    def schema(self) -> str:
        return "tid bigint, label int, x0 double"

    def reader(self, schema) -> DataSourceReader:
        return _MixtureReader(self.options)


class _MixtureReader(DataSourceReader):
    def __init__(self, options):
        self.rows = int(options.get("rows", 1000))
        self.separation = float(options.get("separation", 3.0))
        self.parts = int(options.get("parts", 4))

    def partitions(self):
        step = -(-self.rows // self.parts)
        return [_Slice(a, min(a + step, self.rows)) for a in range(0, self.rows, step)]

    def read(self, part):
        import numpy as np

        prime = 2147483647
        ids = np.arange(part.start, part.stop, dtype=np.int64)
        h1, h2 = (ids * 7919 + 13) % prime, (ids * 15485 + 7) % prime
        z = np.sqrt(-2 * np.log((h1 * h1 % prime + 0.5) / prime)) * np.cos(6.283185307179586 * (h2 * h2 % prime + 0.5) / prime)
        label = ids % 2
        for i, k, v in zip(ids.tolist(), label.tolist(), np.where(label == 0, -self.separation, self.separation) + z, strict=True):
            yield i, k, float(v)
