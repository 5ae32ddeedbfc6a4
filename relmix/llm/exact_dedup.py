"""Exact deduplication against a persistent digest index.

The index is a Parquet table of (digest, keep_id, batch), bucketed and sorted by digest. New data is
digested, its own copies are collapsed (largest id stays) by an aggregate that combines before the
shuffle, and the groups are sort-merge anti-joined with the index: groups whose digest it has are
dropped as known, the others are appended. Buckets spare the index side of the join its shuffle.
Rows learn their group's verdict by digest; the few groups that hold much of the rows are broadcast.

A run that failed after it had appended can be repeated: the row whose id and text the index has stays
kept, and with a ``batch`` name whatever this batch has appended counts as new again (that also covers
texts without an id). Repeated runs append nothing twice.

Equality: same SHA-256 of the UTF-8 text after lower-casing A-Z only; null text counts as empty.
Defined cases: a row with a null id is never the kept one; where all ids of a group are null, keep_id
is null and no row is marked, but ``surviving`` keeps one row of such a group; rows that repeat id and
text are one document and are kept or dropped together; rows that repeat an id with other texts are
judged by their own text; an empty table gives an empty result; very long texts are digested whole;
only the named columns are read, so others of any name cannot clash.
"""

from __future__ import annotations

import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from relmix.llm.columns import ascii_lower, narrow, text_or_empty
from relmix.llm.hot import with_group
from relmix.session import scratch, stored


def digests(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, digest): 32 bytes for each row."""
    rows = narrow(docs, id=id_col, text=text_col)
    return rows.select("id", F.unhex(F.sha2(ascii_lower(text_or_empty("text")), 256)).alias("digest"))


class DigestIndex:
    """A digest index at a path in the shared store; ``open`` finds an existing one with its bucket count."""

    def __init__(self, spark: SparkSession, path: str, buckets: int):
        self.spark, self.path, self.buckets = spark, path, buckets
        self.table = f"digest_index_{uuid.uuid4().hex}"
        spark.sql(
            f"CREATE TABLE {self.table} (digest BINARY, keep_id BIGINT, batch STRING) USING parquet "
            f"CLUSTERED BY (digest) SORTED BY (digest) INTO {buckets} BUCKETS LOCATION '{path}/buckets={buckets}'"
        )

    @classmethod
    def open(cls, spark: SparkSession, path: str, buckets: int = 64) -> DigestIndex:
        at = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
        fs = at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())
        if fs.exists(at):
            for entry in fs.listStatus(at):
                name = entry.getPath().getName()
                if name.startswith("buckets="):
                    buckets = int(name.split("=")[1])
        return cls(spark, path, buckets)

    def rows(self) -> DataFrame:
        return self.spark.table(self.table)

    def close(self) -> None:
        """Take the index out of the catalogue; its files stay."""
        self.spark.sql(f"DROP TABLE IF EXISTS {self.table}")

    def __enter__(self) -> DigestIndex:
        return self

    def __exit__(self, *_) -> None:
        self.close()

    def add(self, groups: DataFrame, batch: str | None = None) -> DataFrame:
        """groups: (digest, best). Appends what is new and returns (digest, keep_id, known) for every group."""
        known = self.rows().withColumn("known", F.lit(True))
        # written first: else the anti-join is pushed below the aggregate and copies of one text meet in a task
        groups = stored(groups, "dedup-found")
        fresh = groups.hint("merge").join(known, "digest", "left_anti").select("digest", F.col("best").alias("keep_id"), F.lit(batch).cast("string").alias("batch"))
        dealt = fresh.repartition(self.buckets, "digest").sortWithinPartitions("digest")
        own = F.col("batch").isNotNull() & F.col("batch").eqNullSafe(F.lit(batch).cast("string"))
        marked = groups.join(known.hint("merge"), "digest", "left").select("digest", F.when(F.col("known"), F.col("keep_id")).otherwise(F.col("best")).alias("keep_id"), (F.col("known").isNotNull() & ~own).alias("known"), "n")
        marked = stored(marked, "dedup-groups")  # before the append changes the index
        dealt.write.format("parquet").bucketBy(self.buckets, "digest").sortBy("digest").mode("append").option("path", f"{self.path}/buckets={self.buckets}").saveAsTable(self.table)
        self.spark.catalog.refreshTable(self.table)
        return marked


def stays() -> Column:
    """The kept id of a text, also where the index has this id for it; in a new group without ids, all rows."""
    return F.col("id").eqNullSafe(F.col("keep_id")) & (~F.col("known") | F.col("id").isNotNull())


def judged(docs: DataFrame, index: DigestIndex, id_col: str, text_col: str, batch: str | None) -> DataFrame:
    """(id, digest, keep_id, known, n) for every row; the index learns the new digests."""
    rows = stored(digests(docs, id_col, text_col), "dedup-digests")
    groups = index.add(rows.groupBy("digest").agg(F.max("id").alias("best"), F.count(F.lit(1)).alias("n")), batch)
    return with_group(rows, groups, "digest")


def deduplicate(docs: DataFrame, index: DigestIndex, id_col: str = "doc_id", text_col: str = "text", batch: str | None = None) -> DataFrame:
    """(id, digest, keep_id, group_size, kept) for every row; the index learns the new digests.

    Against an index that already has a digest all rows of it are dropped but the one that it keeps.
    """
    kept = stays() & F.col("id").isNotNull()
    return judged(docs, index, id_col, text_col, batch).select("id", "digest", "keep_id", F.col("n").alias("group_size"), kept.alias("kept"))


def surviving(docs: DataFrame, index: DigestIndex, id_col: str = "doc_id", text_col: str = "text", batch: str | None = None) -> DataFrame:
    """The documents that stay, in the input's columns. Only ids and digests of dropped rows are joined, not texts."""
    dropped = stored(judged(docs, index, id_col, text_col, batch).filter(~stays()).select(F.col("id").alias("__gone"), F.col("digest").alias("__gone_digest")).distinct(), "dedup-dropped")
    named = F.col(f"`{id_col}`")
    rows = docs.withColumn("__digest", F.unhex(F.sha2(ascii_lower(text_or_empty(text_col)), 256)))
    same = F.col("__digest") == F.col("__gone_digest")
    with_id = rows.filter(named.isNotNull()).join(dropped.filter("__gone IS NOT NULL"), (named == F.col("__gone")) & same, "left_anti")
    # collapsed before the join, so copies of one text do not meet in a task
    without = rows.filter(named.isNull()).dropDuplicates(["__digest"]).join(dropped.filter("__gone IS NULL"), same, "left_anti")
    return with_id.unionAll(without).drop("__digest")


def new_index(spark: SparkSession) -> DigestIndex:
    return DigestIndex.open(spark, scratch(spark, "digest-index"), max(16, int(spark.conf.get("spark.sql.shuffle.partitions"))))


def op2_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    with new_index(spark) as index:
        done = deduplicate(docs, index)
    return done.select(F.col("id").alias("doc_id"), "keep_id", "group_size", "kept", F.lower(F.hex("digest")).alias("text_sha256"))


OP2_SQL = """
WITH d AS (SELECT doc_id, sha256(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')) AS text_sha256 FROM documents),
g AS (SELECT text_sha256, max(doc_id) AS keep_id, count(*) AS group_size FROM d GROUP BY text_sha256)
SELECT doc_id, keep_id, group_size, doc_id = keep_id AS kept, text_sha256 FROM d JOIN g USING (text_sha256)
"""
