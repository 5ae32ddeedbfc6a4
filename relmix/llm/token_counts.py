"""Token counts through a digest cache.

The cache is a Parquet table of (content digest, n_tokens), one folder for each tokenizer version,
the version being the SHA-256 of the tokenizer file and of the options. Contents are joined to it by
digest; of the distinct misses one row each is encoded and the new counts are appended, so a text is
tokenized once, in whatever table and however often it occurs.

Only digests and ids are joined. A text whose digest is a miss and occurs once is encoded where it is
read. Of texts that occur more often one is encoded; those move once, by a key that is unique (digest and
row id), so copies of one text do not meet in a task. Two bounded Bloom filters, of the digests that occur
more often or are known and of the misses, tell the texts apart; where the filters are full more texts
move, and the join decides. The cache is read with one count for each digest, so a folder that two jobs
appended the same digest to does no harm, nor does a repeated run. Rows take the count of their digest from
a table of this input's digests; those few that hold much of the rows are broadcast.

Defined cases: null counts as empty (0 tokens); an empty table gives an empty result; a null id is an
id like any other; rows that repeat id and text are counted alike; very long texts are counted whole;
only the named columns are read, so others of any name cannot clash. No normalisation beyond null to
empty is applied, as the library's counts depend on the exact text.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from functools import lru_cache

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from relmix.llm.columns import narrow, small_batches, text_or_empty
from relmix.llm.hot import with_group
from relmix.llm.prefilter import Filter
from relmix.llm.workers import tidy
from relmix.session import scratch, stored

OPTIONS = b"plain text, no added tokens, v1"
BATCH_CHARS = 1 << 20


def tokenizer_version(path: str) -> str:
    with open(path, "rb") as f:
        return hashlib.sha256(f.read() + OPTIONS).hexdigest()


@lru_cache(maxsize=2)
def _counter(path: str):
    """texts -> counts, by the library that the file's ending names; one for each Python worker."""
    if path.endswith(".model"):
        import sentencepiece

        model = sentencepiece.SentencePieceProcessor(model_file=path)
        return lambda texts: [len(x) for x in model.encode(texts, num_threads=1)]
    import tokenizers

    tokenizer = tokenizers.Tokenizer.from_file(path)
    tokenizer.no_truncation()
    tokenizer.no_padding()
    return lambda texts: [len(x.ids) for x in tokenizer.encode_batch(texts, add_special_tokens=False)]


def _count(path: str):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        count = _counter(path)
        for batch in batches:
            counts, part, size = [], [], 0
            for text in batch.column(1).to_pylist():
                part.append(text)
                size += len(text)
                if size >= BATCH_CHARS:
                    counts += count(part)
                    part, size = [], 0
            counts += count(part) if part else []
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(counts, pa.int64())], names=["digest", "n_tokens"])

    return run


class TokenCountCache:
    def __init__(self, spark: SparkSession, path: str, tokenizer_path: str):
        self.spark, self.tokenizer_path = spark, tokenizer_path
        self.path = f"{path}/tokenizer={tokenizer_version(tokenizer_path)}"

    def _exists(self) -> bool:
        at = self.spark.sparkContext._jvm.org.apache.hadoop.fs.Path(self.path)
        return at.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration()).exists(at)

    def rows(self) -> DataFrame:
        schema = "digest binary, n_tokens bigint"
        if not self._exists():
            return self.spark.createDataFrame([], schema)
        return self.spark.read.schema(schema).parquet(self.path).groupBy("digest").agg(F.first("n_tokens").alias("n_tokens"))

    def count(self, docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
        """(id, n_bytes, n_tokens) for every row; the cache learns the misses."""
        texts = narrow(docs, id=id_col, text=text_col).select("id", text_or_empty("text").alias("text"))
        digested = texts.withColumn("digest", F.unhex(F.sha2("text", 256)))
        keys = stored(digested.select("id", "digest", F.octet_length("text").cast("bigint").alias("n_bytes")), "count-digests")
        groups = keys.groupBy("digest").agg(F.min("id").alias("i"), F.count(F.lit(1)).alias("n"))
        known = self.rows().select("digest", F.lit(True).alias("known"))
        groups = stored(groups.join(known, "digest", "left").withColumnRenamed("digest", "d"), "count-groups")
        missed = groups.filter("known IS NULL")
        moving = Filter(groups.filter("n > 1 OR known").select("d"))
        alone = moving.impossible(digested, F.col("digest")).select("digest", "text")
        some = Filter(missed.select("d")).possible(moving.possible(digested, F.col("digest")), F.col("digest"))
        one = some.join(missed.hint("merge"), (F.col("digest") == F.col("d")) & F.col("id").eqNullSafe(F.col("i"))).select("digest", "text")
        run = tidy(_count(self.tokenizer_path))
        counts = [small_batches(part).mapInArrow(run, "digest binary, n_tokens bigint") for part in (alone, one)]
        counts = counts[0].unionAll(counts[1])
        # rows that repeat a missed (id, text) were each counted: the cache gets one count for each digest
        counts.groupBy("digest").agg(F.first("n_tokens").alias("n_tokens")).write.mode("append").parquet(self.path)
        found = groups.select(F.col("d").alias("digest"), "n").join(self.rows(), "digest")
        return with_group(keys, stored(found, "count-found"), "digest").select("id", "n_bytes", "n_tokens")


def op5_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    cache = TokenCountCache(spark, scratch(spark, "token-counts"), public_tokenizers.path("piece_bpe_32k.model"))
    return cache.count(docs).select(F.col("id").alias("doc_id"), "n_bytes", "n_tokens", (F.col("n_tokens") > 4096).alias("over_limit"))
