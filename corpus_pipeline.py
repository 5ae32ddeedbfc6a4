"""A corpus pipeline over ``documents``: toxicity, exact and near deduplication, mixing, encoding.

Each stage takes (spark, docs, sf_dir) and returns a DataFrame; all but the last return the columns
of documents. Between stages the rows are written as Parquet and read again. Stages see all their
predecessor kept.

Defined cases, stage by stage: a null text counts as empty and is read whole at any length, like every
text; an empty table passes through; columns beside doc_id, text and source are carried along whatever
their names, and only those three are read. Rows without an id: toxicity scores them, exact dedup keeps
one of each text, near dedup keeps all, mixing deals them by the empty id, encoding encodes them.
Repeated rows (same id and text): toxicity treats them alike, both dedup stages keep or drop them
together, mixing takes them alike, encoding encodes each. Ties: a score of 0.5 is toxic, a similarity of
exactly 0.8 links.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from relmix.llm import bpe, exact_dedup, mixing, near_dedup, toxicity
from relmix.session import stored


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that score 0.5 or more go. The model learns from the labelled documents."""
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet")
    scored = toxicity.score(docs, toxicity.learn(docs, labels))
    return scored.filter("toxicity < 0.5").drop("toxicity", "toxic_clauses")


def drop_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of equal texts the one with the largest id stays."""
    with exact_dedup.new_index(spark) as index:
        return exact_dedup.surviving(docs, index)


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of documents linked by 0.8 similarity of five-word shingles the one with the smallest id stays."""
    return near_dedup.surviving(docs)


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Sources meet their target weights: documents are repeated or left out as the mix says."""
    return mixing.repeated(docs)


def encode_bytes(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Every document with its token ids; the ids are decoded again and must give the text."""
    import public_tokenizers

    coded = bpe.encode_checked(docs, public_tokenizers.path("byte_bpe_50k.tiktoken"))
    return coded.select("doc_id", "lang", "source", "n_tokens", "ids", "slice_offsets", "round_trip")


STAGES = [
    ("toxicity", drop_toxic),
    ("exact dedup", drop_copies),
    ("near dedup", drop_near_copies),
    ("mixing", mix_sources),
    ("byte bpe", encode_bytes),
]

#: Learned scores, MinHash groups and token ids are beyond SQL; tests compare with a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES[:-1]:
        docs = stored(stage(spark, docs, sf_dir), "pipeline-" + name.replace(" ", "-"))
    return STAGES[-1][1](spark, docs, sf_dir)
