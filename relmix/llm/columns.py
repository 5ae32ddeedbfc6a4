"""Column helpers shared by the text operators (JVM side)."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
#: A word of the corpus contracts: a run without space or the controls 9-13.
WORD = r"[^\x20\x09-\x0D]+"


def text_or_empty(name: str) -> Column:
    return F.coalesce(F.col(f"`{name}`").cast("string"), F.lit(""))


def ascii_lower(text: Column) -> Column:
    """Lower-case A-Z only. Pure ASCII text takes the fast built-in; other text is mapped letter by letter."""
    return F.when(F.octet_length(text) == F.length(text), F.lower(text)).otherwise(F.translate(text, UPPER, LOWER))


def word_count(text: Column) -> Column:
    return F.regexp_count(text, F.lit(WORD)).cast("long")


def narrow(df: DataFrame, **picked: str) -> DataFrame:
    """Only the named columns under internal names, so other columns of any name cannot clash."""
    return df.select(*[F.col(f"`{v}`").alias(k) for k, v in picked.items()])


def replaced(df: DataFrame, names: list[str]) -> DataFrame:
    """The frame without the columns an operator is about to add; its outputs replace them."""
    low = {n.lower() for n in names}
    return df.drop(*[c for c in df.columns if c.lower() in low])


#: Rows and bytes of one Arrow batch of texts. Spark's default of 10,000 rows makes batches of tens of
#: megabytes, of which every operator in a task holds several outside the heap.
BATCH_ROWS, BATCH_BYTES = 512, 4 << 20


def small_batches(df: DataFrame) -> DataFrame:
    """Bound the session's Arrow batches (a runtime setting) and return the frame."""
    conf = df.sparkSession.conf
    if int(conf.get("spark.sql.execution.arrow.maxRecordsPerBatch", "10000")) not in range(1, BATCH_ROWS + 1):
        conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", str(BATCH_ROWS))
    try:
        conf.set("spark.sql.execution.arrow.maxBytesPerBatch", str(BATCH_BYTES))
    except Exception:  # noqa: BLE001  a Spark version without this bound
        pass
    return df
