"""Joins with one row a group where a group holds a third of all rows."""

import hashlib

import pytest
from pyspark.sql import functions as F

from relmix.llm import exact_dedup, hot
from relmix.session import stored


def test_every_row_meets_its_group_once(spark):
    rows = stored(spark.range(6000).select("id", F.when(F.col("id") % 3 == 0, F.lit(-1)).otherwise(F.col("id") % 2500).alias("g")), "hot-test")
    groups = stored(rows.groupBy("g").agg(F.count(F.lit(1)).alias("n"), F.max("id").alias("top")), "hot-test")
    want = {}
    for r in rows.collect():
        want.setdefault(r.g, []).append(r.id)
    got = hot.with_group(rows, groups, "g").collect()
    assert sorted((r.id, r.n, r.top) for r in got) == sorted((i, len(x), max(x)) for x in want.values() for i in x)
    assert hot.with_group(rows.limit(0), groups.limit(0), "g").collect() == []


@pytest.mark.parametrize("parts", [1, 2, 1000])
def test_verdicts_do_not_depend_on_what_is_broadcast(spark, monkeypatch, parts):
    monkeypatch.setattr(hot, "PARTS", parts)
    texts = [None if i % 3 == 0 else f"Text {i % 40}" for i in range(600)]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id bigint, text string")
    with exact_dedup.new_index(spark) as index:
        got = {r.id: r for r in exact_dedup.deduplicate(docs, index).collect()}
    assert len(got) == 600
    for i, t in enumerate(texts):
        same = [j for j, o in enumerate(texts) if (o or "").lower() == (t or "").lower()]
        assert (got[i].keep_id, got[i].group_size, got[i].kept) == (max(same), len(same), i == max(same))
        assert bytes(got[i].digest) == hashlib.sha256((t or "").lower().encode()).digest()
