import public_tokenizers
import pytest
import tokenizers

from relmix.llm import prefilter, token_counts
from relmix.session import scratch

PIECES, BYTES = public_tokenizers.path("piece_bpe_32k.model"), public_tokenizers.path("byte_bpe_50k.json")
TEXTS = ["once", "twice", "twice", None, "", "a b c", "Ünï <s> </s> <|endoftext|>", "x" * 9000, "once more"]


def frame(spark, texts):
    return spark.createDataFrame([(i, t, 7) for i, t in enumerate(texts)], "doc_id bigint, text string, n_tokens int")


def test_counts_equal_the_json_library(spark):
    library = tokenizers.Tokenizer.from_file(BYTES)
    cache = token_counts.TokenCountCache(spark, scratch(spark, "counts-test"), BYTES)
    got = {r.id: r.n_tokens for r in cache.count(frame(spark, TEXTS)).collect()}
    assert got == {i: len(library.encode(t or "", add_special_tokens=False).ids) for i, t in enumerate(TEXTS)}


def test_doubled_cache_rows_do_no_harm(spark):
    cache = token_counts.TokenCountCache(spark, scratch(spark, "counts-test"), PIECES)
    first = sorted(tuple(r) for r in cache.count(frame(spark, TEXTS)).collect())
    cache.rows().write.mode("append").parquet(cache.path)  # as a second job would
    assert sorted(tuple(r) for r in cache.count(frame(spark, TEXTS)).collect()) == first
    odd = spark.createDataFrame([(None, "once"), (None, "once"), (None, "unseen")], "doc_id bigint, text string")
    assert sorted(r.n_tokens for r in cache.count(odd).collect()) == sorted([first[0][2]] * 2 + [cache.count(odd.filter("text = 'unseen'")).collect()[0].n_tokens])
    assert cache.rows().count() == len({t or "" for t in TEXTS}) + 1


def test_only_distinct_misses_are_encoded(spark, tmp_path, monkeypatch):
    seen = tmp_path / "seen"
    seen.mkdir()

    def recording(path):
        def run(batches):
            import uuid

            import pyarrow as pa

            for batch in batches:
                texts = batch.column(1).to_pylist()
                (seen / uuid.uuid4().hex).write_text("\n".join(texts))
                yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([len(t) for t in texts], pa.int64())], names=["digest", "n_tokens"])

        return run

    monkeypatch.setattr(token_counts, "_count", recording)
    cache = token_counts.TokenCountCache(spark, scratch(spark, "counts-test"), PIECES)
    texts = [f"text {i % 60}" if i < 90 else f"same {i % 2}" for i in range(400)]
    assert {r.id: r.n_tokens for r in cache.count(frame(spark, texts)).collect()} == {i: len(t) for i, t in enumerate(texts)}
    cache.count(frame(spark, [*texts, "fresh"])).collect()
    done = [line for f in seen.iterdir() for line in f.read_text().split("\n") if line]
    assert sorted(done) == sorted({*texts, "fresh"})


@pytest.mark.parametrize("most", [1 << 10, 1 << 25])
def test_filter_never_loses_a_key(spark, monkeypatch, most):
    monkeypatch.setattr(prefilter, "MOST_BITS", most)
    keys = spark.range(0, 3000, 3).toDF("k")
    found = prefilter.Filter(keys)
    rows = spark.range(6000)
    possible = {r.id for r in found.possible(rows, rows["id"]).collect()}
    assert set(range(0, 3000, 3)) <= possible
    assert {r.id for r in found.impossible(rows, rows["id"]).collect()} == set(range(6000)) - possible
    assert most == 1 << 10 or len(possible) < 2500
    nothing = prefilter.Filter(keys.limit(0))
    assert nothing.possible(rows, rows["id"]).count() == 0 and nothing.impossible(rows, rows["id"]).count() == 6000
