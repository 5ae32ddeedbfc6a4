import random

import brute

import corpus_pipeline
from relmix.llm import mixing, toxicity


def make(tmp_path, spark):
    rng = random.Random(2)
    word = lambda: "".join(rng.choice("aeioubcdfglmnprst") for _ in range(rng.randint(2, 7)))
    rows, marks = [], []
    for i in range(120):
        w = [word() for _ in range(rng.randint(10, 80))]
        if i % 10 == 3:
            w.insert(4, "idiot")
        text = " ".join(w)
        rows.append((i, text, "en", f"s{i % 4}", len(text)))
        marks.append((i, 1, int(i % 10 == 3)))
        if i % 15 == 0:
            rows.append((1000 + i, text.upper(), "en", "s0", len(text)))
        if i % 14 == 0 and len(w) > 50:
            near = " ".join(w[:-1] + ["changed"])
            rows.append((2000 + i, near, "en", "s1", len(near)))
    rows += [(5000, None, None, None, None), (5001, "", "en", "s2", 0)]
    d = str(tmp_path)
    spark.createDataFrame(rows, "doc_id bigint, text string, lang string, source string, n_chars bigint").write.parquet(f"{d}/documents.parquet")
    spark.createDataFrame(marks, "doc_id bigint, quality int, toxic int").write.parquet(f"{d}/labels.parquet")
    return d, rows


def test_pipeline_equals_brute_force(spark, tmp_path):
    d, rows = make(tmp_path, spark)
    got = corpus_pipeline.run(spark, d).collect()
    clean = [r for r in rows if not toxicity.Matcher(toxicity.Model()).clauses(r[1] or "")]
    last = {}
    for r in clean:
        key = (r[1] or "").translate(brute.LOW)
        last[key] = max(last.get(key, -1), r[0])
    unique = [r for r in clean if last[(r[1] or "").translate(brute.LOW)] == r[0]]
    groups = brute.near_components([(r[0], r[1]) for r in unique], 5, 80, 100)
    single = [r for r in unique if groups[r[0]][1] == r[0]]
    kept = spark.createDataFrame(single, "doc_id bigint, text string, lang string, source string, n_chars bigint")
    want = sorted(r.doc_id for r in mixing.mix(kept).collect() for _ in range(r.copies))
    assert sorted(r.doc_id for r in got) == want
    assert all(r.round_trip for r in got)


def test_stages_keep_columns_and_pass_empty_tables(spark, tmp_path):
    d, _ = make(tmp_path, spark)
    docs = spark.read.parquet(f"{d}/documents.parquet")
    for name, stage in corpus_pipeline.STAGES:
        out = stage(spark, docs.limit(0), d)
        assert out.count() == 0, name
        if name != "byte bpe":
            assert out.columns == docs.columns
    assert len(corpus_pipeline.STAGES) == 5
