import hashlib
import random

import brute
import pytest

from relmix.llm import exact_dedup, mixing, near_dedup

SCHEMA = "doc_id bigint, text string, lang string, source string, n_chars bigint"


def frame(spark, rows, schema=SCHEMA):
    return spark.createDataFrame(rows, schema)


def doc(i, text, source="a"):
    return (i, text, "en", source, len(text or ""))


def rows_of(df, *names):
    return {tuple(r[n] for n in names) for r in df.collect()}


def test_exact_keeps_largest_id_and_ignores_ascii_case(spark):
    docs = frame(spark, [doc(1, "Abc"), doc(2, "aBC"), doc(3, "É"), doc(4, "é"), doc(5, None), doc(6, "")])
    done = exact_dedup.deduplicate(docs, exact_dedup.new_index(spark))
    assert rows_of(done, "id", "keep_id", "group_size", "kept") == {(1, 2, 2, False), (2, 2, 2, True), (3, 3, 1, True), (4, 4, 1, True), (5, 6, 2, False), (6, 6, 2, True)}


def test_exact_index_is_persistent(spark, tmp_path):
    path = f"file://{tmp_path}/index"
    first = exact_dedup.DigestIndex.open(spark, path, buckets=8)
    exact_dedup.deduplicate(frame(spark, [doc(1, "x"), doc(2, "y")]), first).collect()
    again = exact_dedup.DigestIndex.open(spark, path)
    assert again.buckets == 8
    done = exact_dedup.deduplicate(frame(spark, [doc(7, "x"), doc(8, "z"), doc(9, "z")]), again)
    assert rows_of(done, "id", "keep_id", "kept") == {(7, 1, False), (8, 9, False), (9, 9, True)}
    assert again.rows().count() == 3


def test_exact_empty_null_ids_and_clashing_columns(spark):
    index = exact_dedup.new_index(spark)
    assert exact_dedup.deduplicate(frame(spark, []), index).collect() == []
    odd = spark.createDataFrame([(1, "q", "k"), (None, "q", "k"), (None, "w", "k")], "doc_id bigint, text string, digest string")
    done = exact_dedup.deduplicate(odd, exact_dedup.new_index(spark))
    assert sorted((r.id or 0, r.keep_id or 0, r.kept) for r in done.collect()) == [(0, 0, False), (0, 1, False), (1, 1, True)]
    kept = exact_dedup.surviving(odd, exact_dedup.new_index(spark))
    assert kept.columns == odd.columns


def words(rng, n):
    return [rng.choice(["red", "blue", "Green", "sun", "moon", "star", "é", "x", "tree", "stone"]) + str(rng.randint(0, 40)) for _ in range(n)]


@pytest.mark.parametrize(("width", "num"), [(3, 85), (5, 80)])
def test_near_duplicates_equal_brute_force(spark, width, num):
    rng = random.Random(width)
    texts = []
    for _ in range(25):
        base = words(rng, rng.randint(1, 120))
        texts.append(" ".join(base))
        for _ in range(rng.randint(0, 8)):
            w = list(base)
            for _ in range(rng.randint(0, 3)):
                w[rng.randrange(len(w))] = "edit" + str(rng.randint(0, 9))
            texts.append(rng.choice([" ", "\t", "\n "]).join(w).upper() if rng.random() < 0.3 else " ".join(w))
    texts += ["", None, " \n\t", "one", "One", "one two", "two one"]
    rng.shuffle(texts)
    rows = list(enumerate(texts))
    got = {r.id: (r.n_shingles, r.component_id) for r in near_dedup.near_duplicates(frame(spark, [doc(i, t) for i, t in rows]), width=width, num=num).collect()}
    assert got == brute.near_components(rows, width, num, 100)


def test_near_duplicates_in_many_blocks(spark, monkeypatch):
    monkeypatch.setattr(near_dedup, "BUCKET_BLOCK", 7)
    monkeypatch.setattr(near_dedup, "SHINGLE_BLOCK", 500)
    rng = random.Random(4)
    base = words(rng, 60)
    texts = [" ".join(base[:k] + ["new" + str(i)] + base[k + 1 :]) for i in range(40) for k in [rng.randrange(60)]]
    rows = list(enumerate(texts))
    got = {r.id: (r.n_shingles, r.component_id) for r in near_dedup.near_duplicates(frame(spark, [doc(i, t) for i, t in rows]), width=3, num=85).collect()}
    assert got == brute.near_components(rows, 3, 85, 100)


def test_near_empty_null_id_and_columns(spark):
    assert near_dedup.near_duplicates(frame(spark, [])).collect() == []
    odd = spark.createDataFrame([(None, "a b c d e f", 1), (3, "a b c d e f", 2), (4, "a b c d e f", 3)], "doc_id bigint, text string, n_sh int")
    got = {(r.id, r.component_id, r.kept) for r in near_dedup.near_duplicates(odd).collect()}
    assert got == {(None, None, False), (3, 3, True), (4, 3, False)}
    kept = near_dedup.surviving(odd)
    assert kept.columns == odd.columns and sorted(r.doc_id or 0 for r in kept.collect()) == [0, 3]


def test_near_long_text(spark):
    long = " ".join(f"w{i % 5000}x{i % 77}" for i in range(120_000))
    got = {r.id: r.component_id for r in near_dedup.near_duplicates(frame(spark, [doc(1, long), doc(2, long + " tail"), doc(3, "short")])).collect()}
    assert got == {1: 1, 2: 1, 3: 3}


def water(sizes, weights, cap):
    """Targets by repeated clamping."""
    total, free = sum(sizes), set(range(len(sizes)))
    target, left = [0.0] * len(sizes), float(sum(sizes))
    while free:
        w = sum(weights[i] for i in free)
        over = [i for i in free if left * weights[i] / w > cap * sizes[i]]
        if not over:
            for i in free:
                target[i] = left * weights[i] / w
            break
        for i in over:
            target[i] = cap * sizes[i]
            left -= target[i]
            free.remove(i)
    assert abs(sum(target) - total) < 1e-6
    return target


def test_mix_targets_and_taken(spark):
    rng = random.Random(9)
    counts = {"s1": 400, "s2": 5, "s3": 60, "s4": 900, None: 30}
    rows, i = [], 0
    for source, n in counts.items():
        for _ in range(n):
            i += 1
            rows.append(doc(i, " ".join(["w"] * rng.randint(0, 30)), source))
    got = mixing.mix(frame(spark, rows)).collect()
    order = ["s1", "s2", "s3", "s4", None]
    sizes = [sum(len(brute.WORD.findall(r[1])) for r in rows if r[3] == s) for s in order]
    want = dict(zip(order, water(sizes, [5, 2, 1, 5, 2], 3), strict=True))
    taken = dict.fromkeys(order, 0)
    for r in got:
        assert abs(r.target - want[r.source]) < 1e-6 and 0 <= r.copies <= 3
        taken[r.source] += r.size * r.copies
    for s in order:
        assert abs(taken[s] - want[s]) <= 30
    again = {(r.doc_id, r.copies) for r in mixing.mix(frame(spark, rows)).collect()}
    assert again == {(r.doc_id, r.copies) for r in got}


def test_mix_edges(spark):
    assert mixing.mix(frame(spark, [])).collect() == []
    got = mixing.mix(frame(spark, [doc(1, None), doc(2, "")])).collect()
    assert {(r.doc_id, r.size, r.target, r.copies) for r in got} == {(1, 0, 0.0, 0), (2, 0, 0.0, 0)}
    odd = spark.createDataFrame([(1, "a b", "s", 9), (1, "a b", "s", 9)], "doc_id bigint, text string, source string, size int")
    mixed = mixing.mix(odd)
    assert {(r.size, r.source_size, r.copies) for r in mixed.collect()} == {(2, 4, 1)}
    clash = spark.createDataFrame([(1, "a b", "s", 1, 2, "x")], "doc_id bigint, text string, source string, whole int, bin int, src string")
    assert [(r.whole, r.bin, r.src, r.copies) for r in mixing.mix(clash).collect()] == [(1, 2, "x", 1)]
    assert mixing.repeated(frame(spark, [doc(1, "a b")])).columns == ["doc_id", "text", "lang", "source", "n_chars"]


FIRST_BIN = next(i for i in range(5000, 10**6) if hashlib.md5(f"{i}:17".encode()).hexdigest().startswith("000"))


def off_target(mixed):
    taken, target = {}, {}
    for r in mixed.collect():
        taken[r.source] = taken.get(r.source, 0) + r.size * r.copies
        target[r.source] = r.target
    return {s: abs(taken[s] - target[s]) for s in target}


def test_mix_passes_over_a_dominating_document(spark):
    rows = [doc(i, "w " * 100, "a") for i in range(100)] + [doc(1000 + i, "w " * 10, "b") for i in range(210)]
    rng = random.Random(1)
    rows += [doc(2000 + i, "w " * rng.randint(1, 400), "c") for i in range(50)]
    off = off_target(mixing.mix(frame(spark, [*rows, doc(FIRST_BIN, "w " * 20_000, "a")]), weights=(1, 1, 3)))
    assert off["a"] <= 50 and off["b"] <= 5 and off["c"] <= 200


def test_mix_refines_bins_of_many_documents(spark, monkeypatch):
    monkeypatch.setattr(mixing, "hash_cell", lambda doc_id, seed: (doc_id % 2 * 4096 + doc_id % 1000).cast("int"))
    rng = random.Random(2)
    rows = [doc(i, "w " * rng.randint(1, 9) * (1 + i // 1000 * 3), "ab"[i // 1000]) for i in range(2000)] + [doc(9000, "w " * 20_000, "a")]
    off = off_target(mixing.mix(frame(spark, rows), weights=(1, 12)))
    assert off["a"] <= 5 and off["b"] <= 20


def test_exact_surviving_keeps_texts_without_id_and_judges_by_text(spark):
    rows = [doc(1, "q"), doc(None, "Q"), doc(None, "alone"), doc(None, "twice"), doc(None, "TWICE"), doc(None, None), doc(5, "q"), doc(1, "other"), doc(7, "r"), doc(8, "r")]
    index = exact_dedup.new_index(spark)
    kept = exact_dedup.surviving(frame(spark, rows), index)
    assert sorted(((r.doc_id or 0), (r.text or "").lower()) for r in kept.collect()) == [(0, ""), (0, "alone"), (0, "twice"), (1, "other"), (5, "q"), (8, "r")]
    again = exact_dedup.surviving(frame(spark, [doc(9, "alone"), doc(None, "twice"), doc(None, "new"), doc(10, "last")]), index)
    assert sorted((r.doc_id or 0, r.text) for r in again.collect()) == [(0, "new"), (10, "last")]


def test_exact_repeated_runs_keep_what_the_first_kept(spark, tmp_path):
    rows = [doc(1, "x"), doc(2, "X"), doc(3, "y"), doc(None, "z"), doc(3, "y")]
    with exact_dedup.DigestIndex.open(spark, f"file://{tmp_path}/index", buckets=4) as index:
        first = rows_of(exact_dedup.surviving(frame(spark, rows), index, batch="b1"), "doc_id", "text")
        assert first == {(2, "X"), (3, "y"), (None, "z")}
        assert rows_of(exact_dedup.surviving(frame(spark, rows), index, batch="b1"), "doc_id", "text") == first
        # without the batch's name ids tell; a text without an id is known then
        assert rows_of(exact_dedup.surviving(frame(spark, rows), index), "doc_id", "text") == {(2, "X"), (3, "y")}
        other = exact_dedup.deduplicate(frame(spark, [doc(9, "x"), doc(8, "new"), doc(None, "z")]), index, batch="b2")
        assert rows_of(other, "id", "keep_id", "kept") == {(9, 2, False), (8, 8, True), (None, None, False)}
        assert index.rows().count() == 4
        name = index.table
    assert not spark.catalog.tableExists(name)


def test_exact_long_texts_and_clashing_columns(spark):
    long = "a long text " * 200_000
    rows = [(1, long, 1, "k"), (2, long.upper(), 2, "k"), (2, long.upper(), 2, "k")]
    docs = spark.createDataFrame(rows, "doc_id bigint, text string, keep_id int, known string")
    with exact_dedup.new_index(spark) as index:
        kept = exact_dedup.surviving(docs, index)
        assert kept.columns == docs.columns and [r.doc_id for r in kept.collect()] == [2, 2]
