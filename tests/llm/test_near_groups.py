import random

import brute
import pytest

from relmix.llm import near_dedup

SCHEMA = "doc_id bigint, text string"


def components_of(spark, rows, width=3, num=85):
    return {r.id: (r.n_shingles, r.component_id) for r in near_dedup.near_duplicates(spark.createDataFrame(rows, SCHEMA), width=width, num=num).collect()}


def drifting(rng, n, steps):
    """Texts that change a word at a time, so that neighbours link and far ones do not."""
    w = [f"w{rng.randint(0, 10**6)}" for _ in range(n)]
    out = [" ".join(w)]
    for _ in range(steps):
        w[rng.randrange(n)] = f"n{rng.randint(0, 10**6)}"
        out.append(" ".join(w))
    return out


def test_a_group_of_hundreds_of_near_copies(spark):
    """One passage in 900 variants, most linked with the first, some only with others, some with none."""
    rng = random.Random(5)
    base = [f"b{i}" for i in range(45)]
    texts = []
    for i in range(900):
        w = list(base)
        for _ in range(rng.choice([1, 1, 1, 2, 3, 5])):
            w[rng.randrange(45)] = f"x{rng.randint(0, 400)}"
        texts.append(" ".join(w))
    rows = list(enumerate(texts))
    want = brute.near_components(rows, 3, 85, 100)
    got = components_of(spark, rows)
    assert got == want
    roots = {c for _, c in want.values()}
    assert 1 < len(roots) < 900


@pytest.mark.parametrize("seed", [1, 2, 3])
def test_members_apart_from_most_of_their_group(spark, monkeypatch, seed):
    monkeypatch.setattr(near_dedup, "BUCKET_BLOCK", 5)
    monkeypatch.setattr(near_dedup, "SHINGLE_BLOCK", 300)
    rng = random.Random(seed)
    texts = drifting(rng, 40, 60) + drifting(rng, 25, 40)
    rng.shuffle(texts)
    rows = list(enumerate(texts))
    assert components_of(spark, rows) == brute.near_components(rows, 3, 85, 100)


def test_blocks_are_bounded_whatever_the_group(spark, monkeypatch):
    seen = []
    monkeypatch.setattr(near_dedup, "BUCKET_BLOCK", 50)
    dealt = near_dedup._dealt

    def watched(rows):
        out = dealt(rows)
        seen.append(out.groupBy("key", "bi", "bj").count().agg({"count": "max"}).head()[0] or 0)
        return out

    monkeypatch.setattr(near_dedup, "_dealt", watched)
    base = [f"b{i}" for i in range(60)]
    rows = [(i, " ".join([*base[: i % 60], f"x{i}", *base[i % 60 + 1 :]])) for i in range(1500)]
    got = components_of(spark, rows)
    assert {c for _, c in got.values()} == {0}
    assert seen and max(seen) < 50 * 3
