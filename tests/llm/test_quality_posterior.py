"""The posterior of op 1 against a plain recount with dictionaries."""

import math
import random
from collections import defaultdict

import pyarrow as pa
import pytest

from relmix.llm import quality


def strength(groups, rate):
    """groups: (n, gap). Moments of the spread of group rates around their parents."""
    v, total, squares = rate * (1 - rate), sum(n for n, _ in groups), sum(n * n for n, _ in groups)
    spread = total - squares / total
    if len(groups) < 2 or spread <= 0:
        return 1e6
    between = (sum(n * gap * gap for n, gap in groups) - (len(groups) - 1) * v) / spread
    return min(max(v / between - 1, 1.0), 1e6) if between > 0 else 1e6


def test_posterior_equals_a_plain_recount(spark):
    rng = random.Random(2)
    rows = []
    for i in range(500):
        host = None if i % 50 == 0 else "big" if i % 3 == 0 else f"h{i % 9}"
        loud = rng.random() < (0.8 if host in ("h1", "h4") else 0.2)
        text = " ".join(rng.choice(["BUY!!", "NOW!!", "%$#"] if loud else ["plain", "words", "here", "and", "there"]) for _ in range(rng.randint(0, 30)))
        rows.append((i % 480, None if i % 70 == 0 else text, host, rng.choice(["a", "b", None]), "clash", 1))
    df = spark.createDataFrame(rows, "doc_id bigint, text string, source string, lang string, host string, p int")
    got = quality.judge(df, quality.START).collect()
    assert len(got) == len(rows)
    hosts, paths = defaultdict(list), defaultdict(list)
    for r in got:
        hosts[r.host].append(r.text_quality)
        paths[r.host, r.path].append(r.text_quality)
    rate = sum(map(sum, hosts.values())) / len(rows)
    by_host = strength([(len(x), sum(x) / len(x) - rate) for x in hosts.values()], rate)
    host_rate = {h: (sum(x) + by_host * rate) / (len(x) + by_host) for h, x in hosts.items()}
    by_path = strength([(len(x), sum(x) / len(x) - host_rate[h]) for (h, _), x in paths.items()], rate)
    logit = lambda p: math.log(p / (1 - p))
    for r in got:
        x = paths[r.host, r.path]
        prior = (sum(x) - r.text_quality + by_path * host_rate[r.host]) / (len(x) - 1 + by_path)
        want = 1 / (1 + math.exp(-(logit(r.text_quality) - logit(rate) + logit(prior))))
        assert r.site_quality == pytest.approx(prior, abs=1e-9) and r.quality == pytest.approx(want, abs=1e-9)
        assert r.kept == (r.quality >= 0.5)


def test_distinct_share_has_one_form_at_every_length():
    at = quality.NAMES.index("distinct")
    for n in (3, 60, 399, 400, 401, 5000):
        texts = [" ".join(f"w{i}" for i in range(n)), " ".join(f"w{i % 2}" for i in range(n))]
        x = quality.text_features(pa.array(texts))[:, at]
        assert x[0] == pytest.approx(0) and x[1] == pytest.approx(1 - math.log(3) / math.log(n + 1))
