import itertools
import math

import pytest

from relmix.llm import toxicity as tox

SIGMA = [tox.OTHER, tox.ABUSE, tox.SLUR, tox.PART, tox.LINK, tox.DIRT, tox.VIOLENCE, tox.DEATH, tox.INTENT, tox.WISH, tox.TARGET, tox.NEGATION, tox.SAYS, tox.QUOTE, tox.PAUSE]


def states_of(part, alphabet):
    seen, todo, outs = {part.start}, [part.start], set()
    while todo:
        state = todo.pop()
        for symbol in alphabet:
            after, out, _ = part.arc(state, symbol)
            outs.add(out)
            if after not in seen:
                seen.add(after)
                todo.append(after)
    return seen, outs


def all_paths(part, word, alphabet_states):
    """Every state sequence of the machine that reads the word from its start, by trying them all."""
    found = []
    for path in itertools.product(alphabet_states, repeat=len(word)):
        at, outs, weight = part.start, [], 0.0
        for symbol, after in zip(word, path, strict=True):
            to, out, label = part.arc(at, symbol)
            if to != after:
                break
            at, weight = after, weight + (tox.LABELS[label][0] if label else 0.0)
            outs.append(out)
        else:
            found.append((outs, weight))
    return found


def test_composition_equals_path_enumeration():
    alphabets, machines, now = [], [], set(SIGMA) | {tox.END}
    for part in tox.CHAIN:
        states, outs = states_of(part, now)
        machines.append((part, states))
        alphabets.append(now)
        now = outs
    machine = tox.Composed()
    words = list(itertools.product(SIGMA, repeat=2)) + [tuple(SIGMA[(7 * i + j * (i % 11 + 1)) % len(SIGMA)] for j in range(3)) for i in range(60)]
    for word in words:
        read, weight = [*word, tox.END], 0.0
        for part, states in machines:
            # states far from the word cannot be on its path: those reachable by it are enough
            near = [s for s in states if s in states_of(part, set(read))[0]]
            paths = all_paths(part, read, near)
            assert len(paths) == 1  # deterministic
            read, own = paths[0]
            weight += own
        outs, labels, total = machine.run([*word, tox.END])
        assert outs == read and math.isclose(total, weight, abs_tol=1e-9)
        assert math.isclose(total, sum(tox.LABELS[x][0] for arc in labels for x in arc), abs_tol=1e-9)


@pytest.mark.parametrize(
    ("text", "kinds", "toxic"),
    [
        ("You aren’t an idiot", ["insult_negated"], False),
        ("I hope you die", ["threat_aimed"], True),
        ("he should be shot", ["threat_aimed"], True),
        ("The murder trial of him began", ["threat_other"], False),
        ("I will not kill you", ["threat_other"], False),
        ("you piece of shit", ["insult_aimed"], True),
        ("a piece of garbage lay there", ["insult_plain"], True),
        ("space and time", [], False),
        ("Ich hoffe, die Leute kommen", [], False),
        ("l'idiot", ["insult_plain"], True),
        ("no, you idiot", ["insult_aimed"], True),
        ('"Yes" you idiot', ["insult_aimed"], True),
        ('"You idiot" was said', ["insult_reported"], False),
        ("kill yourself", ["threat_other", "threat_other"], True),  # the target ends the order, nobody else is named
    ],
)
def test_clause_patterns(text, kinds, toxic):
    matcher = tox.Matcher(tox.Model())
    assert [k for _, _, k in matcher.clauses(text)] == kinds
    assert (matcher.score(matcher.matches(text)) >= 0.5) == toxic


def test_counts_have_no_cap_and_repetition_never_lowers_a_score():
    matcher = tox.Matcher(tox.Model())
    scores = [matcher.score(matcher.matches("you idiot. " * n)) for n in range(9)]
    assert scores == sorted(scores) and len(set(scores)) == 9
    assert matcher.features(matcher.matches("you idiot. " * 1000))[0] == math.log2(1001)
    plain, both = (matcher.score(matcher.matches(t)) for t in ("a loser", "don't be stupid! a loser"))
    assert both >= plain


def test_a_very_long_clause_and_odd_tables(spark):
    long = "word " * 200_000 + "you idiot " + "word " * 200_000
    rows = [(1, long, 1.0), (1, long, 1.0), (None, "you idiot", 2.0), (2, None, 3.0), (3, "", 4.0)]
    docs = spark.createDataFrame(rows, "doc_id bigint, text string, toxicity double")
    out = tox.score(docs, tox.Model())
    assert out.columns == ["doc_id", "text", "toxicity", "toxic_clauses"]
    got = [(r.doc_id, r.toxicity >= 0.5, len(r.toxic_clauses)) for r in out.collect()]
    assert got == [(1, True, 1), (1, True, 1), (None, True, 1), (2, False, 0), (3, False, 0)]
    empty = docs.limit(0).select("doc_id", "text")
    labels = spark.createDataFrame([(1, 1)], "doc_id bigint, toxic int")
    assert tox.score(empty, tox.learn(empty, labels)).collect() == []


def test_a_score_on_the_border_is_toxic():
    model = tox.Model()
    model.weights = [0.0] * len(model.weights)
    matcher = tox.Matcher(model)
    assert matcher.score(matcher.matches("you idiot")) == 0.5 and matcher.score([]) == 0.5


def test_weak_entries_need_company(spark):
    import random

    rng = random.Random(3)
    word = lambda: "".join(rng.choice(["ka", "lo", "mi", "nu", "re", "so"]) for _ in range(3))
    rows, marks = [], []
    for i in range(900):
        toxic = i % 6 == 0
        w = [word() for _ in range(40)]
        for _ in range(rng.randint(4, 7) if toxic else int(rng.random() < 0.15)):
            w.insert(rng.randrange(40), "vexu" + word())
        rows.append((i, " ".join(w)))
        marks.append((i, int(toxic)))
    docs, labels = spark.createDataFrame(rows, "doc_id bigint, text string"), spark.createDataFrame(marks, "doc_id bigint, toxic int")
    model = tox.learn(docs, labels)
    assert "vexu" in model.weak_stems and "vexu" not in model.stems
    got = {r.doc_id: r.toxicity >= 0.5 for r in tox.score(docs, model).collect()}
    assert sum(got[i] == bool(t) for i, t in marks) / len(marks) > 0.99
