"""Toxicity by a weighted finite-state pattern grammar over clauses.

A clause (text between stops, semicolons and line ends) becomes a string of word classes. Five weighted
transducers read it in a chain, each on the output of the one before: insults (words, phrases such as
"piece of ...", repetitions), threats (an intention or wish followed by violence or death, an order to
do violence to a target, a bare mention), negation scope, reported speech and targets. Learned words that
clean documents hold too are weak insults with a weight of their own. The arcs carry weighted labels; the chain is composed lazily into one deterministic machine whose arc weights are the
sums of its parts', so a clause weighs the sum along its path. Words alone weigh nothing: the same
insult weighs differently by what the machine says of its clause.

A document's log-odds are the start weight plus, for every weighted arc of the composed machine, its
weight times log2(1 + how often it was taken). For one occurrence that is the path's weight;
repetitions count on without bound but with falling force.

Only clauses with an insult, violence or death can score, so an Aho-Corasick automaton finds candidate
positions in the whole text and the machine reads just their clauses.

Learned from labelled rows, of which about ``MAX_LABELLED`` are used (a seeded hash of the id picks
them; the bound is for fitting alone): (1) insult words and word beginnings, accepted by a
likelihood-ratio test of document counts that allows for the number of candidates and counts
distinct preceding words instead of documents, so near copies cannot vote many times (tried for documents
that hold an entry and for those that hold it twice, with different words before); (2) the arc
weights, by penalised logistic regression around fixed starting weights. Without labels the seed
lexicon and the starting weights are used.

Defined cases: null and empty texts score as texts without a matching clause; very long texts and
clauses are read whole, once; empty tables give empty results; repeated rows score alike; repeated
label rows count once (toxic if any says so); null labels and ids are not learned from; input columns
named like an output are replaced by it; ties at 0.5 are toxic.
"""

from __future__ import annotations

import math
import re
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from relmix.llm.columns import replaced, small_batches
from relmix.llm.workers import tidy
from relmix.session import stored

MAX_LABELLED = 20_000

#: Seed lexicon.
INSULTS = ["idiot", "moron", "stupid", "loser", "scum", "trash", "clown", "pathetic", "worthless", "disgusting", "imbecile", "dumbass", "bastard", "asshole", "bitch", "whore", "cretin", "scumbag", "vermin", "dimwit", "idiota", "imbécile", "connard", "salope", "crétin", "arschloch", "dummkopf", "trottel", "schlampe", "abschaum", "estúpido", "gilipollas", "cabrón", "pendejo"]
THREATS = ["kill", "murder", "strangle", "stab", "slaughter", "umbringen", "töten", "tuerai", "matar", "mataré", "killed", "shot", "hanged", "shoot", "hang"]
DEATHS = ["die", "dead", "death"]
DEATHS_ELSE = ["sterben", "stirb", "mourir", "crever", "morir", "mueras"]
INTENTS = ["will", "ill", "gonna", "going", "want", "wanna", "werde", "werden", "vais", "allons", "voy", "vamos"]
WISHES = ["hope", "wish", "deserve", "deserves", "should", "must", "ought"]
WISHES_ELSE = ["hoffe", "verdienst", "verdient", "sollst", "espère", "mérites", "espero", "mereces", "ojalá"]
PARTS = ["piece", "waste", "pile", "sack", "load", "stück", "haufen", "tas", "pedazo", "montón"]
LINKS = ["of", "de", "von"]
FILTH = ["shit", "crap", "garbage", "filth", "space", "scheiße", "dreck", "merde", "mierda", "basura"]
TARGETS = ["you", "your", "youre", "yourself", "yourselves", "he", "she", "they", "him", "her", "them", "themselves", "people", "everyone", "du", "dich", "dir", "ihr", "euch", "sie", "tu", "toi", "te", "vous", "ils", "tú", "ti", "usted", "ustedes", "vosotros"]
NEGATIONS = ["not", "never", "no", "nobody", "isnt", "arent", "wasnt", "werent", "dont", "doesnt", "didnt", "wont", "wouldnt", "cannot", "cant", "nicht", "kein", "keine", "nie", "pas", "jamais", "nunca", "ni"]
SPEECH = ["said", "says", "say", "called", "calls", "quoted", "wrote", "claimed", "sagte", "sagt", "nannte", "dit", "disait", "appelé", "dijo", "dice", "llamó"]

#: Word classes that the first transducer reads; later ones read the outputs of those before.
OTHER, ABUSE, SLUR, PART, LINK, DIRT, VIOLENCE, INTENT, TARGET, NEGATION, SAYS, QUOTE, PAUSE, END = "other abuse slur part link dirt violence intent target negation says quote pause end".split()
#: English "die" is a German article, so English deaths need English wishes.
WISH, DEATH, WISH_ELSE, DEATH_ELSE = "wish death wish-else death-else".split()
INSULT, THREAT, MENTION = "insult threat mention".split()
DENIED_INSULT, DENIED_THREAT, TOLD_INSULT, TOLD_THREAT = "denied-insult denied-threat told-insult told-threat".split()

#: Labels of weighted arcs with their starting weights and the variances of the prior around them.
LABELS = {
    "insult": (4.5, 1.0),
    "insult_phrase": (4.5, 1.0),
    "insult_weak": (1.0, 1.0),
    "insult_again": (0.5, 0.5),
    "threat": (4.2, 1.0),
    "violence": (0.5, 0.5),
    "denied_insult": (-4.0, 1.0),
    "denied_threat": (-4.0, 1.0),
    "told_insult": (-3.5, 1.0),
    "told_threat": (-3.5, 1.0),
    "aimed_insult": (0.5, 1.0),
    "aimed_threat": (0.8, 1.0),
}
START = -4.0
START_WEIGHTS = np.array([START, *(w for w, _ in LABELS.values())])
PRIOR_VARIANCE = np.array([1.0, *(v for _, v in LABELS.values())])
KINDS = ["insult_aimed", "insult_plain", "insult_negated", "insult_reported", "threat_aimed", "threat_other"]
#: How much likelier in toxic documents an entry of the strong and of the weak lexicon is.
STRONG_LIFT, WEAK_LIFT = 30, 3
SCOPE = 4  # words a negation reaches
REACH = 6  # words an intention or a wish reaches

_TOKEN = re.compile(r"[^\W_]+|[\"“”«»„]")
_WORD = re.compile(r"[^\W_]+(?:['’ʼ][^\W_]+)*|[\"“”«»„]|[,:()]")
_MARK = re.compile("['’ʼ]")
_CLAUSE_END = re.compile(r"[.!?;\n]")
_WISHED = re.compile("|".join([*WISHES, *WISHES_ELSE]))
_PARTED = re.compile("|".join(PARTS))

State = object
Arc = tuple[State, str, str | None]  # next state, output symbol, label


class Transducer:
    """A deterministic weighted transducer given by its arc function; weights hang on the arcs' labels."""

    start: State = 0

    def arc(self, state: State, symbol: str) -> Arc:
        return state, symbol, None


class Insults(Transducer):
    """States: 0, "part" and "link" inside a phrase, "again" right after an insult."""

    def arc(self, state: State, symbol: str) -> Arc:
        if symbol == ABUSE:
            return "again", INSULT, {"again": "insult_again", "link": "insult_phrase"}.get(state, "insult")
        if symbol == SLUR:
            return 0, INSULT, "insult_weak"
        if symbol == DIRT and state == "link":
            return "again", INSULT, "insult_phrase"
        if symbol == PART:
            return "part", OTHER, None
        if symbol == LINK:
            return "link" if state in ("part", "link") else 0, OTHER, None
        return 0, OTHER if symbol == DIRT else symbol, None


class Threats(Transducer):
    """States: 0, (class, words it still reaches) after an intention or a wish, "bare" right after bare violence."""

    def arc(self, state: State, symbol: str) -> Arc:
        meant = state[0] if isinstance(state, tuple) else None
        if symbol in (INTENT, WISH, WISH_ELSE):
            # an intention does not end a wish's reach
            return (meant if symbol == INTENT and meant else symbol, REACH), OTHER, None
        if symbol == VIOLENCE:
            return (0, THREAT, "threat") if meant else ("bare", MENTION, "violence")
        if symbol in (DEATH, DEATH_ELSE):
            return (0, THREAT, "threat") if meant == (WISH if symbol == DEATH else WISH_ELSE) else (self.passed(state), OTHER, None)
        if symbol == TARGET and state == "bare":
            return 0, THREAT, "threat"
        return self.passed(state), symbol, None

    @staticmethod
    def passed(state: State) -> State:
        return (state[0], state[1] - 1) if isinstance(state, tuple) and state[1] > 1 else 0


class Negations(Transducer):
    """State: words that the last negation still reaches."""

    def arc(self, state: State, symbol: str) -> Arc:
        if symbol == NEGATION:
            return SCOPE, OTHER, None
        if symbol == PAUSE:
            return 0, OTHER, None
        rest = max(state - 1, 0)
        if state and symbol == INSULT:
            return rest, DENIED_INSULT, "denied_insult"
        if state and symbol == THREAT:
            return rest, DENIED_THREAT, "denied_threat"
        return rest, symbol, None


class Reports(Transducer):
    """State: (a speech verb was read, inside quotes)."""

    start = (False, False)

    def arc(self, state: State, symbol: str) -> Arc:
        says, quoted = state
        if symbol == SAYS:
            return (True, quoted), OTHER, None
        if symbol == QUOTE:
            return (says, not quoted), OTHER, None
        if (says or quoted) and symbol == INSULT:
            return state, TOLD_INSULT, "told_insult"
        if (says or quoted) and symbol == THREAT:
            return state, TOLD_THREAT, "told_threat"
        return state, symbol, None


class Targets(Transducer):
    """State: (a target was read, the plain insults and threats read); the clause's end tells whom they meet."""

    start = (False, False, False)

    def arc(self, state: State, symbol: str) -> Arc:
        seen, insult, threat = state
        if symbol == END:
            which = "aimed_threat" if threat else "aimed_insult"
            return self.start, END, which if seen and (insult or threat) else None
        return (seen or symbol == TARGET, insult or symbol == INSULT, threat or symbol == THREAT), symbol, None


CHAIN = (Insults(), Threats(), Negations(), Reports(), Targets())


class Composed:
    """The chain as one deterministic machine, built as it is used: (state, symbol) -> (state, output, labels, weight)."""

    def __init__(self, parts: tuple[Transducer, ...] = CHAIN, weights: dict[str, float] | None = None):
        self.parts = parts
        self.weights = weights or {k: w for k, (w, _) in LABELS.items()}
        self.numbers = {tuple(p.start for p in parts): 0}
        self.states = [tuple(p.start for p in parts)]
        self.arcs: list[dict[str, tuple[int, str, tuple[str, ...], float]]] = [{}]

    def _arc(self, at: int, symbol: str) -> tuple[int, str, tuple[str, ...], float]:
        after, out, labels = [], symbol, []
        for part, state in zip(self.parts, self.states[at], strict=True):
            state, out, label = part.arc(state, out)
            after.append(state)
            if label:
                labels.append(label)
        key = tuple(after)
        if key not in self.numbers:
            self.numbers[key] = len(self.states)
            self.states.append(key)
            self.arcs.append({})
        self.arcs[at][symbol] = found = (self.numbers[key], out, tuple(labels), sum(self.weights[x] for x in labels))
        return found

    def run(self, symbols: list[str]) -> tuple[list[str], list[tuple[str, ...]], float]:
        """(output symbols, labels of every weighted arc, weight) of the path that reads the symbols."""
        at, outs, labels, weight = 0, [], [], 0.0
        arcs = self.arcs
        for symbol in symbols:
            at, out, own, w = arcs[at].get(symbol) or self._arc(at, symbol)
            outs.append(out)
            if own:
                labels.append(own)
                weight += w
        return outs, labels, weight


@dataclass
class Model:
    words: list[str] = field(default_factory=lambda: list(INSULTS))
    stems: list[str] = field(default_factory=list)
    weak_words: list[str] = field(default_factory=list)
    weak_stems: list[str] = field(default_factory=list)
    threats: list[str] = field(default_factory=lambda: list(THREATS))
    weights: list[float] = field(default_factory=lambda: START_WEIGHTS.tolist())


@dataclass
class Clause:
    """A clause that holds patterns: place, pattern kinds in order, labels of its path's weighted arcs, its weight."""

    begin: int
    end: int
    kinds: list[str]
    labels: list[tuple[str, ...]]
    weight: float


class Matcher:
    """The compiled model of one task."""

    def __init__(self, model: Model):
        import ahocorasick

        self.weights = dict(zip(LABELS, model.weights[1:], strict=True))
        self.start = model.weights[0]
        self.machine = Composed(weights=self.weights)
        # exact words before beginnings, strong entries before weak ones
        self.lexicon = [(set(model.words), set(model.stems), ABUSE), (set(model.weak_words), set(model.weak_stems), SLUR)]
        self.lengths = sorted({len(s) for _, stems, _ in self.lexicon for s in stems})
        classes = [(TARGETS, TARGET), (NEGATIONS, NEGATION), (SPEECH, SAYS), (INTENTS, INTENT), (WISHES, WISH), (WISHES_ELSE, WISH_ELSE), (PARTS, PART), (LINKS, LINK), (FILTH, DIRT), (DEATHS, DEATH), (DEATHS_ELSE, DEATH_ELSE), (model.threats, VIOLENCE)]
        self.symbol = {w: c for words, c in classes for w in words} | dict.fromkeys('"“”«»„', QUOTE) | dict.fromkeys(",:()", PAUSE)
        # what a clause must hold to score, and what it must hold besides (a class of its own begins no pattern)
        needs = {w: _WISHED for w in [*DEATHS, *DEATHS_ELSE]} | {w: _PARTED for w in FILTH} | dict.fromkeys([w for words, stems, _ in self.lexicon for w in words | stems] + model.threats)
        self.anchors = ahocorasick.Automaton()
        for w, need in needs.items():
            self.anchors.add_word(w, (len(w), need))
        self.anchors.make_automaton()

    def symbol_of(self, word: str) -> str:
        for words, stems, symbol in self.lexicon:
            if word in words or any(word[:n] in stems for n in self.lengths):
                return symbol
        return self.symbol.get(word, OTHER)

    def symbols(self, clause: str) -> list[str]:
        """Word classes of a lowered clause. A word with an apostrophe is one word where that is known, else its parts."""
        out = []
        for word in _WORD.findall(clause):
            parts = _MARK.split(word)
            if len(parts) > 1 and "".join(parts) in self.symbol:
                parts = ["".join(parts)]
            out += map(self.symbol_of, parts)
        return out

    def matches(self, text: str) -> list[Clause]:
        """Every clause that holds an insult or a threat pattern."""
        low = text.lower()  # offsets are those of the lowered text
        found: list[Clause] = []
        done = -1
        for last, (size, need) in self.anchors.iter(low):
            first = last - size + 1
            if first < done or (first and low[first - 1].isalnum()):
                continue
            # back to the clause before at most, so a long text is read once
            begin = max(max(low.rfind(c, max(done, 0), first) for c in ".!?;\n") + 1, done)
            stop = _CLAUSE_END.search(low, last + 1)
            end = stop.start() if stop else len(low)
            if need and not need.search(low, begin, end):
                continue
            done = end
            outs, labels, weight = self.machine.run([*self.symbols(low[begin:end]), END])
            if labels:
                aimed = labels[-1][0].startswith("aimed")
                names = {INSULT: KINDS[0 if aimed else 1], DENIED_INSULT: KINDS[2], TOLD_INSULT: KINDS[3], THREAT: KINDS[4 if aimed else 5]}
                names |= dict.fromkeys((MENTION, DENIED_THREAT, TOLD_THREAT), KINDS[5])
                found.append(Clause(begin, end, [names[o] for o in outs if o in names], labels, weight))
        return found

    def clauses(self, text: str) -> list[tuple[int, int, str]]:
        """(begin, end, kind) of every pattern, with the clause it stands in."""
        return [(c.begin, c.end, kind) for c in self.matches(text) for kind in c.kinds]

    @staticmethod
    def features(clauses: list[Clause]) -> list[float]:
        """For every label the sum of log2(1 + times taken) over the composed arcs that carry it."""
        out = dict.fromkeys(LABELS, 0.0)
        for arc, n in Counter(arc for c in clauses for arc in c.labels).items():
            for label in arc:
                out[label] += math.log2(1 + n)
        return list(out.values())

    def score(self, clauses: list[Clause]) -> float:
        odds = self.start + sum(w * x for w, x in zip(self.weights.values(), self.features(clauses), strict=True))
        return 1 / (1 + math.exp(-max(odds, -700.0)))


def _terms(text: str) -> set[tuple[str, int]]:
    """(word or word beginning with *, hash of the word before) of a text."""
    out, before = set(), ""
    for w in _TOKEN.findall(text.lower()):
        context = hash_of(before)
        if len(w) >= 3:
            out.add((w, context))
            for n in (4, 5, 6):
                if len(w) > n:
                    out.add((w[:n] + "*", context))
        before = w
    return out


def hash_of(word: str) -> int:
    import zlib

    return zlib.crc32(word.encode())


def _term_rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        rows: set[tuple[str, int]] = set()
        for text in batch.column(0).to_pylist():
            rows |= _terms(text or "")
        terms, contexts = zip(*rows, strict=True) if rows else ((), ())
        yield pa.RecordBatch.from_arrays([pa.array(terms, pa.string()), pa.array(contexts, pa.int64())], names=["term", "context"])


def _document_counts(candidates: list[str]):
    wanted = set(candidates)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            counts: Counter[tuple[str, int, int]] = Counter()
            for toxic, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                for term, n in Counter(t for t, _ in _terms(text or "") if t in wanted).items():
                    counts.update([(term, toxic, 1), (term, toxic, 2)] if n > 1 else [(term, toxic, 1)])
            term, toxic, least = zip(*counts, strict=True) if counts else ((), (), ())
            yield pa.RecordBatch.from_arrays([pa.array(term, pa.string()), pa.array(toxic, pa.int32()), pa.array(least, pa.int32()), pa.array(list(counts.values()), pa.int64())], names=["term", "toxic", "least", "n"])

    return run


def _pattern_features(model: Model):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        matcher = Matcher(model)
        for batch in batches:
            rows = [matcher.features(matcher.matches(t or "")) for t in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(rows, pa.list_(pa.float64()))], names=["toxic", "features"])

    return run


def _divergence(k: float, n: float, p: float) -> float:
    """n times the Kullback-Leibler divergence of k / n from p: the exponent of the binomial tail bound."""
    q = k / n
    return n * ((q * math.log(q / p) if q else 0) + ((1 - q) * math.log((1 - q) / (1 - p)) if q < 1 else 0))


def learn(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", label_col: str = "toxic", most: int = MAX_LABELLED) -> Model:
    """Fit lexicon and weights. ``labels`` must hold only rows that may be learned from."""
    marks = labels.select(F.col(f"`{id_col}`").alias("k"), F.col(f"`{label_col}`").cast("int").alias("toxic")).filter("k IS NOT NULL AND toxic IS NOT NULL")
    marks = marks.groupBy("k").agg(F.max("toxic").alias("toxic"))
    total = marks.count()
    if not total:
        return Model()
    share = min(1.0, most / total)
    # about ``most`` rows of 16 bytes: a bounded broadcast
    picked = F.broadcast(marks.filter(F.pmod(F.xxhash64("k", F.lit(3)), F.lit(1_000_000)) < int(share * 1_000_000) + 1))
    texts = docs.select(F.col(f"`{id_col}`").alias("k"), F.col(f"`{text_col}`").alias("text")).join(picked, "k").select("toxic", "text")
    texts = stored(small_batches(texts), "toxic-sample")
    sizes = {r["toxic"]: r["count"] for r in texts.groupBy("toxic").count().collect()}
    bad, good = sizes.get(1, 0), sum(sizes.values()) - sizes.get(1, 0)
    model = Model()
    if not bad or not good:
        return model
    least = max(4, bad * 0.004)
    contexts = texts.filter("toxic = 1").select("text").mapInArrow(tidy(_term_rows), "term string, context bigint").distinct()
    # bounded by the sample: a term needs ``least`` distinct contexts
    support = {r["term"]: r["n"] for r in contexts.groupBy("term").agg(F.count(F.lit(1)).alias("n")).filter(F.col("n") >= least).collect()}
    seeds = [*INSULTS, *THREATS]
    counted = texts.mapInArrow(tidy(_document_counts([*support, *seeds])), "term string, toxic int, least int, n bigint").groupBy("term", "toxic", "least").agg(F.sum("n").alias("n")).collect()
    by_term: dict[tuple[str, int], list[int]] = {}
    for r in counted:
        by_term.setdefault((r["term"], r["least"]), [0, 0])[int(r["toxic"] == 1)] += r["n"]
    prior = bad / (bad + good)
    bar = math.log(2 * len(support) + 1) + 4
    strong: set[str] = set()
    weak: set[str] = set()
    for term, spread in support.items():
        lift, sure = [], []
        for least in (1, 2):
            n, t = by_term.get((term, least), [0, 0])
            t = min(t, spread // least)
            lift.append((t + 0.5) / (bad + 1) / ((n + 0.5) / (good + 1)))
            sure.append(t and lift[-1] >= WEAK_LIFT and t / (t + n) > prior and _divergence(t, t + n, prior) >= bar)
        if sure[0] and lift[0] >= STRONG_LIFT:
            strong.add(term)
        elif any(sure) and lift[0] >= WEAK_LIFT:
            weak.add(term)

    def refuted(word: str) -> bool:
        n, t = by_term.get((word, 1), [0, 0])
        return t + n >= 3 and (t + 0.5) / (bad + 1) / ((n + 0.5) / (good + 1)) < 3

    model.words = sorted({w for w in INSULTS if not refuted(w)} | {c for c in strong if c[-1] != "*" and c not in THREATS})
    model.stems = sorted(c[:-1] for c in strong if c[-1] == "*")
    model.weak_words = sorted(c for c in weak if c[-1] != "*" and c not in THREATS)
    model.weak_stems = sorted(c[:-1] for c in weak if c[-1] == "*")
    model.threats = [w for w in THREATS if not refuted(w)]
    grid = texts.select("toxic", "text").mapInArrow(tidy(_pattern_features(model)), "toxic int, features array<double>").groupBy("toxic", "features").count().collect()
    x = np.array([[1, *r["features"]] for r in grid], float)
    y = np.array([r["toxic"] == 1 for r in grid], float)
    n = np.array([r["count"] for r in grid], float)
    model.weights = fit_weights(x, y, n).tolist()
    return model


def fit_weights(x: np.ndarray, y: np.ndarray, n: np.ndarray, rounds: int = 50) -> np.ndarray:
    """Newton steps for logistic regression with a normal prior around the starting weights."""
    w = START_WEIGHTS.copy()
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-x @ w))
        gradient = x.T @ (n * (y - p)) - (w - START_WEIGHTS) / PRIOR_VARIANCE
        curvature = (x * (n * p * (1 - p))[:, None]).T @ x + np.diag(1 / PRIOR_VARIANCE)
        step = np.linalg.solve(curvature, gradient)
        w = w + step * min(1.0, 2.0 / max(np.abs(step).max(), 1e-9))
        if np.abs(step).max() < 1e-8:
            break
    return w


_SPANS = pa.list_(pa.struct([("begin", pa.int32()), ("end", pa.int32()), ("kind", pa.string()), ("weight", pa.float64())]))


def score(docs: DataFrame, model: Model, text_col: str = "text") -> DataFrame:
    """The frame with ``toxicity`` (0..1) and ``toxic_clauses`` (begin, end, kind, weight of the clause's path); columns of these names are replaced."""
    kept = replaced(docs, ["toxicity", "toxic_clauses"])
    where = [c.lower() for c in kept.columns].index(text_col.lower())

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        matcher = Matcher(model)
        for batch in batches:
            for a in range(0, batch.num_rows, 512):
                rows = batch.slice(a, 512)
                found = [matcher.matches(t or "") for t in rows.column(where).to_pylist()]
                scores = [matcher.score(clauses) for clauses in found]
                named = [[{"begin": c.begin, "end": c.end, "kind": k, "weight": c.weight} for c in clauses for k in c.kinds] for clauses in found]
                yield pa.RecordBatch.from_arrays([*rows.columns, pa.array(scores, pa.float64()), pa.array(named, _SPANS)], names=[*rows.schema.names, "toxicity", "toxic_clauses"])

    schema = T.StructType([T.StructField(f.name, f.dataType, True) for f in kept.schema.fields])
    schema = schema.add("toxicity", "double").add("toxic_clauses", T.ArrayType(T.StructType().add("begin", "integer").add("end", "integer").add("kind", "string").add("weight", "double")))
    return small_batches(kept).mapInArrow(tidy(run), schema)


def held_out(id_col: str = "doc_id"):
    return F.crc32(F.coalesce(F.col(f"`{id_col}`").cast("string"), F.lit("")).cast("binary")) % 5 == 0


def op7_toxicity(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet").filter(~held_out())
    model = learn(docs, labels)
    scored = score(docs, model)
    return scored.select("doc_id", held_out().alias("held_out"), F.col("toxicity").alias("score"), (F.col("toxicity") >= 0.5).cast("int").alias("predicted"), F.size("toxic_clauses").alias("n_clauses"))
