"""Document quality by hierarchical empirical Bayes.

Evidence of a document: a logistic classifier on text statistics (shouting, sign and pipe density,
repeated words, word length and so on), fitted on about ``MAX_LABELLED`` labelled rows.
Prior of a document: the quality of its site. Soft counts of good documents are summed per host and
per host and path; a host's rate is shrunk towards the global rate, a path's rate towards its host's,
each with a strength that the method of moments takes from the spread between the groups, so sparse
sites stay near their parents and large ones speak for themselves. A document's own evidence is
left out of the prior it is judged by. Posterior odds = likelihood ratio of the text times the
site's prior odds.

All group work is aggregates that combine before the shuffle and equi-joins of one row a document
with one row a site; the texts are read in one narrow pass and never shuffled.

Defined cases: null and empty texts are documents without words and judged by that; a null host or
path is a site of its own; without labels of both kinds the fixed starting weights are used; label
rows that repeat an id count once (the lowest label); an empty table gives an empty result; very long texts
are read whole, and the share of distinct words compares logarithms, so it has one form at every length;
rows that repeat are documents of their own; only the named columns are read, so others cannot clash.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from relmix.llm.columns import narrow, small_batches
from relmix.llm.textarrays import chunks, text_bytes, words
from relmix.llm.workers import tidy
from relmix.session import stored

MAX_LABELLED = 20_000
NAMES = ["bias", "upper", "digits", "pipes", "bangs", "signs", "repeats", "distinct", "other", "length", "few"]
#: Starting weights and centre of the prior: a plain text is good, heaps of signs, pipes, capitals and repeats are not.
START = np.array([2.0, -2.0, -0.5, -2.0, -1.0, -2.0, -2.0, -1.0, 0.0, 0.0, -0.5])

_CLASS = np.zeros(256, np.uint8)
_CLASS[65:91] = 1
_CLASS[48:58] = 2
_CLASS[ord("|")] = 3
_CLASS[ord("!")] = 4
_CLASS[[ord(c) for c in "%#*&$@^~<>{}[]\\_=+"]] = 5
_CLASS[128:] = 6


def text_features(column: pa.Array) -> np.ndarray:
    """One row of statistics for each text, from its bytes and word hashes."""
    data, offsets = text_bytes(column)
    out = np.zeros((len(offsets) - 1, len(NAMES)))
    out[:, 0] = 1
    with np.errstate(over="ignore", divide="ignore", invalid="ignore"):
        for a, b in chunks(offsets):
            part = offsets[a : b + 1]
            own, size = data[part[0] : part[-1]], np.diff(part)
            kinds = _CLASS[own]
            row = np.repeat(np.arange(b - a), size)
            n = np.bincount(row * 7 + kinds, minlength=7 * (b - a)).reshape(-1, 7)
            starts, ends, hashed, edges = words(own, part - part[0])
            count = np.diff(edges)
            owner = np.repeat(np.arange(b - a), count)
            again = np.zeros(len(hashed), bool)
            again[1:] = (hashed[1:] == hashed[:-1]) & (owner[1:] == owner[:-1])
            repeats = np.bincount(owner[again], minlength=b - a)
            order = np.lexsort((hashed, owner))
            fresh = np.ones(len(hashed), bool)
            fresh[1:] = (hashed[order][1:] != hashed[order][:-1]) | (owner[order][1:] != owner[order][:-1])
            distinct = np.bincount(owner[order][fresh], minlength=b - a)
            letters = np.bincount(owner, (ends - starts).astype(float), minlength=b - a)
            w, bytes_ = np.maximum(count, 1), np.maximum(size, 1)
            f = out[a:b]
            f[:, 1] = np.minimum(n[:, 1] / bytes_ * 4, 3)
            f[:, 2] = np.minimum(n[:, 2] / bytes_ * 4, 3)
            f[:, 3] = np.minimum(n[:, 3] / w * 6, 3)
            f[:, 4] = np.minimum(n[:, 4] / w * 2, 3)
            f[:, 5] = np.minimum(n[:, 5] / w, 3)
            f[:, 6] = np.minimum(repeats / w * 8, 3)
            f[:, 7] = 1 - np.log1p(distinct) / np.log1p(w)
            f[:, 8] = n[:, 6] / bytes_
            f[:, 9] = np.clip((letters / w - 5) / 5, -1, 3)
            f[:, 10] = 1 / np.sqrt(w)
    return out


def _features(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        x = text_features(batch.column(1))
        lists = pa.ListArray.from_arrays(pa.array(np.arange(0, x.size + 1, x.shape[1], dtype=np.int32)), pa.array(x.reshape(-1)))
        yield pa.RecordBatch.from_arrays([batch.column(0), lists], names=["label", "x"])


def fit(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", label_col: str = "quality", most: int = MAX_LABELLED) -> np.ndarray:
    """Weights by penalised Newton steps on a bounded sample of labelled rows (bound: ``most``)."""
    marks = labels.select(F.col(f"`{id_col}`").alias("k"), F.col(f"`{label_col}`").cast("int").alias("label")).filter("k IS NOT NULL AND label IS NOT NULL")
    marks = marks.groupBy("k").agg(F.min("label").alias("label"))
    total = marks.count()
    if not total:
        return START.copy()
    share = int(min(1.0, most / total) * 1_000_000) + 1
    picked = F.broadcast(marks.filter(F.pmod(F.xxhash64("k", F.lit(5)), F.lit(1_000_000)) < share))  # about ``most`` rows of 16 bytes
    texts = docs.select(F.col(f"`{id_col}`").alias("k"), F.col(f"`{text_col}`").alias("text")).join(picked, "k").select("label", "text")
    rows = small_batches(texts).mapInArrow(tidy(_features), "label int, x array<double>").collect()
    y = np.array([r["label"] == 1 for r in rows], float)
    if not len(y) or y.min() == y.max():
        return START.copy()
    x = np.array([r["x"] for r in rows])
    w = START.copy()
    for _ in range(60):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        step = np.linalg.solve((x * (p * (1 - p))[:, None]).T @ x + 0.1 * np.eye(len(w)), x.T @ (y - p) - 0.1 * (w - START))
        w = w + step * min(1.0, 2.0 / max(np.abs(step).max(), 1e-9))
        if np.abs(step).max() < 1e-8:
            break
    return w


def _evidence(weights: np.ndarray):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            z = np.clip(text_features(batch.column(3)) @ weights, -12, 12)
            yield pa.RecordBatch.from_arrays([*batch.columns[:3], pa.array(1 / (1 + np.exp(-z)))], names=["id", "host", "path", "p"])

    return run


def _logit(p: Column) -> Column:
    return F.log(p / (1 - p))


def _strength(groups: DataFrame, n: str, gap: str, rate: float) -> float:
    """Prior strength (pseudo-documents) from the spread of group rates around their parents, by moments."""
    row = groups.agg(F.sum(n).alias("n"), F.sum(F.col(n) * F.col(n)).alias("nn"), F.sum(F.col(n) * F.pow(F.col(gap), 2)).alias("q"), F.count(F.lit(1)).alias("g")).head()
    v = rate * (1 - rate)
    if not row["n"] or v <= 0 or row["g"] < 2:
        return 1e6
    spread = row["n"] - row["nn"] / row["n"]
    between = max((row["q"] - (row["g"] - 1) * v) / spread, 0.0) if spread > 0 else 0.0
    return float(min(max(v / between - 1, 1.0), 1e6)) if between > 0 else 1e6


def site_posteriors(evidence: DataFrame) -> tuple[DataFrame, float]:
    """(host, path, n, s, host_rate, strength) for every path, and the global rate, from (host, path, p) rows."""
    paths = stored(evidence.groupBy("host", "path").agg(F.count(F.lit(1)).alias("n"), F.sum("p").alias("s")), "quality-paths")
    whole = paths.agg(F.sum("n").alias("n"), F.sum("s").alias("s")).head()
    rate = min(max(whole["s"] / whole["n"], 1e-6), 1 - 1e-6) if whole["n"] else 0.5
    hosts = paths.groupBy("host").agg(F.sum("n").alias("hn"), F.sum("s").alias("hs"))
    by_host = _strength(hosts.withColumn("gap", F.col("hs") / F.col("hn") - rate), "hn", "gap", rate)
    hosts = hosts.withColumn("host_rate", (F.col("hs") + by_host * rate) / (F.col("hn") + by_host)).withColumnRenamed("host", "h")
    joined = stored(paths.join(hosts, F.col("host").eqNullSafe(F.col("h"))).drop("h"), "quality-sites")
    by_path = _strength(joined.withColumn("gap", F.col("s") / F.col("n") - F.col("host_rate")), "n", "gap", rate)
    return joined.select("host", "path", "n", "s", "host_rate").withColumn("strength", F.lit(by_path)), rate


def judge(docs: DataFrame, weights: np.ndarray, id_col: str = "doc_id", text_col: str = "text", host_col: str = "source", path_col: str = "lang") -> DataFrame:
    """(id, host, path, text_quality, site_quality, quality, kept) for every row."""
    rows = narrow(docs, id=id_col, host=host_col, path=path_col, text=text_col)
    kinds = {f.name: f.dataType.simpleString() for f in rows.schema.fields}
    evidence = stored(small_batches(rows).mapInArrow(tidy(_evidence(weights)), f"id {kinds['id']}, host {kinds['host']}, path {kinds['path']}, p double"), "quality-evidence")
    sites, rate = site_posteriors(evidence)
    sites = sites.withColumnsRenamed({"host": "sh", "path": "sp"})
    joined = evidence.join(sites, F.col("host").eqNullSafe(F.col("sh")) & F.col("path").eqNullSafe(F.col("sp")))
    # the document's own share is taken out of its site's sums
    prior = (F.col("s") - F.col("p") + F.col("strength") * F.col("host_rate")) / (F.col("n") - 1 + F.col("strength"))
    prior = F.least(F.greatest(prior, F.lit(1e-6)), F.lit(1 - 1e-6))
    odds = _logit(F.col("p")) - _logit(F.lit(rate)) + _logit(prior)
    quality = 1 / (1 + F.exp(-odds))
    return joined.select("id", "host", "path", F.col("p").alias("text_quality"), prior.alias("site_quality"), quality.alias("quality"), (quality >= 0.5).alias("kept"))


def op1_quality(spark, sf_dir: str) -> DataFrame:
    from relmix.llm.toxicity import held_out

    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text", "source", "lang")
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet").filter(~held_out())
    done = judge(docs, fit(docs, labels))
    return done.select(F.col("id").alias("doc_id"), "text_quality", "site_quality", "quality", "kept")
