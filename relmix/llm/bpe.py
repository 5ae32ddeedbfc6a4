"""Byte-level BPE encoding and decoding with vectorised pre-tokenisation.

Pre-tokenisation uses no regular expression. Code points map to twelve classes through an array; a
finite automaton over the classes knows the run it is in and how much of a contraction it has seen.
Each class is a transition function on the states, functions compose, composition is associative,
and the functions that can arise form a small table: so the states of a whole batch come from a
blocked prefix scan over function numbers. Token starts follow from states and neighbours:

* a run of letters, of numbers or of other signs takes one blank before it along;
* white space before a word keeps its last character apart (a blank joins the word);
* an apostrophe that starts a match and is followed by s, t, m, d, re, ve or ll is a contraction.

The slices go through a bounded cache of merged pieces; a miss is merged by lowest pair rank, with
a heap for long pieces. Slices keep their byte offsets, which decoding uses to answer byte ranges.

Defined cases: null and empty texts give no ids; very long texts are one unit of work each, in
memory proportional to the text; repeated rows give repeated results.
"""

from __future__ import annotations

import base64
import heapq
import unicodedata
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from relmix.llm.columns import replaced, small_batches
from relmix.llm.workers import tidy

# classes
BREAK, BLANK, SPACE, LETTER, NUMBER, OTHER, APOSTROPHE, ONE, R, V, L, E = range(12)
# states: what was consumed last
AT_START, IN_BLANK, IN_SPACE, IN_LETTERS, IN_NUMBERS, IN_OTHERS, QUOTE, QUOTE_R, QUOTE_V, QUOTE_L, CONTRACTED = range(11)
WHITE = [*range(9, 14), 0x20, 0x85, 0xA0, 0x1680, *range(0x2000, 0x200B), 0x2028, 0x2029, 0x202F, 0x205F, 0x3000]
CHUNK = 1 << 20
CACHE_PIECES = 300_000


@lru_cache(maxsize=1)
def class_table() -> np.ndarray:
    table = np.full(0x110000, OTHER, np.uint8)
    for cp in range(0x110000):
        kind = unicodedata.category(chr(cp))[0]
        if kind == "L":
            table[cp] = LETTER
        elif kind == "N":
            table[cp] = NUMBER
    table[WHITE] = SPACE
    table[0x20] = BLANK
    table[ord("'")] = APOSTROPHE
    for letters, cls in (("stmd", ONE), ("r", R), ("v", V), ("l", L), ("e", E)):
        table[[ord(x) for x in letters]] = cls
    return table


def _next_state(state: int, cls: int) -> int:
    if cls in (BREAK, BLANK, SPACE, NUMBER, OTHER):
        return {BREAK: AT_START, BLANK: IN_BLANK, SPACE: IN_SPACE, NUMBER: IN_NUMBERS, OTHER: IN_OTHERS}[cls]
    if cls == APOSTROPHE:
        return IN_OTHERS if state in (IN_BLANK, IN_OTHERS, QUOTE) else QUOTE
    if state == QUOTE:
        return {ONE: CONTRACTED, R: QUOTE_R, V: QUOTE_V, L: QUOTE_L}.get(cls, IN_LETTERS)
    if (state, cls) in ((QUOTE_R, E), (QUOTE_V, E), (QUOTE_L, L)):
        return CONTRACTED
    return IN_LETTERS


@lru_cache(maxsize=1)
def automaton() -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(next state by state and class, function number by class, composition by numbers, state reached from the start by number)."""
    step = np.array([[_next_state(s, c) for c in range(12)] for s in range(11)], np.uint8)
    functions = [tuple(range(11))]  # the identity first
    known = {functions[0]: 0}
    base = [tuple(step[:, c].tolist()) for c in range(12)]
    at = 0
    while at < len(functions):
        for g in base:
            h = tuple(g[s] for s in functions[at])
            if h not in known:
                known[h] = len(functions)
                functions.append(h)
        at += 1
    assert len(functions) < 256
    compose = np.array([[known[tuple(g[s] for s in f)] for g in functions] for f in functions], np.uint8)
    return step, np.array([known[g] for g in base], np.uint8), compose, np.array([f[AT_START] for f in functions], np.uint8)


def scan_states(classes: np.ndarray, block: int = 256) -> np.ndarray:
    """State after every character, by an associative scan of transition functions over blocks."""
    step, number, compose, reached = automaton()
    n = len(classes)
    rows = -(-n // block)
    padded = np.zeros(rows * block, np.uint8)
    padded[:n] = classes
    by_place = np.ascontiguousarray(padded.reshape(rows, block).T)
    functions = number[by_place]
    total = functions[0]
    for j in range(1, block):
        total = compose[total, functions[j]]
    before = np.zeros(rows, np.uint8)  # exclusive prefix over blocks, by doubling
    if rows > 1:
        before[1:] = total[:-1]
        gap = 1
        while gap < rows:
            before[gap:] = compose[before[:-gap], before[gap:]]
            gap *= 2
    state = reached[before]
    out = np.empty((block, rows), np.uint8)
    for j in range(block):
        state = step[state, by_place[j]]
        out[j] = state
    return out.T.reshape(-1)[:n]


def token_starts(points: np.ndarray, breaks: np.ndarray) -> np.ndarray:
    """Mark of every character that starts a slice; ``breaks`` are separators between texts, slices of their own."""
    cls = class_table()[points]
    cls[breaks] = BREAK
    state = scan_states(cls)
    group = np.array([0, 1, 1, 2, 3, 4, 4, 2, 2, 2, 2, 2], np.uint8)[cls]
    start = np.empty(len(cls), bool)
    start[0] = True
    start[1:] = group[1:] != group[:-1]
    word_after_space = np.flatnonzero((group[1:] > 1) & (group[:-1] == 1)) + 1
    start[word_after_space - 1] = True
    start[word_after_space] = cls[word_after_space - 1] != BLANK
    done = np.flatnonzero(state == CONTRACTED)
    if len(done):
        quote = done - np.where(cls[done - 1] == APOSTROPHE, 1, 2)
        start[quote + 1] = False
        follow = done + 1
        start[follow[follow < len(cls)]] = True
    start[breaks] = True
    after = breaks + 1
    start[after[after < len(cls)]] = True
    return start


@lru_cache(maxsize=4)
def load_ranks(path: str) -> dict[bytes, int]:
    with open(path, "rb") as lines:
        return {base64.b64decode(a): int(b) for a, b in map(bytes.split, lines)}


def merge_piece(piece: bytes, ranks: dict[bytes, int]) -> list[int]:
    """Ids of one piece: the whole if it has a rank, else adjacent parts joined by lowest rank, leftmost first."""
    whole = ranks.get(piece)
    if whole is not None:
        return [whole]
    if len(piece) > 48:
        return _merge_long(piece, ranks)
    parts = [piece[i : i + 1] for i in range(len(piece))]
    get = ranks.get
    none = 1 << 60
    pair = [get(parts[i] + parts[i + 1], none) for i in range(len(parts) - 1)]
    while pair:
        low = min(pair)
        if low == none:
            break
        i = pair.index(low)
        parts[i : i + 2] = [parts[i] + parts[i + 1]]
        del pair[i]
        if i < len(pair):
            pair[i] = get(parts[i] + parts[i + 1], none)
        if i:
            pair[i - 1] = get(parts[i - 1] + parts[i], none)
    return [ranks[x] for x in parts]


def _merge_long(piece: bytes, ranks: dict[bytes, int]) -> list[int]:
    n = len(piece)
    end = list(range(1, n + 1))  # part i covers piece[i:end[i]]
    back = list(range(-1, n - 1))
    alive = bytearray(b"\1") * n
    heap = []

    def offer(i: int) -> None:
        j = end[i]
        if j < n:
            r = ranks.get(piece[i : end[j]])
            if r is not None:
                heap.append((r, i, j, end[j])) if not ready else heapq.heappush(heap, (r, i, j, end[j]))

    ready = False
    for i in range(n):
        offer(i)
    heapq.heapify(heap)
    ready = True
    while heap:
        _, i, j, stop = heapq.heappop(heap)
        if not alive[i] or end[i] != j or j >= n or not alive[j] or end[j] != stop:
            continue
        end[i] = stop
        alive[j] = 0
        if stop < n:
            back[stop] = i
        offer(i)
        if back[i] >= 0:
            offer(back[i])
    out, i = [], 0
    while i < n:
        out.append(ranks[piece[i : end[i]]])
        i = end[i]
    return out


class PieceCache(dict):
    """piece -> its ids as packed little-endian 32-bit integers; emptied when it holds ``most`` pieces."""

    def __init__(self, ranks: dict[bytes, int], most: int = CACHE_PIECES):
        super().__init__()
        self.ranks, self.most = ranks, most

    def __missing__(self, piece: bytes) -> bytes:
        if len(self) >= self.most:
            self.clear()
        ids = np.array(merge_piece(piece, self.ranks), "<u4").tobytes()
        if len(piece) <= 256:
            self[piece] = ids
        return ids


_CACHES: dict[str, PieceCache] = {}


def worker_cache(path: str) -> PieceCache:
    """One cache for a Python worker, kept across its tasks."""
    if path not in _CACHES:
        _CACHES[path] = PieceCache(load_ranks(path))
    return _CACHES[path]


def encode_texts(texts: list[str], cache: PieceCache) -> list[tuple[bytes, np.ndarray]]:
    """(packed ids, byte offsets of the slices) of every text."""
    if not texts:
        return []
    joined = "\n".join(texts)
    points = np.frombuffer(joined.encode("utf-32-le"), np.uint32)
    length = np.array([len(t) for t in texts])
    breaks = np.cumsum(length + 1)[:-1] - 1
    raw = joined.encode()
    if not len(points):
        return [(b"", np.empty(0, np.int64))] * len(texts)
    at = np.flatnonzero(token_starts(points, breaks))
    if len(raw) != len(points):
        width = 1 + (points >= 0x80).astype(np.int64) + (points >= 0x800) + (points >= 0x10000)
        byte_at = np.cumsum(width) - width
        at, breaks = byte_at[at], byte_at[breaks]
    edges = np.append(at, len(raw))
    first = np.concatenate([[0], np.searchsorted(at, breaks) + 1])
    last = np.append(np.searchsorted(at, breaks), len(at))
    begins = np.concatenate([[0], breaks + 1])
    places = edges.tolist()
    out = []
    for a, b, origin in zip(first.tolist(), last.tolist(), begins.tolist(), strict=True):
        slices = [raw[s:e] for s, e in zip(places[a:b], places[a + 1 : b + 1], strict=True)]
        out.append((b"".join(map(cache.__getitem__, slices)), at[a:b] - origin))
    return out


def _text_chunks(column: pa.Array) -> Iterator[list[str]]:
    part, size = [], 0
    for x in column.to_pylist():
        part.append(x or "")
        size += len(part[-1])
        if size >= CHUNK:
            yield part
            part, size = [], 0
    if part:
        yield part


def encode(docs: DataFrame, ranks_path: str, text_col: str = "text") -> DataFrame:
    """The frame with ``ids`` (binary, little-endian unsigned 32-bit), ``n_tokens`` and ``slice_offsets``
    (binary, unsigned 32-bit byte offsets of the pre-token slices). Input columns of these names are replaced."""
    kept = replaced(docs, ["ids", "n_tokens", "slice_offsets"])
    where = [c.lower() for c in kept.columns].index(text_col.lower())

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cache = worker_cache(ranks_path)
        for batch in batches:
            done = 0
            for part in _text_chunks(batch.column(where)):
                coded = encode_texts(part, cache)
                extra = [
                    pa.array([x[0] for x in coded], pa.binary()),
                    pa.array([len(x[0]) // 4 for x in coded], pa.int64()),
                    pa.array([x[1].astype("<u4").tobytes() for x in coded], pa.binary()),
                ]
                rows = batch.slice(done, len(part))
                done += len(part)
                yield pa.RecordBatch.from_arrays([*rows.columns, *extra], names=[*rows.schema.names, "ids", "n_tokens", "slice_offsets"])

    schema = T.StructType([T.StructField(f.name, f.dataType, True) for f in kept.schema.fields])
    schema = schema.add("ids", "binary").add("n_tokens", "long").add("slice_offsets", "binary")
    return small_batches(kept).mapInArrow(tidy(run), schema)


@lru_cache(maxsize=2)
def token_bytes(path: str) -> list[bytes]:
    ranks = load_ranks(path)
    table = [b""] * (max(ranks.values()) + 1)
    for piece, i in ranks.items():
        table[i] = piece
    return table


def decode_ids(ids: bytes, table: list[bytes]) -> bytes:
    return b"".join([table[i] for i in np.frombuffer(ids, "<u4").tolist()])


def decode_range(ids: bytes, table: list[bytes], start: int, stop: int) -> bytes:
    """The bytes [start, stop) of a document from its ids alone: only the tokens that touch the range are decoded."""
    numbers = np.frombuffer(ids, "<u4")
    ends = np.cumsum([len(table[i]) for i in numbers.tolist()])
    a, b = int(np.searchsorted(ends, start, "right")), int(np.searchsorted(ends, stop, "left")) + 1
    base = int(ends[a - 1]) if a else 0
    return b"".join(table[i] for i in numbers[a:b].tolist())[start - base : stop - base]


def decode(coded: DataFrame, ranks_path: str, ids_col: str = "ids") -> DataFrame:
    """The frame with ``decoded`` (binary) in place of its ids."""
    kept = replaced(coded, ["decoded"])
    where = [c.lower() for c in kept.columns].index(ids_col.lower())

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = token_bytes(ranks_path)
        for batch in batches:
            for a in range(0, batch.num_rows, 256):
                rows = batch.slice(a, 256)
                texts = [decode_ids(x or b"", table) for x in rows.column(where).to_pylist()]
                yield pa.RecordBatch.from_arrays([*rows.columns, pa.array(texts, pa.binary())], names=[*rows.schema.names, "decoded"])

    schema = T.StructType([T.StructField(f.name, f.dataType, True) for f in kept.schema.fields]).add("decoded", "binary")
    return small_batches(kept).mapInArrow(tidy(run), schema)


def encode_checked(docs: DataFrame, ranks_path: str, text_col: str = "text") -> DataFrame:
    """As ``encode``, with ``round_trip``: whether the ids decode to the text's bytes. Both steps run in one
    worker, so a task keeps one Python process busy instead of two."""
    kept = replaced(docs, ["ids", "n_tokens", "slice_offsets", "round_trip"])
    where = [c.lower() for c in kept.columns].index(text_col.lower())

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cache, table = worker_cache(ranks_path), token_bytes(ranks_path)
        for batch in batches:
            done = 0
            for part in _text_chunks(batch.column(where)):
                coded = encode_texts(part, cache)
                extra = [
                    pa.array([x[0] for x in coded], pa.binary()),
                    pa.array([len(x[0]) // 4 for x in coded], pa.int64()),
                    pa.array([x[1].astype("<u4").tobytes() for x in coded], pa.binary()),
                    pa.array([decode_ids(x[0], table) == t.encode() for x, t in zip(coded, part, strict=True)], pa.bool_()),
                ]
                rows = batch.slice(done, len(part))
                done += len(part)
                yield pa.RecordBatch.from_arrays([*rows.columns, *extra], names=[*rows.schema.names, "ids", "n_tokens", "slice_offsets", "round_trip"])

    schema = T.StructType([T.StructField(f.name, f.dataType, True) for f in kept.schema.fields])
    schema = schema.add("ids", "binary").add("n_tokens", "long").add("slice_offsets", "binary").add("round_trip", "boolean")
    return small_batches(kept).mapInArrow(tidy(run), schema)


def op3_byte_bpe(spark, sf_dir: str) -> DataFrame:
    import public_tokenizers

    path = public_tokenizers.path("byte_bpe_50k.tiktoken")
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    coded = encode(docs, path).select("doc_id", "ids", "n_tokens")
    done = decode(coded, path)
    return done.select("doc_id", "n_tokens", F.sha2("ids", 256).alias("ids_sha256"), F.sha2("decoded", 256).alias("decoded_sha256"))
