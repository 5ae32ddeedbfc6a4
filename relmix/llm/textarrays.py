"""Whole batches of texts as numpy arrays: bytes, words and word shingles as 64-bit hashes.

All functions work on the UTF-8 bytes of an Arrow string column without making Python strings.
Hashes are 64 bits wide; two different words or shingles share one with probability near 2**-64.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa

_RNG = np.random.default_rng(20240607)
_BYTE = _RNG.integers(1, 2**63, 256, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_SPAN = 1024
_STEP = np.uint64(0x9E3779B97F4A7C15)
with np.errstate(over="ignore"):
    _POW = np.cumprod(np.full(_SPAN, _STEP, np.uint64))
_FAR = _RNG.integers(1, 2**63, _SPAN, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_MIX = [np.uint64(x) for x in (0xFF51AFD7ED558CCD, 0xC4CEB9FE1A85EC53)]
_PLACE = _RNG.integers(1, 2**63, 64, dtype=np.uint64) * np.uint64(2) + np.uint64(1)

LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32
SPACE = np.zeros(256, bool)
SPACE[[32, 9, 10, 11, 12, 13]] = True


def mixed(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser (bijective)."""
    x = x ^ (x >> np.uint64(33))
    x = x * _MIX[0]
    x = x ^ (x >> np.uint64(33))
    x = x * _MIX[1]
    return x ^ (x >> np.uint64(33))


def text_bytes(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(bytes, offsets) of a string column; null is empty. Offsets start at 0."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if column.null_count:
        column = column.fill_null("")
    wide = pa.types.is_large_string(column.type)
    buffers = column.buffers()
    offsets = np.frombuffer(buffers[1], np.int64 if wide else np.int32)[column.offset : column.offset + len(column) + 1].astype(np.int64)
    data = np.frombuffer(buffers[2], np.uint8)[offsets[0] : offsets[-1]] if buffers[2] is not None and len(column) else np.empty(0, np.uint8)
    return data, offsets - offsets[0]


def chunks(offsets: np.ndarray, most: int = 1 << 20) -> Iterator[tuple[int, int]]:
    """Row ranges of about ``most`` bytes each; a longer text is a range of its own."""
    at, rows = 0, len(offsets) - 1
    while at < rows:
        to = int(np.searchsorted(offsets, offsets[at] + most, "right")) - 1
        to = min(max(to, at + 1), rows)
        yield at, to
        at = to


def words(data: np.ndarray, offsets: np.ndarray, lower: bool = True) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(starts, ends, word hashes, first word of each row + total), words being runs without ASCII white space."""
    n = len(data)
    edges = np.zeros(len(offsets), np.int64)
    if not n:
        none = np.empty(0, np.int64)
        return none, none, np.empty(0, np.uint64), edges
    inside = ~SPACE[data]
    before = np.empty(n, bool)
    before[0], before[1:] = False, inside[:-1]
    after = np.empty(n, bool)
    after[-1], after[:-1] = False, inside[1:]
    full = offsets[:-1][offsets[1:] > offsets[:-1]]
    before[full] = False
    ends_at = offsets[1:][offsets[1:] > offsets[:-1]]
    after[ends_at - 1] = False
    starts = np.flatnonzero(inside & ~before)
    ends = np.flatnonzero(inside & ~after) + 1
    edges = np.searchsorted(starts, offsets)
    if not len(starts):
        return starts, ends, np.empty(0, np.uint64), edges
    length = ends - starts
    where = np.flatnonzero(inside)
    first = np.cumsum(length) - length
    rel = np.arange(len(where)) - np.repeat(first, length)
    value = _BYTE[(LOWER[data] if lower else data)[where]] * _POW[rel & (_SPAN - 1)]
    if length.max() > _SPAN:
        value = value * _FAR[(rel // _SPAN) & (_SPAN - 1)]
    hashed = mixed(np.add.reduceat(value, first) + length.astype(np.uint64))
    return starts, ends, hashed, edges


def shingles(hashed: np.ndarray, edges: np.ndarray, width: int) -> tuple[np.ndarray, np.ndarray]:
    """Per row the sorted distinct hashes of its ``width``-word shingles: (hashes, row offsets).

    A row with fewer words has its whole sequence as one shingle; a row without words has none.
    """
    n = len(hashed)
    count = np.diff(edges)
    if not n:
        return np.empty(0, np.uint64), np.zeros(len(edges), np.int64)
    stop = np.repeat(edges[1:], count)
    total = np.zeros(n, np.uint64)
    at = np.arange(n)
    for t in range(width):
        ok = at + t < stop
        total[ok] += hashed[at[ok] + t] * _PLACE[t]
    short = (count > 0) & (count < width)
    use = at + width <= stop
    total[edges[:-1][short]] += count[short].astype(np.uint64) * _PLACE[63]
    use[edges[:-1][short]] = True
    total = mixed(total)
    picked, out = [], np.zeros(len(edges), np.int64)
    for i in range(len(count)):
        a, b = edges[i], edges[i + 1]
        one = np.unique(total[a:b][use[a:b]])
        picked.append(one)
        out[i + 1] = out[i] + len(one)
    return np.concatenate(picked), out


def batch_shingles(column: pa.Array, width: int, most: int = 1 << 20) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """(from row, to row, hashes, offsets) over a string column, a bounded number of bytes at a time."""
    data, offsets = text_bytes(column)
    with np.errstate(over="ignore"):
        for a, b in chunks(offsets, most):
            part = offsets[a : b + 1]
            _, _, hashed, edges = words(data[part[0] : part[-1]], part - part[0])
            yield a, b, *shingles(hashed, edges, width)
