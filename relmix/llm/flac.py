"""FLAC media columns: lossless 8-bit mono storage of byte payloads, decoding to seekable PCM blocks.

Both directions work on many frames at once. Encoding picks per frame the cheapest of the constant,
verbatim, fixed (orders 0-4) and linear-prediction (order 8) forms; all bit fields of a batch are
placed by one weighted count over 32-bit words. Decoding walks the frames of a batch in lockstep:
a next-one-bit table turns every Rice code into one gather, and linear predictors are undone one
sample of all frames at a time. Header CRC-8, frame CRC-16 and the stream's MD5 are verified.

``encode`` adds the file (with a seek table of every frame), ``decode`` the payload, whether all
checksums hold, and the block list (sample offset, frame's byte offset, samples); ``pcm_blocks``
turns that into one row a block, and ``read_range`` decodes only the frames of a sample range.

Defined cases: null and empty input become one block of 64 zero bytes; payloads are padded with
zeros to a positive multiple of 64; a null, truncated or altered file gives valid = false and a null
payload; texts of any length are cut into frames of 4,096 samples; equal payloads give equal files.
The lockstep decoder reads 8-bit mono streams of fixed block size with 4-bit Rice parameters, without
escape partitions and wasted bits. All other streams go frame by frame through ``flac_streams``; where they
are not 8-bit mono their payload is interleaved little-endian signed samples and ``feature`` is null.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from relmix.llm.columns import replaced, small_batches
from relmix.llm.workers import tidy

BLOCK, PAD, RATE, ORDER, PRECISION = 4096, 64, 8000, 8, 12
CHUNK = 1 << 20
SEEK_POINT = 18


def _crc_table(bits: int, poly: int) -> list[int]:
    top, mask, table = 1 << (bits - 1), (1 << bits) - 1, []
    for value in range(256):
        crc = value << (bits - 8)
        for _ in range(8):
            crc = ((crc << 1) ^ poly if crc & top else crc << 1) & mask
        table.append(crc)
    return table


CRC8 = _crc_table(8, 0x07)
CRC16 = np.array(_crc_table(16, 0x8005), np.uint16)


def crc8(data: bytes) -> int:
    crc = 0
    for b in data:
        crc = CRC8[crc ^ b]
    return crc


def _crc16_pairs() -> np.ndarray:
    """CRC-16 of every two-byte word, so that a step of the checksum is one look-up for two bytes."""
    high = CRC16[np.arange(65536) >> 8]
    return ((high << 8) ^ CRC16[(high >> 8) ^ (np.arange(65536) & 0xFF)]).astype(np.uint16)


CRC16_PAIRS = _crc16_pairs()


def crc16_many(data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """CRC-16 of many byte ranges, two bytes of all ranges at a time (longest first, so the active ones are a prefix).

    The register starts at 0, so a range of odd length begins with its first byte alone.
    """
    if not len(starts):
        return np.zeros(0, np.uint16)
    size = ends - starts
    order = np.argsort(-size, kind="stable")
    at, left = starts[order].astype(np.int64), size[order]
    words = np.empty(len(data), np.uint16)
    words[:-1] = data[:-1].astype(np.uint16) << 8 | data[1:]
    crc = np.where(left % 2 == 1, CRC16[data[np.minimum(at, len(data) - 1)]], 0).astype(np.uint16)
    at, pairs = at + left % 2, left // 2
    active = np.searchsorted(-pairs, -np.arange(1, pairs.max() + 1), "right")
    if (np.diff(pairs) > 0).any():  # an odd and an even length may share a rank
        active = np.array([np.count_nonzero(pairs >= i) for i in range(1, int(pairs.max()) + 1)])
    for i, n in enumerate(active.tolist()):
        crc[:n] = CRC16_PAIRS[crc[:n] ^ words[at[:n] + 2 * i]]
    out = np.empty_like(crc)
    out[order] = crc
    return out


def _utf8_number(n: int) -> bytes:
    """A frame number in FLAC's extended UTF-8 (up to 36 bits)."""
    if n < 0x80:
        return bytes([n])
    out = []
    room = 0x3F
    while n > room:
        out.append(0x80 | (n & 0x3F))
        n >>= 6
        room >>= 1
    lead = (0xFF << (7 - len(out))) & 0xFF
    return bytes([lead | n, *reversed(out)])


def _read_utf8_number(data: bytes, at: int) -> tuple[int, int]:
    first = data[at]
    if first < 0x80:
        return first, at + 1
    extra = 0
    while first & (0x40 >> extra):
        extra += 1
    if not extra:
        raise ValueError("frame number")
    n = first & (0x3F >> extra)
    for b in data[at + 1 : at + 1 + extra]:
        n = n << 6 | (b & 0x3F)
    return n, at + 1 + extra


def _frame_header(number: int, samples: int) -> bytes:
    size_code = 0b1100 if samples == BLOCK else 0b0111
    head = bytes([0xFF, 0xF8, size_code << 4 | 0b0100, 0b0000_001_0]) + _utf8_number(number)
    if size_code == 0b0111:
        head += (samples - 1).to_bytes(2, "big")
    return head + bytes([crc8(head)])


def _predictors(x: np.ndarray, length: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Quantised coefficients [frames, ORDER] and shifts by the autocorrelation method, all frames together."""
    f = x.astype(np.float64)
    auto = np.stack([(f[:, lag:] * f[:, : f.shape[1] - lag]).sum(1) for lag in range(ORDER + 1)], 1)
    auto[:, 0] = auto[:, 0] * 1.0001 + 1e-9
    a = np.zeros((len(x), ORDER))
    error = auto[:, 0].copy()
    for m in range(ORDER):
        reflect = (auto[:, m + 1] - (a[:, :m] * auto[:, m:0:-1]).sum(1)) / error
        now = a.copy()
        now[:, m] = reflect
        now[:, :m] = a[:, :m] - reflect[:, None] * a[:, :m][:, ::-1]
        a, error = now, error * (1 - reflect**2)
        error = np.maximum(error, 1e-9)
    biggest = np.maximum(np.abs(a).max(1), 1e-6)
    shift = np.clip(PRECISION - 2 - np.floor(np.log2(biggest)).astype(int), 0, 15)
    top = 2 ** (PRECISION - 1)
    return np.clip(np.rint(a * (2.0**shift)[:, None]), -top, top - 1).astype(np.int64), shift


def _zigzag(e: np.ndarray) -> np.ndarray:
    return (e << 1) ^ (e >> (8 * e.itemsize - 1))


def _rice_cost(u: np.ndarray, order: int | np.ndarray, length: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(bits, parameter) of the best Rice parameter by frame; u is zero outside the coded samples."""
    coded = np.maximum(length - order, 1)
    mean = u.sum(1, dtype=np.int64) / coded
    low = np.clip(np.floor(np.log2(np.maximum(mean, 1))).astype(np.int32) - 1, 0, 12)
    best, which = None, low
    for k in (low, low + 1, low + 2):  # the best parameter lies within one of log2 of the mean
        bits = (u >> k[:, None]).sum(1, dtype=np.int64) + coded * (k + 1)
        if best is None:
            best = bits
        else:
            better = bits < best
            best, which = np.where(better, bits, best), np.where(better, k, which)
    return best, which


def _encode_frames(x: np.ndarray, length: np.ndarray, numbers: list[int]) -> tuple[np.ndarray, np.ndarray]:
    """Frames of a padded sample matrix: (bytes of all frames, byte offsets); the last two bytes of each are still zero."""
    inside = np.arange(x.shape[1]) < length[:, None]
    residuals, costs, ks = [], [], []
    e = x.astype(np.int32)
    for order in range(5):
        u = np.where(inside, _zigzag(e), 0)
        u[:, :order] = 0
        bits, k = _rice_cost(u, order, length)
        residuals.append(u)
        costs.append(bits + 8 * order)
        ks.append(k)
        e = np.concatenate([e[:, :1], e[:, 1:] - e[:, :-1]], 1)
    coef, shift = _predictors(np.where(inside, x, 0), length)
    wide, narrow_coef = x.astype(np.int32), coef.astype(np.int32)  # 8 products of 12 and 8 bits fit easily
    guess = np.zeros_like(wide)
    for j in range(ORDER):
        guess[:, ORDER:] += narrow_coef[:, j : j + 1] * wide[:, ORDER - 1 - j : wide.shape[1] - 1 - j]
    u = np.where(inside, _zigzag(wide - (guess >> shift[:, None].astype(np.int32))), 0)
    u[:, :ORDER] = 0
    bits, k = _rice_cost(u, ORDER, length)
    residuals.append(u)
    costs.append(np.where(length > ORDER, bits + ORDER * (8 + PRECISION) + 9, 1 << 40))
    ks.append(k)
    cost = np.stack(costs)
    form = cost.argmin(0)
    verbatim = cost.min(0) + 10 >= 8 * length
    constant = ((x == x[:, :1]) | ~inside).all(1)

    values, widths, frame_bits, heads = [], [], [], []
    for i, n in enumerate(length.tolist()):
        head = _frame_header(numbers[i], n)
        heads.append(head)
        v, w = [np.frombuffer(head, np.uint8).astype(np.int64)], [np.full(len(head), 8)]
        samples = x[i, :n].astype(np.int64) & 0xFF

        def put(value: int, bits: int, v=v, w=w) -> None:
            v.append(np.array([value]))
            w.append(np.array([bits]))

        if constant[i]:
            put(0, 8)
            put(int(samples[0]), 8)
        elif verbatim[i]:
            put(0b00000010, 8)
            v.append(samples)
            w.append(np.full(n, 8))
        else:
            kind = int(form[i])
            order = kind if kind < 5 else ORDER
            put((0b001000 | order if kind < 5 else 0b100000 | (ORDER - 1)) << 1, 8)
            v.append(samples[:order])
            w.append(np.full(order, 8))
            if kind == 5:
                put(PRECISION - 1, 4)
                put(int(shift[i]), 5)
                v.append(coef[i] & ((1 << PRECISION) - 1))
                w.append(np.full(ORDER, PRECISION))
            k = int(ks[kind][i])
            put(0, 6)  # Rice coding with 4-bit parameters, one partition
            put(k, 4)
            code = residuals[kind][i, order:n]
            v.append((code & ((1 << k) - 1)) | (1 << k))
            w.append((code >> k) + (k + 1))
        v, w = np.concatenate(v), np.concatenate(w)
        total = int(w.sum())
        fill = -total % 8
        values += [v, np.zeros(2, np.int64)]
        widths += [w, np.array([fill, 16])]
        frame_bits.append(total + fill + 16)
    value, width = np.concatenate(values), np.concatenate(widths)
    end = np.cumsum(width)
    size = np.array(frame_bits) // 8
    offsets = np.concatenate([[0], np.cumsum(size)])
    # a field's value has at most 16 bits and ends at bit ``end``: it touches one or two 32-bit words
    last = (end - 1) // 32
    up = 32 * (last + 1) - end
    shifted = value.astype(np.uint64) << up.astype(np.uint64)
    words = int(end[-1] + 31) // 32 + 1
    low = np.bincount(last, (shifted & np.uint64(0xFFFFFFFF)).astype(np.float64), words)
    over = (shifted >> np.uint64(32)).astype(np.float64)
    spill = np.flatnonzero(over)
    if len(spill):
        low += np.bincount(last[spill] - 1, over[spill], words)
    data = low.astype(np.uint64).astype(">u4").view(np.uint8)[: offsets[-1]].copy()
    return data, offsets


def payload_of(raw: bytes) -> bytes:
    return raw + bytes(max(PAD, len(raw) + -len(raw) % PAD) - len(raw))


def encode_payloads(payloads: list[bytes]) -> list[bytes]:
    """FLAC files of payloads (each a positive multiple of 64 bytes)."""
    if not payloads:
        return []
    owner, numbers, lengths, rows = [], [], [], []
    for i, p in enumerate(payloads):
        for number, a in enumerate(range(0, len(p), BLOCK)):
            owner.append(i)
            numbers.append(number)
            part = np.frombuffer(p[a : a + BLOCK], np.uint8)
            rows.append(part)
            lengths.append(len(part))
    length = np.array(lengths)
    blobs, begins, base = [], np.zeros(len(rows), np.int64), 0
    sizes = np.zeros(len(rows), np.int64)
    # frames of like length together, a bounded number at a time
    order = np.argsort(length, kind="stable")
    group = CHUNK // 4 // BLOCK
    for a in range(0, len(order), group):
        pick = order[a : a + group]
        x = np.zeros((len(pick), int(length[pick].max())), np.int16)
        for j, f in enumerate(pick):
            x[j, : lengths[f]] = rows[f].astype(np.int16) - 128
        blob, offsets = _encode_frames(x, length[pick], [numbers[f] for f in pick])
        blobs.append(blob)
        begins[pick] = base + offsets[:-1]
        sizes[pick] = np.diff(offsets)
        base += int(offsets[-1])
    whole, ends = np.concatenate(blobs), begins + sizes
    crc = crc16_many(whole, begins, ends - 2)
    whole[ends - 2], whole[ends - 1] = (crc >> 8).astype(np.uint8), (crc & 0xFF).astype(np.uint8)
    raw = whole.tobytes()
    data = [raw[a:b] for a, b in zip(begins.tolist(), ends.tolist(), strict=True)]
    out, at = [], 0
    for i, p in enumerate(payloads):
        stop = at
        while stop < len(owner) and owner[stop] == i:
            stop += 1
        frames, own = data[at:stop], sizes[at:stop].tolist()
        info = BLOCK.to_bytes(2, "big") * 2 + min(own).to_bytes(3, "big") + max(own).to_bytes(3, "big")
        info += (RATE << 44 | 0 << 41 | 7 << 36 | len(p)).to_bytes(8, "big") + hashlib.md5((np.frombuffer(p, np.uint8) ^ 0x80).tobytes()).digest()
        seek, offset = [], 0
        for number, n in enumerate(own):
            seek.append((number * BLOCK).to_bytes(8, "big") + offset.to_bytes(8, "big") + lengths[at + number].to_bytes(2, "big"))
            offset += n
        seek = seek[: (1 << 24) // SEEK_POINT - 1]  # a metadata block's length has 24 bits; readers interpolate beyond
        table = b"".join(seek)
        out.append(b"fLaC" + b"\x00" + len(info).to_bytes(3, "big") + info + b"\x83" + len(table).to_bytes(3, "big") + table + b"".join(frames))
        at = stop
    return out


def _metadata(file: bytes) -> tuple[int, int, bytes, int, list[tuple[int, int, int]]]:
    """(block size, total samples, md5, start of the frames, seek points)."""
    if file[:4] != b"fLaC":
        raise ValueError("marker")
    at, block, total, md5, points, last = 4, 0, 0, b"", [], False
    while not last:
        last, kind, size = bool(file[at] & 0x80), file[at] & 0x7F, int.from_bytes(file[at + 1 : at + 4], "big")
        body = file[at + 4 : at + 4 + size]
        if len(body) != size:
            raise ValueError("metadata")
        if kind == 0:
            block = int.from_bytes(body[2:4], "big")
            packed = int.from_bytes(body[10:18], "big")
            if (packed >> 41) & 7 or (packed >> 36) & 31 != 7 or body[:2] != body[2:4]:
                raise ValueError("only 8-bit mono of fixed block size")
            total, md5 = packed & ((1 << 36) - 1), body[18:34]
        elif kind == 3:
            points = [(int.from_bytes(body[i : i + 8], "big"), int.from_bytes(body[i + 8 : i + 16], "big"), int.from_bytes(body[i + 16 : i + 18], "big")) for i in range(0, size, SEEK_POINT)]
        at += 4 + size
    return block, total, md5, at, points


def _frame_start(data: bytes, at: int, block: int) -> tuple[int, int, int]:
    """(frame number, samples, offset of the subframe) of a frame header, checked against its CRC-8."""
    if data[at : at + 2] != b"\xff\xf8" or data[at + 3] != 0b0000_001_0:
        raise ValueError("frame header")
    number, end = _read_utf8_number(data, at + 4)
    code = data[at + 2] >> 4
    if code == 0b0111:
        samples, end = int.from_bytes(data[end : end + 2], "big") + 1, end + 2
    elif code == 0b0110:
        samples, end = data[end] + 1, end + 1
    elif code >= 8:
        samples = 256 << (code - 8)
    elif 2 <= code <= 5:
        samples = 576 << (code - 2)
    else:
        samples = 192
    if crc8(data[at:end]) != data[end] or samples > block:
        raise ValueError("header checksum")
    return number, samples, end + 1


def _bits_at(words: np.ndarray, at: np.ndarray, width: np.ndarray | int) -> np.ndarray:
    """Unsigned fields of up to 24 bits at bit positions, from big-endian 32-bit words at every byte."""
    return (words[at >> 3].astype(np.int64) >> (32 - (at & 7) - width)) & ((1 << width) - 1)


def _signed(value: np.ndarray, width: int) -> np.ndarray:
    return value - ((value >> (width - 1)) << width)


def decode_frames(raw: bytes, starts: list[int], blocks: list[int]) -> tuple[list[np.ndarray | None], list[int], list[int]]:
    """Decode the frames that begin at ``starts`` (byte ranges need not be known): (samples or None, end offsets, numbers)."""
    n = len(starts)
    data = np.concatenate([np.frombuffer(raw, np.uint8), np.zeros(8, np.uint8)])
    wide = data.astype(np.uint32)
    words = wide[:-3] << 24 | wide[1:-2] << 16 | wide[2:-1] << 8 | wide[3:]
    bits = np.unpackbits(data)
    top = len(bits)
    next_one = np.where(bits, np.arange(top, dtype=np.int32), np.int32(top - 1))
    next_one = np.minimum.accumulate(next_one[::-1])[::-1]
    ok = np.ones(n, bool)
    number, length, at = np.zeros(n, np.int64), np.zeros(n, np.int64), np.zeros(n, np.int64)
    for i in range(n):
        try:
            number[i], length[i], body = _frame_start(raw, starts[i], blocks[i])
            at[i] = 8 * body
        except (ValueError, IndexError):
            ok[i] = False
    limit = 8 * len(raw)
    kind = np.where(ok, _bits_at(words, np.minimum(at, limit), 8) >> 1, 1)
    at = at + 8
    out = np.zeros((int(length.max()) if n else 0, n), np.int32)  # time by frame
    order = np.where(kind >= 32, kind - 31, np.where((kind >= 8) & (kind <= 12), kind - 8, 0))
    predicted = ok & ((kind >= 32) | ((kind >= 8) & (kind <= 12)))
    ok &= predicted | (kind <= 1)
    ok &= order <= length
    for i in np.flatnonzero(ok & (kind == 0)):
        out[: length[i], i] = _signed(_bits_at(words, at[i : i + 1], 8), 8)[0]
        at[i] += 8
    for i in np.flatnonzero(ok & (kind == 1)):
        b = at[i] // 8
        if b + length[i] > len(raw):
            ok[i] = False
            continue
        out[: length[i], i] = data[b : b + length[i]].view(np.int8)
        at[i] += 8 * length[i]
    predicted &= ok
    for t in range(int(order[predicted].max()) if predicted.any() else 0):
        who = np.flatnonzero(predicted & (order > t))
        out[t, who] = _signed(_bits_at(words, at[who], 8), 8)
        at[who] += 8
    linear = np.flatnonzero(predicted & (kind >= 32))
    coef = np.zeros((32, n), np.int64)
    shift = np.zeros(n, np.int64)
    if len(linear):
        precision = _bits_at(words, at[linear], 4) + 1
        shift[linear] = _signed(_bits_at(words, at[linear] + 4, 5), 5)
        at[linear] += 9
        for t in range(int(order[linear].max())):
            live = order[linear] > t
            who, p = linear[live], precision[live]
            value = _bits_at(words, at[who], p)
            coef[t, who] = value - ((value >> (p - 1)) << p)
            at[who] += p
    ok &= shift >= 0
    predicted &= ok
    who = np.flatnonzero(predicted)
    if len(who):
        method, parts = _bits_at(words, at[who], 2), _bits_at(words, at[who] + 2, 4)
        bad = (method != 0) | (length[who] % (1 << parts) != 0) | ((length[who] >> parts) < order[who])
        ok[who[bad]] = False
        who, parts = who[~bad], parts[~bad]
        at[who] += 6
        done = order.copy()
        for j in range(1 << int(parts.max()) if len(who) else 0):
            live = (1 << parts) > j
            _rice_partition(words, next_one, at, who[live], (length[who[live]] >> parts[live]) * (j + 1), done, out, ok, limit)
        _undo_prediction(out, who[ok[who]], kind, order, coef, shift, length)
    ends = -(-at // 8) + 2
    ok &= ends <= len(raw)
    check = np.flatnonzero(ok)
    if len(check):
        crc = crc16_many(data, np.array(starts)[check], ends[check] - 2)
        stored = wide[ends[check] - 2].astype(np.int64) << 8 | wide[ends[check] - 1]
        ok[check] = crc == stored
    samples = [out[: length[i], i] if ok[i] else None for i in range(n)]
    return samples, ends.tolist(), number.tolist()


def _rice_partition(words, next_one, at, who, until, done, out, ok, limit) -> None:
    """One partition of every frame in ``who``: residuals up to sample ``until`` go to ``out``; ``at`` and ``done`` advance."""
    k = _bits_at(words, np.minimum(at[who], limit), 4)
    ok[who[k == 15]] = False  # escape codes are not written by this encoder
    live = k < 15
    who, k, until = who[live], k[live], until[live]
    count = until - done[who]
    rank = np.argsort(-count, kind="stable")
    who, k, count = who[rank], k[rank], count[rank]
    if not len(who) or count[0] <= 0:
        at[who] += 4
        return
    place = (at[who] + 4).astype(np.int64)
    ones = np.zeros((int(count[0]), len(who)), np.int32)
    begin = np.zeros_like(ones)
    step = (k + 1).astype(np.int64)
    last = len(next_one) - 1
    active = np.searchsorted(-count, -np.arange(1, count[0] + 1), "right")
    for i, n in enumerate(active.tolist()):
        p = place[:n]
        one = next_one[p]
        ones[i, :n], begin[i, :n] = one, p
        place[:n] = np.minimum(one + step[:n], last)
    at[who] = place
    ok[who[place > limit]] = False
    inside = np.arange(len(ones))[:, None] < count
    quotient = ones - begin
    low = _bits_at(words, np.minimum(ones.astype(np.int64) + 1, limit), k)
    u = quotient.astype(np.int64) << k | low
    e = np.where(u & 1, -(u >> 1) - 1, u >> 1)
    rows = done[who] + np.arange(len(ones))[:, None]
    columns = np.broadcast_to(who, rows.shape)
    out[rows[inside], columns[inside]] = e[inside]
    done[who] += count


def _undo_prediction(out, who, kind, order, coef, shift, length) -> None:
    for o in range(1, 5):
        fixed = who[(kind[who] == 8 + o)]
        if len(fixed):
            warm, e = out[:o, fixed].copy(), out[:, fixed]
            # the o-th difference is known after the warm-up; its start values come from the warm-up samples
            levels = [warm]
            for _ in range(o - 1):
                levels.append(np.diff(levels[-1], axis=0))
            for level in reversed(levels):
                e[o - 1] = level[-1]
                e[o - 1 :] = np.cumsum(e[o - 1 :], axis=0)
            e[:o] = warm
            out[:, fixed] = e
    linear = who[kind[who] >= 32]
    for o in np.unique(order[linear]):
        own = linear[order[linear] == o]
        own = own[np.argsort(-length[own], kind="stable")]
        s, c, sh = out[:, own], coef[:o, own][::-1].astype(np.int32), shift[own].astype(np.int32)
        longest = int(length[own[0]])
        active = np.searchsorted(-length[own], -np.arange(o + 1, longest + 1), "right")
        for t, n in zip(range(int(o), longest), active.tolist(), strict=True):
            s[t, :n] += np.add.reduce(s[t - o : t, :n] * c[:, :n], 0, np.int32) >> sh[:n]
        out[:, own] = s


def decode_files(files: list[bytes | None]) -> list[tuple[bytes | None, list[tuple[int, int, int]]]]:
    """(payload or None, blocks as (sample offset, byte offset, samples)) of every file, all checksums verified."""
    info, todo = [], []
    for i, file in enumerate(files):
        try:
            block, total, md5, at, points = _metadata(file or b"")
            starts = [at + p[1] for p in points] if sum(p[2] for p in points) == total else None
            info.append((block, total, md5))
            todo.append((i, at, starts))
        except (ValueError, IndexError):
            info.append(None)
    result: list = [(None, [])] * len(files)
    ready = [(i, at, starts) for i, at, starts in todo if starts is not None]
    frames: dict[int, list] = {i: [] for i, _, _ in ready}
    for group in _by_bytes(ready, files):
        raw, begins, blocks, owner = [], [], [], []
        base = 0
        for i, first, stop, starts in group:
            raw.append(files[i][first:stop])
            begins += [base + s - first for s in starts]
            blocks += [info[i][0]] * len(starts)
            owner += [(i, s) for s in starts]
            base += stop - first
        samples, _, numbers = decode_frames(b"".join(raw), begins, blocks)
        for (i, s), x, number in zip(owner, samples, numbers, strict=True):
            frames[i].append((number, s, x))
    for i, found in frames.items():
        result[i] = _joined(found, info[i])
    return [_decode_general(file) if found[0] is None and file else found for file, found in zip(files, result, strict=True)]


def _by_bytes(ready: list, files: list) -> Iterator[list[tuple[int, int, int, list[int]]]]:
    """Groups of frame runs of at most about CHUNK bytes; a long file is cut between frames."""
    group, size = [], 0
    for i, at, starts in ready:
        a = 0
        while a < len(starts):
            b = a + 1
            while b < len(starts) and starts[b] - starts[a] < CHUNK - size:
                b += 1
            stop = starts[b] if b < len(starts) else len(files[i])
            group.append((i, starts[a], stop, starts[a:b]))
            size += stop - starts[a]
            a = b
            if size >= CHUNK:
                yield group
                group, size = [], 0
    if group:
        yield group


def _joined(frames: list, info: tuple) -> tuple[bytes | None, list[tuple[int, int, int]]]:
    block, total, md5 = info
    if any(x is None for _, _, x in frames) or [n for n, _, _ in frames] != list(range(len(frames))):
        return None, []
    signed = np.concatenate([x for _, _, x in frames]).astype(np.int8) if frames else np.empty(0, np.int8)
    if len(signed) != total or hashlib.md5(signed.tobytes()).digest() != md5:
        return None, []
    return (signed.astype(np.int16) + 128).astype(np.uint8).tobytes(), [(n * block, s, len(x)) for n, s, x in frames]


def _decode_general(file: bytes) -> tuple[bytes | None, list[tuple[int, int, int]]]:
    """Streams of other forms, and those without a complete seek table: a frame's end gives the next one's start."""
    from relmix.llm.flac_streams import decode_stream, stream_info

    try:
        payload, blocks = decode_stream(file)
        info = stream_info(file)
    except (ValueError, IndexError):
        return None, []
    if (info.channels, info.bits) == (1, 8):
        payload = (np.frombuffer(payload, np.int8).astype(np.int16) + 128).astype(np.uint8).tobytes()
    return payload, blocks


def _is_bytes(file: bytes) -> bool:
    """8-bit mono, by the packed field of the stream information."""
    return file[20] & 0x0E == 0 and (file[20] & 1) << 4 | file[21] >> 4 == 7


def read_range(file: bytes, start: int, stop: int) -> bytes:
    """Samples [start, stop) as unsigned bytes; only the frames that hold them are decoded, found by the seek table."""
    block, total, _, at, points = _metadata(file)
    stop = min(stop, total)
    if start >= stop:
        return b""
    a, b = start // block, (stop - 1) // block
    starts = [at + p[1] for p in points]
    end = starts[b + 1] if b + 1 < len(starts) else len(file)
    samples, _, _ = decode_frames(file[starts[a] : end], [s - starts[a] for s in starts[a : b + 1]], [block] * (b - a + 1))
    if any(x is None for x in samples):
        raise ValueError("checksum")
    whole = (np.concatenate(samples) + 128).astype(np.uint8).tobytes()
    return whole[start - a * block : stop - a * block]


def feature_of(payload: bytes, blocks: list) -> str:
    """Level and movement of the decoded samples, in whole thousandths so that equal samples give equal text."""
    x = np.frombuffer(payload, np.uint8).astype(np.int64) - 128
    n = len(x)
    crossings = int(((x[1:] < 0) != (x[:-1] < 0)).sum())
    return f"blocks={len(blocks)};mean={int(x.sum()) * 1000 // n};energy={int((x * x).sum()) * 1000 // n};steps={int(np.abs(np.diff(x)).sum()) * 1000 // n};crossings={crossings}"


def _with(rows: pa.RecordBatch, names: list[str], columns: list[pa.Array]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([*rows.columns, *columns], names=[*rows.schema.names, *names])


def _portions(column: pa.Array) -> Iterator[tuple[int, list]]:
    first, part, size = 0, [], 0
    for x in column.to_pylist():
        part.append(x)
        size += len(x or "") + 256
        if size >= CHUNK:
            yield first, part
            first, part, size = first + len(part), [], 0
    if part:
        yield first, part


def _schema(df: DataFrame) -> T.StructType:
    return T.StructType([T.StructField(f.name, f.dataType, True) for f in df.schema.fields])


def encode(docs: DataFrame, text_col: str = "text") -> DataFrame:
    """The frame with ``flac`` (binary); the text is stored as UTF-8, padded with zeros to a positive multiple of 64."""
    kept = replaced(docs, ["flac"])
    where = [c.lower() for c in kept.columns].index(text_col.lower())

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for first, part in _portions(batch.column(where)):
                files = encode_payloads([payload_of(x.encode() if isinstance(x, str) else x or b"") for x in part])
                yield _with(batch.slice(first, len(part)), ["flac"], [pa.array(files, pa.binary())])

    return small_batches(kept).mapInArrow(tidy(run), _schema(kept).add("flac", "binary"))


_BLOCKS = pa.list_(pa.struct([("sample_offset", pa.int64()), ("byte_offset", pa.int64()), ("samples", pa.int32())]))


def decode(media: DataFrame, flac_col: str = "flac") -> DataFrame:
    """The frame with ``payload`` (binary), ``valid``, ``pcm`` (sample_offset, byte_offset, samples) and ``feature``."""
    kept = replaced(media, ["payload", "valid", "pcm", "feature"])
    where = [c.lower() for c in kept.columns].index(flac_col.lower())

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for first, part in _portions(batch.column(where)):
                found = decode_files(part)
                yield _with(
                    batch.slice(first, len(part)),
                    ["payload", "valid", "pcm", "feature"],
                    [
                        pa.array([p for p, _ in found], pa.binary()),
                        pa.array([p is not None for p, _ in found], pa.bool_()),
                        pa.array([[{"sample_offset": a, "byte_offset": b, "samples": c} for a, b, c in x] for _, x in found], _BLOCKS),
                        pa.array([feature_of(p, x) if p and _is_bytes(file) else None for file, (p, x) in zip(part, found, strict=True)], pa.string()),
                    ],
                )

    block = T.StructType().add("sample_offset", "long").add("byte_offset", "long").add("samples", "integer")
    return small_batches(kept).mapInArrow(tidy(run), _schema(kept).add("payload", "binary").add("valid", "boolean").add("pcm", T.ArrayType(block)).add("feature", "string"))


def pcm_blocks(decoded: DataFrame, id_col: str = "doc_id") -> DataFrame:
    """(id, sample_offset, samples, byte_offset, block): one row a PCM block, for tables clustered by offset."""
    # bytes of one sample of all channels
    width = F.expr("octet_length(payload) DIV aggregate(pcm, 0L, (n, b) -> n + b.samples)").alias("width")
    rows = decoded.select(F.col(f"`{id_col}`").alias("id"), "payload", width, F.explode("pcm").alias("b"))
    block = F.expr("substring(payload, CAST(b.sample_offset * width + 1 AS INT), CAST(b.samples * width AS INT))")
    return rows.select("id", "b.sample_offset", "b.samples", "b.byte_offset", block.alias("block"))


def op4_flac(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    done = decode(encode(docs).select("doc_id", F.octet_length(F.coalesce("text", F.lit(""))).cast("long").alias("n_bytes"), "flac"))
    return done.select(
        "doc_id",
        "n_bytes",
        F.octet_length("payload").cast("long").alias("payload_bytes"),
        F.sha2("payload", 256).alias("payload_sha256"),
        F.crc32(F.expr("substring(payload, -64, 64)")).alias("tail_crc32"),
        F.octet_length("flac").cast("long").alias("media_bytes"),
        F.sha2("flac", 256).alias("media_sha256"),
        "feature",
        "valid",
    )
