"""Any FLAC stream: 1-8 channels, 4-32 bits a sample, fixed or variable block size, every subframe form.

The reader behind ``flac.decode_files`` for streams that its lockstep decoder does not take: stereo
decorrelation, both Rice parameter widths, escape partitions, wasted bits, frames of any size. It reads one
frame at a time with whole numbers, so no sample overflows; header CRC-8, frame CRC-16 and, where the stream
names them, the sample count and MD5 are verified. ``ValueError`` means altered, truncated or no FLAC.
"""

from __future__ import annotations

import hashlib
from math import comb
from typing import NamedTuple

import numpy as np

from relmix.llm.flac import _read_utf8_number, crc8, crc16_many

#: Fixed values of the format: bits a sample by frame header code (0: as the stream says, 3: reserved).
SAMPLE_BITS = [0, 8, 12, None, 16, 20, 24, 32]


class Info(NamedTuple):
    channels: int
    bits: int
    total: int
    md5: bytes
    frames: int  # where the frames begin


def stream_info(file: bytes) -> Info:
    if file[:4] != b"fLaC":
        raise ValueError("marker")
    at, last, info = 4, False, None
    while not last:
        head = file[at : at + 4]
        size = int.from_bytes(head[1:], "big")
        body = file[at + 4 : at + 4 + size]
        if len(head) < 4 or len(body) != size:
            raise ValueError("metadata")
        last = bool(head[0] & 0x80)
        if head[0] & 0x7F == 0:
            if size != 34:
                raise ValueError("stream information")
            packed = int.from_bytes(body[10:18], "big")
            info = Info((packed >> 41 & 7) + 1, (packed >> 36 & 31) + 1, packed & ((1 << 36) - 1), body[18:], 0)
        at += 4 + size
    if info is None:
        raise ValueError("stream information")
    return info._replace(frames=at)


class _Bits:
    def __init__(self, data: bytes, at: int):
        self.data, self.at = data, 8 * at

    def take(self, n: int) -> int:
        stop = self.at + n
        first, end = self.at >> 3, (stop + 7) >> 3
        if end > len(self.data):
            raise ValueError("truncated")
        self.at = stop
        return int.from_bytes(self.data[first:end], "big") >> (8 * end - stop) & ((1 << n) - 1)

    def signed(self, n: int) -> int:
        value = self.take(n) if n else 0
        return value - (1 << n) if n and value >> (n - 1) else value

    def zeros(self) -> int:
        """Zero bits up to the next one bit, which is passed."""
        start = self.at
        while True:
            left = 8 - (self.at & 7)
            value = self.take(left)
            if value:
                self.at -= value.bit_length() - 1
                return self.at - start - 1


def _residuals(bits: _Bits, order: int, size: int) -> list[int]:
    method, parts = bits.take(2), bits.take(4)
    each = size >> parts
    if method > 1 or each << parts != size or each < order:
        raise ValueError("residual")
    width, out = 4 + method, []
    for part in range(1 << parts):
        k, n = bits.take(width), each - (order if part == 0 else 0)
        if k == (1 << width) - 1:
            raw = bits.take(5)
            out += [bits.signed(raw) for _ in range(n)]
        else:
            for _ in range(n):
                u = bits.zeros() << k
                u |= bits.take(k) if k else 0
                out.append(-(u >> 1) - 1 if u & 1 else u >> 1)
    return out


def _subframe(bits: _Bits, size: int, width: int) -> list[int]:
    if bits.take(1):
        raise ValueError("subframe")
    kind = bits.take(6)
    wasted = bits.zeros() + 1 if bits.take(1) else 0
    width -= wasted
    if width < 1:
        raise ValueError("wasted bits")
    if kind == 0:
        out = [bits.signed(width)] * size
    elif kind == 1:
        out = [bits.signed(width) for _ in range(size)]
    elif 8 <= kind <= 12 or kind >= 32:
        order = kind - 31 if kind >= 32 else kind - 8
        if order > size:
            raise ValueError("order")
        out, shift = [bits.signed(width) for _ in range(order)], 0
        if kind >= 32:
            precision = bits.take(4) + 1
            shift = bits.signed(5)
            if precision == 16 or shift < 0:
                raise ValueError("predictor")
            weights = [bits.signed(precision) for _ in range(order)]
        else:  # a vanishing difference of this order
            weights = [-comb(order, i) * (-1) ** i for i in range(1, order + 1)]
        weights.reverse()
        for e in _residuals(bits, order, size):
            past = out[len(out) - order :]
            out.append(e + (sum(w * x for w, x in zip(weights, past, strict=True)) >> shift))
    else:
        raise ValueError("subframe")
    return [x << wasted for x in out] if wasted else out


def _frame(file: bytes, at: int, info: Info, frames: int, done: int) -> tuple[list[list[int]], int]:
    """(samples of every channel, where the frame ends); the frame has to name its place in the stream."""
    if len(file) < at + 6 or file[at] != 0xFF or file[at + 1] & 0xFE != 0xF8 or file[at + 3] & 1:
        raise ValueError("frame header")
    size_code, rate_code, layout, bits_code = file[at + 2] >> 4, file[at + 2] & 15, file[at + 3] >> 4, file[at + 3] >> 1 & 7
    number, end = _read_utf8_number(file, at + 4)
    if number != (done if file[at + 1] & 1 else frames):
        raise ValueError("frame number")
    if size_code in (6, 7):
        more = size_code - 5
        size, end = int.from_bytes(file[end : end + more], "big") + 1, end + more
    elif size_code:
        size = 192 if size_code == 1 else 576 << (size_code - 2) if size_code < 6 else 256 << (size_code - 8)
    else:
        raise ValueError("block size")
    end += {12: 1, 13: 2, 14: 2}.get(rate_code, 0)
    width = SAMPLE_BITS[bits_code]
    width = info.bits if width == 0 else width
    channels = layout + 1 if layout < 8 else 2
    if width != info.bits or channels != info.channels or layout > 10 or rate_code == 15 or len(file) <= end or crc8(file[at:end]) != file[end]:
        raise ValueError("frame header")
    bits = _Bits(file, end + 1)
    side = {8: 1, 9: 0, 10: 1}.get(layout)  # the channel that holds a difference has one bit more
    heard = [_subframe(bits, size, width + (c == side)) for c in range(channels)]
    if layout == 8:
        heard[1] = [a - d for a, d in zip(*heard, strict=True)]
    elif layout == 9:
        heard[0] = [d + b for d, b in zip(*heard, strict=True)]
    elif layout == 10:
        sums = [2 * m + (d & 1) for m, d in zip(*heard, strict=True)]
        heard = [[(s + d) >> 1 for s, d in zip(sums, heard[1], strict=True)], [(s - d) >> 1 for s, d in zip(sums, heard[1], strict=True)]]
    stop = (bits.at + 7) >> 3
    if len(file) < stop + 2:
        raise ValueError("truncated")
    crc = crc16_many(np.frombuffer(file, np.uint8), np.array([at]), np.array([stop]))[0]
    if int(crc) != int.from_bytes(file[stop : stop + 2], "big"):
        raise ValueError("frame checksum")
    return heard, stop + 2


def decode_stream(file: bytes) -> tuple[bytes, list[tuple[int, int, int]]]:
    """(interleaved little-endian signed samples of whole bytes, blocks as (sample offset, byte offset, samples))."""
    info = stream_info(file)
    wide, at, done, parts, blocks = (info.bits + 7) // 8, info.frames, 0, [], []
    while at < len(file):
        heard, end = _frame(file, at, info, len(blocks), done)
        samples = np.array(heard, "<i8").T.ravel()
        if len(samples) and not -(1 << (info.bits - 1)) <= samples.min() <= samples.max() < 1 << (info.bits - 1):
            raise ValueError("sample out of range")
        parts.append(samples.view(np.uint8).reshape(-1, 8)[:, :wide].tobytes())
        blocks.append((done, at, len(heard[0])))
        done, at = done + len(heard[0]), end
    payload = b"".join(parts)
    if (info.total and done != info.total) or (any(info.md5) and hashlib.md5(payload).digest() != info.md5):
        raise ValueError("stream checksum")
    return payload, blocks
