"""Streams that this package's encoder never writes, built bit by bit here, and its own files read a second way."""

import hashlib
import random

import numpy as np
import pytest

from relmix.llm import flac, flac_streams


def crc(data, bits, poly):
    value = 0
    for byte in data:
        for i in range(7, -1, -1):
            top = value >> (bits - 1) & 1
            value = (value << 1) & ((1 << bits) - 1)
            if top ^ (byte >> i & 1):
                value ^= poly
    return value


def field(value, n):
    return format(value & ((1 << n) - 1), f"0{n}b") if n else ""


def rice(e, k):
    u = 2 * e if e >= 0 else -2 * e - 1
    return "0" * (u >> k) + "1" + field(u, k)


def residuals(values, order, size, form, parts):
    out = field({"rice": 0, "escape": 0, "rice5": 1, "escape5": 1}[form], 2) + field(parts, 4)
    width, at = (5 if form.endswith("5") else 4), 0
    for p in range(1 << parts):
        n = (size >> parts) - (order if p == 0 else 0)
        own, at = values[at : at + n], at + n
        if form.startswith("escape"):
            raw = max([0, *(e.bit_length() + 1 for e in own if e)])
            out += field(-1, width) + field(raw, 5) + "".join(field(e, raw) for e in own)
        else:
            k = max([0, *(abs(e).bit_length() for e in own)])
            k = min(k, (1 << width) - 2)
            out += field(k, width) + "".join(rice(e, k) for e in own)
    return out


def subframe(x, bits, kind, form="rice", parts=0, wasted=0):
    x = [v >> wasted for v in x]
    bits -= wasted
    flag = "1" + "0" * (wasted - 1) + "1" if wasted else "0"
    if kind == "verbatim":
        return "0" + field(1, 6) + flag + "".join(field(v, bits) for v in x)
    if kind == "constant":
        return "0" + field(0, 6) + flag + field(x[0], bits)
    if kind == "linear":
        weights, shift = [7, -4], 2
        e = [x[i] - ((7 * x[i - 1] - 4 * x[i - 2]) >> shift) for i in range(2, len(x))]
        return "0" + field(33, 6) + flag + "".join(field(v, bits) for v in x[:2]) + field(4, 4) + field(shift, 5) + "".join(field(w, 5) for w in weights) + residuals(e, 2, len(x), form, parts)
    order, e = int(kind), np.array(x, object)
    for _ in range(order):
        e = np.diff(e)
    return "0" + field(8 + order, 6) + flag + "".join(field(v, bits) for v in x[:order]) + residuals([int(v) for v in e], order, len(x), form, parts)


def number(n):
    return chr(n).encode("utf-8", "surrogatepass")


def frame(channels, bits, at, variable, layout, writers):
    size = len(channels[0])
    code = {8: 1, 12: 2, 16: 4, 20: 5, 24: 6, 32: 7}.get(bits, 0)
    head = bytes([0xFF, 0xF9 if variable else 0xF8, 0x7D, layout << 4 | code << 1]) + number(at) + (size - 1).to_bytes(2, "big") + (44).to_bytes(2, "big")
    head += bytes([crc(head, 8, 0x07)])
    wide = [bits] * len(channels)
    if layout >= 8:
        a, b = channels
        d = [u - v for u, v in zip(a, b)]
        channels = {8: [a, d], 9: [d, b], 10: [[(u + v) >> 1 for u, v in zip(a, b)], d]}[layout]
        wide[0 if layout == 9 else 1] += 1
    body = "".join(subframe(x, w, *how) for x, w, how in zip(channels, wide, writers))
    body += "0" * (-len(body) % 8)
    head += int(body, 2).to_bytes(len(body) // 8, "big")
    return head + crc(head, 16, 0x8005).to_bytes(2, "big")


def stream(frames, bits, variable=False, layout=None, writers=None):
    """frames: per frame a list of channels. (file, PCM as interleaved little-endian bytes)."""
    n = len(frames[0])
    wide = (bits + 7) // 8
    pcm = b"".join(int(v).to_bytes(wide, "little", signed=True) for f in frames for row in zip(*f) for v in row)
    total = sum(len(f[0]) for f in frames)
    info = (16).to_bytes(2, "big") + (65535).to_bytes(2, "big") + bytes(6) + (44100 << 44 | (n - 1) << 41 | (bits - 1) << 36 | total).to_bytes(8, "big") + hashlib.md5(pcm).digest()
    out, done = b"fLaC" + bytes([0x80, 0, 0, 34]) + info, 0
    for i, f in enumerate(frames):
        out += frame(f, bits, done if variable else i, variable, n - 1 if layout is None else layout, writers)
        done += len(f[0])
    return out, pcm


def noise(rng, n, bits, step=40):
    top, x, out = 1 << (bits - 1), 0, []
    for _ in range(n):
        x = max(-top, min(top - 1, x + rng.randint(-step, step)))
        out.append(x)
    return out


@pytest.mark.parametrize("form", ["rice", "rice5", "escape", "escape5"])
@pytest.mark.parametrize("kind", ["0", "1", "2", "3", "4", "linear", "verbatim"])
def test_mono_forms(kind, form):
    rng = random.Random(kind + form)
    for bits, parts in ((8, 0), (16, 2), (24, 3)):
        file, pcm = stream([[noise(rng, 64, bits)] for _ in range(3)], bits, writers=[(kind, form, parts)])
        assert flac_streams.decode_stream(file)[0] == pcm


@pytest.mark.parametrize("layout", [1, 8, 9, 10])
@pytest.mark.parametrize("variable", [False, True])
def test_stereo_layouts_and_block_sizes(layout, variable):
    rng = random.Random(layout)
    sizes = [100, 7000, 24, 300] if variable else [128, 128, 50]
    frames = [[noise(rng, n, 16), noise(rng, n, 16)] for n in sizes]
    file, pcm = stream(frames, 16, variable, layout, [("2", "rice"), ("1", "rice5")])
    payload, blocks = flac_streams.decode_stream(file)
    assert payload == pcm and [b[2] for b in blocks] == sizes and [b[0] for b in blocks] == np.cumsum([0, *sizes[:-1]]).tolist()


def test_wasted_bits_constants_and_many_channels():
    rng = random.Random(9)
    shifted = [v << 3 for v in noise(rng, 96, 13)]
    file, pcm = stream([[shifted, [5] * 96, noise(rng, 96, 16)]], 16, writers=[("1", "rice", 1, 3), ("constant",), ("verbatim",)])
    assert flac_streams.decode_stream(file)[0] == pcm


def test_operator_reads_foreign_streams_and_says_no_to_damage(spark):
    rng = random.Random(4)
    stereo, pcm = stream([[noise(rng, 5000, 16), noise(rng, 5000, 16)], [noise(rng, 70, 16), noise(rng, 70, 16)]], 16, layout=10, writers=[("2", "rice"), ("1", "escape")])
    small, low = stream([[noise(rng, 30000, 8, 3)]], 8, writers=[("1", "escape", 2)])
    bad = bytearray(stereo)
    bad[len(bad) // 2] ^= 4
    rows = [(1, stereo), (2, small), (3, bytes(bad)), (4, stereo[:-9]), (5, None), (6, b"fLaC")]
    done = flac.decode(spark.createDataFrame([(i, bytearray(f) if f is not None else None) for i, f in rows], "doc_id bigint, flac binary"))
    got = {r.doc_id: r for r in done.collect()}
    assert bytes(got[1].payload) == pcm and got[1].feature is None
    assert bytes(got[2].payload) == bytes((b + 128) % 256 for b in low) and got[2].feature
    assert [got[i].valid for i in range(1, 7)] == [True, True, False, False, False, False]
    blocks = sorted((b.id, b.sample_offset, bytes(b.block)) for b in flac.pcm_blocks(done).collect())
    assert b"".join(b for i, _, b in blocks if i == 1) == pcm and [len(b) for i, _, b in blocks if i == 1] == [20000, 280]


def test_own_files_read_a_second_way():
    rng = np.random.default_rng(1)
    payloads = [flac.payload_of(x) for x in (b"", bytes(9000), b"word and word, " * 700, rng.bytes(5000), (128 + 90 * np.sin(np.arange(9000) / 11)).astype(np.uint8).tobytes())]
    for payload, file in zip(payloads, flac.encode_payloads(payloads)):
        signed, blocks = flac_streams.decode_stream(file)
        assert bytes((b + 128) % 256 for b in signed) == payload
        assert flac.decode_files([file])[0] == (payload, blocks)
