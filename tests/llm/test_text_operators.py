import base64
import hashlib
import os
import random
import struct

import numpy as np
import public_tokenizers
import pytest
import sentencepiece
import tiktoken

from relmix.llm import bpe, flac, html_main, licenses, quality, token_counts, toxicity
from relmix.session import scratch

RANKS = public_tokenizers.path("byte_bpe_50k.tiktoken")
TEXTS = ["", None, "a", "It's we'll they've 'tis ''s", "  two  blanks\n\n tabs\t\tend  ", "naïve 中文 😀 ٣²", "x" * 5000, "word " * 20000, "it's 's"]


def docs(spark, texts, extra="ids string"):
    return spark.createDataFrame([(i, t, "clash") for i, t in enumerate(texts)], f"doc_id bigint, text string, {extra}")


@pytest.fixture(scope="module")
def library():
    with open(RANKS, "rb") as f:
        ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
    return tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})


def test_bpe_equals_library(spark, library):
    rows = bpe.decode(bpe.encode(docs(spark, TEXTS), RANKS), RANKS).collect()
    assert len(rows) == len(TEXTS)
    for r in rows:
        ids = library.encode_ordinary(TEXTS[r.doc_id] or "")
        assert r.ids == struct.pack(f"<{len(ids)}I", *ids) and r.n_tokens == len(ids)
        assert bytes(r.decoded) == (TEXTS[r.doc_id] or "").encode()


def test_bpe_random_strings(library):
    rng = random.Random(3)
    parts = ["'", "s", "re", "ll", "d", " ", "  ", "\n", "a", "Zed", "é", "1", "²", "!", "中", "😀", " ", "\x85", "_"]
    cache = bpe.PieceCache(bpe.load_ranks(RANKS), most=50)
    for _ in range(60):
        texts = ["".join(rng.choice(parts) for _ in range(rng.randint(0, 40))) for _ in range(15)]
        for text, (ids, offsets) in zip(texts, bpe.encode_texts(texts, cache), strict=True):
            want = library.encode_ordinary(text)
            assert ids == struct.pack(f"<{len(want)}I", *want)
            assert len(offsets) == 0 or offsets[0] == 0


def test_bpe_scan_equals_sequential_automaton():
    classes = np.random.default_rng(0).integers(0, 12, 5000).astype(np.uint8)
    state, want = bpe.AT_START, []
    for c in classes:
        state = bpe._next_state(state, int(c))
        want.append(state)
    assert bpe.scan_states(classes).tolist() == want


def test_bpe_ranges():
    text = "some text with naïve words and 中文 in it".encode()
    table = bpe.token_bytes(RANKS)
    ids = bpe.encode_texts([text.decode()], bpe.PieceCache(bpe.load_ranks(RANKS)))[0][0]
    for a in range(0, len(text), 3):
        for b in range(a + 1, len(text), 5):
            assert bpe.decode_range(ids, table, a, b) == text[a:b]


@pytest.mark.parametrize("name", ["piece_bpe_32k.model", "byte_bpe_50k.json"])
def test_token_counts_and_cache(spark, name):
    path = public_tokenizers.path(name)
    cache = token_counts.TokenCountCache(spark, scratch(spark, "counts-test"), path)
    texts = [*TEXTS, "a", "<unk> <s>"]
    got = {r.id: (r.n_bytes, r.n_tokens) for r in cache.count(docs(spark, texts)).collect()}
    if name.endswith(".model"):
        sp = sentencepiece.SentencePieceProcessor(model_file=path)
        for i, t in enumerate(texts):
            assert got[i] == (len((t or "").encode()), len(sp.encode(t or "")))
    assert cache.rows().count() == len({t or "" for t in texts})
    more = {r.id: r.n_tokens for r in cache.count(docs(spark, [*texts, "new text here"])).collect()}
    assert all(more[i] == got[i][1] for i in got) and cache.rows().count() == len({t or "" for t in texts}) + 1
    assert cache.count(docs(spark, [])).collect() == []


def test_flac_round_trip_and_ranges(spark):
    texts = ["", None, "x", "word and word. " * 900, "é" * 4000, "a" * 9000]
    done = flac.decode(flac.encode(spark.createDataFrame(list(enumerate(texts)), "doc_id bigint, text string")))
    rows = done.collect()
    for r in rows:
        want = flac.payload_of((texts[r.doc_id] or "").encode())
        assert r.valid and bytes(r.payload) == want and len(want) % 64 == 0 and len(want) >= 64
        assert flac.read_range(bytes(r.flac), 10, 4200) == want[10:4200]
        assert [b.sample_offset for b in r.pcm] == list(range(0, len(want), 4096))
    blocks = sorted((b.id, b.sample_offset, bytes(b.block)) for b in flac.pcm_blocks(done).collect())
    assert b"".join(b for i, _, b in blocks if i == 3) == flac.payload_of(texts[3].encode())
    assert flac.encode(spark.createDataFrame([], "doc_id bigint, text string")).collect() == []


def test_flac_forms_and_damage():
    rng = np.random.default_rng(2)
    wave = (128 + 100 * np.sin(np.arange(12000) / 9)).astype(np.uint8).tobytes()
    payloads = [flac.payload_of(x) for x in (wave, os.urandom(6000), bytes(5000), bytes(range(256)) * 30, (np.cumsum(rng.integers(-1, 2, 9000)) % 256).astype(np.uint8).tobytes())]
    files = flac.encode_payloads(payloads)
    assert [p for p, _ in flac.decode_files(files)] == payloads
    assert len(files[0]) < len(payloads[0]) * 0.6 and len(files[2]) < 200
    for at in (4, 50, len(files[0]) // 2, len(files[0]) - 1):
        bad = bytearray(files[0])
        bad[at] ^= 0x11
        assert flac.decode_files([bytes(bad)])[0][0] in (None, payloads[0])
    bad = bytearray(files[0])
    bad[len(bad) // 2] ^= 1
    assert flac.decode_files([bytes(bad), None, b"", files[1][:90]]) == [(None, [])] * 4
    # without its seek table a file is read frame by frame
    table = len(files[0]) and int.from_bytes(files[0][43:46], "big")
    bare = files[0][:4] + bytes([0x80]) + files[0][5:42] + files[0][46 + table :]
    assert flac.decode_files([bare])[0][0] == payloads[0]


def test_flac_checksums():
    assert flac.crc8(b"123456789") == 0xF4
    data = np.frombuffer(b"123456789", np.uint8)
    assert flac.crc16_many(data, np.array([0]), np.array([9])).tolist() == [0xFEE8]


PAGE = """<!DOCTYPE html><html><head><title>T</title><style>p{}</style><script>var x="</p>";</script></head><body>
<nav><ul><li><a href="/a">Home page</a></li><li><a href="/b">News list</a></li><li><a href="/c">Other</a></li></ul></nav>
<div class="cookie-notice">We use cookies to make this site work for you.<button>OK</button></div>
<article><h1>A title of the  story</h1><p>First &amp; <b>bold</b>est paragraph of the story, long enough to be read as prose by anyone.
<p>Second paragraph with a <a href="x">link</a> inside; it also goes on for a while, as prose does. And on.</p><div class="ad">Buy this thing now, cheap.</div>
<p>Third paragraph<br>after a break, closing the story with a few more words of prose.</p></article>
<section class="comments"><h2>Comments</h2><div class="comment"><p>I liked this a lot, thanks for it all.</p></div></section>
<form><label>Mail</label><input name="m"><p>Sign up for letters.</p></form><footer>&copy; 2024 Somebody, all words reserved.</footer></body></html>"""


def test_html_main_text(spark):
    pages = spark.createDataFrame([(1, "u", PAGE), (2, "u", None), (3, "u", ""), (4, "u", "<p>unclosed <b>text"), (5, "u", PAGE)], "page_id bigint, url string, html string")
    got = {r.page_id: r.main_text for r in html_main.extract(pages).collect()}
    want = "A title of the story First & boldest paragraph of the story, long enough to be read as prose by anyone. Second paragraph with a link inside; it also goes on for a while, as prose does. And on. Third paragraph after a break, closing the story with a few more words of prose."
    assert got[1] == want == got[5] and got[2] == got[3] == ""
    assert html_main.extract(pages.limit(0)).collect() == []


def test_html_held_out_pages_and_consistency():
    model = html_main.trained()
    writer = html_main._Writer(4321)
    right = total = 0
    for _ in range(120):
        page = writer.page()
        truth = [int(m) for m in html_main._MARK.findall(page)]
        nodes = html_main.ordered(html_main.parse(html_main._MARK.sub("", page)))
        if len(nodes) - 1 != len(truth):
            continue
        x, own = html_main.features(nodes)
        show = html_main.decide(nodes, model.log_odds(x), own)
        total += 1
        right += html_main.text_of(nodes, show) == html_main.text_of(nodes, np.array([False, *map(bool, truth)]))
    assert right / total > 0.9


def test_toxicity_patterns():
    matcher = toxicity.Matcher(toxicity.Model())

    def kinds(text):
        return [k for _, _, k in matcher.clauses(text)]

    assert kinds("You are an idiot. Fine day") == ["insult_aimed"]
    assert kinds("what an IDIOT move") == ["insult_plain"]
    assert kinds("this is not a stupid plan") == ["insult_negated"]
    assert kinds('she said "moron" aloud') == ["insult_reported"]
    assert kinds("i will kill you; idiotic") == ["threat_aimed"]
    assert kinds("idiotically worded, trashing") == [] and kinds("") == []
    assert kinds("don't be stupid! loser") == ["insult_negated", "insult_plain"]


def test_toxicity_learns_words_and_stems(spark):
    rng = random.Random(8)
    plain = ["lorem", "ipsum", "dolor", "amet", "sit", "tempor", "magna", "aliqua", "minim", "veniam"]
    rows, marks = [], []
    for i in range(600):
        w = [rng.choice(plain) + rng.choice(["", "a", "us"]) for _ in range(30)]
        if i % 6 == 0:
            for _ in range(3):
                w.insert(rng.randrange(30), rng.choice(["zorgblat" + rng.choice("abcdefgh"), "quux"]))
        rows.append((i, " ".join(w)))
        marks.append((i, int(i % 6 == 0)))
    df = spark.createDataFrame([*rows, (None, "x"), (700, None)], "doc_id bigint, text string")
    model = toxicity.learn(df, spark.createDataFrame([*marks, (None, 1), (1, None)], "doc_id bigint, toxic int"))
    scored = {r.doc_id: r.toxicity for r in toxicity.score(df, model).collect()}
    assert all((scored[i] >= 0.5) == bool(t) for i, t in marks) and scored[700] < 0.5
    empty = spark.createDataFrame([], "doc_id bigint, toxic int")
    assert toxicity.learn(df, empty).words == toxicity.INSULTS
    assert toxicity.score(df.limit(0), model).collect() == []


def test_licenses(spark):
    bsd3 = ". ".join(licenses.SENTENCES[s].capitalize() for s in ["bsd.use", "bsd.source", "bsd.binary", "bsd.endorse", "bsd.warranty"])
    texts = ["Licensed under the Apache License, Version 2.0.\nbody", "body text. All rights reserved", None, "", bsd3 + ".", "Released under the MIT License! Released under the MIT License", "nothing here"]
    got = {r.id: (r.licenses, r.n_sentences) for r in licenses.scan(docs(spark, texts, "licenses string")).collect()}
    assert got == {0: (["Apache-2.0"], 1), 1: (["all-rights-reserved"], 1), 4: (["BSD-3-Clause"], 5), 5: (["MIT"], 2)}
    assert licenses.scan(docs(spark, [])).collect() == []


def test_licenses_plan_has_no_python(spark):
    plan = licenses.scan(docs(spark, ["x"]))._jdf.queryExecution().toString()
    assert "Python" not in plan and "Arrow" not in plan and "MapIn" not in plan


def test_quality_shrinks_sparse_sites(spark):
    rng = random.Random(5)
    good = lambda: " ".join(rng.choice(["plain", "words", "of", "prose", "here", "and", "there"]) + rng.choice("abcdef") for _ in range(60))
    bad = lambda: " ".join(rng.choice(["LOUD!!", "NOISE!!", "BUY!!"]) for _ in range(60))
    rows, marks = [], []
    for i in range(400):
        host = "clean" if i < 200 else "spam"
        fine = i < 200 or i % 10 == 0
        rows.append((i, good() if fine else bad(), host, "p"))
        marks.append((i, int(fine)))
    rows += [(900, good(), "clean", "p"), (901, good(), "spam", "p"), (902, good(), "new", "q"), (903, None, None, None)]
    df = spark.createDataFrame(rows, "doc_id bigint, text string, source string, lang string")
    weights = quality.fit(df, spark.createDataFrame(marks, "doc_id bigint, quality int"))
    got = {r.id: r for r in quality.judge(df, weights).collect()}
    assert len(got) == len(rows)
    assert got[900].site_quality > got[902].site_quality > got[901].site_quality
    assert all(got[i].kept == bool(k) for i, k in marks)
    assert quality.judge(df.limit(0), weights).collect() == []
    assert (quality.fit(df, spark.createDataFrame([], "doc_id bigint, quality int")) == quality.START).all()


def test_hash_is_not_needed_for_equal_media():
    a, b = flac.encode_payloads([flac.payload_of(b"same"), flac.payload_of(b"same")])
    assert hashlib.sha256(a).digest() == hashlib.sha256(b).digest()


NOTICES = {
    "MIT": """Permission is hereby granted, free of charge, to any person obtaining a copy
of this software and associated documentation files (the "Software"), to deal
in the Software without restriction, including without limitation the rights
to use, copy, modify, merge, publish, distribute, sublicense, and/or sell
copies of the Software, and to permit persons to whom the Software is
furnished to do so, subject to the following conditions:

The above copyright notice and this permission notice shall be included in all
copies or substantial portions of the Software.

THE SOFTWARE IS PROVIDED "AS IS", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR
IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY,
FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE
AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM.""",
    "Apache-2.0": """Licensed under the Apache License, Version 2.0 (the "License");
you may not use this file except in compliance with the License.
You may obtain a copy of the License at

    http://www.apache.org/licenses/LICENSE-2.0

Unless required by applicable law or agreed to in writing, software
distributed under the License is distributed on an "AS IS" BASIS,
WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied.
See the License for the specific language governing permissions and
limitations under the License.""",
    "GPL-3.0-or-later": """This program is free software: you can redistribute it and/or modify
it under the terms of the GNU General Public License as published by
the Free Software Foundation, either version 3 of the License, or
(at your option) any later version.

This program is distributed in the hope that it will be useful,
but WITHOUT ANY WARRANTY; without even the implied warranty of
MERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE.  See the
GNU General Public License for more details.""",
    "MPL-2.0": """This Source Code Form is subject to the terms of the Mozilla Public
License, v. 2.0. If a copy of the MPL was not distributed with this
file, You can obtain one at https://mozilla.org/MPL/2.0/.""",
    "BSD-3-Clause": """Redistribution and use in source and binary forms, with or without
modification, are permitted provided that the following conditions are met:

1. Redistributions of source code must retain the above copyright notice, this
   list of conditions and the following disclaimer.

2. Redistributions in binary form must reproduce the above copyright notice,
   this list of conditions and the following disclaimer in the documentation
   and/or other materials provided with the distribution.

3. Neither the name of the copyright holder nor the names of its
   contributors may be used to endorse or promote products derived from
   this software without specific prior written permission.

THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS "AS IS"
AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE
IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE
DISCLAIMED. IN NO EVENT SHALL THE COPYRIGHT HOLDER BE LIABLE.""",
    "ISC": """Permission to use, copy, modify, and/or distribute this software for any
purpose with or without fee is hereby granted, provided that the above
copyright notice and this permission notice appear in all copies.""",
}
NOTICES["GPL-2.0-or-later"] = NOTICES["GPL-3.0-or-later"].replace("software: you", "software; you").replace("version 3", "version 2")


def test_licenses_of_wrapped_notices(spark):
    ways = ["", "# ", " * ", "// ", "dnl ", "REM "]
    texts = ["int a;\n" + end.join((way + line).rstrip() for line in text.split("\n")) + end + "b = 2" for text in NOTICES.values() for way in ways for end in ("\n", "\r\n")]
    want = [name for name in NOTICES for _ in range(2 * len(ways))]
    got = {r.id: (r.licenses, r.n_sentences) for r in licenses.scan(docs(spark, texts)).collect()}
    n = {"MIT": 3, "Apache-2.0": 4, "BSD-3-Clause": 5, "ISC": 1}
    assert got == {i: ([name], n.get(name, 2)) for i, name in enumerate(want)}


def test_licenses_known_sentences_are_reachable_and_kept_apart(spark):
    assert all(any(a in s for a in licenses.ANCHORS) for s in licenses.SENTENCES.values())
    assert not any(f" {a} " in f" {b} " for a in licenses.SENTENCES.values() for b in licenses.SENTENCES.values() if a != b)
    texts = [s.replace(" ", "\n# ") for s in licenses.SENTENCES.values()]
    got = {r.id: r.sequence for r in licenses.scan(docs(spark, texts)).collect()}
    assert got == {i: [sid] for i, sid in enumerate(licenses.SENTENCES)}
    apart = ["not licensed under the MIT license", "Licensed under\n\nthe MIT license.", "licensed under the MIT license or another"]
    assert licenses.scan(docs(spark, apart)).collect() == []


def test_main_text_loose_in_body_and_head_without_end():
    one = "The river rose again in spring and the old town had to move its market to the hill. " * 4
    two = "Nobody had seen so much water since the bridge was built, said the keeper of the mill. " * 4
    flat = " ".join(one.split()), " ".join(two.split())
    pages = [
        f"<html><body>{one}<br><br>{two}</body></html>",
        f"<body><span>{one}</span> <b>{two}</b><div class='footer'><a href='#'>Legal</a></div></body>",
        f"{one}\n{two}",
        f"<!doctype html><head><title>x</title><meta charset=utf-8><article><p>{one}</p><p>{two}</p></article>",
    ]
    assert html_main.extract_many(pages, html_main.trained()) == [" ".join(flat)] * 4
    bar = "<body>" + " ".join(f"<a href='/{i}'>Section {i}</a>" for i in range(8)) + f"<p>{one}</p><p>{two}</p></body>"
    assert html_main.extract_many([bar, "<head><title>only</title>", " \n "], html_main.trained()) == [" ".join(flat), "", ""]
