import itertools
import time

import numpy as np
import pytest

from relmix.llm import html_main

TREES = [
    "<div><p>a</p><div><p>b</p></div></div><ul><li>c</li></ul>",
    "text <section>more<p>a longer paragraph</p>tail<ul><li>x</li><li>y z</li></ul></section> end",
    "<article><h1>t</h1><div hidden><p>never</p><p>shown</p></div><p>b</p></article>",
]


@pytest.mark.parametrize("page", TREES)
def test_decoding_is_the_best_consistent_choice(page):
    nodes = html_main.ordered(html_main.parse(page))
    own = np.array([len(" ".join("".join(p for p in n.parts if isinstance(p, str)).split())) for n in nodes], float)
    weight = np.where(own > 0, np.sqrt(own), 0.25)
    rng = np.random.default_rng(len(page))
    for _ in range(40):
        odds = rng.normal(0, 3, len(nodes))
        keep = html_main.decide(nodes, odds, own)
        for n in nodes[1:]:
            if keep[n.index]:
                assert keep[n.parent.index] and not n.hidden
        best = max(
            sum((odds * weight)[[0, *marks]])
            for size in range(len(nodes))
            for marks in itertools.combinations(range(1, len(nodes)), size)
            if all(not nodes[i].hidden and nodes[i].parent.index in (0, *marks) for i in marks)
        )
        assert np.isclose(sum((odds * weight)[keep]), best)
        shown = html_main.text_of(nodes, keep)
        want = " ".join(" ".join("".join(n.parts).split()) for n in nodes if keep[n.index] and not n.children)
        assert shown == " ".join(want.split())


def test_text_stands_in_leaves_alone():
    for page in TREES:
        for node in html_main.ordered(html_main.parse(page)):
            assert not (node.children and any(isinstance(p, str) for p in node.parts))


PAGES = {
    "Hello, this is plain text without tags.": "Hello, this is plain text without tags.",
    "<body>Some text straight in it.</body>": "Some text straight in it.",
    "<body><h1>A title</h1>Some text of it<br>and more text</body>": "A title Some text of it and more text",
    "<head><title>T</title><p>text of the page</p>": "text of the page",
    "<head>text of the page<title>T</title></head><p>and more of it": "text of the page and more of it",
    "<body><noscript><article><h1>Title here</h1><p>The article inside, with a few words of prose to read.</p></article></noscript></body>": "Title here The article inside, with a few words of prose to read.",
    "<article><p>Since <math><mi>x</mi><mo>=</mo><mn>2</mn><annotation>x=2</annotation></math> holds, we can go on with the rest of the proof.</p></article>": "Since x=2 holds, we can go on with the rest of the proof.",
    '<article><p title="abc>The first paragraph goes on for some while.</p><p class="x">The second one, also long enough to read.</p></article>': "The first paragraph goes on for some while. The second one, also long enough to read.",
    "<article><p title='a > b' class=y>The first paragraph goes on for some while.</p></article>": "The first paragraph goes on for some while.",
    "<article><object>Some text that stands in place of the object.</object><p>The rest of the article goes on and on.</p></article>": "Some text that stands in place of the object. The rest of the article goes on and on.",
    "<article><p>The text that a sample follows, as it is written:</p><xmp>1 < 2 &amp; <b></xmp></article>": "The text that a sample follows, as it is written: 1 < 2 &amp; <b>",
}


def test_whole_article_of_odd_layouts():
    got = html_main.extract_many(list(PAGES), html_main.trained())
    assert dict(zip(PAGES, got, strict=True)) == PAGES


def test_long_pages_repeated_rows_and_clashing_columns(spark):
    paragraph = "The river rose again in spring and the old town had to move its market to the hill. "
    long = "<article>" + f"<p>{paragraph * 4}</p>" * 3000 + "</article>"
    broken = '<p title="abc>' * 20_000 + "'\"" * 20_000 + ">" + "<a '" * 20_000
    rows = [(1, "u", long, "x"), (1, "u", long, "x"), (None, None, broken, "y")]
    pages = spark.createDataFrame(rows, "page_id bigint, url string, html string, main_text string")
    began = time.time()
    out = html_main.extract(pages)
    got = [r.main_text for r in out.collect()]
    assert time.time() - began < 120
    assert out.columns == ["page_id", "url", "html", "main_text"]
    assert got[0] == got[1] == " ".join([(paragraph * 4).strip()] * 3000)


def test_unseen_layouts_are_whole():
    model, writer, right, total = html_main.trained(), html_main._Writer(98765), 0, 0
    for _ in range(200):
        read = html_main.read_roles(writer.page())
        if read:
            nodes, roles = read
            x, own = html_main.features(nodes)
            right += html_main.text_of(nodes, html_main.decide(nodes, model.log_odds(x), own)) == html_main.text_of(nodes, roles.astype(bool))
            total += 1
    assert total > 180 and right / total > 0.97
