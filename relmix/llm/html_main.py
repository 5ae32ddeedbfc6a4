"""Main text of web pages by gradient-boosted trees over DOM nodes with hierarchical decoding.

A page becomes a tree of block elements; text that stands beside blocks in one element, or in none, gets
a paragraph of its own, so text is in leaves alone. Every node gets features: tag, words in its attributes,
what its ancestors are, depth, place among and likeness to its siblings, and densities of its whole
subtree (text, links, tags, list items, form fields, stops). Boosted regression trees turn them into
the log-odds that the node belongs to the article. Decoding chooses keep or drop for the whole tree
at once: a dropped node drops everything below it, so no kept node ever stands under a dropped one;
among these consistent choices a dynamic program takes the one with the greatest total log-odds,
weighted by text. What is kept is shown, whole; what is dropped is not.

The trees are trained here, on pages that a generator of this module builds from many layouts with
known roles; no page of a corpus and no label of it is used. Training is seeded and takes a few
seconds on the driver; the model is a few kilobytes and travels with the tasks.

Defined cases: null and empty html give an empty text; an empty table gives an empty one; broken markup
is read leniently (stray end tags are ignored, paragraphs and list items close each other, open elements
close at the end, a quote that no attribute's end closes is a plain sign, so its tag ends at the next
``>``); scripts, styles, templates, markup comments, frames, text fields, hidden elements and the head
never give text, while formulas, drawings' labels, fallback contents and ``noscript`` are read like any
other; character references are decoded as HTML5 does; a page of any length is read whole; repeated rows
give repeated results; log-odds of 0 drop; an input column named like the output is replaced.
"""

from __future__ import annotations

import html as html_lib
import random
import re
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from relmix.llm.columns import replaced, small_batches
from relmix.llm.workers import tidy

#: Element groups of HTML.
VOID = {"area", "base", "br", "col", "embed", "hr", "img", "input", "link", "meta", "param", "source", "track", "wbr"}
RAW = {"script", "style", "textarea", "title", "template", "iframe", "noembed", "noframes", "annotation", "annotation-xml", "desc", "metadata"}
BLOCKS = {"html", "body", "article", "section", "div", "main", "nav", "header", "footer", "aside", "form", "fieldset", "p", "h1", "h2", "h3", "h4", "h5", "h6", "ul", "ol", "li", "dl", "dt", "dd", "table", "thead", "tbody", "tfoot", "tr", "td", "th", "caption", "blockquote", "pre", "figure", "figcaption", "address", "details", "summary", "dialog", "hgroup", "menu", "search", "center", "noscript", "button", "select", "option", "label"}
#: Elements of the head; any other one ends it, as its end tag and <body> do.
HEAD = {"html", "head", "title", "meta", "link", "base", "style", "script", "noscript", "template"}
#: Blocks that stand in a line of text.
IN_LINE = {"button", "select", "option", "label"}
CLOSES_P = BLOCKS - {"html", "body", "noscript", "button", "select", "option", "label", "td", "th", "tr", "tbody", "thead", "tfoot", "caption", "li", "dt", "dd"} | {"hr"}
TAGS = ["article", "main", "section", "div", "p", "h1", "h2", "h3", "ul", "ol", "li", "table", "td", "blockquote", "pre", "figure", "nav", "header", "footer", "aside", "form", "button", "dialog", "address", "details", "figcaption"]
#: Words of class, id and role attributes by what they tell.
HINTS = {
    "ad": {"ad", "ads", "adv", "advert", "advertisement", "advertising", "adsbygoogle", "sponsor", "sponsored", "promo", "promotion", "banner", "adbox", "adslot", "dfp"},
    "nav": {"nav", "navbar", "navigation", "menu", "menubar", "breadcrumb", "breadcrumbs", "crumbs", "pagination", "pager", "tabs", "toolbar", "skip", "toc"},
    "head": {"header", "masthead", "topbar", "logo", "branding", "hero", "site"},
    "foot": {"footer", "foot", "copyright", "contentinfo", "legal", "imprint", "colophon", "bottom"},
    "side": {"sidebar", "side", "aside", "complementary", "widget", "rail", "related", "recommended", "recommendations", "trending", "popular", "more", "teaser", "tags", "tagcloud"},
    "notice": {"cookie", "cookies", "consent", "gdpr", "notice", "alert", "popup", "modal", "overlay", "newsletter", "subscribe", "subscription", "signup", "paywall", "dialog", "alertdialog", "toast", "message", "warning"},
    "comment": {"comment", "comments", "commentlist", "respond", "reply", "replies", "disqus", "discussion", "thread", "reviews", "review", "feedback"},
    "share": {"share", "sharing", "social", "facebook", "twitter", "follow", "print", "rating", "byline", "meta", "author", "timestamp"},
    "form": {"form", "search", "searchbox", "login", "contact", "input", "field"},
    "main": {"article", "content", "main", "post", "entry", "story", "body", "text", "page", "articlebody", "prose", "copy", "maincontent"},
}
_HINT_OF = {w: i for i, (_, words) in enumerate(HINTS.items()) for w in words}

#: A quoted value ends where white space or the tag's end follows its closing quote.
_TAG = re.compile(r"<(?:!--.*?(?:-->|\Z)|![^>]*>|\?[^>]*>|(/?)([a-zA-Z][^\s/>]*)((?>[^>\"']|\"[^\"]*\"(?=[\s/>])|'[^']*'(?=[\s/>])|[\"'])*+)>)", re.S)
_ATTR = re.compile(r"(class|id|role|hidden|style|aria-hidden)(?:\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+)))?", re.I)
_PART = re.compile(r"[a-z]+")
_STOP = re.compile(r"[.!?](?:\s|$)")


class Linked(str):
    """Text inside a link."""


class Node:
    __slots__ = ("tag", "hints", "hidden", "parent", "children", "parts", "index", "tags", "fields", "loose")

    def __init__(self, tag: str, hints: frozenset[int], hidden: bool, parent: Node | None):
        self.tag, self.hints, self.hidden, self.parent = tag, hints, hidden, parent
        self.children: list[Node] = []
        self.parts: list = []  # own text, and the children in their places
        self.index = self.tags = self.fields = 0
        self.loose = False  # a paragraph that no element of the page is


def _hints(attributes: str) -> tuple[frozenset[int], bool]:
    found, hidden = set(), False
    for name, a, b, c in _ATTR.findall(attributes):
        value = (a or b or c).lower()
        low = name.lower()
        if low == "hidden":
            hidden = True
        elif low == "aria-hidden":
            hidden |= value == "true"
        elif low == "style":
            hidden |= "display:none" in value.replace(" ", "")
        else:
            for word in _PART.findall(value):
                if word in _HINT_OF:
                    found.add(_HINT_OF[word])
    return frozenset(found), hidden


def parse(page: str) -> Node:
    """The tree of block elements; inline elements leave their text in the block around them.

    Text beside blocks, or in none, gets a paragraph of its own, up to the next block."""
    root = Node("html", frozenset(), False, None)
    node, at, in_link, end = root, 0, 0, len(page)
    in_head = False
    last_close = page.rfind(">")  # no tag begins beyond it
    while at < end:
        tag = _TAG.search(page, at, last_close + 1) if at <= last_close else None
        text = page[at : tag.start()] if tag else page[at:]
        if text and in_head and not text.isspace():
            in_head = False  # text is no content of a head
        if text and not in_head:
            node.parts.append(Linked(text) if in_link else text)
        if not tag:
            break
        at = tag.end()
        name = tag.group(2)
        if not name:
            if tag.group().startswith("<!--") and not tag.group().endswith("-->"):
                break  # a comment that does not end
            continue
        name = name.lower()
        if tag.group(1):  # an end tag
            if name == "head":
                in_head = False
            elif name == "a":
                in_link = max(in_link - 1, 0)
            elif name in BLOCKS:
                up = node
                while up is not root and up.tag != name:
                    up = up.parent
                if up is not root:
                    node, in_link = up.parent, 0
            continue
        if name not in HEAD:
            in_head = False
        if (name in RAW or name == "xmp") and not tag.group(3).endswith("/"):
            close = re.compile(rf"</{re.escape(name)}\s*>", re.I).search(page, at)
            if name == "xmp":  # shown as it is written
                node.parts.append(html_lib.escape(page[at : close.start() if close else end]))
            at = close.end() if close else end
            node.fields += name == "textarea"
            continue
        if name == "head":
            in_head = True
            continue
        if name == "body":
            in_head = False
            continue
        if name in ("html", "meta", "link", "base"):
            continue
        node.tags += 1
        if name == "a":
            in_link = 1
        elif name in ("br", "hr"):
            node.parts.append(" ")
        elif name in ("input", "select"):
            node.fields += 1
        if name not in BLOCKS:
            continue
        if name in CLOSES_P:
            up = node
            while up is not root and up.tag == "p":
                up = node = up.parent
        if name in ("li", "dt", "dd", "tr", "td", "th", "option"):
            alike = {"li": ("li",), "dt": ("dt", "dd"), "dd": ("dt", "dd"), "tr": ("tr", "td", "th"), "td": ("td", "th"), "th": ("td", "th"), "option": ("option",)}[name]
            up = node
            while up is not root and up.tag not in ("ul", "ol", "dl", "table", "tbody", "thead", "tfoot", "menu", "select", "div", "section", "article"):
                if up.tag in alike:
                    node = up.parent
                    if name != "tr":
                        break
                up = up.parent
        hints, hidden = _hints(tag.group(3)) if tag.group(3) else (frozenset(), False)
        child = Node(name, hints, hidden, node)
        node.parts.append(child)
        node.children.append(child)
        node, in_link = child, 0
    return with_paragraphs(root)


def with_paragraphs(root: Node) -> Node:
    """Runs of text beside blocks, and those of the root, become paragraphs; blank runs there are nothing."""
    for node in ordered(root):
        if not node.children and node is not root:
            continue
        parts: list = []
        run: list[str] = []
        for part in [*node.parts, None]:
            if isinstance(part, str):
                run.append(part)
                continue
            if run and not "".join(run).isspace():
                loose = Node("p", frozenset(), False, node)
                loose.parts, loose.loose = run, True
                parts.append(loose)
            run = []
            if part is not None:
                parts.append(part)
        node.parts, node.children = parts, list(parts)
    return root


def ordered(root: Node) -> list[Node]:
    """Nodes in page order; every node's index is its place."""
    out, stack = [], [root]
    while stack:
        node = stack.pop()
        node.index = len(out)
        out.append(node)
        stack.extend(reversed(node.children))
    return out


N_OWN = len(TAGS) + len(HINTS)
FEATURES = N_OWN + len(HINTS) + 6 + 16


def features(nodes: list[Node]) -> tuple[np.ndarray, np.ndarray]:
    """(feature rows, own text lengths) of a page's nodes."""
    n = len(nodes)
    x = np.zeros((n, FEATURES), np.float32)
    own = np.zeros(n)
    sums = np.zeros((n, 7))  # text, linked text, tags, items, paragraphs, fields, stops
    parent = np.full(n, -1)
    depth = np.zeros(n)
    for i, node in enumerate(nodes):
        texts = [p for p in node.parts if isinstance(p, str)]
        flat = " ".join("".join(texts).split())
        linked = sum(len(p) for p in texts if isinstance(p, Linked))
        own[i] = len(flat)
        sums[i] = (len(flat), min(linked, len(flat)), node.tags, node.tag == "li", node.tag == "p", node.fields, len(_STOP.findall(flat)))
        if node.tag in _TAG_AT:
            x[i, _TAG_AT[node.tag]] = 1
        for h in node.hints:
            x[i, len(TAGS) + h] = 1
        if node.parent is not None:
            j = node.parent.index
            parent[i], depth[i] = j, depth[j] + 1
            # what stands above: attribute words and landmark elements of all ancestors
            x[i, N_OWN : N_OWN + len(HINTS)] = np.maximum(x[j, N_OWN : N_OWN + len(HINTS)], x[j, len(TAGS) : N_OWN])
            base = N_OWN + len(HINTS)
            x[i, base : base + 6] = x[j, base : base + 6]
            mark = _LANDMARK.get(nodes[j].tag)
            if mark is not None:
                x[i, base + mark] = 1
    below = sums.copy()
    for i in range(n - 1, 0, -1):
        below[parent[i]] += below[i]
    total = max(below[0, 0], 1)
    base = N_OWN + len(HINTS) + 6
    text = below[:, 0]
    x[:, base + 0] = np.log1p(text)
    x[:, base + 1] = text / total
    x[:, base + 2] = below[:, 1] / np.maximum(text, 1)
    x[:, base + 3] = text / (1 + below[:, 2])
    x[:, base + 4] = below[:, 3]
    x[:, base + 5] = below[:, 4]
    x[:, base + 6] = below[:, 5]
    x[:, base + 7] = below[:, 6] / np.maximum(text / 100, 1)
    x[:, base + 8] = np.log1p(own)
    x[:, base + 9] = depth
    # share of the page's text that stands before the node
    x[:, base + 10] = (np.cumsum(own) - own) / total
    for node in nodes:
        kids = node.children
        for k, child in enumerate(kids):
            i = child.index
            x[i, base + 11] = k
            x[i, base + 12] = len(kids)
            x[i, base + 13] = k / len(kids)
        if kids:
            alike: dict[str, int] = {}
            for child in kids:
                alike[child.tag] = alike.get(child.tag, 0) + 1
            around = max(sum(below[c.index, 0] for c in kids), 1)
            for child in kids:
                x[child.index, base + 14] = alike[child.tag] / len(kids)
                x[child.index, base + 15] = below[child.index, 0] / around
    return x, own


_TAG_AT = {t: i for i, t in enumerate(TAGS)}
_LANDMARK = {"article": 0, "main": 0, "nav": 1, "header": 2, "footer": 3, "aside": 4, "form": 5, "dialog": 5}


class BoostedTrees:
    """Gradient boosting of depth-limited trees on histogram bins, logistic loss, a seeded share of the rows for each tree."""

    def __init__(self, rounds: int = 120, depth: int = 4, rate: float = 0.2, bins: int = 32, share: float = 0.4, seed: int = 5):
        self.rounds, self.depth, self.rate, self.bins, self.share, self.seed = rounds, depth, rate, bins, share, seed
        self.trees: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
        self.base = 0.0

    def fit(self, x: np.ndarray, y: np.ndarray) -> BoostedTrees:
        edges = [np.unique(np.quantile(x[:, f], np.linspace(0, 1, self.bins + 1)[1:-1])) for f in range(x.shape[1])]
        binned = np.stack([np.searchsorted(e, x[:, f], "left") for f, e in enumerate(edges)], 1)
        rate = y.mean()
        self.base = float(np.log(rate / (1 - rate)))
        score = np.full(len(y), self.base)
        width = self.bins + 1
        flat = binned + np.arange(x.shape[1]) * width
        rng = np.random.default_rng(self.seed)
        for _ in range(self.rounds):
            p = 1 / (1 + np.exp(-score))
            g, h = y - p, p * (1 - p) + 1e-6
            feature = np.full(2 ** (self.depth + 1) - 1, -1)
            cut = np.zeros(2 ** (self.depth + 1) - 1)
            value = np.zeros(2 ** (self.depth + 1) - 1)
            where = np.where(rng.random(len(y)) < self.share, 0, -1)
            for level in range(self.depth + 1):
                for node in range(2**level - 1, 2 ** (level + 1) - 1):
                    rows = np.flatnonzero(where == node)
                    if not len(rows):
                        continue
                    gs, hs = g[rows].sum(), h[rows].sum()
                    value[node] = self.rate * gs / (hs + 1)
                    if level == self.depth or len(rows) < 20:
                        continue
                    at = flat[rows].ravel()
                    gh = np.bincount(at, np.repeat(g[rows], x.shape[1]), width * x.shape[1]).reshape(-1, width).cumsum(1)
                    hh = np.bincount(at, np.repeat(h[rows], x.shape[1]), width * x.shape[1]).reshape(-1, width).cumsum(1)
                    gain = gh**2 / (hh + 1) + (gs - gh) ** 2 / (hs - hh + 1) - gs**2 / (hs + 1)
                    gain[(hh < 1) | (hs - hh < 1)] = 0
                    f, b = np.unravel_index(gain.argmax(), gain.shape)
                    if gain[f, b] < 1e-3 or b >= len(edges[f]):
                        continue
                    feature[node], cut[node] = f, edges[f][b]
                    right = binned[rows, f] > b
                    where[rows] = 2 * node + 1 + right
            self.trees.append((feature, cut, value))
            score += self._one(x, feature, cut, value)
        return self

    def _one(self, x: np.ndarray, feature: np.ndarray, cut: np.ndarray, value: np.ndarray) -> np.ndarray:
        at = np.zeros(len(x), int)
        rows = np.arange(len(x))
        for _ in range(self.depth):
            f = feature[at]
            inner = f >= 0
            at = np.where(inner, 2 * at + 1 + (x[rows, np.maximum(f, 0)] > cut[at]), at)
        return value[at]

    def log_odds(self, x: np.ndarray) -> np.ndarray:
        out = np.full(len(x), self.base)
        for tree in self.trees:
            out += self._one(x, *tree)
        return out


def decide(nodes: list[Node], odds: np.ndarray, own: np.ndarray) -> np.ndarray:
    """Keep marks of greatest total log-odds under: below a dropped or hidden node everything is dropped. The root stays."""
    weight = np.where(own > 0, np.sqrt(own), 0.25)
    best = odds * weight  # of keeping the node, with the best choice for each child
    for i in range(len(nodes) - 1, 0, -1):
        if best[i] > 0 and not nodes[i].hidden:
            best[nodes[i].parent.index] += best[i]
    keep = np.zeros(len(nodes), bool)
    keep[0] = True
    for i in range(1, len(nodes)):
        keep[i] = keep[nodes[i].parent.index] and best[i] > 0 and not nodes[i].hidden
    return keep


def text_of(nodes: list[Node], show: np.ndarray) -> str:
    """Blocks in page order joined by one blank, white space inside a block joined. Text is in nodes without children."""
    texts = (html_lib.unescape("".join(node.parts)) for node in nodes if not node.children and show[node.index])
    return " ".join(filter(None, (" ".join(text.split()) for text in texts)))


# ---------------------------------------------------------------- training pages


_SYLLABLES = "an ber con de en fi ga her is ko la men nor or pa que re sta ti un ver wo za che sch ous tion".split()


#: Signs that a generated page puts into loose text to tell its role; without one it has that of its element.
_ROLES = {"\ue000": 0, "\ue001": 1}


class _Writer:
    """Pages of random layouts; elements carry data-k="1" (article) or data-k="0" (not)."""

    def __init__(self, seed: int):
        self.r = random.Random(seed)

    def word(self) -> str:
        return "".join(self.r.choice(_SYLLABLES) for _ in range(self.r.randint(1, 4)))

    def prose(self, low: int, high: int) -> str:
        words: list[str] = []
        if self.r.random() < 0.1:  # without a stop
            return " ".join(self.word() for _ in range(self.r.randint(low, high)))
        for i in range(self.r.randint(low, high)):
            w = self.word()
            words.append(w.capitalize() if not i or words[-1].endswith(".") else w)
            if self.r.random() < 0.12:
                words[-1] += self.r.choice([".", ",", ".", "&amp;", "!"])
        return " ".join(words) + "."

    def attribute(self, *words: str, chance: float = 0.8) -> str:
        if self.r.random() > chance:
            return ""
        w = self.r.choice(words)
        name = self.r.choice(["class", "class", "id", "class"])
        extra = self.r.choice(["", "", "-box", "-wrap", " " + self.word(), "_inner", "__list"])
        return f' {name}="{w}{extra}"'

    def links(self, n: int, tag: str = "li") -> str:
        rows = "".join(f'<{tag} data-k="0"><a href="/{self.word()}">{self.prose(1, 3)[:-1]}</a></{tag}>' for _ in range(n))
        return f'<ul data-k="0">{rows}</ul>' if tag == "li" else rows

    def nav(self) -> str:
        tag = self.r.choice(["nav", "div", "nav", "ul"])
        inner = self.links(self.r.randint(3, 9)) if tag != "ul" else "".join(f'<li data-k="0"><a href="#">{self.word()}</a></li>' for _ in range(5))
        return f'<{tag} data-k="0"{self.attribute("nav", "menu", "navbar", "breadcrumbs", "main-menu", "pagination", chance=0.5 if tag == "nav" else 1)}>{inner}</{tag}>'

    def header(self) -> str:
        tag = self.r.choice(["header", "div", "header"])
        inner = self.r.choice([f'<p data-k="0">{self.prose(2, 8)}</p>', f'<h1 data-k="0">{self.prose(1, 3)}</h1>', f'<div data-k="0">{self.prose(2, 6)}</div>', self.prose(2, 6)])
        return f'<{tag} data-k="0"{self.attribute("header", "masthead", "topbar", "site-header", chance=0.4 if tag == "header" else 1)}>{inner}{self.nav() if self.r.random() < 0.4 else ""}</{tag}>'

    def footer(self) -> str:
        tag = self.r.choice(["footer", "div", "footer"])
        inner = "&copy; " + self.prose(3, 25) if self.r.random() < 0.6 else f'<p data-k="0">&copy; {self.prose(4, 30)}</p>' + self.links(self.r.randint(2, 6))
        return f'<{tag} data-k="0"{self.attribute("footer", "copyright", "legal", "site-footer", chance=0.3 if tag == "footer" else 1)}>{inner}</{tag}>'

    def aside(self) -> str:
        tag = self.r.choice(["aside", "div", "section"])
        inner = self.r.choice([f'<h3 data-k="0">{self.prose(1, 3)}</h3>' + self.links(self.r.randint(3, 7)), f'<p data-k="0">{self.prose(8, 40)}</p>', "".join(f'<p data-k="0"><a href="#">{self.prose(4, 10)}</a></p>' for _ in range(3))])
        return f'<{tag} data-k="0"{self.attribute("sidebar", "related", "widget", "recommended", "trending", chance=0.3 if tag == "aside" else 1)}>{inner}</{tag}>'

    def advert(self) -> str:
        tag = self.r.choice(["div", "div", "section", "aside", "p"])
        inner = self.prose(5, 25) if tag == "p" or self.r.random() < 0.6 else f'<p data-k="0">{self.prose(5, 25)}</p>'
        return f'<{tag} data-k="0"{self.attribute("ad", "ads", "advert", "sponsored", "promo", "banner", "ad-slot", chance=1)}>{inner}</{tag}>'

    def notice(self) -> str:
        tag = self.r.choice(["div", "div", "section", "dialog", "p"])
        inner = self.prose(8, 30) + ('<button data-k="0">OK</button>' if tag != "p" else "")
        if tag not in ("p",) and self.r.random() < 0.5:
            inner = f'<p data-k="0">{inner}</p>' if "button" not in inner else f'<p data-k="0">{self.prose(8, 30)}</p><button data-k="0">OK</button>'
        return f'<{tag} data-k="0"{self.attribute("cookie-notice", "consent", "notice", "newsletter", "popup", "alert", "subscribe", chance=1)}>{inner}</{tag}>'

    def form(self) -> str:
        fields = "".join(f'<label data-k="0">{self.word()}</label><input name="{self.word()}">' for _ in range(self.r.randint(1, 4)))
        note = f'<p data-k="0">{self.prose(4, 20)}</p>' if self.r.random() < 0.6 else self.prose(2, 10)
        return f'<form data-k="0"{self.attribute("search", "login", "contact", chance=0.5)}>{note}{fields}<button data-k="0">{self.word()}</button></form>'

    def comments(self) -> str:
        tag = self.r.choice(["div", "section", "ol", "ul", "aside"])
        each = "li" if tag in ("ol", "ul") else self.r.choice(["div", "article", "p", "li"])
        rows = "".join(f'<{each} data-k="0"{self.attribute("comment", "reply", "review", chance=0.7)}>{self.prose(5, 60) if each == "p" or self.r.random() < 0.5 else self.word() + "<p data-k=0>" + self.prose(5, 60) + "</p>"}</{each}>' for _ in range(self.r.randint(1, 6)))
        title = f'<h2 data-k="0">{self.prose(1, 2)}</h2>' if tag not in ("ol", "ul") and self.r.random() < 0.6 else ""
        return f'<{tag} data-k="0"{self.attribute("comments", "comment-list", "respond", "discussion", "reviews", chance=1)}>{title}{rows}</{tag}>'

    def share(self) -> str:
        return f'<div data-k="0"{self.attribute("share", "social", "sharing", chance=1)}>{"".join(f"<a href=#>{self.word()}</a> " for _ in range(4))}</div>'

    def clutter(self) -> str:
        return self.r.choice([self.nav, self.header, self.footer, self.aside, self.advert, self.notice, self.form, self.comments, self.share])()

    def unscripted(self) -> str:
        return f'<noscript data-k="0">{self.prose(3, 14)}</noscript>'

    def link_bar(self) -> str:
        """Links that stand in no block."""
        return "\ue000" + self.r.choice([" ", " | ", "\n"]).join(f'<a href="/{self.word()}">{self.prose(1, 2)[:-1]}</a>' for _ in range(self.r.randint(3, 9)))

    def loose_article(self) -> str:
        """A heading or none, and text in no block or in paragraphs, with nothing around it."""
        level = self.r.choice("123")
        parts = [f'<h{level} data-k="1">{self.prose(1, 8)}</h{level}>'] if self.r.random() < 0.4 else []
        for _ in range(self.r.randint(1, 4)):
            if self.r.random() < 0.3:
                parts.append(self.paragraph())
            else:
                most = self.r.choice([6, 60])
                parts.append(self.r.choice(["<br>", "<br><br>", " "]).join(self.prose(1, most) for _ in range(self.r.randint(1, 3))))
        text = "\ue001" + parts[0] if not parts[0].startswith("<") else parts[0]
        return text + "".join(parts[1:])

    def paragraph(self) -> str:
        shape = self.r.random()
        text = self.prose(1, 12) if shape < 0.25 else self.prose(10, 120)
        if shape > 0.9:
            text = f"<b>{self.prose(2, 8)}<br>" + ("" if self.r.random() < 0.5 else text)
        elif shape > 0.75:
            text += f' <a href="#">{self.prose(1, 4)}</a> {self.prose(3, 20)}'
        return f'<p data-k="1">{text}' + ("</p>" if self.r.random() < 0.93 else "")

    def article(self) -> str:
        tag = self.r.choice(["article", "article", "main", "div", "section"])
        parts = [f'<h1 data-k="1">{self.prose(3, 12)}</h1>'] if self.r.random() < 0.85 else []
        for _ in range(self.r.choice([1, 1, 2, 4, 8, 16])):
            kind = self.r.random()
            if kind < 0.72:
                parts.append(self.paragraph())
            elif kind < 0.78:
                parts.append(f'<h2 data-k="1">{self.prose(2, 7)}</h2>')
            elif kind < 0.84:
                items = "".join(f'<li data-k="1">{self.prose(3, 25)}</li>' for _ in range(self.r.randint(2, 6)))
                parts.append(f'<ul data-k="1">{items}</ul>')
            elif kind < 0.88:
                parts.append(f'<blockquote data-k="1"><p data-k="1">{self.prose(5, 40)}</p></blockquote>')
            elif kind < 0.91:
                cells = "".join("<tr data-k=1>" + "".join(f'<td data-k="1">{self.prose(1, 5)}</td>' for _ in range(3)) + "</tr>" for _ in range(3))
                parts.append(f'<table data-k="1">{cells}</table>')
            elif kind < 0.94:
                parts.append(f'<pre data-k="1">{self.prose(5, 30)}</pre>')
            elif kind < 0.96:
                parts.append(f'<div data-k="1">{self.prose(10, 60)}</div>')
            else:
                parts.append(self.r.choice([self.advert, self.notice, self.aside, self.share, self.form, self.advert])())
        inner = "".join(parts)
        if self.r.random() < 0.25:
            inner = f'<div data-k="1"{self.attribute("content", "entry", "body", "text")}>{inner}</div>'
        if self.r.random() < 0.2:
            inner += self.comments()
        hint = self.attribute("article", "post", "content", "story", "entry-content", "main", chance=0.3 if tag in ("article", "main") else 1)
        return f'<{tag} data-k="1"{hint}>{inner}</{tag}>'

    def page(self) -> str:
        if self.r.random() < 0.18:
            bar = self.link_bar() if self.r.random() < 0.3 else ""
            below = self.footer() if self.r.random() < 0.3 else ""
            # a block between keeps the bar and the article apart
            return "<html><body>" + bar + ("<hr><div data-k=0></div>" if bar else "") + self.loose_article() + below + "</body></html>"
        top = [self.r.choice([self.nav, self.header, self.advert, self.notice, self.form, self.unscripted])() for _ in range(self.r.randint(0, 4))]
        low = [self.clutter() for _ in range(self.r.randint(0, 4))]
        middle = self.article()
        if self.r.random() < 0.03:
            middle = f'<noscript data-k="1">{middle}</noscript>'
        if self.r.random() < 0.25:
            middle = f'<main data-k="1">{middle}</main>' if not middle.startswith("<main") else middle
        if self.r.random() < 0.2:
            middle = f'<div data-k="1"{self.attribute("page", "wrapper", "container")}>{middle}{self.aside()}</div>'
        return "<html><body>" + "".join(top) + middle + "".join(low) + (self.footer() if self.r.random() < 0.7 else "") + "</body></html>"


_MARK = re.compile(r" data-k=\"?([01])\"?")


def read_roles(page: str) -> tuple[list[Node], np.ndarray] | None:
    """(nodes, 1 where a node is of the article) of a generated page; None where lenient reading merged its elements."""
    marks = [int(m) for m in _MARK.findall(page)]
    nodes = ordered(parse(_MARK.sub("", page)))
    if sum(not n.loose for n in nodes) - 1 != len(marks):
        return None
    roles, at = np.ones(len(nodes), int), 0
    for i, node in enumerate(nodes[1:], 1):
        if not node.loose:
            roles[i] = marks[at]
            at += 1
            continue
        roles[i] = roles[node.parent.index]
        for sign, role in _ROLES.items():
            if any(sign in p for p in node.parts):
                roles[i] = role
                node.parts = [type(p)(p.replace(sign, "")) for p in node.parts]
    return nodes, roles


def training_rows(pages: int, seed: int) -> tuple[np.ndarray, np.ndarray]:
    writer = _Writer(seed)
    xs, ys = [], []
    for _ in range(pages):
        read = read_roles(writer.page())
        if read is None:
            continue
        nodes, roles = read
        x, _ = features(nodes)
        xs.append(x[1:])
        ys.append(roles[1:])
    return np.concatenate(xs), np.concatenate(ys).astype(float)


@lru_cache(maxsize=2)
def trained(pages: int = 1600, seed: int = 11) -> BoostedTrees:
    return BoostedTrees().fit(*training_rows(pages, seed))


def extract_many(pages: list[str | None], model: BoostedTrees) -> list[str]:
    trees = [ordered(parse(p)) if p else None for p in pages]
    parts = [features(t) if t else (np.zeros((0, FEATURES), np.float32), np.zeros(0)) for t in trees]
    odds = model.log_odds(np.concatenate([x for x, _ in parts])) if parts else np.zeros(0)
    out, at = [], 0
    for nodes, (x, own) in zip(trees, parts, strict=True):
        if nodes is None:
            out.append("")
            continue
        out.append(text_of(nodes, decide(nodes, odds[at : at + len(x)], own)))
        at += len(x)
    return out


def extract(pages: DataFrame, html_col: str = "html", model: BoostedTrees | None = None) -> DataFrame:
    """The frame with ``main_text`` (a column of this name is replaced)."""
    model = model or trained()
    kept = replaced(pages, ["main_text"])
    where = [c.lower() for c in kept.columns].index(html_col.lower())

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for a in range(0, batch.num_rows, 64):
                rows = batch.slice(a, 64)
                texts = extract_many(rows.column(where).to_pylist(), model)
                yield pa.RecordBatch.from_arrays([*rows.columns, pa.array(texts, pa.string())], names=[*rows.schema.names, "main_text"])

    schema = T.StructType([T.StructField(f.name, f.dataType, True) for f in kept.schema.fields]).add("main_text", "string")
    return small_batches(kept).mapInArrow(tidy(run), schema)


def op6_main_text(spark, sf_dir: str) -> DataFrame:
    pages = spark.read.parquet(f"{sf_dir}/pages.parquet").select("page_id", "url", "html")
    return extract(pages).select("page_id", "url", F.col("main_text").alias("text"), F.length("main_text").cast("long").alias("n_chars"))
