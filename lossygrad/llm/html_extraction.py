"""Main text of web pages: boosted trees over DOM nodes with hierarchical decoding.

A page is parsed into elements and text blocks (runs of text between block-level tags),
in time linear in its length.  Each node gets features: tag kind, tokens of class, id and
role, the same of its ancestors, subtree size, link and punctuation density, depth, place
and siblings.  Attribute tokens (words of a name, and pairs of them) are hashed to cells; a
cell's weight, the log-odds that a node with such a token has article text, is learned.
Gradient-boosted trees give each node a probability of belonging to the article.
Decoding picks the most probable set of kept nodes in which the parents of a kept node
are kept and all below a dropped node is dropped; kept blocks are the text.

Weights and trees are learned here, from pages written by ``training_pages`` (no page of
the table is used; the two use different pages), in seconds on the driver; the model is
a few kilobytes.  The pages put words of menus and side bars into names of articles'
containers too (``has-sidebar``, ``comments-open``), so that a name alone settles nothing.

Text: character references are decoded, white space inside a block is one space,
blocks are trimmed and joined by a line feed in page order.  ``<br>`` is white space;
formulas and drawings are inline text.  The head ends at the first thing that cannot stand
in it.  A quoted value runs to its closing quote; where one never closes, quotes mean
nothing from there on, and a tag that never ends is dropped.

Edge cases: null or empty html gives an empty text; markup without a body works;
unclosed, stray or misnested tags never fail; a page of one block keeps it if it looks
like an article; very deep pages need no recursion; equal rows give equal rows.
"""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass
from functools import lru_cache
from html import unescape
from random import Random
from zlib import crc32

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from lossygrad.llm import common

# HTML vocabulary.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
SKIPPED = frozenset("head script style noscript template iframe select option button textarea title".split())
IN_HEAD = frozenset("base link meta title script style template noscript html head".split())
RAW = frozenset("script style textarea title noscript iframe".split())
INLINE = frozenset("a abbr acronym audio b bdi bdo big canvas cite code data del dfn em font i ins kbd label map mark meter object output picture progress q rp rt ruby s samp small span strike strong sub sup time tt u var video wbr br img".split())
FOREIGN = frozenset("math svg".split())
KINDS = {
    tag: i
    for i, group in enumerate(
        ("nav menu", "header", "footer", "aside dialog", "form fieldset", "article", "main", "section", "div center", "p", "h1 h2 h3 h4 h5 h6", "ul ol dl", "li dt dd",
         "table tbody thead tr td th", "blockquote pre figure figcaption", "address details summary", "body html")
    )
    for tag in group.split()
}
N_KINDS = 18
CLOSES_P = frozenset("address article aside blockquote center details dialog div dl fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hr main menu nav ol p pre section table ul".split())
SCOPES = frozenset("table td th button".split())
# A tag is matched without backtracking; the last group is empty where it never ends.
_TAG = re.compile(r"<!--.*?(?:-->|\Z)|<(/?)([a-zA-Z][^\s/>]*+)((?:[^>=]++|=\s*+(?:\"[^\"]*+(?:\"|\Z)|'[^']*+(?:'|\Z))?+)*+)(>?)|<[!?/][^>]*+>?", re.S)
_PLAIN_TAG = re.compile(r"<!--.*?(?:-->|\Z)|<(/?)([a-zA-Z][^\s/>]*+)([^>]*+)(>?)|<[!?/][^>]*+>?", re.S)
_ATTRIBUTE = re.compile(r"\b(class|id|role)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s>]+))", re.I)
_WORDS = re.compile(r"[A-Z]?[a-z]+|[A-Z]+")
_MARK = ""
#: Cells of attribute tokens.
CELLS = 1 << 12
N_FEATURES = N_KINDS + 24


def tokens_of(attributes: str) -> tuple[tuple[int, ...], ...]:
    """For each name in class, id and role: the cells of its words, then of its pairs of words."""
    names = [n for a in _ATTRIBUTE.finditer(attributes) for n in (a[2] or a[3] or a[4] or "").split()]
    return tuple(t for n in names if (t := _cells(n)))


@lru_cache(maxsize=1 << 14)
def _cells(name: str) -> tuple[int, ...]:
    words = [w.lower() for w in _WORDS.findall(name)]
    return tuple(crc32(t.encode()) % CELLS for t in [*words, *(f"{a} {b}" for a, b in zip(words, words[1:]))])


class Page:
    """Nodes of a page in document order; blocks are nodes with ``text``."""

    def __init__(self, html: str):
        self.parent, self.kind, self.depth = [-1], [16], [0]
        self.names: list[tuple[tuple[int, ...], ...]] = [()]
        self.text: list[str | None] = [None]
        self.links: list[int] = [0]  # characters of the block inside links
        self._parse(html)

    def _open(self, parent: int, kind: int, names: tuple = (), text: str | None = None, links: int = 0) -> int:
        self.parent.append(parent)
        self.kind.append(kind)
        self.depth.append(self.depth[parent] + 1)
        self.names.append(names)
        self.text.append(text)
        self.links.append(links)
        return len(self.parent) - 1

    def _parse(self, html: str) -> None:
        stack: list[tuple[str, int, int]] = [("", 0, 0)]  # open block-level elements, each with the place of the paragraph it may close
        opened: Counter[str] = Counter()
        run: list[str] = []
        linked = 0
        anchors = 0
        skipping: list[str] = []
        foreign = ""
        at = 0
        tags = _TAG

        def close_run() -> None:
            nonlocal linked
            if run:
                text = " ".join("".join(run).split())
                if text:
                    self._open(stack[-1][1], 17, (), text, min(linked, len(text)))
                run.clear()
            linked = 0

        def add(piece: str) -> None:
            nonlocal linked
            if piece and skipping == ["head"] and not piece.isspace():
                skipping.clear()
            if piece and not skipping:
                piece = unescape(piece) if "&" in piece else piece
                run.append(piece)
                if anchors:
                    linked += len(piece.strip())

        def close_from(i: int) -> None:
            for tag, _, _ in stack[i:]:
                opened[tag] -= 1
            del stack[i:]

        def close_to(names: tuple[str, ...], stop: frozenset[str] | tuple[str, ...] = ()) -> None:
            if any(opened[n] for n in names):
                for i in range(len(stack) - 1, 0, -1):
                    if stack[i][0] in names:
                        return close_from(i)
                    if stack[i][0] in stop:
                        return None
            return None

        n = len(html)
        while at < n:
            m = tags.search(html, at)
            if m is None:
                add(html[at:])
                break
            if m[2] is not None and not m[4] and tags is _TAG:  # it ran to the end of the page: read on without quotes
                tags = _PLAIN_TAG
                continue
            add(html[at : m.start()])
            at = m.end()
            name = m[2]
            if name is None or not m[4]:
                continue
            tag = name.lower()
            if skipping == ["head"] and not m[1] and tag not in IN_HEAD:
                skipping.clear()
            if m[1]:
                if skipping:
                    if tag in skipping:
                        while skipping.pop() != tag:
                            pass
                    continue
                if foreign:
                    foreign = "" if tag == foreign else foreign
                elif tag == "a":
                    anchors = max(0, anchors - 1)
                elif tag not in INLINE and tag not in VOID:
                    close_run()
                    close_to((tag,))
                continue
            if tag in RAW:
                end = re.compile(rf"</{tag}\s*+>", re.I).search(html, at)
                at = end.end() if end else n
                continue
            if skipping:
                if tag in SKIPPED:
                    skipping.append(tag)
                continue
            if tag == "br":
                run.append(" ")
                continue
            if tag in SKIPPED:
                skipping.append(tag)
                continue
            if foreign or tag in FOREIGN:
                foreign = foreign or (tag if not m[3].endswith("/") else "")
                continue
            if tag == "a":
                anchors += 1
                continue
            if tag in INLINE:
                continue
            close_run()
            anchors = 0
            if tag in VOID:
                continue
            if tag in CLOSES_P and stack[-1][2]:
                close_from(stack[-1][2])
            if tag == "li":
                close_to(("li",), ("ul", "ol", "menu"))
            elif tag in ("dt", "dd"):
                close_to(("dt", "dd"), ("dl",))
            elif tag == "tr":
                close_to(("tr",), ("table",))
            elif tag in ("td", "th"):
                close_to(("td", "th"), ("tr", "table"))
            names = tokens_of(m[3]) if "=" in m[3] else ()
            paragraph = len(stack) if tag == "p" else 0 if tag in SCOPES else stack[-1][2]
            opened[tag] += 1
            stack.append((tag, self._open(stack[-1][1], KINDS.get(tag, 17), names), paragraph))
        close_run()

    def features(self, weights: np.ndarray) -> np.ndarray:
        n = len(self.parent)
        parent, kind = np.array(self.parent), np.array(self.kind)
        text = [t or "" for t in self.text]
        chars = np.array([len(t) for t in text], float)
        words = np.array([t.count(" ") + 1 if t else 0 for t in text], float)
        stops = np.array([t.count(".") + t.count(",") + t.count("?") + t.count("!") if t else 0 for t in text], float)
        links = np.array(self.links, float)
        blocks = (chars > 0).astype(float)
        before = np.cumsum(chars) - chars
        least, most, mean = np.zeros(n), np.zeros(n), np.zeros(n)
        for i, names in enumerate(self.names):
            if names:
                each = [float(weights[list(t)].mean()) for t in names]
                least[i], most[i], mean[i] = min(each), max(each), sum(each) / len(each)
        up_least, up_most, up_mean, inside, article = np.zeros(n), np.zeros(n), np.zeros(n), np.zeros(n), np.zeros(n)
        children, index = np.zeros(n), np.zeros(n)
        for i in range(1, n):  # parents come before children
            p = parent[i]
            up_least[i], up_most[i] = min(up_least[p], least[p]), max(up_most[p], most[p])
            up_mean[i] = mean[p] if mean[p] else up_mean[p]
            inside[i] = inside[p] + (kind[p] <= 4 and not (kind[p] == 1 and article[p]))
            article[i] = article[p] + (kind[p] in (5, 6))
            index[i] = children[p]
            children[p] += 1
        sums = np.stack([chars, words, stops, links, blocks])
        for i in range(n - 1, 0, -1):
            sums[:, parent[i]] += sums[:, i]
        chars, words, stops, links, blocks = sums
        total = max(chars[0], 1.0)
        x = np.zeros((n, N_FEATURES), np.float32)
        x[np.arange(n), kind] = 1
        leaf = np.array([t is not None for t in self.text])
        # A block shows its element's tag as well.
        x[leaf, kind[parent[leaf]]] = 1
        siblings = children[np.maximum(parent, 0)]
        rest = [
            least, most, mean, up_least, up_most, up_mean, np.minimum(inside, 3), np.minimum(article, 3),
            np.log1p(chars), np.log1p(words), links / np.maximum(chars, 1), stops / np.maximum(words, 1), words / np.maximum(blocks, 1), np.log1p(blocks), chars / total,
            np.minimum(np.array(self.depth), 30), before / total, np.log1p(siblings), index / np.maximum(siblings, 1), leaf,
            chars[np.maximum(parent, 0)] / total, links[np.maximum(parent, 0)] / np.maximum(chars[np.maximum(parent, 0)], 1),
            words[np.maximum(parent, 0)] / np.maximum(blocks[np.maximum(parent, 0)], 1), np.full(n, np.log1p(total)),
        ]
        x[:, N_KINDS:] = np.stack(rest, axis=1)
        return x

    def decode(self, p: np.ndarray) -> np.ndarray:
        """Kept nodes: the most probable choice without contradictions; the root is kept."""
        n = len(self.parent)
        p = np.clip(p, 1e-4, 1 - 1e-4)
        keep, drop = np.log(p), np.log1p(-p)
        best, none = keep.tolist(), drop.tolist()  # of the subtree, with the node kept or all of it dropped
        parent = self.parent
        for i in range(n - 1, 0, -1):
            q = parent[i]
            best[q] += max(best[i], none[i])
            none[q] += none[i]
        kept = [False] * n
        kept[0] = True
        for i in range(1, n):
            kept[i] = kept[parent[i]] and best[i] > none[i]
        return np.array(kept)

    def extract(self, p: np.ndarray) -> str:
        kept = self.decode(p)
        return "\n".join(t for t, k in zip(self.text, kept, strict=True) if k and t is not None)


class BoostedTrees:
    """Logistic gradient boosting with histogram splits on up to 32 bins a feature."""

    def __init__(self, trees: int = 40, depth: int = 5, rate: float = 0.2, l2: float = 1.0, least: float = 1.0):
        self.trees, self.depth, self.rate, self.l2, self.least = trees, depth, rate, l2, least

    def fit(self, x: np.ndarray, y: np.ndarray) -> BoostedTrees:
        n, m = x.shape
        edges = [np.unique(np.quantile(x[:, j], np.linspace(0, 1, 33)[1:-1])) for j in range(m)]
        binned = np.stack([np.searchsorted(e, x[:, j], side="left") for j, e in enumerate(edges)], axis=1)
        self.bias = float(np.log((y.mean() + 1e-6) / (1 - y.mean() + 1e-6)))
        score = np.full(n, self.bias)
        inner, leaves = (1 << self.depth) - 1, 1 << self.depth
        self.feature, self.cut = np.zeros((self.trees, inner), np.int64), np.full((self.trees, inner), np.inf)
        self.leaf = np.zeros((self.trees, leaves))
        for t in range(self.trees):
            p = 1 / (1 + np.exp(-score))
            g, h = p - y, np.maximum(p * (1 - p), 1e-6)
            node = np.zeros(n, np.int64)
            for level in range(self.depth):
                first, width = (1 << level) - 1, 1 << level
                gain = np.zeros(width)
                choice = [(0, np.inf, -1)] * width
                sum_g, sum_h = np.bincount(node, g, width), np.bincount(node, h, width)
                own = sum_g**2 / (sum_h + self.l2)
                for j in range(m):
                    if not len(edges[j]):
                        continue
                    size = len(edges[j]) + 1
                    at = node * size + binned[:, j]
                    left_g = np.bincount(at, g, width * size).reshape(width, size).cumsum(1)[:, :-1]
                    left_h = np.bincount(at, h, width * size).reshape(width, size).cumsum(1)[:, :-1]
                    right_g, right_h = sum_g[:, None] - left_g, sum_h[:, None] - left_h
                    won = left_g**2 / (left_h + self.l2) + right_g**2 / (right_h + self.l2) - own[:, None]
                    won[(left_h < self.least) | (right_h < self.least)] = 0
                    b = won.argmax(1)
                    for k in np.flatnonzero(won[np.arange(width), b] > gain + 1e-9):
                        gain[k], choice[k] = won[k, b[k]], (j, edges[j][b[k]], b[k])
                for k, (j, cut, _) in enumerate(choice):
                    self.feature[t, first + k], self.cut[t, first + k] = j, cut
                f, c = self.feature[t, first + node], self.cut[t, first + node]
                node = 2 * node + (x[np.arange(n), f] > c)
            w = -np.bincount(node, g, leaves) / (np.bincount(node, h, leaves) + self.l2) * self.rate
            self.leaf[t] = w
            score += w[node]
        return self

    def predict(self, x: np.ndarray) -> np.ndarray:
        score = np.full(len(x), self.bias)
        rows = np.arange(len(x))
        for t in range(self.trees):
            node = np.zeros(len(x), np.int64)
            for level in range(self.depth):
                at = (1 << level) - 1 + node
                node = 2 * node + (x[rows, self.feature[t, at]] > self.cut[t, at])
            score += self.leaf[t, node]
        return 1 / (1 + np.exp(-score))


# ---- training pages


# Names that the written pages use: of parts beside an article, of articles, and of neither.
ASIDE = (
    "nav navbar navigation menu menubar breadcrumbs sidebar side aside rail footer header masthead topbar ads advert advertisement banner promo sponsored cookie consent notice alert popup modal "
    "comment comments reply replies respond discussion related recommended more share sharing social follow newsletter subscribe signup login search form widget tags pagination copyright legal toolbar"
).split()
STORY = "article content post entry main story body text hentry articleBody postBody mainContent blog prose post-content article-body entry-content main-content story-body".split()
NEUTRAL = "col-md-8 col row container wrapper clearfix grid layout wrap inner box x1 group block lg dark js".split()


class _Writer:
    def __init__(self, r: Random):
        self.r = r

    def words(self, n: int, stops: float = 0.12) -> str:
        r = self.r
        out = ["".join(r.choice("bcdfglmnprstvéüñ") + r.choice("aeiouäè") for _ in range(r.randint(1, 4))) for _ in range(n)]
        out = [w + r.choice(",.,.;?!") if r.random() < stops else w for w in out]
        return " ".join(out).capitalize() + (r.choice(["", "."]) if stops else "")

    def cls(self, *names: str) -> str:
        r = self.r
        if r.random() < 0.2:
            return ""
        name = r.choice(names)
        name = r.choice([name, name, f"{name}-{r.choice(['wrap', 'box', 'inner', 'block', 'x1'])}", f"{r.choice(['site', 'page', 'm', 'c'])}-{name}", name.capitalize()])
        if r.random() < 0.2:
            name += " " + r.choice([*NEUTRAL, *NEUTRAL, self.state()])
        return f' {r.choice(["class", "class", "id"])}="{name}"'

    def state(self) -> str:
        """A name that tells of something elsewhere on the page."""
        r = self.r
        what = r.choice(ASIDE)
        return r.choice([f"{r.choice(['has', 'no', 'with', 'without', 'is', 'show', 'hide', 'page-with'])}-{what}", f"{what}-{r.choice(['open', 'closed', 'enabled', 'disabled', 'on', 'off', 'left', 'right', 'visible', 'info', 'active', 'ready', 'count'])}"])

    def holder(self, *names: str) -> str:
        """Attributes of an element around the article: its own name, states of the page, or neither."""
        r = self.r
        own = [r.choice(names)] if names and r.random() < 0.75 else []
        more = [r.choice([r.choice(NEUTRAL), self.state(), self.state(), r.choice(ASIDE)]) for _ in range(r.choice([0, 0, 1, 1, 2]))]
        listed = own + more
        r.shuffle(listed)
        return f' {r.choice(["class", "class", "class", "id"])}="{" ".join(listed)}"' if listed else ""

    def link(self, n: int) -> str:
        return f'<a href="/{self.r.randint(0, 999)}">{self.words(n, 0)}</a>'

    def links(self, n: int) -> str:
        r = self.r
        style = r.random()
        if style < 0.6:
            return "<ul>" + "".join(f"<li>{self.link(r.randint(1, 3))}</li>" for _ in range(n)) + "</ul>"
        if style < 0.8:
            return " ".join(self.link(r.randint(1, 2)) for _ in range(n))
        return "".join(f"<div>{self.link(r.randint(1, 4))}</div>" for _ in range(n))

    # Parts that are not the article.
    def boiler(self, where: str) -> str:
        r = self.r
        if where == "top":
            return r.choice([
                lambda: f"<nav{self.cls('nav', 'menu', 'navbar')}>{self.links(r.randint(2, 12))}</nav>",
                lambda: f"<div{self.cls('menu', 'navigation', 'nav', 'topbar')}>{self.links(r.randint(3, 12))}</div>",
                lambda: f"<header{self.cls('header', 'masthead')}><h1>{self.words(r.randint(1, 4), 0)}</h1>{self.links(r.randint(0, 6))}<p>{self.words(r.randint(3, 9))}</p></header>",
                lambda: f"<div{self.cls('header', 'banner')}>{self.words(r.randint(2, 8))}</div>",
                lambda: f"<div{self.cls('breadcrumb', 'breadcrumbs')}>{self.link(1)} &gt; {self.link(2)}</div>",
                self.cookie, self.ad, self.form,
            ])()
        if where == "end":
            return r.choice([self.footer, self.footer, self.comments, self.comments, self.related, self.side, self.ad, self.form, self.cookie])()
        return r.choice([self.ad, self.ad, self.share, self.related, self.form])()

    def ad(self) -> str:
        r = self.r
        inner = r.choice([self.words(r.randint(2, 30)), self.link(r.randint(2, 8)), f"<p>{self.words(r.randint(4, 40))}</p>"])
        return f'<div class="{r.choice(["ad", "ads", "advert", "ad-slot", "sponsored", "promo", "banner-ad"])}">{inner}</div>'

    def share(self) -> str:
        return f"<div{self.cls('share', 'social', 'sharing')}>{self.links(self.r.randint(2, 5))}</div>"

    def related(self) -> str:
        r = self.r
        return f"<{(t := r.choice(['div', 'section', 'aside']))}{self.cls('related', 'recommended', 'more')}><h3>{self.words(2, 0)}</h3>{self.links(r.randint(2, 8))}</{t}>"

    def side(self) -> str:
        r = self.r
        inner = "".join(r.choice([lambda: f"<h3>{self.words(2, 0)}</h3>", lambda: self.links(r.randint(2, 6)), lambda: f"<p>{self.words(r.randint(5, 40))}</p>"])() for _ in range(r.randint(1, 4)))
        return f"<aside{self.cls('sidebar', 'widget')}>{inner}</aside>" if r.random() < 0.6 else f'<div class="{r.choice(["sidebar", "side-rail", "widget-area"])}">{inner}</div>'

    def form(self) -> str:
        r = self.r
        return f'<form action="/s"{self.cls("search", "newsletter", "login")}><label>{self.words(r.randint(1, 4), 0)}</label><p>{self.words(r.randint(2, 25))}</p><input name="q"><button>{self.words(1, 0)}</button></form>'

    def cookie(self) -> str:
        r = self.r
        return f'<div class="{r.choice(["cookie", "cookie-notice", "consent", "notice", "gdpr-banner", "alert"])}"><p>{self.words(r.randint(6, 40))}</p><button>{self.words(1, 0)}</button></div>'

    def comments(self) -> str:
        r = self.r
        each = "".join(
            f'<{(t := r.choice(["div", "li", "article"]))} class="{r.choice(["comment", "reply", "comment-body"])}"><b>{self.words(2, 0)}</b><p>{self.words(r.randint(4, 90))}</p></{t}>' for _ in range(r.randint(1, 6))
        )
        return f'<{(s := r.choice(["section", "div", "ol"]))} {r.choice(["id", "class"])}="{r.choice(["comments", "comment-list", "discussion", "respond"])}"><h3>{self.words(2, 0)}</h3>{each}</{s}>'

    def footer(self) -> str:
        r = self.r
        inner = r.choice([f"&copy; {self.words(r.randint(2, 14))}", f"<p>{self.words(r.randint(4, 40))}</p>", self.links(r.randint(2, 9)), f"<p>{self.words(5)}</p>{self.links(4)}"])
        return f"<footer{self.cls('footer')}>{inner}</footer>" if r.random() < 0.7 else f'<div class="{r.choice(["footer", "copyright", "legal", "site-footer"])}">{inner}</div>'

    # The article.
    def own(self, n: int, stops: float = 0.12) -> str:
        text = self.words(n, stops)
        if n > 12 and self.r.random() < 0.2:
            text += f" {self.link(2)} {self.words(4)}"
        if self.r.random() < 0.15:
            text = f"<b>{text}</b><br>{self.words(3)}" if self.r.random() < 0.5 else f"<b>{text}<br>"
        return _MARK + text

    def block(self) -> str:
        r = self.r
        x = r.random()
        if x < 0.72:
            size = r.choice([1, 2, 3, 6, 15, 30, 60, 120, 250])
            return f"<p>{self.own(r.randint(1, size))}" + ("</p>" if r.random() < 0.9 else "")
        if x < 0.8:
            return f"<h{(k := r.randint(2, 4))}>{self.own(r.randint(1, 8), 0)}</h{k}>"
        if x < 0.86:
            return "<ul>" + "".join(f"<li>{self.own(r.randint(1, 25))}</li>" for _ in range(r.randint(1, 6))) + "</ul>"
        if x < 0.9:
            return f"<blockquote><p>{self.own(r.randint(4, 50))}</p></blockquote>"
        if x < 0.93:
            return "<table>" + "".join("<tr>" + "".join(f"<td>{self.own(r.randint(1, 5), 0)}</td>" for _ in range(3)) + "</tr>" for _ in range(r.randint(1, 4))) + "</table>"
        if x < 0.95:
            return f"<pre>{self.own(r.randint(5, 30))}</pre>"
        return f"<div>{self.own(r.randint(5, 80))}</div>"

    def article(self) -> str:
        r = self.r
        parts = []
        if r.random() < 0.85:
            h = f"<h1>{self.own(r.randint(1, 12), 0.03)}</h1>"
            parts.append(f"<header>{h}</header>" if r.random() < 0.15 else h)
        for _ in range(r.choice([1, 1, 2, 3, 5, 8, 14])):
            parts.append(self.block())
            if r.random() < 0.06:
                parts.append(self.boiler("inside"))
        return "".join(parts)

    def page(self) -> str:
        r = self.r
        x = r.random()
        body = self.article()
        if x < 0.4:
            body = f"<article{self.holder('article', 'post', 'entry', 'story', 'hentry')}>{body}</article>"
        elif x < 0.52:
            body = f"<main{self.holder('main', 'content')}>{body}</main>"
        elif x < 0.6:
            body = f"<main{self.holder('main')}><article{self.holder('post')}>{body}</article>{self.side() if r.random() < 0.3 else ''}</main>"
        elif x < 0.9:
            body = f"<{(t := r.choice(['div', 'div', 'section']))}{self.holder(*STORY)}>{body}</{t}>"
        else:
            body = f"<div{self.holder()}>{body}</div>"
        top = "".join(self.boiler("top") for _ in range(r.randint(0, 3)))
        end = "".join(self.boiler("end") for _ in range(r.randint(0, 4)))
        middle = top + body + end
        for _ in range(r.randint(0, 2)):
            middle = f"<div{self.holder('wrapper', 'container', 'page', 'site', 'layout')}>{middle}</div>"
        return f"<!DOCTYPE html><html><head><title>{self.words(4)}</title><script>x</script></head><body{self.holder('home', 'page', 'post', 'single', 'blog')}>{middle}</body></html>"


def training_pages(n: int = 700, seed: int = 5) -> list[tuple[Page, np.ndarray]]:
    """Pages with the truth for every node: whether article text is in or below it."""
    writer = _Writer(Random(seed))
    out = []
    for _ in range(n):
        page = Page(writer.page())
        truth = np.zeros(len(page.parent))
        for i in range(len(page.parent) - 1, -1, -1):
            t = page.text[i]
            if t is not None and _MARK in t:
                truth[i] = 1
                page.text[i] = t.replace(_MARK, "").strip()
            if truth[i] and i:
                truth[page.parent[i]] = 1
        out.append((page, truth))
    return out


def token_weights(data: list[tuple[Page, np.ndarray]], calm: float = 4.0) -> np.ndarray:
    """For each cell, the smoothed log-odds (against all named nodes) that a node with the token has article text."""
    met, good = np.zeros(CELLS), np.zeros(CELLS)
    for page, truth in data:
        for names, y in zip(page.names, truth, strict=True):
            cells = list({c for t in names for c in t})
            met[cells] += 1
            good[cells] += y
    rate = good.sum() / max(met.sum(), 1)
    p = (good + calm * rate) / (met + calm)
    return np.log(p / (1 - p)) - np.log(rate / (1 - rate))


@dataclass
class Model:
    weights: np.ndarray
    trees: BoostedTrees


@lru_cache(maxsize=1)
def model(pages: int = 1800, seed: int = 5) -> Model:
    data = training_pages(pages, seed)
    weights = token_weights(data[::2])
    rest = data[1::2]
    return Model(weights, BoostedTrees().fit(np.concatenate([p.features(weights) for p, _ in rest]), np.concatenate([t for _, t in rest])))


def extract_texts(htmls: list[str], learned: Model) -> list[str]:
    pages = [Page(h) for h in htmls]
    if not pages:
        return []
    x = [p.features(learned.weights) for p in pages]
    cuts = np.cumsum([len(a) for a in x])[:-1]
    return [page.extract(p) for page, p in zip(pages, np.split(learned.trees.predict(np.concatenate(x)), cuts), strict=True)]


def extract(pages: DataFrame, learned: Model | None = None) -> DataFrame:
    """page_id, url, text and n_chars; one pass, no shuffle."""
    spark = common.session_of(pages)
    sent = spark.sparkContext.broadcast(learned or model())  # kilobytes
    rows = common.only(pages, "page_id", "url", "html")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for at in range(0, whole.num_rows, 128):
                batch = whole.slice(at, 128)
                texts = extract_texts([h or "" for h in batch.column("html").to_pylist()], sent.value)
                yield pa.RecordBatch.from_arrays(
                    [batch.column("page_id"), batch.column("url"), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], names=["page_id", "url", "text", "n_chars"]
                )

    return common.map_arrow(rows, run, "page_id long, url string, text string, n_chars long")
