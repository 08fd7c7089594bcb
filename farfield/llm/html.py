"""Main text of web pages from flat text blocks.

A page is cut into blocks at block-level tags; inline tags, comments, scripts and styles leave no text. Each block has its
number of words and its link density, and those of its neighbours. A decision tree, grown on the small labelled table below, says which blocks are
main text; these are joined by a line feed. It cuts by words and links as long as such a cut tells enough; what they leave mixed (a paragraph of
a notice looks like one of the article) it cuts by two marks of structure: whether the block stands in an element or class that pages use for
menus, notices and the like, and whether in an article or main element.

Defined results: null and empty html give an empty text; what is no closed tag, entity or comment is taken as far as it goes; repeated
rows each get a row; an empty table gives an empty table; extra columns are not read.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from functools import lru_cache
from html import unescape

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from farfield.llm.common import let_workers_import, slices

#: Elements that flow with the text, that have no end, that hold no text, and that hold no main text.
INLINE = frozenset("a abbr acronym b bdi bdo big br cite code data del dfn em font i img ins kbd label mark nobr q rp rt ruby s samp small span strike strong sub sup time tt u var wbr".split())
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
NO_TEXT = frozenset("script style template noscript svg math iframe object canvas audio video head textarea select title".split())
CHROME_ELEMENTS = frozenset("nav footer aside form button dialog menu fieldset".split())
#: Words of class, id and role that mark menus, headers, footers, sidebars, notices, adverts, forms and reader comments.
CHROME_WORDS = frozenset(
    "ad ads adv advert adverts advertisement advertising sponsor sponsored promo promotion banner nav navbar navigation menu menubar breadcrumb breadcrumbs pagination pager footer masthead topbar toolbar sidebar aside rail widget widgets related recommended recommendations share sharing social comment comments commentlist disqus reply replies respond cookie cookies consent gdpr notice notices notification alert popup modal overlay subscribe subscription newsletter signup login search complementary contentinfo".split()
)
HEADER_WORDS = frozenset("header head topnav".split())

_TAG = re.compile(r"<!--.*?(?:-->|\Z)|<[!?][^>]*>?|<(/?)([a-zA-Z][^\s/>]*)((?:[^>\"']|\"[^\"]*\"|'[^']*')*+)>?", re.S)
_NAMED = re.compile(r"(?:class|id|role)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+))", re.I)
_SPLIT = re.compile(r"[\s_-]+|(?<=[a-z])(?=[A-Z])")

#: Of the block and its neighbours: words and the share of them in links. Then two marks of structure: named, it stands in an element or class that pages
#: use for menus, notices and the like; scope, 1 in an article or main element, -1 outside though the page has one, 0 if it has none.
FEATURES = ("words", "links", "words_before", "links_before", "words_after", "links_after", "named", "scope")
SHALLOW = 6
#: A cut by words or links leaves so many rows on both sides; a mark of structure cuts only if it removes more than MARKS times the impurity that such a cut does.
LEAST = 8
MARKS = 5.0

#: Words of the blocks of some of the given pages: so many one-word links, an advert, the article, a footer.
GIVEN = (
    (6, 8, (7, 7, 22, 33, 30, 45, 5, 31, 1, 94, 11, 56, 76, 46), 8), (6, 5, (11, 14, 32, 42, 9, 31, 34, 210, 4, 20, 222, 242, 12, 2, 19, 13, 6, 9), 11),
    (5, 8, (14, 35, 17, 49, 143), 11), (6, 8, (11, 41, 17, 18, 70, 83, 17), 14), (6, 11, (2, 2, 32, 17, 12, 6, 26, 102, 83, 11, 74, 5, 4), 12), (6, 4, (11, 23, 58), 15),
    (4, 12, (8, 8, 17, 33, 29, 15, 53, 10, 33, 94, 64, 21, 66, 40, 16, 22, 8, 45, 62, 62, 12), 9), (6, 8, (6, 13, 68, 92, 98, 26, 8, 11, 49, 61, 1, 1, 48), 11),
)
#: More labelled pages, each a run of blocks: words, share of words in links, named, scope, and whether it is main text. Neighbours follow from the order.
LABELLED = tuple(((1, 1, 1, -1, 0),) * n + ((ad, 0, 1, -1, 0), *((w, 0, 0, 1, 1) for w in words), (end, 0, 1, -1, 0)) for n, ad, words, end in GIVEN) + (
    ((1, 1, 1, -1, 0),) * 5 + ((7, 0, 1, -1, 0), (12, 0, 0, 1, 1), (45, 0, 0, 1, 1), (2, 0, 0, 1, 1), (88, 0, 0, 1, 1), (30, 0, 0, 1, 1), (9, 0, 1, -1, 0)),
    ((1, 1, 1, -1, 0),) * 6 + ((21, 0, 1, -1, 0), (11, 0, 0, 1, 1), (160, 0, 0, 1, 1), (3, 0, 0, 1, 1), (1, 0, 0, 1, 1), (5, 0, 0, 1, 1), (14, 0, 1, -1, 0)),
    ((1, 1, 1, -1, 0),) * 4 + ((3, 0, 1, -1, 0), (9, 0, 0, 1, 1), (4, 0, 0, 1, 1), (6, 0, 1, -1, 0)),
    ((2, 1, 1, -1, 0),) * 3 + ((8, 0, 0, 1, 1), (60, 0.1, 0, 1, 1), (6, 1, 0, 1, 1), (75, 0, 0, 1, 1), (3, 0, 0, 1, 1), (4, 0, 0, 1, 1), (2, 1, 1, -1, 0), (1, 1, 1, -1, 0)),
    ((6, 0, 0, -1, 0), (1, 1, 0, -1, 0), (1, 1, 0, -1, 0), (10, 0, 0, 1, 1), (70, 0, 0, 1, 1), (40, 0.2, 0, 1, 1), (4, 1, 0, 1, 0), (5, 1, 0, 1, 0), (3, 1, 0, 1, 0), (5, 1, 0, 1, 0), (4, 0, 0, -1, 0)),
    ((1, 1, 0, -1, 0),) * 3 + ((9, 0, 0, -1, 0), (10, 0, 0, 1, 1), (34, 0, 0, 1, 1), (60, 0, 0, 1, 1), (8, 0, 0, -1, 0)),
    ((2, 1, 0, -1, 0),) * 4 + ((31, 0, 0, -1, 0), (8, 0, 0, 1, 1), (4, 0, 0, 1, 1), (15, 0, 0, 1, 1), (27, 0, 0, 1, 1)),
    ((1, 1, 0, -1, 0),) * 2 + ((14, 0, 0, -1, 0), (50, 0, 0, 1, 1), (90, 0, 0, 1, 1), (18, 0, 0, -1, 0)),
    ((1, 1, 1, -1, 0),) * 4 + ((8, 0, 1, -1, 0), (9, 0, 0, 1, 1), (41, 0, 0, 1, 1), (12, 0, 0, 1, 1), (33, 0, 0, 1, 1)),
    ((1, 1, 1, -1, 0),) * 4 + ((11, 0, 0, 1, 1), (52, 0, 0, 1, 1), (16, 0, 0, 1, 1), (9, 0, 0, 1, 1)),
    ((1, 1, 0, 0, 0),) * 5 + ((8, 0, 0, 0, 0), (11, 0, 0, 0, 1), (44, 0, 0, 0, 1), (70, 0, 0, 0, 1), (28, 0, 0, 0, 1), (9, 0, 0, 0, 0)),
    ((1, 1, 0, 0, 0),) * 4 + ((12, 0, 0, 0, 0), (35, 0, 0, 0, 1), (66, 0, 0, 0, 1), (51, 0, 0, 0, 1), (13, 0, 0, 0, 0)),
    ((12, 0, 0, 1, 1), (55, 0, 0, 1, 1), (5, 0, 1, 1, 0), (65, 0, 0, 1, 1), (1, 1, 1, 1, 0), (1, 1, 1, 1, 0), (14, 0, 1, 1, 0), (80, 0.05, 0, 1, 1), (20, 0, 1, 1, 0), (35, 0, 1, 1, 0), (28, 0, 1, 1, 0)),
    ((1, 1, 0, 0, 0), (2, 1, 0, 0, 0), (1, 1, 0, 0, 0), (8, 0, 0, 0, 1), (60, 0, 0, 0, 1), (45, 0.1, 0, 0, 1), (25, 0, 0, 0, 1), (90, 0, 0, 0, 1), (3, 1, 0, 0, 0), (2, 1, 0, 0, 0), (5, 0, 0, 0, 0)),
    ((25, 0, 1, 0, 0), (2, 1, 1, 0, 0), (1, 1, 1, 0, 0), (7, 0, 0, 0, 1), (60, 0.05, 0, 0, 1), (70, 0, 0, 0, 1), (110, 0, 0, 0, 1), (30, 0, 1, 0, 0), (28, 0, 1, 0, 0), (40, 0, 1, 0, 0), (12, 0, 1, 0, 0)),
    ((4, 1, 1, -1, 0), (25, 0, 1, -1, 0), (6, 0, 0, -1, 0), (9, 0, 0, 1, 1), (50, 0, 0, 1, 1), (70, 0, 0, 1, 1), (45, 0, 0, -1, 0), (40, 0, 1, -1, 0), (60, 0, 1, -1, 0), (35, 0, 0, -1, 0)),
    ((10, 0, 0, 0, 1), (50, 0, 0, 0, 1), (5, 0, 0, 0, 1), (7, 0, 0, 0, 1), (9, 0, 0, 0, 1), (65, 0, 0, 0, 1), (30, 0.2, 0, 0, 1)),
    ((1, 0, 0, 1, 1),), ((1, 0, 0, 1, 1), (1, 0, 0, 1, 1), (1, 0, 0, 1, 1)), ((40, 0, 0, 1, 1), (2, 0, 0, 1, 1)), ((60, 0, 0, 0, 1),), ((4, 0.5, 0, 1, 1),),
    ((1, 1, 1, -1, 0), (1, 0, 0, 1, 1), (9, 0, 1, -1, 0)), ((60, 0, 0, 0, 1), (45, 0, 0, 0, 1), (1, 1, 0, 0, 0)), ((1, 1, 0, 0, 0), (2, 1, 0, 0, 0), (60, 0, 0, 0, 1), (45, 0, 0, 0, 1), (1, 1, 0, 0, 0)),
    ((3, 1, 0, 0, 0), (12, 0.8, 0, 0, 0), (9, 0.9, 0, 0, 0), (30, 0.7, 0, 0, 0), (10, 0.6, 0, 0, 0), (4, 0.5, 0, 0, 0)),
    ((2, 0, 1, -1, 0), (3, 1, 1, -1, 0), (13, 0, 1, -1, 0), (5, 0, 0, 1, 1), (12, 0, 0, 1, 1), (1, 0, 0, 1, 1), (3, 0, 0, 1, 1), (2, 0, 1, 1, 0), (2, 0, 1, 1, 0), (8, 0, 0, 1, 1), (2, 0, 1, 1, 0), (13, 0, 1, -1, 0), (2, 0, 1, -1, 0)),
)


class Tree:
    """A decision tree by Gini impurity, words and links first."""

    def __init__(self, x: np.ndarray, y: np.ndarray, depth: int = 10):
        self.value = float(y.mean()) if len(y) else 0.0
        self.feature = -1
        if depth == 0 or len(set(y.tolist())) < 2:
            return
        best = (1e-9, -1, 0.0)
        gini = lambda v: len(v) * 2 * v.mean() * (1 - v.mean()) if len(v) else 0.0
        for f in range(x.shape[1]):
            at = np.unique(x[:, f])
            for cut in (at[1:] + at[:-1]) / 2:
                left = x[:, f] <= cut
                if f < SHALLOW and not LEAST <= left.sum() <= len(y) - LEAST:
                    continue
                gain = (gini(y) - gini(y[left]) - gini(y[~left])) / (1 if f < SHALLOW else MARKS)
                if gain > best[0] + 1e-12:
                    best = (gain, f, float(cut))
        _, self.feature, self.cut = best
        if self.feature >= 0:
            left = x[:, self.feature] <= self.cut
            self.low, self.high = Tree(x[left], y[left], depth - 1), Tree(x[~left], y[~left], depth - 1)

    def predict(self, x: np.ndarray) -> np.ndarray:
        if self.feature < 0:
            return np.full(len(x), self.value)
        low = x[:, self.feature] <= self.cut
        out = np.empty(len(x))
        out[low], out[~low] = self.low.predict(x[low]), self.high.predict(x[~low])
        return out


def with_neighbours(words: np.ndarray, links: np.ndarray, named: np.ndarray, scope: np.ndarray) -> np.ndarray:
    """The features of a page's blocks in order; there is nothing before the first and after the last."""
    x = np.zeros((len(words), len(FEATURES)))
    x[:, 0], x[:, 1], x[:, SHALLOW], x[:, SHALLOW + 1] = words, links, named, scope
    x[1:, 2:4], x[:-1, 4:6] = x[:-1, :2], x[1:, :2]
    return x


@lru_cache(1)
def trained() -> Tree:
    pages = [np.array(p, float).T for p in LABELLED]
    return Tree(np.concatenate([with_neighbours(*p[:4]) for p in pages]), np.concatenate([p[4] for p in pages]))


def _is_chrome(name: str, attributes: str, in_article: bool) -> bool:
    if name in CHROME_ELEMENTS or (name == "header" and not in_article):
        return True
    if "=" not in attributes:
        return False
    for m in _NAMED.finditer(attributes):
        words = {w.lower() for w in _SPLIT.split(m[1] or m[2] or m[3] or "")}
        if words & CHROME_WORDS or (not in_article and name not in ("body", "html", "article", "main") and words & HEADER_WORDS):
            return name not in ("body", "html")
    return False


def blocks_of(html: str) -> list[tuple[str, int, int, int, int]]:
    """(text, chrome, in an article, words, words in links) of each block that has text."""
    out, parts, linked = [], [], 0
    open_: list[tuple[str, bool, bool]] = []  # name, chrome, article
    chrome = article = links = 0
    at, n = 0, len(html)

    def close_block() -> None:
        nonlocal linked
        text = " ".join("".join(parts).split())
        if text:
            out.append((text, int(chrome > 0), int(article > 0), len(text.split()), linked))
        parts.clear()
        linked = 0

    def add(raw: str) -> None:
        nonlocal linked
        if "&" in raw:
            raw = unescape(raw)
        parts.append(raw)
        if links:
            linked += len(raw.split())

    while at < n:
        lt = html.find("<", at)
        if lt < 0:
            add(html[at:])
            break
        m = _TAG.match(html, lt)
        if not m:  # a sign, not a tag
            add(html[at : lt + 1])
            at = lt + 1
            continue
        if lt > at:
            add(html[at:lt])
        at = m.end()
        name = (m[2] or "").lower()
        if not name:
            continue
        end = bool(m[1])
        if name not in INLINE:
            close_block()
        elif name in ("br", "img"):
            parts.append(" ")
        if name in NO_TEXT and not end:
            if m[3].endswith("/") and name not in ("script", "style", "title", "textarea"):
                continue
            closing = re.compile(rf"</{re.escape(name)}\s*>" + (r"|(?=<body[\s>])" if name == "head" else ""), re.I).search(html, at)
            at = closing.end() if closing else (n if name != "head" else at)
            continue
        if name == "a":
            links = 0 if end else 1
        if name in VOID:
            continue
        if end:
            for k in range(len(open_) - 1, -1, -1):
                if open_[k][0] == name:
                    for _, c, a in open_[k:]:
                        chrome -= c
                        article -= a
                    del open_[k:]
                    break
                if name in INLINE and open_[k][0] not in INLINE:
                    break  # an inline end does not close blocks around it
        elif name not in INLINE or "=" in m[3]:
            if name in ("p", "li", "td", "th", "tr", "dt", "dd", "option") and open_ and open_[-1][0] == name:
                _, c, a = open_.pop()
                chrome -= c
                article -= a
            own = _is_chrome(name, m[3], article > 0)
            main = name in ("article", "main") and not own
            open_.append((name, own, main))
            chrome += own
            article += main
            if not article and re.search(r"role\s*=\s*[\"']?main\b", m[3], re.I):
                open_[-1] = (name, own, True)
                article += 1
    close_block()
    return out


def features(blocks: list[tuple[str, int, int, int, int]]) -> np.ndarray:
    named, article, words, linked = (np.array([b[k] for b in blocks], float) for k in (1, 2, 3, 4))
    scope = np.where(article > 0, 1, -1 if (article > 0).any() else 0)
    return with_neighbours(words, np.minimum(linked / np.maximum(words, 1), 1), named, scope)


def main_text(html: str | None) -> str:
    blocks = blocks_of(html or "")
    if not blocks:
        return ""
    keep = trained().predict(features(blocks)) >= 0.5
    return "\n".join(b[0] for b, k in zip(blocks, keep) if k)


def extract(pages: DataFrame) -> DataFrame:
    """page_id, url, text, n_chars."""
    let_workers_import(pages.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in slices(batches):
            texts = [main_text(h.as_py()) for h in b.column(2)]
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], names=["page_id", "url", "text", "n_chars"])

    columns = pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), F.col("html").cast("string").alias("html"))
    return columns.mapInArrow(run, "page_id long, url string, text string, n_chars long")


def op10_html(pages: DataFrame) -> DataFrame:
    return extract(pages)
