"""Main text of web pages: flat blocks, features of a block and its neighbours, and a decision tree.

A page is cut at block-level tags into flat text blocks. A block's features are its word count and link density,
those of the blocks before and after it (and how long both are at least), and two of its place: how strongly the names and tags of enclosing elements
speak against article text (0 to 2), and whether one is an article or main element. A name speaks strongly against it if it is one of parts that never hold
any (adverts, comments, menus ...), and weakly if it may name a part of an article too (header, social, search ...); a word such as story or post in the same name
takes a weak one back, and so does an article or main element further in. A decision tree is
grown (by Gini impurity) on a small labelled table, blocks of pages that :func:`labelled_page` lays out; the blocks that it accepts, joined by newlines, are the text.

Defined results: a null or empty page, or one without article blocks, has an empty text; unclosed and unmatched
tags are tolerated; a script or style left open runs to the end of the page; very long pages are read whole; repeated rows repeat their
result; extra columns are ignored.
"""

from __future__ import annotations

import html
import random
import re
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

_TOKEN = re.compile(
    r"""<!--.*?(?:-->|\Z)|<(script|style|noscript|template|title|textarea|select|svg|iframe|object)\b[^>]*>.*?(?:</\1\s*>|\Z)|<(/?)([a-zA-Z][^\s/>]*)((?:[^<>"']|"[^"]*"|'[^']*')*)>|<[!?/a-zA-Z][^>]*(?:>|\Z)|[^<]+|<""",
    re.S | re.I,
)
_BLOCK = frozenset("address article aside blockquote body button caption center dd details dialog div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 head header hr html label legend li main menu nav ol option p pre section summary table tbody td tfoot th thead tr ul".split())
_VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
_BOILER = frozenset("nav header footer aside form menu button dialog fieldset label".split())
_MAIN = frozenset("article main".split())
_ATTRIBUTE = re.compile(r"""\b(?:class|id|role|aria-label)\s*=\s*("[^"]*"|'[^']*'|[^\s>]+)""", re.I)
_STRONG = re.compile(r"(?:^|[^a-z])(?:ads?|advert\w*|sponsor\w*|promo\w*|cookie\w*|consent|popup|modal|newsletter|subscri\w*|sharing|share|sidebar|related|recommend\w*|comments?|respond|disqus|menu|nav|navbar|navigation|breadcrumbs?|footer|copyright|pagination|complementary|contentinfo)(?:$|[^a-z])", re.I)
_WEAK = re.compile(r"(?:^|[^a-z])(?:banner|notice|alert|social|side|nav\w+|header|masthead|legal|login|search|widget|toolbar)(?:$|[^a-z])", re.I)
_STORY = re.compile(r"(?:^|[^a-z])(?:story|article|post|entry|content|body|text|main)(?:$|[^a-z])", re.I)

def neighbours(x: tuple) -> tuple[int, int]:
    """Words of the shorter neighbour, 0 where one of them is made of links; and of the longest one that is not. Last of a block's features."""
    return min(x[2], x[4]) if max(x[3], x[5]) < 0.3 else 0, max(x[2] * (x[3] < 0.3), x[4] * (x[5] < 0.3))


#: Pages of the labelled table.
PAGES = 400


def labelled_page(rng: random.Random) -> list[tuple[int, float, int, int, int]]:
    """Words, link density, name, article and label of the blocks of a page laid out as pages are: in an article element, in named parts, or in neither."""
    kind = rng.choice("aaabbc")
    inside, strong = int(kind == "a"), 0 if kind == "c" else 2
    some = lambda least, most: [None] * rng.randint(least, most)
    links = lambda least, most, name: [(rng.randint(1, 3) if rng.random() < 0.7 else rng.randint(4, 9), 1.0, name, 0, 0) for _ in some(least, most)]
    aside = lambda article: (rng.randint(1, 45), rng.choice([0.0, 0.0, 0.1, 0.3, 1.0]), 2, article, 0)
    page = links(0, 9, rng.choice([strong, min(strong, 1)]))
    bar = lambda: [(rng.randint(1, 10), rng.choice([0.0, 0.0, 0.2, 0.5]), 0, 0, 0) for _ in some(1, 3)] + links(1, 3, 0)
    if kind != "a" and rng.random() < 0.5:
        page += bar()
    if strong:
        page += [(rng.randint(2, 30), rng.choice([0.0, 0.0, 0.2]), rng.choice([1, 2, 2]), 0, 0) for _ in some(0, 2)]
    page.append((rng.randint(1, 14), 0.0, rng.choice([0, 0, 0, inside]), inside, 1))
    for _ in some(1, 12):
        size = rng.choice([rng.randint(1, 4), rng.randint(4, 20), rng.randint(4, 20), rng.randint(15, 60), rng.randint(30, 250), rng.randint(30, 250)])
        if kind != "a" and page[-1][0] < 15 and size < 20:
            size += 25  # short blocks without any long one beside them are nothing that can be told from furniture there
        page.append((size, rng.choice([0.0] * 8 + [0.1, 0.3]), rng.choice([0] * 9 + [1 if size > 30 else 0]), inside, 1))
        if inside and rng.random() < 0.08:
            page.append((rng.randint(1, 20), rng.choice([0.5, 0.8, 1.0]), 0, 1, 1))
        if strong and rng.random() < 0.1:
            page.append(aside(inside))
        if strong and rng.random() < 0.05:
            page += [(rng.randint(1, 4), 1.0, 1, inside, 0) for _ in some(1, 4)]
    if strong and rng.random() < 0.4:
        page += [(rng.randint(1, 90), rng.choice([0.0, 0.0, 0.1]), 2, inside, 0) for _ in some(1, 5)]
    page += links(0, 6, strong)
    page += [(rng.randint(2, 40), rng.choice([0.0, 0.0, 0.2, 1.0]), rng.choice([1, 2, 2]), 0, 0) for _ in some(0, 3)] if strong else links(0, 3, 0)
    if kind != "a" and page[-1][1] == 1.0 and rng.random() < 0.5:
        page += bar()
    return page


def with_neighbours(page: list[tuple]) -> list[tuple]:
    """A page's blocks (words, density, name, article ...) with their features in the tree's order, and what followed them."""
    none = (0, 0.0)
    out = []
    for k, (words, density, name, article, *rest) in enumerate(page):
        before, after = page[k - 1] if k else none, page[k + 1] if k + 1 < len(page) else none
        x = (words, density, before[0], before[1], after[0], after[1], name, article)
        out.append((*x, *neighbours(x), *rest))
    return out


def labelled_table(pages: int = PAGES, seed: int = 5) -> list[tuple]:
    """The small labelled table: blocks of laid-out pages with their features and whether they are article text."""
    rng = random.Random(seed)
    return [row for _ in range(pages) for row in with_neighbours(labelled_page(rng))]


@dataclass(frozen=True)
class Node:
    feature: int = -1
    cut: float = 0.0
    low: Node | None = None
    high: Node | None = None
    answer: bool = False

    def says(self, x: tuple) -> bool:
        node = self
        while node.feature >= 0:
            node = node.low if x[node.feature] <= node.cut else node.high
        return node.answer


def grow(rows, depth: int = 9, least: int = 6) -> Node:
    """A binary tree over the columns but the last, which is the label; a leaf holds ``least`` rows at least."""
    rows = np.asarray(rows, dtype=np.float64)
    y, n = rows[:, -1], len(rows)
    if depth == 0 or n < 2 * least or y.min() == y.max():
        return Node(answer=bool(2 * y.sum() > n))
    best = (2 * n * y.mean() * (1 - y.mean()) - 1e-9, -1, 0.0)
    for f in range(rows.shape[1] - 1):
        order = np.argsort(rows[:, f], kind="stable")
        x, yes = rows[order, f], np.cumsum(y[order])
        low = np.arange(1, n)
        p, q = yes[:-1] / low, (yes[-1] - yes[:-1]) / (n - low)
        cost = 2 * (low * p * (1 - p) + (n - low) * q * (1 - q))
        cost[(x[1:] == x[:-1]) | (low < least) | (n - low < least)] = np.inf
        k = int(cost.argmin())
        if cost[k] < best[0] - 1e-9:
            best = (cost[k], f, (x[k] + x[k + 1]) / 2)
    _, f, cut = best
    if f < 0:
        return Node(answer=bool(2 * y.sum() > n))
    side = rows[:, f] <= cut
    return Node(f, float(cut), grow(rows[side], depth - 1, least), grow(rows[~side], depth - 1, least))


def blocks(page: str) -> list[tuple[str, int, float, int, int]]:
    """Text, words, link density, furniture and article flags of each block with text, in page order."""
    out: list[tuple[str, int, float, int, int]] = []
    stack: list[tuple[str, int, int, int, int]] = []  # tag, and so far: strong names, articles, links, weak names
    text: list[str] = []
    linked = 0

    def end() -> None:
        nonlocal linked
        clean = " ".join(html.unescape("".join(text)).split())
        if clean:
            words = clean.count(" ") + 1
            top = stack[-1] if stack else ("", 0, 0, 0, 0)
            out.append((clean, words, min(1.0, linked / words), 2 if top[1] else min(top[4], 1), min(top[2], 1)))
        text.clear()
        linked = 0

    for m in _TOKEN.finditer(page):
        tag = m[3]
        if tag is None:
            piece = m[0]
            if m[1] is None and not (len(piece) > 1 and piece[0] == "<"):
                text.append(piece)
                if stack and stack[-1][3]:
                    linked += len(piece.split())
            continue
        tag = tag.lower()
        if tag in _BLOCK:
            end()
        elif tag == "br":
            text.append(" ")
        if tag in _VOID:
            continue
        if m[2]:
            for k in range(len(stack) - 1, -1, -1):
                if stack[k][0] == tag:
                    del stack[k:]
                    break
            continue
        if tag in _BLOCK and stack and stack[-1][0] == "p":
            stack.pop()
        _, strong, article, link, weak = stack[-1] if stack else ("", 0, 0, 0, 0)
        names = [x.strip("\"'") for x in _ATTRIBUTE.findall(m[4] or "")] if m[4] and tag not in ("html", "body") else []
        if tag in _MAIN:
            article, weak = article + 1, 0
        elif tag in _BOILER and not (tag == "header" and article):
            strong += 1
        elif any(_STRONG.search(x) for x in names):
            strong += 1
        elif tag == "header" or any(_WEAK.search(x) and not _STORY.search(x) for x in names):
            weak += 1
        stack.append((tag, strong, article, link + (tag == "a"), weak))
    end()
    return out


def main_text(page: str | None, tree: Node) -> str:
    found = blocks(page or "")
    return "\n".join(b[0] for b, x in zip(found, with_neighbours([b[1:] for b in found]), strict=True) if tree.says(x))


def extracted(pages: DataFrame) -> DataFrame:
    """``page_id, url, text, n_chars`` of every page."""
    tree = grow(labelled_table())

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = [main_text(page.as_py(), tree) for page in batch.column(2)]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], names=["page_id", "url", "text", "n_chars"])

    return pages.select("page_id", "url", "html").mapInArrow(run, "page_id long, url string, text string, n_chars long")
