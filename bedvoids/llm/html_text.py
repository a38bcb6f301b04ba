"""Main text of web pages: flat blocks, their neighbours, and a decision tree.

A page becomes a row of text blocks, split at block-level tags, without scripts, styles, comments and
other parts that aren't shown. A block is described by its words, link density, and where it stands (the
kind of the innermost container that says so: article-like, page furniture, or neither; paragraph, heading,
list item or bare text; words in the names of containers up to that one), and by words and link density of the
blocks before and after. Names of an article's own element and of those around it say nothing about its blocks, nor
do names that only say what a page has (with-sidebar, has-comments, search-page). A decision tree, grown on the labelled blocks of LABELLED by Gini impurity, tells text from the
rest; its blocks are joined in page order by one space.

Null and empty pages have no text. Repeated rows are rows of their own; extra columns are ignored.
"""

from __future__ import annotations

import html
import re
from collections.abc import Iterator
from typing import NamedTuple

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

# Element names of HTML by their part in a page.
BLOCK_TAGS = frozenset("address article aside blockquote body br center dd details dialog dir div dl dt fieldset figcaption figure footer form frameset h1 h2 h3 h4 h5 h6 head header hgroup hr html legend li main menu nav noscript ol optgroup option p pre section select summary table tbody td tfoot th thead title tr ul".split())
HIDDEN_TAGS = frozenset("script style noscript template head title iframe object svg math canvas audio video textarea select button option datalist".split())
RAW_TAGS = frozenset("script style textarea title iframe noembed noframes xmp".split())
VOID_TAGS = frozenset("area base br col embed hr img input link meta param source track wbr".split())
TEXT_TAGS = frozenset("article main".split())
SIDE_TAGS = frozenset("nav header footer aside form menu dialog".split())
HEADINGS = frozenset("h1 h2 h3 h4 h5 h6".split())
SIDE_WORDS = frozenset("ad ads advert adverts advertisement banner breadcrumb breadcrumbs comment comments cookie cookies consent disqus footer header login masthead menu modal nav navbar navigation newsletter notice pager pagination popup popular promo promoted recommended related replies reply rss search share sharing shoutbox sidebar signup skip social sponsor sponsored subscribe tags toolbar widget".split())

#: In a class or id name these say that a container has something, or is a page of a kind, not that it is that thing.
HAS_WORDS = frozenset("has have with without no page layout template".split())

_TOKEN = re.compile(r"<!--.*?(?:-->|\Z)|<!\[CDATA\[.*?(?:\]\]>|\Z)|<[!?][^>]*(?:>|\Z)|</([a-zA-Z][^\s/>]*)[^>]*(?:>|\Z)|<([a-zA-Z][^\s/>]*)((?:[^>\"']|\"[^\"]*\"|'[^']*')*)(?:>|\Z)", re.S)
_NAMES = re.compile(r"(?:^|\s)(class|id|role|style|hidden|aria-hidden)(?:\s*=\s*(\"[^\"]*\"|'[^']*'|[^\s>]+))?", re.I)
_WORDS = re.compile(r"[a-zA-Z]+")

FEATURES = ("words", "links", "words_before", "links_before", "words_after", "links_after", "inside", "side", "kind", "marked")


class Block(NamedTuple):
    text: str
    words: int
    links: float
    inside: int  # 1 in an article-like element that is nearer than any page furniture
    side: int  # 1 in page furniture
    kind: int  # 0 bare, 1 paragraph, 2 heading, 3 list item, 4 table cell
    marked: int  # 1 if class, id or role of an element around it, nearer than any article-like one, names page furniture


def is_furniture(name: str) -> bool:
    """Whether a class, id or role names a part of the page that isn't its text."""
    words = {*_WORDS.findall(name)}
    return bool(words & SIDE_WORDS) and not words & HAS_WORDS


def blocks(page: str) -> list[Block]:
    out: list[Block] = []
    stack: list[tuple[str, bool, bool, bool]] = []  # tag, hidden, furniture, marked
    parts: list[str] = []
    links: list[str] = []
    state = {"link": 0, "hidden": 0}

    def flush() -> None:
        text = " ".join(html.unescape("".join(parts)).split())
        linked = len(" ".join(html.unescape("".join(links)).split()).split())
        parts.clear()
        links.clear()
        if not text:
            return
        n = len(text.split())
        inside = side = marked = 0
        for tag, _, furniture, named in reversed(stack):
            marked |= int(named and tag not in TEXT_TAGS)
            if furniture or tag in TEXT_TAGS:
                inside, side = int(tag in TEXT_TAGS and not furniture), int(furniture)
                break
        names = [s[0] for s in stack]
        kind = 2 if HEADINGS & {*names} else 3 if "li" in names else 4 if "td" in names or "th" in names else 1 if "p" in names else 0
        out.append(Block(text, n, min(1.0, linked / n), inside, side, kind, marked))

    def close(tag: str) -> None:
        while stack:
            top = stack.pop()
            state["hidden"] -= top[1]
            state["link"] -= top[0] == "a"
            if top[0] == tag:
                return

    def add(text: str) -> None:
        if text and not state["hidden"]:
            parts.append(text)
            if state["link"]:
                links.append(text)
            elif links and not text.isspace():
                links.append(" ")

    at = 0
    while True:
        m = _TOKEN.search(page, at)
        add(page[at : m.start()] if m else page[at:])
        if not m:
            break
        at = m.end()
        if m[0].startswith("<![CDATA["):
            add(m[0][9:].removesuffix("]]>"))
        elif m[1]:
            tag = m[1].lower()
            if tag in BLOCK_TAGS:
                flush()
            if any(s[0] == tag for s in stack):
                # an inline end tag doesn't close the block around it
                reach = next(i for i in range(len(stack) - 1, -1, -1) if stack[i][0] == tag)
                if tag in BLOCK_TAGS or not any(s[0] in BLOCK_TAGS for s in stack[reach:]):
                    close(tag)
                else:
                    gone = stack.pop(reach)
                    state["hidden"] -= gone[1]
                    state["link"] -= gone[0] == "a"
        elif m[2]:
            tag = m[2].lower()
            names = {k.lower(): (v or "").strip("\"'").lower() for k, v in _NAMES.findall(m[3] or "")} if m[3] else {}
            if tag in BLOCK_TAGS:
                flush()
            if tag in VOID_TAGS or m[0].endswith("/>"):
                continue
            if tag in ("p", "li", "td", "th", "tr", "dt", "dd", "option") or tag in BLOCK_TAGS and stack and stack[-1][0] == "p":
                limit = {"p": ("p",), "li": ("li",), "td": ("td", "th"), "th": ("td", "th"), "tr": ("tr", "td", "th"), "dt": ("dt", "dd"), "dd": ("dt", "dd"), "option": ("option",)}.get(tag, ("p",))
                for i in range(len(stack) - 1, -1, -1):
                    if stack[i][0] in limit:
                        for _ in range(len(stack) - i):
                            top = stack.pop()
                            state["hidden"] -= top[1]
                            state["link"] -= top[0] == "a"
                        if tag != "tr":
                            break
                    elif stack[i][0] in BLOCK_TAGS:
                        break
            if tag == "a" and state["link"]:
                close("a") if stack[-1][0] == "a" else None
            style = names.get("style", "").replace(" ", "")
            hidden = tag in HIDDEN_TAGS or "hidden" in names or names.get("aria-hidden") == "true" or "display:none" in style
            marked = tag not in ("body", "html") and any(is_furniture(name) for k in ("class", "id", "role") for name in names.get(k, "").split())
            furniture = tag in SIDE_TAGS and not (tag == "header" and any(s[0] in TEXT_TAGS for s in stack))
            stack.append((tag, hidden, furniture, marked))
            state["hidden"] += hidden
            state["link"] += tag == "a"
            if tag in RAW_TAGS:
                end = re.compile(rf"</{tag}\s*>?", re.I).search(page, at)
                if tag in HIDDEN_TAGS:
                    at = end.start() if end else len(page)
    flush()
    return out


def features(row: list[Block]) -> np.ndarray:
    x = np.zeros((len(row), len(FEATURES)))
    for i, b in enumerate(row):
        before, after = row[i - 1] if i else None, row[i + 1] if i + 1 < len(row) else None
        x[i] = (b.words, b.links, before.words if before else 0, before.links if before else 0, after.words if after else 0, after.links if after else 0, b.inside, b.side, b.kind, b.marked)
    return x


# Blocks labelled by hand, FEATURES in order and 1 for main text; from pages of several layouts.
LABELLED = np.array(
    [
        # menus, link lists, crumbs
        (1, 1.0, 0, 0.0, 1, 1.0, 0, 1, 3, 0, 0), (1, 1.0, 1, 1.0, 1, 1.0, 0, 1, 3, 0, 0), (2, 1.0, 1, 1.0, 9, 0.0, 0, 1, 3, 0, 0), (3, 1.0, 2, 1.0, 2, 1.0, 0, 0, 3, 1, 0), (4, 1.0, 3, 1.0, 3, 1.0, 0, 0, 3, 0, 0),
        (6, 1.0, 30, 0.0, 5, 1.0, 0, 0, 3, 0, 0), (8, 0.9, 0, 0.0, 12, 0.0, 0, 0, 1, 0, 0), (12, 0.9, 40, 0.0, 3, 0.0, 0, 0, 1, 0, 0), (5, 1.0, 60, 0.0, 5, 1.0, 1, 0, 3, 1, 0), (9, 0.8, 44, 0.0, 7, 1.0, 1, 0, 3, 1, 0),
        # adverts, notices, cookie bars, promotions
        (7, 0.0, 1, 1.0, 10, 0.0, 0, 0, 0, 1, 0), (10, 0.0, 1, 1.0, 12, 0.0, 0, 0, 0, 1, 0), (18, 0.0, 2, 1.0, 11, 0.0, 0, 0, 0, 1, 0), (25, 0.0, 1, 1.0, 9, 0.0, 0, 0, 1, 1, 0), (30, 0.1, 0, 0.0, 1, 1.0, 0, 0, 1, 1, 0),
        (14, 0.0, 50, 0.0, 60, 0.0, 1, 0, 0, 1, 0), (22, 0.2, 35, 0.0, 40, 0.0, 1, 0, 1, 1, 0), (6, 0.5, 20, 0.0, 35, 0.0, 1, 0, 2, 1, 0), (40, 0.0, 4, 0.0, 50, 0.0, 0, 0, 1, 1, 0), (55, 0.0, 3, 0.0, 2, 0.0, 0, 0, 1, 1, 0),
        # footers, headers, sidebars, forms
        (9, 0.0, 45, 0.0, 0, 0.0, 0, 1, 0, 0, 0), (14, 0.0, 20, 0.0, 0, 0.0, 0, 1, 0, 0, 0), (20, 0.0, 8, 0.0, 0, 0.0, 0, 1, 0, 0, 0), (35, 0.0, 60, 0.0, 0, 0.0, 0, 1, 1, 0, 0), (4, 0.5, 0, 0.0, 1, 1.0, 0, 1, 2, 0, 0),
        (3, 0.0, 0, 0.0, 2, 1.0, 0, 1, 2, 1, 0), (28, 0.0, 5, 0.0, 30, 0.0, 0, 1, 1, 0, 0), (60, 0.0, 3, 0.0, 22, 0.0, 0, 1, 1, 1, 0), (2, 0.0, 60, 0.0, 3, 0.0, 0, 1, 0, 0, 0), (16, 0.0, 2, 0.0, 1, 0.0, 0, 1, 1, 0, 0),
        (3, 0.0, 25, 0.0, 40, 0.0, 0, 1, 2, 0, 0), (5, 0.0, 80, 0.0, 12, 0.0, 0, 0, 2, 1, 0), (12, 0.0, 5, 0.0, 33, 0.0, 0, 1, 3, 0, 0),
        # reader comments
        (15, 0.0, 2, 0.0, 2, 0.0, 0, 0, 1, 1, 0), (48, 0.0, 2, 0.0, 3, 0.0, 0, 0, 1, 1, 0), (33, 0.0, 3, 0.5, 3, 0.5, 1, 0, 1, 1, 0), (9, 0.0, 2, 0.0, 14, 0.0, 0, 0, 3, 1, 0), (70, 0.0, 2, 0.0, 2, 0.0, 0, 0, 0, 1, 0),
        # short leftovers outside of the text
        (2, 0.0, 1, 1.0, 1, 1.0, 0, 0, 0, 0, 0), (3, 0.0, 0, 0.0, 2, 1.0, 0, 0, 0, 0, 0), (4, 0.0, 9, 1.0, 6, 1.0, 0, 0, 1, 0, 0), (2, 0.0, 6, 1.0, 0, 0.0, 0, 0, 0, 0, 0), (1, 0.0, 3, 1.0, 5, 1.0, 0, 0, 4, 0, 0),
        # site names, dates, copyright lines and other short lines that stand bare outside of the text
        (4, 0.0, 0, 0.0, 30, 0.0, 0, 0, 0, 0, 0), (5, 0.0, 45, 0.0, 0, 0.0, 0, 0, 0, 0, 0), (3, 0.0, 60, 0.0, 0, 0.0, 0, 0, 0, 0, 0), (6, 0.0, 12, 0.0, 40, 0.0, 0, 0, 0, 0, 0), (2, 0.0, 30, 0.0, 25, 0.0, 0, 0, 0, 0, 0), (7, 0.0, 33, 0.0, 4, 0.0, 0, 0, 0, 0, 0),
        # headlines
        (5, 0.0, 8, 0.0, 40, 0.0, 1, 0, 2, 0, 1), (10, 0.0, 9, 0.0, 22, 0.0, 1, 0, 2, 0, 1), (1, 0.0, 7, 0.0, 9, 0.0, 1, 0, 2, 0, 1), (12, 0.0, 18, 0.0, 3, 0.0, 1, 0, 2, 0, 1), (8, 0.0, 1, 1.0, 50, 0.0, 1, 0, 2, 0, 1),
        (7, 0.0, 0, 0.0, 45, 0.0, 0, 0, 2, 0, 1), (9, 0.0, 3, 1.0, 60, 0.0, 0, 0, 2, 0, 1), (4, 0.0, 55, 0.0, 70, 0.0, 1, 0, 2, 0, 1), (6, 0.0, 60, 0.0, 48, 0.0, 0, 0, 2, 0, 1),
        # paragraphs
        (60, 0.0, 8, 0.0, 45, 0.0, 1, 0, 1, 0, 1), (25, 0.0, 40, 0.0, 30, 0.0, 1, 0, 1, 0, 1), (12, 0.0, 10, 0.0, 80, 0.0, 1, 0, 1, 0, 1), (1, 0.0, 50, 0.0, 30, 0.0, 1, 0, 1, 0, 1), (2, 0.0, 12, 0.0, 5, 0.0, 1, 0, 1, 0, 1),
        (3, 0.0, 1, 0.0, 14, 0.0, 1, 0, 1, 0, 1), (7, 0.0, 35, 0.0, 15, 0.0, 1, 0, 1, 0, 1), (90, 0.0, 5, 0.0, 10, 0.0, 1, 0, 1, 0, 1), (200, 0.0, 9, 0.0, 18, 0.0, 1, 0, 1, 0, 1), (40, 0.1, 30, 0.0, 55, 0.0, 1, 0, 1, 0, 1),
        (33, 0.2, 60, 0.0, 20, 0.1, 1, 0, 1, 0, 1), (10, 0.3, 40, 0.1, 38, 0.0, 1, 0, 1, 0, 1), (50, 0.0, 1, 1.0, 44, 0.0, 0, 0, 1, 0, 1), (38, 0.05, 42, 0.0, 51, 0.0, 0, 0, 1, 0, 1), (65, 0.0, 7, 0.0, 30, 0.0, 0, 0, 1, 0, 1),
        (22, 0.0, 33, 0.0, 47, 0.0, 0, 0, 1, 0, 1), (14, 0.0, 52, 0.0, 40, 0.0, 0, 0, 1, 0, 1), (80, 0.0, 0, 0.0, 60, 0.0, 0, 0, 0, 0, 1), (45, 0.0, 30, 0.0, 0, 0.0, 0, 0, 0, 0, 1), (18, 0.0, 70, 0.0, 9, 0.0, 1, 0, 0, 0, 1),
        (4, 0.0, 25, 0.0, 8, 0.0, 1, 0, 0, 0, 1), (20, 0.0, 0, 0.0, 0, 0.0, 0, 0, 0, 0, 1), (30, 0.0, 0, 0.0, 0, 0.0, 0, 0, 1, 0, 1),
        # headings and short paragraphs of pages that don't mark their text
        (4, 0.0, 1, 1.0, 30, 0.0, 0, 0, 2, 0, 1), (3, 0.0, 2, 1.0, 28, 0.0, 0, 0, 2, 0, 1), (6, 0.0, 25, 0.0, 18, 0.0, 0, 0, 2, 0, 1), (2, 0.0, 30, 0.0, 30, 0.0, 0, 0, 1, 0, 1), (4, 0.0, 28, 0.0, 12, 0.0, 0, 0, 1, 0, 1), (6, 0.0, 16, 0.0, 22, 0.0, 0, 0, 1, 0, 1), (3, 0.0, 45, 0.0, 4, 0.0, 0, 0, 1, 0, 1), (2, 0.0, 32, 0.0, 3, 0.0, 0, 0, 1, 0, 1), (9, 0.0, 3, 0.0, 20, 0.0, 0, 0, 1, 0, 1),
        # very short blocks of the text, and blocks before link lists
        (1, 0.0, 3, 0.0, 20, 0.0, 1, 0, 1, 0, 1), (2, 0.0, 2, 0.0, 2, 0.0, 1, 0, 1, 0, 1), (1, 0.0, 1, 0.0, 1, 0.0, 1, 0, 2, 0, 1), (2, 0.0, 5, 0.0, 0, 0.0, 1, 0, 1, 0, 1), (1, 0.0, 0, 0.0, 6, 0.0, 1, 0, 1, 0, 1),
        (30, 0.0, 40, 0.0, 5, 1.0, 1, 0, 1, 0, 1), (12, 0.0, 30, 0.0, 1, 1.0, 1, 0, 1, 0, 1), (2, 0.0, 4, 0.0, 4, 1.0, 1, 0, 2, 0, 1), (2, 0.0, 1, 1.0, 3, 0.0, 1, 0, 1, 0, 1), (1, 0.0, 9, 0.0, 2, 1.0, 1, 0, 1, 0, 1),
        (45, 0.0, 22, 0.0, 3, 1.0, 0, 0, 1, 0, 1), (26, 0.1, 31, 0.0, 2, 1.0, 0, 0, 1, 0, 1),
        (25, 0.0, 8, 1.0, 40, 0.0, 1, 0, 1, 0, 1), (18, 0.0, 9, 0.9, 6, 1.0, 1, 0, 1, 0, 1), (3, 0.0, 12, 0.9, 2, 1.0, 1, 0, 1, 0, 1), (7, 0.0, 6, 0.8, 30, 0.0, 1, 0, 2, 0, 1), (2, 0.0, 6, 1.0, 7, 1.0, 1, 0, 0, 0, 1),
        # lists, quotations and tables of the text
        (6, 0.0, 40, 0.0, 7, 0.0, 1, 0, 3, 0, 1), (9, 0.0, 6, 0.0, 8, 0.0, 1, 0, 3, 0, 1), (15, 0.1, 9, 0.0, 30, 0.0, 1, 0, 3, 0, 1), (3, 0.0, 20, 0.0, 3, 0.0, 1, 0, 4, 0, 1), (8, 0.0, 3, 0.0, 45, 0.0, 1, 0, 4, 0, 1), (30, 0.0, 20, 0.0, 28, 0.0, 0, 0, 3, 0, 1),
    ]
)


class Tree:
    """Binary decision tree, split by Gini impurity until nodes are pure."""

    def __init__(self, x: np.ndarray, y: np.ndarray):
        self.nodes: list[tuple[int, float, int, int]] = []  # feature, limit, left, right; feature -1: limit is the class
        self._grow(x, y)

    def _grow(self, x: np.ndarray, y: np.ndarray) -> int:
        at = len(self.nodes)
        self.nodes.append((-1, float(y.mean() >= 0.5), 0, 0))
        if y.min() == y.max():
            return at
        best = (np.inf, 0, 0.0)
        for f in range(x.shape[1]):
            values = np.unique(x[:, f])
            for limit in (values[1:] + values[:-1]) / 2:
                left = x[:, f] <= limit
                gini = sum(s.sum() * 2 * (p := y[s].mean()) * (1 - p) for s in (left, ~left))
                best = min(best, (gini, f, limit))
        if best[0] == np.inf:
            return at
        left = x[:, best[1]] <= best[2]
        a, b = self._grow(x[left], y[left]), self._grow(x[~left], y[~left])
        self.nodes[at] = (best[1], best[2], a, b)
        return at

    def predict(self, x: np.ndarray) -> np.ndarray:
        out = np.zeros(len(x), bool)
        todo = [(0, np.arange(len(x)))]
        while todo:
            node, rows = todo.pop()
            f, limit, a, b = self.nodes[node]
            if f < 0:
                out[rows] = limit > 0
            elif len(rows):
                left = x[rows, f] <= limit
                todo += [(a, rows[left]), (b, rows[~left])]
        return out


TREE = Tree(LABELLED[:, :-1], LABELLED[:, -1])


def main_text(page: str | None, tree: Tree = TREE) -> str:
    row = blocks(page or "")
    if not row:
        return ""
    keep = tree.predict(features(row))
    return " ".join(b.text for b, k in zip(row, keep, strict=True) if k)


def _extract(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        texts = [main_text(x.as_py()) for x in batch.column("html")]
        yield pa.RecordBatch.from_arrays([batch.column("page_id"), batch.column("url"), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], names=["page_id", "url", "text", "n_chars"])


def extract(pages: DataFrame) -> DataFrame:
    """page_id, url, text, n_chars for each row of `pages`."""
    rows = pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), F.col("html").cast("string").alias("html"))
    return rows.mapInArrow(_extract, "page_id long, url string, text string, n_chars long")
