"""HTML extraction: flat text blocks, classified by a decision tree that is trained on a small labelled table.

A page is cut into flat blocks at block-level tags. Each block has its number of words and its link density, those of
its two neighbours, and what its surroundings say: whether it stands in an element whose name, class, id or role is that
of page furniture, in the article or main element, or in a heading. The tree is grown on the blocks of the small pages
below, which carry their labels as an attribute; it is a few nodes deep and goes with the task.

Readings of what belongs to an article. Marks are judged from the article's place inwards: an element that holds the whole
article (a div named has-sidebar, a form around the page) is a wrapper and marks nothing, while the menus and forms beside or
inside the article keep their marks. Comments in article elements of their own are no article, since they lie in marked
elements that the article is outside of. A header or footer element inside the article is a header or footer and goes,
headline included; headings that stand in the article itself stay. Formulas and the fallback text of maps and objects are text.
"""

from __future__ import annotations

import html
import re
from collections.abc import Iterator
from dataclasses import dataclass, field
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import text_batches, with_field

#: Elements that end a block, elements without content, elements whose content is no text.
BLOCKS = frozenset("address article aside blockquote body button caption center dd details dialog div dl dt fieldset figcaption figure footer form frameset h1 h2 h3 h4 h5 h6 head header hr html legend li main menu nav ol optgroup option p pre search section select summary table tbody td tfoot th thead title tr ul".split())
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
SILENT = frozenset("applet audio button canvas datalist dialog embed form head iframe input noembed noframes noscript option picture script select style svg template textarea title video".split())
RAW = ("script", "style", "textarea", "title", "noscript", "iframe", "xmp", "noframes", "noembed", "template")
#: Elements, roles and parts of class and id names that mark page furniture, and those that mark the article.
FURNITURE = frozenset("nav header footer aside menu form".split())
ROLES = frozenset("navigation banner contentinfo complementary search menu menubar dialog alert alertdialog form toolbar".split())
NAMES = frozenset("ad ads advert adverts advertisement advertising adbox adsense banner sponsor sponsored promo promotion promoted nav navbar navigation menu menubar breadcrumb breadcrumbs header masthead topbar footer foot colophon copyright legal disclaimer sidebar sidebars aside rail widget widgets notice notices cookie cookies consent gdpr alert popup modal overlay banner comment comments commentlist discussion disqus replies reply respond feedback share sharing social related recommended recommendations teaser teasers newsletter subscribe subscription signup login form search pagination pager toc tags skip hidden tracking".split())
MAINS = frozenset("article main".split())
HEADINGS = frozenset("h1 h2 h3 h4 h5 h6".split())
BODY_NAMES = frozenset("article content story post entry".split())
#: A form with over this share of a page's words, where no article shows its place, is a wrapper.
WHOLE = 0.5

_DEAD = re.compile(r"<!--.*?(?:-->|\Z)|<!\[CDATA\[.*?(?:\]\]>|\Z)|<(" + "|".join(RAW) + r")\b[^>]*>.*?(?:</\1\s*>|\Z)", re.S | re.I)
_TAG = re.compile(r"<(/?)([a-zA-Z][^\s/>]*)((?:[^>\"']|\"[^\"]*\"|'[^']*')*)>|<[!?/][^>]*>|<[a-zA-Z/!?][^>]*\Z")
_ATTR = re.compile(r"([^\s=/\"'>]+)(?:\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+)))?")
_PART = re.compile(r"[a-z]+")


@dataclass
class Block:
    text: str
    words: int
    linked: int
    tag: str
    furniture: bool
    main: bool
    heading: bool
    label: str | None = None


@dataclass(eq=False)
class _Open:
    """An element as it was opened. main: 2 for an article or main element, 1 for one that is named like it, else 0."""

    tag: str
    furniture: bool = False
    main: int = 0
    silent: bool = False
    label: str | None = None


@dataclass
class _Cutter:
    found: list[tuple[str, int, tuple[_Open, ...]]] = field(default_factory=list)
    pieces: list[str] = field(default_factory=list)
    linked: int = 0
    stack: list[_Open] = field(default_factory=list)
    mains: list[tuple[_Open, ...]] = field(default_factory=list)

    def end(self) -> None:
        text = " ".join(html.unescape("".join(self.pieces)).split())
        if text:
            self.found.append((text, min(self.linked, len(text.split(" "))), tuple(self.stack)))
        self.pieces, self.linked = [], 0

    def wrappers(self) -> set[_Open]:
        """Marked elements around the article: of article and main elements (else of those named like them) the ones inside the
        fewest marked elements show it. Without any, forms that hold most of the page."""
        around = []
        for kind in (2, 1):
            around = around or [[o for o in path[:-1] if o.furniture or o.tag == "form"] for path in self.mains if path[-1].main == kind]
        if around:
            least = min(map(len, around))
            return {o for path in around if len(path) == least for o in path}
        words: dict[_Open, int] = {}
        for text, _, path in self.found:
            for o in path:
                if o.tag == "form":
                    words[o] = words.get(o, 0) + len(text.split(" "))
        every = sum(len(text.split(" ")) for text, *_ in self.found)
        return {o for o, n in words.items() if n > WHOLE * every}

    def blocks(self) -> list[Block]:
        free, out = self.wrappers(), []
        for text, linked, path in self.found:
            bound = [o for o in path if o not in free]
            if any(o.silent for o in bound):
                continue
            tag = next((o.tag for o in reversed(path) if o.tag in BLOCKS), "body")
            label = next((o.label for o in reversed(path) if o.label), None)
            marked = any(o.furniture for o in bound)
            out.append(Block(text, len(text.split(" ")), linked, tag, marked, any(o.main for o in path), any(o.tag in HEADINGS for o in path), label))
        return out


def _opened(tag: str, attributes: str, inside: bool) -> _Open:
    out = _Open(tag, tag in FURNITURE, 2 * (tag in MAINS), tag in SILENT)
    for name, *values in _ATTR.findall(attributes):
        name, value = name.lower(), html.unescape("".join(values)).lower()
        if name in ("class", "id"):
            # a name that belongs to the whole page or the article itself says nothing against what it holds
            if tag not in ("html", "body", "article", "main"):
                out.furniture |= any(p in NAMES for p in _PART.findall(value))
            if not inside and not out.furniture and any(p in BODY_NAMES for p in _PART.findall(value)):
                out.main = max(out.main, 1)
        elif name == "role":
            out.furniture |= value in ROLES
            out.main = 2 if value in MAINS else out.main
        elif name == "hidden" or (name == "aria-hidden" and value == "true") or (name == "style" and re.search(r"display\s*:\s*none|visibility\s*:\s*hidden", value)):
            out.silent = True
        elif name == "data-label":
            out.label = value
    return out


def blocks_of(page: str | None) -> list[Block]:
    """The flat blocks of a page in order. Comments, scripts, styles, forms and hidden elements give none; tags that are
    cut off at the end are dropped; a missing end tag ends with its parent."""
    cutter, at, page = _Cutter(), 0, _DEAD.sub(lambda m: " " if m[1] is None else f"<{m[1]}></{m[1]}>", page or "")
    stack = cutter.stack

    def say(piece: str) -> None:
        if piece and not any(o.silent and o.tag != "form" for o in stack):  # whether a form is a wrapper shows later
            cutter.pieces.append(piece)
            if any(o.tag == "a" for o in stack):
                cutter.linked += len(piece.split())

    for m in _TAG.finditer(page):
        say(page[at : m.start()])
        at = m.end()
        if m[2] is None:
            continue
        tag, ends = m[2].lower(), bool(m[1])
        if tag in BLOCKS:
            cutter.end()
        elif tag == "br":
            say(" ")
        if ends:
            for k in range(len(stack) - 1, -1, -1):
                if stack[k].tag == tag:
                    del stack[k:]
                    break
                if stack[k].tag in BLOCKS and tag not in BLOCKS:
                    break  # an inline end tag doesn't reach out of its block
            continue
        if tag in BLOCKS:  # inline elements left open end with the block before; p, li and the like end each other
            while stack and (stack[-1].tag not in BLOCKS or stack[-1].tag == "p" or (tag == stack[-1].tag and tag in ("li", "dd", "dt", "tr", "td", "th", "option"))):
                stack.pop()
        if tag not in VOID and not m[3].rstrip().endswith("/"):
            stack.append(_opened(tag, m[3], any(o.main for o in stack)))
            if stack[-1].main:
                cutter.mains.append(tuple(stack))
    say(page[at:])
    cutter.end()
    return cutter.blocks()


def table_of(blocks: list[Block]) -> np.ndarray:
    """A row for each block: words and link density of the block before, itself and the next, furniture, main, heading."""
    words = np.array([0, *(b.words for b in blocks), 0], float)
    links = np.array([0, *(b.linked for b in blocks), 0], float)
    density = links / np.maximum(words, 1)
    n = len(blocks)
    marks = np.array([[b.furniture, b.main, b.heading] for b in blocks], float).reshape(n, 3)
    return np.column_stack([words[:-2], density[:-2], words[1:-1], density[1:-1], words[2:], density[2:], marks])


@dataclass
class Tree:
    """A binary tree: feature -1 marks a leaf, whose value is the share of kept blocks in it."""

    feature: list[int] = field(default_factory=list)
    limit: list[float] = field(default_factory=list)
    left: list[int] = field(default_factory=list)
    right: list[int] = field(default_factory=list)
    value: list[float] = field(default_factory=list)

    def grow(self, x: np.ndarray, y: np.ndarray, depth: int) -> int:
        me = len(self.feature)
        for column, v in zip((self.feature, self.limit, self.left, self.right, self.value), (-1, 0.0, -1, -1, float(y.mean())), strict=True):
            column.append(v)
        best = (1e-9, -1, 0.0)
        if depth and 0 < y.mean() < 1:
            whole = y.mean() * (1 - y.mean())
            for f in range(x.shape[1]):
                values = np.unique(x[:, f])
                for limit in (values[:-1] + values[1:]) / 2:
                    side = x[:, f] <= limit
                    gain = whole - sum(s.mean() * y[s].mean() * (1 - y[s].mean()) for s in (side, ~side))
                    if gain > best[0] + 1e-12:
                        best = (gain, f, float(limit))
        if best[1] >= 0:
            side = x[:, best[1]] <= best[2]
            self.feature[me], self.limit[me] = best[1], best[2]
            self.left[me] = self.grow(x[side], y[side], depth - 1)
            self.right[me] = self.grow(x[~side], y[~side], depth - 1)
        return me

    def predict(self, x: np.ndarray) -> np.ndarray:
        at = np.zeros(len(x), int)
        feature, limit, left, right = (np.array(c) for c in (self.feature, self.limit, self.left, self.right))
        while len(at) and (feature[at] >= 0).any():
            f = feature[at]
            go = np.where(x[np.arange(len(x)), np.maximum(f, 0)] <= limit[at], left[at], right[at])
            at = np.where(f >= 0, go, at)
        return np.array(self.value)[at] >= 0.5


def labelled_pages() -> list[str]:
    """Small pages whose blocks say with data-label whether they are kept. They vary in layout, not in language:
    with and without article elements, short and long paragraphs, link lists, notices, adverts and comments."""

    def words(n: int) -> str:
        return " ".join(["lorem"] * n)

    def links(n: int, each: int = 1) -> str:
        return "".join(f'<li><a href="/">{words(each)}</a></li>' for _ in range(n))

    def paragraphs(*sizes: int) -> str:
        return "".join(f"<p>{words(n)}</p>" for n in sizes)

    out = []
    for long, heads in ((60, True), (25, False), (120, True), (8, False)):
        head = f"<h1>{words(6)}</h1>" if heads else ""
        body = head + paragraphs(long, 2, 1, long // 2, 5, 12, 3, long) + f"<p>{words(long)} <a>{words(2)}</a> {words(9)}</p><p>{words(3)} <a>{words(4)}</a></p>"
        for box in (f'<article data-label="keep">{body}</article>', f'<main data-label="keep">{body}</main>', f'<div class="content" data-label="keep">{body}</div>'):
            drop = 'data-label="drop"'
            out.append(f'<nav {drop}><ul>{links(5)}</ul></nav><div class="ad" {drop}>{words(9)}</div>{box}<footer {drop}>{words(7)} <a>{words(2)}</a></footer>')
            out.append(f'<header {drop}><p>{words(4)}</p></header><aside {drop}><p>{words(40)}</p><ul>{links(3, 5)}</ul></aside>{box}<section class="comments" {drop}>{paragraphs(30, 150, 12, 70, 200)}</section>')
            out.append(f'<div class="cookie-notice" {drop}>{words(22)}</div>{box}<div {drop}><ul>{links(6, 4)}</ul></div><div {drop}>{words(4)}</div>')
            out.append(box.replace("</article>", f'<div class="related" {drop}><p>{words(6)}</p><ul>{links(4, 6)}</ul></div></article>').replace("</p><p>lorem</p>", f'</p><p>lorem</p><ul {drop}>{links(4, 3)}</ul>'))
        # nothing but the blocks themselves tells: long texts stay, short ones between short or linked ones go
        if long > 20:
            for kind in ("comments", "sidebar", "notice"):
                out.append(f'<div data-label="keep">{paragraphs(long, long, 14, long)}</div><div class="{kind}" data-label="drop">{paragraphs(30, 150, 12, 70, 200)}</div>')
            for n in (1, 2):  # lone links before and behind
                out.append(f'<div data-label="drop"><a href="/">{words(n)}</a></div><div data-label="keep">{paragraphs(long, long)}</div><div data-label="drop"><a href="/">{words(n)}</a></div>')
            out.append(f'<div data-label="drop"><ul>{links(7)}</ul></div><div data-label="drop">{words(3)}</div><div data-label="keep">{paragraphs(long, long, 14, long)}</div><div data-label="drop">{words(4)}</div><div data-label="drop"><ul>{links(3, 2)}</ul></div>')
    return out


@lru_cache(maxsize=2)
def trained(depth: int = 6) -> Tree:
    """The tree grown on the labelled pages."""
    x, y = [], []
    for page in labelled_pages():
        blocks = blocks_of(page)
        x.append(table_of(blocks))
        y += [b.label == "keep" for b in blocks]
    tree = Tree()
    tree.grow(np.concatenate(x), np.array(y, float), depth)
    return tree


def main_text(page: str | None, tree: Tree | None = None) -> str:
    blocks = blocks_of(page)
    kept = (tree or trained()).predict(table_of(blocks))
    return "\n\n".join(b.text for b, k in zip(blocks, kept, strict=True) if k)


def extract(pages: DataFrame, source: str = "html") -> DataFrame:
    """Adds text and n_chars (code points) to every page; columns with these names are replaced.

    A null or empty page, or one without article, gives an empty text. Broken markup gives what can be read of it.
    """
    pages = pages.drop(*(c for c in ("text", "n_chars") if c != source))
    schema = with_field(pages.schema, "text", "string")

    def add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tree = trained()
        for b in text_batches(batches, source):
            got = [main_text(t, tree) for t in b.column(b.schema.get_field_index(source)).to_pylist()]
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(got, pa.string())], names=[*b.schema.names, "text"])

    return pages.mapInArrow(add, schema).withColumn("n_chars", F.length("text").cast("long"))
