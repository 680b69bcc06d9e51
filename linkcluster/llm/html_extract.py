"""Main-text extraction by tag-path ratios.

A page is cut into blocks in page order.  Each block knows its root-to-leaf tag path, on which elements
with telling class, id or role words are marked.  For each path two ratios are gathered over all
of its blocks: characters of unlinked text, and punctuation marks in it, for each block.  Along
the page both are smoothed with a Gaussian and fused, the product of text and one plus marks.  A path's
score is the mean over its blocks; ``side_prior`` scales it for each marked path, as the words are a hint
and no proof.  Paths whose score reaches a share of the spread of all scores are content.

The innermost container of nearly all text on content paths is the article, and an ``article`` or
``main`` element around it widens it.  Inside, headings and short paragraphs count too, unless their path
is marked or mostly links.  On a page without such a container, where it would be the whole body, the
blocks on content paths and the headings before them are the text.

Elements that hold no article text by the definition of HTML (scripts, styles, menus, asides,
forms, page headers and footers, hidden ones) never become blocks.

Defined cases: a null or empty page, or one without article text, gives the empty string; a page may
be unclosed, badly nested or without any block tag; all work is linear in the length of a page,
however deep or broken it is; other columns, whatever their names, are not read.
"""

from __future__ import annotations

import html as _html
import math
import re
from collections import Counter
from dataclasses import dataclass

import pyarrow as pa
from pyspark.sql import DataFrame

NAME = re.compile(r"<(/?)([a-zA-Z][^\s/<>]*)")
STOP = re.compile(r"""[>"']""")
ATTR = re.compile(r"""(?<![\w-])(class|id|role|hidden|aria-hidden|style)(?![\w-])\s*(?:=\s*(?:"([^"]*)"|'([^']*)'|([^\s>]+)))?""", re.IGNORECASE)
WORD = re.compile(r"[A-Z]?[a-z]+|[A-Z]+(?![a-z])|\d+")
PUNCTUATION = re.compile(r"[.,;:!?…。，、！？；：¿¡]")
# Tag sets of HTML.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style noscript template iframe textarea title svg math object canvas noembed noframes xmp".split())
BLOCK = frozenset(
    "html head body address article aside blockquote center dd details dialog dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr li main menu nav ol p pre section summary table tbody td tfoot th thead tr ul caption".split()
)
CLOSES_P = BLOCK - {"html", "head", "body", "td", "th", "tr", "tbody", "thead", "tfoot", "caption"}
SIBLINGS = {"li": {"li"}, "dt": {"dt", "dd"}, "dd": {"dt", "dd"}, "td": {"td", "th"}, "th": {"td", "th"}, "tr": {"tr", "td", "th"}, "option": {"option"}}
SCOPES = frozenset("html body table ul ol dl div article section main aside nav td th blockquote form".split())
NEVER = frozenset("nav aside footer form head button select option menu dialog label".split())
HEADINGS = frozenset("h1 h2 h3 h4 h5 h6".split())
#: Words of class or id that hint at a region that is no article text.
SIDE_WORDS = frozenset(
    "ad ads adv advert adverts advertisement advertising advertorial sponsor sponsored sponsors promo promos promotion banner banners sidebar side nav navbar navigation menu menus breadcrumb breadcrumbs "
    "footer masthead cookie cookies consent gdpr notice notices alert popup modal overlay newsletter subscribe subscription signup login share sharing social related recommended recommendations "
    "comment comments commentlist disqus replies reply respond discussion widget widgets pagination pager toolbar copyright disclaimer paywall toc skip".split()
)
ROLES = frozenset("navigation banner contentinfo complementary search form dialog alert menu menubar alertdialog".split())
KEEP = frozenset("html body article main".split())


@dataclass(frozen=True)
class PathRatioConfig:
    #: Standard deviation of the smoothing, in blocks.
    sigma: float = 0.5
    #: Share of the spread of fused scores that a content path must reach.
    threshold: float = 0.5
    #: What the score of a path through a marked element is multiplied by.
    side_prior: float = 0.002
    #: Share of the content text that the article's container must hold.
    holds: float = 0.9
    #: Share of unlinked text that a path needs to count inside the article without being content.
    free: float = 0.3


#: What an element's attributes say: nothing, a hint, or that it is not shown.
PLAIN, MARKED, HIDDEN = 0, 1, 2


def _hint(tag: str, attrs: str, in_article: bool) -> int:
    if tag in NEVER or (tag == "header" and not in_article):
        return HIDDEN
    if tag in KEEP or not attrs:
        return PLAIN
    found = PLAIN
    for m in ATTR.finditer(attrs):
        name, value = m.group(1).lower(), (m.group(2) or m.group(3) or m.group(4) or "")
        if name == "hidden" or (name == "aria-hidden" and value.lower() == "true"):
            return HIDDEN
        if name == "style" and re.search(r"display\s*:\s*none|visibility\s*:\s*hidden", value, re.IGNORECASE):
            return HIDDEN
        if name == "role" and value.lower() in ROLES:
            found = MARKED
        elif name in ("class", "id"):
            words = {w.lower() for w in WORD.findall(value)}
            if words & SIDE_WORDS or (words & {"header"} and not in_article):
                found = MARKED
    return found


@dataclass
class Element:
    """An open element; ``path`` numbers the tag path down to it."""

    tag: str
    path: int
    #: Number of the nearest block element from here upwards, 0 at the top.
    holder: int
    hidden: bool
    marked: bool
    in_article: bool


@dataclass
class Block:
    path: int
    holder: int
    marked: bool
    heading: bool
    parts: list
    linked: int = 0
    text: str = ""


class Page:
    """The blocks of a page outside hidden elements, in page order, and its block elements as (tag, parent)."""

    def __init__(self, page: str) -> None:
        self.blocks: list[Block] = []
        self.elements: list[tuple[str, int]] = [("", 0)]
        self._page, self._paths = page, {}
        self._stack: list[Element] = []
        self._open: Counter = Counter()
        self._current: Block | None = None
        self._none_from: dict[str, int] = {}
        self._failed: set[int] = set()
        self._read()
        for b in self.blocks:
            b.text = " ".join(_html.unescape("".join(b.parts)).split())
        self.blocks = [b for b in self.blocks if b.text]

    def _find(self, what: str, at: int) -> int:
        """``str.find`` that never looks for the same missing thing twice."""
        if at >= self._none_from.get(what, len(self._page) + 1):
            return -1
        k = self._page.find(what, at)
        if k < 0:
            self._none_from[what] = at
        return k

    def _tag_end(self, at: int) -> int:
        """Where the tag whose attributes start here closes, quotes skipped; -1 if it never does."""
        seen = []
        while at not in self._failed:
            seen.append(at)
            m = STOP.search(self._page, at) if at < self._none_from.get("stop", len(self._page) + 1) else None
            if m is None:
                self._none_from["stop"] = min(at, self._none_from.get("stop", at))
                break
            if m.group() == ">":
                return m.start()
            k = self._find(m.group(), m.end())
            if k < 0:
                break
            at = k + 1
        self._failed.update(seen)
        return -1

    def _add(self, raw: str) -> None:
        top = self._stack[-1] if self._stack else None
        if not raw or (top and top.hidden):
            return
        if self._current is None:
            if not raw.strip():
                return
            heading = any(self._open[t] for t in HEADINGS)
            self._current = Block(top.path if top else 0, top.holder if top else 0, bool(top and top.marked), heading, [])
            self.blocks.append(self._current)
        self._current.parts.append(raw)
        if self._open["a"]:
            self._current.linked += len(raw)

    def _close_to(self, depth: int) -> None:
        while len(self._stack) > depth:
            tag = self._stack.pop().tag
            self._open[tag] -= 1
            if tag in BLOCK:
                self._current = None

    def _close(self, tag: str) -> None:
        if not self._open[tag]:
            return
        for i in range(len(self._stack) - 1, -1, -1):
            if self._stack[i].tag == tag:
                return self._close_to(i)
            if tag not in BLOCK and self._stack[i].tag in BLOCK:
                return None  # a stray inline end tag closes nothing outside its block

    def _start(self, tag: str, attrs: str) -> None:
        ends = ({"p"} if tag in CLOSES_P else set()) | SIBLINGS.get(tag, set())
        if any(self._open[t] for t in ends):
            for i in range(len(self._stack) - 1, -1, -1):
                if self._stack[i].tag in ends:
                    self._close_to(i)
                    break
                if self._stack[i].tag in SCOPES:
                    break
        if tag in BLOCK:
            self._current = None
        if attrs.rstrip().endswith("/") and tag not in BLOCK:
            return
        up = self._stack[-1] if self._stack else Element("", 0, 0, False, False, False)
        hint = _hint(tag, attrs, up.in_article)
        path = self._paths.setdefault((up.path, tag, hint == MARKED), len(self._paths) + 1)
        holder = up.holder
        if tag in BLOCK:
            holder = len(self.elements)
            self.elements.append((tag, up.holder))
        self._stack.append(Element(tag, path, holder, up.hidden or hint == HIDDEN, up.marked or hint == MARKED, up.in_article or tag in ("article", "main")))
        self._open[tag] += 1

    def _read(self) -> None:
        page, at, done = self._page, 0, 0
        while True:
            at = self._find("<", at)
            if at < 0:
                return self._add(page[done:])
            end = -1
            if page.startswith("<!--", at):
                k = self._find("-->", at + 4)
                self._add(page[done:at])
                at = done = k + 3 if k >= 0 else len(page)
                continue
            if page.startswith("<![CDATA[", at) and (k := self._find("]]>", at + 9)) >= 0:
                self._add(page[done:at])
                self._add(_html.escape(page[at + 9 : k], quote=False))
                at = done = k + 3
                continue
            m = NAME.match(page, at)
            if m:
                end = self._tag_end(m.end())
            elif page[at + 1 : at + 2] in ("!", "?"):
                end = self._find(">", at)
            if end < 0:
                at += 1
                continue
            self._add(page[done:at])
            at = done = end + 1
            if not m:
                continue
            tag, attrs = m.group(2).lower(), page[m.end() : end]
            if m.group(1):
                self._close(tag)
            elif tag == "br":
                self._add(" ")
            elif tag in VOID:
                if tag == "hr":
                    self._current = None
            elif tag in RAW:
                if not attrs.rstrip().endswith("/"):
                    close = re.compile(rf"</{re.escape(tag)}\b", re.IGNORECASE).search(page, at)
                    k = self._find(">", close.end()) if close else -1
                    at = done = k + 1 if k >= 0 else len(page)
            else:
                self._start(tag, attrs)


def _smooth(x: list[float], sigma: float) -> list[float]:
    r = max(1, math.ceil(3 * sigma))
    kernel = [math.exp(-(i * i) / (2 * sigma * sigma)) for i in range(-r, r + 1)]
    out = []
    for i in range(len(x)):
        lo, hi = max(0, i - r), min(len(x), i + r + 1)
        k = kernel[lo - i + r : hi - i + r]
        out.append(sum(a * b for a, b in zip(k, x[lo:hi])) / sum(k))
    return out


def _spread(x: list[float]) -> float:
    mean = sum(x) / len(x)
    return math.sqrt(sum((v - mean) ** 2 for v in x) / len(x))


def path_scores(blocks: list[Block], cfg: PathRatioConfig) -> dict[int, float]:
    """Fused and smoothed text and punctuation ratio of each tag path, under the prior."""
    sums: dict[int, list[float]] = {}
    for b in blocks:
        free = max(0, len(b.text) - b.linked)
        x = sums.setdefault(b.path, [0.0, 0.0, 0.0])
        x[0] += free
        x[1] += len(PUNCTUATION.findall(b.text)) * (free / len(b.text))
        x[2] += 1
    text = _smooth([sums[b.path][0] / sums[b.path][2] for b in blocks], cfg.sigma)
    marks = _smooth([sums[b.path][1] / sums[b.path][2] for b in blocks], cfg.sigma)
    fused: dict[int, list[float]] = {}
    for b, t, m in zip(blocks, text, marks):
        fused.setdefault(b.path, []).append(t * (1 + m) * (cfg.side_prior if b.marked else 1.0))
    return {p: sum(x) / len(x) for p, x in fused.items()}


def content_paths(blocks: list[Block], cfg: PathRatioConfig) -> set[int]:
    score = path_scores(blocks, cfg)
    least = cfg.threshold * _spread([score[b.path] for b in blocks])
    return {p for p, s in score.items() if s >= least}


def _container(page: Page, content: set[int], cfg: PathRatioConfig) -> int:
    """Number of the innermost block element that holds nearly all text on content paths, widened to its article; 0 for none."""
    weight = [0] * len(page.elements)
    for b in page.blocks:
        if b.path in content:
            weight[b.holder] += len(b.text)
    for n in range(len(weight) - 1, 0, -1):  # parents have smaller numbers
        weight[page.elements[n][1]] += weight[n]
    wide = [n for n, w in enumerate(weight) if n and w >= cfg.holds * weight[0] and page.elements[n][0] not in ("p", "li")]
    inner = n = max(wide, default=0)  # elements that hold so much lie inside one another
    while n:
        if page.elements[n][0] in ("article", "main"):
            return n
        n = page.elements[n][1]
    return 0 if page.elements[inner][0] in ("html", "body") else inner


def main_text(page: str | None, cfg: PathRatioConfig = PathRatioConfig()) -> str:
    if not page:
        return ""
    p = Page(page)
    if not p.blocks:
        return ""
    content = content_paths(p.blocks, cfg)
    article = _container(p, content, cfg)
    inside = [False] * len(p.elements)
    for n in range(1, len(inside)):
        inside[n] = n == article or inside[p.elements[n][1]]
    whole, free = Counter(), Counter()
    for b in p.blocks:
        whole[b.path] += len(b.text)
        free[b.path] += max(0, len(b.text) - b.linked)
    if article:
        near = [inside[b.holder] and not b.marked and free[b.path] >= cfg.free * whole[b.path] for b in p.blocks]
        keep = [inside[b.holder] and (b.path in content or n) for b, n in zip(p.blocks, near)]
    else:
        last = max((i for i, b in enumerate(p.blocks) if b.path in content), default=-1)
        keep = [b.path in content or (b.heading and not b.marked and i < last) for i, b in enumerate(p.blocks)]
    return "\n\n".join(b.text for b, k in zip(p.blocks, keep) if k)


def extract(pages: DataFrame, cfg: PathRatioConfig = PathRatioConfig(), keys: tuple[str, ...] = ("page_id", "url"), html: str = "html") -> DataFrame:
    """(keys, text, n_chars) of every page."""

    def run(batches):
        for b in batches:
            texts = [main_text(x.as_py(), cfg) for x in b.column(len(keys))]
            yield pa.RecordBatch.from_arrays([*[b.column(i) for i in range(len(keys))], pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], [*keys, "text", "n_chars"])

    slim = pages.select(*keys, html)
    kinds = dict(slim.dtypes)
    return slim.mapInArrow(run, ", ".join(f"`{k}` {kinds[k]}" for k in keys) + ", text string, n_chars bigint")
