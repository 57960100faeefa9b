"""Main text of raw pages: parser events, text-to-tag ratio per line, Gaussian smoothing, threshold clustering.

The standard library's parser streams events; every block element ends a line.
A line's ratio is its visible characters over its tags (links weigh most), and
structure is a weight on it: a line in a menu, header, footer or sidebar, or in an element
whose class, id or role names a notice, advert or comment, counts little. The weighted
ratios are smoothed and split by a threshold between two clusters. The clusters
choose the region, and every plain line of it stays, however short or linked; a line
that structure speaks against stays only if its ratio is in the upper cluster all the
same. The region is the <article> or <main> elements that hold content lines, if most
of the content lies in such; else the smallest element that holds the content lines, with
the blocks around it up to the next block of links. Forms, scripts, styles and the
like have no lines.

Defined results: null or empty html, and pages without content, give an empty
text; cut-off tags and unclosed elements are read as the parser reads them.
"""

from __future__ import annotations

import os
import re
from collections.abc import Iterator
from html.parser import HTMLParser

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from momentbuf.llm.common import arrow_map, records, table

#: Element names by role.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
BLOCK = frozenset("address article aside blockquote body caption center dd details dialog dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr html legend li main menu nav ol optgroup option p pre section summary table tbody td tfoot th thead title tr ul".split())
DROP = frozenset("audio button canvas datalist dialog form head iframe input label math noembed noframes noscript object option script select style svg template textarea title video".split())
DOUBTFUL = frozenset("aside footer menu nav".split())
CLOSES_P = BLOCK - {"body", "html"}
#: Words of class, id and role names that mark what isn't the article.
NOT_ARTICLE = frozenset(
    "ad ads adv advert adverts advertisement advertising adsense banner sponsor sponsored promo promotion cookie cookies consent gdpr notice notices alert popup modal overlay newsletter subscribe subscription signup paywall "
    "sidebar sidebars rail widget widgets aside comment comments commentlist respond replies disqus discussion menu menus nav navbar navigation breadcrumb breadcrumbs pagination pager toolbar topbar masthead header footer colophon "
    "share sharing social related recommended login search searchform form complementary contentinfo alertdialog skip".split()
)
#: Elements that can be the region.
_REGIONS = frozenset("body center div fieldset html section td".split())
_HEADINGS = frozenset("h1 h2 h3 h4 h5 h6".split())
_HOLDERS = frozenset(("div", "section", "ul", "ol", "dl", "table", "p", "span", "article", "li", "details", "header", "figure", "td", "center"))
#: Weight of a ratio where structure speaks against a line.
DOUBT = 0.05
_NAME = re.compile(r"[A-Z]?[a-z]+|[A-Z]+")


class _Lines(HTMLParser):
    """Collects lines: text, tags, link characters, the number of the <article> or <main> they lie in (0: none), and whether structure speaks against them.

    Also their links and the numbers of the elements they lie in, outermost first.
    """

    def __init__(self) -> None:
        super().__init__(convert_charrefs=True)
        self.lines: list[tuple[str, int, int, int, bool]] = []
        self.within: list[tuple[int, tuple[int, ...]]] = []
        self.names: list[str] = []
        self.open: list[tuple[str, bool, bool, int, int]] = []
        self.skipped = self.doubts = self.article = self.articles = self.links = 0
        self.parts: list[str] = []
        self.tags = self.linked = self.anchors = 0

    def line(self) -> None:
        if self.parts:
            text = " ".join("".join(self.parts).split())
            if text:
                self.lines.append((text, self.tags, self.linked, self.article, self.doubts > 0))
                self.within.append((self.anchors, tuple(x[4] for x in self.open)))
                self.tags = self.linked = self.anchors = 0
            self.parts = []

    @staticmethod
    def _named_out(tag: str, attrs: list) -> bool:
        return tag in _HOLDERS and any(k in ("class", "id", "role") and v and any(x.lower() in NOT_ARTICLE for x in _NAME.findall(v)) for k, v in attrs)

    @staticmethod
    def _hidden(tag: str, attrs: list) -> bool:
        return tag in _HOLDERS and any(k == "hidden" or (k == "aria-hidden" and v == "true") for k, v in attrs)

    def _pop_to(self, at: int) -> None:
        while len(self.open) > at:
            tag, skip, doubt, before, _ = self.open.pop()
            self.skipped -= skip
            self.doubts -= doubt
            self.links -= tag == "a"
            if before >= 0:
                self.article = before

    def handle_starttag(self, tag: str, attrs: list) -> None:
        if tag in BLOCK:
            self.line()
            if tag in CLOSES_P:
                for i in range(len(self.open) - 1, -1, -1):
                    x = self.open[i][0]
                    if x == "p" or (x == tag and tag in ("li", "dt", "dd", "option", "td", "tr")):
                        self._pop_to(i)
                        break
                    if x in BLOCK:
                        break
        elif tag == "br":
            self.parts.append(" ")
        self.tags += 1
        if tag in VOID:
            return
        inside = self.article > 0
        skip = tag in DROP or self._hidden(tag, attrs)
        doubt = tag in DOUBTFUL or (tag == "header" and not inside) or self._named_out(tag, attrs)
        before = -1
        if tag in ("article", "main") and not skip and not doubt and not self.doubts and not (inside and tag == "main"):
            before = self.article
            if not inside:
                self.articles += 1
                self.article = self.articles
        self.open.append((tag, skip, doubt, before, len(self.names)))
        self.names.append(tag)
        self.skipped += skip
        self.doubts += doubt
        self.links += tag == "a"

    def handle_startendtag(self, tag: str, attrs: list) -> None:
        self.handle_starttag(tag, attrs)
        if tag not in VOID:
            self.handle_endtag(tag)

    def handle_endtag(self, tag: str) -> None:
        if tag in BLOCK:
            self.line()
        elif tag == "br":
            self.parts.append(" ")
        self.tags += 1
        for i in range(len(self.open) - 1, -1, -1):
            if self.open[i][0] == tag:
                self._pop_to(i)
                break

    def handle_data(self, data: str) -> None:
        if not self.skipped:
            self.parts.append(data)
            if self.links:
                self.linked += len(data)
                self.anchors += bool(data.strip())


def smoothed(ratio: np.ndarray, sigma: float) -> np.ndarray:
    """Gaussian smoothing over lines, weights cut at three sigma and normalised at the ends."""
    r = max(1, int(np.ceil(3 * sigma)))
    w = np.exp(-0.5 * (np.arange(-r, r + 1) / sigma) ** 2)
    return np.convolve(ratio, w)[r:-r] / np.convolve(np.ones_like(ratio), w)[r:-r]


def two_clusters(x: np.ndarray) -> float:
    """Threshold halfway between the means of two clusters of numbers (iterated to rest)."""
    lo, hi = float(x.min()), float(x.max())
    if lo == hi:
        return lo - 1.0
    t = (lo + hi) / 2
    for _ in range(50):
        new = (x[x <= t].mean() + x[x > t].mean()) / 2
        if abs(new - t) < 1e-9:
            break
        t = new
    return t


def region(within: list[tuple[int, tuple[int, ...]]], names: list[str], content: np.ndarray, dense: np.ndarray, chars: np.ndarray, linked: np.ndarray) -> np.ndarray:
    """The lines that belong to the article of a page whose content lies outside <article> and <main>; content: the lines that choose it, one at least;
    dense: lines of as high a ratio before smoothing, which choose it too where they are siblings of content lines.

    The smallest element that holds the content lines is taken whole (of one that is
    the whole page, the blocks from the first to the last with content). Blocks beside
    it, then beside the elements around it, join up to the next block of links on
    either side; and where no title is among them, the last one above with what lies between.
    """
    n, paths = len(chars), [w for _, w in within]
    anchors = np.array([k for k, _ in within])
    heading = [next((names[i] for i in reversed(w) if names[i] in _HEADINGS), "") for w in paths]
    linky = (linked > 0.8 * chars) & np.array([not h for h in heading])
    parents = {paths[i][:-1] for i in np.flatnonzero(content)}
    content = content | dense & np.array([w[:-1] in parents for w in paths])
    where = np.flatnonzero(content)
    holder = os.path.commonprefix([paths[i] for i in where])
    while holder and names[holder[-1]] not in _REGIONS:
        holder = holder[:-1]

    def inside(holder: tuple[int, ...]) -> tuple[int, int]:
        at = [i for i, w in enumerate(paths) if w[: len(holder)] == holder]
        return at[0], at[-1] + 1

    def blocks(holder: tuple[int, ...]) -> list[tuple[int, int, bool]]:
        """Start, end and whether it is a block of links, of each child of an element; links one a block are such where they neighbour."""
        lo, hi = inside(holder)
        key = [w[len(holder)] if len(w) > len(holder) else -1 - i for i, w in enumerate(paths)]
        edge = [i for i in range(lo, hi) if i == lo or key[i] != key[i - 1]] + [hi]
        spans = list(zip(edge[:-1], edge[1:], strict=True))
        only = [bool(linky[s:e].all()) for s, e in spans]
        many = [anchors[s:e].sum() > 1 and linked[s:e].sum() > 0.5 * chars[s:e].sum() and any(not h for h in heading[s:e]) for s, e in spans]
        beside = [x and (any(only[max(0, i - 1) : i]) or any(only[i + 1 : i + 2])) for i, x in enumerate(only)]
        return [(s, e, bool(m or b)) for (s, e), m, b in zip(spans, many, beside, strict=True)]

    first, last = inside(holder)
    if (first, last) == (0, n):
        of = [(s, e) for s, e, _ in blocks(holder) if content[s:e].any()]
        first, last = of[0][0], of[-1][1]
    elif holder:
        holder = holder[:-1]
    while True:
        around = blocks(holder)
        above = [x for x in around if x[1] <= first]
        below = [x for x in around if x[0] >= last]
        while above and not above[-1][2]:
            first = above.pop()[0]
        while below and not below[0][2]:
            last = below.pop(0)[1]
        if above or below or not holder:
            break
        holder = holder[:-1]
    keep = np.zeros(n, bool)
    keep[first:last] = True
    if not any(h in ("h1", "h2") for h in heading[first:last]):
        titles = [i for i in range(first) if heading[i] == "h1"]
        if titles:
            keep[titles[-1] : first] = ~linky[titles[-1] : first]
    return keep


def main_text(html: str | None, sigma: float = 1.0) -> str:
    """The article's blocks, joined by line ends."""
    p = _Lines()
    p.feed(html or "")
    p.close()
    p.line()
    doubt = np.array([x[4] for x in p.lines], bool)
    if doubt.all():
        return ""
    chars = np.array([len(x[0]) for x in p.lines], float)
    linked = np.array([x[2] for x in p.lines], float)
    ratio = np.log1p((chars - np.minimum(linked, chars)) / np.maximum(1, [x[1] for x in p.lines])) * np.where(doubt, DOUBT, 1.0)
    level = smoothed(ratio, sigma)
    threshold = two_clusters(np.r_[level, 0.0])  # a line of no text is always in the lower cluster
    plain = np.flatnonzero(~doubt)
    chars_p, linked_p, ratio_p = chars[plain], linked[plain], ratio[plain]
    linky = linked_p > 0.8 * chars_p
    content = (level[plain] > threshold) & ~linky
    where = np.array([x[3] for x in p.lines])
    inside = where[plain] > 0
    keep = np.zeros(len(p.lines), bool)
    if inside.any() and (not content.any() or 2 * chars_p[content & inside].sum() >= chars_p[content].sum()):
        hold = set(where[plain][content & inside].tolist()) or {int(np.bincount(where[plain][inside], weights=chars_p[inside]).argmax())}
        within = np.isin(where, list(hold))
        keep[plain] = within[plain]
    elif content.any():
        keep[plain] = region([p.within[i] for i in plain.tolist()], p.names, content, (ratio_p > threshold) & ~linky, chars_p, linked_p)
        at = np.flatnonzero(keep)
        within = (np.arange(len(keep)) >= at[0]) & (np.arange(len(keep)) <= at[-1]) if len(at) else keep
    else:
        keep[plain] = ~linky
        within = keep.copy()
    keep |= doubt & within & (ratio > threshold) & (level > threshold)
    return "\n".join(x[0] for x, k in zip(p.lines, keep.tolist(), strict=True) if k)


_OUT = pa.schema([("page_id", pa.int64()), ("url", pa.string()), ("text", pa.string()), ("n_chars", pa.int64())])


def _extract(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in batches:
        texts = [main_text(h).encode("utf-8", "replace").decode() for h in b.column("html").to_pylist()]
        yield records(_OUT, page_id=b.column("page_id"), url=b.column("url"), text=texts, n_chars=[len(t) for t in texts])


def extract(pages: DataFrame) -> DataFrame:
    """page_id, url, text and n_chars of every page; a map without exchange."""
    return arrow_map(pages.select("page_id", "url", "html"), _extract, "page_id long, url string, text string, n_chars long")


def op10_main_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    return extract(table(spark, sf_dir, "pages", "page_id", "url", "html"))
