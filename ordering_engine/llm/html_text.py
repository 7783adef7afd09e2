"""Main text of web pages from streaming parser events, text-to-tag ratios and smoothing.

The standard library's parser streams a page into blocks (lines). Each has its text, the tags met
in it and the container it is in. A line's ratio is its text length over its tags, links counting
against it; the ratios are smoothed by a Gaussian, and lines above a threshold from their mean and
deviation form content clusters. The clusters choose the region: the outermost article and main
elements if these hold a good part of the clusters' text, or else the container with the most of it, widened to
what holds all containers with a third as much, and on to any that itself holds a line of a cluster. Every line of the
region is kept, short ones included, except what its container's kind or name tells to be a menu, header, footer,
sidebar, notice, advert, form or reader comment; such lines take no part in the clusters either. Scripts, styles and the
like have no lines. Without any such names, and without article elements, the clusters alone find the region.

A page takes time in proportion to its length: a container has the number of its last descendant, so that
"is inside" is a comparison of numbers, and what a container inherits is noted when it opens.

Defined results: null or empty html, or a page with nothing but such parts, gives an empty text;
unclosed, unknown and misnested tags are tolerated; repeated rows are read row by row; an empty table
gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass
from html.parser import HTMLParser

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from .shared import raw_texts

#: Elements, roles and class or id words of page parts that aren't the article.
DROPPED = frozenset("head title script style noscript template nav aside footer form button select textarea input fieldset iframe object svg canvas math dialog menu audio video datalist map".split())
DROPPED_ROLES = frozenset("navigation banner contentinfo complementary search form alert alertdialog dialog menu menubar toolbar note".split())
DROPPED_WORDS = frozenset(
    """ad ads adv advert adverts advertisement advertising adsense adslot advertorial aside banner banners breadcrumb breadcrumbs comment comments commentlist commentform consent cookie cookies copyright
    disclaimer discussion disqus footer footers gdpr header headers login masthead menu menus modal nav navbar navigation newsletter notice notices notification notifications overlay pager pagination paywall
    popup promo promoted promotion recommended related replies reply respond responses search share sharing sidebar sidebars signup skip social sponsor sponsored subscribe subscription toolbar toc widget widgets""".split()
)
DROPPED_IN_ARTICLE = frozenset("ad advert advertisement comment comments promo related reply replies sponsored teaser".split())
#: With one of these the words tell how a container is laid out, not what it is.
ABOUT_LAYOUT = frozenset("has no with without".split())
BLOCKS = frozenset(
    "html body address article aside blockquote center dd details dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr li main menu nav ol p pre section summary table tbody td tfoot th thead tr ul".split()
)
#: Blocks of text, which are no regions.
TEXT_BLOCKS = frozenset("p h1 h2 h3 h4 h5 h6 li blockquote pre".split())
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
#: A start tag of the first ends open ones of the second.
CLOSES = {"li": {"li"}, "dt": {"dt", "dd"}, "dd": {"dt", "dd"}, "tr": {"tr", "td", "th"}, "td": {"td", "th"}, "th": {"td", "th"}}
WORD = re.compile(r"[a-z0-9]+")
SPACE = re.compile(r"[\x20\t\n\r\x0b\x0c\xa0  ]+")


@dataclass(slots=True)
class Line:
    text: str
    tags: int
    linked: int
    inside: int
    dropped: bool


@dataclass(slots=True)
class Element:
    """An open block, with what it has from the blocks around it."""

    number: int
    tag: str
    hard: bool  # in an element of a kind that is dropped
    soft: bool  # in one whose names tell it is dropped, up to the innermost article
    articles: int  # open article elements


class LineReader(HTMLParser):
    """Collects a page's lines; only blocks, and elements that are dropped, are kept on the stack."""

    def __init__(self) -> None:
        super().__init__(convert_charrefs=True)
        self.lines: list[Line] = []
        self.stack = [Element(0, "", False, False, 0)]
        self.kinds, self.parents, self.mains, self.lasts = [""], [-1], [-1], [-1]  # by number; 0 is the page
        self.open: dict[str, int] = {}
        self.text: list[str] = []
        self.tags = self.linked = self.links = 0

    def _end_line(self, at: int = -1) -> None:
        if self.text:
            text = SPACE.sub(" ", "".join(self.text)).strip(" ")
            if text:
                own = self.stack[at]
                self.lines.append(Line(text, self.tags, self.linked, own.number, own.hard or own.soft))
        self.text, self.tags, self.linked = [], 0, 0

    def _pop(self) -> None:
        own = self.stack.pop()
        self.open[own.tag] -= 1
        self.lasts[own.number] = len(self.kinds) - 1

    def _named(self, tag: str, attrs: list, inside: bool) -> bool:
        """Whether the attributes tell that this is no part of the article."""
        for name, value in attrs:
            if not value:
                if name == "hidden":
                    return True
            elif name == "role":
                if value.lower() in DROPPED_ROLES:
                    return True
            elif name in ("class", "id") and tag not in ("html", "body", "main", "h1"):
                words = set(WORD.findall(value.lower())) - ({"header", "headers", "notice", "share"} if inside and tag == "header" else set())
                if words & (DROPPED_IN_ARTICLE if tag == "article" else DROPPED_WORDS) and not words & ABOUT_LAYOUT:
                    return True
            elif name == "aria-hidden" and value == "true":
                return True
        return False

    def handle_starttag(self, tag: str, attrs: list) -> None:
        self.tags += 1
        block = tag in BLOCKS
        if block:
            self._end_line()
            closes = CLOSES.get(tag, ())
            while self.stack[-1].tag == "p" or self.stack[-1].tag in closes:
                self._pop()
        elif tag == "br":
            self.text.append(" ")
        elif tag == "a":
            self.links += 1
        if tag in VOID:
            return
        up = self.stack[-1]
        hard = tag in DROPPED or tag == "header" and not up.articles  # an article's own header holds its title
        dropped = hard or bool(attrs) and self._named(tag, attrs, up.articles > 0)
        if block or dropped:
            if not block:  # a dropped inline element ends the line before it, and itself is one
                self._end_line()
            main = tag in ("article", "main") or any(k == "role" and v == "main" for k, v in attrs)
            number = len(self.kinds)
            self.kinds.append(tag)
            self.parents.append(up.number)
            self.mains.append(self.mains[up.number] if self.mains[up.number] >= 0 else number if main else -1)
            self.lasts.append(-1)
            self.open[tag] = self.open.get(tag, 0) + 1
            # An article inside a container that only its class names is no part of it (think of ``has-sidebar``).
            self.stack.append(Element(number, tag, up.hard or hard, dropped if main else up.soft or dropped, up.articles + (tag == "article")))

    def handle_endtag(self, tag: str) -> None:
        self.tags += 1
        if tag == "a":
            self.links = max(0, self.links - 1)
        if self.open.get(tag):
            self._end_line()
            while self.stack[-1].tag != tag:
                self._pop()
            self._pop()

    def finish(self) -> None:
        self.close()
        self._end_line()
        while len(self.stack) > 1:
            self._pop()
        self.lasts[0] = len(self.kinds) - 1

    def handle_data(self, data: str) -> None:
        self.text.append(data)
        if self.links:
            self.linked += len(data)

    def unknown_decl(self, data: str) -> None:
        pass


def smoothed(values: np.ndarray, sigma: float) -> np.ndarray:
    """Gaussian smoothing over neighbouring lines."""
    reach = max(1, int(3 * sigma))
    kernel = np.exp(-0.5 * (np.arange(-reach, reach + 1) / sigma) ** 2)
    weight = np.convolve(np.ones_like(values), kernel, "full")[reach : reach + len(values)]
    return np.convolve(values, kernel, "full")[reach : reach + len(values)] / weight


def clusters(lines: list[Line], sigma: float) -> np.ndarray:
    """Which lines are content: those whose smoothed ratio of text to tags is above the threshold."""
    own = np.array([max(0, len(x.text) - x.linked) for x in lines])
    level = smoothed(own / (1 + np.array([x.tags for x in lines])), sigma)
    return level >= max(0.0, level.mean() - 0.5 * level.std())


def region(page: LineReader, sigma: float, share: float = 1 / 3) -> list[Line]:
    """The kept lines."""
    lines = [x for x in page.lines if not x.dropped]
    if not lines:
        return []
    content = clusters(lines, sigma)
    mass: dict[int, int] = {}  # text of the clusters by the container that holds its lines
    total = in_mains = 0
    for x, is_content in zip(lines, content, strict=True):
        if is_content:
            home, size = x.inside, max(0, len(x.text) - x.linked)
            while page.kinds[home] in TEXT_BLOCKS:
                home = page.parents[home]
            mass[home] = mass.get(home, 0) + size
            total += size
            in_mains += size if page.mains[x.inside] >= 0 else 0
    if 0 < in_mains >= 0.3 * total:
        return [x for x in lines if page.mains[x.inside] >= 0]
    chosen = max(mass, key=lambda k: (mass[k], -k))
    large = [k for k in mass if mass[k] >= share * mass[chosen]]
    low, high, at = min(large), max(large), chosen
    while at >= 0:
        if page.lasts[chosen] < high or chosen > low or mass.get(at):
            chosen = at
        at = page.parents[at]
    return [x for x in lines if chosen <= x.inside <= page.lasts[chosen]]


def main_text(html: str, sigma: float = 1.0) -> str:
    reader = LineReader()
    reader.feed(html)
    reader.finish()
    return "\n".join(x.text for x in region(reader, sigma))


def extract(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", html_col: str = "html") -> DataFrame:
    """One row per page: id, url, ``text``, ``n_chars``."""

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = [main_text(raw.decode("utf-8", "replace")) for raw in raw_texts(batch.column(2))]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], names=[id_col, url_col, "text", "n_chars"])

    kind = pages.schema[id_col].dataType.simpleString()
    return pages.select(id_col, url_col, html_col).mapInArrow(read, f"`{id_col}` {kind}, `{url_col}` string, text string, n_chars bigint")
