"""HTML extraction: parser events to block lines, text-to-tag ratios, Gaussian smoothing, threshold clustering.

The standard library's streaming parser turns a page into block lines with the number of tags each holds.
Lines inside menus, headers, footers, sidebars, notices, adverts, forms, scripts, styles or comments (by element or
by a class, id or role that is or starts with such a word) are never content. Class words never drop an article or main, nor an
element that contains one; only readers' comments and related pages that come as articles stay out if the page has other articles.

The smoothed text-to-tag ratio of the other lines is split at its deviation; the lines above form the clusters that select the
region: from the page's top down, the container that holds most of their text. An article or main element is only a
prior there: its clusters count PRIOR times and an article is not divided further. In other regions a container without
any clustered line is left out; headings just before a region belong to it. All other lines of a region are kept, short ones too.

Defined cases: null or empty html gives an empty text; unclosed elements end with their parent or the page; on a page whose lines
all have one ratio every line is in a cluster; nothing is capped.
"""

from __future__ import annotations

import re
from html.parser import HTMLParser

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from .common import map_batches

#: Elements that are never content, void elements, elements that stay inside a line.
DROPPED = frozenset("nav header footer aside form script style noscript template iframe object svg canvas select button textarea head title dialog menu video audio".split())
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
INLINE = frozenset("a abbr acronym b bdi bdo big cite code data del dfn em font i img ins kbd label mark q rp rt ruby s samp small span strike strong sub sup time tt u var wbr input".split())
RAW = frozenset(("script", "style"))
#: Words of class, id or role that mark page furniture.
FURNITURE = re.compile(r"(?:^|\s)(?:ads?|advert\w*|sponsor\w*|promo\w*|banner|cookies?|consent|gdpr|notice|alert|popup|modal|nav\w*|menu\w*|breadcrumbs?|sidebar|side|aside|widget\w*|footer|header|masthead|comments?|replies|disqus|respond|share|sharing|social|related|recommend\w*|newsletter|subscribe|signup|login|form|search|pagination|pager|toolbar|copyright|contentinfo|navigation|complementary)(?:$|[\s_-])", re.I)
#: Those whose articles are other people's texts.
OTHERS = re.compile(r"(?:^|\s)(?:comments?|replies|disqus|respond|related|recommend\w*)(?:$|[\s_-])", re.I)
CLOSES = {"p": frozenset(("p",)), "li": frozenset(("li",)), "dt": frozenset(("dt", "dd")), "dd": frozenset(("dt", "dd")), "tr": frozenset(("tr", "td", "th")), "td": frozenset(("td", "th")), "th": frozenset(("td", "th")), "option": frozenset(("option",))}
BLOCKS = frozenset("h1 h2 h3 h4 h5 h6 div p ul ol table article section main nav header footer aside form blockquote pre dl hr figure".split())
ROOTS = frozenset(("article", "main"))
TITLES = frozenset(("h1", "h2", "h3"))
#: Elements that only hold others; the region is one of them.
CONTAINERS = frozenset("html body div section main article center table tbody tr td".split())
#: Parameters: share of the clustered text that makes a container the region, weight of clustered text in article or main.
DOMINANT, PRIOR = 0.6, 3.0


class Lines(HTMLParser):
    """Collects (parts, tags, block) for each block line; blocks know their parent, tag and whether they lie in an article or main.

    Whether an element with a furniture word contains an article is known at the page's end, so parts of lines keep such elements.
    """

    def __init__(self):
        super().__init__(convert_charrefs=True)
        self.stack: list[tuple[str, int, bool, tuple[int, ...]]] = []  # tag, block number, dropped, elements with furniture words
        self.lines: list[tuple[list[tuple[str, tuple[int, ...]]], int, int]] = []
        self.parts: list[tuple[str, tuple[int, ...]]] = []
        self.parent, self.tag, self.rooted = [0], [""], [False]
        self.holders: set[int] = set()
        self.others: set[int] = set()
        self.tags = self.count = 0

    def top(self) -> tuple[str, int, bool, tuple[int, ...]]:
        return self.stack[-1] if self.stack else ("", 0, False, ())

    def end_line(self) -> None:
        if self.parts and not self.top()[2]:
            self.lines.append((self.parts, self.tags, self.top()[1]))
        if self.parts:
            self.parts = []
        self.tags = 0

    def handle_starttag(self, tag, attrs):
        if tag not in INLINE:
            self.end_line()
        if tag in BLOCKS:  # a block start ends an open paragraph with whatever is left open in it
            for k in range(len(self.stack) - 1, -1, -1):
                if self.stack[k][0] == "p":
                    del self.stack[k:]
                    break
                if self.stack[k][0] not in INLINE:
                    break
        elif tag in CLOSES and self.stack and self.stack[-1][0] in CLOSES[tag]:
            self.stack.pop()
        self.tags += 1
        if tag in VOID:
            return
        self.count += 1
        _, block, dropped, marks = self.top()
        words = " ".join(v for k, v in attrs if k in ("class", "id", "role") and v)
        dropped = dropped or tag in DROPPED or any(k == "hidden" or k == "aria-hidden" and v == "true" for k, v in attrs)
        if tag in ROOTS:
            if not dropped:
                self.holders.update(marks)
        elif words and tag not in ("body", "html") and FURNITURE.search(words):
            marks = (*marks, self.count)
            if OTHERS.search(words):
                self.others.add(self.count)
        if tag not in INLINE:
            self.parent.append(block)
            self.tag.append(tag)
            self.rooted.append(tag in ROOTS or self.rooted[block])
            block = len(self.parent) - 1
        self.stack.append((tag, block, dropped, marks))

    def handle_startendtag(self, tag, attrs):
        self.handle_starttag(tag, attrs)
        if tag not in VOID:
            self.handle_endtag(tag)

    def handle_endtag(self, tag):
        self.tags += 1
        if tag not in INLINE:
            self.end_line()
        for k in range(len(self.stack) - 1, -1, -1):
            if self.stack[k][0] == tag:
                del self.stack[k:]
                return
            if tag in INLINE and self.stack[k][0] not in INLINE:
                return

    def handle_data(self, data):
        if not self.top()[2]:
            self.parts.append((data, self.top()[3]))

    def finish(self) -> list[tuple[str, int, int]]:
        if self.rawdata and not (self.stack and self.stack[-1][0] in RAW):
            self.close()
        self.end_line()
        lines = self.kept(self.holders - self.others)
        return lines if any(self.rooted[block] for _, _, block in lines) else self.kept(self.holders)

    def kept(self, excused: set[int]) -> list[tuple[str, int, int]]:
        """The lines' texts outside furniture."""
        texts = (" ".join("".join(d for d, marks in parts if excused.issuperset(marks)).split()) for parts, *_ in self.lines)
        return [(t, *line[1:]) for t, line in zip(texts, self.lines) if t]

    def above(self, block: int) -> list[int]:
        """A block and its ancestors, the page's top (0) last."""
        out = [block]
        while block:
            block = self.parent[block]
            out.append(block)
        return out


def smooth(x: np.ndarray, radius: int = 2) -> np.ndarray:
    """Gaussian smoothing with reflected ends."""
    if len(x) < 2:
        return x
    reach = np.arange(-radius, radius + 1)
    kernel = np.exp(-(reach**2) / (2 * (radius / 2) ** 2))
    return np.convolve(np.pad(x, radius, mode="symmetric"), kernel / kernel.sum(), "valid")


def clustered(lines: list[tuple[str, int, int]]) -> list[bool]:
    """Whether a line's smoothed text-to-tag ratio reaches the deviation of all."""
    ratio = smooth(np.array([len(t) / max(1, n) for t, n, _ in lines], float))
    return (ratio >= min(ratio.std(), ratio.max())).tolist()


def content_lines(page: Lines, lines: list[tuple[str, int, int]], marked: list[bool]) -> list[str]:
    """The lines of the region that the marked ones select."""
    if not lines:
        return []
    mass: dict[int, float] = {}
    held: dict[int, int] = {}
    chains = [page.above(block) for _, _, block in lines]
    for (text, _, block), chain, mark in zip(lines, chains, marked):
        weight = mark * len(text) * (PRIOR if page.rooted[block] else 1.0)
        for b in chain:
            mass[b] = mass.get(b, 0.0) + weight
            held[b] = held.get(b, 0) + 1
    children: dict[int, set[int]] = {}
    for b in mass:
        if b:
            children.setdefault(page.parent[b], set()).add(b)
    home, goal = 0, DOMINANT * mass[0]
    while page.tag[home] != "article":
        inner = [b for b in children.get(home, ()) if page.tag[b] in CONTAINERS and mass[b] >= goal and (held[b] > 1 or page.tag[b] in ROOTS or held[home] == 1)]
        if not inner:
            break
        home = max(inner, key=mass.__getitem__)
    around = page.parent[home] if home else 0
    out: list[str] = []
    inside = False
    for (text, _, block), chain in zip(lines, chains):
        if home in chain:
            inside = True
            branch = chain[chain.index(home) - 1] if block != home else home
            if page.tag[home] == "article" or branch == home or mass[branch] or held[branch] == 1 or page.tag[branch] not in CONTAINERS:
                out.append(text)
        elif not inside and page.tag[block] in TITLES and page.parent[block] == around and page.tag[around] not in ("", "html", "body"):
            out.append(text)
    return out


def main_text(html: str | None) -> str:
    if not html:
        return ""
    parser = Lines()
    parser.feed(html)
    lines = parser.finish()
    return " ".join(content_lines(parser, lines, clustered(lines) if lines else []))


def extract_pages(pages: DataFrame) -> DataFrame:
    """(page_id, url, text, n_chars) of every page."""

    def make():
        def step(batch: pa.RecordBatch) -> pa.RecordBatch:
            texts = [main_text(h) for h in batch.column(2).to_pylist()]
            return pa.RecordBatch.from_arrays([batch.column(0).cast(pa.int64()), batch.column(1), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], ["page_id", "url", "text", "n_chars"])

        return step

    return map_batches(pages.select("page_id", "url", "html"), make, "page_id long, url string, text string, n_chars long", "html")
