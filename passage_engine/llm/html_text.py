"""Main text of web pages by the text-to-tag ratio of lines.

The standard library's parser streams a page's events. Block elements begin new lines; elements
that never hold the article's text (menus, headers, footers, sidebars, notices, adverts, forms,
scripts, styles, reader comments) are left out with all inside. Each line has a ratio of its text to
its tags; ratios are smoothed by a Gaussian kernel and cut by two-means clustering into content and
other lines. The region with most content text is selected: the innermost <article>, <main> or else
body that holds it. It stays whole; of the regions around it and of those beside it that hold at least
half as much content, the lines of the content cluster stay too (a headline above the article, the
parts of an article in several elements). In a page without such an element the lines between the
first and last content line stay.
"""

from __future__ import annotations

import re
from dataclasses import dataclass, field
from html.parser import HTMLParser

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

#: Fixed lists of elements and of name parts.
BLOCKS = frozenset("address article aside blockquote body caption center dd details dialog dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hr html legend li main menu nav ol optgroup option p pre section summary table tbody td tfoot th thead tr ul".split())
DROPPED = frozenset("head title script style noscript template iframe object svg canvas audio video nav header footer aside form button select textarea menu dialog fieldset".split())
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
NAMES = re.compile(r"(?:^|[\s_-])(?:ads?|advert\w*|banner|promo\w*|sponsor\w*|cookies?|consent|notice|notification|alert|popup|modal|sidebar|side-?bar|widget|menu|nav|navbar|navigation|breadcrumbs?|header|masthead|footer|comments?|comment-?list|replies|respond|disqus|share|sharing|social|related|recommend\w*|newsletter|subscribe|signup|login|search|toolbar|tags|pagination|pager)(?:$|[\s_-])", re.I)
LAYOUT = ("has-", "with-", "no-", "without-")  # of wrappers: they tell of a sidebar, they aren't one
OWN_HEAD = re.compile(r"(?:^|[_-])header$", re.I)
ROLES = frozenset("navigation banner contentinfo complementary search form dialog alert menu menubar".split())
CLOSES_P = BLOCKS - {"body", "html", "caption", "td", "th", "tr", "tbody", "thead", "tfoot", "option", "optgroup"}
ITEMS = {"li": {"li"}, "dt": {"dt", "dd"}, "dd": {"dt", "dd"}, "tr": {"tr", "td", "th"}, "td": {"td", "th"}, "th": {"td", "th"}, "option": {"option"}}


@dataclass
class Line:
    region: int
    parts: list[str] = field(default_factory=list)
    tags: int = 0

    def text(self) -> str:
        return " ".join("".join(self.parts).split())


class Events(HTMLParser):
    """Gathers lines; self.open holds (element, leaves out, region)."""

    def __init__(self):
        super().__init__(convert_charrefs=True)
        self.lines: list[Line] = []
        self.parents = [0]
        self.open: list[tuple[str, bool, int]] = []
        self.now = Line(0)

    def updatepos(self, i, j):
        return j  # positions in lines and columns aren't needed

    def cut(self):
        if self.now.parts or self.now.tags:
            self.lines.append(self.now)
        self.now = Line(self.open[-1][2] if self.open else 0)

    def out(self) -> bool:
        return bool(self.open) and self.open[-1][1]

    def close_to(self, k: int):
        self.open = self.open[:k]
        self.cut()

    def handle_starttag(self, tag, attrs):
        if tag in CLOSES_P:
            for k in range(len(self.open) - 1, -1, -1):
                if self.open[k][0] == "p":
                    self.close_to(k)
                    break
                if self.open[k][0] in BLOCKS:
                    break
        if tag in ITEMS:
            for k in range(len(self.open) - 1, -1, -1):
                if self.open[k][0] in ITEMS[tag]:
                    self.close_to(k)
                    break
                if self.open[k][0] in ("ul", "ol", "dl", "table", "select"):
                    break
        if tag in BLOCKS:
            self.cut()
        if not self.out():
            self.now.tags += 1
            if tag == "br":
                self.now.parts.append(" ")
        if tag in VOID:
            return
        region = self.open[-1][2] if self.open else 0
        inside = region > 0
        # a page's own <header> inside its article holds the headline, others are left out
        left = self.out() or (tag in DROPPED and not (tag == "header" and inside))
        if attrs and not left:
            a = {k: v or "" for k, v in attrs}
            left = a.get("role", "").lower() in ROLES or "hidden" in a or a.get("aria-hidden") == "true"
            if not left and tag not in ("html", "body", "article", "main"):
                names = [x for x in (a.get("class", "") + " " + a.get("id", "")).split() if not x.lower().startswith(LAYOUT)]
                left = any(NAMES.search(x) and not (inside and OWN_HEAD.search(x)) for x in names)
        if not left and tag in ("article", "main"):
            self.parents.append(region)
            region = len(self.parents) - 1
        self.open.append((tag, left, region))
        if tag in BLOCKS:
            self.now.region = region

    def handle_startendtag(self, tag, attrs):
        self.handle_starttag(tag, attrs)
        if tag not in VOID:
            self.handle_endtag(tag)

    def handle_endtag(self, tag):
        for k in range(len(self.open) - 1, -1, -1):
            if self.open[k][0] == tag:
                if not self.out():
                    self.now.tags += 1
                if tag in BLOCKS or self.open[k][1]:
                    self.close_to(k)
                else:
                    del self.open[k]
                return
            if self.open[k][0] in BLOCKS and tag not in BLOCKS:
                return  # no element inside this block is called so

    def handle_data(self, data):
        if not self.out():
            self.now.parts.append(data)


def lines_of(html: str) -> tuple[list[tuple[str, int, int]], list[int]]:
    """(text, tags, region) of each line with text, and the regions' parents."""
    tail = html.rfind("<")
    if tail >= 0 and re.match(r"<[A-Za-z/!?]", html[tail:]) and ">" not in html[tail:] and not html.startswith("<!--", tail):
        html = html[:tail]  # a tag that the page's end cuts off
    events = Events()
    events.feed(html)
    events.close()
    events.cut()
    return [(t, x.tags, x.region) for x in events.lines if (t := x.text())], events.parents


def smooth(values: np.ndarray, sigma: float = 1.0, radius: int = 2) -> np.ndarray:
    k = np.exp(-0.5 * (np.arange(-radius, radius + 1) / sigma) ** 2)
    weight = np.convolve(np.ones(len(values)), k, "same")
    if len(values) < len(k):
        return np.array([(values * (g := np.exp(-0.5 * ((np.arange(len(values)) - i) / sigma) ** 2))).sum() / g.sum() for i in range(len(values))])
    return np.convolve(values, k, "same") / weight


def content_lines(lines: list[tuple[str, int, int]]) -> np.ndarray:
    """True for lines of the cluster of large smoothed ratios."""
    ratio = np.log1p(np.array([len(t) / max(1, n) for t, n, _ in lines], float))
    s = smooth(ratio)
    low, high = float(s.min()), float(s.max())
    if high - low < 1e-9:
        return np.ones(len(s), bool)
    ranked = np.sort(s)
    sums, size, last = np.cumsum(ranked), len(s), -1
    while (k := int(np.searchsorted(ranked, (low + high) / 2, "right"))) != last and 0 < k < size:
        last, low, high = k, float(sums[k - 1]) / k, float(sums[-1] - sums[k - 1]) / (size - k)
    return s > (low + high) / 2


def main_text(html: str) -> str:
    lines, parents = lines_of(html)
    if not lines:
        return ""
    chosen = content_lines(lines)
    weight = np.zeros(len(parents))
    for (t, _, region), c in zip(lines, chosen, strict=True):
        if c:
            weight[region] += len(t)
    best = int(weight[1:].argmax()) + 1 if len(parents) > 1 and weight[1:].any() else 0
    if not best and len(parents) > 1 and (own := [r for _, _, r in lines if r]):
        best = own[0]  # an article without a line of the content cluster is still the article

    def within(region: int) -> bool:
        while region and region != best:
            region = parents[region]
        return region == best

    if best:
        around, r = set(), parents[best]
        while r:
            around.add(r)
            r = parents[r]
        beside = {r for r in range(1, len(parents)) if r != best and parents[r] == parents[best] and 2 * weight[r] >= weight[best] > 0}
        keep = [t for (t, _, r), c in zip(lines, chosen, strict=True) if within(r) or (c and r in around | beside)]
    else:
        at = np.flatnonzero(chosen)
        keep = [t for t, _, _ in lines[at[0] : at[-1] + 1]]
    return "\n\n".join(keep)


def extract(pages: DataFrame) -> DataFrame:
    """Pages (page_id, url, html) to (page_id, url, text, n_chars).

    Null html is empty; a page without content has the empty text. White space inside a block is
    one space; blocks are joined by two line ends. Repeated rows stay; other columns are not read.
    """

    def run(batches):
        for b in batches:
            got = [main_text(h or "") for h in b.column("html").to_pylist()]
            yield pa.record_batch([b.column("page_id"), b.column("url"), pa.array(got, pa.string()), pa.array([len(t) for t in got], pa.int64())], names=["page_id", "url", "text", "n_chars"])

    kinds = {f.name: f.dataType.simpleString() for f in pages.schema}
    return pages.select("page_id", "url", "html").mapInArrow(run, f"page_id {kinds['page_id']}, url {kinds['url']}, text string, n_chars long")
