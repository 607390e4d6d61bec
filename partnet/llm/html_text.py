"""Main text of web pages: parser events, text-to-tag ratios, Gaussian smoothing, threshold clustering.

The standard library's streaming parser turns a page into lines, one for each
block of text. A line's ratio is its characters per tag; the logarithms of the
ratios, raised inside of article and main elements, are smoothed with a Gaussian
along the page and split in two by one-dimensional clustering. Lines above the
threshold are content.

Lines belong to groups: an article or main element, or, outside of these, what
stands directly in the same division or section. A group stays if half of its
characters or more are content, and the one with most content does in any case.
A division whose own lines hold half of all content keeps what is nested between
them. All lines of a group stay together, short ones too; a group that is not content
goes whole.

Lines in navigation, headers, footers, asides, forms, scripts, styles and in
elements whose class or id names an advert, notice, sidebar, menu or comment
never stay, whatever their ratio. Names are whole tokens or compounds of known
words, and headings have none; an article or main on or under such a name counts
if the page has no other and less text elsewhere.

Defined results: null and empty pages give an empty text, as do pages without
any text outside of boilerplate; unclosed and stray tags are tolerated; repeated
rows and null ids or urls are judged each on their own; extra columns are ignored.
"""

from __future__ import annotations

import re
from html.parser import HTMLParser

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from partnet.llm.common import map_rows

VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
#: elements that begin and end a line
BLOCKS = frozenset(
    "address article aside blockquote body center dd details dialog dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 head header hgroup hr html legend li main menu nav ol optgroup option p pre section select summary table tbody td tfoot th thead title tr ul".split()
)
DROPPED = frozenset("head title script style noscript template nav footer aside form button select textarea iframe object svg canvas dialog menu".split())
REGION = frozenset(("article", "main"))
#: elements that hold the lines of a group
BOXES = frozenset("body article main section div td th center fieldset".split())
#: what an article or main element adds to the logarithm of a line's ratio
TAGGED = 3.0
#: clusters of ratios within a factor of two are one
SINGLE = float(np.log(2))
#: an opening tag of the first kind closes an open element of the second, up to a boundary
IMPLIED = {"li": {"li"}, "dt": {"dt", "dd"}, "dd": {"dt", "dd"}, "tr": {"tr", "td", "th"}, "td": {"td", "th"}, "th": {"td", "th"}, "option": {"option"}}
CLOSES_P = BLOCKS - {"body", "html", "head", "title", "option", "optgroup", "legend", "li", "td", "th", "tr", "tbody", "thead", "tfoot", "summary", "dd", "dt"}
SCOPES = frozenset("ul ol dl table select body html article section div main aside nav td th".split())
#: class, id and role tokens that name boilerplate, alone or in a compound with each other and with the words below
BOILERPLATE = frozenset(
    "ad ads advert adverts advertisement advertising sponsor sponsored promo promotion banner sidebar menu nav navbar navigation breadcrumb breadcrumbs footer masthead cookie cookies consent gdpr notice notices disclaimer popup modal overlay newsletter subscribe signup share sharing social related recommended comment comments disqus replies reply widget toolbar pagination pager".split()
)
COMPOUNDS = frozenset(("site-header", "side-bar"))
NEUTRAL = frozenset(
    "site main page top bottom left right primary secondary global box area list block wrap wrapper container section bar inner outer link links button buttons icon icons post posts article articles item items story stories slot unit zone form message text title thread media google dfp".split()
)
HEADINGS = frozenset(("h1", "h2", "h3", "h4", "h5", "h6"))


def names_boilerplate(marks: str) -> bool:
    """Whether a whole token does; has-sidebar, comments-open and share-price say something about an element, not what it is."""
    for token in marks.lower().split():
        parts = [x for x in re.split(r"[_-]+", token) if x and not x.isdigit()]
        if token.replace("_", "-") in COMPOUNDS or (any(x in BOILERPLATE for x in parts) and all(x in BOILERPLATE or x in NEUTRAL for x in parts)):
            return True
    return False


#: dropped by the name of an element on or above the region, or by anything else
BY_NAME, WHOLLY = 1, 2


class PageLines(HTMLParser):
    """Lines of a page: (text, tags met since the last line, article or main element or 0, dropped: 0, BY_NAME or WHOLLY, box).

    boxes has the box around each box; the page is box 0, in itself.
    """

    def __init__(self):
        super().__init__(convert_charrefs=True)
        self.open: list[tuple[str, int, int, bool, int]] = []  # tag, dropped, region, opened a line, box
        self.lines: list[tuple[str, int, int, int, int]] = []
        self.parts: list[str] = []
        self.boxes = [0]
        self.tags = self.regions = 0

    def state(self) -> tuple[int, int, int]:
        return (*self.open[-1][1:3], self.open[-1][4]) if self.open else (0, 0, 0)

    def end_line(self) -> None:
        text = " ".join("".join(self.parts).split())
        if text:
            dropped, region, box = self.state()
            self.lines.append((text, self.tags, region, dropped, box))
            self.tags = 0
        self.parts = []

    def handle_starttag(self, tag: str, attrs: list) -> None:
        block = tag in BLOCKS or tag in DROPPED
        if block:
            self.end_line()
        self.tags += 1
        if tag in VOID:
            if tag == "br":
                self.parts.append(" ")
            return
        self.close_implied(tag)
        dropped, region, box = self.state()
        marks = " ".join(v for k, v in attrs if k in ("class", "id", "role") and v)
        names = bool(marks) and tag not in ("html", "body") and tag not in HEADINGS and names_boilerplate(marks)
        if tag in DROPPED or (names and region) or (tag == "header" and not region) or any(k == "hidden" for k, _ in attrs):
            dropped = WHOLLY
        elif names:
            dropped = max(dropped, BY_NAME)
        if names and not block:
            self.end_line()
        if tag in REGION and dropped < WHOLLY and not region:
            self.regions += 1
            region = self.regions
        if tag in BOXES:
            self.boxes.append(box)
            box = len(self.boxes) - 1
        self.open.append((tag, dropped, region, block or names, box))

    def close_implied(self, tag: str) -> None:
        targets = IMPLIED.get(tag)
        if tag in CLOSES_P:
            at = next((i for i in range(len(self.open) - 1, -1, -1) if self.open[i][0] == "p" or self.open[i][0] in SCOPES), None)
            if at is not None and self.open[at][0] == "p":
                del self.open[at:]
        elif targets:
            for i in range(len(self.open) - 1, -1, -1):
                if self.open[i][0] in targets:
                    del self.open[i:]
                    break
                if self.open[i][0] in SCOPES:
                    break

    def handle_endtag(self, tag: str) -> None:
        self.tags += 1
        if tag == "br":
            self.parts.append(" ")
        at = next((i for i in range(len(self.open) - 1, -1, -1) if self.open[i][0] == tag), None)
        if at is None:
            return
        if any(x[3] for x in self.open[at:]):
            self.end_line()
        del self.open[at:]

    def handle_startendtag(self, tag: str, attrs: list) -> None:
        self.handle_starttag(tag, attrs)
        if tag in ("svg", "iframe"):
            self.handle_endtag(tag)

    def handle_data(self, data: str) -> None:
        self.parts.append(data)

    def finish(self) -> PageLines:
        self.close()
        self.end_line()
        return self


def page_lines(html: str) -> PageLines:
    try:
        page = PageLines()
        page.feed(html)
        return page.finish()
    except (AssertionError, ValueError):  # declarations that the parser can't read become text
        page = PageLines()
        page.feed(html.replace("<!", "&lt;!"))
        return page.finish()


def smooth(values: np.ndarray, sigma: float = 1.5) -> np.ndarray:
    reach = int(np.ceil(3 * sigma))
    kernel = np.exp(-0.5 * (np.arange(-reach, reach + 1) / sigma) ** 2)
    weight = np.convolve(np.ones(values.size), kernel)[reach : reach + values.size]
    return np.convolve(values, kernel)[reach : reach + values.size] / weight


def split_level(values: np.ndarray) -> float:
    """Threshold between two one-dimensional clusters: midway between their means, repeated until it rests.

    Means closer than SINGLE are one cluster, and everything is above the threshold.
    """
    level, low, high = float(values.mean()), values[:0], values[:0]
    for _ in range(50):
        low, high = values[values < level], values[values >= level]
        if not low.size or not high.size:
            break
        fresh = float(low.mean() + high.mean()) / 2
        if abs(fresh - level) < 1e-9:
            break
        level = fresh
    return level if low.size and high.size and high.mean() - low.mean() >= SINGLE else float(values.min())


def content_groups(group: np.ndarray, content: np.ndarray, size: np.ndarray) -> dict[int, int]:
    """Groups that stay, with their characters of content."""
    whole, mass = {}, {}
    for g, yes, n in zip(group.tolist(), content.tolist(), size.tolist(), strict=True):
        whole[g] = whole.get(g, 0) + n
        mass[g] = mass.get(g, 0) + n * yes
    most = max(mass.values(), default=0)
    return {g: m for g, m in mass.items() if m and (2 * m >= whole[g] or m == most)}


def main_text(html: str | None, sigma: float = 1.5, level: float | None = None) -> str:
    """level: a threshold in place of the one that clustering finds."""
    page = page_lines(html) if html else None
    if not page or not page.lines:
        return ""
    lines = page.lines
    region, box = np.array([x[2] for x in lines]), np.array([x[4] for x in lines])
    own = np.array([not x[3] for x in lines])
    named = np.array([x[3] == BY_NAME for x in lines]) & (region > 0)
    size = np.array([len(x[0]) for x in lines])
    if not (own & (region > 0)).any() and size[named].sum() > size[own].sum():
        own = named  # the page's only region lies in a wrapper with such a name
    if not own.any():
        return ""
    ratio = np.log1p(size / np.maximum(1, [x[1] for x in lines])) + TAGGED * (region > 0) * own
    smoothed = smooth(ratio, sigma)
    content = smoothed >= (split_level(smoothed) if level is None else level)
    group = np.where(region > 0, -region, box)  # boxes from 0 up, regions below
    mine = np.flatnonzero(own)
    stays = content_groups(group[mine], content[mine], size[mine])
    half = sum(stays.values()) / 2
    spans = {g: np.flatnonzero(own & (group == g))[[0, -1]] for g, mass in stays.items() if g >= 0 and mass >= half}

    def enclosed(k: int) -> bool:
        at = int(box[k])
        while at and at not in spans:
            at = page.boxes[at]
        return at in spans and spans[at][0] < k < spans[at][1]

    return "\n".join(lines[k][0] for k in mine if int(group[k]) in stays or enclosed(k))


def extract_pages(pages: DataFrame, sigma: float = 1.5) -> DataFrame:
    """Per page: page_id, url, text, n_chars (code points)."""

    def start():
        def step(batch: pa.RecordBatch) -> pa.RecordBatch:
            texts = [main_text(x, sigma) for x in batch["html"].to_pylist()]
            return pa.RecordBatch.from_arrays([batch["page_id"], batch["url"], pa.array(texts, pa.string()), pa.array([len(x) for x in texts], pa.int64())], ["page_id", "url", "text", "n_chars"])

        return step

    return map_rows(pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), F.col("html").cast("string").alias("html")), start, "page_id long, url string, text string, n_chars long")
