"""Main text of web pages by text-to-tag ratios of parser events.

The standard library's parser streams events; no tree is kept. Block tags cut the page into lines. A line knows its
text, how much of it stands in links, its tags, the element that holds it, and two signals of the markup: whether an
enclosing element is of a kind that never holds main text (menus, headers, footers, sidebars, forms, scripts, notices,
adverts, comments by name), and whether it lies in an article or main element.

On every page the ratio of text outside links to tags decides: ratios of lines are smoothed with a Gaussian, and a
threshold found by two-means of their logarithms parts content lines from others. The signals only weigh in: lines
of a kind that never holds main text have the ratio 0 and stay out; where a page has article or main elements, lines outside of them keep a
fraction of their ratio. Content regions are then drawn around content lines: an element most of whose own text
stands in content lines is content with its headings and short lines; elsewhere short lines between content lines of one element, and headings
right before them, go along.

Defined results: null and empty pages give the empty text; broken and unclosed markup is read as far as the parser
goes; bytes that are no UTF-8 are read as replacement characters; very long pages are read whole; pages repeat as
given; white space inside a block is one space; an empty table gives an empty result; columns of the input other than page_id, url and html are not read.
"""

from __future__ import annotations

import math
import re
from dataclasses import dataclass
from html.parser import HTMLParser

import pyarrow as pa
from pyspark.sql import DataFrame

from .common import byte_column, map_rows

# Tag and attribute names.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
BLOCK = frozenset(
    "address article aside blockquote body br button caption center dd details dialog dir div dl dt fieldset figcaption "
    "figure footer form h1 h2 h3 h4 h5 h6 head header hr html legend li main menu nav ol option p pre section select "
    "summary table tbody td textarea tfoot th thead title tr ul".split()
)
NEVER = frozenset(
    "aside button dialog fieldset footer form head header iframe input label menu nav noscript object option "
    "script select style svg template textarea title".split()
)
MAIN = frozenset("article main".split())
CLOSES_P = BLOCK - frozenset("br".split())
#: Elements that hold lines; p, headings and list items are lines of the element around them.
HOLDERS = BLOCK - frozenset("br caption dd dt figcaption h1 h2 h3 h4 h5 h6 hr legend li option p pre summary tr".split())
HEADINGS = frozenset("h1 h2 h3 h4 h5 h6".split())
BAD_NAME = re.compile(
    r"(?:^|[-_ ])(?:ad|ads|adv|advert\w*|banner|breadcrumbs?|comments?|consent|cookies?|copyright|disqus|discussion|footer|"
    r"gdpr|header|masthead|menu|modal|nav\w*|newsletter|notice|notification|overlay|pagination|popup|promo\w*|related|replies|"
    r"reply|respond|share|sharing|sidebar|social|sponsor\w*|subscribe|toolbar|tags?|widget)(?:$|[-_ ])"
)
BAD_ROLE = frozenset("navigation banner contentinfo complementary search alert dialog menu menubar form".split())
SIGMA = 1.5


#: What is left of the ratio of lines outside article and main elements, where a page has them.
OUTSIDE = 0.1


@dataclass
class Line:
    text: str
    links: int  # characters in links
    tags: int
    bad: bool
    main: bool
    holder: int
    heading: bool


class Lines(HTMLParser):
    """Collects the lines of a page."""

    def __init__(self) -> None:
        super().__init__(convert_charrefs=True)
        self.lines: list[Line] = []
        self.parts: list[str] = []
        self.tags = self.links = self.in_links = 0
        self.open: list[tuple[str, bool, bool, int]] = []  # tag, bad, main, holder before it
        self.count: dict[str, int] = {}
        self.bad = self.main = self.holder = self.holders = self.headings = 0
        self.page = {0}  # holders that are the page itself

    def cut(self) -> None:
        text = " ".join("".join(self.parts).split())
        if text:
            self.lines.append(Line(text, self.links, self.tags, self.bad > 0, self.main > 0, self.holder, self.headings > 0))
            self.tags = 0
        self.links = 0
        self.parts.clear()

    def handle_starttag(self, tag, attrs):
        self.tags += 1
        if tag in BLOCK:
            self.cut()
        if tag in CLOSES_P and self.count.get("p"):
            for i in range(len(self.open) - 1, -1, -1):
                if self.open[i][0] == "p":
                    self.leave(i)
                    break
                if self.open[i][0] in HOLDERS:
                    break
        if tag in VOID:
            return
        a = dict(attrs)
        names = f"{a.get('class') or ''} {a.get('id') or ''}".lower()
        bad = (
            tag in NEVER and not (tag == "header" and self.main > 0)
            or (a.get("role") or "").lower() in BAD_ROLE
            or tag not in MAIN and tag not in ("html", "body") and bool(names.strip()) and bool(BAD_NAME.search(names))
            or "hidden" in a
            or (a.get("aria-hidden") or "").lower() == "true"
            or "display:none" in (a.get("style") or "").replace(" ", "").lower()
        )
        main = tag in MAIN or (a.get("role") or "").lower() == "main"
        self.open.append((tag, bad, main, self.holder))
        self.count[tag] = self.count.get(tag, 0) + 1
        self.bad += bad
        self.main += main
        self.in_links += tag == "a"
        self.headings += tag in HEADINGS
        if tag in HOLDERS:
            self.holders += 1
            self.holder = self.holders
            if tag in ("html", "body"):
                self.page.add(self.holder)

    def leave(self, to: int) -> None:
        for tag, bad, main, _ in self.open[to:]:
            self.bad -= bad
            self.main -= main
            self.count[tag] -= 1
            self.in_links -= tag == "a"
            self.headings -= tag in HEADINGS
        self.holder = self.open[to][3]
        del self.open[to:]

    def handle_startendtag(self, tag, attrs):
        self.handle_starttag(tag, attrs)
        if tag not in VOID:
            self.handle_endtag(tag)

    def handle_endtag(self, tag):
        self.tags += 1
        if tag in BLOCK:
            self.cut()
        if self.count.get(tag):
            for i in range(len(self.open) - 1, -1, -1):
                if self.open[i][0] == tag:
                    self.leave(i)
                    return

    def handle_data(self, data):
        if not self.open or self.open[-1][0] not in ("script", "style"):
            self.parts.append(data)
            if self.in_links:
                self.links += len(data)


def smooth(values: list[float], sigma: float = SIGMA) -> list[float]:
    reach = math.ceil(2 * sigma)
    kernel = [math.exp(-k * k / (2 * sigma * sigma)) for k in range(-reach, reach + 1)]
    out = []
    for i in range(len(values)):
        lo, hi = max(0, i - reach), min(len(values), i + reach + 1)
        w = kernel[lo - i + reach : hi - i + reach]
        out.append(sum(a * b for a, b in zip(w, values[lo:hi], strict=True)) / sum(w))
    return out


def threshold(values: list[float]) -> float:
    """Boundary of two means in one dimension."""
    lo, hi = min(values), max(values)
    for _ in range(50):
        cut = (lo + hi) / 2
        low, high = [x for x in values if x <= cut], [x for x in values if x > cut]
        if not low or not high:
            return lo
        new = sum(low) / len(low), sum(high) / len(high)
        if new == (lo, hi):
            break
        lo, hi = new
    return (lo + hi) / 2


def ratios(lines: list[Line]) -> list[float]:
    """Logarithm of the text-to-tag ratio of each line, with the signals of the markup weighed in."""
    parted = any(x.main and not x.bad for x in lines)
    out = []
    for x in lines:
        r = 0.0 if x.bad else max(0, len(x.text) - x.links) / max(1, x.tags)
        out.append(math.log1p(r * OUTSIDE if parted and not x.main else r))
    return out


def content(lines: list[Line], page: set[int]) -> list[bool]:
    """Which lines are content: two clusters of smoothed ratios, then regions around the upper one."""
    own = ratios(lines)
    if not own or max(own) == 0:
        return [False] * len(lines)
    near = smooth(own)
    cut = threshold(near)
    # Lines of one kind are no two clusters. A line of markup beside content is lifted by smoothing, so its own ratio
    # has to reach half of the cut too.
    flat = max(own) - min(own) < 1.0
    high = [not x.bad and o > 0 and (flat or n >= cut and 2 * o >= cut) for x, o, n in zip(lines, own, near, strict=True)]
    mass: dict[int, list[int]] = {}
    for x, h in zip(lines, high, strict=True):
        if not x.bad:
            m = mass.setdefault(x.holder, [0, 0])
            m[h] += len(x.text)
    ends: dict[int, list[int]] = {}
    for i, (x, h) in enumerate(zip(lines, high, strict=True)):
        if h:
            ends.setdefault(x.holder, [i, i])[1] = i
    kept = list(high)
    for i in range(len(lines) - 1, -1, -1):
        x = lines[i]
        if kept[i] or x.bad or own[i] == 0:
            continue
        low, up = mass[x.holder]
        first, last = ends.get(x.holder, (i + 1, i - 1))
        whole = up >= low and x.holder not in page  # the page itself holds everything
        leads = x.heading and i + 1 < len(lines) and kept[i + 1]
        kept[i] = whole or first < i < last or leads
    return kept


def extract(html: str | None) -> str:
    if not html:
        return ""
    parser = Lines()
    parser.feed(html)
    parser.close()
    parser.cut()
    return " ".join(x.text for x, k in zip(parser.lines, content(parser.lines, parser.page), strict=True) if k)


def extract_pages(pages: DataFrame) -> DataFrame:
    """page_id, url, text, n_chars of every page."""

    def one(batch):
        texts = [extract(None if x is None else x.decode("utf-8", "replace")) for x in byte_column(batch, "html")]
        cols = [batch.column(0), batch.column(1), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())]
        yield pa.RecordBatch.from_arrays(cols, ["page_id", "url", "text", "n_chars"])

    slim = pages.selectExpr("cast(page_id as long) page_id", "url", "html")
    return map_rows(slim, "page_id long, url string, text string, n_chars long", one)
