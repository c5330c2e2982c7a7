"""Main text of HTML pages from streaming parser events.

The standard library's parser feeds lines: a block-level tag ends one.  Every
visible line of the page, menus and footers included, carries its text length
and the tags met in it; its ratio is the one over the other.  Ratios are
smoothed along the page with a Gaussian, and a threshold from two clusters of
the smoothed values splits lines into content and the rest.

Content lines choose the region: article and main elements that hold a fair
share of them and are mostly content; where there are none, or content lies
elsewhere, the innermost plain container that holds nearly all content, without
its boxes that are not content.  A chosen region is kept whole, so that its
headings and short paragraphs stay, but for lines in elements that never hold
content (menus, forms, notices, comments and the like).

Cases: null and empty pages give the empty text; broken markup is read as far
as the parser reads it; a page in which no line stands out counts all lines
outside such elements as content; character references are decoded.
"""

from __future__ import annotations

import re
from html.parser import HTMLParser

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gridpress.session import arrow_rows, ship

# fixed values: element names by the HTML standard's roles
BLOCKS = frozenset("address article aside blockquote body br caption center dd details dialog dir div dl dt fieldset figcaption figure footer form frameset h1 h2 h3 h4 h5 h6 header hgroup hr html legend li main menu nav ol option p pre section summary table tbody td tfoot th thead tr ul".split())
UNSEEN = frozenset("script style template noscript head title svg iframe object canvas noembed noframes datalist audio video".split())
NEVER = UNSEEN | frozenset("nav header footer aside form button select textarea menu dialog".split())
HEADINGS = frozenset(["h1", "h2"])
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
REGIONS = frozenset(["article", "main"])
CONTAINERS = frozenset(["div", "section", "td", "body", "blockquote", "article", "main"])
NEVER_ROLES = frozenset("navigation banner contentinfo complementary search form menu menubar dialog alert alertdialog toolbar".split())
NEVER_NAMES = re.compile(
    r"(?:^|[\s_-])(?:ads?|advert\w*|banner|sponsor\w*|promo\w*|nav\w*|menu\w*|breadcrumb\w*|sidebar\w*|widget\w*|footer|header|masthead|comments?|reply|replies|respond|disqus\w*|cookie\w*|consent|gdpr|notice\w*|alert\w*|popup|modal|overlay|newsletter|subscri\w*|share|sharing|social\w*|related|recommend\w*|pager|pagination|login|signup|search|toolbar|skip\w*|toc|hidden|copyright|legal|disclaimer)(?:$|[\s_-])",
    re.IGNORECASE,
)
BLANKS = re.compile(r"\s+")
# a paragraph's end tag may be left out before these, by the HTML standard
ENDS_P = frozenset("address article aside blockquote center details dialog dir div dl fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr main menu nav ol p pre section summary table ul".split())
SIGMA = 1.5
# shares of content lines' characters: what marked elements must hold, a region of itself, and an inner container of the outer
MARKED_SHARE, OWN_SHARE, INNER_SHARE = 1 / 3, 0.5, 0.9


class Lines(HTMLParser):
    """Visible lines of a page: text, tags met, characters in links, the region they stand in, and whether they can be content."""

    def __init__(self):
        super().__init__(convert_charrefs=True)
        self.stack: list[tuple[str, int, int]] = []  # name; 0 open to content, 1 furniture, 2 unseen; region
        self.text: list[str] = []
        self.tags: list[int] = []
        self.region: list[int] = []
        self.out: list[bool] = []
        self.head: list[bool] = []
        self.links: list[int] = []
        self.kinds: list[str] = ["page"]
        self.parent: list[int] = [0]
        self.held: list[str] = []
        self.met = 0
        self.linked = 0

    def _at(self) -> tuple[int, int]:
        return self.stack[-1][1:] if self.stack else (0, 0)

    def _cut(self) -> None:
        joined = BLANKS.sub(" ", "".join(self.held)).strip(" ")
        if joined:
            out, region = self._at()
            self.text.append(joined)
            self.tags.append(max(self.met, 1))
            self.region.append(region)
            self.out.append(out > 0)
            self.head.append(any(x[0] in HEADINGS for x in self.stack[-3:]))
            self.links.append(self.linked)
            self.met = 0
        self.held.clear()
        self.linked = 0

    def handle_starttag(self, tag, attrs):
        self.met += 1
        if tag in BLOCKS or tag in NEVER:
            self._cut()
        if tag in ENDS_P and self.stack and any(x[0] == "p" for x in self.stack[-4:]):
            self._close("p", ENDS_P - {"p"} | CONTAINERS)
        if tag in VOID:
            return
        out, region = self._at()
        if out < 2:
            d = dict(attrs)
            if tag in UNSEEN or "hidden" in d or (d.get("aria-hidden") or "").lower() == "true" or re.search(r"display\s*:\s*none", d.get("style") or "", re.IGNORECASE):
                out = 2
        if not out:
            inside = self.kinds[region] in REGIONS
            out = int(tag in NEVER or (d.get("role") or "").lower() in NEVER_ROLES)
            if not out and tag not in ("html", "body", *REGIONS):
                out = int(bool(NEVER_NAMES.search(f"{d.get('class') or ''} {d.get('id') or ''}")))
            if not out and (tag in REGIONS or (tag in CONTAINERS and not inside)):
                self.kinds.append(tag)
                self.parent.append(region)
                region = len(self.kinds) - 1
        self.stack.append((tag, out, region))

    def handle_startendtag(self, tag, attrs):
        self.met += 1
        if tag in BLOCKS:
            self._cut()

    def _close(self, tag: str, stop: frozenset) -> None:
        for i in range(len(self.stack) - 1, -1, -1):
            if self.stack[i][0] == tag:
                del self.stack[i:]
                return
            if self.stack[i][0] in stop:
                return

    def handle_endtag(self, tag):
        self.met += 1
        if tag in BLOCKS or tag in NEVER:
            self._cut()
        # an inline end tag closes nothing beyond its block, a block end tag closes what is open in it
        self._close(tag, frozenset() if tag in BLOCKS or tag in NEVER else BLOCKS)

    def handle_data(self, data):
        if self._at()[0] == 2:
            return
        self.held.append(data)
        if any(x[0] == "a" for x in self.stack[-4:]):
            self.linked += len(data.strip())

    def finish(self) -> None:
        self.close()
        self._cut()


def smooth(x: np.ndarray, sigma: float = SIGMA) -> np.ndarray:
    """Gaussian smoothing; weights at the borders add to one again."""
    reach = max(1, int(np.ceil(3 * sigma)))
    w = np.exp(-0.5 * (np.arange(-reach, reach + 1) / sigma) ** 2)
    return np.convolve(x, w, "full")[reach : reach + len(x)] / np.convolve(np.ones(len(x)), w, "full")[reach : reach + len(x)]


def split_value(x: np.ndarray) -> float:
    """The threshold between two clusters of values (means of both sides, until it stays)."""
    t = float(x.mean())
    for _ in range(50):
        low, high = x[x < t], x[x >= t]
        if not len(low) or not len(high):
            return float(x.min())
        new = (low.mean() + high.mean()) / 2
        if abs(new - t) < 1e-9:
            break
        t = float(new)
    return t


def content_lines(p: Lines) -> np.ndarray:
    """Whether each visible line is in the upper cluster of smoothed text-to-tag ratios."""
    size = np.array([len(t) for t in p.text], float)
    value = smooth(np.log1p(size / np.array(p.tags)))
    return value >= split_value(value)


def kept_lines(p: Lines, content: np.ndarray) -> np.ndarray:
    """Lines of the regions that content lines choose."""
    size = np.array([len(t) for t in p.text], float)
    region, out, head = np.array(p.region), np.array(p.out), np.array(p.head)
    n = len(p.kinds)
    content = content & ~out
    if not content.any():
        content = ~out
    own = np.bincount(region, size * ~out, n)
    solid = np.bincount(region, size * content, n)
    marked = np.array([k in REGIONS for k in p.kinds])
    if solid[marked].sum() >= MARKED_SHARE * solid.sum() > 0:
        # mostly content by itself, else the one that holds most of it
        chosen = marked & (solid >= OWN_SHARE * own) & (solid > 0)
        if not chosen.any():
            chosen[np.argmax(np.where(marked, solid, -1))] = True
        return chosen[region] & ~out
    within = solid.copy()  # with inner containers; an inner one has a larger number
    for r in range(n - 1, 0, -1):
        within[p.parent[r]] += within[r]
    line = np.arange(len(region))
    at = 0
    while True:
        inner = [r for r in range(1, n) if p.parent[r] == at and within[r] >= INNER_SHARE * within[at]]
        if not inner:
            break
        inside = _under(p.parent, inner[0], n)[region]
        if (head & content & ~inside & _under(p.parent, at, n)[region] & (line < np.argmax(inside))).any():
            break  # its heading stands just outside
        at = inner[0]
    links = np.bincount(region, np.array(p.links) * ~out, n)
    # a box of the chosen container goes if it is not mostly content, or is mostly links without content
    box = (solid >= OWN_SHARE * own) & ((links < OWN_SHARE * own) | (solid > links))
    box[at] = box[at] or own[at] > 0 and links[at] < OWN_SHARE * own[at]
    return (_under(p.parent, at, n) & box)[region] & ~out


def _under(parent: list[int], top: int, n: int) -> np.ndarray:
    """Which regions are top or stand in it."""
    yes = np.zeros(n, bool)
    yes[top] = True
    for r in range(top + 1, n):
        yes[r] = yes[parent[r]]
    return yes


def main_text(html: str | None) -> str:
    if not html:
        return ""
    p = Lines()
    try:
        p.feed(html)
        p.finish()
    except AssertionError:  # what the parser raises on some broken declarations; lines so far stand
        p._cut()
    if not p.text:
        return ""
    keep = kept_lines(p, content_lines(p))
    return " ".join(t for t, k in zip(p.text, keep, strict=True) if k)


def extract_pages(pages: DataFrame, html_col: str = "html", keep: tuple[str, ...] = ("page_id", "url")) -> DataFrame:
    """keep columns, text, n_chars (code points) of each row; every page is read whole."""
    spark = pages.sparkSession
    ship(spark)
    arrow_rows(spark)

    def run(bs):
        for b in bs:
            texts = [main_text(h.as_py()) for h in b.column(len(keep))]
            yield pa.RecordBatch.from_arrays([*(b.column(i) for i in range(len(keep))), pa.array(texts, pa.string())], names=[*names, "_text"])

    names = [f"_k{i}" for i in range(len(keep))]
    types = ", ".join(f"{n} {pages.schema[c].dataType.simpleString()}" for n, c in zip(names, keep, strict=True))
    got = pages.select(*(F.col(c).alias(n) for n, c in zip(names, keep, strict=True)), F.col(html_col).alias("_html")).mapInArrow(run, types + ", _text string")
    return got.select(*(F.col(n).alias(c) for n, c in zip(names, keep, strict=True)), F.col("_text").alias("text"), F.length("_text").cast("long").alias("n_chars"))
