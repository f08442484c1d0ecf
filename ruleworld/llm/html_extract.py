"""Main text of web pages from streamed parser events and text-to-tag ratios.

The standard library's parser streams events. Text between block-level boundaries is one line; a line has a ratio of
text (link text left out) to the tags seen since the line before. What elements, roles, and words of class and id say
only lowers or raises ratios: a line's ratio is multiplied by the factors of the blocks that hold it. The ratios are smoothed over
neighbouring lines with a Gaussian kernel, and a two-means threshold over the smoothed ratios separates content lines
from the rest. The content region is the smallest block that holds most of what the content lines weigh (their
ratios), or the outermost article or main element around it, with its like under the same parent. Factors of blocks that hold the whole region say nothing
about its parts and are taken back. From the region come its content lines, and all other lines that no factor lowers, so that short
paragraphs stay; where the region is the whole body, only headings before and lines between content lines.

Rules of nesting are those that matter here: a block start ends an open paragraph, an item start an open item, an end tag
closes what is open inside it, an end tag without start is ignored, an inline end tag closes no block, an open head ends
where something else than its content starts, missing end tags are closed at the end. Blocks and the inline elements
open in each are counted by name, so broken markup takes time in proportion to its length.

Edge cases: null or empty html gives the empty text; broken markup gives what can be read; pages without text outside
furniture give the empty text; equal rows give equal results; extra columns are ignored.
"""

from __future__ import annotations

from collections import Counter
from html.parser import HTMLParser
from typing import NamedTuple

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

BLOCKS = frozenset(
    "address article aside blockquote body caption center dd details dialog dir div dl dt fieldset figcaption figure footer form "
    "frameset h1 h2 h3 h4 h5 h6 head header hgroup hr html legend li main menu nav ol optgroup option p pre search section summary "
    "table tbody td tfoot th thead tr ul".split()
)
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
#: Elements whose text is never shown as text of the page.
SILENT = frozenset("audio button canvas datalist embed head iframe math noembed noframes noscript object script select style svg template textarea title video".split())
FURNITURE = frozenset("aside dialog footer form menu nav search".split())
ROLES = frozenset("alert alertdialog banner complementary contentinfo dialog form menu menubar navigation search toolbar".split())
#: Words of class and id that tell of furniture.
MARKS = frozenset(
    "ad ads adbox adslot advert adverts advertisement advertisements advertising adsense sponsor sponsored sponsors promo promos promotion promoted banner "
    "banners cookie cookies consent gdpr notice notices notification notifications alert alerts announcement disclaimer sidebar sidebars rail widget widgets "
    "menu menus navigation nav navbar navlinks breadcrumb breadcrumbs pagination pager footer footers masthead topbar header headers comment comments "
    "commentlist disqus reply replies respond discussion share sharing social follow related recommended recommendations trending popular "
    "newsletter subscribe subscription signup login signin register modal popup overlay paywall toolbar skip tags".split()
)
ARTICLES = frozenset(("article", "main"))
HEAD_CONTENT = frozenset("base basefont bgsound head html link meta noframes noscript script style template title".split())
HEADINGS = frozenset(("h1", "h2", "h3", "h4", "h5", "h6"))
#: A start of the first ends an open one of the second.
CLOSES = {"li": {"li"}, "dt": {"dt", "dd"}, "dd": {"dt", "dd"}, "tr": {"tr", "td", "th"}, "td": {"td", "th"}, "th": {"td", "th"}, "option": {"option"}}
#: Blocks of a sentence or a list item are no regions.
PARAGRAPHS = HEADINGS | frozenset("address caption dd dt figcaption hr legend li option p pre summary tr td th".split())
CLOSED = FURNITURE - {"form"}  # no region lies in these; whole pages may lie in a form
#: What furniture elements, page headers, and telling words multiply a ratio by; and what articles do.
ELEMENT, HEADER, WORD, ARTICLE = 0.02, 0.05, 0.1, 2.0


def block_factor(tag: str, attrs: list[tuple[str, str | None]], inside: bool) -> float:
    """What a block multiplies its lines' ratios by; 0 where it is hidden. ``inside``: it stands in an article, whose header holds the title."""
    words: set[str] = set()
    factor = ELEMENT if tag in FURNITURE else HEADER if tag == "header" and not inside else 1.0
    for k, v in attrs:
        if k in ("class", "id"):
            for name in (v or "").lower().replace("_", "-").split():
                if not name.startswith(("has-", "with-", "no-", "without-")):  # these tell of another element
                    words.update(name.split("-"))
        elif k == "role" and (v or "").lower() in ROLES:
            factor = min(factor, ELEMENT)
        elif k == "hidden" or k == "aria-hidden" and v == "true" or k == "style" and "display:none" in (v or "").replace(" ", "").lower():
            return 0.0
    if tag not in ("html", "body") and words & MARKS - ({"header", "headers"} if inside else set()):
        factor = min(factor, WORD)
    return factor


class Line(NamedTuple):
    text: str
    tags: int
    linked: int  # characters of link text
    block: int
    heading: bool


class Page(HTMLParser):
    """Lines of a page and the blocks that hold them; a block's number is above that of the block that holds it."""

    def __init__(self):
        super().__init__(convert_charrefs=True)
        self.lines: list[Line] = []
        self.tag, self.parent, self.factor, self.article = ["html"], [0], [1.0], [False]
        self.text: list[str] = []
        self.tags = self.linked = self.silent = self.links = 0
        self.open: list[tuple[int, list[tuple[str, bool]], Counter]] = [(0, [], Counter())]  # block, its open inline elements
        self.count: Counter = Counter()  # open blocks by tag

    def flush(self) -> None:
        line = " ".join("".join(self.text).split()) if self.text else ""
        if line:
            k = self.open[-1][0]
            self.lines.append(Line(line, self.tags, self.linked, k, self.tag[k] in HEADINGS))
            self.tags = 0
        self.text, self.linked = [], 0

    def _drop(self) -> None:
        """Close the last open inline element of the last open block."""
        _, inline, names = self.open[-1]
        tag, silent = inline.pop()
        names[tag] -= 1
        self.silent -= silent
        self.links -= tag == "a"

    def _close(self) -> None:
        """Close the last open block."""
        while self.open[-1][1]:
            self._drop()
        k, _, _ = self.open.pop()
        self.count[self.tag[k]] -= 1
        self.silent -= self.tag[k] in SILENT

    def _top(self) -> str:
        return self.tag[self.open[-1][0]]

    def _leave_head(self) -> None:
        while self.count["head"]:
            self._close()

    def handle_starttag(self, tag, attrs):
        self.tags += 1
        if self.count["head"] and (tag == "body" or self._top() == "head" and tag not in HEAD_CONTENT):
            self._leave_head()
        if tag == "br":
            self.text.append(" ")
        if tag not in BLOCKS:
            if tag not in VOID:
                silent = tag in SILENT or any(k == "hidden" for k, _ in attrs)
                self.open[-1][1].append((tag, silent))
                self.open[-1][2][tag] += 1
                self.silent += silent
                self.links += tag == "a"
            return
        self.flush()
        if tag in VOID:
            return
        while len(self.open) > 1 and (self._top() == "p" or self._top() in CLOSES.get(tag, ())):
            self._close()
        up = self.open[-1][0]
        article = self.article[up] or tag in ARTICLES or any(k == "role" and v == "main" for k, v in attrs)
        self.open.append((len(self.tag), [], Counter()))
        self.factor.append(block_factor(tag, attrs, self.article[up]))
        self.tag.append(tag)
        self.parent.append(up)
        self.article.append(article)
        self.count[tag] += 1
        self.silent += tag in SILENT

    def handle_startendtag(self, tag, attrs):
        self.handle_starttag(tag, attrs)
        if tag not in VOID:
            self.handle_endtag(tag)

    def handle_endtag(self, tag):
        self.tags += 1
        if tag in BLOCKS:
            self.flush()
            if self.count[tag]:
                while self._top() != tag:
                    self._close()
                self._close()
        elif self.open[-1][2][tag]:
            while self.open[-1][1][-1][0] != tag:
                self._drop()
            self._drop()

    def handle_data(self, data):
        if self.count["head"] and self._top() == "head" and not self.open[-1][1] and data.strip():
            self._leave_head()
        if not self.silent:
            self.text.append(data)
            if self.links:
                self.linked += len(data)


def read_page(html: str) -> Page:
    page = Page()
    page.feed(html)
    page.close()
    page.flush()
    return page


def line_ratios(page: Page) -> np.ndarray:
    """Characters outside links to tags, by line."""
    return np.array([(len(x.text) - min(x.linked, len(x.text)) + 1) / max(1, x.tags) for x in page.lines])


def block_products(page: Page, spared: frozenset | set = frozenset()) -> np.ndarray:
    """By block, the product of the factors of all that hold it and its own, without those of the ``spared`` blocks."""
    out = np.ones(len(page.tag))
    for k in range(1, len(out)):
        out[k] = out[page.parent[k]] * (1.0 if k in spared else page.factor[k])
    return out


def smoothed(ratio: np.ndarray, radius: int = 2, sigma: float = 1.0) -> np.ndarray:
    """Ratios under a Gaussian kernel; the kernel is cut, and made whole again, at the page's ends."""
    kernel = np.exp(-(np.arange(-radius, radius + 1) ** 2) / (2 * sigma**2))
    return np.convolve(ratio, kernel)[radius : radius + len(ratio)] / np.convolve(np.ones(len(ratio)), kernel)[radius : radius + len(ratio)]


def threshold(values: np.ndarray, rounds: int = 20) -> float:
    """Border between two means of the values; below all of them where they are equal."""
    low, high = float(values.min()), float(values.max())
    if low == high:
        return low - 1
    for _ in range(rounds):
        cut = (low + high) / 2
        new = float(values[values <= cut].mean()), float(values[values > cut].mean())
        if new == (low, high):
            break
        low, high = new
    return (low + high) / 2


def region(page: Page, weight: np.ndarray, content: np.ndarray, most: float = 0.7) -> tuple[int, int]:
    """The smallest block with ``most`` of the content lines' weight and more than one of them, where one in an article will do,
    and the outermost article around that block."""
    held, lines = np.zeros(len(page.tag)), np.zeros(len(page.tag), int)
    for x, w, c in zip(page.lines, weight, content, strict=True):
        if c:
            held[x.block] += w
            lines[x.block] += 1 + page.article[x.block]
    best: dict[int, int] = {}
    for k in range(len(held) - 1, 0, -1):
        up = page.parent[k]
        held[up] += held[k]
        lines[up] += lines[k]
        if page.tag[k] not in PARAGRAPHS and page.tag[k] not in CLOSED and held[k] >= held[best.get(up, k)]:
            best[up] = k
    core = 0
    while core in best and held[best[core]] >= most * held[core] and lines[best[core]] > 1:
        core = best[core]
    outer = at = core
    while at := page.parent[at]:
        if page.article[at]:
            outer = at
    return core, outer


def main_text(html: str | None) -> str:
    page = read_page(html) if html else None
    if page is None or not page.lines:
        return ""
    block, ratio = np.array([x.block for x in page.lines]), line_ratios(page)
    product = block_products(page)[block]
    raised = ratio * product * np.where(page.article, ARTICLE, 1.0)[block]
    value = smoothed(raised)
    content = value > threshold(value)
    core, outer = region(page, raised, content)
    path, at = {core}, core
    while at:
        at = page.parent[at]
        path.add(at)
    if not core and product.max() < 1:
        return ""
    inside, central = np.zeros(len(page.tag), bool), np.zeros(len(page.tag), bool)
    for k, up in enumerate(page.parent):
        like = k == outer or page.article[outer] and up == page.parent[outer] and page.tag[k] == page.tag[outer]
        inside[k], central[k] = like or k > 0 and inside[up], like or k == core or k > 0 and central[up]
    # within the region, what lowers all of it says nothing
    here = np.flatnonzero(inside[block])
    lower = block_products(page, path)[block[here]]
    own = ratio[here] * lower
    again = smoothed(own)
    cut = threshold(again)
    told = content[here] & (lower == 1)
    taken = np.where(lower == 1, True, (own > cut) & (again > cut) & (lower > 0))
    listed = np.array([2 * page.lines[k].linked > len(page.lines[k].text) for k in here])
    if page.tag[outer] in ("html", "body"):
        span = np.flatnonzero(told)
        if len(span):
            first = span[0]
            while first and lower[first - 1] == 1 and page.lines[here[first - 1]].heading:
                first -= 1
            taken[:first] = taken[span[-1] + 1 :] = False
        taken &= told | ~listed | (lower < 1)
    else:
        taken &= central[block[here]] | ~listed
    return "\n\n".join(page.lines[k].text for k, t in zip(here.tolist(), taken.tolist(), strict=True) if t)


def _extracting(batches):
    for b in batches:
        texts = [main_text(h) for h in b.column(2).to_pylist()]
        yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], names=["page_id", "url", "text", "n_chars"])


def extract(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", html_col: str = "html") -> DataFrame:
    """``page_id, url, text, n_chars`` of every page; one scan, no shuffle."""
    chosen = pages.select(F.col(id_col).cast("long").alias("page_id"), F.col(url_col).alias("url"), F.col(html_col).alias("html"))
    return chosen.mapInArrow(_extracting, "page_id bigint, url string, text string, n_chars bigint")
