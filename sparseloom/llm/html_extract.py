"""Main text of web pages from parser events, text-to-tag ratios and clustering.

The standard library's streaming parser turns a page into blocks of text (one per block-level
element or break) and remembers the elements around each. Preparation takes out what can't be content by
its role: scripts, styles, hidden parts, menus, footers, sidebars and dialogs by element name, and parts that a form, an
ARIA role, or a word of class or id makes suspect (adverts, notices, reader comments, related matter and so on).
A suspicion is only a prior: an element that holds the page's marked main part, or nearly all of its text, is not taken out.

What is content is then decided by the text-to-tag ratio: of each remaining block, a "line" of the page, the ratio of text outside
links to tags is taken, smoothed by a Gaussian along the page, and cut by a threshold between two clusters. The text in the
high cluster is the mass that regions are chosen by. From the page's root the choice descends into the element that holds
most of the mass, as long as one does; where it ends is the content region. Marks (`main`, `article`, and the ARIA role or schema
property for them) are one more input: the descent ends at a marked article, and goes on from another
element to the marked parts below it only if these hold most of its mass. All blocks of a region of its own are content, so that
an article's short headings and closing lines stay; where no element stands out, blocks are kept one by one, by the
ratio alone.

Defined results: null and empty pages, and pages without text, give an empty text; broken markup is read as
the parser reads it (unclosed and stray tags end at the next block or at their container's end);
repeated rows each give a row; a null page_id stays null; other columns are ignored.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass, field
from html.parser import HTMLParser

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import map_batches

# Element names of HTML.
_VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
_RAW = frozenset("script style noscript template iframe object svg math canvas audio video textarea select option datalist title".split())
_ROLE_ELEMENTS = frozenset("nav aside footer button dialog menu".split())
_BLOCK = frozenset(
    "address article aside blockquote body br caption center dd details dialog dir div dl dt fieldset figcaption figure "
    "footer form h1 h2 h3 h4 h5 h6 head header hgroup hr html legend li main menu nav ol optgroup option p pre search section "
    "summary table tbody td tfoot th thead title tr ul".split()
)
_PARAGRAPH_ENDERS = _BLOCK - {"br", "td", "th", "tr", "li", "dd", "dt", "body", "html", "head"}
_ROLES = frozenset("navigation banner contentinfo complementary search form menu menubar dialog alertdialog alert toolbar tablist status".split())
#: Words of class and id that name parts beside the content. Compared with whole words of the names.
_ASIDE_WORDS = frozenset(
    "ad ads adv advert adverts advertisement advertising sponsor sponsored promo promotion banner cookie cookies consent gdpr "
    "notice notices popup modal overlay newsletter subscribe subscription signup login paywall nav navbar navigation menu menus "
    "breadcrumb breadcrumbs sidebar sidebars aside widget widgets footer masthead toolbar share sharing social related "
    "recommended recommendations trending comment comments disqus respond replies pagination pager skip hidden copyright "
    "disclaimer toc tags taglist".split()
)
_WORD = re.compile(r"[A-Z]?[a-z]+|[A-Z]+(?![a-z])|\d+")
_MAIN_NAMES = frozenset(["main", "article"])
#: In the class of an `article` element: words of the article itself, and words of other matter.
_MAIN_WORDS = frozenset("article post entry hentry story main".split())
_READER_WORDS = frozenset("ad ads advert promo sponsored comment comments reply replies related recommended widget sidebar".split())
#: Words that name a part's matter. Others, such as sidebar or menu, may also tell how the element around everything is laid out.
_MATTER_WORDS = frozenset(
    "ad ads adv advert adverts advertisement advertising sponsor sponsored promo promotion cookie cookies consent gdpr notice notices popup "
    "newsletter subscribe subscription signup login paywall comment comments disqus respond replies related recommended recommendations copyright disclaimer".split()
)
_TEXT_ELEMENTS = frozenset("p h1 h2 h3 h4 h5 h6 li dd dt pre blockquote td th figcaption caption summary legend address".split())
#: Shares of text or mass from which an element counts as the one that holds it.
NEARLY_ALL, MOST = 0.9, 0.75
_SPACE = re.compile(r"\s+")


def _words(value: str | None) -> set[str]:
    return {w.lower() for w in _WORD.findall(value or "")}


@dataclass
class Element:
    """An element around blocks. `suspect`: a prior that it is beside the content; `matter`: by what it is about."""

    tag: str
    above: int
    out: bool = False  # never shown: it, or an element around it
    suspect: bool = False
    matter: bool = False
    marked: str = ""  # "main" or "article"
    chars: int = 0
    blocks: int = 0
    mass: float = 0.0


@dataclass
class Block:
    """A line of the page: its text, characters of it inside links, the tags it was made with, and the element it is in."""

    text: str
    tags: int
    links: int
    element: int
    pieces: list[tuple[int, str, bool]] = field(default_factory=list)  # element, text, whether inside a link


class _Events(HTMLParser):
    """Parser events to elements and blocks. Text that is never shown is passed over as it streams by."""

    def __init__(self) -> None:
        super().__init__(convert_charrefs=True)
        self.elements = [Element("", 0)]
        self.blocks: list[Block] = []
        self.open: list[int] = []
        self.pieces: list[tuple[int, str, bool]] = []
        self.tags = self.linked = 0

    def _end_block(self) -> None:
        if self.pieces:
            self.blocks.append(Block("", self.tags, 0, self.open[-1] if self.open else 0, self.pieces))
            self.pieces = []
        self.tags = 0

    def handle_starttag(self, tag: str, attrs: list[tuple[str, str | None]]) -> None:
        if tag in _BLOCK:
            if tag in _PARAGRAPH_ENDERS:
                self._close_open("p", within=_BLOCK - {"p"})
            elif tag in ("li", "dd", "dt", "tr", "td", "th"):
                self._close_open(tag, within=frozenset(["ul", "ol", "dl", "table", "menu"]))
            self._end_block()
        self.tags += 1
        if tag in _VOID:
            return
        above = self.open[-1] if self.open else 0
        self.elements.append(self._element(tag, dict(attrs), above))
        self.open.append(len(self.elements) - 1)
        self.linked += tag == "a"

    def _element(self, tag: str, of: dict[str, str | None], above: int) -> Element:
        role = (of.get("role") or "").lower()
        hidden = "hidden" in of or (of.get("aria-hidden") or "").lower() == "true" or "display:none" in (of.get("style") or "").replace(" ", "").lower()
        found = Element(tag, above, self.elements[above].out or hidden or tag in _RAW or tag in _ROLE_ELEMENTS)
        if found.out or tag in ("html", "body"):
            return found
        names = _words(of.get("class")) | _words(of.get("id"))
        marked = tag in _MAIN_NAMES or role in _MAIN_NAMES or "articleBody" in (of.get("itemprop") or "")
        if names & _ASIDE_WORDS and not (marked and (names & _MAIN_WORDS or not names & _READER_WORDS)):
            found.suspect, found.matter = True, bool(names & _MATTER_WORDS)
        elif marked:
            found.marked = "main" if "main" in (tag, role) else "article"
        found.suspect |= tag == "form" or role in _ROLES or tag == "header" and not self._inside_marked(above)
        return found

    def _inside_marked(self, at: int) -> bool:
        while at:
            if self.elements[at].marked:
                return True
            at = self.elements[at].above
        return False

    def handle_endtag(self, tag: str) -> None:
        self.tags += 1
        if tag in _BLOCK:
            self._end_block()
        if tag not in _VOID:
            self._close_open(tag, within=frozenset())

    def _close_open(self, name: str, within: frozenset[str]) -> None:
        """Close the nearest open `name` and what is open inside it; an element of `within` shields it."""
        for k in range(len(self.open) - 1, -1, -1):
            tag = self.elements[self.open[k]].tag
            if tag == name:
                if name in _BLOCK:
                    self._end_block()
                self.linked -= sum(self.elements[e].tag == "a" for e in self.open[k:])
                del self.open[k:]
                return
            if tag in within:
                return

    def handle_data(self, data: str) -> None:
        at = self.open[-1] if self.open else 0
        if not self.elements[at].out:
            self.pieces.append((at, data, self.linked > 0))

    def finish(self) -> tuple[list[Element], list[Block]]:
        self.close()
        self._end_block()
        return self.elements, self.blocks


def _around(elements: list[Element], at: int) -> Iterator[int]:
    """The element and all around it, up to the root."""
    while at:
        yield at
        at = elements[at].above
    yield 0


def set_aside(elements: list[Element], blocks: list[Block]) -> list[Block]:
    """Blocks without what suspect elements hold, except those that hold the marked main part or nearly everything."""
    marked_chars = [0] * len(elements)  # text inside a marked part below, or at, the element
    for b in blocks:
        for at, text, _ in b.pieces:
            n, inside = len(text.strip()), False
            for e in _around(elements, at):
                elements[e].chars += n
                marked_chars[e] += n * inside
                inside |= bool(elements[e].marked)
        for e in _around(elements, b.element):
            elements[e].blocks += 1
    everything = elements[0].chars
    gone = [False] * len(elements)
    for k, e in enumerate(elements):
        if e.suspect:
            holds_main = marked_chars[k] and marked_chars[k] * 2 >= e.chars and marked_chars[k] * 2 >= marked_chars[0] and not e.matter
            lays_out = e.blocks > 1 and e.chars >= NEARLY_ALL * everything and not e.matter and marked_chars[k] == marked_chars[0]
            gone[k] = not (holds_main or lays_out)
        gone[k] |= bool(k) and gone[e.above]
    out = []
    for b in blocks:
        kept = [(t, inside) for at, t, inside in b.pieces if not gone[at]]
        text = _SPACE.sub(" ", "".join(t for t, _ in kept)).strip()
        if text:
            out.append(Block(text, b.tags, sum(len(t) for t, inside in kept if inside), b.element))
    return out


def text_to_tag(blocks: list[Block]) -> np.ndarray:
    """Characters outside links per tag, for each line of the page."""
    return np.array([max(0, len(b.text) - b.links) / max(1, b.tags) for b in blocks], float)


def smooth(values: np.ndarray, sigma: float = 1.0) -> np.ndarray:
    """Gaussian smoothing along the page; the edges keep their weight."""
    if len(values) < 2:
        return values
    reach = max(1, int(3 * sigma))
    kernel = np.exp(-0.5 * (np.arange(-reach, reach + 1) / sigma) ** 2)
    weight = np.convolve(np.ones(len(values)), kernel)[reach : reach + len(values)]
    return np.convolve(values, kernel)[reach : reach + len(values)] / weight


def two_clusters(values: np.ndarray) -> float:
    """Threshold midway between the means of a low and a high cluster."""
    low, high = float(values.min()), float(values.max())
    for _ in range(50):
        cut = (low + high) / 2
        above = values > cut
        if above.all() or not above.any():
            return cut
        new = float(values[~above].mean()), float(values[above].mean())
        if new == (low, high):
            break
        low, high = new
    return (low + high) / 2


def content_region(elements: list[Element], blocks: list[Block], high: np.ndarray) -> list[int]:
    """Elements whose blocks are the content, by the mass of the high cluster; the root alone if none stands out."""
    below: list[list[int]] = [[] for _ in elements]
    for e in elements:
        e.mass = e.blocks = 0
    for b, counts in zip(blocks, high):
        for e in _around(elements, b.element):
            elements[e].mass += len(b.text) * bool(counts)
            elements[e].blocks += 1
    for k, e in enumerate(elements[1:], 1):
        if e.mass:
            below[e.above].append(k)
    at = 0
    while elements[at].marked != "article":
        best = max(below[at], key=lambda k: elements[k].mass, default=0)
        if not best or elements[best].mass < MOST * elements[at].mass:
            break
        if elements[best].tag in _TEXT_ELEMENTS or elements[best].blocks < 2 and not elements[best].marked:
            break
        if elements[at].marked and not elements[best].marked:
            break  # the rest of a marked part belongs to it
        at = best
    if elements[at].marked:
        return [at]
    marked = [k for k, e in enumerate(elements) if e.marked and e.mass and at in _around(elements, k) and not any(elements[x].marked for x in _around(elements, e.above))]
    if marked and sum(elements[k].mass for k in marked) >= elements[at].mass / 2:
        most = max(elements[k].mass for k in marked)
        return [k for k in marked if elements[k].mass * 4 >= most]
    return [at]


def main_text(html: str, sigma: float = 1.0) -> str:
    """The page's main text: content blocks in order, joined by one space."""
    events = _Events()
    events.feed(html)
    elements, blocks = events.finish()
    blocks = set_aside(elements, blocks)
    if not blocks:
        return ""
    ratio = smooth(text_to_tag(blocks), sigma)
    # half of the clusters' midpoint keeps short paragraphs within a content region
    high = ratio > two_clusters(ratio) / 2 if float(ratio.max() - ratio.min()) > 1e-9 else np.ones(len(blocks), bool)
    region = content_region(elements, blocks, high)
    if region == [0] or elements[region[0]].tag in ("html", "body"):
        return " ".join(b.text for b, counts in zip(blocks, high) if counts)
    inside = set(region)
    mostly_links = lambda b: b.links * 2 > len(b.text) and not any(elements[k].marked for k in region)
    return " ".join(b.text for b in blocks if not inside.isdisjoint(_around(elements, b.element)) and not mostly_links(b))


def extract_pages(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", html_col: str = "html") -> DataFrame:
    """page_id, url, text, n_chars (code points) for every row."""
    rows = pages.select(
        F.col(id_col).cast("long").alias("page_id"), F.col(url_col).cast("string").alias("url"),
        F.coalesce(F.col(html_col).cast("string"), F.lit("")).alias("html"),
    )

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = [main_text(x) for x in batch.column(2).to_pylist()]
            counts = pa.array([len(x) for x in found], pa.int64())
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(found, pa.string()), counts], ["page_id", "url", "text", "n_chars"])

    return map_batches(rows, work, "page_id long, url string, text string, n_chars long")
