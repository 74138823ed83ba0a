"""Main text of web pages: parser events, text-to-tag ratios of lines, Gaussian smoothing, threshold clusters.

The events of the standard library's streaming parser are cut into lines: a line is the text between two
block-level tags, with the tags met since the line before. Scripts, styles and other raw elements give no
line. Lines inside menus, page headers and footers, sidebars, notices, adverts, forms and reader comments are marked
as boilerplate: by element or role, or by a word of class or id. Names are weaker evidence. A name that tells of
a state ("has-sidebar", "comments-open") says nothing; an element that holds an ``article`` or ``main`` with at
least ``share`` of the page's unmarked characters is a wrapper, whatever its name; and where names leave less than
a tenth of the characters of an element that they mark, few of them in links, that element is not marked. Each line's ratio is its characters over
its tags; the ratios of the page, boilerplate at zero, are smoothed by a Gaussian kernel, and lines above a
threshold (half the standard deviation over the smoothed ratios, at most half the greatest) form clusters. A
cluster votes with its characters for the elements that hold it. The article is the least element that holds
all clusters and headings that are not boilerplate. Where an ``article`` or ``main`` element or role holds at
least ``share`` of the votes, only clusters inside such elements, and headings inside the outermost one around
it, count. All its lines that are not boilerplate are the text, short ones included: the ratios choose the
region, and nothing inside it is dropped for being short.

Character references are decoded, white space inside a line becomes one space, lines are joined by ``\\n``.
Null, empty and tag-only pages give an empty text; text without any tag is one line; a tag broken off by the end of
the page is no text. Nothing is capped:
a page of any length is parsed in one pass, with memory in proportion to the page. Pages are independent, so
rows that repeat get equal results and skew cannot arise; other columns are ignored.
"""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Iterator
from html.parser import HTMLParser

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame

from .common import id_as_string, id_back

# Elements of HTML.
RAW = frozenset("script style noscript template svg math iframe object head select option textarea button datalist canvas audio video".split())
#: start tags that a head may hold; any other closes it
HEAD = frozenset("base basefont bgsound head html link meta noframes noscript script style template title".split())
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
BLOCK = frozenset(
    "html body address article aside blockquote center dd details dialog dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr li main menu nav ol p pre search section summary table caption colgroup tbody td tfoot th thead tr ul".split()
)
BOILERPLATE = frozenset("nav aside footer form menu dialog search".split())
ROLES = frozenset("navigation banner contentinfo complementary search form dialog alert alertdialog menu menubar toolbar".split())
#: words of class and id names
NAMES = frozenset(
    "ad ads adv advert adverts advertisement advertising advertorial sponsor sponsored sponsors promo promoted promotion banner billboard nav navbar navigation menu menubar breadcrumb breadcrumbs sidebar aside rail footer masthead topbar toolbar cookie cookies consent gdpr notice notices notification alert popup modal overlay newsletter subscribe subscription signup login share sharing social related recommended recommendations comment comments commentlist disqus reply replies respond responses pagination pager widget widgets outbrain taboola".split()
)
#: a name with one of these tells of a state of the page, not of what the element holds
STATES = frozenset("has with without no not open opened closed enabled disabled allowed".split())
CONTENT = frozenset("article main".split())
#: names of reader comments: never taken for the article by their length
COMMENTS = frozenset("comment comments commentlist disqus reply replies respond responses".split())
_NAME = re.compile(r"[a-z]+|[0-9]+")
_CAMEL = re.compile(r"(?<=[a-z])(?=[A-Z])")
_SPACE = re.compile(r"[\x20\x09-\x0D\x85\xA0  -     　]+")
_TAG_START = re.compile(r"<[A-Za-z/!?]")
#: an end tag that closes elements left open inside it; what may not be crossed by an end of p
_P_CLOSERS = BLOCK - frozenset("li dd dt td th tr tbody thead tfoot caption colgroup summary figcaption html body".split())


class Element:
    __slots__ = ("tag", "parent", "marked", "named", "comments", "boilerplate", "content", "depth", "votes", "size", "linked", "core", "block", "within")

    def __init__(self, tag: str, parent: Element | None, marked: bool = False, named: bool = False, content: bool = False, comments: bool = False):
        self.tag, self.parent, self.marked, self.named, self.content, self.comments = tag, parent, marked, named, content, comments
        self.boilerplate = False  # known when the page is read
        self.depth = parent.depth + 1 if parent else 0
        self.votes = 0.0
        self.size = self.linked = self.core = 0  # characters: of lines without a mark, of links, inside content elements
        self.block = self if tag in BLOCK else parent.block if parent else None  # the innermost block
        self.within = content or parent is not None and parent.within  # inside a content element


class Line:
    __slots__ = ("text", "tags", "element", "linked")

    def __init__(self, text: str, tags: int, element: Element, linked: int = 0):
        self.text, self.tags, self.element, self.linked = text, tags, element, linked


def names_of(attrs: list[tuple[str, str | None]]) -> tuple[set[str], str, bool]:
    """The words of NAMES in class and id, but for names that tell of a state; the role; whether it is hidden."""
    words: set[str] = set()
    role, hidden = "", False
    for key, value in attrs:
        if key in ("class", "id") and value:
            for name in value.split():
                parts = _NAME.findall(_CAMEL.sub(" ", name).lower())
                if STATES.isdisjoint(parts):
                    words.update(NAMES.intersection(parts))
        elif key == "role" and value:
            role = value.strip().lower()
        elif key == "hidden" or key == "aria-hidden" and value == "true" or key == "style" and value and re.search(r"display\s*:\s*none|visibility\s*:\s*hidden", value, re.I):
            hidden = True
    return words, role, hidden


class LineParser(HTMLParser):
    def __init__(self):
        super().__init__(convert_charrefs=True)
        self.root = self.open = Element("", None)
        self.elements: list[Element] = [self.root]  # parents before children
        self.lines: list[Line] = []
        self.parts: list[str] = []
        self.tags = self.linked = self.links = 0
        self.opened: Counter = Counter()  # how many elements of each tag are open
        self.raw = 0  # open raw elements

    def cut(self) -> None:
        if self.parts:
            text = _SPACE.sub(" ", "".join(self.parts)).strip(" ")
            self.parts.clear()
            if text:
                self.lines.append(Line(text, self.tags, self.open, min(self.linked, len(text))))
                self.tags = 0
            self.linked = 0

    def handle_starttag(self, tag: str, attrs: list) -> None:
        self.tags += 1
        if self.open.tag == "head" and tag not in HEAD:  # the end of a head may be left out
            self.leave(self.open)
        if tag in RAW:
            self.cut_if_block(tag)
            self.push(tag, [])
            self.raw += 1
            return
        if self.raw:
            return
        if tag == "br":
            self.parts.append(" ")
            return
        if tag in BLOCK:
            self.cut()
            if tag in _P_CLOSERS:
                self.close_through("p", BLOCK - {"p"})
            elif tag in ("li", "dd", "dt", "tr", "td", "th", "option"):
                same = ("dd", "dt") if tag in ("dd", "dt") else ("td", "th") if tag in ("td", "th") else (tag,)
                for x in same:
                    self.close_through(x, frozenset(("ul", "ol", "dl", "table", "menu", "div", "body", "article", "section") if tag != "tr" else ("table",)) | ({"tr"} if tag in ("td", "th") else frozenset()))
        if tag not in VOID:
            self.push(tag, attrs)

    def cut_if_block(self, tag: str) -> None:
        if tag in ("head", "select", "textarea", "iframe"):
            self.cut()

    def push(self, tag: str, attrs: list) -> None:
        parent = self.open
        words, role, hidden = names_of(attrs) if attrs else ((), "", False)
        content = tag in CONTENT or role in CONTENT
        marked = hidden or tag in BOILERPLATE or role in ROLES or (tag == "header" and not parent.within)
        named = bool(words) and tag not in ("html", "body") and not content
        self.open = Element(tag, parent, marked, named, content, named and not COMMENTS.isdisjoint(words))
        self.elements.append(self.open)
        self.links += tag == "a"
        self.opened[tag] += 1

    def close_through(self, tag: str, stops: frozenset) -> None:
        """Close the nearest open ``tag``, if no element of ``stops`` is open inside it."""
        if not self.opened[tag]:
            return
        e = self.open
        while e is not self.root and e.tag != tag:
            if e.tag in stops:
                return
            e = e.parent
        if e is not self.root:
            self.cut()
            self.leave(e)

    def leave(self, e: Element) -> None:
        """Close the open elements up to ``e``."""
        x = self.open
        while x is not e.parent:
            self.raw -= x.tag in RAW
            self.links -= x.tag == "a"
            self.opened[x.tag] -= 1
            x = x.parent
        self.open = x

    def handle_endtag(self, tag: str) -> None:
        self.tags += 1
        if not self.opened[tag]:
            if tag in BLOCK and not self.raw:
                self.cut()
            return
        e = self.open
        while e.tag != tag:
            if e.tag in RAW and tag not in ("body", "html"):
                return
            e = e.parent
        if tag not in BLOCK and tag not in RAW:  # an inline end does not close a block
            x = self.open
            while x is not e:
                if x.tag in BLOCK:
                    return
                x = x.parent
        if tag in BLOCK:
            self.cut()
        self.leave(e)

    def handle_startendtag(self, tag: str, attrs: list) -> None:
        if tag in VOID or tag in RAW:
            self.tags += 1
            if not self.raw:
                if tag == "br":
                    self.parts.append(" ")
                elif tag in BLOCK:
                    self.cut()
        else:
            self.handle_starttag(tag, attrs)

    def handle_data(self, data: str) -> None:
        if not self.raw:
            self.parts.append(data)
            self.linked += len(data) if self.links > 0 else 0

    def unknown_decl(self, data: str) -> None:
        if data.startswith("CDATA[") and not self.raw:
            self.parts.append(data[6:])


def weigh_names(elements: list[Element], lines: list[Line], share: float, left: float = 0.1, linked: float = 0.3) -> None:
    """Decide for every element whether it is boilerplate; names give way to what the elements hold."""
    for e in elements:
        e.boilerplate = e.marked or e.parent is not None and e.parent.boilerplate
    total = 0
    for x in lines:
        if not x.element.boilerplate:
            total += len(x.text)
            x.element.size += len(x.text)
            x.element.linked += x.linked
    for e in reversed(elements[1:]):
        e.parent.size += e.size
        e.parent.linked += e.linked
        e.parent.core += e.size if e.content else e.core
    for e in elements:
        if e.named and e.core >= share * total > 0:
            e.named = False

    def spread() -> int:
        """Marks and names pass on to all inside; what is left has so many characters."""
        for e in elements:
            e.boilerplate = e.marked or e.named or e.parent is not None and e.parent.boilerplate
        return sum(len(x.text) for x in lines if not x.element.boilerplate)

    while True:
        rest = spread()
        starved = [e for e in elements if e.named and not e.comments and rest < left * e.size and e.linked < linked * e.size]
        if not starved:
            return
        most = max(e.size for e in starved)
        for e in starved:
            e.named = 2 * e.size < most


def smoothed(ratios: np.ndarray, sigma: float) -> np.ndarray:
    radius = int(np.ceil(2 * sigma)) + 1
    x = np.arange(-radius, radius + 1)
    kernel = np.exp(-(x**2) / (2 * sigma**2))
    padded = np.pad(ratios, radius, mode="edge")
    return np.convolve(padded, kernel / kernel.sum(), mode="valid")


def content_lines(lines: list[Line], sigma: float = 1.0) -> np.ndarray:
    """Which lines are content by their smoothed ratios alone."""
    ratios = np.array([0.0 if x.element.boilerplate else len(x.text) / max(1, x.tags) for x in lines])
    even = smoothed(ratios, sigma)
    clear = np.array([not x.element.boilerplate for x in lines])
    threshold = min(0.5 * float(even.std()), 0.5 * float(even.max()))
    return clear & (even >= threshold) & (even > 0)


def complete(html: str) -> str:
    """``html`` without a tag or comment that its end breaks off. (The parser would look for each one's end again and again.)"""
    last = html.rfind(">") + 1
    broken = _TAG_START.search(html, last)
    return html if broken is None else html[: broken.start()]


def main_text(html: str | None, share: float = 0.5) -> str:
    if not html:
        return ""
    parser = LineParser()
    parser.feed(complete(html))
    parser.close()
    parser.cut()
    lines = parser.lines
    weigh_names(parser.elements, lines, share)
    if not any(not x.element.boilerplate for x in lines):
        return ""
    elements, chosen = parser.elements, content_lines(lines)
    for x, yes in zip(lines, chosen, strict=True):
        x.element.votes += len(x.text) * bool(yes)
    for e in reversed(elements[1:]):
        e.parent.votes += e.votes
    total = elements[0].votes
    core = max((e for e in elements if e.content and e.votes and e.votes >= share * total), key=lambda e: e.depth, default=None)
    outer = core
    for e in above(core):
        if e.content and not e.boilerplate:
            outer = e
    inside = marked_inside(elements, outer)
    marks = dict.fromkeys(elements, 0)
    for x, yes in zip(lines, chosen, strict=True):
        e = x.element
        if not e.boilerplate and (yes or heading(e) if core is None else yes and e.within or heading(e) and inside[e]):
            marks[e] += 1
    if core is not None:
        marks[core] += 1
    for e in reversed(elements[1:]):
        marks[e.parent] += marks[e]
    if not marks[elements[0]]:
        return ""
    region = max((e for e in elements if marks[e] == marks[elements[0]]), key=lambda e: e.depth)
    # no single paragraph: what holds a lone long block is its parent
    while region is not core and region.parent is not None and (leaf(region) or region.tag not in BLOCK):
        region = region.parent
    inside = marked_inside(elements, region)
    return "\n".join(x.text for x in lines if not x.element.boilerplate and inside[x.element])


def marked_inside(elements: list[Element], outer: Element | None) -> dict[Element, bool]:
    """For each element whether it is ``outer`` or inside it."""
    out: dict[Element, bool] = {}
    for e in elements:
        out[e] = e is outer or e.parent is not None and out[e.parent]
    return out


def above(e: Element | None) -> Iterator[Element]:
    """An element and all that hold it."""
    while e is not None:
        yield e
        e = e.parent


def heading(e: Element) -> bool:
    """Whether the innermost block is a heading."""
    return e.block is not None and e.block.tag in ("h1", "h2", "h3", "h4", "h5", "h6")


def leaf(e: Element) -> bool:
    return e.tag in ("p", "h1", "h2", "h3", "h4", "h5", "h6", "li", "td", "th", "tr", "tbody", "table", "ul", "ol", "dl", "dd", "dt", "pre", "blockquote", "figure", "figcaption", "caption")


def extract_pages(pages: DataFrame) -> DataFrame:
    """page_id, url, text, n_chars: a row per row of ``pages(page_id, url, html)``."""

    def extract(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            texts = [main_text(x) for x in frame["html"]]
            yield pd.DataFrame({"page_id": frame["page_id"], "url": frame["url"], "text": texts, "n_chars": [len(x) for x in texts]})

    found = pages.select(id_as_string(pages, "page_id"), "url", "html").mapInPandas(extract, "page_id string, url string, text string, n_chars long")
    return found.withColumn("page_id", id_back(pages, "page_id"))
