"""Main text of web pages by line-block distribution.

Markup is stripped to one line for each block element; elements that hold no article text (menus, headers, footers, asides, forms, code,
adverts, notices, comments of readers) leave an empty line.  The text lengths of ``WINDOW`` consecutive lines are summed at every line; text
of links counts for nothing, as menus are made of it.  A surge is a line where this sum passes ``SURGE``, or half of the page's largest sum if
that is less, after a quiet stretch; the dive that ends it is the next line from which the sum is zero.  The text of all stretches between
surge and dive is the result.

Where most of that text lies inside article and main elements, these bound the lines: surge and dive run once more with all lines outside
taken as empty, and since every line inside is the article's, any text is a surge and links count.

Broken markup hides no more than it must.  An element ends with the element around it.  A hidden one that is never closed ends at the next
block if its class alone, or its being embedded, hides it; menus, footers and asides that are never closed end at an article.
"""

from __future__ import annotations

import html
import re

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from thriftline.llm.arrowrun import annotate, columns_of

WINDOW, SURGE = 3, 80

# Element names and words that mark page furniture.
BLOCKS = frozenset("address article aside blockquote body center dd details dialog dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr html legend li main menu nav ol p pre search section summary table tbody td tfoot th thead tr ul".split())
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style textarea title xmp".split())
EMBEDDED = frozenset("noscript template iframe svg math object canvas audio video select".split())
FURNITURE = frozenset("nav header footer aside form menu dialog button fieldset search head label".split())
REGIONS = frozenset("nav header footer aside menu".split())
WORDS = frozenset("ad ads advert adverts advertisement advertising sponsor sponsored promo promotion banner nav navbar navigation menu breadcrumb breadcrumbs header masthead footer sidebar aside comment comments respond replies disqus cookie cookies consent gdpr notice notices alert popup modal newsletter subscribe subscription signup login share sharing social related recommended widget toolbar pagination pager copyright disclaimer skip".split())
COMMENTS = frozenset("comment comments respond replies disqus".split())
#: Words that mark furniture around an article, but parts of it inside.
INNER = frozenset("header label".split())
ROLES = frozenset("navigation banner contentinfo complementary search form dialog alertdialog alert menu menubar toolbar".split())
PLAIN = frozenset("html body main".split())
HOMES = frozenset("article main".split())

_TAG = re.compile(r"""<!--.*?(?:-->|\Z)|<[!?][^>]*(?:>|\Z)|<(/?)([a-zA-Z][^\s/>]*)((?:[^<>"']|"[^"]*"|'[^']*')*)>|<(/?)([a-zA-Z][^\s/>]*)([^>]*)(?:>|\Z)""", re.S)
_RAW_END = {tag: re.compile(rf"</{tag}\b[^>]*(?:>|\Z)", re.I) for tag in RAW}
_ATTRIBUTE = re.compile(r"""([a-zA-Z-]+)\s*(?:=\s*("[^"]*"|'[^']*'|[^\s"'>]+))?""")
_HIDDEN = re.compile(r"display\s*:\s*none|visibility\s*:\s*hidden", re.I)
_SPLIT = re.compile(r"[\s_\-]+")
_TEXT, _OPEN, _CLOSE = range(3)


def _furniture(tag: str, attributes: str, inside: bool) -> str:
    """Why an element is furniture: 'comments', 'tag' or 'words'; '' if it is not."""
    if tag in FURNITURE and not (inside and tag in INNER):
        return "tag"
    if not attributes or tag in PLAIN:
        return ""
    for name, value in _ATTRIBUTE.findall(attributes):
        name, value = name.lower(), value.strip("\"'").lower()
        if name in ("class", "id"):
            words = set(_SPLIT.split(value))
            if not COMMENTS.isdisjoint(words):
                return "comments"
            if tag != "article" and not WORDS.isdisjoint(words - INNER if inside else words):
                return "words"
        elif tag != "article" and name == "role" and value in ROLES or name == "hidden" or name == "aria-hidden" and value == "true" or name == "style" and _HIDDEN.search(value):
            return "words"
    return ""


def _events(page: str) -> list[tuple[int, str, str]]:
    """Text, opened and closed elements of a page in order: (kind, text or name, attributes)."""
    out, at = [], 0
    while at < len(page):
        found = _TAG.search(page, at)
        if not found:
            out.append((_TEXT, page[at:], ""))
            break
        if found.start() > at:
            out.append((_TEXT, page[at : found.start()], ""))
        at = found.end()
        tag = (found[2] or found[5] or "").lower()
        if not tag:
            continue
        attributes = found[3] or found[6] or ""
        if found[1] or found[4]:
            out.append((_CLOSE, tag, ""))
        elif tag in RAW:
            end = _RAW_END[tag].search(page, at)
            at = end.end() if end else len(page)
        elif tag in EMBEDDED and attributes.endswith("/"):
            continue
        else:
            out.append((_OPEN, tag, attributes))
    return out


def _opened(stack: list, tag: str) -> int:
    """Where a new block ends an open paragraph: its place in the stack of (name, ...), or the length of the stack."""
    for at in range(len(stack) - 1, -1, -1):
        if stack[at][0] == "p":
            return at
        if stack[at][0] in BLOCKS:
            break
    return len(stack)


def _matched(events: list) -> tuple[set[int], set[int]]:
    """The opened elements, by number, that are closed by their own tag; and those around a main element or the first article."""
    stack: list[tuple[str, int]] = []
    closed, around, article = set(), set(), False
    for n, (kind, tag, _) in enumerate(events):
        if kind == _CLOSE:
            if any(t == tag for t, _ in stack):
                while True:
                    name, at = stack.pop()
                    if name == tag:
                        closed.add(at)
                        break
        elif kind == _OPEN:
            if tag in BLOCKS:
                del stack[_opened(stack, tag) :]
            if tag == "main" or tag == "article" and not article:
                around.update(at for _, at in stack)
                article = article or tag == "article"
            if tag not in VOID:
                stack.append((tag, n))
    return closed, around


def lines_of(page: str) -> list[tuple[str, bool, int]]:
    """The lines of a page in order, each with whether an article or main element is around it, and its length without links."""
    events = _events(page)
    closed, around = _matched(events)
    out: list[tuple[str, bool, int]] = []
    stack: list[tuple[str, str, bool, bool]] = []
    text: list[str] = []
    # What hides text now: '' nothing, 'end' an element that will end, 'block' one that the next block ends, 'home' one that an article ends.
    skip, home, link, linked = "", False, False, 0

    def end_line():
        nonlocal linked
        if text:
            line = " ".join(html.unescape("".join(text)).split())
            text.clear()
            if line:
                out.append((line, home, max(0, len(line) - linked)))
            linked = 0

    for n, (kind, tag, attributes) in enumerate(events):
        if kind == _TEXT:
            if not skip:
                text.append(tag)
                linked += len(html.unescape(tag).strip()) if link else 0
            continue
        if tag in BLOCKS:
            end_line()
            if skip == "block" or skip == "home" and kind == _OPEN and tag in HOMES:
                skip = ""
        if kind == _CLOSE:
            if any(t == tag for t, _, _, _ in stack):
                while True:
                    name, skip, home, link = stack.pop()
                    if name == tag:
                        break
            continue
        if tag == "br" and not skip:
            text.append(" ")
        if tag in BLOCKS and (at := _opened(stack, tag)) < len(stack):
            _, skip, home, link = stack[at]
            del stack[at:]
        if tag in VOID:
            continue
        stack.append((tag, skip, home, link))
        if skip:
            continue
        if tag in EMBEDDED:
            skip = "end" if n in closed else "block"
        elif (why := _furniture(tag, attributes, home)) and (n not in around or why == "comments"):
            end_line()
            out.append(("", False, 0))
            skip = "end" if n in closed else "home" if why == "tag" and tag in REGIONS else "block"
        elif tag in HOMES:
            home = True
        elif tag == "a":
            link = True
    end_line()
    return out


def _core(lengths: list[int], surge: float) -> list[int]:
    """The lines of all stretches between a surge and its dive."""
    size = len(lengths)
    sums = [sum(lengths[i : i + WINDOW]) for i in range(size)]
    core: list[int] = []
    i = 0
    while i < size:
        if sums[i] <= surge:
            i += 1
            continue
        # The surge begins with the first line of a run with text that reaches into the window, and the dive follows the last one.
        first = i
        while not lengths[first]:
            first += 1
        while first > 0 and lengths[first - 1]:
            first -= 1
        stop = first
        while stop < size and sums[stop]:
            stop += 1
        last = stop
        while not lengths[last - 1]:
            last -= 1
        core.extend(range(first, last))
        i = max(stop, i + 1)
    return core


def main_text(page: str | None) -> str:
    """The article text of a page: its blocks joined by newlines; empty if the page is null or has none."""
    if not page:
        return ""
    lines = lines_of(page)
    lengths = [own for _, _, own in lines]
    core = _core(lengths, min(SURGE, max((sum(lengths[i : i + WINDOW]) for i in range(len(lengths))), default=0) / 2))
    inside = sum(len(lines[i][0]) for i in core if lines[i][1])
    if 2 * inside >= sum(len(lines[i][0]) for i in core) and any(home for _, home, _ in lines):
        core = _core([len(line) if home else 0 for line, home, _ in lines], 0)
        return "\n".join(lines[i][0] for i in core if lines[i][0] and lines[i][1])
    return "\n".join(lines[i][0] for i in core if lines[i][0])


def extract(pages: DataFrame) -> DataFrame:
    """page_id, url, text and n_chars (code points) for each row of ``pages`` (page_id, url, html).

    Null and empty pages, and pages without article text, have an empty text.  Repeated rows, null ids and null urls are rows like
    others; extra columns are left.  Pages of any length are read whole; a page whose markup breaks off is read to its end, and of elements
    that are never closed only script, style, textarea and title take what follows.
    """

    def make():
        return lambda column: [pa.array([main_text(page) for page in column.to_pylist()], pa.string())]

    out = annotate(columns_of(pages, "page_id", "url", "html"), make, [("text", "string")], text="html", keep_text=False)
    return out.select("page_id", "url", "text", F.length("text").cast("long").alias("n_chars"))
