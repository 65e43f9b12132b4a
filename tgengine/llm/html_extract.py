"""Main text of web pages by line-block distribution.

Markup is stripped so that each block element ends a line; scripts, styles, comments, forms and elements that are page
furniture by their name, role or class give no text. Lengths of the remaining lines (words inside links don't count) are
summed over a sliding window of `WINDOW` lines, over the whole page. A text region starts where the sums surge: at a window
of at least `SURGE` characters whose following sums stay above zero; it ends where they dive to zero. Regions with at most
`GAP` lines between them, such as a list of links inside the text, are one; the region with most text is the main text.

The region's bounds are then set by the markup that holds it. Where the page marks articles or a main part, the marked elements
that surge, each with at least 1 / `PART` of the text of the largest, are kept whole, links too, and no other line; they are passed
over only if together they hold less than 1 / `PART` of the main region. Without marks it is the lowest element that holds
`MOST` of the region's text: lines outside it go, as those of an advert beside the text, and up to `GAP` lines that it holds
beyond the region come, as a linked head. A page on which nothing
surges gives its marked lines, or all lines.

An element that looks like furniture is read after all if it holds the article: a marked one where no other is seen, or,
on pages without marks, more text than is seen where nothing seen surges, or a main heading and `PART` times all other text.

Null and empty pages, and pages without text, give the empty text; unclosed and cut-off markup ends with the page; null
ids and repeated rows are answered row by row; other columns are ignored.
"""

from __future__ import annotations

import html
import re
from dataclasses import dataclass
from itertools import accumulate

from pyspark.sql import DataFrame

from .common import map_rows, read

WINDOW = 3
SURGE = 60
GAP = 2 * WINDOW
PART = 4
MOST = 0.9
TAG = re.compile(r"<!--.*?(?:-->|\Z)|<(/?)([a-zA-Z][a-zA-Z0-9:-]*)((?:[^<>\"']|\"[^\"]*\"|'[^']*')*)(?:>|\Z)|<[!?][^>]*(?:>|\Z)", re.S)
#: Elements whose content isn't text of the page, page furniture, and blocks.
RAW = {"script", "style", "noscript", "template", "textarea", "iframe", "svg", "math", "object", "canvas", "title"}
FURNITURE = {"nav", "header", "footer", "aside", "form", "button", "select", "menu", "dialog", "head"}
#: Furniture that holds the text only where it also holds a marked article.
LISTS = {"nav", "footer", "button", "select", "menu"}
BLOCKS = set("address article aside blockquote body br caption center dd details dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 head header hr html li main menu nav ol option p pre section summary table tbody td tfoot th thead title tr ul".split())
VOID = {"br", "hr", "img", "input", "meta", "link", "area", "base", "col", "embed", "source", "track", "wbr"}
LABEL = re.compile(r"(?:class|id|role)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s>]+))", re.I)
NAMES = re.compile(
    r"(?:^|[\s_-])(?:ads?|adverts?|advertisement|banner|sponsor(?:ed)?|promo|nav|navbar|navigation|menu|breadcrumbs?|header|masthead|footer|sidebar|side|aside|widget|related|"
    r"cookies?|consent|notice|popup|modal|overlay|newsletter|subscribe|signup|login|search|share|social|comments?|replies|respond|disqus|complementary|contentinfo)(?:$|[\s_-])", re.I)
SPACE = re.compile(r"\s+")


#: Parts of names that say nothing about what an element holds.
NEUTRAL = set("bar block body box button buttons container content form group inner item items link links list outer panel posts row section text title top wrap wrapper".split())
PARTS = re.compile(r"[\s_-]+")
#: Elements that can hold a text; others, such as paragraphs, are parts of one.
HOLDERS = set("html body div section article main td center form header details dl table tbody tr".split())


def _is_furniture(tag: str, attributes: str, in_article: bool) -> bool:
    """By name, role or class; within an article a class counts only if all its parts speak of furniture, so that `share-price` is text."""
    if tag in FURNITURE and not (tag == "header" and in_article):
        return True
    if not attributes or tag in ("body", "html", "article", "main"):
        return False
    for found in LABEL.findall(attributes):
        for token in "".join(found).split():
            if NAMES.search(token) and (not in_article or all(p.lower() in NEUTRAL or NAMES.search(p) for p in PARTS.split(token) if p)):
                return True
    return False


@dataclass
class Hidden:
    start: int
    tag: str
    size: int = 0  # characters outside links
    marked: bool = False  # holds an article or a main part
    headed: bool = False  # holds a main heading


@dataclass
class Line:
    text: str
    size: int  # characters outside links
    mark: int  # number of the outermost article or main part that holds it, 0: none
    at: int  # number of the element that holds it


def lines(page: str, shown: frozenset[int] = frozenset()) -> tuple[list[Line], list[Hidden], list[tuple[int, str]]]:
    """Lines with text, the elements left out, and all elements as (number of the parent, name), parents first.

    `shown`: starts of elements that are read though they look like furniture. One pass, linear in the page's length."""
    out: list[Line] = []
    left: list[Hidden] = []
    parts: list[str] = []
    linked = [0]
    elements: list[tuple[int, str]] = [(0, "html")]
    stack: list[tuple[str, int]] = []  # open elements, outermost first
    opened: dict[str, int] = {}  # how many of a name are open
    hidden = 0  # depth in the stack from which nothing is read; 0: reading
    article, link, marks, at = 0, 0, 0, 0

    def end() -> None:
        text = SPACE.sub(" ", html.unescape("".join(parts))).strip()
        if text:
            out.append(Line(text, max(0, len(text) - linked[0]), marks if article else 0, stack[-1][1] if stack else 0))
        parts.clear()
        linked[0] = 0

    def close() -> str:
        nonlocal article, link
        top, _ = stack.pop()
        opened[top] -= 1
        article -= top in ("article", "main")
        link -= top == "a"
        return top

    size = len(page)
    while at < size:
        m = TAG.search(page, at)
        stop = m.start() if m else size
        if stop > at and not hidden:
            parts.append(page[at:stop])
            if link:
                linked[0] += stop - at
        elif stop > at and not link:
            left[-1].size += len(page[at:stop].strip())
        if not m:
            break
        at = m.end() if m.end() > m.start() else m.end() + 1
        tag = (m[2] or "").lower()
        if not tag:
            continue
        if tag in BLOCKS and not hidden:
            end()
        if m[1]:
            if opened.get(tag):
                while close() != tag:
                    pass
                hidden = hidden if hidden <= len(stack) else 0
            continue
        if tag in VOID or m[3].endswith("/"):
            continue
        if tag in ("p", "li", "dt", "dd", "tr", "td", "th", "option") and stack and stack[-1][0] == tag:
            close()
            hidden = hidden if hidden <= len(stack) else 0
        if tag in RAW:
            shut = re.compile(f"</{tag}\\s*>", re.I).search(page, at)
            at = shut.end() if shut else size
            continue
        elements.append((stack[-1][1] if stack else 0, tag))
        stack.append((tag, len(elements) - 1))
        opened[tag] = opened.get(tag, 0) + 1
        if tag in ("article", "main"):
            article += 1
            marks += article == 1 and not hidden
        link += tag == "a"
        if hidden:
            left[-1].marked |= tag in ("article", "main")
            left[-1].headed |= tag == "h1"
        elif m.start() not in shown and _is_furniture(tag, m[3], article > 0):
            hidden = len(stack)
            left.append(Hidden(m.start(), tag))
    if not hidden:
        end()
    return out, left, elements


def holder(found: list[Line], left: list[Hidden], window: int, surge: int) -> int | None:
    """Start of the element left out that holds the article, if one does."""
    if any(x.mark for x in found):
        return None
    marked = [x for x in left if x.marked and x.size]
    if marked:
        return max(marked, key=lambda x: (x.size, -x.start)).start
    seen = sum(x.size for x in found)
    most = max((x for x in left if x.tag not in LISTS), key=lambda x: (x.size, -x.start), default=None)
    if most is None or most.size < surge:
        return None
    others = seen + sum(x.size for x in left) - most.size
    alone = most.size > seen and not regions([x.size for x in found], window, surge)
    return most.start if alone or (most.headed and most.size >= PART * others) else None


def regions(lengths: list[int], window: int = WINDOW, surge: int = SURGE) -> list[tuple[int, int]]:
    """Half-open line ranges between surge and dive points of the windowed sums."""
    n = len(lengths)
    upto = [0, *accumulate(lengths)]
    sums = [upto[min(n, i + window)] - upto[i] for i in range(n)]
    found, i = [], 0
    while i < n:
        if sums[i] >= surge:
            j = i
            while j < n and sums[j] > 0:
                j += 1
            a, b = i, j  # the window looks ahead: the surge is at its first line with text, the dive after the last
            while a < b and not lengths[a]:
                a += 1
            while b > a and not lengths[b - 1]:
                b -= 1
            found.append((a, b))
            i = j
        i += 1
    return found


def joined(spans: list[tuple[int, int]], gap: int = GAP) -> list[tuple[int, int]]:
    out: list[tuple[int, int]] = []
    for a, b in spans:
        if out and a - out[-1][1] <= gap:
            out[-1] = (out[-1][0], b)
        else:
            out.append((a, b))
    return out


def within_holder(found: list[Line], span: tuple[int, int], elements: list[tuple[int, str]]) -> list[Line]:
    """The region's lines inside the lowest element that holds most of its text."""
    a, b = span
    weight, rows = [0] * len(elements), [0] * len(elements)
    for x in found[a:b]:
        weight[x.at] += x.size
        rows[x.at] += 1
    for i in range(len(elements) - 1, 0, -1):  # children before their parents
        weight[elements[i][0]] += weight[i]
        rows[elements[i][0]] += rows[i]
    least = MOST * weight[0]
    best = max((i for i in range(len(elements)) if weight[i] >= least and elements[i][1] in HOLDERS and (rows[i] > 1 or b - a == 1)), default=0)
    inside = [False] * len(elements)
    inside[best] = True
    for i in range(best + 1, len(elements)):
        inside[i] = inside[elements[i][0]]
    whole, part = [x for x in found if inside[x.at]], [x for x in found[a:b] if inside[x.at]]
    # a few lines without text of their own, such as a linked head, are the element's; many are a menu in the same element
    return whole if elements[best][1] not in ("html", "body") and len(whole) - len(part) <= GAP else part


def main_text(page: str | None, window: int = WINDOW, surge: int = SURGE) -> str:
    shown: frozenset[int] = frozenset()
    found, left, elements = lines(page or "")
    for _ in range(16):  # elements that hold the article may stand in each other
        more = holder(found, left, window, surge)
        if more is None:
            break
        shown |= {more}
        found, left, elements = lines(page or "", shown)
    weight = lambda rows: sum(x.size for x in rows)
    surges = regions([x.size for x in found], window, surge)
    spans = joined(surges)
    a, b = max(spans, key=lambda s: (weight(found[s[0] : s[1]]), -s[0]), default=(0, 0))
    marked = [x for x in found if x.mark]
    if not spans:
        return "\n".join(x.text for x in marked or [x for x in found if x.size])
    by_mark: dict[int, int] = {}
    for x in marked:
        by_mark[x.mark] = by_mark.get(x.mark, 0) + x.size
    touched = {x.mark for s, e in surges for x in found[s:e] if x.mark}
    kept = {k for k in touched if PART * by_mark[k] >= max(by_mark[j] for j in touched)}
    chosen = [x for x in marked if x.mark in kept]
    if chosen and PART * weight(chosen) >= weight(found[a:b]):
        return "\n".join(x.text for x in chosen)
    if marked and not chosen and PART * weight(marked) >= weight(found[a:b]):
        return "\n".join(x.text for x in marked)
    return "\n".join(x.text for x in within_holder(found, (a, b), elements))


def report(pages: DataFrame) -> DataFrame:
    """page_id, url, text, n_chars of every page."""

    def run(batches):
        for b in batches:
            t = [main_text(h) for h in b["html"]]
            yield {"page_id": b["page_id"], "url": b["url"], "text": t, "n_chars": [len(x) for x in t]}

    return map_rows(pages.select("page_id", "url", "html"), "page_id long, url string, text string, n_chars long", run)


def op1_html_extraction(spark, sf_dir: str) -> DataFrame:
    return report(read(spark, sf_dir, "pages"))
