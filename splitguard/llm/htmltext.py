"""Main text of web pages by line-block distribution.

1. Markup is stripped into lines, one for each block of the page; what stood at the border of
   an article or main element leaves blank lines. Scripts, styles and forms give no lines.
2. Every line has a weight: its characters outside links, or none where most of it is links.
   Hints only change weights: lines of an element that is, or names itself, a menu, header,
   footer, sidebar, notice, advert or comment weigh nothing; lines inside an article or main
   element weigh SURGE more, so that short paragraphs of an article don't break it.
3. Weights are summed over sliding windows. A surge is where the sum rises over a threshold,
   a dive where it has fallen under it; lines between a surge and its dive are a region.
4. The heaviest region tells where the article is: in an article element, in a main element or
   outside both. The text is the regions of that place (outside an article element, those with
   an eighth of the heaviest's weight), the lines between them there and the headings right
   before them.

Defined results: a null or empty page has an empty text; character references are decoded
after the markup is gone; an unclosed element ends with the page; the threshold is lower on a
page without a window of some length, so a page of a few words is its words; if all lines weigh
nothing, the names that elements give themselves are not heeded; very long pages and broken
markup take time in proportion to their length; repeated rows give equal results; an empty
table gives an empty result; other columns are ignored unless named in `keep`.
"""

from __future__ import annotations

import html as references
import re
from collections.abc import Iterator
from dataclasses import dataclass
from functools import lru_cache
from itertools import accumulate

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from splitguard.llm.rows import lean

WINDOW = 3
SURGE = 60
#: Outside an article element, a region belongs to the text if it has one part in SHARE of the heaviest's weight.
SHARE = 8
OUTSIDE, MAIN, ARTICLE = 0, 1, 2
#: How often a page may be read in vain for the end of a quoted attribute.
QUOTED_READS = 16

# Names of elements, and words by which elements name their role.
_RAW = frozenset("script style noscript template svg iframe object canvas textarea select title audio video".split())
_BARE = frozenset("nav header footer aside form head menu dialog button".split())
_INLINE = frozenset(
    "a abbr acronym b bdi bdo big cite code data del dfn em font i ins kbd label mark math mi mn mo mrow "
    "msqrt msub msup q rp rt ruby s samp small span strike strong sub sup time tt u var wbr img input".split()
)
_VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
_HEADINGS = frozenset("h1 h2 h3".split())
_ROLES = frozenset(
    "ad ads advert adverts advertisement advertisements aside banner breadcrumb breadcrumbs comment comments "
    "complementary consent contentinfo cookie cookies disqus footer header login masthead menu modal nav navbar "
    "navigation newsletter notice notices overlay pagination popup promo recommended related replies respond "
    "search share sharing sidebar signup social sponsor sponsored subscribe toolbar widget".split()
)
#: Words that say where, how big or whose an element is, but not what; beside a role word they change nothing.
_LAYOUT = frozenset(
    "area bar block bottom box center col column container content desktop fixed floating footer form global header "
    "holder inner item items left link links list lower main mobile module nav outer page panel post posts primary "
    "rail reader readers right row secondary section site slot small sticky strip sub text thread top unit upper "
    "user users wrap wrapper zone".split()
)

_NAME = re.compile(r"[a-zA-Z][a-zA-Z0-9:-]*")
_ATTRIBUTES = re.compile(r"""[^"'>]*(?:(?:"[^"]*"|'[^']*')[^"'>]*)*""")
_HINTS = re.compile(
    r"""(?:^|[\s"'])(?:class|id|role|aria-label)\s*=\s*(?:"([^"]*)"|'([^']*)'|([^\s"'>]+))""", re.IGNORECASE
)
_HIDDEN = re.compile(
    r"""(?:^|\s)hidden(?:$|[\s=/])|aria-hidden\s*=\s*["']?true|display\s*:\s*none""", re.IGNORECASE
)
_PARTS = re.compile(r"[A-Z]?[a-z]+|[A-Z]+|\w")
_CUT = re.compile(r"<[a-zA-Z/!]")


@dataclass(slots=True)
class Line:
    text: str
    linked: int  # characters inside links
    place: int  # OUTSIDE, MAIN or ARTICLE
    heading: bool
    bare: bool  # in an element that is or names itself something else than text

    def weight(self) -> int:
        if self.bare or not self.text:
            return 0
        if self.place:
            return len(self.text) + SURGE
        return 0 if 2 * self.linked > len(self.text) else len(self.text) - self.linked


_BLANK = Line("", 0, OUTSIDE, False, False)


@lru_cache(1 << 14)
def _names_a_role(token: str) -> bool:
    """Whether a class or id is a role word, alone or with words of layout only."""
    words = [w.lower() for w in _PARTS.findall(token) if not w.isdigit()]
    return any(w in _ROLES for w in words) and all(w in _ROLES or w in _LAYOUT for w in words)


def _bare(name: str, attrs: str, hints: bool) -> bool:
    if name in _BARE:
        return True
    if not hints or not attrs or name in ("html", "body", "article", "main"):
        return False
    if _HIDDEN.search(attrs):
        return True
    return any(_names_a_role(t) for a, b, c in _HINTS.findall(attrs) for t in (a or b or c).split())


def _tags(page: str) -> Iterator[tuple[int, int, str, bool, str]]:
    """(start, end, name, closing, attributes) of all markup; comments and raw elements have no name.

    Every character is looked at a bounded number of times, whatever the markup: quotes are
    heeded until searches for a tag's end that ran past all of them have read QUOTED_READS pages.
    """
    last = page.rfind(">")
    budget = QUOTED_READS * len(page)
    lowered = ""
    at = page.find("<")
    while -1 < at < last:
        if page.startswith("<!--", at):
            end = page.find("-->", at + 4)
            end = len(page) if end < 0 else end + 3
            yield at, end, "", False, ""
        elif page.startswith(("<!", "<?"), at):
            end = page.find(">", at) + 1
            yield at, end, "", False, ""
        else:
            closing = page.startswith("/", at + 1)
            name = _NAME.match(page, at + 1 + closing)
            if not name and not closing:
                at = page.find("<", at + 1)
                continue
            start = name.end() if name else at
            end = _ATTRIBUTES.match(page, start).end() if budget > 0 else start
            if not page.startswith(">", end):  # a quote without an end
                budget -= end - start
                end = page.find(">", start)
            attrs = page[start:end]
            end += 1
            tag = name[0].lower() if name else ""
            if tag in _RAW and not closing and not attrs.endswith("/"):
                lowered = lowered or re.sub("[A-Z]", lambda m: m[0].lower(), page)  # keeps all positions
                close = lowered.find(f"</{tag}", end)
                close = page.find(">", close) + 1 if close >= 0 else 0
                yield at, close or len(page), "", False, ""
                end = close or len(page)
            else:
                yield at, end, tag, closing, attrs
        at = page.find("<", end)


def page_lines(page: str, hints: bool = True, gap: int = WINDOW - 1) -> list[Line]:
    """Lines of text, one a block; `gap` blank ones at the borders of article and main elements.

    Without hints only the names of elements tell what is no text, not their attributes.
    """
    lines: list[Line] = []
    pieces: list[tuple[str, bool]] = []
    at, links, heading = 0, 0, False
    inside = {"article": 0, "main": 0}  # open elements of either name
    skipped = muted = ""  # the open element whose lines are bare, or whose words are left out of a line
    depth = 0

    def end_block() -> None:
        nonlocal pieces
        text = " ".join("".join(p for p, _ in pieces).split())
        if text:
            linked = sum(len("".join(p.split())) for p, in_link in pieces if in_link)
            place = ARTICLE if inside["article"] else MAIN if inside["main"] else OUTSIDE
            lines.append(Line(text, min(linked, len(text)), place, heading, bool(skipped)))
        pieces = []

    for start, end, name, closing, attrs in _tags(page):
        if start > at and not muted:
            pieces.append((references.unescape(page[at:start]), links > 0))
        at = end
        if not name:
            continue
        single = name in _VOID or attrs.endswith("/")
        if muted or skipped:
            if skipped and name not in _INLINE:
                end_block()
            if name == (muted or skipped) and not single:
                depth += -1 if closing else 1
                if not depth:
                    skipped = muted = ""
            continue
        if not closing and not single and _bare(name, attrs, hints):
            depth = 1
            if name in _INLINE:
                muted = name
            else:
                end_block()
                skipped = name
            continue
        if name == "a":
            links = max(0, links + (-1 if closing else 1))
        if name in _INLINE:
            continue
        end_block()
        heading = name in _HEADINGS and not closing
        if name in inside:
            inside[name] = max(0, inside[name] + (-1 if closing else 1))
            lines += [_BLANK] * gap
    if at < len(page) and not muted:
        tail = page[at:]
        cut = _CUT.search(tail)  # a tag cut off by the end
        pieces.append((references.unescape(tail[: cut.start()] if cut else tail), links > 0))
    end_block()
    return lines


def window_sums(weights: list[int], window: int) -> list[int]:
    """Sums of all runs of `window` weights, or of all weights if there are fewer."""
    if not weights:
        return []
    width = min(window, len(weights))
    upto = [0, *accumulate(weights)]
    return [upto[i + width] - upto[i] for i in range(len(weights) - width + 1)]


def regions(weights: list[int], window: int = WINDOW, surge: int = SURGE) -> list[tuple[int, int]]:
    """(surge, dive) index pairs: runs of lines covered by windows of enough text."""
    width = min(window, len(weights))
    found: list[tuple[int, int]] = []
    for i, total in enumerate(window_sums(weights, window)):
        if total < surge:
            continue
        first, last = i, i + width
        while first < last and not weights[first]:
            first += 1
        while last > first and not weights[last - 1]:
            last -= 1
        if found and first <= found[-1][1]:
            found[-1] = (found[-1][0], max(last, found[-1][1]))
        elif last > first:
            found.append((first, last))
    return found


def main_text(page: str | None, window: int = WINDOW, surge: int = SURGE) -> str:
    if not page:
        return ""
    lines = page_lines(page, True, window - 1)
    if not any(x.weight() for x in lines):  # a wrapper may be named after its parts
        lines = page_lines(page, False, window - 1)
    weights = [x.weight() for x in lines]
    # A page without any long window surges at a quarter of its best one.
    most = max(window_sums(weights, window), default=0)
    found = [(s, e, sum(weights[s:e])) for s, e in regions(weights, window, min(surge, 1 + most // 4))]
    if not found:
        return ""
    best = max(found, key=lambda r: r[2] * (1 + lines[r[0]].place))
    place = lines[best[0]].place
    # Outside an article element a region may be something else; a small one is.
    least = 0 if place == ARTICLE else best[2] // SHARE
    own = [(s, e) for s, e, size in found if lines[s].place == place and size >= least]
    start, end = own[0][0], own[-1][1]
    kept = [x.text for x, w in zip(lines[start:end], weights[start:end]) if w and x.place == place]
    for x in reversed(lines[:start]):
        if not x.text:
            continue
        if not x.heading or not x.weight() or (place and not x.place):
            break
        kept.insert(0, x.text)
    return " ".join(kept)


def extract(
    pages: DataFrame, id_col: str = "page_id", html_col: str = "html", keep: tuple[str, ...] = ("url",)
) -> DataFrame:
    """(page_id, keep..., text, n_chars) for every page."""
    slim = pages.select(
        F.col(id_col).cast("long").alias("page_id"), *keep, F.col(html_col).alias("html")
    )
    names = ["page_id", *keep]
    types = dict(slim.dtypes)

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = [main_text(p.as_py()) for p in batch.column("html")]
            columns = [batch.column(c) for c in names]
            columns += [pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())]
            yield pa.RecordBatch.from_arrays(columns, names=[*names, "text", "n_chars"])

    schema = ", ".join(f"`{c}` {types[c]}" for c in names)
    return slim.mapInArrow(lean(kernel), f"{schema}, text string, n_chars long")
