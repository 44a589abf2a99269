"""Main text of web pages from a stream of parser events.

``html.parser`` events are folded into lines: a block-level tag ends a line.
Every line has a text-to-tag ratio (characters of text by tags in it). The
ratios are smoothed with a Gaussian, and a threshold parts content lines from
the rest. Only content lines vote, with their characters, for the container
that holds the article; its lines are the content region, short ones as well.
The names article and main only widen it: to the outermost of them around the
elected container, and to articles beside it that have content lines too.
Lines inside menus, forms, notices and the like never belong to it. A class or
role that marks such a part counts inside the region only, so a layout wrapper
cannot silence the region that it holds.
"""

from __future__ import annotations

import re
from collections import defaultdict
from collections.abc import Iterator
from html.parser import HTMLParser

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from canopy.arrow import arrow_map

# fixed values: names of elements by their part in a page
INLINE = frozenset("a abbr acronym b bdi bdo big cite code data del dfn em font i ins kbd label mark nobr q ruby s samp small span strike strong sub sup time tt u var wbr".split())
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
HIDDEN = frozenset("script style noscript template head title iframe object svg math canvas audio video select textarea button option map".split())
ASIDE = frozenset("nav header footer aside form menu dialog fieldset".split())
SCOPE = frozenset("html body main article section div td nav header footer aside form menu dialog fieldset table figure ul ol dl blockquote".split())
ARTICLE = frozenset("article main".split())
# fixed values: words of a class or id that name noise, and words that only say where or how it stands
NOISE = frozenset(
    "ad ads advert adverts advertisement advertisements advertising sponsor sponsored promo promos promotion promotions banner banners menu nav navbar navigation breadcrumb breadcrumbs "
    "sidebar aside footer header masthead comment comments respond replies disqus cookie cookies consent gdpr notice notices alert popup modal overlay newsletter subscribe signup login "
    "share sharing social related recommended widget toolbar pagination pager".split()
)
PLACE = frozenset("left right top bottom main primary secondary site page global list lists item items box wrap wrapper container inner outer area block section bar links link buttons button icons slot unit form posts articles stories 1 2 3".split())
WORD = re.compile(r"[a-z]+|[0-9]+")
ROLES = frozenset("navigation banner contentinfo complementary search form dialog alert menu menubar".split())
WIDTH = 2.0


def names_noise(value: str) -> bool:
    """Whether one of the names in a class or id says noise, and nothing else but its place.

    ``site-footer`` and ``sidebarLeft`` do; ``login-required`` and ``social-science`` speak of the content.
    """
    for name in re.sub(r"(?<=[a-z])(?=[A-Z])", "-", value).lower().split():
        words = WORD.findall(name.replace("side-bar", "sidebar"))
        if any(w in NOISE for w in words) and all(w in NOISE or w in PLACE for w in words):
            return True
    return False


class Lines(HTMLParser):
    """Folds parser events into lines: text, tags, container, whether it may vote, and what silences it.

    Silence is None inside noise by tag, else the containers around the elements that are noise by class or role.
    """

    def __init__(self):
        super().__init__(convert_charrefs=True)
        self.open: list[tuple[str, int, bool, tuple | None]] = []  # name, number of its container, noise for the vote, silence
        self.parts: list[str] = []
        self.tags = self.containers = 0
        self.parents, self.is_article, self.lines = [-1], [False], []

    def end_line(self) -> None:
        text = " ".join("".join(self.parts).split())
        if text or self.tags:
            self.lines.append((text, self.tags, *(self.open[-1][1:] if self.open else (0, False, ()))))
        self.parts, self.tags = [], 0

    def handle_starttag(self, tag: str, attrs: list) -> None:
        if tag not in INLINE:
            self.end_line()
        self.tags += 1
        if tag in VOID:
            return
        if tag == "p" or tag == "li":  # their end tags may be left out
            self.leave(tag, SCOPE)
        _, holder, noise, silence = self.open[-1] if self.open else ("", 0, False, ())
        if tag in HIDDEN or tag in ASIDE:
            noise, silence = True, None
        elif silence is not None:
            named = False
            if attrs and (not noise or tag in ARTICLE) and tag not in ("html", "body"):
                values = {k: v or "" for k, v in attrs}
                gone = "hidden" in values or values.get("aria-hidden") == "true"
                named = names_noise(values.get("class", "")) or names_noise(values.get("id", "")) or values.get("role", "") in ROLES
                if gone:
                    noise, silence = True, None
                elif named and tag not in ARTICLE:
                    noise, silence = True, (*silence, holder)
            if tag in ARTICLE and not named and silence is not None:  # may vote inside a wrapper
                noise = False
        if tag in SCOPE:
            self.containers += 1
            self.parents.append(holder)
            self.is_article.append(tag in ARTICLE)
            holder = self.containers
        if tag in SCOPE or noise or tag not in INLINE:
            self.open.append((tag, holder, noise, silence))

    def leave(self, tag: str, barrier: frozenset) -> None:
        for k in range(len(self.open) - 1, -1, -1):
            if self.open[k][0] == tag:
                del self.open[k:]
                return
            if self.open[k][0] in barrier:
                return

    def handle_endtag(self, tag: str) -> None:
        if tag not in INLINE:
            self.end_line()
        self.tags += 1
        if tag not in VOID:
            # an end tag reaches its match; only containers stop one that is none itself
            self.leave(tag, frozenset() if tag in SCOPE else SCOPE - {tag})

    def handle_startendtag(self, tag: str, attrs: list) -> None:
        if tag not in INLINE:
            self.end_line()
        self.tags += 1

    def handle_data(self, data: str) -> None:
        if not (self.open and self.open[-1][0] in HIDDEN):
            self.parts.append(data)


def smooth(ratio: np.ndarray, width: float = WIDTH) -> np.ndarray:
    reach = int(np.ceil(2 * width))
    kernel = np.exp(-np.arange(-reach, reach + 1) ** 2 / (2 * width**2))
    return np.convolve(ratio, kernel / kernel.sum())[reach : reach + len(ratio)]


def clustered(level: np.ndarray) -> np.ndarray:
    """Content lines: those at or above the standard deviation of the smoothed ratios, or above zero if all are equal."""
    spread = level.std()
    return level >= spread if spread > 1e-9 * max(float(level.max(initial=0)), 1.0) else level > 0


def main_text(html: str) -> str:
    """The article of a page, its blocks in order with one space between; empty if there is none."""
    parser = Lines()
    for at in range(0, len(html), 1 << 16):
        parser.feed(html[at : at + (1 << 16)])
    parser.close()
    parser.end_line()
    lines = parser.lines
    if not lines:
        return ""
    ratio = np.array([len(t) / max(tags, 1) for t, tags, *_ in lines])
    content = clustered(smooth(ratio))
    votes: dict[int, float] = defaultdict(float)
    may = [bool(text) and not noise for text, _, _, noise, _ in lines]
    chosen = [m and c for m, c in zip(may, content)]
    for (text, _, holder, *_), good in zip(lines, chosen if any(chosen) else may):  # a page of tags only has no dense line
        if good:
            votes[holder] += len(text)
    if not votes:
        return ""
    total, up = defaultdict(float), parser.parents
    for holder, v in votes.items():
        while holder >= 0:
            total[holder] += v
            holder = up[holder]
    best = 0  # the innermost container that has most of the votes
    while inner := [k for k in total if k and up[k] == best and total[k] >= 0.6 * total[0]]:
        best = max(inner, key=total.get)
    holder = best
    while holder >= 0:
        best, holder = holder if parser.is_article[holder] else best, up[holder]
    region = {best}
    if parser.is_article[best]:  # articles beside it that have content lines of their own
        region |= {k for k in total if up[k] == up[best] and parser.is_article[k]}

    def within(holder: int) -> bool:
        while holder >= 0 and holder not in region:
            holder = up[holder]
        return holder >= 0

    inside = {h: within(h) for h in range(len(up))}
    return " ".join(t for t, _, h, _, silence in lines if t and inside[h] and silence is not None and not any(inside[p] for p in silence))


def extract(pages: DataFrame) -> DataFrame:
    """``(page_id, url, text, n_chars)`` of every row.

    A null page is empty, and so is one without a content line. Rows that
    repeat a page are extracted one by one; containers of equal votes give the
    first on the page. Whole pages count, parsed in parts of bounded size.
    Extra columns are ignored, and an empty table gives no row.
    """

    def make():
        def step(ids: list, urls: list, pages: list) -> Iterator[tuple]:
            for page_id, url, html in zip(ids, urls, pages):
                text = main_text(html or "")
                yield page_id, url, text, len(text)

        return step

    return arrow_map(pages.select(F.col("page_id").cast("long").alias("page_id"), "url", "html"), make, "page_id long, url string, text string, n_chars long")
