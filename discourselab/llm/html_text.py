"""Main text of HTML pages by text-to-tag ratios over streaming parser events.

The standard library's parser streams events; block tags end a line. Each line has a ratio: its characters
outside links over its tags. The ratios are smoothed with a Gaussian and clustered by a threshold (their
standard deviation): lines above it are content. Every container is scored by the lines in it: content
counts its characters, other lines count against it by their link text and ``LINE`` each, first-level
headings count ``HEADING`` at least. The region is the container of the highest score, widened to the outermost article
around it, or else the outermost main. All of its lines are kept, so short paragraphs between and before long
ones stay; without an article or main, blocks of mostly links at its ends go.

What elements, roles and class names say is a weak feature of the choice: a container that they call
boilerplate counts nothing for what encloses it and may still be the region, at ``FORM`` or ``HINT`` of its
score (menus, asides, footers and page headers are never). Inside the region such parts are left out. A class or
id hints only if all words of one of its names do, so ``related-work`` and ``no-sidebar`` hint at nothing.

One narrow pass; nothing is shuffled. Pages are parsed whole, in time linear in their length and depth.

Defined cases
    Null or empty pages, and pages without content, give an empty text. Tags that are never closed end
    where their parent or the page does; paragraphs, list items, table cells and the like end where the next
    begins. Repeated rows are extracted each. An empty table gives an empty result. Other columns are ignored.
"""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Iterator
from html.parser import HTMLParser

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from discourselab.session import prepare

SIGMA = 1.0
RADIUS = 2
#: What a line that is not content counts against its containers, besides its link text.
LINE = 10
#: What a first-level heading counts at least.
HEADING = 4 * LINE
#: Shares of their score that forms, and parts that class or id call boilerplate, compete with.
FORM, HINT = 0.25, 0.5

_VOID = frozenset("area base br col embed hr img input link meta source track wbr".split())
_BLOCKS = frozenset((
    "address article aside blockquote body caption center dd details dialog div dl dt fieldset figcaption figure footer "
    "form h1 h2 h3 h4 h5 h6 header hr html legend li main menu nav ol option p pre section summary table tbody td tfoot th "
    "thead tr ul"
).split())
#: Elements that may be the region.
_REGIONS = frozenset("article body center div form html main section".split())
#: Elements whose text is never shown as running text.
_UNSEEN = frozenset("head script style noscript template iframe object svg canvas math button select textarea dialog".split())
_BOILERPLATE = frozenset("nav aside footer form menu".split())
_ROLES = frozenset("navigation banner contentinfo complementary search alert alertdialog dialog menu menubar form".split())
_HINTS = frozenset((
    "ad ads advert adverts advertisement advertising adsense sponsor sponsored promo promotion banner cookie cookies "
    "consent gdpr notice notices popup modal overlay newsletter subscribe signup login sidebar sidebars widget widgets "
    "menu menus nav navbar navigation breadcrumb breadcrumbs footer masthead topbar toolbar comment comments commentlist "
    "disqus respond replies share sharing social related recommended recommendations trending pagination pager"
).split())
#: Words that say nothing by themselves beside a hint.
_PLAIN = frozenset((
    "area bar block bottom box buttons column container content form group inner items item left link links list main "
    "outer panel posts primary right secondary section site slot stories text top unit wrap wrapper"
).split())
_NAME, _WORD = re.compile(r"\S+"), re.compile(r"[A-Za-z]+")
#: What the start of a tag ends, up to the nearest element that is not listed here.
_ENDS = {
    "li": {"li"},
    "dt": {"dt", "dd"},
    "dd": {"dt", "dd"},
    "td": {"td", "th"},
    "th": {"td", "th"},
    "tr": {"td", "th", "tr"},
    "option": {"option"},
    "tbody": {"td", "th", "tr", "tbody", "thead"},
    "tfoot": {"td", "th", "tr", "tbody", "thead"},
}
_OPENABLE = frozenset().union(*_ENDS.values(), {"p", "head"})


def hints(value: str | None) -> bool:
    """Whether a name in a class or id attribute is made of words for boilerplate."""
    for name in _NAME.findall((value or "").lower()):
        words = _WORD.findall(name)
        if words and not _HINTS.isdisjoint(words) and all(w in _HINTS or w in _PLAIN for w in words):
            return True
    return False


class _Lines(HTMLParser):
    """Collects the lines of a page and the tree of the elements that hold them.

    Parallel lists by element: ``parents``, ``tags`` and ``shares`` (1 for what is not called boilerplate, the
    share that it competes with for what is, 0 for what is never the region). Element 0 is the page.
    """

    def __init__(self) -> None:
        super().__init__(convert_charrefs=True)
        self.parents, self.tags, self.shares = [0], ["body"], [1.0]
        #: (text, characters in links, tags, element, is a first-level heading)
        self.lines: list[tuple[str, int, int, int, bool]] = []
        self.open: list[tuple[str, int, bool]] = []  # tag, element, unseen
        self.held: Counter[str] = Counter()
        self.here = self.unseen = self.links = self.linked = self.count = 0
        self.text: list[str] = []
        self.heading = False

    def end_line(self) -> None:
        if self.text and (text := " ".join("".join(self.text).split())):
            self.lines.append((text, min(self.linked, len(text)), max(1, self.count), self.here, self.heading))
            self.count = 0
        self.text, self.linked = [], 0

    def pop(self) -> str:
        tag, _, unseen = self.open.pop()
        self.unseen -= unseen
        self.held[tag] -= 1
        self.here = self.open[-1][1] if self.open else 0
        return tag

    def imply_ends(self, tag: str) -> None:
        """End what the start of ``tag`` ends: inline elements, a paragraph, the head, an item or cell."""
        if tag in _BLOCKS:
            while self.open and self.open[-1][0] not in _BLOCKS and (self.open[-1][0] not in _UNSEEN or self.open[-1][0] == "head"):
                self.pop()
            if self.open and self.open[-1][0] == "p":
                self.pop()
        if ends := _ENDS.get(tag):
            k = len(self.open)
            while k and self.open[k - 1][0] in _OPENABLE:
                k -= 1
                if self.open[k][0] in ends and not (k and self.open[k - 1][0] in ends):
                    while len(self.open) > k:
                        self.pop()
                    return

    def share(self, tag: str, attrs: list[tuple[str, str | None]]) -> float:
        if tag in ("html", "body", "article", "main"):
            return 1.0
        if tag in _BOILERPLATE or tag == "header" and not (self.held["article"] or self.held["main"]):
            return FORM if tag == "form" else 0.0
        out = 1.0
        for name, value in attrs:
            if name == "hidden" or name == "aria-hidden" and value == "true" or name == "role" and (value or "").lower() in _ROLES:
                return 0.0
            if name in ("class", "id") and hints(value):
                out = HINT
        return out

    def handle_starttag(self, tag: str, attrs: list[tuple[str, str | None]]) -> None:
        if tag in _BLOCKS:
            self.end_line()
            self.imply_ends(tag)
            self.heading = tag == "h1"
        elif tag == "br":
            self.text.append(" ")
        self.count += not self.unseen
        if tag in _VOID:
            return
        self.links += tag == "a"
        share = self.share(tag, attrs)
        if tag in _BLOCKS:
            self.parents.append(self.here)
            self.tags.append(tag)
            self.shares.append(share)
            self.here = len(self.tags) - 1
        unseen = tag in _UNSEEN or tag not in _BLOCKS and share < 1
        if tag in _BLOCKS or unseen:
            self.open.append((tag, self.here, unseen))
            self.held[tag] += 1
            self.unseen += unseen

    def handle_startendtag(self, tag: str, attrs: list[tuple[str, str | None]]) -> None:
        if tag in _VOID:
            self.handle_starttag(tag, attrs)
        elif tag in _BLOCKS:
            self.end_line()

    def handle_endtag(self, tag: str) -> None:
        if tag in _BLOCKS:
            self.end_line()
            self.heading = False
        self.count += not self.unseen
        self.links = max(0, self.links - (tag == "a"))
        if self.held[tag]:
            while self.pop() != tag:
                pass

    def handle_data(self, data: str) -> None:
        if not self.unseen:
            self.text.append(data)
            if self.links:
                self.linked += len(data.strip())


def parsed(html: str) -> _Lines:
    parser = _Lines()
    parser.feed(html)
    parser.close()
    parser.end_line()
    return parser


def smoothed(ratios: np.ndarray, sigma: float = SIGMA, radius: int = RADIUS) -> np.ndarray:
    """Gaussian smoothing, with the first and last value repeated beyond the ends."""
    kernel = np.exp(-(np.arange(-radius, radius + 1) ** 2) / (2 * sigma**2))
    return np.convolve(np.pad(ratios, radius, mode="edge"), kernel / kernel.sum(), mode="valid")


def content_lines(lines: list[tuple[str, int, int, int, bool]]) -> list[bool]:
    """Which lines lie above the threshold of the smoothed text-to-tag ratios."""
    ratios = np.array([(len(text) - linked) / tags for text, linked, tags, _, _ in lines])
    curve = smoothed(ratios)
    return (curve >= min(ratios.std(), curve.max())).tolist()


def region(parser: _Lines, content: list[bool]) -> int | None:
    """The element of the highest score, widened to its article or main."""
    parents, tags, shares = parser.parents, parser.tags, parser.shares
    score = [0.0] * len(tags)
    for (text, linked, _, element, heading), good in zip(parser.lines, content, strict=True):
        score[element] += max(len(text), heading * HEADING) if good or heading else -LINE - linked
    for k in range(len(tags) - 1, 0, -1):
        if shares[k] == 1:
            score[parents[k]] += score[k]
    factor, best, most = shares.copy(), None, 0.0
    for k in range(len(tags)):
        if k:
            factor[k] *= factor[parents[k]]
        worth = factor[k] * score[k]
        if tags[k] in _REGIONS and (worth > most or worth == most > 0 and parents[k] == best):
            best, most = k, worth
    if best is None:
        return None
    wider: dict[str, int] = {}
    k = best
    while True:
        wider[tags[k]] = k
        if not k or shares[k] < 1:
            break
        k = parents[k]
    return wider.get("article", wider.get("main", best))


def main_text(html: str | None) -> str:
    """Main text of one page, a line for each block."""
    parser = parsed(html or "")
    lines, content = parser.lines, content_lines(parser.lines) if parser.lines else []
    chosen = region(parser, content) if lines else None
    if chosen is None:
        return ""
    # by element: the part of the region (a child of it) that it lies in, -1 outside and in boilerplate
    part = [-1] * len(parser.tags)
    part[chosen] = chosen
    for k in range(chosen + 1, len(part)):
        above = part[parser.parents[k]]
        if above >= 0 and parser.shares[k] == 1:
            part[k] = k if parser.parents[k] == chosen else above
    kept = [k for k, line in enumerate(lines) if part[line[3]] >= 0]
    if parser.tags[chosen] not in ("article", "main"):
        kept = _without_link_blocks(lines, content, part, kept, chosen)
    return "\n".join(lines[k][0] for k in kept)


def _without_link_blocks(lines: list[tuple[str, int, int, int, bool]], content: list[bool], part: list[int], kept: list[int], chosen: int) -> list[int]:
    """Lines but those of parts of mostly link text before the first or after the last part with content."""
    parts = [part[lines[k][3]] for k in kept]
    good = {p for k, p in zip(kept, parts, strict=True) if content[k] or lines[k][4]}
    text, linked = Counter(), Counter()
    for k, p in zip(kept, parts, strict=True):
        text[p] += len(lines[k][0])
        linked[p] += lines[k][1]
    first = next((i for i, p in enumerate(parts) if p in good), 0)
    last = len(parts) - next((i for i, p in enumerate(parts[::-1]) if p in good), 0)
    return [k for i, (k, p) in enumerate(zip(kept, parts, strict=True)) if first <= i < last or p == chosen or 2 * linked[p] < text[p]]


def extract(pages: DataFrame) -> DataFrame:
    """page_id, url, text and n_chars of every row of a (page_id, url, html) table."""
    prepare(pages.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = [main_text(x.as_py()) for x in batch.column(2)]
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), batch.column(1), pa.array(texts, pa.string()), pa.array([len(x) for x in texts], pa.int64())],
                ["page_id", "url", "text", "n_chars"],
            )

    return pages.select(F.col("page_id").cast("long").alias("page_id"), "url", "html").mapInArrow(run, "page_id long, url string, text string, n_chars long")
