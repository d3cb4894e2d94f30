"""Main text of a web page by line-block distribution.

Markup is stripped into lines, one for each block element. A line's weight is its text outside links; lines of what surrounds an
article by its nature (menus, headers, footers, sidebars, notices, adverts, forms, comments) stay as one line
without text and weight for each element. A block is a sliding window of lines. Text surges where a window's sum reaches a threshold, from the line
on after which no window was empty, and dives where a whole window is empty again. The main text lies between the first surge and
the last dive of any weight beside the heaviest; everything between is kept, so short paragraphs and headings stay.

What surrounds is told by element, or by class and id for an element that holds no main part, not the largest article and little of
the page's unlinked text (comments may be longer), and never for headings and paragraphs. Where the marks of an article hold most of the
text between surge and dive, lines outside of them lose their weight, and surge and dive are located once more; marks of
lighter parts, such as teasers, change nothing, and a page without marks is read by its line blocks alone.

Defined cases: null or empty html gives an empty text, an empty table an empty result; on a page without a surge the heaviest
window is one, the first of equal ones; unclosed elements end where their parent ends, and an unclosed tag or comment ends the
page; a very long page is read whole in one pass; repeated rows are extracted alike; other columns pass through, and columns named ``text`` or ``n_chars`` are replaced.
"""

from __future__ import annotations

import html
import re
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from mediarel.llm import common

#: Lines of a window, and the window sum (characters) at which text surges.
WINDOW = 3
SURGE = 80
#: Text between a surge and a dive counts beside the heaviest from this share of its weight on.
BESIDE = 1 / 4

#: Element names of HTML by their role here.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style textarea title noscript template iframe svg math object canvas xmp".split())
SURROUND = frozenset("nav footer aside form menu dialog select button fieldset noembed noframes head".split()) | RAW
INLINE = frozenset(
    "a abbr acronym b bdi bdo big cite code data del dfn em font i img ins kbd label mark nobr q rp rt ruby s samp small span strike strong sub sup time tt u var wbr".split()
)
ARTICLE = frozenset(("article", "main"))
ENDS_PARAGRAPH = frozenset(
    "address article aside blockquote center details dialog dir div dl fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr main menu nav ol p pre section table ul".split()
)
SAME_ENDS = frozenset("li dt dd tr td th option".split())
HEADINGS = frozenset("h1 h2 h3 h4 h5 h6".split())
#: Elements that no class or id takes out.
KEPT = frozenset(("html", "body", "p", *ARTICLE)) | HEADINGS
#: Words in a class, id or role that mark what surrounds an article, alone or in any compound.
STRONG = frozenset(
    "ads advert advertisement adverts banner sponsored promo gdpr popup modal navbar breadcrumb breadcrumbs sidebar widget footer masthead topbar toolbar "
    "sharing recommended recommendations newsletter subscribe signup disqus pagination pager complementary contentinfo".split()
)
#: Words that also name subjects: they mark alone and in compounds of nothing but such words and ``FURNITURE``.
WEAK = frozenset(
    "ad advertising sponsor promotion cookie cookies consent notice notices alert overlay nav navigation menu side aside foot share social related "
    "subscription login comment comments replies respond reader skip search".split()
)
#: A header holds a heading inside an article, so this word marks only outside.
HEADER = "header"
FURNITURE = frozenset(
    "area article articles bar block body bottom box btn button buttons col column container content entry fixed form global group holder icon icons inner items item label left "
    "link links list main mobile module outer page panel pane post posts primary region right row secondary section site slot sticky stories thread title top unit wrap wrapper".split()
)
#: Before a word these tell of a page that has such a part, not of the part.
WRAPPER = frozenset("has have with without no not hide hides show shows is layout page".split())
#: Comments may be longer than the article itself.
COMMENTS = frozenset("comment comments replies respond disqus".split())
#: The largest share of a page's unlinked text that a class or id may take out; what cannot surge is little beside other text.
LITTLE = 1 / 3
_TOKEN = re.compile(r"<!--.*?(?:-->|\Z)|<[!?][^>]*(?:>|\Z)|<(/?)([a-zA-Z][^\s>/]*)((?:[^>\"']++|\"[^\"]*\"|'[^']*'|[\"'])*+)(?:>|\Z)", re.S)
_ATTRIBUTE = re.compile(r"([^\s=\"'/]+)(?:\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"']+)))?")
_NOT_SHOWN = re.compile(r"(?:^|[;\s])display\s*:\s*none", re.I)
_UNQUOTED_SLASH = re.compile(r"=\s*[^\s\"'>]*/\Z")


@dataclass
class Line:
    """A block of text, how much of it stands in links, and the number of the outermost mark of either kind around it (0: none)."""

    text: str
    linked: int
    article: int
    main: int

    @property
    def weight(self) -> int:
        return len(self.text) - self.linked


@dataclass
class _Open:
    name: str
    dropped: bool
    article: int
    main: int
    region: int


@dataclass
class _Region:
    """An element that may surround an article: it goes unless it holds the article or much of the text."""

    parent: int
    comments: bool
    weight: int = 0
    holds: bool = False


def _attributes(text: str) -> dict[str, str]:
    found: dict[str, str] = {}
    for m in _ATTRIBUTE.finditer(text):
        found.setdefault(m[1].lower(), html.unescape(next((v for v in m.groups()[1:] if v is not None), "")))
    return found


def _hidden(found: dict[str, str]) -> bool:
    return (
        found.get("hidden", "until-found").strip().lower() != "until-found"
        or found.get("aria-hidden", "").strip().lower() == "true"
        or bool(_NOT_SHOWN.search(found.get("style", "")))
    )


def marks_surroundings(value: str, inside_article: bool = False) -> set[str]:
    """Words of a class, id or role value by which it marks what surrounds an article."""
    marking: set[str] = set()
    for token in value.lower().split():
        parts = [x for x in re.split(r"[_-]+", token) if x and not x.isdigit()]
        weak = {x for x in parts if x in WEAK or x == HEADER and not inside_article}
        strong = {x for k, x in enumerate(parts) if x in STRONG and not (k and parts[k - 1] in WRAPPER)}
        if weak and all(x in weak or x in STRONG or x in FURNITURE for x in parts):
            marking |= weak
        marking |= strong
    return marking


class _Reader:
    """One pass over the tags of a page. ``lenient`` trusts nothing but scripts and the like, menus and footers by their name alone."""

    def __init__(self, lenient: bool):
        self.lenient = lenient
        self.found: list[tuple[list[tuple[str, bool, int]], int, int]] = []
        self.pieces: list[tuple[str, bool, int]] = []
        self.count = dict.fromkeys(ARTICLE, 0)
        self.in_link = False
        self.taken = 0
        self.n_taken = 0
        self.opened: list[_Open] = []
        self.held: Counter[str] = Counter()
        self.regions: list[_Region] = [_Region(0, False)]
        self.around: dict[tuple[str, int], int] = {}

    @property
    def last(self) -> _Open:
        return self.opened[-1] if self.opened else _Open("", False, 0, 0, 0)

    def end_line(self) -> None:
        if self.pieces:
            self.found.append((self.pieces, self.last.article, self.last.main))
            self.pieces = []

    def add(self, text: str) -> None:
        last = self.last
        if not last.dropped:
            self.pieces.append((text, self.in_link, last.region))
        elif not text.isspace():
            # What is taken out leaves an empty line, one for each element.
            self.taken += 0 if self.in_link else len(text)
            self.pieces.append(("", self.n_taken, last.region))

    def close(self, name: str) -> None:
        """End the innermost open element of this name and what is open inside it."""
        if self.held[name]:
            while self.opened:
                last = self.opened.pop()
                self.held[last.name] -= 1
                if last.name == name:
                    break

    def surrounds(self, name: str, attributes: str, inside_article: bool) -> tuple[bool, bool, set[str]]:
        """(goes in any case, goes if it is small, words that mark it)."""
        named = name in SURROUND or name == "header" and not inside_article
        found = _attributes(attributes) if attributes and not attributes.isspace() and name not in ("html", "body") else {}
        hidden = _hidden(found)
        words = set().union(*(marks_surroundings(found.get(k, ""), inside_article) for k in ("class", "id", "role")))
        sure = name in RAW or name in ("nav", "footer", "head")
        return sure or not self.lenient and (named or hidden), bool(named or hidden or words and name not in KEPT), words

    def start(self, name: str, attributes: str) -> None:
        if name in ENDS_PARAGRAPH:
            self.close("p")
        elif name in SAME_ENDS and self.opened and self.opened[-1].name == name:
            self.close(name)
        if name in VOID or attributes.rstrip().endswith("/"):
            return
        last = self.last
        article, main, region = last.article, last.main, last.region
        gone, small, words = (True, False, set()) if last.dropped else self.surrounds(name, attributes, bool(article or main))
        if gone and not last.dropped:
            self.n_taken += 1
        if not gone and small:
            self.regions.append(_Region(region, bool(words & COMMENTS)))
            region = len(self.regions) - 1
        elif name in INLINE and not gone:
            return
        if name in ARTICLE and not gone and not (article if name == "article" else main):
            self.count[name] += 1
            article, main = (self.count[name], main) if name == "article" else (article, self.count[name])
            # A marked article, as a comment or a teaser may be, keeps nothing around it.
            if not words:
                self.around[name, self.count[name]] = region
        self.opened.append(_Open(name, gone, article, main, region))
        self.held[name] += 1

    def gone(self) -> set[int]:
        """Regions that go: not the one with the largest article, a main part or much of the unlinked text."""
        total, marked = 0, Counter()
        for pieces, article, main in self.found:
            for text, linked, region in pieces:
                weight = 0 if linked else len("".join(text.split()))
                total += weight
                marked["article", article] += weight
                marked["main", main] += weight
                while region:
                    self.regions[region].weight += weight
                    region = self.regions[region].parent
        largest = max((k for k in self.around if k[0] == "article"), key=lambda k: marked[k], default=None)
        for mark, region in self.around.items():
            while region and (mark == largest or mark[0] == "main"):
                self.regions[region].holds = True
                region = self.regions[region].parent
        out: set[int] = set()
        for k, r in enumerate(self.regions[1:], 1):
            outside = total - r.weight
            small = r.weight <= LITTLE * total or r.weight < SURGE and outside or r.comments and outside >= SURGE
            if r.parent in out or small and not r.holds:
                out.add(k)
        return out

    def lines(self) -> list[Line]:
        gone, made, before = self.gone(), [], None
        for pieces, article, main in self.found:
            left = [x for x in pieces if x[2] not in gone and x[0]]
            text = " ".join(html.unescape("".join(x[0] for x in left)).split())
            if text:
                made.append(Line(text, min(sum(len(x[0]) for x in left if x[1]), len(text)), article, main))
                before = None
            elif out := [x for x in pieces if not x[0] or x[2] in gone and not x[0].isspace()]:
                _, number, region = out[-1]
                while self.regions[region].parent in gone:
                    region = self.regions[region].parent
                # All lines of one element that is taken out are one empty line.
                element = (region, 0) if region in gone else (0, number)
                if element != before:
                    made.append(Line("", 0, article, main))
                before = element
        return made


def lines(page: str) -> list[Line]:
    """Text lines of a page in order; what surrounds an article leaves empty ones."""
    return read_page(page).lines()


def read_page(page: str, lenient: bool = False) -> _Reader:
    """One pass over a page. ``lenient`` takes out forms, sidebars and hidden parts only if they are small."""
    reader, at = _Reader(lenient), 0
    while at < len(page):
        m = _TOKEN.search(page, at)
        if m is None:
            reader.add(page[at:])
            break
        if m.start() > at:
            reader.add(page[at : m.start()])
        at = m.end()
        if m[2] is None:
            continue
        name = m[2].lower()
        if name not in INLINE:
            reader.end_line()
        if m[1]:
            if name == "a":
                reader.in_link = False
            reader.close(name)
        elif name in RAW:
            if name in ("svg", "math") and m[3].endswith("/") and not _UNQUOTED_SLASH.search(m[3]):
                continue
            # Their content is no markup: it goes on to their own end tag.
            ends = re.compile(rf"</{re.escape(name)}(?=[\s/>]|\Z)[^>]*(?:>|\Z)", re.I).search(page, at)
            at = ends.end() if ends else len(page)
        else:
            if name == "a":
                reader.in_link = True
            reader.start(name, m[3])
    reader.end_line()
    return reader


def surges(weights: list[int], window: int = WINDOW, surge: int = SURGE) -> list[tuple[int, int, int]]:
    """(start, end, weight) of the lines [start, end) between a surge and its dive, in order."""
    found: list[tuple[int, int, int]] = []
    total, first, last, weight, heavy = sum(weights[:window]), -1, -1, 0, False
    for i, w in enumerate(weights):
        if w:
            first, last, weight = i if first < 0 else first, i, weight + w
        heavy = heavy or total >= surge
        total += (weights[i + window] if i + window < len(weights) else 0) - w
        if not total and first >= 0:
            # The window that starts at the next line is empty.
            if heavy:
                found.append((first, last + 1, weight))
            first, weight, heavy = -1, 0, False
    return found


def main_span(weights: list[int], window: int = WINDOW, surge: int = SURGE, beside: float = BESIDE) -> tuple[int, int]:
    """Lines [start, end) between the first surge and the last dive of weight; the heaviest window surges if no other does."""
    found = surges(weights, window, surge)
    if not found and any(weights):
        found = surges(weights, window, max(sum(weights[i : i + window]) for i in range(len(weights))))[:1]
    if not found:
        return 0, 0
    most = max(weight for _, _, weight in found)
    kept = [x for x in found if x[2] >= beside * most]
    return kept[0][0], kept[-1][1]


def _read(found: list[Line]) -> tuple[str, bool]:
    """Text between surge and dive, located again within the articles, else the main parts, that hold most of it, and whether one does."""
    start, end = main_span([x.weight for x in found])
    span, marked = found[start:end], False
    for own in (lambda x: x.article, lambda x: x.main):
        chosen = {own(x) for x in span if own(x)}
        if 2 * sum(x.weight for x in span if own(x)) > sum(x.weight for x in span):
            found = [x if own(x) in chosen else Line("", 0, 0, 0) for x in found]
            start, end = main_span([x.weight for x in found], beside=0)
            marked = True
            break
    return " ".join(x.text for x in found[start:end] if x.text), marked


def extract(page: str | None) -> str:
    """Main text of a page: its blocks joined by one space."""
    if not page:
        return ""
    reader = read_page(page)
    strict = reader.lines()
    text, marked = _read(strict)
    surged = bool(surges([x.weight for x in strict]))
    if surged and (marked or reader.taken <= len(text)):
        return text
    # An article may stand in a form or another part that seems to surround one.
    lenient = read_page(page, lenient=True).lines()
    other, marked = _read(lenient)
    if marked if surged else surges([x.weight for x in lenient]) or not text:
        return other
    return text


def with_main_text(pages: DataFrame, column: str = "html") -> DataFrame:
    """``pages`` with ``text`` and ``n_chars``, replacing columns of these names."""
    kept = pages.drop("text", "n_chars")

    def run(batches: Iterator[pa.Array]) -> Iterator[pa.Array]:
        for batch in batches:
            yield pa.array([extract(p) for p in common.each_text_of(batch)], pa.string())

    run = F.arrow_udf(run, "string")
    return kept.withColumn("text", run(F.col(column))).withColumn("n_chars", F.length("text").cast("long"))


def op8_html_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    return with_main_text(common.table(spark, sf_dir, "pages")).select("page_id", "url", "text", "n_chars")
