"""Main text of web pages: parser events to lines, text-to-tag ratios, smoothing, clustering.

The parser's events cut a page into lines, one per block, and a tree of containers. What never is
article text by its element or name (menus, forms, scripts, asides, notices, adverts, reader
comments) is left out. Every other line gets a text-to-tag ratio, a Gaussian smooths the ratios in
page order, and a two-means threshold parts content lines from the rest. The region is found by
walking down from the page's root into the container that holds the content lines' text, as long
as one does; elements that name an article settle which of several it is. Where no single container holds
the content, its parts that hold content lines are taken together. All lines of the region are
the text, short ones too.
"""

from __future__ import annotations

import math
import re
from collections.abc import Iterator
from html.parser import HTMLParser

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import ship

# Element names by what they mean for text, and the words that name page furniture.
NEVER = frozenset("script style noscript template head title nav footer aside form button select textarea option iframe svg canvas object menu dialog audio video map fieldset".split())
CONTAINERS = frozenset("html body main article section div header footer nav aside form ul ol dl table tbody thead tfoot tr td figure blockquote details center menu dialog fieldset select head button noscript template svg".split())
BLOCKS = CONTAINERS | frozenset("p h1 h2 h3 h4 h5 h6 li dt dd th pre address caption figcaption summary hr br option title textarea legend".split())
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
LAYOUT = frozenset("html body main article section div center table tbody tr td".split())
REGIONS = frozenset(("article", "main"))
ROLES = frozenset("navigation banner contentinfo complementary search form dialog alertdialog alert menu menubar toolbar tablist status note".split())
# Words that name furniture wherever they stand in a name, inside an article too.
ALWAYS = frozenset("ad ads advert adverts advertisement advertisements advertising adsense sponsored cookie cookies consent gdpr sidebar sidebars navbar breadcrumb breadcrumbs newsletter comment comments commentlist disqus outbrain taboola paywall tagcloud".split())
# Words that do so only where the whole name is made of them and of plain words; the first kind inside an article as well.
INNER = frozenset("sponsor sponsors promo promotion promoted banner menu menus notice notices alert popup modal overlay share sharing social related recommended subscribe subscription signup login toolbar widget widgets pagination pager skip hidden feedback teaser teasers nav navigation".split())
OUTER = frozenset("aside footer masthead topbar header respond reply replies discussion".split())
PLAIN = frozenset("site page top bottom left right main inner outer box block wrapper wrap container section area list item items links link bar buttons icons post posts article articles content js is the and".split())
NEGATED = frozenset("has with no without not hide show".split())
COMMENTS = frozenset("comment comments commentlist disqus".split())
_WORD = re.compile(r"[a-z]+")
_CAMEL = re.compile(r"([a-z])([A-Z])")
_UNSEEN = re.compile(r"display\s*:\s*none|visibility\s*:\s*hidden", re.I)

#: Weight of a line below the threshold, share of a container's weight that a child must hold to stand for it.
FAINT, SHARE = 0.1, 0.8


def names_furniture(names: str, inside: bool) -> int:
    """1 if a class or id attribute names page furniture, 2 if reader comments, else 0; ``inside`` an article fewer names do."""
    for name in names.split():
        words = _WORD.findall(_CAMEL.sub(r"\1 \2", name).lower())
        if not words or words[0] in NEGATED:
            continue
        if COMMENTS.intersection(words):
            return 2
        if ALWAYS.intersection(words):
            return 1
        told = INNER if inside else INNER | OUTER
        content = () if inside else ("article", "articles", "post", "posts", "content")
        if told.intersection(words) and all(w in told or (w in PLAIN and w not in content) for w in words):
            return 1
    return 0


class _Lines(HTMLParser):
    """Collects ``lines``: (text, tags since the line before, container, heading) of blocks outside page furniture.

    Containers are numbered in page order with their parent's number, so a line stores one number
    however deep it lies; counters say what is open, so no event walks the stack but to close.
    """

    def __init__(self, by_name: bool = True):
        super().__init__(convert_charrefs=True)
        self.by_name = by_name
        self.lines: list[tuple[str, int, int, bool]] = []
        self.kinds, self.parents = ["#root"], [0]
        self.open: list[tuple[str, int, int]] = []  # name, number, 0 shown / 1 left out / 2 reader comments
        self.counts: dict[str, int] = {}
        self.states = [0, 0, 0]
        self.buf: list[str] = []
        self.tags = 0
        self.block = ""

    def _flush(self) -> None:
        if self.buf:
            text = " ".join("".join(self.buf).split())
            self.buf.clear()
            if text:
                self.lines.append((text, self.tags, self.open[-1][1] if self.open else 0, self.block == "h1"))
                self.tags = 0

    def _state(self, tag: str, attrs) -> int:
        if tag in NEVER:
            return 1
        inside = bool(self.counts.get("article") or self.counts.get("main"))
        if tag == "header" and not inside:
            return 1
        for k, v in attrs:
            if k in ("hidden", "inert") or k == "aria-hidden" and v == "true":
                return 1
            if not v:
                continue
            if k == "role" and v.lower() in ROLES:
                return 1
            if k == "style" and _UNSEEN.search(v):
                return 1
            if k in ("class", "id") and tag not in ("html", "body", "main") and self.by_name:
                got = names_furniture(v, inside)
                if got and (tag != "article" or got == 2):
                    return got
        return 0

    def _close_to(self, at: int) -> None:
        for tag, _, state in self.open[at:]:
            self.counts[tag] -= 1
            self.states[state] -= 1
        del self.open[at:]

    def handle_starttag(self, tag, attrs):
        self.tags += 1
        if tag in BLOCKS:
            self._flush()
            self.block = tag
        if tag in VOID:
            return
        state = self._state(tag, attrs)
        if tag in REGIONS and not state and self.states[1] and not self.states[2]:
            # furniture that was never closed ends where the article begins
            self._close_to(next(i for i, (_, _, s) in enumerate(self.open) if s))
        if tag in CONTAINERS or state:
            self.parents.append(self.open[-1][1] if self.open else 0)
            self.kinds.append(tag)
            self.open.append((tag, len(self.kinds) - 1, state))
            self.counts[tag] = self.counts.get(tag, 0) + 1
            self.states[state] += 1

    def handle_startendtag(self, tag, attrs):
        self.tags += 1
        if tag in BLOCKS:
            self._flush()

    def handle_endtag(self, tag):
        self.tags += 1
        if tag in BLOCKS:
            self._flush()
            self.block = ""
        if self.counts.get(tag):
            at = len(self.open) - 1
            while self.open[at][0] != tag:
                at -= 1
            self._close_to(at)

    def handle_data(self, data):
        if not (self.states[1] or self.states[2]):
            self.buf.append(data)

    def finish(self) -> None:
        self.close()
        self._flush()


def ratios(lines: list[tuple[str, int, int, bool]]) -> list[float]:
    """Text-to-tag ratio of each line: characters for each tag since the line before."""
    return [len(line[0]) / max(1, line[1]) for line in lines]


def smooth(values: list[float], sigma: float = 1.0) -> list[float]:
    """Gaussian smoothing with a radius of two sigma, renormalised at the ends."""
    r = max(1, math.ceil(2 * sigma))
    w = [math.exp(-(d * d) / (2 * sigma * sigma)) for d in range(-r, r + 1)]
    out = []
    for i in range(len(values)):
        lo, hi = max(0, i - r), min(len(values), i + r + 1)
        k = w[lo - i + r : hi - i + r]
        out.append(sum(a * b for a, b in zip(k, values[lo:hi], strict=True)) / sum(k))
    return out


def threshold(values: list[float], rounds: int = 20) -> float:
    """The middle between the two means that one-dimensional two-means settles on."""
    lo, hi = min(values), max(values)
    for _ in range(rounds):
        mid = (lo + hi) / 2
        a, b = [v for v in values if v <= mid], [v for v in values if v > mid]
        if not b:
            return lo
        nlo, nhi = sum(a) / len(a) if a else lo, sum(b) / len(b)
        if (nlo, nhi) == (lo, hi):
            break
        lo, hi = nlo, nhi
    return (lo + hi) / 2


def region(p: _Lines, content: list[bool]) -> list[bool]:
    """Which lines belong to the content region, given which lines the clustering took for content."""
    n = len(p.kinds)
    own, sub, holds = [0.0] * n, [0.0] * n, [False] * n
    for (text, _, at, _), yes in zip(p.lines, content, strict=True):
        own[at] += len(text) * (1.0 if yes else FAINT)
        holds[at] = holds[at] or yes
    children: list[list[int]] = [[] for _ in range(n)]
    for i in range(n - 1, 0, -1):  # a child's number is above its parent's
        sub[i] += own[i]
        sub[p.parents[i]] += sub[i]
        holds[p.parents[i]] = holds[p.parents[i]] or holds[i]
        if p.kinds[i] in LAYOUT and sub[i]:
            children[p.parents[i]].append(i)
    sub[0] += own[0]
    at, above = 0, []
    while p.kinds[at] != "article" and children[at]:
        best = max(children[at], key=lambda i: (sub[i], -i))
        named = p.kinds[best] in REGIONS and sub[best] >= own[at]
        if not named and (sub[best] < SHARE * sub[at] or p.kinds[at] == "main"):
            break
        above.append(at)
        at = best
    # with no single container for the content, the ones that hold none of its lines go
    out = {c for c in children[at] if not holds[c]} if p.kinds[at] not in REGIONS else set()
    inside, bare = [False] * n, [False] * n
    inside[at] = True
    for i in range(at + 1, n):
        inside[i] = inside[p.parents[i]] and i not in out
    for i in above:
        bare[i] = True
    first = next((k for k, line in enumerate(p.lines) if inside[line[2]]), 0)
    return [inside[c] or (heading and bare[c] and k < first) for k, (_, _, c, heading) in enumerate(p.lines)]


def main_text(html: str | None, sigma: float = 1.0) -> str:
    """The article's text, blocks in page order joined by one space; empty for null or text-free pages.

    Should names of classes leave nothing of a page, they are not believed.
    """
    if not html:
        return ""
    for by_name in (True, False):
        p = _Lines(by_name)
        p.feed(html)
        p.finish()
        if p.lines:
            break
    else:
        return ""
    smoothed = smooth(ratios(p.lines), sigma)
    cut = threshold(smoothed)
    kept = region(p, [s >= cut for s in smoothed])
    return " ".join(line[0] for line, yes in zip(p.lines, kept, strict=True) if yes)


OUT = T.StructType([T.StructField("page_id", T.LongType()), T.StructField("url", T.StringType()), T.StructField("text", T.StringType()), T.StructField("n_chars", T.LongType())])


def extract(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", html_col: str = "html") -> DataFrame:
    """``page_id, url, text, n_chars`` of every row, from the whole html.

    Null or empty html, and pages without text, give the empty string and 0; null ids and urls
    pass through; repeated rows each come back; other columns are not read; one page is in memory
    at a time, which takes room and time in proportion to its length, however deep its elements nest.
    """
    ship(pages.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for at in range(0, b.num_rows, 512):
                part = b.slice(at, 512)
                text = [main_text(h.as_py()) for h in part.column(2)]
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(1), pa.array(text, pa.string()), pa.array([len(t) for t in text], pa.int64())], names=OUT.names)

    rows = pages.select(F.col(id_col).cast("long").alias("page_id"), F.col(url_col).cast("string").alias("url"), F.col(html_col).cast("string").alias("html"))
    return rows.mapInArrow(run, OUT)
