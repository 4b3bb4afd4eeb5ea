"""Main text of web pages by the distribution of text over line blocks.

Markup is stripped into lines, one per block element, in page order. Every line has a weight:
its characters outside links, nothing if it is mostly links, and a bonus if its element is one
of prose. Lines of elements that never hold the article (menus, footers, adverts, forms,
comments ...) weigh nothing, and if the page names its article (``article``, ``main``), so do
all lines outside it. Weights are summed over sliding windows of ``WINDOW`` lines: text starts
where that sum surges and ends where it dives, and the lines with a weight between the two
points are kept. The thresholds are the same on every page but for pages with very little
text, whose own densest window lowers them.

Elements are read as browsers do: an open ``p``, ``li``, ``td`` ... ends where the next one or
its container does, end tags without a start are ignored, and unclosed elements end with their
container or the page. A class, id or role marks boilerplate only by a whole name, such as
``sidebar`` or ``cookie-notice``, never by a part of one (``post-with-sidebar``). If nothing
is left that way, the page is read again without such marks, and at last without the tags
that hold boilerplate.

Defined results: null, empty and text-free pages give the empty string; a cut-off tag is
dropped; very long pages are read whole, in time linear in their length; repeated rows give
equal texts; an empty table gives no rows; columns other than page_id, url and html are not
read, whatever their names.
"""

from __future__ import annotations

import html as refs
import re
from collections import Counter
from collections.abc import Iterable
from dataclasses import dataclass
from functools import partial

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import map_batches

WINDOW = 3
#: Windowed weight at which text starts; it ends under a part of that.
SURGE = 80
DIVE = 4
#: Of runs without prose, those with less than this share of the heaviest run's weight are no article.
SHARE = 0.3
#: A line with a larger share of its characters in links is a list of links.
LINKS = 0.6
#: Elements whose text is not read, that never hold the article, that end a line, without content.
UNREAD = frozenset("script style noscript template svg math head title iframe object textarea select option canvas audio video datalist".split())
ASIDE = frozenset("nav header footer aside form menu dialog button fieldset".split())
LINE = frozenset(
    "address article aside blockquote body center dd details dialog div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 "
    "header hr html legend li main menu nav ol p pre section summary table tbody td tfoot th thead tr ul".split()
)
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
MAIN = frozenset(("article", "main"))
PROSE = frozenset("p h1 h2 h3 h4 h5 h6 blockquote pre".split())
#: Which open elements a start tag ends, and the containers past which it does not look.
ENDS = {
    **dict.fromkeys(LINE - frozenset("body html li dd dt td th tr tbody thead tfoot legend summary figcaption".split()), ("p",)),
    "li": ("p", "li"), "dt": ("p", "dt", "dd"), "dd": ("p", "dt", "dd"), "td": ("p", "td", "th"), "th": ("p", "td", "th"),
    "tr": ("p", "td", "th", "tr"), "tbody": ("p", "td", "th", "tr", "tbody", "thead", "tfoot"), "tfoot": ("p", "td", "th", "tr", "tbody", "thead"),
}
WALLS = {"p": frozenset("table td th button".split()), "li": frozenset(("ul", "ol", "menu", "table")), "dt": frozenset(("dl",)), "dd": frozenset(("dl",))}
TABLE = frozenset(("table",))
#: Names in class, id or role of boilerplate; the first also mark paragraphs, the others only containers.
NOISE = frozenset(
    "ad ads advert adverts advertisement advertising advertorial breadcrumb breadcrumbs comment comments commentlist consent cookie cookies copyright disqus gdpr "
    "newsletter notice pagination popup promo promotion related replies respond share sharing signup social sponsor sponsored subscribe".split()
)
FRAME = frozenset("banner footer header masthead menu modal nav navbar navigation search sidebar toolbar widget widgets complementary contentinfo".split())
#: Parts that may stand beside such a name in a compound one.
PLAIN = frozenset("area bar block bottom box button buttons center container form global inner item items left link links list main panel primary right secondary section site slot thread top wrap wrapper".split())
_TAG = re.compile(
    r"<!--.*?(?:-->|\Z)|<!\[CDATA\[.*?(?:\]\]>|\Z)|<[!?][^>]*(?:>|\Z)"
    r"|<(?P<end>/?)(?P<name>[a-zA-Z][^\s/>]*)(?P<attrs>(?:[^>\"']|\"[^\"]*(?:\"|\Z)|'[^']*(?:'|\Z))*+)(?P<shut>>|\Z)|</?\Z",
    re.S,
)
_MARK = re.compile(r"\b(?:class|id|role)\s*=\s*(\"[^\"]*\"|'[^']*'|[^\s>\"']+)", re.I)
_PARTS = re.compile(r"[-_]+")


@dataclass
class Line:
    """A line's text, how many of its characters stand in links, whether it lies in a named article, and the element it is of."""

    text: str
    linked: int
    named: bool
    block: str

    @property
    def prose(self) -> bool:
        return self.block in PROSE or self.named and self.block in MAIN

    @property
    def weight(self) -> int:
        if not self.text:
            return 0
        bare = max(0, len(self.text) - self.linked)
        if self.prose:
            return bare + SURGE
        return bare if self.linked <= LINKS * len(self.text) else 0


def marked(attrs: str, names: Iterable[str]) -> bool:
    """True if a whole class, id or role is one of ``names``, alone or with plain parts beside it."""
    for value in _MARK.findall(attrs):
        for token in value.strip("\"'").lower().split():
            parts = [x for x in _PARTS.split(token) if x]
            if any(x in names for x in parts) and all(x in names or x in NOISE or x in FRAME or x in PLAIN for x in parts):
                return True
    return False


class _Reader:
    """The open elements of a page and the lines read so far."""

    def __init__(self, strict: int) -> None:
        #: 2: tags and marks show boilerplate, 1: tags, 0: nothing does.
        self.strict = strict
        self.lines: list[Line] = []
        self.parts: list[str] = []
        self.stack: list[str] = []
        self.open: Counter[str] = Counter()
        self.linked = self.links = self.inside = 0
        #: Open elements outside the boilerplate now skipped, if any is.
        self.skip = -1

    def text(self, text: str) -> None:
        if self.skip < 0 and text:
            self.parts.append(text)
            if self.links:
                self.linked += len(" ".join(refs.unescape(text).split()))

    def flush(self) -> None:
        if self.skip >= 0:
            if self.stack[self.skip] in LINE:
                self.lines.append(Line("", 0, False, ""))
            return
        text = " ".join(refs.unescape("".join(self.parts)).split())
        self.lines.append(Line(text, self.linked, self.inside > 0, self.stack[-1] if self.stack else ""))
        self.parts.clear()
        self.linked = 0

    def close(self, depth: int) -> None:
        """Ends all open elements from ``depth`` on."""
        self.flush()
        for name in self.stack[depth:]:
            self.inside -= name in MAIN
            self.open[name] -= 1
        del self.stack[depth:]
        if self.links > depth:
            self.links = 0
        if 0 <= depth <= self.skip:
            self.skip = -1

    def push(self, name: str) -> None:
        self.stack.append(name)
        self.open[name] += 1
        self.inside += name in MAIN

    def noise(self, name: str, attrs: str) -> bool:
        if name == "header" and self.inside:
            return False  # an article's own header holds its title
        if self.strict and name in ASIDE:
            return True
        return self.strict > 1 and (marked(attrs, NOISE) or name not in PROSE and name not in MAIN and marked(attrs, FRAME))

    def start(self, name: str, attrs: str) -> None:
        for kind in ENDS.get(name, ()):
            if not self.open[kind]:
                continue
            walls = WALLS.get(kind, TABLE)
            for depth in range(len(self.stack) - 1, -1, -1):
                if self.stack[depth] == kind:
                    self.close(depth)
                    break
                if self.stack[depth] in walls:
                    break
        if self.skip < 0 and name not in ("html", "body") and self.noise(name, attrs):
            if name in LINE:
                self.flush()
            self.skip = len(self.stack)
            self.push(name)
        elif name in LINE:
            self.flush()
            self.push(name)
        elif self.skip >= 0 and name == self.stack[self.skip]:
            self.push(name)  # an inline element in one of its own name
        elif name == "a":
            self.links = len(self.stack) + 1

    def end(self, name: str) -> None:
        if name == "a":
            self.links = 0
        if self.open[name]:
            self.close(len(self.stack) - 1 - self.stack[::-1].index(name))


def lines_of(page: str, strict: int = 2) -> list[Line]:
    """The page's lines in order; those of elements that never hold the article are left as empty ones."""
    r, at = _Reader(strict), 0
    while at < len(page):
        m = _TAG.search(page, at)
        r.text(page[at : m.start() if m else len(page)])
        if not m:
            break
        at, name = m.end(), (m["name"] or "").lower()
        if not name:
            continue
        if m["end"]:
            r.end(name)
        elif name in UNREAD:
            # raw text up to its own end tag, whatever looks like markup in it
            stop = re.compile(rf"</{re.escape(name)}\s*>", re.I).search(page, at)
            if name == "head" and not stop:
                continue
            at = stop.end() if stop else len(page)
        elif name == "br":
            r.text(" ")
        elif name == "hr":
            r.flush()
        elif name not in VOID:
            r.start(name, m["attrs"])
    r.close(0)
    return r.lines


def window_sums(weights: list[int], window: int = WINDOW) -> list[int]:
    """Each line's weight and that of the lines after it, ``window`` in all."""
    out, now = [0] * len(weights), 0
    for i in range(len(weights) - 1, -1, -1):
        now += weights[i] - (weights[i + window] if i + window < len(weights) else 0)
        out[i] = now
    return out


def spans(weights: list[int], surge: int, dive: int, window: int = WINDOW) -> list[tuple[int, int]]:
    """Half-open runs of lines from a surge of the windowed sum, at a line with a weight, to where it dives."""
    found, start = [], -1
    for i, s in enumerate(window_sums(weights, window)):
        if start < 0 and weights[i] and s >= surge:
            start = i
        elif start >= 0 and s < dive:
            found.append((start, i))
            start = -1
    return [*found, (start, len(weights))] if start >= 0 else found


def kept_lines(lines: list[Line]) -> list[Line]:
    """The lines between surges and dives."""
    named = any(x.named and x.text for x in lines)
    weights = [x.weight if x.named or not named else 0 for x in lines]
    surge = max(1, min(SURGE, max(window_sums(weights), default=0) // 2))
    runs = spans(weights, surge, max(1, surge // DIVE))
    most = max((sum(weights[a:b]) for a, b in runs), default=0)
    runs = [(a, b) for a, b in runs if sum(weights[a:b]) >= SHARE * most or any(lines[i].prose and weights[i] for i in range(a, b))]
    return [lines[i] for a, b in runs for i in range(a, b) if weights[i]]


def main_text(page: str | None) -> str:
    """The article's blocks, joined by an empty line."""
    for strict in (2, 1, 0):
        if found := kept_lines(lines_of(page or "", strict)):
            return "\n\n".join(x.text for x in found)
    return ""


def _work():
    def of(batch: pa.RecordBatch) -> pa.RecordBatch:
        texts = [main_text(p) for p in batch.column("html").to_pylist()]
        return pa.RecordBatch.from_arrays(
            [batch.column("page_id"), batch.column("url"), pa.array(texts, pa.string()), pa.array(map(len, texts), pa.int64())],
            ["page_id", "url", "text", "n_chars"],
        )

    return of


def extract(pages: DataFrame) -> DataFrame:
    """page_id, url, text and n_chars (code points) of every page."""
    kept = pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), F.col("html").cast("string").alias("html"))
    return map_batches(kept, partial(_work), "page_id long, url string, text string, n_chars long")
