"""Main text of web pages from a streaming parser's events.

The standard library's parser emits tags and text; every block of text becomes a line with
its text-to-tag ratio, link text not counted. What the parser knows of a line's place weighs
the ratio: nothing inside scripts, menus, forms and the like counts, and an element named
after an advert, a notice or reader comments counts little. The weighed ratios are smoothed
with a Gaussian and split by a threshold (one standard deviation, the mean at most): the
lines above it are content. Content lines select regions: the other lines of their own
element, what lies between them in sibling elements, and the headings that lead to them. Where
article elements hold at least half of the content, they are the region; otherwise they join it.

Defined cases: null html is empty and gives empty text; pages without any line that counts
give the whole body; repeated rows stay repeated; an empty table gives no rows; other columns
are ignored.
"""

from __future__ import annotations

import math
import re
from html.parser import HTMLParser
from typing import NamedTuple

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vecspark.llm.common import arrow_rows, slices

# Element names and the words that name what is not content.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
BLOCKS = frozenset("address article aside blockquote body caption center dd details dialog dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr html legend li main menu nav ol p pre section summary table tbody td tfoot th thead tr ul".split())
HOLDERS = frozenset("html body main article section div td center".split())
DROPPED = frozenset("head script style noscript template nav footer aside form button select option textarea iframe svg canvas object menu dialog title audio video".split())
UNSEEN = frozenset("head script style noscript template title option".split())
ROLES = frozenset("navigation banner contentinfo complementary search form alert alertdialog dialog menu menubar toolbar".split())
WORDS = frozenset(
    "ad ads adv advert adverts advertisement advertising adsense sponsor sponsored promo promotion cookie cookies consent gdpr banner notice notices "
    "sidebar sidebars menu menus nav navbar navigation breadcrumb breadcrumbs footer masthead comment comments disqus respond reply replies share sharing social "
    "related recommended newsletter subscribe subscription signup popup modal overlay widget widgets toolbar pagination pager skip alert".split()
)
EXEMPT = frozenset("html body main".split())
CLOSES = {"li": ("li",), "dt": ("dt", "dd"), "dd": ("dt", "dd"), "tr": ("tr", "td", "th"), "td": ("td", "th"), "th": ("td", "th"), "option": ("option",)}
FENCES = frozenset("ul ol dl table tbody thead tfoot select article section div body".split())
PART = re.compile(r"[^a-z0-9]+")


HEADINGS = frozenset("h1 h2 h3 h4 h5 h6".split())
NAMED = 0.05  # weight of lines in an element with one of the words


class Line(NamedTuple):
    text: str
    tags: int
    holder: int
    dropped: bool
    linked: int  # characters inside links
    heading: bool


class Lines(HTMLParser):
    """Turns parser events into lines."""

    def __init__(self):
        super().__init__(convert_charrefs=True)
        self.stack: list[tuple[str, int, bool]] = []  # name, holder, inside something dropped
        self.lines: list[Line] = []
        self.holders: list[tuple[str, int]] = [("", -1)]  # name, parent
        self.suspects: set[int] = set()  # holders with a class word
        self.body: list[str] = []  # lines that a reader can see
        self.text: list[str] = []
        self.tags = self.links = self.linked = 0

    def named(self, tag: str, attrs) -> bool:
        """Whether a class or id has one of the words of what is not content."""
        return tag not in EXEMPT and any(v and n in ("class", "id") and not WORDS.isdisjoint(PART.split(v.lower())) for n, v in attrs)

    def state(self) -> tuple[int, bool]:
        return (self.stack[-1][1], self.stack[-1][2]) if self.stack else (0, False)

    def flush(self):
        text = " ".join("".join(self.text).split())
        if text:
            holder, dropped = self.state()
            heading = any(name in HEADINGS for name, _, _ in self.stack[-2:])
            self.lines.append(Line(text, self.tags, holder, dropped, self.linked, heading))
            if not dropped or UNSEEN.isdisjoint(name for name, _, _ in self.stack):
                self.body.append(text)
        self.text, self.tags, self.linked = [], 0, 0

    def unwanted(self, tag: str, attrs) -> bool:
        if tag in DROPPED:
            return True
        if tag == "header":
            return not any(name in ("article", "main") for name, _, _ in self.stack)
        if tag in EXEMPT:
            return False
        for name, value in attrs:
            if name == "hidden" or name == "aria-hidden" and value == "true":
                return True
            if value and name == "role" and value.lower() in ROLES:
                return True
            if value and name == "style" and "display:none" in value.replace(" ", "").lower():
                return True
        return False

    def handle_starttag(self, tag, attrs):
        if tag in BLOCKS:
            self.flush()
            if self.stack and self.stack[-1][0] == "p":
                self.stack.pop()
            for other in CLOSES.get(tag, ()):
                for i in range(len(self.stack) - 1, -1, -1):
                    if self.stack[i][0] == other:
                        del self.stack[i:]
                        break
                    if self.stack[i][0] in FENCES:
                        break
        elif tag == "br":
            self.text.append(" ")
        self.tags += 1
        if tag in VOID:
            return
        if tag == "a":
            self.links += 1
        holder, dropped = self.state()
        bad, suspect = self.unwanted(tag, attrs), self.named(tag, attrs)
        if tag in BLOCKS or bad or suspect:
            if tag not in BLOCKS:
                self.flush()
            if tag in HOLDERS or suspect:
                self.holders.append((tag, holder))
                holder = len(self.holders) - 1
                if suspect:
                    self.suspects.add(holder)
            self.stack.append((tag, holder, dropped or bad))

    def handle_startendtag(self, tag, attrs):
        if tag in VOID:
            self.handle_starttag(tag, attrs)
        else:
            self.handle_starttag(tag, attrs)
            self.handle_endtag(tag)

    def handle_endtag(self, tag):
        self.tags += 1
        if tag in VOID:
            return
        if tag == "a":
            self.links = max(0, self.links - 1)
        for i in range(len(self.stack) - 1, -1, -1):
            if self.stack[i][0] == tag:
                self.flush()
                del self.stack[i:]
                return
            if self.stack[i][0] in ("article", "body") and tag not in ("article", "body", "html", "main"):
                break
        if tag in BLOCKS:
            self.flush()

    def handle_data(self, data):
        self.text.append(data)
        if self.links:
            self.linked += len(data.strip())


def smooth(values: list[float], sigma: float = 1.0, reach: int = 2) -> list[float]:
    weights = [math.exp(-(d * d) / (2 * sigma * sigma)) for d in range(-reach, reach + 1)]
    out = []
    for i in range(len(values)):
        total = weight = 0.0
        for d in range(-reach, reach + 1):
            if 0 <= i + d < len(values):
                total += weights[d + reach] * values[i + d]
                weight += weights[d + reach]
        out.append(total / weight)
    return out


def held_by(lines: list[Line], holders: list[tuple[str, int]]) -> list[int]:
    """Characters of the lines inside each holder."""
    held = [0] * len(holders)
    for x in lines:
        held[x.holder] += len(x.text)
    for i in range(len(holders) - 1, 0, -1):  # parents come before their children
        held[holders[i][1]] += held[i]
    return held


def within(holders: list[tuple[str, int]], roots: set[int]) -> list[bool]:
    inside = [False] * len(holders)
    for i in range(len(holders)):
        inside[i] = i in roots or holders[i][1] >= 0 and inside[holders[i][1]]
    return inside


def weights(parser: Lines, small: float) -> tuple[list[float], list[bool]]:
    """The weight of each holder's lines, and whether the holder is an article's. An element named for
    what is not content loses weight where it holds at most the share ``small`` of the page's text,
    or stands apart from the articles."""
    holders = parser.holders
    held = held_by([x for x in parser.lines if not x.dropped], holders)
    marked = {i for i in range(len(holders)) if held[i] and holders[i][0] in ("article", "main")}
    around = set(marked)  # holders that an article is in
    for i in range(len(holders) - 1, 0, -1):
        if i in around:
            around.add(holders[i][1])
    good = within(holders, marked)
    bad = within(holders, {i for i in parser.suspects if held[i] <= small * held[0] or marked and i not in around and not good[i]})
    return [NAMED if b else 1.0 for b in bad], [g and not b for b, g in zip(bad, good, strict=True)]


def content(lines: list[Line], weight: list[float], ratio=None) -> list[bool]:
    """Which lines the threshold on smoothed, weighed ratios calls content."""
    ratio = ratio or (lambda x: max(0, len(x.text) - x.linked) / max(1, x.tags))
    raw = [0.0 if x.dropped else ratio(x) * weight[x.holder] for x in lines]
    scores = smooth(raw)
    mean = sum(scores) / len(scores)
    spread = math.sqrt(sum((s - mean) ** 2 for s in scores) / len(scores))
    least = min(spread, mean)
    # A short line beside a long one is smoothed up: a line of its element must reach the threshold alone.
    strong = {x.holder for x, r in zip(lines, raw, strict=True) if r >= least}
    return [not x.dropped and s >= least and s > 0 and x.holder in strong and weight[x.holder] > NAMED for x, s in zip(lines, scores, strict=True)]


def main_text(html: str | None, small: float = 0.5, ratio=None) -> str:
    """The article's blocks, joined by newlines. ``small``: share of the page's text up to which an
    element loses weight for a word in its class or id; ``ratio``: another ratio of a line."""
    if not html:
        return ""
    parser = Lines()
    parser.feed(html)
    parser.close()
    parser.flush()
    lines, holders = parser.lines, parser.holders
    if all(x.dropped for x in lines):
        return "\n".join(parser.body)
    weight, articles = weights(parser, small)
    plain = [not x.dropped and weight[x.holder] > NAMED for x in lines]
    chosen = content(lines, weight, ratio)
    if not any(chosen):  # nothing but links or named elements
        chosen = plain
        if not any(chosen):
            return "\n".join(parser.body)
    marked = [p and articles[x.holder] for x, p in zip(lines, plain, strict=True)]
    inside = sum(len(x.text) for x, c, m in zip(lines, chosen, marked, strict=True) if c and m)
    if any(marked) and 2 * inside >= sum(len(x.text) for x, c in zip(lines, chosen, strict=True) if c):
        return "\n".join(x.text for x, m in zip(lines, marked, strict=True) if m)
    chosen = [c or m for c, m in zip(chosen, marked, strict=True)]
    own = {x.holder for x, c in zip(lines, chosen, strict=True) if c}
    aunts = {holders[h][1] for h in own}
    places = [i for i, c in enumerate(chosen) if c]
    kept = list(chosen)
    for i, x in enumerate(lines):
        if plain[i] and not chosen[i] and 2 * x.linked <= len(x.text):
            between = places[0] < i < places[-1] and (holders[x.holder][1] in aunts or x.holder in aunts)
            kept[i] = x.holder in own or between
    for i in range(len(lines) - 2, -1, -1):  # headings that lead to what is kept
        x = lines[i]
        if x.heading and kept[i + 1] and plain[i]:
            kept[i] = True
    return "\n".join(x.text for x, k in zip(lines, kept, strict=True) if k)


SCHEMA = "page_id long, url string, text string, n_chars long"


def _extract():
    schema = pa.schema([("page_id", pa.int64()), ("url", pa.string()), ("text", pa.string()), ("n_chars", pa.int64())])

    def each(batch: pa.RecordBatch):
        for part in slices(batch):
            texts = [main_text(h) for h in part.column(2).to_pylist()]
            yield pa.RecordBatch.from_arrays([part.column(0), part.column(1), pa.array(texts, pa.string()), pa.array(map(len, texts), pa.int64())], schema=schema)

    return each


def extract_main_text(pages: DataFrame) -> DataFrame:
    """(page_id, url, html) -> (page_id, url, text, n_chars); map-only."""
    return arrow_rows(pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), F.col("html").cast("string").alias("html")), _extract, SCHEMA)
