"""Main text of web pages from streaming parser events.

The standard library's parser feeds events; block elements split the page into
lines, each with its text, its number of tags and its place in the open
elements. The ratio of text to tags per line is smoothed by a Gaussian and lines
above the threshold form content clusters; the smallest container around all of
them is the article, and its lines, short ones included, are the result. Tags
such as article and main are evidence only. Elements that are boilerplate by
kind never give lines, those by name only if they hold most of the page's prose.

Null or empty html, or a page without content, gives an empty string. Repeated
rows each get theirs.
"""

from __future__ import annotations

import math
import re
from functools import lru_cache
from html.parser import HTMLParser

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
SKIPPED = frozenset(
    "head title script style noscript template nav footer aside form button select textarea input label iframe svg canvas object dialog menu header".split()
)
BLOCK = frozenset(
    "address article blockquote body center dd details div dl dt fieldset figcaption figure h1 h2 h3 h4 h5 h6 hr html li main ol p pre section summary table tbody td tfoot th thead tr ul caption".split()
)
CLOSES_P = BLOCK | {"nav", "footer", "aside", "form", "header"}
CONTAINER = frozenset("article main section div body td".split())
MARKED = ("article", "main")
#: Names of boilerplate in class, id and role.
NAMES = frozenset(
    "ad ads advert adverts advertisement advertising banner breadcrumb breadcrumbs comment comments commentlist complementary consent contentinfo cookie cookies dialog disqus footer form gdpr "
    "masthead menu modal nav navbar navigation newsletter notice pagination popup promo promotion related replies reply respond search share sharing sidebar side signup "
    "skip social sponsor sponsored subscribe toolbar widget alert header topbar".split()
)
ARTICLE_NAMES = frozenset("comment reply ad promo related".split())
#: Words after the head of a name that only say which or where; words that make a name a mere modifier; owners of a header that holds the headline.
TAIL = frozenset("area list box block section container inner outer item items post posts article articles story stories content link links button buttons icons bar left right top bottom slot unit panel thread".split())
MODIFIERS = frozenset("with without no non not has have is hide show".split())
OWNERS = frozenset("article entry post story".split())
BLANKS = re.compile(r"\s+")
_UNCLOSED = re.compile(r"<(?:!--|/?[A-Za-z!?])").match
_PARTS = re.compile(r"[_-]+")
#: PROSE: this many characters a tag are prose, however dense the rest of the page is.
SIGMA, PROSE = 1.0, 40


@lru_cache(8192)
def boilerplate(value: str, names: frozenset = NAMES) -> bool:
    """Whether a token of an attribute is a name of boilerplate, as a whole or by its head word."""
    for token in value.lower().split():
        words = [w for w in _PARTS.split(token) if w and not w.isdigit()]
        while len(words) > 1 and words[-1] in TAIL and words[-1] not in names:
            words.pop()
        if words and words[-1] in names and not MODIFIERS.intersection(words[:-1]) and not (words[-1] == "header" and OWNERS.intersection(words[:-1])):
            return True
    return False


class _Lines(HTMLParser):
    def __init__(self):
        super().__init__(convert_charrefs=True)
        self.open: list[tuple[str, bool, int, int]] = []  # tag, skipped, node, gate
        self.parents: list[int] = [-1]
        self.kinds: list[str] = [""]
        self.gates: list[int] = []  # subtrees with names of boilerplate: the gate around each
        self.lines: list[tuple[str, int, int, int]] = []  # text, tags, node, gate
        self.text: list[tuple[int, str]] = []
        self.tags = 0

    @property
    def node(self) -> int:
        return self.open[-1][2] if self.open else 0

    @property
    def gate(self) -> int:
        return self.open[-1][3] if self.open else -1

    def flush(self) -> None:
        parts: dict[int, list[str]] = {}
        for gate, data in self.text:
            parts.setdefault(gate, []).append(data)
        for gate, held in parts.items():
            text = BLANKS.sub(" ", "".join(held)).strip()
            if text:
                self.lines.append((text, self.tags, self.node, gate))
                self.tags = 0
        self.text = []

    def handle_starttag(self, tag, attrs):
        self.tags += 1
        if tag in CLOSES_P:
            self.flush()
            for i in range(len(self.open) - 1, -1, -1):
                if self.open[i][0] == "p":
                    del self.open[i:]
                    break
                if self.open[i][0] in CONTAINER:
                    break
        if tag in ("li", "td", "th", "tr", "dt", "dd", "option"):
            for i in range(len(self.open) - 1, -1, -1):
                if self.open[i][0] == tag:
                    del self.open[i:]
                    break
                if self.open[i][0] in ("ul", "ol", "table", "dl", "select"):
                    break
        if tag == "br":
            self.text.append((self.gate, " "))
        if tag in VOID:
            return
        skipped = bool(self.open and self.open[-1][1]) or tag in SKIPPED
        if not skipped and attrs and tag not in ("html", "body", "article", "main"):
            skipped = any(k == "hidden" or k == "aria-hidden" and v == "true" for k, v in attrs)
            named = any(v and k in ("class", "id", "role") and boilerplate(v) for k, v in attrs)
        else:
            named = tag == "article" and any(v and k in ("class", "id") and boilerplate(v, ARTICLE_NAMES) for k, v in attrs)
        node, gate = self.node, self.gate
        if named and not skipped:
            self.gates.append(gate)
            gate = len(self.gates) - 1
        if tag in CONTAINER and not skipped:
            self.parents.append(node)
            self.kinds.append(tag)
            node = len(self.parents) - 1
        self.open.append((tag, skipped, node, gate))

    def handle_startendtag(self, tag, attrs):
        self.handle_starttag(tag, attrs)
        if tag not in VOID:
            self.handle_endtag(tag)

    def handle_endtag(self, tag):
        self.tags += 1
        if tag in CLOSES_P or tag in SKIPPED:
            self.flush()
        for i in range(len(self.open) - 1, -1, -1):
            if self.open[i][0] == tag:
                del self.open[i:]
                return

    def handle_data(self, data):
        if not (self.open and self.open[-1][1]):
            self.text.append((self.gate, data))

    def above(self, node: int) -> list[int]:
        """The container and all around it."""
        out = []
        while node >= 0:
            out.append(node)
            node = self.parents[node]
        return out


def smooth(values: list[float], sigma: float = SIGMA) -> list[float]:
    """Gaussian smoothing with weights renewed at the ends."""
    reach = max(1, math.ceil(3 * sigma))
    weights = [math.exp(-(i * i) / (2 * sigma * sigma)) for i in range(-reach, reach + 1)]
    out = []
    for at in range(len(values)):
        pairs = [(w, values[at + i]) for i, w in zip(range(-reach, reach + 1), weights) if 0 <= at + i < len(values)]
        out.append(sum(w * v for w, v in pairs) / sum(w for w, _ in pairs))
    return out


def visible(page: _Lines) -> list[tuple[str, int, int]]:
    """Lines outside boilerplate by name; a named subtree with most of the page's prose, and no article outside it, is none."""
    mass = [0] * len(page.gates)
    total, articles = 0, 0
    for text, tags, node, gate in page.lines:
        if len(text) < PROSE * max(1, tags):
            continue
        total += len(text)
        if gate < 0 and any(page.kinds[n] in MARKED for n in page.above(node)):
            articles += len(text)
        while gate >= 0:
            mass[gate] += len(text)
            gate = page.gates[gate]
    return [(text, tags, node) for text, tags, node, gate in page.lines if gate < 0 or not articles and 2 * mass[gate] > total]


def region(page: _Lines, lines: list[tuple[str, int, int]]) -> int:
    """The smallest container around all lines of content.

    Content is dense as smoothed and by itself. Where article and main hold more
    than half of it, lines outside them must be half as dense as those inside.
    """
    raw = [len(text) / max(1, tags) for text, tags, _ in lines]
    ratio = smooth(raw)
    mean = sum(ratio) / len(ratio)
    spread = math.sqrt(sum((r - mean) ** 2 for r in ratio) / len(ratio))
    least = min(PROSE, max(mean - spread, mean / 4))
    dense = [i for i in range(len(lines)) if ratio[i] >= least and raw[i] >= least] or list(range(len(lines)))
    paths = {node: page.above(node) for _, _, node in lines}
    inner = {i for i in dense if any(page.kinds[n] in MARKED for n in paths[lines[i][2]])}
    if 2 * sum(len(lines[i][0]) for i in inner) > sum(len(lines[i][0]) for i in dense):
        bar = sorted(raw[i] for i in inner)[len(inner) // 2] / 2
        dense = [i for i in dense if i in inner or raw[i] >= bar]
    shared = set.intersection(*[set(paths[lines[i][2]]) for i in dense])
    return max(shared)  # a container's number is above those around it


def main_text(html: str | None) -> str:
    if not html:
        return ""
    page = _Lines()
    page.feed(html)
    if _UNCLOSED(page.rawdata):  # a comment or tag that never ends takes the rest with it
        page.rawdata = ""
    page.close()
    page.flush()
    lines = visible(page)
    if not lines:
        return ""
    best = region(page, lines)
    return "\n".join(text for text, _, node in lines if best in page.above(node))


def extract(pages: DataFrame) -> DataFrame:
    """(page_id, url, text, n_chars) of every row of ``pages``."""

    def run(batches):
        for batch in batches:
            for lo in range(0, batch.num_rows, 512):
                part = batch.slice(lo, 512)
                texts = [main_text(h) for h in part.column(2).to_pylist()]
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(1), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], ["page_id", "url", "text", "n_chars"])

    rows = pages.select(F.col("page_id").cast("long"), F.col("url").cast("string"), F.col("html").cast("string"))
    return rows.mapInArrow(run, "page_id long, url string, text string, n_chars long")
