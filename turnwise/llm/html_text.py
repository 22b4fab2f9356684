"""Main text of web pages: text-to-tag ratio by line, Gaussian smoothing, threshold clustering.

The standard library's parser is run as a stream of events. Each block-level element starts a line; a line knows its
characters, its tags, the characters inside links and the open elements around it. Elements that are page furniture by
their tag or by a name in their class, id or role never count as text; a name of several words is one of furniture only
if all of them speak of furniture or layout ("comment-list" does, "related-work" and "share-price" don't). Over the rest, text-to-tag ratios are smoothed
with a Gaussian window, and lines whose smoothed ratio lies above the threshold that splits the page's lines best into
two clusters are content. The region of content starts as the smallest container that holds nearly all characters of
those lines and grows to the article or main element around it, or without one as long as what it takes in isn't mostly
links; every line of text in it is kept, short ones too, so that clustering decides where the article is and drops
nothing inside it. A region without a first-level heading also has the last one before it.

Edge cases: null and empty html give an empty text; unclosed and stray tags don't matter; a page without any tag is one
block; repeated rows are extracted each; long pages are read whole; columns but id, url and html are not read.
"""

from __future__ import annotations

import re
from html.parser import HTMLParser

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from turnwise.llm.common import map_arrow, table, text_of

#: Elements that begin a block, have no end tag, never hold an article's text, or close an open one of their kind.
BLOCKS = frozenset("address article aside blockquote body caption center dd details dialog dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr html legend li main menu nav ol optgroup option p pre search section summary table tbody td tfoot th thead tr ul".split())
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
HIDDEN = frozenset("head title script style noscript template nav footer aside form button select textarea input iframe object svg canvas audio video map dialog menu search label datalist".split())
CLOSES = {"li": "li", "p": "p", "dt": "dt dd", "dd": "dt dd", "tr": "tr td th", "td": "td th", "th": "td th", "option": "option"}
NO_PARAGRAPH = BLOCKS - {"td", "th", "tr", "tbody", "thead", "tfoot", "caption", "li", "dd", "dt", "option", "optgroup", "legend", "summary", "figcaption", "body", "html"} | {"p"}
CONTAINERS = frozenset("html body main article section div center table tbody tr td".split())
FURNITURE = frozenset(
    "ad ads adv advert adverts advertisement advertising adbox adsense adslot banner sponsor sponsored promo promotion popup modal overlay cookie cookies consent gdpr notice notices alert disclaimer "
    "menu nav navbar navigation breadcrumb breadcrumbs pagination pager toolbar sidebar side rail widget widgets header masthead topbar footer foot colophon "
    "comment comments commentlist respond reply replies disqus discussion share sharing social related recommended recommendations newsletter subscribe subscription signup login search skip".split()
)
#: Words that say nothing of the content beside one of FURNITURE.
LAYOUT = frozenset(
    "area bar block body bottom box btn button buttons card center class cell col column container content count desktop div element entry fixed form global group grid head heading hidden holder home icon icons id image images "
    "inner item items js label layer left link links list lists main middle mobile module outer page panel part placeholder primary right row secondary section segment site slot small sticky sub tab text title top unit wrap wrapper zone".split()
)
_WORD = re.compile(r"[a-z]+")
_BLANK = re.compile(r"\s+")


def is_furniture(name: str) -> bool:
    """Whether a class, id or role names furniture."""
    words = _WORD.findall(name)
    return not FURNITURE.isdisjoint(words) and all(x in FURNITURE or x in LAYOUT or len(x) == 1 for x in words)


class Lines(HTMLParser):
    """Blocks of text of a page with what the ratio needs; elements are numbered in page order."""

    def __init__(self):
        super().__init__(convert_charrefs=True)
        self.open: list[tuple[str, int, bool]] = []  # tag, number, furniture
        self.places: dict[str, list[int]] = {}  # where the open elements of each tag are
        self.parent: list[int] = []
        self.kinds: list[str] = []
        self.lines: list[tuple[str, int, int, int]] = []  # text, tags, characters in links, element
        self.parts: list[str] = []
        self.tags = self.linked = self.hidden = self.links = 0
        self.line_of = -1

    def _end_line(self) -> None:
        text = _BLANK.sub(" ", "".join(self.parts)).strip()
        if text:
            self.lines.append((text, self.tags, min(self.linked, len(text)), self.line_of))
        if text or self.parts:
            self.tags = 0
        self.parts.clear()
        self.linked = 0

    def _furniture(self, tag: str, attrs) -> bool:
        if tag in HIDDEN:
            return True
        if tag == "header":
            return not (self.places.get("article") or self.places.get("main"))
        for name, value in attrs:
            if name in ("class", "id", "role") and value and tag not in ("html", "body", "article", "main") and any(map(is_furniture, value.lower().split())):
                return True
            if name == "hidden" or (name == "aria-hidden" and value == "true"):
                return True
        return False

    def _pop(self, k: int) -> None:
        """Close the k-th open element and all inside it."""
        for tag, _, furniture in self.open[k:]:
            self.places[tag].pop()
            self.hidden -= furniture
            self.links -= tag == "a"
        del self.open[k:]

    def handle_starttag(self, tag, attrs):
        self.tags += 1
        if tag in BLOCKS:
            self._end_line()
        if tag in VOID:
            if tag == "br":
                self.parts.append(" ")
            return
        if tag in NO_PARAGRAPH:
            self._close("p", stop=("article", "main", "div", "section", "td", "li", "body"))
        for other in CLOSES.get(tag, "").split():
            if other != "p":
                self._close(other, stop=("ul", "ol", "dl", "table", "select"))
        furniture = self._furniture(tag, attrs)
        self.parent.append(self.open[-1][1] if self.open else -1)
        self.kinds.append(tag)
        self.places.setdefault(tag, []).append(len(self.open))
        self.open.append((tag, len(self.parent) - 1, furniture))
        self.hidden += furniture
        self.links += tag == "a"

    def handle_startendtag(self, tag, attrs):
        self.handle_starttag(tag, attrs)
        if tag not in VOID and tag in ("script", "style", "iframe", "svg", "object"):
            self._close(tag)

    def _close(self, tag: str, stop: tuple[str, ...] = ()) -> bool:
        last = lambda t: (self.places.get(t) or (-1,))[-1]
        k = last(tag)
        if k < 0 or any(last(t) > k for t in stop):
            return False
        self._pop(k)
        return True

    def handle_endtag(self, tag):
        self.tags += 1
        if tag in BLOCKS:
            self._end_line()
        if tag == "br":
            self.parts.append(" ")
        elif tag not in VOID:
            self._close(tag)

    def handle_data(self, data):
        if self.hidden:
            return
        if not self.parts:
            self.line_of = self.open[-1][1] if self.open else -1
        self.parts.append(data)
        if self.links:
            self.linked += len(data)

    def result(self):
        self._end_line()
        return self.lines, self.parent, self.kinds


def smooth(x: np.ndarray, radius: int = 2, sigma: float = 1.0) -> np.ndarray:
    """x under a Gaussian window that is normalised at the edges."""
    k = np.exp(-0.5 * (np.arange(-radius, radius + 1) / sigma) ** 2)
    size = len(x)
    return np.convolve(x, k)[radius : radius + size] / np.convolve(np.ones(size), k)[radius : radius + size]


def threshold(x: np.ndarray) -> float:
    """The value that splits x into the two clusters of least variance within; the lower cluster ends below it."""
    s = np.sort(x)
    n = len(s)
    if n < 2 or s[0] == s[-1]:
        return s[0]
    left, count = np.cumsum(s)[:-1], np.arange(1, n)
    between = (s.sum() * count / n - left) ** 2 / (count * (n - count))
    between[s[1:] == s[:-1]] = -1
    return float(s[1 + int(np.argmax(between))])


def _widened(best: int, lines: list[tuple[str, int, int, int]], parent: list[int], kinds: list[str]) -> int:
    """The article or main element around an element, or the largest container around it that adds more text than links."""
    above = [best]
    while above[-1] >= 0:
        above.append(parent[above[-1]])
    above.pop()
    whole = next((e for kind in ("article", "main") for e in reversed(above) if kinds[e] == kind), None)
    now, last = (best, None) if whole is None else (whole, "main")
    if last and not any(kinds[e] == last for e in above[above.index(now) + 1 :]):
        return now
    # the text and the links of the lines whose way up enters the chain at each place
    place = {e: k for k, e in enumerate(above)}
    enters: list[int] = []
    for e, up in enumerate(parent):
        enters.append(place.get(e, enters[up] if up >= 0 else len(above)))
    text, linked = [0] * (len(above) + 1), [0] * (len(above) + 1)
    for x, _, links, e in lines:
        k = enters[e] if e >= 0 else len(above)
        text[k] += len(x)
        linked[k] += links
    new_text = new_links = 0
    for k in range(place[now] + 1, len(above)):
        new_text, new_links = new_text + text[k], new_links + linked[k]
        if 2 * new_links > new_text:
            break
        if kinds[above[k]] in CONTAINERS:
            now, new_text, new_links = above[k], 0, 0
        if kinds[above[k]] == last:
            break
    return now


def main_text(html: str, share: float = 0.9) -> str:
    """The blocks of the page's main region, one a line."""
    parser = Lines()
    parser.feed(html)
    parser.close()
    lines, parent, kinds = parser.result()
    if not lines:
        return ""
    size = np.array([len(x[0]) for x in lines], float)
    ratio = np.maximum(size - 2 * np.array([x[2] for x in lines]), 0) / np.maximum([x[1] for x in lines], 1)
    level = smooth(ratio)
    chosen = level >= min(threshold(level), level.std() if level.std() > 0 else level[0])
    weight: dict[int, float] = {}
    for (_, _, _, element), n, yes in zip(lines, size, chosen, strict=True):
        if yes:
            weight[element] = weight.get(element, 0) + n
    # each element's weight includes that of the elements in it; children have larger numbers than their parents
    for e in range(len(parent) - 1, -1, -1):
        if e in weight:
            weight[parent[e]] = weight.get(parent[e], 0) + weight[e]
    need = share * weight.get(-1, 0)
    best = max(e for e in [-1, *weight] if weight.get(e, 0) >= need and (e < 0 or kinds[e] in CONTAINERS))
    if best >= 0:
        best = _widened(best, lines, parent, kinds)
    inside = {best}
    for e in range(max(best, 0), len(parent)):
        if parent[e] in inside:
            inside.add(e)
    kept = [best == -1 or x[3] in inside for x in lines]
    heading = lambda x: x[3] >= 0 and _within(x[3], "h1", parent, kinds)
    first = next((k for k, yes in enumerate(kept) if yes), 0)
    if not any(yes and heading(x) for yes, x in zip(kept, lines, strict=True)):
        title = next((k for k in range(first - 1, -1, -1) if heading(lines[k])), None)
        if title is not None:
            kept[title] = True
    return "\n".join(x[0] for yes, x in zip(kept, lines, strict=True) if yes)


def _within(element: int, kind: str, parent: list[int], kinds: list[str], up: int = 8) -> bool:
    """Whether an element or one of those right around it is of this kind."""
    while element >= 0 and up:
        if kinds[element] == kind:
            return True
        if kinds[element] in BLOCKS:
            return False
        element, up = parent[element], up - 1
    return False


def extract(pages: DataFrame, html_col: str = "html", keep: tuple[str, ...] = ("page_id", "url")) -> DataFrame:
    """The columns of keep, text and n_chars of every row."""
    kinds = ", ".join(f"{c} {pages.schema[c].dataType.simpleString()}" for c in keep)

    def make():
        def run(batch: pa.RecordBatch) -> pa.RecordBatch:
            texts = [main_text(x) for x in batch.column(len(keep)).to_pylist()]
            return pa.RecordBatch.from_arrays([*batch.columns[: len(keep)], pa.array(texts, pa.string()), pa.array(map(len, texts), pa.int64())], [*keep, "text", "n_chars"])

        return run

    return map_arrow(pages.select(*keep, text_of(html_col).alias("html")), make, f"{kinds}, text string, n_chars bigint")


def op8_main_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    return extract(table(spark, sf_dir, "pages"))
