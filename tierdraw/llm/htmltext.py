"""Main text of web pages by tag-path ratios.

Every text node has a root-to-leaf tag path. Per path, text length and punctuation are summed over its nodes, less the more of a node's block lies in links; the
ratios per node are smoothed over neighbouring nodes in page order and fused with their own value. What the names on a path say (navigation, notices,
comments, a place outside a marked article) enters as one bounded factor. Paths whose score stays below a share of the best one are dropped, so that nodes of
one path are kept or dropped together. A page is read in one pass, in time in proportion to its length, however deep or broken its markup is.
"""

from __future__ import annotations

import html
import re
from collections.abc import Collection, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import types as T

#: Share of the best path's score that a path needs; width of the smoothing in nodes; least factor of a path by its names, and that of names that may mislead.
THRESHOLD, SIGMA, FLOOR, DOUBT = 0.014, 1.5, 0.004, 0.03
#: Names of HTML elements and of roles that are not an article's text.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
BLOCKS = frozenset("address article aside blockquote body br caption center dd details dialog dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 head header hr html legend li main menu nav ol option p pre section summary table tbody td tfoot th thead title tr ul".split())
SILENT = frozenset("script style noscript template textarea title iframe svg math object select button head canvas audio video".split())
ASIDE_TAGS = frozenset("nav footer aside form menu dialog fieldset label input".split())
MARKERS = frozenset(
    "ad ads adv advert adverts advertisement advertising sponsor sponsored promo promotion banner cookie cookies consent gdpr notice notices notification alert sidebar sidebars rail menu menus nav navbar navigation breadcrumb breadcrumbs "
    "footer masthead topbar comment comments commentlist disqus discussion respond reply replies share sharing social related recommended recommendations newsletter subscribe subscription signup login popup modal overlay widget widgets toolbar "
    "pager pagination copyright legal disclaimer skip search searchform".split()
)
HEADERS = frozenset(["header", "head", "top"])
ARTICLE = frozenset(["article", "main"])
ARTICLE_NAMES = frozenset("article articlebody post postcontent entry story content maincontent".split())
PUNCTUATION = frozenset(".,;:!?…。，、；：！？")
#: Start tags that end an open paragraph or item.
ENDS_P = BLOCKS - {"br", "option", "li", "dd", "dt", "td", "th", "tr", "tbody", "thead", "tfoot", "body", "html", "head"}
SAME = {"li": ("li",), "dt": ("dt", "dd"), "dd": ("dt", "dd"), "tr": ("tr", "td", "th"), "td": ("td", "th"), "th": ("td", "th"), "option": ("option",)}
SCOPE = {"li": ("ul", "ol", "menu"), "dt": ("dl",), "dd": ("dl",), "tr": ("table",), "td": ("table",), "th": ("table",), "option": ("select",)}

RAW = frozenset("script style textarea title noscript iframe template svg".split())
#: Names that, as a part of a longer name, may as well be those of an article's section.
UNSURE = frozenset("related recommended recommendations discussion legal respond reply replies social share sharing head top".split())
_NAME = re.compile(r"[a-zA-Z][^\s/>]*")
_QUOTED = re.compile(r"[^>\"']*")
_RAW_END = {name: re.compile(rf"</{name}(?=[\s/>])", re.I) for name in RAW}
_ATTR = re.compile(r"(?:^|[\s\"'/])(class|id|role|hidden|aria-hidden|style)(?:\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+)))?", re.I)
_PARTS = re.compile(r"[A-Z]?[a-z]+|[A-Z]+(?![a-z])|\d+")


@dataclass(slots=True)
class Node:
    """A stretch of text: the number of its path, whether it lies in a link, and the number of its block."""

    path: int
    link: bool
    block: int
    text: str


@dataclass
class Page:
    """Text nodes in order, and of each path the factor that its names give and whether it lies in an article."""

    nodes: list[Node]
    factors: list[float]
    inside: list[bool]


def _doubt(name: str, in_article: bool) -> float:
    """Factor of one class or id."""
    parts = [p.lower() for p in _PARTS.findall(name)]
    if parts and parts[0] in ("has", "with", "no", "without", "is", "js"):
        return 1.0
    found = MARKERS.intersection(parts)
    if not in_article:
        found |= HEADERS.intersection(parts[:1] + parts[-1:])
    if not found:
        return 1.0
    return DOUBT if found <= UNSURE and len(parts) > len(found) else FLOOR


def _said(tag: str, attrs: str, in_article: bool) -> tuple[str, float, bool]:
    """Label of an element on paths, the factor of its name and attributes, and whether it is an article."""
    names: list[str] = []
    factor = FLOOR if tag in ASIDE_TAGS or tag == "header" and not in_article else 1.0
    article = tag in ARTICLE
    for m in _ATTR.finditer(attrs) if attrs else ():
        key, value = m[1].lower(), m[2] or m[3] or m[4] or ""
        if key in ("class", "id"):
            names += value.split()
        elif key == "hidden" or key == "aria-hidden" and value.lower() == "true" or key == "style" and re.search(r"display\s*:\s*none", value, re.I):
            factor = FLOOR
        elif key == "role":
            factor = FLOOR if value.lower() in ("navigation", "banner", "contentinfo", "complementary", "search", "form", "dialog", "alert", "menu") else factor
            article |= value.lower() in ("main", "article")
    if tag not in ("html", "body") and tag not in ARTICLE:
        for name in names:
            factor = min(factor, _doubt(name, in_article))
            parts = [p.lower() for p in _PARTS.findall(name)]
            article |= "".join(parts) in ARTICLE_NAMES or "".join(parts[-2:]) in ("articlebody", "postcontent", "entrycontent", "articlecontent", "maincontent")
    return f"{tag}.{names[0]}" if names else tag, factor, article and factor == 1.0


def _tag_end(page: str, at: int) -> int:
    """Place of the ``>`` that ends a tag; quotes count after ``=``. -1 if none does."""
    while True:
        at = _QUOTED.match(page, at).end()
        if at >= len(page):
            return -1
        if page[at] == ">":
            return at
        shut = page.find(page[at], at + 1) if page[max(0, at - 8) : at].rstrip().endswith("=") else at
        at = (shut if shut >= 0 else at) + 1  # a quote that nothing closes is a character like others


class _Stack:
    """Open elements: tag, path, in article, in link. Knows where each name stands, so that closing looks at no element but those that go."""

    def __init__(self) -> None:
        self.items: list[tuple[str, int, bool, bool]] = []
        self.places: dict[str, list[int]] = {}

    def push(self, tag: str, path: int, article: bool, link: bool) -> None:
        self.places.setdefault(tag, []).append(len(self.items))
        self.items.append((tag, path, article, link))

    def last(self, names: Collection[str]) -> int:
        """Place of the innermost element of these names, -1 if there is none."""
        return max((self.places[n][-1] for n in names if self.places.get(n)), default=-1)

    def close(self, names: Collection[str], stop: Collection[str] = ()) -> None:
        """End the innermost element of these names and all inside it, unless one of ``stop`` lies between."""
        at = self.last(names)
        if at >= 0 and at >= self.last(stop):
            for tag, *_ in self.items[at:]:
                self.places[tag].pop()
            del self.items[at:]


def read(page: str) -> Page:
    """Text nodes of a page. Unclosed and stray tags are put up with; comments, scripts and the like have no nodes."""
    out = Page([], [1.0], [False])
    paths: dict[tuple[int, str, bool], int] = {}
    stack, block, at = _Stack(), 0, 0

    def emit(raw: str) -> None:
        _, path, _, link = stack.items[-1] if stack.items else ("", 0, False, False)
        if raw and not any(stack.places.get(s) for s in SILENT):
            out.nodes.append(Node(path, link, block, html.unescape(raw)))

    begun = 0  # of the text that is not emitted yet
    while (at := page.find("<", at)) >= 0:
        nxt = page[at + 1 : at + 2]
        if nxt in "!?" and nxt:
            emit(page[begun:at])
            stop = page.find("-->", at + 4) + 2 if page.startswith("<!--", at) else page.find(">", at)
            at = begun = stop + 1 if stop >= (2 if page.startswith("<!--", at) else 0) and stop > at else len(page)
            continue
        closing = nxt == "/"
        m = _NAME.match(page, at + 1 + closing)
        if not m:
            at += 1  # a character like others
            continue
        emit(page[begun:at])
        end = _tag_end(page, m.end())
        if end < 0:
            return out  # cut off within a tag
        tag, attrs, at = m[0].lower(), page[m.end() : end], end + 1
        begun = at
        if closing:
            inline = tag in ("p", "b", "i", "a", "span", "em", "strong", "li", "div")
            stack.close((tag,), ("table", "article", "main", "body") if inline else ())
        elif tag in RAW and not attrs.endswith("/"):
            shut = _RAW_END[tag].search(page, at)
            stop = page.find(">", shut.end()) if shut else -1
            at = begun = stop + 1 if stop >= 0 else len(page)
        elif tag not in RAW:
            if tag in ENDS_P:
                stack.close(("p",), ("div", "article", "main", "section", "td", "th", "li", "blockquote", "body", "aside", "nav", "footer", "header", "form"))
            if tag in SAME:
                stack.close(SAME[tag], SCOPE[tag])
            if tag not in VOID:
                _, parent, article, link = stack.items[-1] if stack.items else ("", 0, False, False)
                label, factor, is_article = _said(tag, attrs, article)
                key = parent, f"{label} {factor}", article or is_article
                if key not in paths:
                    paths[key] = len(out.factors)
                    out.factors.append(min(factor, out.factors[parent]))
                    out.inside.append(article or is_article and out.factors[parent] == 1.0)
                stack.push(tag, paths[key], out.inside[paths[key]], link or tag == "a")
        block += tag in BLOCKS
    emit(page[begun:])
    return out


def path_scores(page: Page, ratios: bool = True) -> np.ndarray:
    """Score of every path; without ``ratios``, the factor of its names alone, where it has text."""
    n_paths = len(page.factors)
    at, block = (np.array([getattr(n, c) for n in page.nodes], np.int64) for c in ("path", "block"))
    length = np.array([sum(map(len, n.text.split())) for n in page.nodes], float)
    marks = np.array([sum(map(PUNCTUATION.__contains__, n.text)) for n in page.nodes], float)
    some = length > 0
    if not some.any():
        return np.zeros(n_paths)
    linked = length * np.array([n.link for n in page.nodes])
    inside = np.array(page.inside)
    factor = np.array(page.factors)
    if (inside[at] & some & (factor[at] == 1.0)).any():
        factor = np.where(inside, factor, FLOOR)
    count = np.maximum(np.bincount(at[some], minlength=n_paths), 1)
    if not ratios:
        return np.where(np.bincount(at[some], minlength=n_paths) > 0, factor, 0.0)
    in_links = np.bincount(block, linked) / np.maximum(np.bincount(block, length), 1)  # share of each block's text
    unlinked = np.bincount(at, length * (1 - 0.95 * in_links[block]) ** 2, n_paths)
    own = unlinked / count * (1 + np.bincount(at, marks, n_paths) / count)
    reach = int(3 * SIGMA)
    kernel = np.exp(-0.5 * (np.arange(-reach, reach + 1) / SIGMA) ** 2)
    weighed = (own * factor)[at[some]]
    smooth = np.convolve(weighed, kernel)[reach : reach + len(weighed)] / np.convolve(np.ones(len(weighed)), kernel)[reach : reach + len(weighed)]
    mean = np.bincount(at[some], smooth, n_paths) / count
    return np.sqrt(np.sqrt(own * mean)) * factor  # the root keeps short headings and long paragraphs of an article within one range


def kept_paths(page: Page, ratios: bool = True) -> set[int]:
    """Paths whose score reaches the threshold."""
    scores = path_scores(page, ratios)
    best = scores.max(initial=0.0)
    return set(np.flatnonzero((scores >= THRESHOLD * best) & (scores > 0)).tolist())


def main_text(page: str | None, ratios: bool = True) -> str:
    """The article of a page: references decoded, white space in a block as one space, blocks joined by one space. Null and empty pages have none."""
    if not page:
        return ""
    found = read(page)
    keep = kept_paths(found, ratios)
    blocks: list[str] = []
    parts: list[str] = []
    current = -1
    for n in found.nodes:
        if n.path not in keep:
            continue
        if n.block != current:
            blocks.append("".join(parts))
            parts, current = [], n.block
        parts.append(n.text)
    blocks.append("".join(parts))
    return " ".join(t for t in (" ".join(b.split()) for b in blocks) if t)


def extract(pages: DataFrame, html_col: str = "html") -> DataFrame:
    """All rows and columns of ``pages`` but the html, plus text and n_chars (replaced if there).

    Each page is read whole and by itself, so repeated rows and ids make no difference; null and empty pages give an empty text. Empty table: no rows.
    """
    keep = [f for f in pages.schema.fields if f.name not in ("text", "n_chars", html_col)]
    schema = T.StructType([*keep, T.StructField("text", T.StringType()), T.StructField("n_chars", T.LongType())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            at = batch.schema.get_field_index
            texts = [main_text(p.as_py()) for p in batch.column(at(html_col))]
            # a reference may name half of a character, which no UTF-8 text can hold
            texts = [t.encode("utf-8", "replace").decode() for t in texts]
            cols = [*[batch.column(at(f.name)) for f in keep], pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())]
            yield pa.RecordBatch.from_arrays(cols, names=schema.names)

    return pages.select(*[f"`{f.name}`" for f in pages.schema.fields]).mapInArrow(run, schema)
