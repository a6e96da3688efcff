"""Main text of web pages by tag-path ratios.

A page is read once, in time that grows with its length, into blocks: runs of text between block-level tags, each
with the path of block tags from the root. Per path the characters, the punctuation marks and the blocks are
summed; a path's ratio is characters per block, another is punctuation per block. Each block
takes its path's ratios, they are smoothed along the page with a small Gaussian window, scaled to
the page's largest and fused by their product. Paths whose mean fused value reaches SHARE of the page's largest
are content, and their nearest common ancestor is the article. Below it headings, lists and short
paragraphs stay with the text around them, but a container without any content path goes when none of its paths
reaches LEAST of the largest. Parts that are never article text (menus, page headers and footers, sidebars,
forms, notices, adverts, reader comments, scripts and styles) are left out before counting, by
their tag, role, or the words of their class and id.

Null or empty pages have empty text. A tag, comment, script or style that never ends takes the rest of the page, as in
browsers; an unclosed button or drawing ends with the element around it. Unclosed and misnested tags are read as browsers do: a new
block closes an open paragraph, a close tag closes up to its nearest open tag, inline tags never
take part in a path. Repeated rows each give a row.
"""

from __future__ import annotations

import html
import math
import re
from collections.abc import Iterator
from dataclasses import dataclass, field

import pyarrow as pa
from pyspark.sql import DataFrame

from fairlink.llm.common import RowBuffer, slices

TEXTS = "page_id long, url string, text string, n_chars long"
_SCHEMA = pa.schema([("page_id", pa.int64()), ("url", pa.string()), ("text", pa.string()), ("n_chars", pa.int64())])

# Fixed tag sets of HTML.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
INLINE = frozenset(
    "a abbr acronym b bdi bdo big cite code data del dfn em font i ins kbd label mark q s samp small span strike strong sub sup time tt u var wbr nobr ruby rt rp".split()
)
RAW = frozenset("script style textarea title noscript iframe xmp noembed noframes".split())
AWAY = frozenset("nav footer aside form menu dialog fieldset head template svg math object select button canvas audio video".split())
CONTAINERS = frozenset("div section td".split())
BARRIERS = ("table", "button", "article", "section", "div", "body")
HEADING = frozenset("h1 h2 h3 h4 h5 h6".split())
CLOSES_P = frozenset(
    "address article aside blockquote center details dialog dd dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr li main menu nav ol p pre section table ul body tr td th tbody".split()
)
#: Words of class and id names that mark parts beside the article.
BESIDE = frozenset(
    "ad ads adv advert adverts advertisement advertising sponsor sponsored sponsors promo promotion banner cookie cookies consent gdpr notice notices alert newsletter subscribe subscription signup "
    "nav navbar navigation menu breadcrumb breadcrumbs sidebar aside widget related recommended recommendations share sharing social comment comments disqus reply replies respond "
    "footer masthead popup modal overlay toolbar pagination pager login search rail discussion feedback reactions announcement disclaimer legal copyright outbrain taboola".split()
)
ROLES = frozenset("navigation banner contentinfo complementary search form dialog alert".split())

#: Share of the largest fused ratio that makes a path content, and that a container's paths must reach to stay.
SHARE, LEAST = 0.35, 0.02

_NAME = re.compile(r"/?([a-zA-Z][a-zA-Z0-9:-]*)")
_STOP = re.compile(r"=[ \t\n\r\f]*([\"'])|>")
_ATTRIBUTE = re.compile(r"\b(class|id|role)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s>]+))", re.I)
_WORD = re.compile(r"[A-Z]?[a-z]+|[A-Z]+")
_PUNCTUATION = re.compile(r"[.,;:!?…。，、！？؛،]")
_SPACE = re.compile(r"\s+")


def _beside(tag: str, attributes: str, inside: bool) -> bool:
    """Whether an element starts a part that is not article text."""
    if tag in AWAY or tag == "header" and not inside:
        return True
    if "=" not in attributes:
        return False
    for m in _ATTRIBUTE.finditer(attributes):
        value = m[2] or m[3] or m[4] or ""
        if m[1].lower() == "role":
            if value.strip().lower() in ROLES:
                return True
        elif tag not in ("html", "body", "article", "main") and any(w.lower() in BESIDE for w in _WORD.findall(value)):
            return True
    return False


def _mark(tag: str, attributes: str) -> str:
    """An element's name in a path: containers with a class or id are told apart by it."""
    if tag in ("div", "section", "td", "ul") and "=" in attributes:
        names = [m[2] or m[3] or m[4] or "" for m in _ATTRIBUTE.finditer(attributes) if m[1].lower() != "role"]
        if names:
            return f"{tag}.{'.'.join(names)}"
    return tag


def _tags(page: str) -> Iterator[tuple[int, int, str, bool, str]]:
    """Markup in order: where it starts and ends, tag name (empty for comments and the like), closing, attributes.

    Every character is passed a bounded number of times: what is searched for and not found is not searched for again.
    """
    at, end = page.find("<"), len(page)
    lost: set[str] = set()

    def find(what: str, after: int) -> int:
        if what in lost:
            return -1
        place = page.find(what, after)
        if place < 0:
            lost.add(what)
        return place

    while at >= 0:
        m = _NAME.match(page, at + 1)
        if not m:
            after = page[at + 1 : at + 2]
            if page.startswith("<!--", at):
                stop = find("-->", at + 2)
                yield at, stop + 3 if stop >= 0 else end, "", False, ""
                at = page.find("<", stop + 3) if stop >= 0 else -1
            elif after in ("!", "?", "/") and after:
                stop = find(">", at)
                yield at, stop + 1 if stop >= 0 else end, "", False, ""
                at = page.find("<", stop + 1) if stop >= 0 else -1
            else:  # a sign in the text
                at = page.find("<", at + 1)
            continue
        stop = m.end()
        while True:
            sign = _STOP.search(page, stop)
            if not sign:
                yield at, end, "", False, ""
                return
            stop = sign.end()
            if sign[1] is None:
                break
            close = find(sign[1], stop)  # a quote that never ends is none
            stop = close + 1 if close >= 0 else stop
        name = m[1].lower()
        closing = page[at + 1] == "/"
        if name in RAW and not closing and page[stop - 2] != "/":
            close = re.compile(rf"</{name}(?=[\s/>])[^>]*>?", re.I).search(page, stop)
            yield at, close.end() if close else end, name, False, ""
            at = page.find("<", close.end()) if close else -1
        else:
            yield at, stop, name, closing, page[m.end() : stop - 1]
            at = page.find("<", stop)


@dataclass
class Paths:
    """Tag paths as numbered nodes of a tree; node 0 is the root."""

    parent: list[int] = field(default_factory=lambda: [-1])
    mark: list[str] = field(default_factory=lambda: [""])
    known: dict = field(default_factory=dict)

    def child(self, node: int, mark: str) -> int:
        at = self.known.get((node, mark))
        if at is None:
            at = self.known[node, mark] = len(self.parent)
            self.parent.append(node), self.mark.append(mark)
        return at


def blocks(page: str) -> tuple[Paths, list[tuple[int, str]]]:
    """The page's text blocks in order, each with its path, without the parts beside the article."""
    paths, out = Paths(), []
    stack: list[tuple[str, bool, int]] = []  # block elements; whether one starts a part beside the article; its path
    depths: dict[str, list[int]] = {}  # of each tag's open elements
    hidden, held, at = 0, [], 0

    def flush() -> None:
        if held:
            text = _SPACE.sub(" ", html.unescape("".join(held))).strip()
            held.clear()
            if text:
                out.append((stack[-1][2] if stack else 0, text))

    def pop() -> None:
        nonlocal hidden
        tag, beside, _ = stack.pop()
        depths[tag].pop()
        hidden -= beside

    def top(tag: str) -> int:
        return depths[tag][-1] if depths.get(tag) else -1

    for start, stop, tag, closing, attributes in _tags(page):
        if start > at and not hidden:
            held.append(page[at:start])
        at = stop
        if not tag:
            continue
        if tag == "br":
            held.append(" ")
            continue
        if tag in INLINE:
            continue
        if closing:
            if top(tag) >= 0:
                flush()
                while stack[-1][0] != tag:
                    pop()
                pop()
            elif tag == "p":
                flush()
            continue
        flush()
        if tag in RAW:
            continue
        if tag in CLOSES_P and top("p") > max(map(top, BARRIERS)):
            for _ in range(len(stack) - top("p")):
                pop()
        if tag in VOID or attributes.endswith("/"):
            continue
        if tag in ("li", "dd", "dt", "tr", "td", "th", "option"):
            mates = {"dd": ("dd", "dt"), "dt": ("dd", "dt"), "td": ("td", "th"), "th": ("td", "th"), "tr": ("tr", "td", "th")}.get(tag, (tag,))
            while stack and stack[-1][0] in mates:
                pop()
        beside = _beside(tag, attributes, top("article") >= 0 or top("main") >= 0)
        depths.setdefault(tag, []).append(len(stack))
        stack.append((tag, beside, paths.child(stack[-1][2] if stack else 0, _mark(tag, attributes))))
        hidden += beside
    if at < len(page) and not hidden:
        held.append(page[at:])
    flush()
    return paths, out


def ratios(paths: Paths, found: list[tuple[int, str]]) -> dict[int, float]:
    """The mean smoothed and fused ratio of each path with text."""
    sums: dict[int, list[float]] = {}
    for path, text in found:
        row = sums.setdefault(path, [0, 0, 0])
        row[0] += len(text)
        row[1] += len(_PUNCTUATION.findall(text))
        row[2] += 1
    ratio = {p: (c / n, (m + 0.5) / n) for p, (c, m, n) in sums.items()}
    kernel = [math.exp(-(d * d) / 2) for d in range(3)]
    smooth = []
    for k in (0, 1):
        values = [ratio[p][k] for p, _ in found]
        row = []
        for i in range(len(values)):
            near = [(kernel[abs(d)], values[i + d]) for d in range(-2, 3) if 0 <= i + d < len(values)]
            row.append(sum(w * v for w, v in near) / sum(w for w, _ in near))
        largest = max(row) or 1
        smooth.append([v / largest for v in row])
    article = [False] * len(paths.parent)  # a node comes after its parent
    for node in range(1, len(article)):
        article[node] = paths.mark[node] in ("article", "main") or article[paths.parent[node]]
    fused: dict[int, list[float]] = {}
    for i, (path, _) in enumerate(found):
        fused.setdefault(path, []).append(smooth[0][i] * smooth[1][i] * (4.0 if article[path] else 1.0))
    return {p: sum(v) / len(v) for p, v in fused.items()}


def content(paths: Paths, found: list[tuple[int, str]]) -> set[int]:
    """The paths whose blocks are the main text."""
    mean = ratios(paths, found)
    parent, n = paths.parent, len(paths.parent)
    body = {p: v for p, v in mean.items() if paths.mark[p] not in HEADING and p} or mean
    largest = max(body.values())
    chosen = {p for p, v in body.items() if v >= SHARE * largest}
    # Chosen paths below each node; the deepest node above all of them is the article.
    below, best = [0] * n, [0.0] * n
    for p, v in mean.items():
        below[p] += p in chosen
        best[p] = v
    for node in range(n - 1, 0, -1):
        below[parent[node]] += below[node]
        best[parent[node]] = max(best[parent[node]], best[node])
    root = max(node for node in range(n) if below[node] == len(chosen))
    if root in chosen and root:
        root = parent[root]
    border = node = root
    while node > 0:  # a nested part of an article is not its border
        if paths.mark[node] in ("article", "main"):
            border = node
        node = parent[node]
    kept = [False] * n
    for node in range(n):
        if node == border:
            kept[node] = True
        elif node:
            idle = paths.mark[node].split(".", 1)[0] in CONTAINERS and not below[node] and best[node] < LEAST * largest
            kept[node] = kept[parent[node]] and not idle
    return {p for p in mean if kept[p]}


def main_text(page: str | None) -> str:
    paths, found = blocks(page or "")
    if not found:
        return ""
    chosen = content(paths, found)
    return "\n".join(t for p, t in found if p in chosen)


def extract(web: DataFrame) -> DataFrame:
    """The main text of every page."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        out = RowBuffer(_SCHEMA, 512)
        for keys, urls, sources in slices(batches, "page_id", "url", "html"):
            for key, url, source in zip(keys, urls, sources, strict=True):
                text = main_text(source)
                out.add((key, url, text, len(text)))
                if out.full():
                    yield out.take()
        yield out.take()

    return web.select("page_id", "url", "html").mapInArrow(run, TEXTS)
