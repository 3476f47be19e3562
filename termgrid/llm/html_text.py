"""Main text of web pages by a minimum cut between content and boilerplate."""

from __future__ import annotations

import html as entities
import math
import re
from collections import deque

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..shipping import shipped
from .common import unused

#: Elements whose text is never shown (with markup inside, or raw up to their end tag), elements that start a
#: block, elements without an end.
HIDDEN = frozenset("template object svg math canvas select option optgroup datalist audio video".split())
RAW = frozenset("script style noscript title iframe textarea xmp noembed noframes".split())
BLOCKS = frozenset("html body address article aside blockquote center dd details dialog dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr legend li main menu nav ol p pre section summary table tbody td tfoot th thead tr ul caption".split())
EMPTY = frozenset("area base br col embed hr img input link meta param source track wbr".split())
#: Hidden elements that the start of a block ends, as blocks can't stand in them.
NO_BLOCKS = frozenset("svg math select option optgroup datalist".split())
#: Elements closed by the start of the elements named.
CLOSED_BY = {"p": BLOCKS, "li": frozenset(["li"]), "dd": frozenset(["dd", "dt"]), "dt": frozenset(["dd", "dt"]), "tr": frozenset(["tr", "tbody", "tfoot"]), "td": frozenset(["td", "th", "tr"]), "th": frozenset(["td", "th", "tr"])}
#: Words of names and roles, and elements, that speak against or for content.
AGAINST_TAG = frozenset("nav header footer aside form menu button dialog fieldset".split())
AGAINST = re.compile(r"(?<![a-z])(ads?|advert\w*|promo\w*|sponsor\w*|banner|nav\w*|menu|footer|header|masthead|side-?bar|widget\w*|cookies?|consent|notices?|alert|popup|modal|overlay|newsletter|subscri\w*|signup|login|share|sharing|social|related|recommend\w*|comments?|commentlist|disqus|respond|repl(y|ies)|breadcrumbs?|pagination|pager|copyright|legal|disclaimer|search|toolbar|tags|meta|byline|skip|print-only|hidden|contentinfo|complementary|navigation)(?![a-z])")
FOR = re.compile(r"(?<![a-z])(article|content|main|post|story|entry|body|text)(?![a-z])")
_TOKEN = re.compile(r"<!--.*?(?:-->|$)|<!\[CDATA\[.*?(?:\]\]>|$)|<(/?)([a-zA-Z][a-zA-Z0-9:-]*)((?:[^<>\"']|\"[^\"<]*\"|'[^'<]*'|[\"'])*)(?:>|$|(?=<))|<[!?][^>]*(?:>|$)", re.S)
_NAMES = re.compile(r"(?:^|\s)(?:class|id|role)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+))", re.I)
#: Strength of the edges between neighbours, by the elements they share.
NEXT_TO, SAME_PARENT, FAR = 1.2, 2.0, 0.15
#: Weights of what a block itself shows (see ``traits``) before training: constant, words, sentence end, link share, text
#: element, list or table cell, copyright. Training keeps near them by ``HOLD``, the more so the fewer blocks it has.
PRIOR, HOLD = (-0.9, 0.9, 1.0, -4.0, 0.8, -0.5, -2.0), 20.0
#: Pages, about, on which the classifier is trained; the most labelled blocks of a class that weigh against ``PRIOR``.
SAMPLE, EVIDENCE = 2000, 400.0


class Place:
    """An open block element: its parent, its depth, and what the elements from the root down to it say of their content."""

    __slots__ = ("above", "article", "boiler", "depth", "lean", "name")

    def __init__(self, above: Place | None, name: str, names: str):
        self.above, self.name = above, name
        self.depth = above.depth + 1 if above else 0
        self.article = bool(above and above.article) or name == "article"
        self.boiler = bool(above and above.boiler) or name in AGAINST_TAG
        self.lean = above.lean if above else 0.0
        if name in AGAINST_TAG:
            # a header inside an article may hold its title
            self.lean -= 3.0 if name == "header" and above and above.article else 9.0
        if name in ("article", "main"):
            self.lean += 3.5
        if names:
            # names at the root speak of the layout, not of the block
            if name not in ("body", "html") and AGAINST.search(names):
                self.lean -= 8.0
                self.boiler = True
            elif FOR.search(names):
                self.lean += 1.2


def _end_tag(name: str) -> re.Pattern:
    if name not in _END:
        _END[name] = re.compile(f"</{name}(?![a-z0-9:-])[^>]*(?:>|$)", re.I | re.A)
    return _END[name]


_END: dict[str, re.Pattern] = {}


def blocks(page: str) -> list[tuple[str, int, Place | None]]:
    """Text blocks in page order: decoded text, its characters within links, the block element around it.

    Every open element is left once, so the time grows with the length of the page, not with its depth.
    """
    out: list[tuple[str, int, Place | None]] = []
    #: open elements as (name, place if a block else None); how many of each name; open hidden elements
    stack: list[tuple[str, Place | None]] = []
    count: dict[str, int] = {}
    places: list[Place] = []
    ends: dict[str, int] = {}
    text, linked, hidden = [], 0, 0

    def close() -> None:
        nonlocal linked
        joined = " ".join("".join(text).split())
        if joined:
            out.append((joined, linked, places[-1] if places else None))
        text.clear()
        linked = 0

    def add(raw: str) -> None:
        nonlocal linked
        if raw and not hidden:
            decoded = entities.unescape(raw)
            text.append(decoded)
            if count.get("a"):
                linked += len(decoded.strip())

    def pop() -> None:
        nonlocal hidden
        name, place = stack[-1]
        if place is not None:
            close()
            places.pop()
        hidden -= name in HIDDEN
        count[name] -= 1
        stack.pop()

    def end_after(name: str, at: int) -> int:
        """Where the next end tag of the name starts, -1 if there is none; each stretch of the page is searched once a name."""
        if ends.get(name, 0) != -1 and ends.get(name, 0) <= at:
            m = _end_tag(name).search(page, at)
            ends[name] = m.start() + 1 if m else -1
        return ends[name] - 1 if ends[name] != -1 else -1

    at, n = 0, len(page)
    while at < n:
        m = _TOKEN.search(page, at)
        if m is None:
            add(page[at:])
            break
        add(page[at : m.start()])
        at = max(m.end(), at + 1)
        if not m[2]:
            if m[0].startswith("<![CDATA[") and not hidden:
                text.append(m[0][9:].removesuffix("]]>"))
            continue
        name = m[2].lower()
        if name == "br":
            if not hidden:
                text.append(" ")
            continue
        if m[1]:
            if count.get(name):
                k = len(stack) - 1
                while stack[k][0] != name and (name in BLOCKS or name in HIDDEN or stack[k][1] is None):
                    k -= 1
                if stack[k][0] == name:  # an inline end doesn't cross a block
                    while len(stack) > k:
                        pop()
            continue
        if name in RAW:
            if not m[3].endswith("/") or name in ("script", "style"):
                end = end_after(name, at)
                if end >= 0:
                    at = _end_tag(name).match(page, end).end()
                elif name in ("script", "style"):
                    break
            continue
        if name in HIDDEN:
            if m[3].endswith("/"):
                continue
            if name in ("option", "optgroup") and count.get("option"):
                while stack[-1][0] != "option":
                    pop()
                pop()
            # hidden elements without an end would hide the rest of the page
            if name in NO_BLOCKS or end_after(name, at) >= 0:
                stack.append((name, None))
                count[name] = count.get(name, 0) + 1
                hidden += 1
            continue
        if name in BLOCKS:
            while hidden and stack[-1][0] in NO_BLOCKS:
                pop()
            if hidden:
                continue
            close()
            while stack and (stack[-1][1] is None or name in CLOSED_BY.get(stack[-1][0], ())):
                pop()
        if name in EMPTY or m[3].endswith("/") or hidden:
            continue
        place = None
        if name in BLOCKS:
            place = Place(places[-1] if places else None, name, " ".join("".join(x) for x in _NAMES.findall(m[3])).lower())
            places.append(place)
        stack.append((name, place))
        count[name] = count.get(name, 0) + 1
    close()
    return out


def traits(text: str, linked: int, place: Place | None) -> tuple[int, int, int, int, int, int]:
    """What a block itself shows, in few values: words (80 at most), sentence end, tenths within links, text element, list
    or table cell, copyright."""
    name = place.name if place is not None else ""
    return (
        min(text.count(" ") + 1, 80),
        int(text[-1] in ".!?:…\"”»"),
        round(10 * min(1.0, linked / max(1, len(text)))),
        int(name in ("h1", "h2", "h3", "h4", "h5", "h6", "p", "pre", "blockquote", "figcaption")),
        int(name in ("li", "td", "th", "dt")),
        int(re.match(r"(©|\(c\)|copyright\b|all rights reserved)", text, re.I) is not None),
    )


def leaning(text: str, linked: int, place: Place | None, weights: tuple[float, ...] = PRIOR) -> float:
    """Log-odds that a block is content: a linear classifier of what it shows, and what the elements around it say."""
    words, ends, links, *rest = traits(text, linked, place)
    shown = (1.0, math.log1p(words) / math.log(10), ends, links / 10, *rest)
    return sum(w * x for w, x in zip(weights, shown, strict=True)) + (place.lean if place is not None else 0.0)


def fit(cells: list[tuple[tuple[int, ...], bool, int]]) -> tuple[float, ...]:
    """Weights from ``(traits, is content, blocks)``: logistic regression with a Gaussian prior at ``PRIOR``, by Newton steps.

    Both classes weigh the same, as the elements around a block are added to the log-odds afterwards: together as many
    blocks as the smaller class has, ``EVIDENCE`` at most, so a few pages move the weights little. Without blocks of both
    classes they stay at ``PRIOR``.
    """
    prior = np.array(PRIOR)
    n = [sum(c for _, y, c in cells if y == side) for side in (False, True)]
    if not all(n):
        return PRIOR
    cells = sorted(cells)
    t = np.array([c[0] for c in cells], float)
    x = np.column_stack((np.ones(len(t)), np.log1p(t[:, 0]) / math.log(10), t[:, 1], t[:, 2] / 10, t[:, 3:]))
    y = np.array([c[1] for c in cells], float)
    weight = np.array([c[2] * min(*n, EVIDENCE) / n[c[1]] for c in cells], float)
    w = prior.copy()
    loss = lambda w: float((weight * np.logaddexp(0, np.where(y == 1, -1, 1) * (x @ w))).sum() + HOLD / 2 * ((w - prior) ** 2).sum())
    for _ in range(50):
        p = 1 / (1 + np.exp(-(x @ w)))
        slope = x.T @ (weight * (p - y)) + HOLD * (w - prior)
        step = np.linalg.solve((x * (weight * p * (1 - p))[:, None]).T @ x + HOLD * np.eye(len(w)), slope)
        size = 1.0
        while size > 1e-6 and loss(w - size * step) > loss(w):
            size /= 2
        w = w - size * step
        if np.abs(step).max() < 1e-9:
            break
    return tuple(float(v) for v in w)


def smoothness(a: Place | None, b: Place | None) -> float:
    """Strength of the tie between two blocks: whole for children of one element, weaker with each element between."""
    depth = lambda x: x.depth + 1 if x else 0
    apart = 0
    while a is not b and apart <= 3:
        # the deeper one goes up, both if equal, so ``apart`` is the distance of the deeper block from what they share
        x, y = depth(a), depth(b)
        a, b = a.above if x >= y else a, b.above if y >= x else b
        apart += 1
    return SAME_PARENT if apart <= 1 else NEXT_TO / (apart - 1) if apart <= 3 else FAR


def min_cut(scores: list[float], ties: list[tuple[int, int, float]]) -> list[bool]:
    """True for nodes on the content side of a minimum cut, by augmenting level by level."""
    n = len(scores)
    source, sink = n, n + 1
    to, room, of = [], [], [[] for _ in range(n + 2)]

    def edge(a: int, b: int, there: float, back: float) -> None:
        of[a].append(len(to))
        to.append(b)
        room.append(there)
        of[b].append(len(to))
        to.append(a)
        room.append(back)

    for i, s in enumerate(scores):
        edge(source, i, s, 0.0) if s > 0 else edge(i, sink, -s, 0.0)
    for a, b, w in ties:
        edge(a, b, w, w)
    tiny = 1e-9
    while True:
        level = [-1] * (n + 2)
        level[source] = 0
        queue = deque([source])
        while queue:
            a = queue.popleft()
            for e in of[a]:
                if room[e] > tiny and level[to[e]] < 0:
                    level[to[e]] = level[a] + 1
                    queue.append(to[e])
        if level[sink] < 0:
            return [level[i] >= 0 for i in range(n)]
        tried = [0] * (n + 2)
        path: list[int] = []
        a = source
        while True:
            if a == sink:
                least = min(room[e] for e in path)
                for k, e in enumerate(path):
                    room[e] -= least
                    room[e ^ 1] += least
                back = next(k for k, e in enumerate(path) if room[e] <= tiny)
                a = to[path[back] ^ 1]
                del path[back:]
                continue
            while tried[a] < len(of[a]):
                e = of[a][tried[a]]
                if room[e] > tiny and level[to[e]] == level[a] + 1:
                    path.append(e)
                    a = to[e]
                    break
                tried[a] += 1
            else:
                if a == source:
                    break
                level[a] = -1
                a = to[path.pop() ^ 1]


def main_text(page: str | None, weights: tuple[float, ...] = PRIOR) -> str:
    """Content blocks joined by an empty line; empty for null and empty pages and pages without content."""
    found = blocks(page or "")
    if not found:
        return ""
    scores = [leaning(*b, weights) for b in found]
    ties = [(i, i + 1, smoothness(found[i][2], found[i + 1][2])) for i in range(len(found) - 1)]
    last: dict[int, int] = {}
    for i, (_, _, place) in enumerate(found):
        holder = id(place.above) if place is not None and place.above is not None else 0
        if holder in last and last[holder] < i - 1:
            ties.append((last[holder], i, SAME_PARENT / 2))
        last[holder] = i
    # two cuts are possible where costs cancel; the source side is the smaller content
    return "\n\n".join(b[0] for b, kept in zip(found, min_cut(scores, ties)) if kept)


def _labelled(batches):
    """``traits``, class and number of the blocks whose elements tell their class, summed over a batch."""
    for batch in batches:
        cells: dict[tuple, int] = {}
        for page in batch.column(0).to_pylist():
            for text, linked, place in blocks(page):
                if place is not None and (place.boiler or place.article):
                    key = (traits(text, linked, place), not place.boiler)
                    cells[key] = cells.get(key, 0) + 1
        yield pa.RecordBatch.from_arrays([pa.array([list(k[0]) for k in cells], pa.list_(pa.int32())), pa.array([k[1] for k in cells], pa.bool_()), pa.array(list(cells.values()), pa.int64())], ["traits", "content", "n"])


def train(pages: DataFrame, sample: int = SAMPLE) -> tuple[float, ...]:
    """Weights of the classifier, fitted on the pages themselves.

    Pages carry no labels, but elements do: a block inside ``article`` and nothing that speaks against content counts as
    content, one inside ``nav``, ``footer`` or an element of such a name as boilerplate; other blocks don't train. What a
    block itself shows is learned from those, so that it decides where elements say nothing. About ``sample`` pages, chosen
    by a hash of the row, are used, copies of a row once. Only counts of equal traits reach the driver, at most some 20000.
    """
    filled = pages.where("html is not null and html <> ''")
    n = filled.count()
    key, page = unused("page_key", pages), unused("page_html", pages)
    rows = filled.select(F.xxhash64(F.col("page_id").cast("string"), F.col("url").cast("string"), "html").alias(key), F.col("html").alias(page))
    if n > sample:
        rows = rows.where(F.pmod(F.col(key), F.lit(1 << 30)) < int((1 << 30) * sample / n))
    rows = rows.groupBy(key).agg(F.min(page).alias(page)).select(page)
    cells = shipped(rows).mapInArrow(_labelled, "traits array<int>, content boolean, n long").groupBy("traits", "content").agg(F.sum("n").alias("n"))
    return fit([(tuple(r.traits), r.content, r.n) for r in cells.collect()])


def extract(pages: DataFrame, sample: int = SAMPLE) -> DataFrame:
    """``page_id, url, text, n_chars`` of each row of ``pages``.

    Blocks of a page are nodes; a linear classifier's log-odds, trained on about ``sample`` pages, tie each to the content
    or the boilerplate terminal, neighbours in the page and under one element are tied to each other, and a maximum flow
    finds the cheapest cut. White space within a block is one space. Null and empty html gives an empty text and doesn't
    train. Rows keep their number and ids as they are; copies of a row have one text. Other columns don't matter.
    """
    weights = train(pages, sample)

    def run(batches):
        for batch in batches:
            texts = [main_text(h, weights) for h in batch.column(2).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], ["page_id", "url", "text", "n_chars"])

    return shipped(pages).select(F.col("page_id").cast("long").alias("page_id"), "url", "html").mapInArrow(run, "page_id long, url string, text string, n_chars long")
