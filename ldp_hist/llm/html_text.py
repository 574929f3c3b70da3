"""HTML main-text extraction by minimum-cut labelling of a page's blocks.

A fitted classifier over text, link, tag and name features gives each block its terminal capacities; page order and nearness
in the document tree give the smoothness edges; the minimum cut separates content from boilerplate.
"""

from __future__ import annotations

import html
import re
from collections import Counter, deque
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

_TOKEN = re.compile(r"""<!--.*?(?:-->|\Z)|<!\[CDATA\[.*?(?:\]\]>|\Z)|<[!?][^>]*(?:>|\Z)|<(/?)([a-zA-Z][^\s/>]*)((?:[^>"']++|"[^"]*+"|'[^']*+')*+|[^>]*+)(?:>|\Z)""", re.S)
_ATTRIBUTE = re.compile(r"""\b(class|id|role|hidden|aria-hidden)\b(?:\s*=\s*("[^"]*"|'[^']*'|[^\s>]+))?""", re.I)
# Fixed values of HTML and of common page templates.
RAW = frozenset("script style textarea noscript template iframe xmp noembed noframes svg math".split())
BLOCK = frozenset(
    "address article aside blockquote body button caption center dd details dialog div dl dt fieldset figcaption figure footer form "
    "h1 h2 h3 h4 h5 h6 head header hgroup hr html legend li main menu nav ol optgroup option p pre search section select summary "
    "table tbody td tfoot th thead title tr ul".split()
)
_END = {name: re.compile(rf"</{name}\b[^>]*>", re.I) for name in RAW}
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
OUTSIDE = frozenset("head title nav footer aside form button select menu dialog search option".split())
CLOSED_BY = {"p": BLOCK - {"button", "option", "caption", "body", "html"}, "li": {"li"}, "dt": {"dt", "dd"}, "dd": {"dt", "dd"}, "option": {"option"},
             "tr": {"tr", "tbody", "tfoot"}, "td": {"td", "th", "tr"}, "th": {"td", "th", "tr"}, "head": {"body"}}
SCOPE = frozenset("ul ol dl table article section div nav header footer aside main form body html td blockquote".split())
#: Words by which class and id values name what an element is, and words that say nothing by themselves.
OUT_WORDS = frozenset(
    "ad ads adsense advert adverts advertisement advertisements banner breadcrumb breadcrumbs comment commentlist comments consent cookie cookies disqus footer "
    "gdpr masthead menu modal nav navbar navigation newsletter notice notices overlay popup promo promoted related replies respond share sharing sidebar social "
    "sponsor sponsored subscribe toolbar widget widgets".split()
)
IN_WORDS = frozenset("article body content entry main page post story text".split())
PLAIN_WORDS = frozenset("area bar block box container form group holder inner item list outer panel row section slot unit wrap wrapper".split())
_PARTS = re.compile(r"[^a-z]+")
OUT_ROLES = frozenset("navigation banner contentinfo complementary search form alert dialog alertdialog menu menubar toolbar".split())
HEADINGS = frozenset("h1 h2 h3 h4 h5 h6".split())
SURE = 1_000_000


@dataclass
class Element:
    """What an open tag says, its ancestors included where that is said."""

    name: str
    parent: int
    depth: int
    outside: bool  # it or an ancestor is a menu, footer, form, ... by tag, role or attribute
    article: bool  # within the page's article
    main: bool
    remark: bool  # within an article that is itself within the article: by HTML's definition a comment on it
    named: int  # its own names: 2 if one of them says it is boilerplate, 1 if one has such a part, -2 for content
    holds: bool = False  # an article, main or h1 is within


@dataclass
class Block:
    """A run of text between block boundaries in one element, and how many elements up lead to the block before."""

    text: str
    element: int
    linked: int
    meet: int


def naming(label: str) -> int:
    """What the class and id values ``label`` say of an element.

    A value all of whose words name boilerplate ("ad", "cookie-notice", "comment-list") is its author's word for the
    element. One that only has such a part ("comments-open", "has-sidebar") tells of a state, and little. Names for both cancel out.
    """
    out = inner = part = False
    for value in label.split():
        words = [w for w in _PARTS.split(value) if w]
        telling = [w for w in words if w not in PLAIN_WORDS]
        if telling and all(w in OUT_WORDS for w in telling):
            out = True
        elif telling and all(w in IN_WORDS for w in telling):
            inner = True
        else:
            part |= any(w in OUT_WORDS for w in words)
    return 0 if out and inner else 2 if out else -2 if inner else int(part)


def blocks_of(page: str) -> tuple[list[Element], list[Block]]:
    """The page's elements and blocks in order; markup, comments, scripts and styles are gone, references decoded.

    Time is linear in the page: an element knows its parent, and ancestors are marked once each.
    """
    elements, blocks = [Element("", -1, 0, False, False, False, False, 0)], []
    stack, opened = [0], Counter()
    parts: list[str] = []
    links, linked, at, meet, articles = 0, 0, 0, 0, 0

    def flush() -> None:
        nonlocal linked, meet
        text = " ".join("".join(parts).split())
        if text:
            blocks.append(Block(text, stack[-1], min(linked, len(text)), min(meet, len(stack) - 1)))
            meet = len(stack) - 1
        parts.clear()
        linked = 0

    def close(depth: int) -> None:
        nonlocal meet
        for i in stack[depth:]:
            opened[elements[i].name] -= 1
        del stack[depth:]
        meet = min(meet, len(stack) - 1)

    def mark(i: int) -> None:
        while i >= 0 and not elements[i].holds:
            elements[i].holds = True
            i = elements[i].parent

    def add(raw: str) -> None:
        nonlocal linked
        if raw:
            text = html.unescape(raw)
            parts.append(text)
            if links:
                linked += len(text)

    while True:
        m = _TOKEN.search(page, at)
        add(page[at : m.start() if m else len(page)])
        if not m:
            break
        at = m.end()
        if m[0].startswith("<![CDATA["):
            add(html.escape(m[0][9:].removesuffix("]]>"), quote=False))
        if not m[2]:
            continue
        name = m[2].lower()
        if m[1]:
            if name == "a":
                links = max(0, links - 1)
            elif name == "br":
                parts.append(" ")
            elif name in BLOCK:
                flush()
                for depth in range(len(stack) - 1, 0, -1) if opened[name] else ():
                    if elements[stack[depth]].name == name:
                        close(depth)
                        break
                    if name in ("p", "li", "dt", "dd") and elements[stack[depth]].name in SCOPE:
                        break
            continue
        if name in RAW:
            end = _END[name].search(page, at)
            if not m[3].endswith("/"):
                at = end.end() if end else len(page)
            parts.append(" ")
        elif name == "a":
            links = 1
        elif name in VOID:
            if name == "hr":
                flush()
            elif name == "br":
                parts.append(" ")
        elif name in BLOCK:
            flush()
            links = 0 if name != "p" else links
            while len(stack) > 1 and name in CLOSED_BY.get(elements[stack[-1]].name, ()):
                close(len(stack) - 1)
            up = elements[stack[-1]]
            values = {k.lower(): v.strip("\"'").lower() for k, v in _ATTRIBUTE.findall(m[3])} if m[3] else {}
            named = 0 if name in ("html", "body", "main") else naming(f"{values.get('class', '')} {values.get('id', '')}")
            known = up.article or up.main or up.named == -2
            e = Element(
                name, stack[-1], len(stack), up.outside or name in OUTSIDE or (name == "header" and not known) or values.get("role") in OUT_ROLES or "hidden" in values,
                up.article, up.main or name == "main" or values.get("role") == "main", up.remark, named,
            )
            if name == "article":
                if up.article:
                    e.remark = True
                elif not articles or not (named == 2 or _named_out(elements, stack)):
                    e.article, e.named = True, min(named, 0)
                    articles += 1
            elements.append(e)
            if (name == "article" and e.article and not e.remark) or name in ("main", "h1"):
                mark(len(elements) - 1)
            stack.append(len(elements) - 1)
            opened[name] += 1
    flush()
    return elements, blocks


def _named_out(elements: list[Element], stack: list[int]) -> bool:
    return any(elements[i].named == 2 for i in stack)


#: Per block: text's length in hundreds (400 at most), share of linked characters, sentence ends per hundred characters, is it a
#: heading, a list item, a table cell, has its element a boilerplate name, part of such a name, a name for content, and one.
FEATURES = 10
#: Weights before any page is seen: text and sentences speak for content, links against it, names as far as they go.
PRIOR = np.array([1.0, -6.0, 0.3, 1.0, 0.0, 0.3, -12.0, -1.0, 1.0, 0.05])
#: How far the markup of article and main moves a block: within, elsewhere on a page that has it, and a remark.
ARTICLE, MAIN, REMARK = 5.0, 3.0, -14.0
#: The bound on the pages that weights are fitted on, and the strength by which they are held to ``PRIOR``.
SAMPLE_PAGES, RIDGE = 2_000, 50.0


def _names(elements: list[Element]) -> list[int]:
    """Of every element the strongest word for boilerplate (or, failing it, for content) of itself and its ancestors.

    A wrapper of the article, the main part or the h1 is neither, whatever its names are.
    """
    out: list[int] = []
    for e in elements:
        own, up = 0 if e.holds and e.named > 0 else e.named, out[e.parent] if e.parent >= 0 else 0
        out.append(max(own, up) if own > 0 or up > 0 else min(own, up))
    return out


def features(elements: list[Element], blocks: list[Block]) -> np.ndarray:
    x, names = np.zeros((len(blocks), FEATURES)), _names(elements)
    for row, b in zip(x, blocks, strict=True):
        n, tag, named = len(b.text), elements[b.element].name, names[b.element]
        ends = b.text.count(".") + b.text.count("!") + b.text.count("?")
        row[:] = min(n, 400) / 100, b.linked / n, min(5.0, 100 * ends / n), tag in HEADINGS, tag in ("li", "dd", "dt"), tag in ("td", "th"), named == 2, named == 1, named == -2, 1
    return x


def markup(elements: list[Element], blocks: list[Block]) -> tuple[np.ndarray, np.ndarray]:
    """By block: whether its tags alone put it outside, and what article and main say."""
    has_article, has_main = any(e.article for e in elements), any(e.main for e in elements)
    outside, value = np.zeros(len(blocks), bool), np.zeros(len(blocks))
    for i, b in enumerate(blocks):
        e = elements[b.element]
        outside[i] = e.outside
        if e.remark:
            value[i] = REMARK
        elif has_article:
            value[i] = ARTICLE if e.article else -ARTICLE
        elif has_main:
            value[i] = MAIN if e.main else -MAIN
    return outside, value


def fit_weights(pages: list[str], ridge: float = RIDGE) -> np.ndarray:
    """Logistic regression of ``features``, by Newton's method, held to ``PRIOR`` by ``ridge``.

    No page is labelled, but most mark their article: on those, its blocks are content, all others boilerplate, and what the
    features learn there is what decides on pages without such marks. Weights of names keep their prior: within an
    article the markup says nothing about adverts, so there is nothing to learn them from.
    """
    xs, ys = [], []
    for page in pages:
        elements, blocks = blocks_of(page)
        if blocks and any(e.article for e in elements):
            xs.append(features(elements, blocks))
            outside, value = markup(elements, blocks)
            ys.append(~outside & (value > 0))
    if not xs:
        return PRIOR.copy()
    x, y, w = np.concatenate(xs), np.concatenate(ys).astype(float), PRIOR.copy()
    free = np.array([True] * 6 + [False] * 3 + [True])
    hold = np.diag(np.full(free.sum(), ridge))
    for _ in range(20):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        gradient = x[:, free].T @ (p - y) + ridge * (w - PRIOR)[free]
        step = np.linalg.solve((x[:, free] * (p * (1 - p))[:, None]).T @ x[:, free] + hold, gradient)
        w[free] -= step
        if np.abs(step).max() < 1e-6:
            break
    return np.round(w, 4)


def costs(elements: list[Element], blocks: list[Block], weights: np.ndarray) -> list[tuple[int, int]]:
    """What it costs to call each block boilerplate, and to call it content (the terminal capacities)."""
    outside, value = markup(elements, blocks)
    score = np.rint(100 * (value + features(elements, blocks) @ weights)).astype(int)
    return [(0, SURE) if o else (int(v), 0) if v > 0 else (0, int(-v)) for o, v in zip(outside, score, strict=True)]


def edges(elements: list[Element], blocks: list[Block]) -> dict[tuple[int, int], int]:
    """Smoothness capacities: between neighbours in page order, and neighbours under the same parent element.

    They fall with the number of elements that one has to leave and enter between the two blocks.
    """
    out: dict[tuple[int, int], int] = {}
    last: dict[int, int] = {}
    for i, b in enumerate(blocks):
        e = elements[b.element]
        if i:
            steps = elements[blocks[i - 1].element].depth + e.depth - 2 * b.meet
            out[i - 1, i] = round(200 / (1 + steps))
        j = last.get(e.parent, i - 1)
        if 0 <= j < i - 1:
            steps = elements[blocks[j].element].depth + e.depth - 2 * max(e.depth - 1, 0)
            out[j, i] = round(200 / (1 + steps))
        last[e.parent] = i
    return {k: c for k, c in out.items() if c}


def min_cut(terminals: list[tuple[int, int]], links: dict[tuple[int, int], int]) -> list[bool]:
    """For each node whether it stays with the source in a minimum cut (Dinic's algorithm).

    A node whose terminal difference outweighs all its open links is settled first and its links are folded into its
    neighbours' terminals; that leaves the cut's value as it is and most pages without a flow problem.
    """
    n = len(terminals)
    lean = [a - b for a, b in terminals]
    near: list[dict[int, int]] = [{} for _ in range(n)]
    for (i, j), c in links.items():
        near[i][j] = near[i].get(j, 0) + c
        near[j][i] = near[j].get(i, 0) + c
    side: list[bool | None] = [None] * n
    queue = deque(range(n))
    while queue:
        i = queue.popleft()
        if side[i] is None and abs(lean[i]) > sum(near[i].values()):
            side[i] = lean[i] > 0
            for j, c in near[i].items():
                lean[j] += c if side[i] else -c
                del near[j][i]
                queue.append(j)
            near[i] = {}
    left = [i for i in range(n) if side[i] is None]
    if left:
        reached = _flow(left, lean, near)
        for i in left:
            side[i] = i in reached
    return [bool(s) for s in side]


def _flow(nodes: list[int], lean: list[int], near: list[dict[int, int]]) -> set[int]:
    source, sink = -1, -2
    room: dict[int, dict[int, int]] = {i: dict(near[i]) for i in nodes} | {source: {}, sink: {}}
    for i in nodes:
        if lean[i] > 0:
            room[source][i], room[i][source] = lean[i], 0
        else:
            room[i][sink], room[sink][i] = -lean[i], 0
    while True:
        level, queue = {source: 0}, deque([source])
        while queue:
            x = queue.popleft()
            for y, c in room[x].items():
                if c and y not in level:
                    level[y] = level[x] + 1
                    queue.append(y)
        if sink not in level:
            return set(level)
        turn = {x: list(room[x]) for x in room}
        path = [source]
        while path:
            x = path[-1]
            if x == sink:
                least = min(room[a][b] for a, b in zip(path, path[1:], strict=False))
                for a, b in zip(path, path[1:], strict=False):
                    room[a][b] -= least
                    room[b][a] += least
                path = [source]
                continue
            while turn[x] and not (room[x][turn[x][-1]] and level.get(turn[x][-1]) == level[x] + 1):
                turn[x].pop()
            if turn[x]:
                path.append(turn[x][-1])
            else:
                path.pop()
                if path:
                    turn[path[-1]].pop()


def main_text(page: str | None, weights: np.ndarray = PRIOR) -> str:
    """The text of the blocks that the minimum cut leaves with content, joined by one space in page order."""
    elements, blocks = blocks_of(page or "")
    stays = min_cut(costs(elements, blocks, weights), edges(elements, blocks))
    return " ".join(b.text for b, s in zip(blocks, stays, strict=True) if s)


def _extract(weights: np.ndarray):
    def run(batches):
        for batch in batches:
            for at in range(0, batch.num_rows, 512):
                part = batch.slice(at, 512)
                texts = [main_text(p.as_py(), weights) for p in part.column(2)]
                yield pa.record_batch([part.column(0), part.column(1), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())],
                                      names=["page_id", "url", "text", "n_chars"])

    return run


def train(pages: DataFrame, bound: int = SAMPLE_PAGES) -> np.ndarray:
    """Weights fitted on at most ``bound`` pages, those of the least hashes; what the classifier is applied to is all pages."""
    total = pages.count()
    if not total:
        return PRIOR.copy()
    order = F.xxhash64(F.lit("sample"), "page_id", "html")
    # Twice as many as asked for are below this hash, give or take; the least of them are taken.
    below = min((1 << 63) - 1, -(1 << 63) + (1 << 65) * bound // total)
    some = pages.where(order <= below).select(order.alias("o"), "html").orderBy("o", "html").limit(bound)
    return fit_weights([r["html"] or "" for r in some.collect()])


def extract_pages(pages: DataFrame) -> DataFrame:
    """page_id, url, text and n_chars for every row of ``pages``; null and empty html give the empty text.

    The classifier is fitted on a bounded sample of the same pages. Repeated rows give repeated results, null ids and addresses are carried,
    other columns are ignored, and an empty table gives an empty result. Long and deeply nested pages take time in proportion.
    """
    read = pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), F.col("html").cast("string").alias("html"))
    return read.mapInArrow(_extract(train(read)), "page_id long, url string, text string, n_chars long")
