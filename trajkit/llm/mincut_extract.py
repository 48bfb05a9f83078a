"""Main-text extraction by minimum-cut labelling of a page's blocks.

A page is cut into text blocks, each with its path in the document tree. A classifier gives each block the
log odds of being content: marks of its ancestors (tags, class names) plus a logistic model of the text itself (length, links,
punctuation, tag). The model is fitted on a bounded sample of pages, with the blocks that marks decide as its labels.
The two negative log probabilities are the block's terminal capacities. Blocks that follow each other, and next siblings, are
joined by smoothness edges that weaken with their distance in the tree. The minimum cut, found by max-flow, labels all
blocks of a page at once. Time and memory grow in proportion to the page, but for very unusual flows.
"""

from __future__ import annotations

import html as entities
import math
import re
from collections import Counter, deque

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from trajkit.llm.common import pieces

#: Element names by role.
BLOCKS = frozenset(
    "address article aside blockquote body button caption center dd details dialog dir div dl dt fieldset figcaption figure footer form "
    "h1 h2 h3 h4 h5 h6 head header hgroup html legend li main menu nav ol optgroup option p pre section select summary table tbody td tfoot th thead tr ul".split()
)
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style noscript template textarea title iframe svg math object canvas audio video xmp".split())
BOILERPLATE_TAGS = frozenset("nav footer aside form menu dialog select button fieldset head".split())
CONTENT_TAGS = frozenset("article main".split())
BOILERPLATE_NAMES = frozenset(
    "nav navbar navigation menu menubar header masthead footer foot sidebar aside rail ad ads advert adverts advertisement advertising adbox banner sponsor sponsored promo promotion "
    "cookie cookies consent gdpr notice notices alert popup modal overlay subscribe subscription newsletter signup login share sharing social related recommended recommendations "
    "comment comments reply replies discussion disqus breadcrumb breadcrumbs pagination pager widget toolbar search copyright legal disclaimer skip hidden form".split()
)
CONTENT_NAMES = frozenset("article content post entry story main maintext body text".split())
#: Names that make even an article element a reader's comment.
COMMENT_NAMES = frozenset("comment comments reply replies discussion disqus".split())
#: Log odds of a mark that decides, of a mere name, of a header; of an unmarked block on a page with marked content, and on one without; what an outer mark keeps.
MARK, NAME, HEADER, OUTSIDE, UNMARKED, OUTER = 4.0, 1.5, -2.0, -1.5, 3.0, 0.25
#: Log odds of a tag of running text.
PROSE, PROSE_TAGS = 1.0, frozenset("p pre blockquote h1 h2 h3 h4 h5 h6 figcaption".split())
#: Smoothness between neighbours, across a mark, between siblings.
NEAR, ACROSS, SIBLING, TINY = 1.6, 0.1, 0.8, 1e-12
#: Weights of the text model where the sample has no marks of both kinds; pages in the sample, and blocks of a page and kind, at most.
PLAIN, SAMPLE_PAGES, PAGE_BLOCKS, RIDGE = (-1.5, 1.5, -4.0, 1.0), 2000, 16, 20.0
_TOKEN = re.compile(r"<!--.*?(?:-->|\Z)|<(/?)([A-Za-z][A-Za-z0-9:-]*)((?:[^<>\"']|\"[^\"]*\"|'[^']*')*)/?>|<[!?][^>]*>|<(?=[/A-Za-z])[^>]*(?:>|\Z)", re.S)
_ATTRIBUTE = re.compile(r"(class|id|role|style|hidden|aria-hidden)(?:\s*=\s*(\"[^\"]*\"|'[^']*'|[^\s>]+))?", re.I)
_WORDS = re.compile(r"[A-Za-z][a-z]*")


class Element:
    """``marks``: log odds that the marks from here up give a block; ``head``: the same for a main heading; ``inside``: in marked content."""

    __slots__ = ("name", "parent", "depth", "hint", "marks", "head", "inside")

    def __init__(self, name: str, parent: "Element | None", hint: int):
        self.name, self.parent, self.hint = name, parent, hint
        self.depth, self.marks, self.head, self.inside = (parent.depth + 1, parent.marks, parent.head, parent.inside) if parent else (0, 0.0, 0.0, False)
        if hint == 1:
            self.marks, self.head = self.marks + NAME, self.head + NAME
        elif hint:
            own = MARK if hint > 0 else -MARK
            self.marks, self.head = own + OUTER * self.marks, own + OUTER * self.head
        elif name == "header":
            self.marks, self.head = self.marks + HEADER, self.head + (0 if self.inside else HEADER)
        self.inside = self.inside or hint > 0


class Block:
    __slots__ = ("text", "element", "links")

    def __init__(self, text: str, element: Element, links: int):
        self.text, self.element, self.links = text, element, links


def hint_of(name: str, attributes: str) -> int:
    """-1: the element marks boilerplate; 2: content, by its tag; 1: content, by a mere name; 0: neither."""
    hint = -1 if name in BOILERPLATE_TAGS else 2 if name in CONTENT_TAGS else 0
    if not attributes or name in ("body", "html"):
        return hint
    for m in _ATTRIBUTE.finditer(attributes):
        key, value = m[1].lower(), (m[2] or "").strip("\"'")
        if key == "hidden" or key == "aria-hidden" and value == "true" or key == "style" and re.search(r"display\s*:\s*none|visibility\s*:\s*hidden", value, re.I):
            return -1
        if key in ("class", "id", "role"):
            words = {w.lower() for w in _WORDS.findall(value)} | set(value.lower().split())
            if key == "role" and words & {"complementary", "contentinfo", "banner", "navigation", "search"}:
                return -1
            if words & (COMMENT_NAMES if name in CONTENT_TAGS else BOILERPLATE_NAMES):
                return -1
            if words & CONTENT_NAMES:
                hint = hint or 1
    return hint


def blocks_of(page: str) -> list[Block]:
    """Text blocks in page order. White space inside a block is one space; character references are decoded; comments, scripts and styles are gone."""
    root = Element("", None, 0)
    stack, out, text, links, in_link, still_open = [root], [], [], 0, 0, Counter()
    at, size = 0, len(page)

    def close():
        nonlocal links
        if text:
            joined = " ".join("".join(text).split())
            if joined:
                out.append(Block(joined, stack[-1], min(links, len(joined))))
            text.clear()
        links = 0

    def end_from(k: int):
        still_open.subtract(e.name for e in stack[k:])
        del stack[k:]

    def add(piece: str):
        nonlocal links
        if piece:
            decoded = entities.unescape(piece) if "&" in piece else piece
            text.append(decoded)
            if in_link:
                links += len(decoded.strip())

    while at < size:
        m = _TOKEN.search(page, at)
        if not m:
            add(page[at:])
            break
        add(page[at : m.start()])
        at = m.end()
        if m[2] is None:
            continue
        name, ends = m[2].lower(), bool(m[1])
        if name in RAW:
            if not ends:
                if name == "title":
                    close()
                end = re.compile(rf"</{name}\s*>", re.I).search(page, at)
                at = end.end() if end else size
            continue
        if name == "br":
            text.append(" ")
        elif name == "a":
            in_link = 0 if ends else 1
        elif name in BLOCKS or name == "hr":
            close()
            if name == "hr":
                continue
            if ends:
                if still_open[name]:
                    end_from(next(k for k in range(len(stack) - 1, 0, -1) if stack[k].name == name))
                in_link = 0 if name in ("nav", "ul", "ol", "footer", "article") else in_link
                continue
            # An open paragraph or item ends where the next block of its kind starts.
            for k in range(len(stack) - 1, 0, -1):
                open_name = stack[k].name
                if open_name == "p" or open_name == name == "li" or open_name in ("dt", "dd") and name in ("dt", "dd") or open_name in ("td", "th") and name in ("td", "th", "tr") or open_name == name == "tr" or open_name == name == "option":
                    end_from(k)
                    break
                if open_name not in ("p", "li", "td", "th", "dt", "dd", "tr", "option"):
                    break
            still_open[name] += 1
            stack.append(Element(name, stack[-1], hint_of(name, m[3])))
    close()
    return out


def text_features(b: Block) -> tuple[float, ...]:
    """1, length, share of link text, marks of sentences a word."""
    n = len(b.text)
    stops = sum(b.text.count(c) for c in ".,;:!?")
    return 1.0, math.log1p(n) / 5, b.links / n, min(1.0, 4 * stops / (1 + b.text.count(" ")))


def marks_of(b: Block) -> float:
    return b.element.head if b.element.name in ("h1", "h2") else b.element.marks


def log_odds(blocks: list[Block], weights: tuple[float, ...]) -> list[float]:
    """Of each block being content."""
    unmarked = OUTSIDE if any(b.element.inside for b in blocks) else UNMARKED
    return [sum(w * x for w, x in zip(weights, text_features(b))) + (marks_of(b) or unmarked) + (PROSE if b.element.name in PROSE_TAGS else 0.0) for b in blocks]


def terminal_costs(odds: float) -> tuple[float, float]:
    """What it costs to call a block content, and boilerplate: the negative log probabilities."""
    other = math.log1p(math.exp(-abs(odds)))
    return (other, odds + other) if odds >= 0 else (other - odds, other)


def taught_by(page: str | None) -> list[tuple[float, ...]]:
    """Features and label of at most PAGE_BLOCKS blocks of each kind, evenly spaced, that the marks of a page decide."""
    out = []
    blocks = blocks_of(page or "")
    for label in (0.0, 1.0):
        sure = [b for b in blocks if abs(marks_of(b)) >= MARK / 2 and (marks_of(b) > 0) == bool(label)]
        step = max(1, -(-len(sure) // PAGE_BLOCKS))
        out += [(*text_features(b), label) for b in sure[::step]]
    return out


def fitted(pages: DataFrame) -> tuple[float, ...]:
    """The text model: ridge logistic regression on blocks that marks decide, from at most SAMPLE_PAGES pages by a hash of id and url.

    The choice reads two narrow columns; repeated rows teach once; at most 2 * PAGE_BLOCKS rows a page reach the driver.
    """
    key = F.xxhash64("page_id", "url")
    ids = pages.select(key.alias("k")).distinct().orderBy("k").limit(SAMPLE_PAGES).agg(F.max("k")).first()[0]
    if ids is None:
        return PLAIN
    some = pages.filter(key <= ids).groupBy("page_id", "url").agg(F.min("html").alias("html")).select("html")

    def run(batches):
        for b in pieces(batches):
            for x in b.column(0):
                yield pa.RecordBatch.from_arrays([pa.array([np.array(taught_by(x.as_py()), np.float64).tobytes()], pa.binary())], ["rows"])

    rows = np.concatenate([np.zeros((0, len(PLAIN) + 1)), *(np.frombuffer(r[0], np.float64).reshape(-1, len(PLAIN) + 1) for r in some.mapInArrow(run, "rows binary").collect())])
    rows = rows[np.lexsort(rows.T)]  # sums don't depend on the order of tasks
    x, y = rows[:, :-1], rows[:, -1]
    if not 0 < y.sum() < len(y):
        return PLAIN
    w = np.zeros(x.shape[1])
    for _ in range(50):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        step = np.linalg.solve((x * (p * (1 - p))[:, None]).T @ x + RIDGE * np.eye(len(w)), x.T @ (p - y) + RIDGE * w)
        w = w - np.clip(step, -2, 2)
        if np.abs(step).max() < 1e-9:
            break
    return tuple(float(v) for v in w)


def tree_distance(a: Element, b: Element) -> tuple[int, bool]:
    """Steps between two elements, and whether the way crosses a marked element."""
    steps, crossed = 0, False
    while a is not b:
        if a.depth >= b.depth:
            crossed, a = crossed or bool(a.hint), a.parent
        else:
            crossed, b = crossed or bool(b.hint), b.parent
        steps += 1
    return steps, crossed


def smoothness(blocks: list[Block]) -> list[tuple[int, int, float]]:
    edges, last = [], {}
    for i, b in enumerate(blocks):
        if i:
            steps, crossed = tree_distance(blocks[i - 1].element, b.element)
            edges.append((i - 1, i, (ACROSS if crossed else NEAR) / (1 + steps / 2)))
        sibling = last.get(id(b.element.parent))
        if sibling is not None and sibling < i - 1:
            edges.append((sibling, i, SIBLING))
        last[id(b.element.parent)] = i
    return edges


def min_cut(as_content: list[float], as_boiler: list[float], edges: list[tuple[int, int, float]]) -> list[bool]:
    """True where a node is on the content side of the minimum cut; ties go to content.

    Nodes whose terminal costs outweigh all their edges are settled first, which is exact and leaves small connected
    graphs; max-flow settles each of those.
    """
    n = len(as_content)
    near: list[dict[int, float]] = [{} for _ in range(n)]
    for a, b, w in edges:
        near[a][b] = near[a].get(b, 0.0) + w
        near[b][a] = near[b].get(a, 0.0) + w
    cost, label = [list(x) for x in zip(as_content, as_boiler)], [None] * n
    queue = deque(range(n))
    while queue:
        i = queue.popleft()
        if label[i] is not None:
            continue
        lean, pull = cost[i][1] - cost[i][0], sum(near[i].values())
        if abs(lean) >= pull:
            label[i] = lean >= 0
            for j, w in near[i].items():
                del near[j][i]
                cost[j][0 if not label[i] else 1] += w  # disagreeing with i costs w
                queue.append(j)
            near[i] = {}
    for part in _connected([i for i in range(n) if label[i] is None], near):
        for i, content in zip(part, _by_flow([cost[i][1] - cost[i][0] for i in part], part, near)):
            label[i] = content
    return label


def _connected(nodes: list[int], near: list[dict[int, float]]) -> list[list[int]]:
    seen, out = set(), []
    for i in nodes:
        if i not in seen:
            part, queue = [], [i]
            seen.add(i)
            while queue:
                part.append(u := queue.pop())
                more = [v for v in near[u] if v not in seen]
                seen.update(more)
                queue += more
            out.append(part)
    return out


def _by_flow(lean: list[float], nodes: list[int], near: list[dict[int, float]]) -> list[bool]:
    """Max-flow by blocking flows on levels, from nodes that lean to content to those that lean to boilerplate; True: content side.

    What a node gets from the source and may give to the sink at once has been cancelled already (``lean`` is the difference).
    """
    at = {u: k for k, u in enumerate(nodes)}
    arcs: list[list[int]] = [[] for _ in nodes]
    to, room = [], []
    for u, k in at.items():
        for v, w in near[u].items():
            if u < v:  # an edge is two arcs, each the other's way back
                arcs[k].append(len(to))
                arcs[at[v]].append(len(to) + 1)
                to += [at[v], k]
                room += [w, w]
    give, take = [max(0.0, x) for x in lean], [max(0.0, -x) for x in lean]
    while True:
        level = [0 if g > TINY else -1 for g in give]
        queue, found = deque(k for k, g in enumerate(give) if g > TINY), False
        while queue:
            u = queue.popleft()
            found = found or take[u] > TINY
            for a in arcs[u]:
                if room[a] > TINY and level[to[a]] < 0:
                    level[to[a]] = level[u] + 1
                    queue.append(to[a])
        if not found:
            break
        tried = [0] * len(nodes)
        for source in [k for k, g in enumerate(give) if g > TINY]:
            path, u = [], source
            while give[source] > TINY:
                if take[u] > TINY:
                    flow = min(give[source], take[u], *(room[a] for a in path))
                    give[source] -= flow
                    take[u] -= flow
                    for a in path:
                        room[a] -= flow
                        room[a ^ 1] += flow
                    full = next((k for k, a in enumerate(path) if room[a] <= TINY), len(path))
                    u = to[path[full] ^ 1] if full < len(path) else u
                    del path[full:]
                    continue
                while tried[u] < len(arcs[u]):
                    a = arcs[u][tried[u]]
                    if room[a] > TINY and level[to[a]] == level[u] + 1:
                        path.append(a)
                        u = to[a]
                        break
                    tried[u] += 1
                else:
                    if not path:
                        break
                    u = to[path.pop() ^ 1]
                    tried[u] += 1
    # Boilerplate is what still reaches the sink; everything else, ties included, is content.
    content = [t <= TINY for t in take]
    queue = deque(k for k, c in enumerate(content) if not c)
    while queue:
        v = queue.popleft()
        for a in arcs[v]:
            if room[a ^ 1] > TINY and content[to[a]]:
                content[to[a]] = False
                queue.append(to[a])
    return content


def main_text(page: str | None, weights: tuple[float, ...] = PLAIN) -> str:
    blocks = blocks_of(page or "")
    if not blocks:
        return ""
    costs = [terminal_costs(z) for z in log_odds(blocks, weights)]
    keep = min_cut([c for c, _ in costs], [b for _, b in costs], smoothness(blocks))
    return "\n".join(b.text for b, k in zip(blocks, keep) if k)


def extract(pages: DataFrame) -> DataFrame:
    """page_id, url, text, n_chars for every row, from the whole html.

    Null or empty html: empty text. Null ids and urls stay null. Repeated rows give repeated results. Broken markup is read as
    far as it goes: unclosed comments, scripts and tags end with the page. Empty table: no rows. Other columns are ignored.
    """

    weights = fitted(pages)

    def run(batches):
        for b in pieces(batches):
            texts = [main_text(x.as_py(), weights) for x in b.column(2)]
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(texts, pa.string()), pa.array([len(x) for x in texts], pa.int64())], ["page_id", "url", "text", "n_chars"])

    return pages.select(F.col("page_id").cast("long").alias("page_id"), "url", "html").mapInArrow(run, "page_id long, url string, text string, n_chars long")
