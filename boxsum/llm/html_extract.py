"""Main text of HTML pages by a minimum cut over their blocks.

A page becomes a list of text blocks. A linear classifier over a block's features (length, end, share of link
text, heading, and the tags, roles and names of the elements around it) gives the cost of calling it content or
boilerplate; these are capacities from the source and to the sink. All are finite and fitted (`fit`), so that no
single feature decides. Blocks that are next to each other are joined by smoothness edges, the stronger the
nearer they are in the tree, and so are the next two children of one element; edges that enter or leave a section
(what stands for or against content around the one and not the other) are weak. The minimum cut labels all blocks
at once. Blocks whose own cost outweighs all their edges keep their side in some minimum cut, so they are settled
first and their edges folded into their neighbours' costs; maximum flow decides what is left.

Scripts, styles and the like, forms and hidden elements are no blocks. White space inside a block, line breaks by
tag included, becomes one space. Null, empty and text-free pages have an empty text. Tags that are never closed end
with the page or with the element around them; a tag whose quotes don't close ends at the next bracket, and what is
no tag at all is text. Time is linear in the length of a page, however deep it is nested.
"""

from __future__ import annotations

import html as entities
import re
from collections import Counter, deque
from collections.abc import Iterable, Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from boxsum.llm.shared import blocks

NAME = re.compile(r"(/?)([a-zA-Z][^\s/>]*)")
#: What follows a tag's name up to its bracket; quotes count after an equals sign only.
INSIDE = re.compile(r"(?:=\s*+(?:\"[^\"]*+\"|'[^']*+')|[^>])*+")
ATTRIBUTE = re.compile(r"([^\s=/\"'>]++)(?:\s*+=\s*+(?:\"([^\"]*+)\"|'([^']*+)'|([^\s\"'>]++)))?")
SPACE = re.compile(r"\s+")
KEYWORD = re.compile(r"[a-z]+")
UNSEEN = re.compile(r"display\s*:\s*none|visibility\s*:\s*hidden")

# Element and attribute vocabularies.
RAW = {"script", "style", "noscript", "template", "iframe", "svg", "math", "object", "canvas", "audio", "video", "head", "textarea", "title"}
VOID = {"area", "base", "br", "col", "embed", "hr", "img", "input", "link", "meta", "source", "track", "wbr"}
INLINE = {"a", "abbr", "acronym", "b", "bdi", "bdo", "big", "cite", "code", "data", "del", "dfn", "em", "font", "i", "ins", "kbd", "label", "mark", "q", "s", "samp", "small", "span", "strike", "strong", "sub", "sup", "time", "tt", "u", "var", "ruby", "rt", "rp"}
ENDS_P = {"address", "article", "aside", "blockquote", "center", "details", "dir", "div", "dl", "fieldset", "figcaption", "figure", "footer", "form", "h1", "h2", "h3", "h4", "h5", "h6", "header", "hr", "main", "menu", "nav", "ol", "p", "pre", "section", "table", "ul"}
OWN_END = {"li": {"ul", "ol", "menu"}, "dt": {"dl"}, "dd": {"dl"}, "tr": {"table"}, "td": {"tr", "table"}, "th": {"tr", "table"}, "option": {"select"}}
SAME_END = {"dt": {"dt", "dd"}, "dd": {"dt", "dd"}, "td": {"td", "th"}, "th": {"td", "th"}}
FORMS = {"form", "button", "select", "fieldset"}
AROUND = {"nav", "footer", "aside", "menu", "dialog"}
ROLES = {"navigation", "banner", "contentinfo", "complementary", "search", "form", "dialog", "alert", "alertdialog", "menu", "menubar", "toolbar"}
WORDS = {"ad", "ads", "advert", "adverts", "advertisement", "advertising", "adsense", "banner", "sponsor", "sponsored", "promo", "promotion", "cookie", "cookies", "consent", "gdpr", "notice", "notification", "alert", "popup", "modal", "overlay", "newsletter", "subscribe", "signup", "login", "nav", "navbar", "navigation", "menu", "breadcrumb", "breadcrumbs", "sidebar", "footer", "masthead", "comment", "comments", "disqus", "respond", "replies", "reply", "social", "share", "sharing", "related", "recommended", "widget", "toolbar", "pagination", "pager", "tags", "copyright", "disclaimer", "skip", "search", "form"}
GOOD = {"article", "content", "main", "post", "entry", "story", "body", "text"}
HEADINGS = {"h1", "h2", "h3", "h4", "h5", "h6"}
CELLS = {"li", "td", "th", "dt", "dd"}
ENDS = tuple(".!?:\"'”»…。！？")

# What is around a block: a bit for each.
IN_ARTICLE, IN_MAIN, GOOD_NAME, IN_HEADER, AROUND_TAG, AROUND_NAME, UNSHOWN, IN_FORM = 1, 2, 4, 8, 16, 32, 64, 128
OUT = UNSHOWN | IN_FORM
SECTION = IN_ARTICLE | IN_MAIN | IN_HEADER | AROUND_TAG | AROUND_NAME

# Capacities in tenths of a nat. Weights of the classifier, positive for content, as `fit` finds them on the labelled
# pages of the tests; edges by hand.
WEIGHTS = {"bias": 11, "article": 56, "main": 54, "good_name": 33, "header": -57, "heading": 42, "links": -61, "long": 29, "middle": 16, "short": -22, "sentence": 1, "cell": -4, "bare": 0, "around_tag": -60, "around_name": -79, "mark": -34}
NEXT, SIBLING, ACROSS = 20, 10, 2


@dataclass(slots=True)
class Block:
    text: str
    tag: str
    around: int  # bits of what is around it
    parent: int  # number of the element around its own
    linked: int  # characters inside links
    near: int  # steps in the tree from the block before, up and down


@dataclass(slots=True)
class _Open:
    tag: str
    around: int
    holder: str  # tag of the block element it is or is in
    block: bool
    number: int  # of the block element it is or is in
    parent: int  # of the block element around that
    depth: int  # block elements around, itself included


def _tell(tag: str, attributes: str) -> int:
    """The bits that an element's tag and attributes set for what is inside."""
    told = IN_FORM if tag in FORMS else AROUND_TAG if tag in AROUND else IN_ARTICLE if tag == "article" else IN_MAIN if tag == "main" else IN_HEADER if tag == "header" else 0
    if not attributes or "=" not in attributes and "hidden" not in attributes:
        return told
    for m in ATTRIBUTE.finditer(attributes):
        name, value = m[1].lower(), (m[2] or m[3] or m[4] or "").lower()
        if name in ("class", "id", "data-component", "aria-label"):
            before = ""
            for word in KEYWORD.findall(value):
                # "has-sidebar" tells of another element; whole pages and articles are never told against by a name
                if word in WORDS and before not in ("has", "no", "with", "without") and tag not in ("html", "body", "article", "main"):
                    told |= AROUND_NAME
                if word in GOOD:
                    told |= GOOD_NAME
                before = word
        elif name == "role":
            told |= AROUND_TAG if value in ROLES else IN_MAIN if value == "main" else IN_ARTICLE if value == "article" else 0
        elif name == "hidden" or name == "aria-hidden" and value == "true" or name == "style" and UNSEEN.search(value):
            told |= UNSHOWN
    return told


def blocks_of(page: str) -> list[Block]:
    """The text blocks of a page in their order."""
    out: list[Block] = []
    stack = [_Open("", 0, "", True, 0, 0, 0)]
    opened: Counter[str] = Counter()
    parts: list[str] = []
    linked = number = in_link = low = last = 0
    at, size, bracket = 0, len(page), 0

    def flush() -> None:
        nonlocal linked, low, last
        if parts:
            text = SPACE.sub(" ", "".join(parts)).strip()
            parts.clear()
            top = stack[-1]
            if text and not top.around & OUT:
                low = min(low, top.depth)
                out.append(Block(text, top.holder, top.around, top.parent, linked, last + top.depth - 2 * low))
                low = last = top.depth
        linked = 0

    def close(to: int) -> None:
        nonlocal low
        if any(o.block or o.around != stack[to - 1].around for o in stack[to:]):
            flush()
        for o in stack[to:]:
            opened[o.tag] -= 1
        del stack[to:]
        low = min(low, stack[-1].depth)

    def say(text: str) -> None:
        nonlocal linked
        if text:
            text = entities.unescape(text) if "&" in text else text
            parts.append(text)
            if in_link:
                linked += len(text.strip())

    while at < size:
        start = page.find("<", at)
        if start < 0:
            say(page[at:])
            break
        if bracket <= start:
            bracket = page.find(">", start)
            if bracket < 0:  # no tag ends any more: the rest is text, but for a comment that is still open
                end = page.find("<!--", at)
                say(page[at : end if end >= 0 else size])
                break
        say(page[at:start])
        follows = page[start + 1 : start + 2]
        if follows in ("!", "?"):
            if page.startswith("<!--", start):
                end = page.find("-->", start + 4)
                at = end + 3 if end >= 0 else size
            else:
                at = bracket + 1
            continue
        m = NAME.match(page, start + 1)
        if m is None:
            if follows == "/":
                at = bracket + 1
            else:
                parts.append("<")
                at = start + 1
            continue
        end = INSIDE.match(page, m.end()).end()
        end = end if end < size else bracket
        tag, closing, attributes = m[2].lower(), bool(m[1]), page[m.end() : end]
        at = end + 1
        if closing:
            if tag == "a":
                in_link = max(0, in_link - 1)
            if not opened[tag]:
                if tag == "p":
                    flush()
                continue
            for k in range(len(stack) - 1, 0, -1):
                if stack[k].tag == tag:
                    close(k)
                    break
                if tag in INLINE and stack[k].block:
                    break  # an inline end tag doesn't close blocks
            continue
        if tag in RAW:
            if not attributes.endswith("/"):
                # a head without an end tag ends at the body
                found = re.compile(rf"</{re.escape(tag)}\s*+>" + (r"|(?=<body\b)" if tag == "head" else ""), re.I).search(page, at)
                at = found.end() if found else size
            if tag not in ("svg", "math", "noscript", "script", "template"):
                flush()
            continue
        if tag == "br":
            parts.append(" ")
            continue
        if tag in VOID:
            if tag == "hr":
                flush()
            continue
        inline = tag in INLINE
        if not inline:
            if tag in ENDS_P and opened["p"]:
                for k in range(len(stack) - 1, 0, -1):
                    if stack[k].tag == "p":
                        close(k)
                        break
                    if stack[k].block and stack[k].tag not in HEADINGS:
                        break
            if tag in OWN_END:
                ends = SAME_END.get(tag, {tag})
                if any(opened[x] for x in ends):
                    for k in range(len(stack) - 1, 0, -1):
                        if stack[k].tag in ends:
                            close(k)
                            break
                        if stack[k].tag in OWN_END[tag]:
                            break
            flush()
            in_link = 0 if tag in ("article", "main", "body") else in_link
        if tag == "a":
            in_link = 1
        top = stack[-1]
        around = top.around | _tell(tag, attributes)
        if tag in ("article", "main"):
            around &= ~IN_FORM  # of a form around a whole page
        if inline and around != top.around:
            flush()
        if not inline:
            number += 1
            stack.append(_Open(tag, around, tag, True, number, top.number, top.depth + 1))
            opened[tag] += 1
        elif not attributes.endswith("/"):
            stack.append(_Open(tag, around, top.holder, False, top.number, top.parent, top.depth))
            opened[tag] += 1
    flush()
    return out


def features(b: Block) -> dict[str, float]:
    """What the classifier looks at."""
    n, words = len(b.text), b.text.count(" ") + 1
    out = {"bias": 1.0, "links": min(1.0, b.linked / max(1, n)), "long" if words >= 25 else "middle" if words >= 8 else "short" if words < 4 else "some": 1.0}
    against = b.around & (AROUND_TAG | AROUND_NAME)
    for name, bit in (("article", IN_ARTICLE), ("main", IN_MAIN), ("good_name", GOOD_NAME), ("around_tag", AROUND_TAG), ("around_name", AROUND_NAME)):
        if b.around & bit and (not against or bit & against):  # what an article holds apart is not spoken for by it
            out[name] = 1.0
    heading = b.tag in HEADINGS
    if b.around & IN_HEADER and not (heading and b.around & (IN_ARTICLE | IN_MAIN)):
        out["header"] = 1.0
    elif heading and not against:  # the name of a site or of a section apart is no title
        out["heading"] = 1.0
    if b.text.endswith(ENDS):
        out["sentence"] = 1.0
    if b.tag in CELLS:
        out["cell"] = 1.0
    if b.tag in ("", "html", "body"):
        out["bare"] = 1.0
    if b.text[0] in "©®™«»‹›|•·":
        out["mark"] = 1.0
    return out


def score(b: Block, weights: dict[str, float] | None = None) -> int:
    """Tenths of a nat for content."""
    weights = WEIGHTS if weights is None else weights
    return round(sum(weights.get(name, 0) * x for name, x in features(b).items()))


def fit(labelled: Iterable[tuple[Block, bool]], ridge: float = 1.0, most: int = 80) -> dict[str, int]:
    """Weights for blocks with their labels, by logistic regression; in tenths of a nat, `most` at most."""
    rows = [(features(b), y) for b, y in labelled]
    names = [name for name in WEIGHTS if any(name in x for x, _ in rows)]
    x = np.array([[f.get(name, 0.0) for name in names] for f, _ in rows])
    y = np.array([float(good) for _, good in rows])
    share = np.where(y > 0, 0.5 / max(y.mean(), 1e-9), 0.5 / max(1 - y.mean(), 1e-9))  # both classes count the same
    w, penalty = np.zeros(len(names)), np.array([1e-3 if name == "bias" else ridge for name in names])
    for _ in range(50):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        step = np.linalg.solve((x.T * (share * np.maximum(p * (1 - p), 1e-6))) @ x + np.diag(penalty), x.T @ (share * (y - p)) - penalty * w)
        w = w + step * min(1.0, 2 / max(1e-9, np.abs(step).max()))
        if np.abs(step).max() < 1e-8:
            break
    return {name: int(np.clip(round(10 * v), -most, most)) for name, v in zip(names, w, strict=True)}


@dataclass
class Cut:
    """Costs of nodes (positive: the source's side) and undirected edges; `sides` is a minimum cut."""

    costs: list[int]
    edges: dict[tuple[int, int], int] = field(default_factory=dict)

    def join(self, a: int, b: int, weight: int) -> None:
        self.edges[min(a, b), max(a, b)] = self.edges.get((min(a, b), max(a, b)), 0) + weight

    def sides(self) -> list[bool]:
        n, costs = len(self.costs), list(self.costs)
        around: list[dict[int, int]] = [{} for _ in range(n)]
        for (a, b), w in self.edges.items():
            around[a][b] = around[b][a] = w
        side: list[bool | None] = [None] * n
        # settle what outweighs its edges
        queue = deque(range(n))
        while queue:
            i = queue.popleft()
            if side[i] is None and abs(costs[i]) >= sum(around[i].values()) and (costs[i] or not around[i]):
                side[i] = costs[i] > 0
                for j, w in around[i].items():
                    costs[j] += w if side[i] else -w
                    del around[j][i]
                    queue.append(j)
                around[i] = {}
        left = [i for i in range(n) if side[i] is None]
        if left:
            for i, s in zip(left, _max_flow(left, costs, around), strict=True):
                side[i] = s
        return side


def _max_flow(nodes: list[int], costs: list[int], around: list[dict[int, int]]) -> list[bool]:
    """Whether each node is reached from the source when the flow is at its most (level graphs, augmented by depth)."""
    place = {v: k for k, v in enumerate(nodes)}
    source, sink = len(nodes), len(nodes) + 1
    to: list[int] = []
    room: list[int] = []
    out: list[list[int]] = [[] for _ in range(sink + 1)]

    def edge(a: int, b: int, forth: int, back: int) -> None:
        out[a].append(len(to))
        to.append(b)
        room.append(forth)
        out[b].append(len(to))
        to.append(a)
        room.append(back)

    for v in nodes:
        if costs[v] > 0:
            edge(source, place[v], costs[v], 0)
        elif costs[v] < 0:
            edge(place[v], sink, -costs[v], 0)
        for u, w in around[v].items():
            if u > v:
                edge(place[v], place[u], w, w)
    while True:
        level = [-1] * (sink + 1)
        level[source] = 0
        queue = deque([source])
        while queue:
            a = queue.popleft()
            for e in out[a]:
                if room[e] > 0 and level[to[e]] < 0:
                    level[to[e]] = level[a] + 1
                    queue.append(to[e])
        if level[sink] < 0:
            return [level[k] >= 0 for k in range(len(nodes))]
        turn = [0] * (sink + 1)
        path: list[int] = []
        a = source
        while True:
            if a == sink:
                least = min(room[e] for e in path)
                for e in path:
                    room[e] -= least
                    room[e ^ 1] += least
                cut = next(k for k, e in enumerate(path) if room[e] == 0)
                a = to[path[cut] ^ 1]
                del path[cut:]
                continue
            while turn[a] < len(out[a]):
                e = out[a][turn[a]]
                if room[e] > 0 and level[to[e]] == level[a] + 1:
                    break
                turn[a] += 1
            else:
                if a == source:
                    break
                level[a] = -1
                a = to[path.pop() ^ 1]
                continue
            path.append(e)
            a = to[e]


def graph(found: list[Block], weights: dict[str, float] | None = None) -> Cut:
    """The costs and edges of a page's blocks."""
    cut = Cut([score(b, weights) for b in found])
    last_child: dict[int, int] = {}
    for i, b in enumerate(found):
        if i:
            same = not (found[i - 1].around ^ b.around) & SECTION
            cut.join(i - 1, i, max(ACROSS, 2 * NEXT // max(2, b.near)) if same else ACROSS)
        before = last_child.get(b.parent)
        if before is not None and not (found[before].around ^ b.around) & SECTION:
            cut.join(before, i, SIBLING)
        last_child[b.parent] = i
    return cut


def extract(page: str | None, weights: dict[str, float] | None = None) -> str:
    """The main text of a page, its blocks joined by newlines."""
    found = blocks_of(page or "")
    return "\n".join(b.text for b, content in zip(found, graph(found, weights).sides(), strict=True) if content)


def main_text(pages: DataFrame, id_col: str = "page_id", html_col: str = "html", keep: tuple[str, ...] = ("url",)) -> DataFrame:
    """(id, *keep, text, n_chars) of every row; `keep` names further columns, which must not be text or n_chars."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in blocks(batches, "__html"):
            texts = [extract(t) for t in b.column(b.num_columns - 1).to_pylist()]
            yield pa.RecordBatch.from_arrays([*b.columns[:-1], pa.array(texts, pa.string()), pa.array(map(len, texts), pa.int64())], [*b.schema.names[:-1], "text", "n_chars"])

    rows = pages.select(id_col, *keep, F.col(html_col).cast("string").alias("__html"))
    schema = ", ".join(f"`{c}` {k}" for c, k in rows.dtypes[:-1])
    return rows.mapInArrow(run, f"{schema}, text string, n_chars long")
