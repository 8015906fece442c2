"""Main text of web pages by minimum-cut labelling of their blocks.

A page is read once into text blocks. For each block a linear score of its place in the DOM and of its text gives the cost
of calling it content or boilerplate; these costs are the terminal capacities of a graph whose other edges join
neighbouring blocks and blocks of one parent, the stronger the closer they stand in the DOM. The minimum cut, found by
maximum flow, labels all blocks at once.

Class names and ids that speak of boilerplate count against what is in their element, except on html, body, main and
article. Where a name only has such a part (has-sidebar, tag-economy), it does not count on an element that also has a
name of content, or that holds half of the page's prose or more.

Defined results: null and empty html, and pages without content blocks, give the empty text. Unclosed and crossed tags are
read as browsers do for the common cases (block tags end an open paragraph, an end tag closes what is open inside).
A script, style, textarea, title, iframe or comment that never ends takes the rest of the page. What an svg, object, canvas,
select, template or noscript holds counts as boilerplate if the element is closed; where its end tag is missing, its text
is read like any other (a select ends at the next block tag). Text within math stays. Rows that repeat are extracted alike.
"""

from __future__ import annotations

import html as entities
import re
from collections import deque
from functools import lru_cache
from itertools import groupby
from math import inf

import pandas as pd
from pyspark.sql import DataFrame, functions as F

from .common import bounded_batches

_TOKEN = re.compile(
    r"<!--.*?(?:-->|\Z)"
    r"|<[!?][^>]*+>"
    r"|<(?P<end>/?)(?P<tag>[a-zA-Z][a-zA-Z0-9:-]*+)(?P<attrs>(?:[^>\"']++|\"[^\"]*+\"|'[^']*+')*+|[^>]*+)>",
    re.DOTALL | re.IGNORECASE,
)

# Element kinds of HTML.
RAW_TAGS = {tag: re.compile(rf"</{tag}\s*>", re.IGNORECASE) for tag in ("script", "style", "textarea", "title", "iframe")}
EMBEDDED_TAGS = frozenset("svg object canvas select template noscript".split())
HOLDERS = frozenset("select svg foreignobject".split())
BLOCK_TAGS = frozenset(
    "address article aside blockquote body caption center dd details dialog dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 "
    "head header hgroup hr html legend li main menu nav ol optgroup option p pre search section summary table tbody td tfoot th thead tr ul".split()
)
VOID_TAGS = frozenset("area base br col embed hr img input link meta param source track wbr".split())
HEADINGS = frozenset("h1 h2 h3 h4 h5 h6".split())

#: Score that a tag adds to all blocks in it.
EMBEDDED_BIAS = -9.0
TAG_BIAS = {"article": 3.0, "main": 2.5, "nav": -9.0, "menu": -9.0, "footer": -9.0, "aside": -9.0, "form": -9.0, "button": -9.0, "dialog": -9.0, "label": -6.0, "search": -9.0, "fieldset": -6.0}
ROLE_BIAS = {"navigation": -9.0, "banner": -9.0, "contentinfo": -9.0, "complementary": -9.0, "search": -9.0, "form": -9.0, "dialog": -9.0, "alert": -9.0, "alertdialog": -9.0, "menu": -9.0, "menubar": -9.0, "toolbar": -9.0, "main": 2.5, "article": 3.0}
_NAMES = re.compile(r"""(?:class|id)\s*=\s*("[^"]*"|'[^']*'|[^\s>]+)""", re.IGNORECASE)
_ROLE = re.compile(r"""role\s*=\s*["']?([a-z]+)""", re.IGNORECASE)
_HIDDEN = re.compile(r"""(?:^|\s)hidden(?:\s|=|$)|aria-hidden\s*=\s*["']?true|display\s*:\s*none""", re.IGNORECASE)
_BAD_NAME = re.compile(
    r"(?:^|[\s_-])(?:ads?|adv|advert\w*|adsense|banner|promo\w*|sponsor\w*|sidebar|side|aside|menu\w*|nav\w*|breadcrumbs?|footer|foot|header|masthead|cookies?|notices?|notification|consent|gdpr|"
    r"alert|popup|modal|overlay|comments?|commentlist|disqus|repl(?:y|ies)|respond|discussion|related|recommend\w*|share|sharing|social|newsletter|subscribe|subscription|signup|login|search|"
    r"widgets?|toolbar|pagination|pager|tags?|copyright|legal|disclaimer|outbrain|taboola)(?:$|[\s_-])",
    re.IGNORECASE,
)
#: Parts of a name that say where a thing stands or how it is wrapped, not what it is.
_PLACE = frozenset("site page main primary secondary left right top bottom upper lower global area block box bar wrap wrapper container inner outer section list item items row col column panel thread 1 2 3".split())
_GOOD_NAME = re.compile(r"(?:^|[\s_-])(?:article\w*|content|post|entry|story|main|text|body)(?:$|[\s_-])", re.IGNORECASE)


class Block:
    __slots__ = ("bias", "heading", "linked", "mark", "parent", "path", "text")

    def __init__(self, text, bias, heading, linked, parent, path, mark=0):
        self.text, self.bias, self.heading, self.linked, self.parent, self.path, self.mark = text, bias, heading, linked, parent, path, mark

    @property
    def score(self) -> float:
        """Log-odds of content: place in the DOM, length, share of linked text, sentence ends."""
        words = self.text.count(" ") + 1
        z = self.bias - 0.6 + min(1.8, 0.12 * words) - 5.0 * min(1.0, self.linked / len(self.text))
        if self.text[-1] in ".!?:;\"'»”…)。！？":
            z += 0.5
        return z + 0.8 * self.heading


@lru_cache(4096)
def _name_kind(names: str) -> str:
    """What class names and ids say: bad (a whole name does), part (a part of a name does), good, or nothing."""
    if not _BAD_NAME.search(names):
        return "good" if _GOOD_NAME.search(names) else ""
    good = False
    for name in names.split():
        parts = [x for x in re.split("[-_]+", name.lower()) if x]
        bad = [_BAD_NAME.search(x) is not None for x in parts]
        if any(bad) and all(b or x in _PLACE for b, x in zip(bad, parts)):
            return "bad"
        good = good or name.lower() == "hentry" or bool(parts) and all(_GOOD_NAME.search(x) for x in parts)
    return "good" if good else "part"


def _bias(tag: str, attrs: str, above: float) -> tuple[float, float]:
    """(score that an element adds to all blocks in it, further score if it turns out not to hold most of the page)."""
    own, later = TAG_BIAS.get(tag, 0.0), 0.0
    if tag == "header":
        own = -9.0 if above < 2 else -1.0  # a header within an article holds its title
    if attrs:
        if names := " ".join(m.strip("\"'") for m in _NAMES.findall(attrs)):
            kind = _name_kind(names)
            if tag in ("main", "article"):
                own += 1.5 * (_GOOD_NAME.search(names) is not None)
            elif tag in ("html", "body"):
                pass
            elif kind == "bad":
                own = min(own, 0.0) - 9.0
            elif kind == "part":
                later = min(own, 0.0) - 9.0 - own
            elif kind == "good":
                own += 1.5
        if (m := _ROLE.search(attrs)) and m[1].lower() in ROLE_BIAS:
            own += ROLE_BIAS[m[1].lower()]
        if _HIDDEN.search(attrs):
            own -= 9.0
    return own, later


def _settle(blocks: list[Block], marked: dict[int, tuple[int, float]], closed: set[int]) -> None:
    """Adds to blocks what `closed` embedded elements cost, and names in elements that do not hold half of the prose or more.

    `marked` holds, by number of element, the marked element around it and the cost of its names, outer elements first.
    """
    cost = {0: 0.0}
    for k, (above, _) in marked.items():
        cost[k] = cost[above] + EMBEDDED_BIAS * (k in closed)
    held, total = dict.fromkeys(cost, 0), 0
    for b in blocks:
        b.bias += cost[b.mark]
        if b.score > 0:
            total += len(b.text) - b.linked
            held[b.mark] += len(b.text) - b.linked
    for k in reversed(marked):
        held[marked[k][0]] += held[k]
    for k, (above, names) in marked.items():
        cost[k] = cost[above] + (0.0 if 2 * held[k] >= total > 0 else names)
    for b in blocks:
        b.bias += cost[b.mark]


def blocks_of(page: str) -> list[Block]:
    """The page's text blocks in order."""
    out: list[Block] = []
    # Of each open element: tag, score with its ancestors, number, heading, link, path of block ancestors' numbers, number of the
    # marked element around it, places in the stack (0: none) of the outermost embedded element and of the last HOLDERS element.
    stack = [("", 0.0, 0, False, False, (0,), 0, 0, 0)]
    marked: dict[int, tuple[int, float]] = {}
    closed: set[int] = set()
    pieces: list[str] = []
    inner: list[tuple] = []  # (open element, text) within embedded elements: kept apart, so they do not split a paragraph
    linked, number, at = 0, 0, 0

    def emit(parts, e, linked):
        if text := " ".join("".join(parts).split()):
            path = e[5]
            out.append(Block(text, e[1], e[3], min(linked, len(text)), path[-2] if len(path) > 1 else path[-1], path, e[6]))

    def flush():
        nonlocal linked
        if pieces:
            emit(pieces, stack[stack[-1][7] - 1], linked)  # place 0 gives the last
            pieces.clear()
        linked = 0
        if inner:
            for _, group in groupby(inner, key=lambda x: x[0][6]):
                group = list(group)
                emit([x for _, x in group], group[0][0], sum(len(x.strip()) for e, x in group if e[4]))
            inner.clear()

    def add(raw: str):
        nonlocal linked
        text = entities.unescape(raw) if "&" in raw else raw
        if stack[-1][7]:
            inner.append((stack[-1], text))
            return
        pieces.append(text)
        if stack[-1][4]:
            linked += len(text.strip())

    while m := _TOKEN.search(page, at):
        if m.start() > at:
            add(page[at: m.start()])
        at = m.end()
        tag = m["tag"]
        if tag is None:
            continue
        tag = tag.lower()
        if tag in RAW_TAGS:
            if not m["end"] and not (m["attrs"].endswith("/") and any(e[0] in ("svg", "math") for e in stack)):
                end = RAW_TAGS[tag].search(page, at)
                at = end.end() if end else len(page)
            continue
        block = tag in BLOCK_TAGS
        if block and stack[-1][7]:
            k = stack[-1][8]
            if stack[k][0] == "select" and tag in ("option", "optgroup", "hr"):
                add(" ")
                continue
            if stack[k][0] in ("select", "svg") and not m["end"]:  # these hold no blocks
                del stack[k:]
        if m["end"]:
            if block:
                flush()
            for k in range(len(stack) - 1, 0, -1):
                if stack[k][0] == tag:
                    if tag in EMBEDDED_TAGS:
                        closed.add(stack[k][2])
                    del stack[k:]
                    break
                # An inline end tag closes nothing outside its block.
                if not block and tag not in EMBEDDED_TAGS and stack[k][0] in BLOCK_TAGS:
                    break
            continue
        if tag == "br":
            add(" ")
            continue
        if block:
            flush()
            for k in range(len(stack) - 1, 0, -1):  # a block ends an open paragraph, and an item the item before
                if stack[k][0] == "p" or stack[k][0] == tag == "li":
                    del stack[k:]
                    break
                if stack[k][0] in BLOCK_TAGS or stack[k][0] in EMBEDDED_TAGS:
                    break
        if tag in VOID_TAGS or m["attrs"].endswith("/"):
            continue
        top = stack[-1]
        number += 1
        embedded = tag in EMBEDDED_TAGS
        own, names = (0.0, 0.0) if embedded else _bias(tag, m["attrs"], top[1])
        mark = top[6]
        if names or embedded:
            marked[number] = (mark, names)
            mark = number
        if tag == "select":
            closed.add(number)
        path = (*top[5], number) if block and len(top[5]) < 60 else top[5]
        place = len(stack)
        stack.append((tag, top[1] + own, number, top[3] or tag in HEADINGS, top[4] or tag == "a", path, mark, top[7] or place * embedded, place if tag in HOLDERS else top[8]))
    if at < len(page):
        add(page[at:])
    flush()
    if marked:
        _settle(out, marked, closed)
    return out


def min_cut(scores: list[float], edges: dict[tuple[int, int], float]) -> list[bool]:
    """For each node whether it lies on the content side of the minimum cut.

    Calling node i content instead of boilerplate saves scores[i] (negative: costs); each edge costs its weight if its ends
    differ. Nodes whose own score outweighs all their edges are settled first, which changes no optimum; maximum flow
    decides the others. Ties go to boilerplate.
    """
    n = len(scores)
    z = list(scores)
    near: list[dict[int, float]] = [{} for _ in range(n)]
    for (i, j), w in edges.items():
        if i != j and w > 0:
            near[i][j] = near[i].get(j, 0.0) + w
            near[j][i] = near[j].get(i, 0.0) + w
    label: list = [None] * n
    todo = deque(range(n))
    while todo:
        i = todo.popleft()
        if label[i] is None and abs(z[i]) > sum(near[i].values()):
            label[i] = z[i] > 0
            for j, w in near[i].items():
                del near[j][i]
                z[j] += w if label[i] else -w
                todo.append(j)
            near[i] = {}
    rest = [i for i in range(n) if label[i] is None]
    if rest:
        for i, side in zip(rest, _flow_sides([z[i] for i in rest], [{rest.index(j): w for j, w in near[i].items()} for i in rest] if len(rest) < 50 else _renumber(rest, near))):
            label[i] = side
    return [bool(x) for x in label]


def _renumber(rest, near):
    place = {i: k for k, i in enumerate(rest)}
    return [{place[j]: w for j, w in near[i].items()} for i in rest]


def _flow_sides(z: list[float], near: list[dict[int, float]]) -> list[bool]:
    """Maximum flow by shortest augmenting paths in level graphs; source side = content."""
    n = len(z)
    s, t = n, n + 1
    cap: list[dict[int, float]] = [dict(d) for d in near] + [{}, {}]
    for i, x in enumerate(z):
        if x > 0:
            cap[s][i], cap[i][s] = x, 0.0
        elif x < 0:
            cap[i][t] = -x
            cap[t][i] = 0.0
    eps = 1e-9
    while True:
        level = {s: 0}
        queue = deque([s])
        while queue:
            u = queue.popleft()
            for v, c in cap[u].items():
                if c > eps and v not in level:
                    level[v] = level[u] + 1
                    queue.append(v)
        if t not in level:
            return [i in level for i in range(n)]
        ways = [list(cap[u]) for u in range(n + 2)]
        path, u = [s], s
        while path:
            u = path[-1]
            if u == t:
                push = min((cap[a][b] for a, b in zip(path, path[1:])), default=inf)
                for a, b in zip(path, path[1:]):
                    cap[a][b] -= push
                    cap[b][a] = cap[b].get(a, 0.0) + push
                path = [s]
                continue
            while ways[u]:
                v = ways[u][-1]
                if cap[u][v] > eps and level.get(v) == level[u] + 1:
                    path.append(v)
                    break
                ways[u].pop()
            else:
                path.pop()
                if path:
                    ways[path[-1]].pop()


def smoothness(blocks: list[Block]) -> dict[tuple[int, int], float]:
    """Edges between neighbours in page order, and from each block to the one before it under the same parent."""
    edges: dict[tuple[int, int], float] = {}
    last: dict[int, int] = {}
    for j, b in enumerate(blocks):
        if j:
            a = blocks[j - 1]
            common = 0
            for x, y in zip(a.path, b.path):
                if x != y:
                    break
                common += 1
            far = len(a.path) + len(b.path) - 2 * common
            edges[j - 1, j] = 2.0 / (1 + far) * (1.0 if abs(a.bias - b.bias) < 3 else 0.25)
        i = last.get(b.parent)
        if i is not None:
            edges[i, j] = edges.get((i, j), 0.0) + 0.5
        last[b.parent] = j
    return edges


def main_text(page: str | None) -> str:
    """Content blocks in page order, joined by two line feeds."""
    blocks = blocks_of(page or "")
    if not blocks:
        return ""
    scores = [b.score for b in blocks]
    keep = min_cut(scores, smoothness(blocks))
    return "\n\n".join(b.text for b, k in zip(blocks, keep) if k)


def extract(df: DataFrame, html: str = "html", columns: tuple[str, ...] = ("page_id", "url")) -> DataFrame:
    """`columns` of every row, with text and n_chars (code points)."""
    bounded_batches(df.sparkSession)

    @F.pandas_udf("string")
    def text(pages: pd.Series) -> pd.Series:
        return pages.map(main_text, na_action=None)

    rows = df.select(*columns, text(F.col(html)).alias("_main"))
    return rows.select(*columns, F.col("_main").alias("text"), F.char_length("_main").cast("long").alias("n_chars"))
