"""Main text of web pages by minimum-cut labelling of their blocks.

A page becomes a sequence of text blocks. Two classifiers give the log odds of a block being content: one sees its shape
(length, links, punctuation, kind of element), the other the region that its ancestors declare (an article, navigation, a
class that hints at an advert, ...). Their sum is the capacity of the block's edge to one of the two terminals.
Neighbours in page order and neighbours under one parent are joined by smoothness edges, weaker the further apart in
the tree. The maximum flow's cut is the labelling of least cost; no declaration decides alone.

The weights are learned from the pages without labels, each classifier from the other: shapes from pages that declare an
article, regions from the labels that shapes and flow give to all pages.
"""

from __future__ import annotations

import html as _html
import re
from collections import deque
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

#: Pages to fit the block classifier on, thinned by a hash of their id.
FIT_PAGES = 2_000
#: Capacities are whole numbers, in hundredths of a nat: of neighbours in page order and of neighbours under one parent.
NEXT, KIN = 100, 100
#: Bounds of the log odds. Against content a region may outweigh a shape, as readers' remarks look like an article, but not
#: a shape and the edges of a block; for content it may not.
SURE, SURE_NOT = 3.0, 5.0
#: Depth of open elements that is kept; deeper ones count as part of the last.
DEEP = 512

#: Regions that an element declares; the innermost counts, but nothing inside OTHER or REMARKS is an article again.
NONE, ARTICLE, OTHER, HEADER, HINT, REMARKS = range(6)
GONE = -1

#: Element names and the words of class, id and role that declare what is not the article.
DROPPED = frozenset("script style noscript template iframe svg math canvas object select option button textarea input form head title audio video map datalist dialog".split())
OUTSIDE = frozenset("nav footer aside menu".split())
MAIN = frozenset("article main".split())
WHOLE = MAIN | {"html", "body"}
BLOCKS = frozenset("address article aside blockquote body br caption center dd details dialog dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 head header hr html legend li main menu nav ol optgroup option p pre section summary table tbody td tfoot th thead title tr ul".split())
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style textarea title noscript template iframe svg".split())
CLOSES = {"p": frozenset(["p"]), "li": frozenset(["li"]), "dt": frozenset(["dt", "dd"]), "dd": frozenset(["dt", "dd"]), "tr": frozenset(["tr", "td", "th"]), "td": frozenset(["td", "th"]), "th": frozenset(["td", "th"]), "option": frozenset(["option"])}
ENDS_P = BLOCKS - frozenset("br body html head td th tr li dd dt".split())
AWAY = frozenset(
    "ad ads adv advert adverts advertisement advertising adsense banner sponsor sponsored sponsors promo promos promotion nav navbar navigation menu menus breadcrumb breadcrumbs pagination pager footer foot sidebar sidebars aside rail widget widgets notice notices cookie cookies consent gdpr alert alerts popup modal overlay subscribe subscription newsletter signup login comment comments commentlist reply replies respondents disqus discussion social share sharing related recommended recommendations masthead toolbar search tags copyright legal disclaimer skip hidden".split()
)
COMMENTS = frozenset("comment comments commentlist reply replies respondents disqus discussion".split())
AWAY_OUTSIDE = frozenset("header head top topbar site".split())
ROLES = frozenset("navigation banner contentinfo complementary search form dialog alert alertdialog menu menubar".split())

# Every expression here is read once from each place: repeats are possessive, and names start at their first letter.
_BODY = re.compile(r"(?:[^>\"']++|\"[^\"]*+\"|'[^']*+')*+")
_NAME = re.compile(r"/?[A-Za-z][A-Za-z0-9:-]*+")
_ATTR = re.compile(r"(?<![A-Za-z-])([A-Za-z-]++)\s*+=\s*+(?:\"([^\"]*+)\"|'([^']*+)'|([^\s\"'>]++))")
_HIDDEN = re.compile(r"(?:^|\s)hidden(?:\s|=|/|$)")
_UNSEEN = re.compile(r"display\s*+:\s*+none|visibility\s*+:\s*+hidden")
_SPLIT = re.compile(r"[^a-z]+")
_RAW = {name: re.compile(rf"</{name}(?![A-Za-z0-9:-])", re.I) for name in RAW}
_ZEROS = re.compile(r"&#([xX]?)0{6,}+(?=[0-9a-fA-F])")
_TOO_LARGE = re.compile(r"&#(?:[0-9]{8,}+|[xX][0-9a-fA-F]{7,}+);?")


def _unescape(text: str) -> str:
    """Character references decoded; numbers beyond any character become the replacement sign, however long they are."""
    if "&#" in text:
        text = _TOO_LARGE.sub("\ufffd", _ZEROS.sub(r"&#\1", text))
    return _html.unescape(text)


def tags(page: str) -> Iterator[tuple[int, int, str, str]]:
    """Start, end, name (with a slash in end tags) and attributes of each tag; other markup has an empty name.

    Time is linear: a quote that nothing closes is read to the end of the page once, and up to it tags end at the next >.
    """
    n, pos, loose = len(page), 0, -1
    last = page.rfind(">")
    cdata_ends = page.rfind("]]>")
    while True:
        at = page.find("<", pos)
        if at < 0 or at + 1 >= n:
            return
        c = page[at + 1]
        if c in "!?":
            if page.startswith("<!--", at):
                end = page.find("-->", at + 4)
                pos = end + 3 if end >= 0 else n
            elif page.startswith("<![CDATA[", at) and at + 9 <= cdata_ends:
                pos = page.find("]]>", at + 9) + 3
            else:
                end = page.find(">", at)
                pos = end + 1 if end >= 0 else n
            yield at, pos, "", ""
            continue
        name = _NAME.match(page, at + 1)
        if name is None:
            pos = at + 1
            continue
        if at > last:  # cut off
            yield at, n, "", ""
            return
        end = -1
        if at > loose:
            end = _BODY.match(page, name.end()).end()
            if end >= n or page[end] != ">":
                loose, end = end, -1
        if end < 0:
            end = page.find(">", at)
        yield at, end + 1, name[0].lower(), page[name.end() : end]
        pos = end + 1


def _region(name: str, attrs: str, above: int) -> int:
    """The region inside an element: GONE where nothing is shown, else the region above or the one that it declares."""
    if name in DROPPED:
        return GONE
    verdict = OTHER if name in OUTSIDE else ARTICLE if name in MAIN else HEADER if name == "header" and above != ARTICLE else NONE
    if attrs:
        for key, *values in _ATTR.findall(attrs):
            key = key.lower()
            value = next((v for v in values if v), "").lower()
            if key in ("class", "id") and name not in WHOLE:
                words = _SPLIT.split(value)
                if not COMMENTS.isdisjoint(words):
                    verdict = REMARKS
                elif verdict in (NONE, ARTICLE) and (not AWAY.isdisjoint(words) or (above != ARTICLE and not AWAY_OUTSIDE.isdisjoint(words))):
                    verdict = HINT
            elif key == "role":
                if value in ROLES:
                    verdict = OTHER
                elif value in MAIN and verdict == NONE:
                    verdict = ARTICLE
            elif key == "style" and _UNSEEN.search(value):
                return GONE
        if _HIDDEN.search(attrs) or 'aria-hidden="true"' in attrs:
            return GONE
    if above in (OTHER, REMARKS):
        return REMARKS if REMARKS in (verdict, above) else OTHER
    return verdict or above


class Block:
    __slots__ = ("chars", "kind", "linked", "parents", "region", "text")

    def __init__(self, text: str, linked: int, region: int, kind: str, parents: tuple[int, ...]):
        self.text, self.linked, self.region, self.kind, self.parents = text, linked, region, kind, parents
        self.chars = len(text)


def blocks(page: str) -> list[Block]:
    """The visible text blocks of a page in order; markup may be broken or cut off."""
    out: list[Block] = []
    stack: list[tuple[str, int, int]] = [("", 0, NONE)]  # name, number, region
    count = 0
    buffer: list[str] = []
    linked = at = links = 0

    def close() -> None:
        nonlocal linked
        if buffer:
            text = " ".join(_unescape("".join(buffer)).split())
            if text:
                owner = next((s for s in reversed(stack) if s[0] in BLOCKS), stack[0])
                out.append(Block(text, linked, stack[-1][2], owner[0], tuple(s[1] for s in stack if s[0] in BLOCKS or not s[0])[-4:]))
            buffer.clear()
        linked = 0

    def text_of(part: str) -> None:
        nonlocal linked
        if part and stack[-1][2] != GONE:
            buffer.append(part)
            if links:
                linked += len(part.strip())

    def pop(names: frozenset[str], stop: frozenset[str] | None = None) -> None:
        """Ends the nearest open element of these names, and all in it."""
        nonlocal links
        for k in range(len(stack) - 1, 0, -1):
            if stack[k][0] in names:
                for s in stack[k:]:
                    links -= s[0] == "a"
                del stack[k:]
                return
            if stop and stack[k][0] in stop:
                return

    for start, end, name, attrs in tags(page):
        if start < at:  # inside an element whose content is no markup
            continue
        text_of(page[at:start])
        at = end
        if not name:
            if page.startswith("<![CDATA[", start) and end - start > 12:
                text_of(_html.escape(page[start + 9 : end - 3]))
            continue
        if name[0] == "/":
            if name[1:] in BLOCKS:
                close()
                pop(frozenset([name[1:]]))
            else:
                pop(frozenset([name[1:]]), BLOCKS - {"p"})
            continue
        if name in BLOCKS:
            close()
        if name in CLOSES:
            pop(CLOSES[name], frozenset(["ul", "ol", "dl", "table", "div", "article", "section", "blockquote", "main", "aside", "nav", "footer", "form"]))
        elif name in ENDS_P:
            pop(CLOSES["p"], frozenset(["div", "article", "section", "blockquote", "main", "aside", "nav", "footer", "td", "li", "form"]))
        if name in VOID or attrs.endswith("/") and name not in BLOCKS:
            continue
        if name in RAW:
            over = _RAW[name].search(page, end)
            stop = page.find(">", over.end()) if over else -1
            at = stop + 1 if stop >= 0 else len(page)
            continue
        count += 1
        if len(stack) < DEEP:
            above = stack[-1][2]
            stack.append((name, count, above if above == GONE else _region(name, attrs, above)))
            links += name == "a"
    text_of(page[at:])
    close()
    return out


def shape(b: Block) -> int:
    """Number of the block's shape, under SHAPES."""
    size = min(7, max(0, b.chars.bit_length() - 2))
    link = 0 if not b.linked else 1 if b.linked * 3 < b.chars else 2 if b.linked * 3 < 2 * b.chars else 3
    stops = b.text.count(".") + b.text.count(",") + b.text.count("?") + b.text.count("!")
    punct = 0 if not stops else 1 if stops * 60 < b.chars else 2
    kind = 0 if b.kind == "p" else 1 if b.kind in ("h1", "h2", "h3", "h4", "h5", "h6") else 2 if b.kind in ("li", "td", "th", "dd", "dt") else 3
    return ((size * 4 + link) * 3 + punct) * 4 + kind


SHAPES = 8 * 4 * 3 * 4


def _features(i: int) -> list[int]:
    i, kind = divmod(i, 4)
    i, punct = divmod(i, 3)
    size, link = divmod(i, 4)
    return [size, 8 + link, 12 + punct, 15 + kind]


def cut(own: list[tuple[int, int]], edges: list[tuple[int, int, int]]) -> list[bool]:
    """Labels of least cost: own has the cost of each node as content and as other, edges the cost of parting two.

    A node whose own cost outweighs all its edges is on that side of some least cut; it is taken out, and its edges become
    own costs of its neighbours, which may settle them in turn. A maximum flow parts what is left, group by group.
    """
    n = len(own)
    lean = [other - content for content, other in own]  # above zero: content
    near: list[dict[int, int]] = [{} for _ in range(n)]
    for a, b, c in edges:
        near[a][b] = near[a].get(b, 0) + c
        near[b][a] = near[b].get(a, 0) + c
    weight = [sum(x.values()) for x in near]
    side: list[bool | None] = [None] * n
    todo = list(range(n))
    while todo:
        i = todo.pop()
        if side[i] is None and (lean[i] > weight[i] or -lean[i] >= weight[i]):
            side[i] = lean[i] > 0
            for j, c in near[i].items():
                if side[j] is None:
                    lean[j] += c if side[i] else -c
                    weight[j] -= c
                    todo.append(j)
    for i in range(n):
        if side[i] is None:
            group, number = [i], {i: 0}
            for k in group:
                for j in near[k]:
                    if side[j] is None and j not in number:
                        number[j] = len(group)
                        group.append(j)
            part = [(number[k], number[j], c) for k in group for j, c in near[k].items() if j in number and k < j]
            for k, yes in zip(group, flow_cut([(max(0, -lean[k]), max(0, lean[k])) for k in group], part), strict=True):
                side[k] = yes
    return [bool(x) for x in side]


def flow_cut(own: list[tuple[int, int]], edges: list[tuple[int, int, int]]) -> list[bool]:
    """The same by maximum flow alone.

    Augmenting paths along breadth-first layers; nodes still reached from the source afterwards are content.
    """
    n = len(own)
    from_source = [max(0, other - content) for content, other in own]
    to_sink = [max(0, content - other) for content, other in own]
    near: list[dict[int, int]] = [{} for _ in range(n)]
    for a, b, c in edges:
        near[a][b] = near[a].get(b, 0) + c
        near[b][a] = near[b].get(a, 0) + c
    while True:
        level = [-1] * n
        queue = deque(i for i in range(n) if from_source[i])
        for i in queue:
            level[i] = 0
        goal = False
        while queue:
            i = queue.popleft()
            goal = goal or to_sink[i] > 0
            for j, c in near[i].items():
                if c and level[j] < 0:
                    level[j] = level[i] + 1
                    queue.append(j)
        if not goal:
            return [x >= 0 for x in level]
        arcs = [list(near[i]) for i in range(n)]
        for s in range(n):
            while from_source[s]:
                path, i = [s], s
                while path and not to_sink[i]:
                    while arcs[i]:
                        j = arcs[i][-1]
                        if near[i][j] and level[j] == level[i] + 1:
                            break
                        arcs[i].pop()
                    if arcs[i]:
                        i = arcs[i][-1]
                        path.append(i)
                    else:
                        path.pop()
                        if path:
                            arcs[path[-1]].pop()
                            i = path[-1]
                if not path:
                    break
                flow = min([from_source[s], to_sink[i], *(near[a][b] for a, b in zip(path, path[1:], strict=False))])
                from_source[s] -= flow
                to_sink[i] -= flow
                for a, b in zip(path, path[1:], strict=False):
                    near[a][b] -= flow
                    near[b][a] += flow


def _proximity(a: tuple[int, ...], b: tuple[int, ...]) -> int:
    """Steps from the nearest common ancestor (of the last four) down to the two, at most 4."""
    for up, x in enumerate(reversed(a)):
        if x in b:
            return max(up, len(b) - 1 - b.index(x))
    return 4


#: Log odds of content by region, on pages that declare an article and on others, before any page is seen.
PRIOR = np.array([[0.0, 0.0, -4.0, -2.0, -2.5, -4.5], [-1.5, 2.0, -4.0, -3.0, -3.5, -4.5]])


def label(found: list[Block], odds: np.ndarray, regions: np.ndarray) -> list[bool]:
    """Whether each block is content."""
    declared = int(any(b.region == ARTICLE for b in found))
    own: list[tuple[int, int]] = []
    edges: list[tuple[int, int, int]] = []
    last: dict[int, int] = {}
    for i, b in enumerate(found):
        z = int(100 * (odds[shape(b)] + regions[declared, b.region]))
        own.append((max(0, -z), max(0, z)))
        if i:
            p = found[i - 1]
            edges.append((i - 1, i, NEXT // (1 + _proximity(p.parents, b.parents)) // (1 if p.region == b.region else 4)))
        parent = b.parents[-2] if b.kind in ("p", "li", "h1", "h2", "h3", "h4", "h5", "h6") and len(b.parents) > 1 else b.parents[-1]
        if parent in last:
            edges.append((last[parent], i, KIN))
        last[parent] = i
    return cut(own, edges)


def main_text(page: str | None, odds: np.ndarray, regions: np.ndarray = PRIOR) -> str:
    found = blocks(page or "")
    return " ".join(b.text for b, yes in zip(found, label(found, odds, regions), strict=True) if yes)


def _tally(batches: Iterator[pa.RecordBatch], seen) -> Iterator[pa.RecordBatch]:
    """The share of blocks of each (label, key), with the labels and keys that seen gives for a page; every page counts the same."""
    count: dict[tuple[int, int], float] = {}
    for batch in batches:
        for page in batch.column(0):
            found = seen(blocks(page.as_py() or ""))
            for x in found:
                count[x] = count.get(x, 0.0) + 1 / len(found)
    y, key = zip(*count, strict=True) if count else ((), ())
    yield pa.record_batch([pa.array(y, pa.int64()), pa.array(key, pa.int64()), pa.array(list(count.values()), pa.float64())], names=["y", "key", "n"])


def _declared(found: list[Block]) -> list[tuple[int, int]]:
    if not any(b.region == ARTICLE for b in found):
        return []
    return [(int(b.region == ARTICLE), shape(b)) for b in found]


def _by_shape(odds: np.ndarray):
    def seen(found: list[Block]) -> list[tuple[int, int]]:
        declared = int(any(b.region == ARTICLE for b in found))
        return [(int(yes), (declared * 6 + b.region) * SHAPES + shape(b)) for b, yes in zip(found, label(found, odds, np.zeros((2, 6))), strict=True)]

    return seen


def _regress(x: np.ndarray, count: np.ndarray, offset: np.ndarray, prior: np.ndarray, ridge: float) -> np.ndarray:
    """Weights of a logistic regression on counted rows, drawn to the prior."""
    w = prior.copy()
    total = count.sum()
    if not total:
        return w
    k, p = count.sum(0), count[1] / np.maximum(1, count.sum(0))
    for _ in range(25):
        q = 1 / (1 + np.exp(-np.clip(x @ w + offset, -30, 30)))
        grad = x.T @ (k * (p - q)) / total - ridge * (w - prior)
        w += np.clip(np.linalg.solve((x * (k * q * (1 - q) / total)[:, None]).T @ x + ridge * np.eye(len(w)), grad), -2, 2)
    return w


def fit(pages: DataFrame) -> tuple[np.ndarray, np.ndarray]:
    """Log odds of each shape and of each region for content; at most FIT_PAGES pages are read.

    Shapes are learned from pages that declare an article, without which they keep a prior: length and links. Regions
    are learned with the shapes' odds as offset, from the labels of shapes and flow on all pages, drawn to PRIOR.
    """
    n = pages.count()
    rows = pages if n <= FIT_PAGES else pages.filter(F.pmod(F.xxhash64("page_id", "url"), F.lit(1 << 20)) < int(FIT_PAGES / n * (1 << 20)))
    rows = rows.select(F.col("html").cast("string").alias("html"))

    def counted(seen, size: int) -> np.ndarray:
        out = np.zeros((2, size))
        for r in rows.mapInArrow(lambda b: _tally(b, seen), "y long, key long, n double").groupBy("y", "key").agg(F.sum("n").alias("n")).collect():
            out[r["y"], r["key"]] = r["n"]
        return out

    x = np.zeros((SHAPES, 20))
    for i in range(SHAPES):
        x[i, _features(i)] = 1
    x[:, 19] = 1
    prior = np.zeros(20)
    prior[:8] = np.linspace(-1.5, 1.5, 8)
    prior[8:12] = [0.5, 0, -1, -2]
    count = counted(_declared, SHAPES)
    odds = np.clip(x @ (_regress(x, count, np.zeros(SHAPES), prior, 0.003) if count[0].sum() and count[1].sum() else prior), -SURE, SURE)

    count = counted(_by_shape(odds), 12 * SHAPES)
    kept = np.flatnonzero(count.sum(0))
    w = _regress(np.eye(12)[kept // SHAPES], count[:, kept], odds[kept % SHAPES], PRIOR.ravel(), 0.01)
    return odds, np.clip(w, -SURE_NOT, SURE).reshape(2, 6)


def _extract(odds):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = [main_text(x.as_py(), *odds.value) for x in batch.column(2)]
            yield pa.record_batch([batch.column(0).cast(pa.int64()), batch.column(1), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], names=["page_id", "url", "text", "n_chars"])

    return run


def extract(pages: DataFrame) -> DataFrame:
    """page_id, url, text, n_chars of each page, in one pass over whole pages.

    Null and empty pages, and pages without article, give an empty text. White space inside a block becomes one
    space, blocks are joined by one. Every row gives one, rows that are repeated, share an id or have none too; other
    columns are not read, and an empty table gives an empty result.
    """
    odds = pages.sparkSession.sparkContext.broadcast(fit(pages))
    rows = pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), F.col("html").cast("string").alias("html"))
    return rows.mapInArrow(_extract(odds), "page_id long, url string, text string, n_chars long")
