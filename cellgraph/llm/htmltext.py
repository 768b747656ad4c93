"""Main-text extraction from HTML by minimum-cut labelling.

A page becomes a sequence of text blocks.  A classifier gives each block log-odds for content: a
logistic model of its text (length, link share, how it ends, its tag), fitted on a bounded sample of
pages whose own markup says what is article and what is not, plus evidence from where it stands
(article, navigation, class names).  These are the capacities to the two terminals.  Blocks that
follow each other, and blocks under one parent, are joined by smoothness edges that weaken with
their distance in the tree, strong enough to overrule a block's own odds.  The minimum cut separates
content from the rest.

Blocks whose terminal cost outweighs all their edges keep their own label in every minimum cut; they
are folded into their neighbours' costs first, and max-flow runs on what is left.
"""

from __future__ import annotations

import math
import re
from collections import Counter, deque
from collections.abc import Iterator
from dataclasses import dataclass, field, replace
from html import unescape

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

# Tag and class vocabularies of HTML pages.
BLOCK_TAGS = frozenset(
    "address article aside blockquote body caption center dd details dialog dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 head header hgroup hr html legend li main menu nav ol optgroup option p pre section summary table tbody td tfoot th thead tr ul".split()
)
VOID_TAGS = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW_TAGS = frozenset("script style textarea title iframe noembed noframes xmp".split())
DROPPED_TAGS = frozenset("script style textarea title iframe noembed noframes xmp template noscript svg math canvas object audio video".split())
AVOIDED_TAGS = frozenset("nav footer aside form menu dialog select datalist button".split())
AVOIDED_ROLES = frozenset("navigation banner contentinfo complementary search form dialog alertdialog alert menu menubar toolbar tablist".split())
TELLING_NAMES = frozenset(
    "ad ads adv advert adverts advertisement advertising adsense adslot nav navbar navigation menu breadcrumb breadcrumbs sidebar footer cookie cookies consent gdpr comment comments commentlist disqus replies newsletter popup modal outbrain taboola".split()
)
HINTING_NAMES = frozenset(
    "sponsor sponsored sponsors promo promoted promotion rail masthead banner notice notices notification alert reply respond discussion share sharing social related recommended recommendations subscribe subscription signup overlay login search widget widgets pagination pager copyright disclaimer toolbar skip".split()
)
NEUTRAL_NAMES = frozenset(
    "article articles post posts story stories news entry entries main primary secondary text body page site wrap wrapper container layout box bar block area section panel list links link items item buttons button icons icon inner outer top bottom left right header head title content unit slot row col column group form field input count count meta info small large sticky fixed the and of".split()
)
CLOSED_BY_BLOCK = frozenset("p h1 h2 h3 h4 h5 h6".split())
ITEM_SCOPES = {"li": ("ul", "ol", "menu"), "dt": ("dl",), "dd": ("dl",), "tr": ("table",), "td": ("tr", "table"), "th": ("tr", "table"), "option": ("select",)}

_MARKUP = re.compile(r"<!--.*?(?:-->|\Z)|<!\[CDATA\[.*?(?:\]\]>|\Z)|<[!?][^>]*(?:>|\Z)|<(/?)([a-zA-Z][^\s/>]*)([^>\"']*(?:\"[^\"]*\"[^>\"']*|'[^']*'[^>\"']*)*)>|<(/?)([a-zA-Z][^\s/>]*)([^>]*)(?:>|\Z)", re.S)
_ATTRIBUTE = re.compile(r"""([^\s=/"'>]+)(?:\s*=\s*(?:"([^"]*)"|'([^']*)'|([^\s"'>]+)))?""")
_NAME_PARTS = re.compile(r"[A-Z]?[a-z]+|[A-Z]+")


#: Features of a block's text, in the order of their weights.
TEXT_FEATURES = ("any", "long", "sentence", "short", "linked", "heading", "paragraph", "copyright")


@dataclass(frozen=True)
class Weights:
    """Log-odds for content: of the text features (fitted), of the place (evidence), and the smoothness of the labelling."""

    text: tuple[float, ...] = (0.0, 1.5, 1.0, -0.7, -3.0, 0.5, 0.7, -2.0)
    text_limit: float = 2.5
    inside_main: float = 2.0
    tag: float = -6.0
    telling_name: float = -6.0
    hinting_name: float = -2.0
    page_header: float = -5.0
    adjacent: float = 1.2
    same_parent: float = 0.8


@dataclass
class Node:
    tag: str
    parent: Node | None
    depth: int
    main: bool
    avoided: bool  # by tag or role
    named: int  # 2: a telling class name, 1: a hint
    header: bool
    linked: bool


@dataclass
class Block:
    node: Node
    parts: list[str] = field(default_factory=list)
    linked: int = 0
    text: str = ""


def name_evidence(names: str) -> int:
    """2 if a class name or id tells that this is no article, 1 if it hints at it, 0 else.

    A name counts only if all its parts are of that kind or neutral: ``share-bar`` does, ``share-price`` does not.
    """
    found = 0
    for name in names.split():
        parts = {p.lower() for p in _NAME_PARTS.findall(name)}
        if parts & TELLING_NAMES and parts <= TELLING_NAMES | HINTING_NAMES | NEUTRAL_NAMES:
            return 2
        if parts & HINTING_NAMES and parts <= HINTING_NAMES | NEUTRAL_NAMES:
            found = 1
    return found


def _opened(tag: str, attributes: str, parent: Node) -> Node:
    main = parent.main or tag in ("article", "main")
    avoided = parent.avoided or tag in AVOIDED_TAGS
    header = parent.header or (tag == "header" and not main)
    named = parent.named
    if attributes and tag not in ("html", "body", "main", "article"):
        given = {k.lower(): a or b or c for k, a, b, c in _ATTRIBUTE.findall(attributes)}
        names = f"{given.get('class', '')} {given.get('id', '')}"
        named = max(named, name_evidence(names))
        avoided = avoided or given.get("role", "").lower() in AVOIDED_ROLES
        if not main and any(p.lower() in ("header", "masthead") for n in names.split() for p in [n]):
            header = True
        if given.get("role", "").lower() == "main" or given.get("itemprop", "").lower() == "articlebody":
            main = True
    return Node(tag, parent, parent.depth + 1, main, avoided, named, header, parent.linked or tag == "a")


def blocks_of(html: str) -> list[Block]:
    """The page's text blocks in order, white space settled, empty ones left out."""
    root = Node("#root", None, 0, False, False, 0, False, False)
    unclosed: set[str] = set()
    stack, out, current, at, end = [root], [], None, 0, len(html)

    def add(raw: str) -> None:
        nonlocal current
        if not raw:
            return
        if current is None:
            home = stack[-1]
            while home.tag not in BLOCK_TAGS and home.parent is not None:
                home = home.parent
            current = Block(home)
            out.append(current)
        current.parts.append(raw)
        if stack[-1].linked:
            current.linked += len(raw)

    def close(index: int) -> None:
        nonlocal current
        if any(n.tag in BLOCK_TAGS for n in stack[index:]):
            current = None
        del stack[index:]

    while at < end:
        m = _MARKUP.search(html, at)
        if m is None:
            add(html[at:])
            break
        if m.start() > at:
            add(html[at : m.start()])
        at = m.end()
        closing, tag, attributes = (m[1], m[2], m[3]) if m[2] else (m[4], m[5], m[6])
        if not tag:
            continue
        tag = tag.lower()
        if closing:
            for i in range(len(stack) - 1, 0, -1):
                if stack[i].tag == tag:
                    close(i)
                    break
            continue
        if tag in DROPPED_TAGS:
            if attributes.endswith("/"):
                continue
            stop = None if tag in unclosed else re.compile(rf"</{re.escape(tag)}[\s/>]", re.I).search(html, at)
            if stop is None:
                unclosed.add(tag)  # nor does it close further on
                at = end if tag in RAW_TAGS else at
            else:
                at = html.find(">", stop.start()) + 1 or end
            continue
        if tag in BLOCK_TAGS:
            if tag in ITEM_SCOPES:
                for i in range(len(stack) - 1, 0, -1):
                    if stack[i].tag in ITEM_SCOPES[tag]:
                        break
                    if stack[i].tag == tag or (tag in ("td", "th") and stack[i].tag in ("td", "th")) or (tag in ("dt", "dd") and stack[i].tag in ("dt", "dd")):
                        close(i)
                        break
            elif len(stack) > 1:
                for i in range(len(stack) - 1, 0, -1):  # an open paragraph ends where a block begins
                    if stack[i].tag in CLOSED_BY_BLOCK:
                        if stack[i].tag == "p" or tag in CLOSED_BY_BLOCK:
                            close(i)
                        break
                    if stack[i].tag in BLOCK_TAGS:
                        break
            current = None
        elif tag == "br":
            add(" ")
        if tag not in VOID_TAGS and not attributes.endswith("/"):
            stack.append(_opened(tag, attributes, stack[-1]))
    kept = []
    for b in out:
        raw = "".join(b.parts)
        b.text = " ".join((unescape(raw) if "&" in raw else raw).split())
        if b.text:
            kept.append(b)
    return kept


def text_features(b: Block) -> int:
    """`TEXT_FEATURES` as bits."""
    t, tag = b.text, b.node.tag
    words = t.count(" ") + 1
    heading = tag in ("h1", "h2", "h3", "h4", "h5", "h6")
    on = (True, words >= 20, words >= 6 and t[-1] in ".!?…\"'”»:;", words < 4 and not heading, b.linked * 2 > len(t), heading, tag == "p", t[0] == "©" or t[:9].lower() == "copyright")
    return sum(1 << i for i, x in enumerate(on) if x)


def content_odds(b: Block, w: Weights) -> float:
    """Log-odds that the block is content."""
    n, bits = b.node, text_features(b)
    odds = sum(x for i, x in enumerate(w.text) if bits >> i & 1)
    odds = max(-w.text_limit, min(w.text_limit, odds))
    if n.main:
        odds += w.inside_main
    if n.avoided:
        odds += w.tag
    if n.named:
        odds += w.telling_name if n.named == 2 else w.hinting_name
    if n.header:
        odds += w.page_header
    return odds


def own_label(b: Block) -> int:
    """What the page's markup says of a block: 1 for article, 0 for none, -1 if it says nothing."""
    n = b.node
    outside = n.avoided or n.named == 2 or n.header
    return 0 if outside else 1 if n.main and not n.named else -1


def fit_text_weights(counts: dict[tuple[int, int], int], prior: Weights = Weights(), strength: float = 4.0, steps: int = 25) -> Weights:
    """Logistic regression of the label on the text features from ``counts[features, label]``, both labels weighing alike.

    ``strength`` pulls towards the prior's weights; features that were never seen keep those.
    """
    rows = [(f, y, n) for (f, y), n in sorted(counts.items()) if y >= 0]
    totals = Counter()
    for _, y, n in rows:
        totals[y] += n
    if len(totals) < 2:
        return prior
    x = np.array([[f >> i & 1 for i in range(len(TEXT_FEATURES))] for f, _, _ in rows], dtype=float)
    y = np.array([y for _, y, _ in rows], dtype=float)
    n = np.array([n / totals[y] for _, y, n in rows]) * 100.0
    start = np.array(prior.text)
    w = start.copy()
    for _ in range(steps):  # Newton steps
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        grad = x.T @ (n * (y - p)) - strength * (w - start)
        hess = (x * (n * p * (1 - p))[:, None]).T @ x + strength * np.eye(len(w))
        w = w + np.linalg.solve(hess, grad)
    return replace(prior, text=tuple(round(float(v), 6) for v in w))


def tree_distance(a: Node, b: Node) -> int:
    steps = 0
    while a is not b:
        if a.depth >= b.depth:
            a = a.parent
        else:
            b = b.parent
        steps += 1
    return steps


def min_cut(odds: list[float], edges: dict[tuple[int, int], float]) -> list[bool]:
    """True where a node is on the source (content) side of a minimum cut.

    Node i has capacity odds[i] from the source if positive, else -odds[i] to the sink.  Of several
    minimum cuts the one with fewest content nodes is taken.
    """
    n = len(odds)
    near: list[dict[int, float]] = [{} for _ in range(n)]
    for (i, j), c in edges.items():
        near[i][j] = near[i].get(j, 0.0) + c
        near[j][i] = near[j].get(i, 0.0) + c
    pull, label = list(odds), [None] * n
    pressure = [sum(x.values()) for x in near]
    todo = deque(range(n))
    while todo:
        i = todo.popleft()
        if label[i] is None and abs(pull[i]) > pressure[i]:
            label[i] = pull[i] > 0
            for j, c in near[i].items():
                if label[j] is None:
                    pull[j] += c if label[i] else -c
                    pressure[j] -= c
                    todo.append(j)
    rest = [i for i in range(n) if label[i] is None]
    if rest:
        inside = _source_side([pull[i] for i in rest], {(a, b): near[i][j] for a, i in enumerate(rest) for b, j in enumerate(rest) if j in near[i]})
        for i, side in zip(rest, inside, strict=True):
            label[i] = side
    return label


def _source_side(pull: list[float], arcs: dict[tuple[int, int], float]) -> list[bool]:
    """Max-flow by blocking flows in level graphs; ``arcs`` holds both directions of each edge."""
    n = len(pull)
    s, t = n, n + 1
    cap: list[dict[int, float]] = [{} for _ in range(n + 2)]
    for (a, b), c in arcs.items():
        cap[a][b] = cap[a].get(b, 0.0) + c
    for i, p in enumerate(pull):
        if p > 0:
            cap[s][i], cap[i][s] = p, 0.0
        elif p < 0:
            cap[i][t], cap[t][i] = -p, 0.0
    tiny = 1e-12
    while True:
        level = {s: 0}
        queue = deque([s])
        while queue:
            u = queue.popleft()
            for v, c in cap[u].items():
                if c > tiny and v not in level:
                    level[v] = level[u] + 1
                    queue.append(v)
        if t not in level:
            return [i in level for i in range(n)]
        paths = {u: iter(list(cap[u])) for u in level}
        trail = [s]
        while trail:
            u = trail[-1]
            if u == t:
                flow = min(cap[a][b] for a, b in zip(trail, trail[1:], strict=False))
                for a, b in zip(trail, trail[1:], strict=False):
                    cap[a][b] -= flow
                    cap[b][a] = cap[b].get(a, 0.0) + flow
                trail = [s]
                paths = {x: iter(list(cap[x])) for x in level}
                continue
            for v in paths[u]:
                if cap[u].get(v, 0.0) > tiny and level.get(v) == level[u] + 1:
                    trail.append(v)
                    break
            else:
                level.pop(u, None)
                trail.pop()


def page_costs(blocks: list[Block], w: Weights) -> tuple[list[float], dict[tuple[int, int], float]]:
    """Terminal capacities (log-odds) and smoothness edges of a page."""
    edges: dict[tuple[int, int], float] = {}
    last_under: dict[int, int] = {}
    for i, b in enumerate(blocks):
        if i:
            edges[(i - 1, i)] = w.adjacent * 2.0 ** (-tree_distance(blocks[i - 1].node, b.node) / 2)
        parent = id(b.node.parent)
        if parent in last_under:
            pair = (last_under[parent], i)
            edges[pair] = edges.get(pair, 0.0) + w.same_parent
        last_under[parent] = i
    return [content_odds(b, w) for b in blocks], edges


def extract(html: str | None, weights: Weights = Weights()) -> str:
    """The page's main text: its content blocks in page order, one per line."""
    blocks = blocks_of(html) if html else []
    if not blocks:
        return ""
    return "\n".join(b.text for b, content in zip(blocks, min_cut(*page_costs(blocks, weights)), strict=True) if content)


def cut_effect(html: str | None, weights: Weights = Weights()) -> tuple[int, int]:
    """(blocks, blocks whose label differs from the sign of their own odds)."""
    blocks = blocks_of(html) if html else []
    if not blocks:
        return 0, 0
    odds, edges = page_costs(blocks, weights)
    return len(blocks), sum(label != (o > 0) for label, o in zip(min_cut(odds, edges), odds, strict=True))


def fit_weights(pages: DataFrame, id_col: str = "page_id", html_col: str = "html", sample: int = 2000, seed: int = 5) -> Weights:
    """Fits the text weights on about ``sample`` pages by id hash, all pages if there are fewer.

    The driver gets a count per combination of the binary text features and label.
    """
    total = pages.count()
    if not total:
        return Weights()
    near = F.pmod(F.xxhash64(F.lit(seed), id_col), F.lit(1 << 30)) < math.ceil((1 << 30) * min(1.0, sample / total))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: Counter = Counter()
        for b in batches:
            for h in b.column(0):
                seen.update((text_features(x), own_label(x)) for x in blocks_of(h.as_py() or ""))
        rows = sorted((f, y, n) for (f, y), n in seen.items() if y >= 0)
        cols = list(zip(*rows, strict=True)) or [(), (), ()]
        yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in cols], names=["f", "y", "n"])

    chosen = pages.where(F.coalesce(near, F.lit(True))).select(html_col)
    counts = chosen.mapInArrow(run, "f long, y long, n long").groupBy("f", "y").agg(F.sum("n").alias("n")).collect()
    return fit_text_weights({(r["f"], r["y"]): r["n"] for r in counts})


def extract_text(pages: DataFrame, id_col: str = "page_id", html_col: str = "html", keep: tuple[str, ...] = ("url",), weights: Weights | None = None) -> DataFrame:
    """``(id, keep.., text, n_chars)`` from whole pages: one pass without a shuffle, after `fit_weights` unless weights are given.

    A null or empty page, and one without content, has the text ''.  Broken markup is read as far as it
    goes, in time linear in the page.  Repeated rows get equal answers; ids may be null; an empty table gives an empty
    result; other columns are ignored.
    """
    fitted = fit_weights(pages, id_col, html_col) if weights is None else weights
    columns = [id_col, *keep]
    schema = pages.select(*columns).schema.add("text", "string").add("n_chars", "long")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            texts = [extract(h.as_py(), fitted) for h in b.column(len(columns))]
            yield pa.RecordBatch.from_arrays([*b.columns[:-1], pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], names=[*columns, "text", "n_chars"])

    return pages.select(*columns, html_col).mapInArrow(run, schema)


def extraction_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return extract_text(spark.read.parquet(f"{sf_dir}/pages.parquet"))
