"""Main text of web pages by minimum-cut labelling of blocks.

A page becomes a list of blocks (text between block-level tags).  A logistic classifier over a block's shape (words, linked share, last character,
tag) gives log-odds of being content; what the page says of the block's place (article, menu, footer, form, names of classes and ids) adds fixed
log-odds.  Positive sums are capacities from the content terminal, negative ones to the boilerplate terminal.  Neighbours in page order and
consecutive blocks of one container are joined by smoothness edges.  The minimum cut of this graph, found by maximum flow, labels
all blocks at once.  No cost is infinite: a name inside an article, or one that is only part of a word, can be outvoted by shape and neighbours.

The classifier is fitted to the pages themselves: paragraphs and headings of articles are examples of content, what stands in menus, footers, asides and forms of
boilerplate, and only their shapes are inputs.  About `SAMPLE` pages, chosen by hash, are counted by shape (`SHAPES` rows at most), and
the weights are those of greatest posterior around `PRIOR`; without pages they are `PRIOR`.

Before the flow, blocks whose own capacity outweighs all their edges are settled and folded into their neighbours, which leaves
the cut unchanged; most pages are settled so.  Work is one pass over the page plus a flow over the unsettled blocks.

Defined cases: null or empty html gives an empty text; unclosed tags end with their container; a tag cut off at the end of the page is
dropped; comments, scripts and styles never give text; repeated rows are extracted one by one; ids may be null; extra columns are ignored.
"""

from __future__ import annotations

import html as entities
import re
from collections import Counter, deque
from math import log1p, log2

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import table

#: Elements that begin and end blocks (fixed values, from the HTML standard).
BLOCK = set(
    "address article aside blockquote body caption center dd details dialog dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 "
    "head header hgroup hr html legend li main menu nav ol optgroup option p pre search section select summary table tbody td tfoot th thead title tr ul".split()
)
#: Elements whose raw content is no markup and no text.
RAW = {"script", "style", "noscript", "template", "iframe", "object", "svg", "math", "textarea", "xmp", "noframes", "canvas", "audio", "video"}
#: Elements that hold no article text.
OUTSIDE = {"nav", "footer", "aside", "form", "head", "title", "menu", "dialog", "select", "button", "fieldset", "datalist", "search"}
VOID = {"area", "base", "br", "col", "embed", "hr", "img", "input", "link", "meta", "source", "track", "wbr"}
ROLES = {"navigation", "banner", "contentinfo", "complementary", "search", "dialog", "alertdialog", "alert", "menu", "menubar", "form"}
#: Words in class or id that tell of boilerplate, and words that say nothing of a block (fixed values).
TELLING = set(
    "ad ads advert adverts advertisement advertising sponsor sponsored promo promotion banner cookie cookies consent gdpr notice alert popup modal overlay sidebar rail menu nav "
    "navbar navigation breadcrumb breadcrumbs footer masthead header topbar toolbar social share sharing related recommended recommendations comment comments disqus replies reply respond "
    "widget widgets newsletter subscribe subscription signup login pagination pager copyright legal disclaimer skip hidden".split()
)
NEUTRAL = set(
    "site page main post posts entry article left right top bottom global primary secondary block box container wrapper wrap inner outer section list area bar links link content slot unit "
    "form item items text thread module panel group col column row js sr only side user reader readers icons buttons button 1 2 3".split()
)
TOKEN = re.compile(r"<!--.*?(?:-->|\Z)|<[!?][^>]*(?:>|\Z)|<(/?)([a-zA-Z][^\s/>]*)([^>\"']*+(?:(?:\"[^\"]*+\"|'[^']*+')[^>\"']*+)*+>|[^>]*(?:>|\Z))|</[^a-zA-Z][^>]*(?:>|\Z)", re.S)
ATTRIBUTE = re.compile(r"(class|id|role|hidden|aria-hidden)\b(?:\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+)))?", re.I)

#: Smoothness between neighbours in page order of one container, of two, and between consecutive blocks of a container.
SAME, OTHER, PROXIMITY = 0.8, 0.15, 0.6
#: Log-odds of a block's place: in an article, in an element or role that holds no article text, and in one of a telling name or hinting name.
INSIDE, BARRED, NAMED, HINTED = 3.0, -9.0, -7.0, -2.0
#: Tags that carry a weight of their own; a name on one of the first is a hint only.
LEAVES = {"p", "h1", "h2", "h3", "h4", "h5", "h6", "li", "td", "th", "dd", "dt", "blockquote", "pre", "span", "a", "b", "i", "em", "strong", "font"}
KIND = {"p": 4, "blockquote": 4, "pre": 4, "h1": 5, "h2": 5, "h3": 5, "li": 6, "td": 7, "th": 7}
#: Weights before any page is seen: constant, log of words, linked share, ends like a sentence, paragraph, heading, list item, table cell.
PRIOR = np.array([-1.2, 0.6, -3.0, 0.3, 0.8, 0.7, -0.4, -0.2])
#: Pages that the classifier is fitted to, at about; what all of them weigh against the prior; shapes that are told apart, at most.
SAMPLE, EVIDENCE, SHAPES = 2000, 20.0, 40 * 11 * 2 * 5 * 2


def place_cost(tag: str, attributes: str, inside_article: bool) -> float:
    """Log-odds that the attributes and the tag of an element add to the blocks in it."""
    if tag in OUTSIDE or (tag == "header" and not inside_article):
        return BARRED
    if not attributes.strip("/> \n\t"):
        return 0.0
    cost = 0.0
    for name, a, b, c in ATTRIBUTE.findall(attributes):
        value, name = (a or b or c).lower(), name.lower()
        if name == "hidden" or (name == "aria-hidden" and value == "true") or (name == "role" and value in ROLES):
            return BARRED
        if name in ("class", "id") and tag not in ("html", "body", "article", "main"):
            for word in value.split():
                parts = re.split(r"[-_]+", word)
                if any(p in TELLING for p in parts):
                    whole = all(p in TELLING or p in NEUTRAL for p in parts)
                    cost = min(cost, NAMED if whole and tag not in LEAVES else HINTED)
    return cost


def blocks_of(page: str) -> list[tuple[str, int, float, bool, str, int]]:
    """(text, container, cost of its place, in article?, tag, linked characters) per block, in page order."""
    out, piece, linked = [], [], 0
    stack: list[tuple[str, int, float, bool]] = [("", 0, 0.0, False)]  # tag, number, cost, in article
    open_tags: Counter = Counter()  # of the stack, so that a closing tag need not search it
    containers, in_link, at = 0, False, 0

    def flush():
        nonlocal linked, in_link
        if piece:
            text = " ".join(entities.unescape("".join(piece)).split())
            if text:
                tag, _, cost, inside = stack[-1]
                depth = -2 if tag in ("p", "li", "h1", "h2", "h3", "h4", "h5", "h6", "td", "th", "dd", "dt", "pre") and len(stack) > 1 else -1
                out.append((text, stack[depth][1], cost, inside, tag, linked))
            piece.clear()
        linked = 0
        in_link = False

    def pop() -> str:
        tag = stack.pop()[0]
        open_tags[tag] -= 1
        return tag

    end = len(page)
    while at < end:
        match = TOKEN.search(page, at)
        text = page[at : match.start()] if match else page[at:]
        if text:
            piece.append(text)
            if in_link:
                linked += len(text)
        if not match:
            break
        at = match.end()
        closing, tag, attributes = match[1], match[2], match[3]
        if not tag:
            continue
        tag = tag.lower()
        if tag in RAW and not closing:
            if not attributes.endswith("/>"):
                close = re.compile(rf"</{re.escape(tag)}\b[^>]*(?:>|\Z)", re.I).search(page, at)
                at = close.end() if close else end
            continue
        if tag == "a":
            in_link = not closing
        if tag == "br" or tag == "img":
            piece.append(" ")
        hides = not closing and tag not in VOID and tag not in BLOCK and place_cost(tag, attributes, stack[-1][3]) < 0
        if tag not in BLOCK and not hides and not (closing and open_tags[tag]):
            continue
        flush()
        if tag in VOID:
            continue
        if closing:
            if open_tags[tag]:
                while pop() != tag:
                    pass
            continue
        if tag in ("p", "li", "dt", "dd", "tr", "td", "th", "option") or stack[-1][0] == "p":
            ends = {"li": ("li",), "dt": ("dt", "dd"), "dd": ("dt", "dd"), "tr": ("tr", "td", "th"), "td": ("td", "th"), "th": ("td", "th"), "option": ("option",)}.get(tag, ())
            while len(stack) > 1 and (stack[-1][0] == "p" or stack[-1][0] in ends):
                pop()
        containers += 1
        cost, inside = stack[-1][2], stack[-1][3] or tag in ("article", "main")
        stack.append((tag, containers, min(cost, place_cost(tag, attributes, stack[-1][3])), inside))
        open_tags[tag] += 1
    flush()
    return out


def shape(text: str, tag: str, linked: int) -> tuple[int, float, int, int]:
    """Words, linked share, ends like a sentence, kind of tag."""
    return text.count(" ") + 1, min(1.0, linked / len(text)), int(text[-1] in ".!?…\"”"), KIND.get(tag, 0)


def log_odds(weights, words: float, share: float, ends: int, kind: int) -> float:
    return weights[0] + weights[1] * log1p(words) + weights[2] * share + weights[3] * ends + (weights[kind] if kind else 0.0)


def example_of(block) -> int | None:
    """1 for examples of content, 0 of boilerplate, None for blocks that the page does not tell of."""
    _, _, cost, inside, tag, _ = block
    if cost <= BARRED:
        return 0
    return 1 if inside and cost == 0 and KIND.get(tag) in (4, 5) else None


def fitted(shapes: pd.DataFrame) -> np.ndarray:
    """Weights of greatest posterior; shapes(words, share, ends, kind, label, n) counts examples."""
    w = PRIOR.copy()
    if not len(shapes) or shapes["label"].nunique() < 2:
        return w
    x = np.zeros((len(shapes), len(PRIOR)))
    x[:, 0], x[:, 1], x[:, 2], x[:, 3] = 1.0, np.log1p(shapes["words"]), shapes["share"], shapes["ends"]
    for kind in (4, 5, 6, 7):
        x[:, kind] = shapes["kind"] == kind
    y = shapes["label"].to_numpy(float)
    counts = shapes["n"].to_numpy(float)
    half = np.where(y == 1, counts[y == 1].sum(), counts[y == 0].sum())  # both kinds of example weigh the same
    counts = EVIDENCE / 2 * counts / half
    for _ in range(50):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        gradient = x.T @ (counts * (y - p)) - (w - PRIOR)
        move = np.linalg.solve(x.T @ (x * (counts * p * (1 - p))[:, None]) + np.eye(len(w)), gradient)
        w = w + move
        if np.abs(move).max() < 1e-9:
            break
    return np.round(w, 9)


def fit_weights(pages: DataFrame, html_col: str = "html") -> np.ndarray:
    """Fit the classifier to about SAMPLE pages of the table."""
    total = pages.count()
    if not total:
        return PRIOR

    def examples(batches):
        for pdf in batches:
            out = []
            for page in pdf["html"]:
                for block in blocks_of(page if isinstance(page, str) else ""):
                    if (label := example_of(block)) is not None:
                        words, share, ends, kind = shape(block[0], block[4], block[5])
                        out.append((2 ** (min(39, int(2 * log2(words))) / 2), round(share, 1), ends, kind, label))
            yield pd.DataFrame(out, columns=["words", "share", "ends", "kind", "label"])

    chosen = pages.where(F.pmod(F.xxhash64(html_col), F.lit(1 << 40)) < F.lit(-(-SAMPLE * (1 << 40) // total)))
    rows = chosen.select(F.col(html_col).alias("html")).mapInPandas(examples, "words double, share double, ends int, kind int, label int")
    order = ["words", "share", "ends", "kind", "label"]
    return fitted(rows.groupBy(*order).agg(F.count("*").alias("n")).toPandas().sort_values(order, ignore_index=True))  # SHAPES rows at most


def min_cut(scores: list[float], edges: dict[tuple[int, int], float]) -> list[bool]:
    """True for the nodes on the content side of the minimum cut (on ties: content for scores above 0)."""
    n = len(scores)
    near: list[dict[int, float]] = [{} for _ in range(n)]
    for (a, b), w in edges.items():
        near[a][b] = near[a].get(b, 0.0) + w
        near[b][a] = near[b].get(a, 0.0) + w
    own, label = list(scores), [None] * n
    queue = deque(range(n))
    while queue:
        i = queue.popleft()
        if label[i] is not None or abs(own[i]) < sum(near[i].values()):
            continue
        label[i] = own[i] > 0
        for j, w in near[i].items():
            del near[j][i]
            own[j] += w if label[i] else -w
            queue.append(j)
        near[i] = {}
    rest = [i for i in range(n) if label[i] is None]
    if rest:
        for i, content in zip(rest, flow_side(rest, own, near), strict=True):
            label[i] = content
    return label


def flow_side(rest: list[int], own: list[float], near: list[dict[int, float]]) -> list[bool]:
    """Maximum flow over the unsettled nodes, by blocking flows on level graphs; who stays reachable from the content terminal."""
    place = {i: k for k, i in enumerate(rest)}
    source, sink = len(rest), len(rest) + 1
    arcs: list[list[int]] = [[] for _ in range(len(rest) + 2)]  # numbers of arcs; arc e ^ 1 is the reverse of e
    to, room = [], []

    def join(a, b, forth, back):
        arcs[a].append(len(to))
        arcs[b].append(len(to) + 1)
        to.extend((b, a))
        room.extend((forth, back))

    for k, i in enumerate(rest):
        if own[i] > 0:
            join(source, k, own[i], 0.0)
        else:
            join(k, sink, -own[i], 0.0)
        for j, w in near[i].items():
            if i < j:
                join(k, place[j], w, w)

    def levels():
        level, queue = [-1] * len(arcs), deque([source])
        level[source] = 0
        while queue:
            a = queue.popleft()
            for e in arcs[a]:
                if room[e] > 1e-12 and level[to[e]] < 0:
                    level[to[e]] = level[a] + 1
                    queue.append(to[e])
        return level

    while (level := levels())[sink] >= 0:
        tried = [0] * len(arcs)
        path, a = [], source
        while True:
            if a == sink:
                push = min(room[e] for e in path)
                for e in path:
                    room[e] -= push
                    room[e ^ 1] += push
                full = next(k for k, e in enumerate(path) if room[e] <= 1e-12)
                a = to[path[full] ^ 1]
                del path[full:]
            while tried[a] < len(arcs[a]):
                e = arcs[a][tried[a]]
                if room[e] > 1e-12 and level[to[e]] == level[a] + 1:
                    break
                tried[a] += 1
            if tried[a] < len(arcs[a]):
                path.append(arcs[a][tried[a]])
                a = to[path[-1]]
            elif path:
                a = to[path.pop() ^ 1]
                tried[a] += 1
            else:
                break
    return [level[k] >= 0 for k in range(len(rest))]


def extract(page: str | None, weights=PRIOR) -> str:
    blocks = blocks_of(page or "")
    if not blocks:
        return ""
    scores = [log_odds(weights, *shape(text, tag, linked)) + cost + (INSIDE if inside else 0.0) for text, _, cost, inside, tag, linked in blocks]
    edges: dict[tuple[int, int], float] = {}
    last: dict[int, int] = {}
    for i, b in enumerate(blocks):
        if i:
            edges[(i - 1, i)] = SAME if blocks[i - 1][1] == b[1] else OTHER
        if b[1] in last:
            edges[(last[b[1]], i)] = edges.get((last[b[1]], i), 0.0) + PROXIMITY
        last[b[1]] = i
    return "\n\n".join(b[0] for b, keep in zip(blocks, min_cut(scores, edges), strict=True) if keep)


def extract_pages(pages: DataFrame, id_col: str = "page_id", html_col: str = "html", weights=None) -> DataFrame:
    """One row per page: page_id, url, text, n_chars.  `weights` of the classifier are fitted to `pages` unless given."""
    weights = fit_weights(pages, html_col) if weights is None else weights

    def run(batches):
        for pdf in batches:
            texts = [extract(x if isinstance(x, str) else None, weights) for x in pdf["html"]]
            yield pd.DataFrame({"page_id": pdf["page_id"].astype("Int64"), "url": pdf["url"], "text": texts, "n_chars": [len(t) for t in texts]})

    chosen = pages.select(F.col(id_col).cast("long").alias("page_id"), "url", F.col(html_col).alias("html"))
    return chosen.mapInPandas(run, "page_id long, url string, text string, n_chars long")


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return extract_pages(table(spark, sf_dir, "pages"))


QUERIES = {"op8_html_extraction": query}
ORACLE_SQL: dict[str, str] = {}
