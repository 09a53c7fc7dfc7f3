"""Main text of web pages by minimum-cut labelling of their blocks.

A page is cut into blocks at block-level tags; a block knows the elements around it. A linear classifier over the block's
surroundings and words gives the cost of calling it content and of calling it boilerplate; these are the capacities to the two
terminals. Blocks that follow each other, and blocks under one parent, are tied by edges whose capacity falls with their
distance in the element tree and is of the order of a block's doubt, so blocks that are unclear by themselves go with their
neighbours. The cheapest labelling is a minimum cut, found by blocking flows over short paths.

The classifier is a logistic regression, fitted on at most ``SAMPLE`` pages chosen by a hash and ``PER_PAGE`` blocks of each: blocks inside an article or main element, and
blocks inside elements that the markup sets apart (navigation, footer, aside and the like), are its examples. Each stands twice among them,
with and without what is known of its surroundings, so that the words count by themselves on pages that mark nothing. A normal prior around
``PRIOR`` keeps the weights of what the sample does not show.
"""

from __future__ import annotations

import html
import math
import re
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import table

#: Fixed values of the markup language.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style title noscript iframe template xmp noframes noembed object svg math".split())
INLINE = frozenset("a abbr b bdi bdo big cite code data del dfn em font i img ins kbd mark q rb rp rt ruby s samp small span strike strong sub sup time tt u var wbr".split())
CLOSED_BY = {"p": frozenset("address article aside blockquote center details dialog dir div dl fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr main menu nav ol p pre section table ul li dt dd tr td th".split()), "li": frozenset(["li"]), "dt": frozenset(["dt", "dd"]), "dd": frozenset(["dt", "dd"]), "tr": frozenset(["tr"]), "td": frozenset(["td", "th", "tr"]), "th": frozenset(["td", "th", "tr"]), "option": frozenset(["option"])}
TOKEN = re.compile(r"""<!--.*?(?:-->|$)|<[!?][^>]*(?:>|$)|<(/?)([a-zA-Z][^\s/>]*)([^>"']*(?:(?:"[^"]*"|'[^']*')[^>"']*)*)>|<(/?)([a-zA-Z][^\s/>]*)([^>]*)(?:>|$)""", re.S)
NAMED = re.compile(r"""(?i)(?:^|\s)(class|id|role|hidden|style|aria-hidden|itemprop|aria-label)(?:\s*=\s*("[^"]*"|'[^']*'|[^\s"'>]+))?""")
WORD = re.compile(r"[A-Z]?[a-z0-9]+|[A-Z]+")
#: Words of class, id and role that speak for boilerplate or for the article.
AGAINST = frozenset("ad ads adv advert adverts advertisement advertising sponsor sponsored banner promo promotion sidebar aside rail menu nav navbar navigation navi breadcrumb breadcrumbs footer foot header masthead topbar toolbar cookie cookies consent gdpr notice notification alert popup modal overlay dialog comment comments disqus reply replies respond discussion share sharing social follow subscribe newsletter signup login search form related recommended recommend more widget pagination pager tags tagcloud copyright legal disclaimer skip contentinfo complementary complaint".split())
FOR = frozenset("article main content post entry story body text articlebody maincontent".split())
HIDDEN = re.compile(r"(?i)display\s*:\s*none|visibility\s*:\s*hidden")
#: Log-odds for content before any page is seen, by feature: always; inside an article or main element; in a paragraph; in a heading; log2 of the
#: words, up to 6; ends like a sentence; linked part of the words; elements around it that speak against, page headers, and hidden ones.
PRIOR = {"bias": -1.0, "main": 2.2, "paragraph": 0.8, "heading": 0.4, "length": 0.3, "stops": 0.3, "links": -1.5, "against": -6.0, "page_header": -4.0, "hidden": -8.0}
#: Features of a block's surroundings, which its second example goes without.
AROUND = ("main", "against", "page_header", "hidden")
#: Pages that the fit sees, blocks of each (spread over the page), its steps, and how firmly weights are held to the prior.
SAMPLE, PER_PAGE, STEPS, FIRMNESS = 300, 400, 200, 0.05
#: Capacity between neighbours in the page, and between neighbours under one parent; both fall with distance in the tree and end at FAR.
ADJACENT, SIBLING, FAR = 3.0, 0.8, 32
OUTSIDE = frozenset("nav footer aside form menu dialog button select label fieldset address".split())


@dataclass
class Element:
    tag: str
    parent: Element | None
    depth: int
    against: bool = False
    favour: bool = False
    hidden: bool = False
    main: bool = False
    marked: bool = False
    apart: bool = False
    n_against: int = 0
    n_header: int = 0
    n_hidden: int = 0


@dataclass
class Block:
    text: str
    parent: Element
    linked: int = 0
    heading: bool = False
    log_odds: float = 0.0
    content: bool = field(default=False)


def _open(tag: str, attributes: str, parent: Element) -> Element:
    e = Element(tag, parent, parent.depth + 1, main=parent.main, marked=parent.marked, apart=parent.apart, n_against=parent.n_against, n_header=parent.n_header, n_hidden=parent.n_hidden)
    if attributes.strip():
        for name, value in NAMED.findall(attributes):
            name, value = name.lower(), value.strip("\"'")
            if name == "hidden" or (name == "aria-hidden" and value.lower() == "true") or (name == "style" and HIDDEN.search(value)):
                e.hidden = True
            elif name in ("class", "id", "role", "itemprop"):
                words = {w.lower() for w in WORD.findall(value)}
                e.against |= bool(words & AGAINST)
                e.favour |= bool(words & FOR) or value.lower() in FOR
    if tag in ("article", "main") or (e.favour and not e.against and tag not in INLINE):
        e.main = True
    e.marked |= tag in ("article", "main")
    e.apart |= tag in OUTSIDE
    e.n_against += tag in OUTSIDE or (e.against and tag not in ("article", "main", "body", "html"))
    e.n_header += tag == "header" and not parent.main
    e.n_hidden += e.hidden
    return e


def blocks_of(page: str) -> list[Block]:
    """Blocks with text, in page order. Text of scripts, styles and titles is none."""
    root = Element("#", None, 0)
    stack, out, at, n = [root], [], 0, len(page)
    buffer: list[str] = []
    opened: Counter[str] = Counter()  # how many elements of a tag are open, so that a stray end tag costs nothing
    linked = heading = 0

    def flush() -> None:
        nonlocal linked, heading
        if buffer:
            text = " ".join("".join(buffer).split())
            buffer.clear()
            if text:
                holder = stack[-1]
                while holder.tag in INLINE and holder.parent:
                    holder = holder.parent
                out.append(Block(text, holder, linked, bool(heading)))
        linked = 0

    def shut(k: int) -> None:
        for e in stack[k:]:
            opened[e.tag] -= 1
        del stack[k:]

    while at < n:
        found = TOKEN.search(page, at)
        end = found.start() if found else n
        if end > at:
            piece = html.unescape(page[at:end])
            buffer.append(piece)
            if any(e.tag == "a" for e in stack[-3:]):
                linked += len(piece.split())
        if not found:
            break
        at = found.end()
        tag = (found[2] or found[5] or "").lower()
        if not tag:
            continue
        if found[1] or found[4]:
            if tag in ("br", "p") and not opened[tag]:
                buffer.append(" ")
                continue
            for k in range(len(stack) - 1, 0, -1) if opened[tag] else ():
                if stack[k].tag == tag:
                    if tag not in INLINE or any(e.tag not in INLINE for e in stack[k:]):
                        if tag in INLINE:  # an inline end never closes a block around it
                            break
                        flush()
                    shut(k)
                    break
            if tag in ("h1", "h2", "h3", "h4", "h5", "h6"):
                heading = 0
            continue
        attributes = found[3] or found[6] or ""
        if tag in RAW:
            if not attributes.endswith("/"):
                close = re.compile(rf"(?i)</{re.escape(tag)}\s*[^>]*>").search(page, at)
                at = close.end() if close else n
            continue
        if tag == "br":
            buffer.append(" ")
            continue
        if tag in VOID:
            if tag == "hr":
                flush()
            continue
        if tag not in INLINE:
            flush()
            while len(stack) > 1:
                k = len(stack) - 1
                while k > 0 and stack[k].tag in INLINE:
                    k -= 1
                if stack[k].tag in CLOSED_BY and tag in CLOSED_BY[stack[k].tag]:
                    shut(k)
                else:
                    break
            heading = tag in ("h1", "h2", "h3", "h4", "h5", "h6")
        stack.append(_open(tag, attributes, stack[-1]))
        opened[tag] += 1
    flush()
    return out


def features(block: Block) -> list[float]:
    """What the classifier sees of a block, in the order of PRIOR."""
    words = block.text.count(" ") + 1
    e = block.parent
    told = [1.0, e.main, e.tag in ("p", "blockquote", "pre"), block.heading, min(6.0, math.log2(1 + words)), block.text[-1] in ".!?…。:;\"”»", min(1.0, block.linked / words), min(e.n_against, 3), min(e.n_header, 2), min(e.n_hidden, 2)]
    return [float(x) for x in told]


def score(block: Block, weights: list[float]) -> float:
    """Log-odds that a block is content."""
    return sum(w * x for w, x in zip(weights, features(block)))


def examples(blocks: list[Block]) -> list[tuple[list[float], float]]:
    """(features, label) of the blocks that the page's own elements tell to be article or not."""
    out = []
    around = [n for n, k in enumerate(PRIOR) if k in AROUND]
    for b in blocks:
        if b.parent.apart or b.parent.marked:
            x = features(b)
            y = float(not (b.parent.apart or b.parent.n_against or b.parent.n_hidden))
            out += [(x, y), ([0.0 if n in around else v for n, v in enumerate(x)], y)]
    return out


def regression(x: np.ndarray, y: np.ndarray) -> list[float]:
    """Weights of least loss: the mean log-loss of the examples, and half of FIRMNESS times the squared distance to the prior."""
    prior = np.array(list(PRIOR.values()))
    w = prior.copy()
    for _ in range(STEPS if len(x) else 0):  # Newton steps, halved until the loss falls
        p = 1 / (1 + np.exp(-np.clip(x @ w, -50, 50)))
        slope = x.T @ (p - y) / len(x) + FIRMNESS * (w - prior)
        bend = (x * (p * (1 - p))[:, None]).T @ x / len(x) + FIRMNESS * np.eye(len(w))
        step = np.linalg.solve(bend, slope)
        loss = lambda v: np.logaddexp(0, np.where(y > 0, -(x @ v), x @ v)).mean() + FIRMNESS / 2 * ((v - prior) ** 2).sum()
        size = 1.0
        while size > 1e-6 and loss(w - size * step) > loss(w):
            size /= 2
        w = w - size * step
        if np.abs(size * step).max() < 1e-9:
            break
    return w.tolist()


def tree_distance(a: Element, b: Element) -> int:
    """Steps between two elements, FAR at most."""
    d = 0
    while a is not b and d < FAR:
        if a.depth >= b.depth:
            a = a.parent
        else:
            b = b.parent
        d += 1
    return d


def minimum_cut(terminal: list[float], edges: list[tuple[int, int, float]]) -> list[bool]:
    """Which nodes stay on the source's side. terminal: capacity from the source (above 0) or to the sink (below 0) of each node."""
    n, left = len(terminal), list(terminal)
    if all(x > 0 for x in left) or all(x <= 0 for x in left):
        return [x > 0 for x in left]
    around: list[list[int]] = [[] for _ in range(n)]
    to, cap = [], []
    for a, b, c in edges:  # both directions; an arc's twin is its number xor 1
        around[a].append(len(to))
        around[b].append(len(to) + 1)
        to += [b, a]
        cap += [c, c]
    tiny = 1e-12
    while True:
        level = [-1] * n
        queue = [i for i in range(n) if left[i] > tiny]
        for i in queue:
            level[i] = 0
        reached = False
        for i in queue:
            for arc in around[i]:
                j = to[arc]
                if cap[arc] > tiny and level[j] < 0:
                    level[j] = level[i] + 1
                    queue.append(j)
                    reached |= left[j] < -tiny
        if not reached:
            return [x >= 0 for x in level]
        place = [0] * n
        for s in range(n):
            if level[s]:
                continue
            path: list[int] = []
            i = s
            while left[s] > tiny:
                if left[i] < -tiny:
                    flow = min(left[s], -left[i], *(cap[a] for a in path)) if path else 0
                    for a in path:
                        cap[a] -= flow
                        cap[a ^ 1] += flow
                    left[s] -= flow
                    left[i] += flow
                    path, i = [], s
                    continue
                while place[i] < len(around[i]):
                    arc = around[i][place[i]]
                    if cap[arc] > tiny and level[to[arc]] == level[i] + 1:
                        break
                    place[i] += 1
                if place[i] < len(around[i]):
                    path.append(around[i][place[i]])
                    i = to[path[-1]]
                elif path:
                    i = to[path.pop() ^ 1]
                    place[i] += 1
                else:
                    break


def label(blocks: list[Block], weights: list[float] | None = None) -> list[Block]:
    """Blocks with their labels."""
    weights = weights or list(PRIOR.values())
    edges, last = [], {}
    for n, b in enumerate(blocks):
        b.log_odds = score(b, weights)
        if n and (d := tree_distance(blocks[n - 1].parent, b.parent)) < FAR:
            edges.append((n - 1, n, ADJACENT / (1 + d) ** 2))
        under = b.parent.parent or b.parent
        if id(under) in last and last[id(under)] != n - 1:
            edges.append((last[id(under)], n, SIBLING / 4))
        last[id(under)] = n
    for b, side in zip(blocks, minimum_cut([b.log_odds for b in blocks], edges)):
        b.content = side
    return blocks


def main_text(page: str | None, weights: list[float] | None = None) -> str:
    return " ".join(b.text for b in label(blocks_of(page or ""), weights) if b.content)


def _learner(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for page in batch.column(0):
            blocks = blocks_of(page.as_py() or "")
            told = examples(blocks[:: max(1, -(-len(blocks) // PER_PAGE))])
            yield pa.RecordBatch.from_arrays([pa.array([x for x, _ in told], pa.list_(pa.float64())), pa.array([y for _, y in told], pa.float64())], names=["x", "y"])


def fitted(pages: DataFrame, id_col: str = "page_id", html_col: str = "html", sample: int = SAMPLE) -> list[float]:
    """The classifier's weights, fitted on at most ``sample`` pages: those of least hash of id. Without examples: the prior."""
    rows = pages.where(F.col(html_col).isNotNull()).select(F.pmod(F.xxhash64(F.col(id_col).cast("string")), F.lit(1_000_000)).alias("h"), F.col(html_col).cast("string").alias("html"))
    n = rows.count()
    if not n:
        return list(PRIOR.values())
    few = rows.where(F.col("h") < min(1_000_000, int(1_500_000 * sample / n) + 1)).orderBy("h", "html").limit(sample).select("html")
    got = few.mapInArrow(_learner, "x array<double>, y double").orderBy("y", "x").toPandas()  # in an order of their own, so that sums come out the same
    return regression(np.array(got["x"].tolist(), np.float64).reshape(-1, len(PRIOR)), got["y"].to_numpy(np.float64))


def _extractor(names: list[str], weights: list[float] | None):  # noqa: ANN202
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, len(batch), 256):
                part = batch.slice(at, 256)
                texts = [main_text(x.as_py(), weights) for x in part.column(part.num_columns - 1)]
                yield pa.RecordBatch.from_arrays([*part.columns[:-1], pa.array(texts, pa.string())], names=[*names, "text"])

    return run


def extract(pages: DataFrame, keep: tuple[str, ...] = ("page_id", "url"), html_col: str = "html", weights: list[float] | None = None) -> DataFrame:
    """The ``keep`` columns and text, the main text of each whole page, its blocks joined by one space, by a classifier of these weights (or the prior's).

    Null and empty pages and pages without content have an empty text; repeated rows and null ids stay; broken
    markup is read as far as it goes; an empty frame gives an empty one. Other columns are ignored.
    """
    schema = ", ".join(f"`{k}` {pages.schema[k].dataType.simpleString()}" for k in keep) + ", text string"
    return pages.select(*keep, F.col(html_col).cast("string").alias("__html")).mapInArrow(_extractor(list(keep), weights), schema)


def op9_html_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = table(spark, sf_dir, "pages", "page_id", "url", "html")
    found = extract(pages, weights=fitted(pages))
    return found.select("page_id", "url", "text", F.length("text").cast("long").alias("n_chars"))
