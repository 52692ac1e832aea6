"""Main-content extraction by a tree-structured graphical model of the DOM.

Each node of a page's tree is content or not. A node's features give its own potential,
and each parent-child edge a 2 x 2 potential; sum-product messages from the leaves to the
root and back give every node's exact marginal. Weights and edge potentials are learned
by maximum likelihood: the gradient is the observed minus the expected features, and the
expectations are the same marginals. A page's text is that of the text nodes whose
content marginal is at least one half.

The pages that learning reads are at most ``TRAIN_PAGES`` labelled ones: pages that mark
their content by an ``article`` or ``main`` element. The model never sees those two tags:
they count as plain containers, so it carries over to pages without them.

Edge cases: null or empty html gives empty text and no nodes; unclosed and stray tags are
repaired like a browser does for the common cases, in time that grows with the page's
length; pages are worked on in groups of bounded bytes, so memory grows with the largest
single page; elements nested deeper than ``MAX_DEPTH`` become siblings; repeated rows are
pages like others; an empty table gives no rows; null page_ids keep their row; without
labelled pages all text outside scripts and styles is content.
"""

from __future__ import annotations

import html as entities
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import SLICE_BYTES, text_arrays

TRAIN_PAGES, STEPS, RATE, RIDGE = 200, 100, 0.5, 1e-3
TAG = re.compile(r"<(/?)([a-zA-Z][a-zA-Z0-9]*)")
STOP = re.compile(r"[>\"']")
RAW = {name: re.compile(rf"</{name}\s*>", re.I) for name in ("script", "style", "noscript", "template")}
#: Elements below this depth become children of the last one above it, as in browsers.
MAX_DEPTH = 512
VOID = frozenset("area base br col embed hr img input link meta source track wbr".split())
BLOCK = frozenset("p div ul ol li table tr td th h1 h2 h3 h4 h5 h6 article main section nav header footer aside form blockquote pre body html".split())
GROUPS = {
    **dict.fromkeys(("p",), 0), **dict.fromkeys(("h1", "h2", "h3", "h4", "h5", "h6"), 1), **dict.fromkeys(("a",), 2), **dict.fromkeys(("ul", "ol", "dl"), 3), **dict.fromkeys(("li", "dt", "dd"), 4),
    **dict.fromkeys(("nav",), 5), **dict.fromkeys(("footer",), 6), **dict.fromkeys(("header", "title", "head"), 7), **dict.fromkeys(("aside", "form", "button", "select"), 8), **dict.fromkeys(("b", "i", "em", "strong", "span", "u", "small", "code"), 9),
    **dict.fromkeys(("table", "tr", "td", "th", "tbody", "thead"), 10), **dict.fromkeys(("body", "html"), 11), **dict.fromkeys(("blockquote", "pre"), 12),
}
CONTAINER, TEXT = 13, 14
NOISE = re.compile(r"\b(ad|ads|advert|banner|nav|menu|footer|sidebar|promo|cookie|share|social|comment|related)\b", re.I)
WIDTH = 26


def tokens(page: str) -> Iterator[tuple[str, str, str]]:
    """(kind, name or text, attributes) of a page; kinds are text, open and close. Reads every sign a bounded number of times.

    Comments, scripts, styles and declarations are left out, unclosed ones to the end of the
    page. Attribute values in quotes may hold ``>``; from the first tag on whose quotes
    are never closed, quotes are not looked at. Without a further ``>`` the rest is text.
    """
    at, begin, n, last, quotes = 0, 0, len(page), page.rfind(">"), True
    ends = {q: page.rfind(q) for q in "\"'"}
    while 0 <= (at := page.find("<", at)) <= last:
        if page.startswith("<!--", at):
            stop = page.find("-->", at + 4)
            end, token = n if stop < 0 else stop + 3, None
        elif page.startswith(("<!", "<?"), at):
            end, token = page.find(">", at) + 1, None
        elif (tag := TAG.match(page, at)) is None:
            at += 1
            continue
        else:
            spot = tag.end()
            end = page.find(">", spot) + 1
            while quotes and (stop := STOP.search(page, spot)):
                if stop[0] == ">":
                    end = stop.end()
                    break
                if ends[stop[0]] <= stop.start():
                    break
                spot = page.find(stop[0], stop.end()) + 1
            else:
                quotes = False
            if not end:
                break
            token = ("close" if tag[1] else "open", tag[2].lower(), page[tag.end() : end - 1])
        if at > begin:
            yield "text", page[begin:at], ""
        if token is not None and token[0] == "open" and token[1] in RAW:
            closing = RAW[token[1]].search(page, end)
            end, token = closing.end() if closing else n, None
        if token is not None:
            yield token
        at = begin = end
    if begin < n:
        yield "text", page[begin:], ""


def parse(page: str) -> tuple[list[int], list[str], list[str], list[str]]:
    """(parents, tags, attributes, texts) of the DOM's nodes in document order; text nodes have tag ``#``."""
    parents, tags, attributes, texts = [-1], ["#root"], [""], [""]
    stack = [0]
    #: Places in the stack of the open elements of each name, and of all block elements.
    opened: dict[str, list[int]] = {}
    blocks: list[int] = []

    def close(depth: int) -> None:
        for k in range(len(stack) - 1, depth - 1, -1):
            name = tags[stack[k]]
            opened[name].pop()
            if name in BLOCK:
                blocks.pop()
        del stack[depth:]

    for kind, name, attribute in tokens(page):
        if kind == "text":
            if name.strip():
                parents.append(stack[-1])
                tags.append("#")
                attributes.append("")
                texts.append(" ".join(entities.unescape(name).split()))
            continue
        if kind == "close":
            if opened.get(name) and (name in BLOCK or not blocks or blocks[-1] < opened[name][-1]):
                close(opened[name][-1])
            continue
        if name in BLOCK and blocks:
            open_tag = tags[stack[blocks[-1]]]
            if open_tag == "p" or (open_tag == name and name in ("li", "tr", "td", "th")):
                close(blocks[-1])
        parents.append(stack[-1])
        tags.append(name)
        attributes.append(attribute)
        texts.append("")
        if name not in VOID and not attribute.endswith("/") and len(stack) < MAX_DEPTH:
            opened.setdefault(name, []).append(len(stack))
            if name in BLOCK:
                blocks.append(len(stack))
            stack.append(len(parents) - 1)
    return parents, tags, attributes, texts


class Forest:
    """Trees of many pages in one set of arrays, with features."""

    def __init__(self, pages: list[str]):
        parents, tags, attributes, texts, self.first = [], [], [], [], [0]
        for page in pages:
            p, t, a, x = parse(page)
            shift = len(parents)
            parents += [k + shift if k >= 0 else -1 for k in p]
            tags += t
            attributes += a
            texts += x
            self.first.append(len(parents))
        self.parent, self.tags, self.texts = np.array(parents, np.int64), tags, texts
        n = len(parents)
        self.depth = np.zeros(n, np.int64)
        group = np.array([TEXT if t == "#" else GROUPS.get(t, CONTAINER) for t in tags], np.int64) if n else np.zeros(0, np.int64)
        depth = self.depth
        for k in range(n):
            if parents[k] >= 0:
                depth[k] = depth[parents[k]] + 1
        self.levels = np.split(np.argsort(depth, kind="stable"), np.cumsum(np.bincount(depth))[:-1]) if n else []
        length = np.array([len(x) for x in texts], float)
        stops = np.array([x.count(".") + x.count(",") + x.count("!") + x.count("?") for x in texts], float)
        linked = np.where(group == 2, 1.0, 0.0)
        noise = np.array([bool(a) and NOISE.search(a) is not None for a in attributes], float)
        hidden = np.array([t == "title" or t == "head" for t in tags], float)
        for level in self.levels[1:]:
            up = self.parent[level]
            linked[level] = np.maximum(linked[level], linked[up])
            noise[level] = np.maximum(noise[level], noise[up])
            hidden[level] = np.maximum(hidden[level], hidden[up])
        below, anchor, points, kids = length.copy(), length * linked, stops.copy(), np.zeros(n)
        for level in reversed(self.levels[1:]):
            for array in (below, anchor, points):
                np.add.at(array, self.parent[level], array[level])
            np.add.at(kids, self.parent[level], 1.0)
        self.hidden = hidden > 0
        x = np.zeros((n, WIDTH))
        x[np.arange(n), group] = 1.0
        up = np.maximum(self.parent, 0)
        x[:, 15] = np.log1p(below) / 8
        x[:, 16] = np.where(below > 0, anchor / np.maximum(below, 1), 0.0)
        x[:, 17] = np.minimum(points / np.maximum(below, 1) * 20, 2.0)
        x[:, 18] = noise
        x[:, 19] = linked
        x[:, 20] = np.minimum(depth, 12) / 12
        x[:, 21] = np.log1p(kids) / 4
        x[:, 22] = group[up] == 0 if n else 0
        x[:, 23] = np.isin(group[up], (3, 4, 5, 6, 7, 8)) if n else 0
        x[:, 24] = np.log1p(below[up]) / 8 if n else 0
        x[:, 25] = 1.0
        self.x = x

    def labels(self) -> np.ndarray:
        """1 for nodes inside an article or main element, else 0."""
        inside = np.array([t in ("article", "main") for t in self.tags], float)
        for level in self.levels[1:]:
            inside[level] = np.maximum(inside[level], inside[self.parent[level]])
        return inside.astype(np.int64)


def marginals(forest: Forest, unary: np.ndarray, edge: np.ndarray) -> tuple[np.ndarray, np.ndarray, float]:
    """(node marginals of state 1, summed edge marginals 2 x 2, log partition sum) by sum-product.

    ``unary`` holds the log potential of state 1 (state 0 has 0), ``edge`` log potentials
    by parent and child state. Messages go up level by level, then down.
    """
    n = len(unary)
    local = np.stack([np.zeros(n), unary], 1)
    up = np.zeros((n, 2))
    inside = local.copy()
    for level in reversed(forest.levels[1:]):
        up[level] = np.logaddexp(edge[None, :, 0] + inside[level, None, 0], edge[None, :, 1] + inside[level, None, 1])
        np.add.at(inside, forest.parent[level], up[level])
    belief = inside.copy()
    joint = np.zeros((2, 2))
    total = 0.0
    for depth, level in enumerate(forest.levels):
        if depth:
            parent = forest.parent[level]
            outside = belief[parent] - up[level]
            outside -= np.logaddexp(outside[:, 0], outside[:, 1])[:, None]
            pair = outside[:, :, None] + edge[None] + inside[level][:, None, :]
            pair -= np.logaddexp(np.logaddexp(pair[:, 0, 0], pair[:, 0, 1]), np.logaddexp(pair[:, 1, 0], pair[:, 1, 1]))[:, None, None]
            chance = np.exp(pair)
            joint += chance.sum(0)
            belief[level] = np.logaddexp(pair[:, 0, :], pair[:, 1, :])
        else:
            total = float(np.logaddexp(belief[level, 0], belief[level, 1]).sum())
        belief[level] -= np.logaddexp(belief[level, 0], belief[level, 1])[:, None]
    return np.exp(belief[:, 1]), joint, total


def fit_forest(forest: Forest, steps: int = STEPS) -> tuple[np.ndarray, np.ndarray]:
    """(weights, edge potentials) that maximise the likelihood of the forest's labels (adaptive steps)."""
    y = forest.labels()
    child = np.flatnonzero(forest.parent >= 0)
    seen = np.zeros((2, 2))
    np.add.at(seen, (y[forest.parent[child]], y[child]), 1.0)
    observed = np.concatenate([forest.x.T @ y, seen.ravel()])
    theta, first, second = np.zeros(WIDTH + 4), np.zeros(WIDTH + 4), np.zeros(WIDTH + 4)
    for step in range(1, steps + 1):
        p, joint, _ = marginals(forest, forest.x @ theta[:WIDTH], theta[WIDTH:].reshape(2, 2))
        gradient = (observed - np.concatenate([forest.x.T @ p, joint.ravel()])) / max(1, len(y)) - RIDGE * theta
        first = 0.9 * first + 0.1 * gradient
        second = 0.99 * second + 0.01 * gradient**2
        theta += RATE * (first / (1 - 0.9**step)) / (np.sqrt(second / (1 - 0.99**step)) + 1e-8) / np.sqrt(step)
    return theta[:WIDTH], theta[WIDTH:].reshape(2, 2)


Model = tuple[np.ndarray, np.ndarray]


def fit(pages: DataFrame, limit: int = TRAIN_PAGES) -> Model | None:
    """Model from at most ``limit`` labelled pages, those with the least scrambled page_id (null ids are left out).

    Ids are chosen first, so that no other page than the chosen ones is carried anywhere.
    """
    named = pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("html").cast("string").alias("html")).where("page_id is not null")
    marked = F.col("html").rlike("(?i)<(article|main)[ >]")
    order = F.xxhash64("page_id"), F.col("page_id")
    ids = {r.page_id for r in named.where(marked).select("page_id").orderBy(*order).limit(limit).collect()}
    # The pattern is looked for in the chosen pages alone, not in all pages again.
    rows = named.where(F.col("page_id").isin(*ids)).where(marked).orderBy(*order, F.xxhash64("html"), "html").limit(limit).collect() if ids else []
    return fit_forest(Forest([r.html for r in rows])) if rows else None


def extract_texts(pages: list[str], model: Model | None) -> list[tuple[str, int, int]]:
    """(content, text nodes, content nodes) of each page."""
    forest = Forest(pages)
    if model is None:
        p = np.ones(len(forest.tags))
    else:
        p, _, _ = marginals(forest, forest.x @ model[0], model[1])
    good = (p >= 0.5) & ~forest.hidden
    out = []
    for a, b in zip(forest.first, forest.first[1:]):
        nodes = [k for k in range(a, b) if forest.tags[k] == "#"]
        kept = [k for k in nodes if good[k]]
        parts: list[str] = []
        block = None
        for k in kept:
            owner = int(forest.parent[k])
            while owner > a and forest.tags[owner] not in BLOCK:
                owner = int(forest.parent[owner])
            if parts and owner == block:
                parts[-1] += " " + forest.texts[k]
            else:
                parts.append(forest.texts[k])
            block = owner
        out.append(("\n".join(parts), len(nodes), len(kept)))
    return out


def extractor(model: Model | None, limit: int = SLICE_BYTES):
    """Function of Arrow batches of (page_id, html); works on at most ``limit`` bytes of pages at once, or on one page."""

    def run(batches):
        for batch in batches:
            for a, b, texts in text_arrays(batch, "html", limit):
                found = extract_texts(texts.to_pylist(), model)
                yield pa.RecordBatch.from_arrays([batch.column("page_id").slice(a, b - a), pa.array([f[0] for f in found], pa.string()), pa.array([f[1] for f in found], pa.int64()), pa.array([f[2] for f in found], pa.int64())], ["page_id", "content", "text_nodes", "content_nodes"])

    return run


def extract(pages: DataFrame, model: Model | None) -> DataFrame:
    """(page_id, content, text_nodes, content_nodes) of every row."""
    return pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("html").cast("string").alias("html")).mapInArrow(extractor(model), "page_id long, content string, text_nodes long, content_nodes long")
