"""Elimination orders and tree decompositions."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..graph import Graph, bits, mask_of
from ..plans.options import Options
from . import kernels
from .search import Run, Walk


def reached(graph: Graph, removed: int, v: int) -> int:
    """Vertices outside ``removed`` that v reaches directly or through it."""
    seen, found, stack = 1 << v, 0, [v]
    while stack:
        new = graph.masks[stack.pop()] & ~seen
        seen |= new
        found |= new & ~removed
        stack.extend(bits(new & removed))
    return found


def order_degrees(graph: Graph, order: list[int]) -> list[int]:
    """Degree of each vertex at the moment of its removal."""
    removed, out = 0, []
    for v in order:
        out.append(reached(graph, removed, v).bit_count())
        removed |= 1 << v
    return out


def order_width(graph: Graph, order: list[int]) -> int:
    return max(order_degrees(graph, order), default=0)


def _row(front, names: list[str], mask: int | None) -> tuple[int, int] | None:
    """(set, last four) of one state of a frontier: that of ``mask``, or the least one."""
    if isinstance(front, tuple):
        sets, last, _ = front
        if not sets.shape[1]:
            return None
        if mask is None:
            at = 0
        else:
            want = kernels.split_mask(mask, len(names))
            hit = np.flatnonzero((sets == want[:, None]).all(0))
            if not len(hit):
                return None
            at = int(hit[0])
        return sum(int(sets[w, at]) << 64 * w for w in range(len(names))), int(last[at])
    frame: DataFrame = front
    if mask is not None:
        for s, word in zip(names, kernels.split_mask(mask, len(names)).view(np.int64)):
            frame = frame.where(F.col(s) == int(word))
    row = frame.orderBy(*names).limit(1).collect()
    if not row:
        return None
    return sum((int(row[0][s]) & (1 << 64) - 1) << 64 * w for w, s in enumerate(names)), int(row[0]["last"])


def elimination_order(graph: Graph, options: Options | None = None, method: str = "levels", spark: SparkSession | None = None) -> tuple[Run, list[int]]:
    """(run, an order of least width).

    'levels'   keep every fourth level, counted from the last; a state's packed last four
               vertices lead back to the one before
    'parents'  keep every level and go back by one vertex at a time
    'rerun'    keep the last level alone: bar the vertices known to come last and walk again
               for four more, in a session's own walks where there is one
    Levels of over KEEP_LOCAL states are kept in the shared store, where there is a session.
    """
    options = options or Options()
    walk = Walk(graph, options, spark)
    keep: dict = {}
    run = walk.width(keep, {"levels": 4, "parents": 1, "rerun": 0}[method])
    if run.width is None:
        return run, []
    if not keep:
        return run, list(range(graph.n))
    top = max(keep)
    mask, last = _row(keep[top], walk.names, None)
    tail = [v for v in range(graph.n) if not mask >> v & 1]
    order: list[int] = []
    level = top
    step = 1 if method == "parents" else 4
    while level > 0:
        take = min(step, level)
        four = [(last & 0xFFFFFFFF) >> 8 * j & 0xFF for j in range(take)]
        order = four[::-1] + order
        mask &= ~mask_of(four)
        level -= take
        if not level:
            break
        if method == "rerun":
            barred = (1 << graph.n) - 1 & ~mask
            found = _barred_walk(graph, run.width, barred, level, options, spark)
        else:
            found = _row(keep[level], walk.names, mask)
        if found is None:
            raise RuntimeError("a level lost the state that led on")
        mask, last = found
    if walk.store is not None:
        walk.store.drop()
    return run, order + tail


def _barred_walk(graph: Graph, k: int, barred: int, levels: int, options: Options, spark: SparkSession | None) -> tuple[int, int] | None:
    """The state of ``levels`` vertices that a walk within the others than ``barred`` ends in."""
    again = Walk(graph, options.but(clique="none", early_stop=False, augment=False, clique_on="input", mmw="off", capacity=None), spark)
    again.clique = barred
    keep: dict = {}
    again.decide(k, keep, 0, levels)
    found = _row(keep[levels], again.names, None) if levels in keep else None
    if again.store is not None:
        again.store.drop()
    return found


def tree_decomposition(graph: Graph, order: list[int]) -> list[tuple[int, int, list[int]]]:
    """(bag, parent bag, vertices): the bag of a vertex is itself and what it reaches; -1 is no parent."""
    place = {v: k for k, v in enumerate(order)}
    removed, out = 0, []
    for k, v in enumerate(order):
        near = reached(graph, removed, v)
        parent = min((place[u] for u in bits(near)), default=-1)
        out.append((k, parent, sorted([v, *bits(near)])))
        removed |= 1 << v
    return out


def check_decomposition(graph: Graph, bags: list[tuple[int, int, list[int]]]) -> bool:
    """Every vertex and edge in a bag, and the bags of a vertex connected."""
    held = {b: mask_of(vs) for b, _, vs in bags}
    if any(not any(m >> v & 1 for m in held.values()) for v in range(graph.n)):
        return False
    if any(not any(m >> u & 1 and m >> v & 1 for m in held.values()) for u, v in graph.edges()):
        return False
    # Bags of a vertex form a tree: exactly one of them has no parent that holds the vertex.
    return all(sum(1 for b, p, vs in bags if v in vs and (p < 0 or not held[p] >> v & 1)) == 1 for v in range(graph.n))


def eliminate(edges: DataFrame, v: int) -> DataFrame:
    """Edges after removing one vertex of every graph and joining its neighbours."""
    mine = edges.where((F.col("u") == v) | (F.col("v") == v)).select("graph_id", F.when(F.col("u") == v, F.col("v")).otherwise(F.col("u")).alias("a"))
    joined = mine.join(mine.withColumnRenamed("a", "b"), "graph_id").where("a < b").select("graph_id", F.col("a").alias("u"), F.col("b").alias("v"))
    return edges.where((F.col("u") != v) & (F.col("v") != v)).unionByName(joined).distinct()
