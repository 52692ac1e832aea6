"""Lower bounds by edge contraction, and greedy upper bounds.

The contraction bound takes a vertex of least degree again and again and contracts it
into its neighbour of least degree; the largest of the least (or second least) degrees met
is a lower bound of the width. Ties go to the lowest vertex.
"""

from __future__ import annotations

from collections.abc import Callable

import numpy as np

from ..graph import Graph, bits, mask_of
from . import kernels

U64 = np.uint64


def mmw(graph: Graph, rule: str = "min") -> int:
    """Bound of one graph; rule 'min' or 'second' (second least degree)."""
    masks = {v: m for v, m in enumerate(graph.masks)}
    best = 0
    while len(masks) > 1:
        order = sorted((m.bit_count(), v) for v, m in masks.items())
        best = max(best, order[1 if rule == "second" else 0][0])
        v = order[0][1]
        near = bits(masks[v])
        if near:
            u = min(near, key=lambda w: (masks[w].bit_count(), w))
            masks[u] = (masks[u] | masks[v]) & ~(1 << u | 1 << v)
        for w in near:
            masks[w] &= ~(1 << v)
            if w != u:
                masks[w] |= 1 << u
        del masks[v]
    return best


def exceeds_explicit(sets: np.ndarray, degree: np.ndarray, table: np.ndarray, k: int, rule: str) -> np.ndarray:
    """Which states' remaining graphs have a bound above k: contraction on a copy of the remaining graph."""
    words, n = table.shape
    graph = kernels.remaining(sets, table)
    batch = sets.shape[1]
    live = np.array([kernels._has(sets, v) == 0 for v in range(n)])
    over = np.zeros(batch, bool)
    rows = np.arange(batch)
    big = 1 << 20
    for _ in range(n - 1):
        rows = rows[~over[rows] & (live[:, rows].sum(0) > 1)]
        if not len(rows):
            break
        part = graph[:, :, rows]
        deg = np.where(live[:, rows], np.bitwise_count(part).sum(1, dtype=np.int64), big)
        v = deg.argmin(0)
        at = np.arange(len(rows))
        low = deg[v, at]
        if rule == "second":
            rest = deg.copy()
            rest[v, at] = big
            over[rows] = rest.min(0) > k
        else:
            over[rows] = low > k
        mine = part[v, :, at]
        member = np.array([mine[:, w >> 6] >> U64(w & 63) & U64(1) for w in range(n)]).astype(bool)
        u = np.where(member, deg, big).argmin(0)
        some = member.any(0)
        union = mine | part[u, :, at]
        for x in (u, v):
            union[at, x >> 6] &= ~(U64(1) << (x & 63).astype(U64))
        joined = np.array([union[:, w >> 6] >> U64(w & 63) & U64(1) for w in range(n)]).astype(bool) & some
        for w in range(n):
            row = graph[w][:, rows]
            row[v >> 6, at] &= ~(U64(1) << (v & 63).astype(U64))
            bit = np.where(joined[w], U64(1) << (u & 63).astype(U64), U64(0))
            row[u >> 6, at] |= bit
            graph[w][:, rows] = row
        hit = np.flatnonzero(some)
        graph[u[hit], :, rows[hit]] = union[hit]
        live[v, rows] = False
    return over


def exceeds_implicit(sets: np.ndarray, degree: np.ndarray, table: np.ndarray, k: int, rule: str) -> np.ndarray:
    """The same without a copy of the graph: a byte of degree and a byte of representative per vertex.

    Neighbours of a merged vertex are found by a search through the removed set and
    through the vertices merged with it.
    """
    words, n = table.shape
    near = [[u for u in range(n) if int(table[u >> 6, v]) >> (u & 63) & 1] for v in range(n)]
    over = np.zeros(sets.shape[1], bool)
    for column in range(sets.shape[1]):
        removed = 0
        for w in range(words):
            removed |= int(sets[w, column]) << 64 * w
        deg = degree[:, column].astype(np.uint8)
        leader = np.arange(n, dtype=np.uint8)
        members: dict[int, list[int]] = {v: [v] for v in range(n) if not removed >> v & 1}

        def around(v: int) -> set[int]:
            seen, found, stack = 0, set(), list(members[v])
            while stack:
                for w in near[stack.pop()]:
                    if not seen >> w & 1:
                        seen |= 1 << w
                        if removed >> w & 1:
                            stack.append(w)
                        elif leader[w] != v:
                            found.add(int(leader[w]))
            return found

        while len(members) > 1:
            order = sorted((int(deg[v]), v) for v in members)
            if order[1 if rule == "second" else 0][0] > k:
                over[column] = True
                break
            v = order[0][1]
            mine = around(v)
            if mine:
                u = min(mine, key=lambda w: (int(deg[w]), w))
                common = mine & around(u)
                deg[u] = int(deg[u]) + int(deg[v]) - 2 - len(common)
                for w in common:
                    deg[w] -= 1
                leader[members[v]] = u
                members[u] += members.pop(v)
            else:
                del members[v]
    return over


def state_bound(k: int, rule: str, impl: str) -> Callable | None:
    """The bound of expand(): which states of a batch stay."""
    if rule == "off":
        return None
    exceeds = {"explicit": exceeds_explicit, "implicit": exceeds_implicit}[impl]
    return lambda sets, degree, table: ~exceeds(sets, degree, table, k, rule)


def greedy_order(graph: Graph, rule: str = "fill") -> tuple[int, list[int]]:
    """(width, order) of removing the vertex of least degree ('degree') or least new edges ('fill')."""
    masks = list(graph.masks)
    left = set(range(graph.n))
    order, width = [], 0

    def cost(v: int) -> tuple:
        near = bits(masks[v])
        if rule == "degree":
            return (len(near), v)
        return (sum((masks[v] & ~masks[u] & ~(1 << u)).bit_count() for u in near), len(near), v)

    while left:
        v = min(left, key=cost)
        near = bits(masks[v])
        width = max(width, len(near))
        for u in near:
            masks[u] = (masks[u] | masks[v]) & ~(1 << u | 1 << v)
        left.remove(v)
        order.append(v)
    return width, order


def degeneracy(graph: Graph) -> int:
    """Largest least degree of any subgraph: a weaker bound, for comparison."""
    masks, left, best = list(graph.masks), set(range(graph.n)), 0
    keep = mask_of(left)
    while left:
        v = min(left, key=lambda w: ((masks[w] & keep).bit_count(), w))
        best = max(best, (masks[v] & keep).bit_count())
        left.remove(v)
        keep &= ~(1 << v)
    return best
