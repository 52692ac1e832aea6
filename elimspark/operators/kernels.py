"""Degrees of all remaining vertices for a batch of removed sets, and expansion of a batch.

States are arrays of words x batch (uint64). A kernel returns n x batch degrees: for a
vertex outside the set, the number of outside vertices that it reaches directly or through
the set. Five kernels compute the same numbers by different principles:

``search``  per vertex, grow the part of the set that it reaches until nothing is added;
``parts``   components of the set and their neighbourhoods once per state, then one look-up
            per edge;
``remove``  remove the set's vertices one by one from a copy of the adjacency, per state;
            the only one that takes a graph per state;
``prefix``  as remove, but what is left after the highest vertices of a set is computed once for
            all sets of the batch that share them: the default, as the fastest, best on sorted batches;
``expr``    Catalyst expressions, see :mod:`elimspark.functions.bits`.
"""

from __future__ import annotations

import os
from concurrent.futures import ThreadPoolExecutor

import numpy as np

U64 = np.uint64
BLOCK = 8192


def _has(sets: np.ndarray, v: int) -> np.ndarray:
    """Whether each set (words x batch) holds v, as all ones or zero."""
    return U64(0) - (sets[v >> 6] >> U64(v & 63) & U64(1))


def _finish(reach: np.ndarray, sets: np.ndarray) -> np.ndarray:
    """Sizes of reached sets (n x words x batch) outside the removed sets and the vertex itself."""
    n = len(reach)
    out = np.zeros((n, sets.shape[1]), np.uint16)
    for v in range(n):
        outside = reach[v] & ~sets
        outside[v >> 6] &= ~(U64(1) << U64(v & 63))
        out[v] = np.bitwise_count(outside).sum(0, dtype=np.uint16) if len(outside) > 1 else np.bitwise_count(outside[0])
    return out


def degrees_search(sets: np.ndarray, table: np.ndarray) -> np.ndarray:
    words, n = table.shape
    reach = np.empty((n, words, sets.shape[1]), U64)
    for v in range(n):
        met = np.repeat(table[:, v, None], sets.shape[1], 1)
        seen = np.zeros_like(sets)
        while True:
            new = met & sets & ~seen
            if not new.any():
                break
            seen |= new
            for u in range(n):
                if (on := _has(new, u)).any():
                    met |= on[None] & table[:, u, None]
        reach[v] = met
    return _finish(reach, sets)


def degrees_parts(sets: np.ndarray, table: np.ndarray) -> np.ndarray:
    words, n = table.shape
    batch = sets.shape[1]
    near = [[u for u in range(n) if int(table[u >> 6, v]) >> (u & 63) & 1] for v in range(n)]
    part = np.zeros((n, words, batch), U64)
    edge = np.zeros((n, words, batch), U64)
    for u in range(n):
        on = _has(sets, u)
        if not on.any():
            continue
        members = np.zeros((words, batch), U64)
        members[u >> 6] = U64(1) << U64(u & 63)
        around = np.repeat(table[:, u, None], batch, 1)
        for w in near[u]:
            if w < u:
                members |= part[w]
                around |= edge[w]
        members &= on
        around &= on
        part[u], edge[u] = members, around
        for w in range(u):
            inside = _has(members, w)
            part[w] |= inside & members
            edge[w] |= inside & around
    reach = np.empty((n, words, batch), U64)
    for v in range(n):
        met = np.repeat(table[:, v, None], batch, 1)
        for w in near[v]:
            met |= edge[w]
        reach[v] = met
    return _finish(reach, sets)


def remaining(sets: np.ndarray, table: np.ndarray) -> np.ndarray:
    """Adjacency of what remains after removing each set: n x words x batch.

    ``table`` is words x n, or n x words x batch with a graph per state.
    """
    if table.ndim == 2:
        graph = np.repeat(table.T[:, :, None], sets.shape[1], 2)
    else:
        graph = table.copy()
    n = len(graph)
    for u in range(n):
        on = _has(sets, u)
        if not on.any():
            continue
        gone = graph[u] & on
        touch = U64(0) - (graph[:, u >> 6] >> U64(u & 63) & U64(1))
        graph |= touch[:, None, :] & gone[None]
    for v in range(n):
        graph[v] &= ~sets
        graph[v, v >> 6] &= ~(U64(1) << U64(v & 63))
    return graph


def degrees_remove(sets: np.ndarray, table: np.ndarray, skip: int = 0) -> np.ndarray:
    """Removal, with what the batch shares done once; vertices of ``skip`` get no degree.

    Frontiers are sorted, so neighbouring sets share their high vertices: those in all sets
    of the batch leave one common graph first, those in none are never removed. The
    vertices that are left are renumbered, so the masks fit the narrowest integers.
    """
    if table.ndim != 2 or len(sets) > 1:
        return np.bitwise_count(remaining(sets, table)).sum(1, dtype=np.uint16)
    row = sets[0]
    n, batch = table.shape[1], len(row)
    common, some = int(np.bitwise_and.reduce(row)), int(np.bitwise_or.reduce(row))
    masks = [int(m) for m in table[0]]
    for u in range(n):
        if common >> u & 1:
            gone, masks[u] = masks[u] & ~(1 << u), 0
            for v in range(n):
                if masks[v] >> u & 1:
                    masks[v] = (masks[v] | gone) & ~(1 << u | 1 << v)
    left = [v for v in range(n) if not common >> v & 1]
    # Vertices that need a row come first, so that their bits are the low ones.
    left.sort(key=lambda v: (skip >> v & 1, v))
    width = next(w for w in (16, 32, 64) if len(left) <= w)
    kind, signed = getattr(np, f"uint{width}"), getattr(np, f"int{width}")
    rows = [v for v in left if not skip >> v & 1]
    packed = np.zeros(batch, kind)
    for i, u in enumerate(rows):
        if some >> u & 1:
            packed |= (row >> U64(u) & U64(1)).astype(kind) << kind(i)
    graph = np.empty((len(rows), batch), kind)
    graph[:] = np.array([sum(1 << i for i, u in enumerate(left) if masks[v] >> u & 1) for v in rows], kind)[:, None]
    touch = np.empty_like(graph)
    for i, u in enumerate(rows):
        if not some >> u & 1:
            continue
        shift = kind(width - 1 - i)
        gone = graph[i] & ((packed << shift).view(signed) >> signed(width - 1)).view(kind)
        np.left_shift(graph, shift, out=touch)
        np.right_shift(touch.view(signed), signed(width - 1), out=touch.view(signed))
        np.bitwise_and(touch, gone, out=touch)
        np.bitwise_or(graph, touch, out=graph)
    graph &= ~packed
    out = np.zeros((n, batch), np.uint8)
    for i, v in enumerate(rows):
        out[v] = np.bitwise_count(graph[i] & kind((1 << width) - 1 & ~(1 << i)))
    return out


#: The last graphs that were renumbered; a plain dictionary, as cached functions don't travel by value.
_NUMBERED: dict[tuple[bytes, int], tuple[list[int], np.ndarray]] = {}


def _numbered(blob: bytes, n: int, skip: int) -> tuple[list[int], np.ndarray]:
    """(vertices that need a row, masks of these rows) with the vertices renumbered: those with a row have the low bits."""
    if (blob, skip) in _NUMBERED:
        return _NUMBERED[blob, skip]
    if len(_NUMBERED) >= 8:
        _NUMBERED.clear()
    masks = np.frombuffer(blob, U64).tolist()
    left = sorted(range(n), key=lambda v: (skip >> v & 1, v))
    rows = [v for v in left if not skip >> v & 1]
    width = next(w for w in (16, 32, 64) if n <= w)
    _NUMBERED[blob, skip] = rows, np.array([[sum(1 << i for i, u in enumerate(left) if masks[v] >> u & 1)] for v in rows], getattr(np, f"uint{width}"))
    return _NUMBERED[blob, skip]


def degrees_prefix(sets: np.ndarray, table: np.ndarray, skip: int = 0) -> np.ndarray:
    """Removal along a tree of shared prefixes; vertices of ``skip`` get no degree.

    The prefix of length d of a set is its d highest vertices. In a sorted batch sets that
    share a prefix stand side by side, so the graphs of all prefixes of length d + 1 come
    from those of length d by one gather and one removal each, and most of the work is the
    last removal. Sets of more than one word go to ``remove``.
    """
    if table.ndim != 2 or len(sets) > 1:
        return degrees_remove(sets, table, skip)
    row = sets[0]
    n, batch = table.shape[1], len(row)
    out = np.zeros((n, batch), np.uint8)
    if not batch:
        return out
    rows, graph = _numbered(table.tobytes(), n, skip)
    kind = graph.dtype.type
    width = 8 * graph.dtype.itemsize
    signed = getattr(np, f"int{width}")
    if rows == list(range(len(rows))):
        packed = row.astype(kind)
    else:
        packed = np.zeros(batch, kind)
        for i, u in enumerate(rows):
            packed |= (row >> U64(u) & U64(1)).astype(kind) << kind(i)
    chain = [packed]
    while chain[-1].any():
        chain.append(chain[-1] & (chain[-1] - kind(1)))
    parent_of = np.zeros(batch, np.intp)
    for prefix in reversed(chain[:-1]):
        first = np.empty(batch, bool)
        first[0] = True
        np.not_equal(prefix[1:], prefix[:-1], out=first[1:])
        begins = np.flatnonzero(first)
        here, parents = prefix[begins], parent_of[begins]
        graph = np.take(graph, parents, axis=1, mode="clip")
        low = here & (~here + kind(1))
        vertex = np.bitwise_count(low - kind(1)).astype(np.intp)
        vertex[low == 0] = 0
        gone = graph[vertex, np.arange(len(begins))] & (kind(0) - (low != 0).astype(kind))
        touch = np.left_shift(graph, (width - 1 - vertex).astype(kind)[None])
        np.right_shift(touch.view(signed), signed(width - 1), out=touch.view(signed))
        np.bitwise_and(touch, gone, out=touch)
        np.bitwise_or(graph, touch, out=graph)
        parent_of = np.cumsum(first) - 1
    if len(chain) == 1:
        graph = np.repeat(graph, batch, 1)
    elif graph.shape[1] != batch:
        graph = graph[:, parent_of]
    graph &= ~packed
    graph &= np.array([(1 << width) - 1 & ~(1 << i) for i in range(len(rows))], kind)[:, None]
    out[rows] = np.bitwise_count(graph)
    return out


KERNELS = {"search": degrees_search, "parts": degrees_parts, "remove": degrees_remove, "prefix": degrees_prefix}


def split_mask(mask: int, words: int) -> np.ndarray:
    low = (1 << 64) - 1
    return np.array([mask >> 64 * w & low for w in range(words)], U64)


def fold(sets: np.ndarray, last: np.ndarray, ways: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """One row per distinct set, sorted: the least ``last``, summed ``ways``.

    The sort is stable and merges runs, which is what expansion makes: one rising run per vertex.
    """
    if not sets.shape[1]:
        return sets, last, ways
    order = np.argsort(sets[0], kind="stable") if len(sets) == 1 else np.lexsort(sets)
    sets = sets[:, order]
    new = np.concatenate([[True], (sets[:, 1:] != sets[:, :-1]).any(0)])
    begins = np.flatnonzero(new)
    return sets[:, begins], np.minimum.reduceat(last[order], begins), np.add.reduceat(ways[order], begins)


def fold_runs(found: list[tuple[np.ndarray, np.ndarray, np.ndarray]]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """fold() of several rising runs (sets, last, ways); large ones by threads that take a range of sets each."""
    if len(found[0][0]) > 1 or sum(f[0].shape[1] for f in found) < 1 << 18:
        return fold(*(np.concatenate([f[j] for f in found], 1 if j == 0 else 0) for j in range(3)))
    sample = np.sort(np.concatenate([f[0][0, :: max(1, f[0].shape[1] // 64)] for f in found]))
    cuts = np.unique(sample[np.linspace(0, len(sample) - 1, 2 * THREADS + 1).astype(int)[1:-1]])
    places = [np.concatenate([[0], np.searchsorted(f[0][0], cuts), [f[0].shape[1]]]) for f in found]

    def one(j: int):
        spans = [(f, p[j], p[j + 1]) for f, p in zip(found, places) if p[j + 1] > p[j]]
        if not spans:
            return None
        return fold(*(np.concatenate([f[i][..., a:b] for f, a, b in spans], -1) for i in range(3)))

    with ThreadPoolExecutor(THREADS) as pool:
        parts = [p for p in pool.map(one, range(len(cuts) + 1)) if p is not None]
    return tuple(np.concatenate([p[j] for p in parts], -1) for j in range(3))


def _block(sets: np.ndarray, last: np.ndarray, table: np.ndarray, k: int, barred: np.ndarray, kernel: str, bound) -> tuple[list, int]:
    """Per vertex the feasible supersets of one block, and how many sets the bound dropped."""
    n = table.shape[1]
    if kernel in ("remove", "prefix") and bound is None:
        degree = KERNELS[kernel](sets, table, sum(int(w) << 64 * i for i, w in enumerate(barred)))
    else:
        degree = KERNELS[kernel](sets, table)
    pruned = 0
    if bound is not None:
        good = bound(sets, degree, table)
        pruned = int((~good).sum())
        sets, last, degree = sets[:, good], last[good], degree[:, good]
    batch = sets.shape[1]
    if not batch:
        return [None] * n, pruned
    closed = sets | barred[:, None]
    fits = degree <= k
    for w in range(len(sets)):
        mine = slice(64 * w, min(n, 64 * w + 64))
        own = U64(1) << np.arange(mine.stop - mine.start, dtype=U64)
        fits[mine] &= (closed[w][None] & own[:, None]) == 0
    hit = np.flatnonzero(fits)
    vertex, at = np.divmod(hit, batch)
    more = sets[:, at]
    if len(sets) == 1:
        more[0] |= U64(1) << vertex.astype(U64)
    else:
        more[vertex >> 6, np.arange(len(hit))] |= U64(1) << (vertex & 63).astype(U64)
    tail = (last[at].view(np.uint32) << np.uint32(8) | vertex.astype(np.uint32)).view(np.int32)
    ends = np.searchsorted(hit, np.arange(n + 1) * batch)
    return [(more[:, i:j], tail[i:j]) if j > i else None for i, j in zip(ends, ends[1:])], pruned


#: Threads that merge runs on the driver.
THREADS = os.cpu_count() or 1


def expand(sets: np.ndarray, last: np.ndarray, table: np.ndarray, k: int, clique: int = 0, kernel: str = "prefix", bound=None, block: int = BLOCK) -> tuple[np.ndarray, np.ndarray, np.ndarray, int]:
    """Feasible supersets by one vertex of every set of a batch: (sets, last, ways, sets dropped by the bound).

    A set's vertex v is feasible if v is outside the set and the clique and its degree is
    at most k. ``bound(sets, degrees, table)`` may drop sets before they are expanded.
    ``last`` shifts in the new vertex, so it holds the last four. Results come vertex by
    vertex, each a rising run if the batch is sorted.
    """
    words, n = table.shape
    barred = split_mask(clique, words)
    last = np.ascontiguousarray(last)
    done = [_block(sets[:, a : a + block], last[a : a + block], table, k, barred, kernel, bound) for a in range(0, sets.shape[1], block)]
    found = [part[v] for v in range(n) for part, _ in done if part[v] is not None]
    pruned = sum(p for _, p in done)
    if not found:
        return np.zeros((words, 0), U64), np.zeros(0, np.int32), np.zeros(0, np.int64), pruned
    out = np.concatenate([f[0] for f in found], 1)
    return out, np.concatenate([f[1] for f in found]), np.ones(out.shape[1], np.int64), pruned
