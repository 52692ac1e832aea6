"""Cliques that need not be removed, and edges that every target width forces."""

from __future__ import annotations

from collections import deque

from ..graph import Graph, bits, mask_of


def max_clique(graph: Graph) -> list[int]:
    """The lexicographically first of the largest cliques, by branch and bound with greedy colours."""
    best: list[int] = []

    def colours(candidates: int) -> int:
        count = 0
        while candidates:
            count += 1
            free = candidates
            while free:
                v = (free & -free).bit_length() - 1
                candidates &= ~(1 << v)
                free &= ~(1 << v) & ~graph.masks[v]
        return count

    def grow(chosen: list[int], candidates: int) -> None:
        nonlocal best
        if len(chosen) > len(best):
            best = list(chosen)
        while candidates:
            if len(chosen) + candidates.bit_count() <= len(best) or len(chosen) + colours(candidates) <= len(best):
                return
            v = (candidates & -candidates).bit_length() - 1
            candidates &= ~(1 << v)
            grow([*chosen, v], candidates & graph.masks[v])

    grow([], (1 << graph.n) - 1)
    return best


def greedy_clique(graph: Graph) -> list[int]:
    """From each vertex, add the neighbour with most candidates left; the largest result."""
    best: list[int] = []
    for start in range(graph.n):
        chosen, candidates = [start], graph.masks[start]
        while candidates:
            v = max(bits(candidates), key=lambda w: ((graph.masks[w] & candidates).bit_count(), -w))
            chosen.append(v)
            candidates &= graph.masks[v]
        if len(chosen) > len(best):
            best = sorted(chosen)
    return best


def disjoint_paths(graph: Graph, s: int, t: int) -> int:
    """Vertex-disjoint paths between two vertices that aren't adjacent, by augmenting flow on split vertices."""
    # Node 2v enters v, 2v + 1 leaves it; inner vertices carry one path.
    flow: dict[tuple[int, int], int] = {}

    def room(a: int, b: int) -> int:
        if a // 2 == b // 2 and a % 2 == 0 and b == a + 1:
            base = graph.n if a // 2 in (s, t) else 1
        else:
            base = 1 if a % 2 == 1 and b % 2 == 0 and graph.masks[a // 2] >> b // 2 & 1 else 0
        return base - flow.get((a, b), 0)

    steps = {2 * v: [2 * v + 1, *(2 * u + 1 for u in bits(graph.masks[v]))] for v in range(graph.n)}
    steps |= {2 * v + 1: [2 * v, *(2 * u for u in bits(graph.masks[v]))] for v in range(graph.n)}
    count = 0
    while True:
        came = {2 * s + 1: -1}
        queue = deque(came)
        while queue and 2 * t not in came:
            a = queue.popleft()
            for b in steps[a]:
                if b not in came and room(a, b) > 0:
                    came[b] = a
                    queue.append(b)
        if 2 * t not in came:
            return count
        b = 2 * t
        while came[b] >= 0:
            a = came[b]
            flow[a, b] = flow.get((a, b), 0) + 1
            flow[b, a] = flow.get((b, a), 0) - 1
            b = a
        count += 1


def all_disjoint_paths(graph: Graph) -> dict[tuple[int, int], int]:
    """Path counts of every pair that isn't adjacent."""
    return {(u, v): disjoint_paths(graph, u, v) for u in range(graph.n) for v in range(u + 1, graph.n) if not graph.masks[u] >> v & 1}


def augment(graph: Graph, paths: dict[tuple[int, int], int], k: int) -> Graph:
    """The graph with the edges that a width of at most k forces; counts come from the graph as given."""
    return graph.add(p for p, c in paths.items() if c >= k + 1)


def clique_mask(graph: Graph, choice: str | tuple[int, ...]) -> int:
    if isinstance(choice, tuple):
        if any(not graph.masks[u] >> v & 1 for u in choice for v in choice if u < v):
            raise ValueError("the vertices given as clique are not one")
        return mask_of(choice)
    if choice == "none":
        return 0
    return mask_of(max_clique(graph) if choice == "max" else greedy_clique(graph))
