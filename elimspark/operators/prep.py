"""Splitting at safe separators, and reductions of vertices.

A graph's width is the largest of its pieces' widths if it is split at a safe separator
and each piece keeps the separator as a clique. Safe are: the empty set (components),
single vertices, minimal pairs, minimal triples that leave two sides of two or more
vertices or span an edge, minimal cliques, and minimal cliques but for one vertex.
"""

from __future__ import annotations

from itertools import combinations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..graph import MAX_VERTICES, Graph, bits, mask_of
from ..storage import LevelStore

#: Triples are tried on every piece that a search can take; larger pieces are refused whatever their triples are.
TRIPLE_LIMIT = MAX_VERTICES


def parts_without(graph: Graph, removed: int) -> list[int]:
    """Components of the graph without some vertices, as masks."""
    left, out = (1 << graph.n) - 1 & ~removed, []
    while left:
        part = front = left & -left
        while front:
            near = 0
            for v in bits(front):
                near |= graph.masks[v]
            front = near & left & ~part
            part |= front
        out.append(part)
        left &= ~part
    return out


def around(graph: Graph, part: int) -> int:
    near = 0
    for v in bits(part):
        near |= graph.masks[v]
    return near & ~part


def articulation_points(graph: Graph, removed: int = 0) -> list[int]:
    """Vertices whose removal disconnects their component of the graph without ``removed``."""
    order, low, parent = {}, {}, {}
    found: set[int] = set()
    for root in range(graph.n):
        if removed >> root & 1 or root in order:
            continue
        parent[root] = -1
        order[root] = low[root] = len(order)
        stack = [(root, iter(bits(graph.masks[root] & ~removed)))]
        kids = 0
        while stack:
            v, near = stack[-1]
            step = next(near, None)
            if step is None:
                stack.pop()
                if stack:
                    u = stack[-1][0]
                    low[u] = min(low[u], low[v])
                    if u != root and low[v] >= order[u]:
                        found.add(u)
            elif step not in order:
                parent[step] = v
                order[step] = low[step] = len(order)
                kids += v == root
                stack.append((step, iter(bits(graph.masks[step] & ~removed))))
            elif step != parent[v]:
                low[v] = min(low[v], order[step])
        if kids > 1:
            found.add(root)
    return sorted(found)


def minimal(graph: Graph, separator: int) -> bool:
    """Whether at least two components see the whole separator."""
    return sum(around(graph, p) == separator for p in parts_without(graph, separator)) > 1


def is_clique(graph: Graph, mask: int) -> bool:
    return all(mask & ~graph.masks[v] == 1 << v for v in bits(mask))


def pairs(graph: Graph) -> int | None:
    """A minimal separator of two vertices."""
    for u in range(graph.n):
        for w in articulation_points(graph, 1 << u):
            if minimal(graph, s := 1 << u | 1 << w):
                return s
    return None


def triples(graph: Graph, limit: int = TRIPLE_LIMIT) -> int | None:
    """A safe separator of three vertices, in a graph without smaller separators."""
    if graph.n > limit:
        return None
    for u, w in combinations(range(graph.n), 2):
        for x in articulation_points(graph, 1 << u | 1 << w):
            s = 1 << u | 1 << w | 1 << x
            if not minimal(graph, s):
                continue
            sides = [p for p in parts_without(graph, s) if p.bit_count() >= 2]
            if len(sides) >= 2 or any(graph.masks[a] & s for a in bits(s)):
                return s
    return None


def minimal_triangulation(graph: Graph) -> tuple[list[int], list[int]]:
    """(order, later neighbours in a minimal triangulation): weights raised along paths of lighter vertices."""
    n = graph.n
    weight, left, order = [0] * n, (1 << n) - 1, []
    fill = list(graph.masks)
    while left:
        v = max(bits(left), key=lambda w: (weight[w], -w))
        left &= ~(1 << v)
        raised = graph.masks[v] & left
        reach: list[int] = [0] * (n + 1)
        for u in bits(raised):
            reach[weight[u]] |= 1 << u
        seen = raised
        for level in range(n):
            while reach[level]:
                u = (reach[level] & -reach[level]).bit_length() - 1
                reach[level] &= ~(1 << u)
                for w in bits(graph.masks[u] & left & ~seen):
                    seen |= 1 << w
                    if weight[w] > level:
                        raised |= 1 << w
                        reach[weight[w]] |= 1 << w
                    else:
                        reach[level] |= 1 << w
        for u in bits(raised):
            weight[u] += 1
            fill[u] |= 1 << v
            fill[v] |= 1 << u
        order.append(v)
    order.reverse()
    later, gone = [0] * n, 0
    for v in order:
        gone |= 1 << v
        later[v] = fill[v] & ~gone
    return order, later


def clique_separator(graph: Graph) -> int | None:
    """A minimal separator that is a clique."""
    order, later = minimal_triangulation(graph)
    for v in order:
        s = later[v]
        if s and is_clique(graph, s) and len(parts := parts_without(graph, s)) > 1:
            for part in parts:
                if minimal(graph, near := around(graph, part)) and is_clique(graph, near):
                    return near
    return None


def almost_clique_separator(graph: Graph) -> int | None:
    """A minimal separator that is a clique but for one vertex."""
    for v in range(graph.n):
        rest, old = graph.induced(u for u in range(graph.n) if u != v)
        s = clique_separator(rest)
        if s is not None and minimal(graph, whole := mask_of(old[u] for u in bits(s)) | 1 << v):
            return whole
    return None


RULES = {
    "components": lambda g: 0 if len(parts_without(g, 0)) > 1 else None,
    "articulation": lambda g: 1 << p[0] if (p := articulation_points(g)) else None,
    "pairs": pairs,
    "triples": triples,
    "clique": clique_separator,
    "almost_clique": almost_clique_separator,
}


def split(graph: Graph, rules: tuple[str, ...] = tuple(RULES)) -> tuple[list[tuple[Graph, list[int]]], list[tuple[str, list[int]]]]:
    """(pieces with the old labels of their vertices, separators used): rules in turn until none applies.

    Triples are safe only where no smaller separator is left, so they bring the rules before them along.
    """
    if "triples" in rules:
        rules = tuple(RULES)[:4] + tuple(r for r in rules if r not in tuple(RULES)[:4])
    done, used = [], []
    todo = [(graph, list(range(graph.n)))]
    while todo:
        g, names = todo.pop()
        for rule in rules:
            s = RULES[rule](g) if g.n > 1 else None
            if s is None:
                continue
            used.append((rule, [names[v] for v in bits(s)]))
            filled = g.add(combinations(bits(s), 2))
            for part in parts_without(g, s):
                piece, old = filled.induced(bits(part | s))
                todo.append((piece, [names[v] for v in old]))
            break
        else:
            done.append((g, names))
    return done, used


def reduce_simplicial(graph: Graph, low: int = 0) -> tuple[Graph, int, list[int]]:
    """(rest, lower bound, removed): vertices whose neighbours are a clique, or one within the bound."""
    masks, left, removed = list(graph.masks), set(range(graph.n)), []
    again = True
    while again:
        again = False
        for v in sorted(left):
            near = bits(masks[v])
            gaps = [(u, w) for u, w in combinations(near, 2) if not masks[u] >> w & 1]
            almost = bool(gaps) and len(near) <= low and any(all(x in g for g in gaps) for x in gaps[0])
            if gaps and not almost:
                continue
            if not gaps:
                low = max(low, len(near))
            for u in near:
                masks[u] = (masks[u] | (masks[v] if almost else 0)) & ~(1 << v | 1 << u)
            left.remove(v)
            removed.append(v)
            again = True
    rest, _ = Graph(graph.n, tuple(masks[v] if v in left else 0 for v in range(graph.n)), graph.name).induced(left)
    return rest, low, removed


def components(edges: DataFrame) -> DataFrame:
    """(graph_id, vid, component): the least vertex of each component, by least labels and pointer jumps.

    Each round halves label paths, so rounds grow with the logarithm of the diameter.
    """
    store = LevelStore(edges.sparkSession, "components")
    both = store.write(edges.select("graph_id", "u", "v").unionByName(edges.select("graph_id", F.col("v").alias("u"), F.col("u").alias("v"))).distinct(), 0, 0)
    labels = store.write(both.groupBy("graph_id", F.col("u").alias("vid")).agg(F.least(F.min("v"), F.col("u")).alias("label")), 1, 0)
    step = 0
    while True:
        step += 1
        named = labels.select("graph_id", F.col("vid").alias("v"), F.col("label").alias("near"))
        low = both.join(named, ["graph_id", "v"]).groupBy("graph_id", F.col("u").alias("vid")).agg(F.min("near").alias("near"))
        hooked = labels.join(low, ["graph_id", "vid"]).select("graph_id", "vid", F.col("label").alias("old"), F.least("label", "near").alias("label"))
        jump = labels.select("graph_id", F.col("vid").alias("label"), F.col("label").alias("far"))
        new = store.write(hooked.join(jump, ["graph_id", "label"]).select("graph_id", "vid", F.least("label", "far").alias("label"), (F.least("label", "far") < F.col("old")).alias("moved")), 1, step)
        moved = new.where("moved").limit(1).count()
        labels = new.select("graph_id", "vid", "label")
        if not moved:
            return labels.select("graph_id", "vid", F.col("label").alias("component"))


def simplicial_vertices(edges: DataFrame) -> DataFrame:
    """(graph_id, vid): vertices whose neighbours are all adjacent to one another; joins only."""
    both = edges.select("graph_id", "u", "v").unionByName(edges.select("graph_id", F.col("v").alias("u"), F.col("u").alias("v")))
    near = both.select("graph_id", F.col("u").alias("vid"), F.col("v").alias("a"))
    wedge = near.join(near.withColumnRenamed("a", "b"), ["graph_id", "vid"]).where("a < b")
    closed = wedge.join(edges.select("graph_id", F.col("u").alias("a"), F.col("v").alias("b")), ["graph_id", "a", "b"])
    have = closed.groupBy("graph_id", "vid").agg(F.count("*").alias("closed"))
    want = near.groupBy("graph_id", "vid").agg(F.count("*").alias("d"))
    return want.join(have, ["graph_id", "vid"], "left").where("d * (d - 1) div 2 = coalesce(closed, 0)").select("graph_id", "vid")


def relabelled(edges: DataFrame, labels: DataFrame) -> DataFrame:
    """Edges of every component as graphs of their own, named graph_id/component, with dense ids."""
    held = labels.select("graph_id", F.col("vid").alias("u"), "component")
    named = edges.join(held, ["graph_id", "u"]).select(F.concat_ws("/", "graph_id", F.col("component").cast("string")).alias("graph_id"), "u", "v")
    ends = named.select("graph_id", F.explode(F.array("u", "v")).alias("x")).distinct().withColumn("vid", F.row_number().over(Window.partitionBy("graph_id").orderBy("x")) - 1)
    left, right = (ends.select("graph_id", F.col("x").alias(c), F.col("vid").alias(f"new_{c}")) for c in "uv")
    return named.join(left, ["graph_id", "u"]).join(right, ["graph_id", "v"]).select("graph_id", F.col("new_u").alias("u"), F.col("new_v").alias("v"))
