"""Graphs given by formulas."""

from __future__ import annotations

from itertools import combinations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..graph import Graph


def queen(r: int) -> Graph:
    cells = [(i, j) for i in range(r) for j in range(r)]
    edges = [(a, b) for a, (i, j) in enumerate(cells) for b, (x, y) in enumerate(cells) if a < b and (i == x or j == y or abs(i - x) == abs(j - y))]
    return Graph.of(r * r, edges, f"queen{r}_{r}")


def mycielski(i: int) -> Graph:
    """i-th graph of the doubling construction on one edge: originals, copies, apex."""
    n, edges = 2, [(0, 1)]
    for _ in range(i - 1):
        edges = edges + [(u + n, v) for u, v in edges] + [(u, v + n) for u, v in edges] + [(n + k, 2 * n) for k in range(n)]
        n = 2 * n + 1
    return Graph.of(n, edges, f"myciel{i}")


def lcf(n: int, code: list[int], name: str = "lcf") -> Graph:
    """A cycle with a chord from each vertex, lengths by a repeated code."""
    edges = [(k, (k + 1) % n) for k in range(n)] + [(k, (k + code[k % len(code)]) % n) for k in range(n)]
    return Graph.of(n, edges, name)


def mcgee() -> Graph:
    return lcf(24, [12, 7, -7], "McGeeGraph")


def dyck() -> Graph:
    return lcf(32, [5, -5, 13, -13], "DyckGraph")


def grid(r: int, c: int) -> Graph:
    return Graph.of(r * c, [(i * c + j, i * c + j + 1) for i in range(r) for j in range(c - 1)] + [(i * c + j, i * c + j + c) for i in range(r - 1) for j in range(c)], f"grid{r}x{c}")


def torus(r: int, c: int) -> Graph:
    return Graph.of(r * c, [(i * c + j, i * c + (j + 1) % c) for i in range(r) for j in range(c)] + [(i * c + j, (i + 1) % r * c + j) for i in range(r) for j in range(c)], f"{r}x{c}_torusGrid")


def complete(n: int) -> Graph:
    return Graph.of(n, combinations(range(n), 2), f"K{n}")


def cycle(n: int) -> Graph:
    return Graph.of(n, [(k, (k + 1) % n) for k in range(n)], f"C{n}")


def path(n: int) -> Graph:
    return Graph.of(n, [(k, k + 1) for k in range(n - 1)], f"P{n}")


def kneser(a: int, b: int) -> Graph:
    sets = list(combinations(range(a), b))
    return Graph.of(len(sets), [(i, j) for i in range(len(sets)) for j in range(i) if not set(sets[i]) & set(sets[j])], f"KneserGraph_{a}_{b}")


def unitary_polar() -> Graph:
    """The 63 points of the plane over nine elements off a Hermitian curve, joined where their line touches the curve."""
    times = lambda x, y: ((x[0] * y[0] - x[1] * y[1]) % 3, (x[0] * y[1] + x[1] * y[0]) % 3)
    bar = lambda x: (x[0], -x[1] % 3)
    field = [(a, b) for a in range(3) for b in range(3)]

    def form(p, q):
        parts = [times(x, bar(y)) for x, y in zip(p, q)]
        return sum(x[0] for x in parts) % 3, sum(x[1] for x in parts) % 3

    zero, one = (0, 0), (1, 0)
    points = [(one, x, y) for x in field for y in field] + [(zero, one, y) for y in field] + [(zero, zero, one)]
    off = [p for p in points if form(p, p) != zero]
    touch = lambda p, q: times(form(p, q), bar(form(p, q))) == times(form(p, p), form(q, q))
    return Graph.of(len(off), [(u, v) for v in range(len(off)) for u in range(v) if touch(off[u], off[v])], "NonisotropicUnitaryPolarGraph_3_3")


KINDS = {"queen": queen, "mycielski": mycielski, "grid": grid, "torus": torus, "complete": complete, "cycle": cycle, "path": path, "kneser": kneser, "mcgee": lambda *_: mcgee(), "dyck": lambda *_: dyck(), "unitary_polar": lambda *_: unitary_polar()}


def edge_frame(spark: SparkSession, *graphs: Graph) -> DataFrame:
    rows = [(g.name, u, v) for g in graphs for u, v in g.edges()]
    return spark.createDataFrame(rows, "graph_id string, u int, v int")


def queen_edges(spark: SparkSession, r: int) -> DataFrame:
    """The queen board as a plan over a range of squares, without driver rows."""
    a = spark.range(r * r).select(F.col("id").cast("int").alias("u"))
    b = spark.range(r * r).select(F.col("id").cast("int").alias("v"))
    row, col = lambda x: F.floor(F.col(x) / r), lambda x: F.col(x) % r
    sees = (row("u") == row("v")) | (col("u") == col("v")) | (F.abs(row("u") - row("v")) == F.abs(col("u") - col("v")))
    return a.crossJoin(b).where("u < v").where(sees).select(F.lit(f"queen{r}_{r}").alias("graph_id"), "u", "v")
