"""The graph of one search, and edge tables.

An edge table has (graph_id STRING, u INT, v INT) with u < v and dense ids from 0. A
:class:`Graph` is the same for one graph on the driver or in a worker: at most 256
vertices, so at most a few KiB.
"""

from __future__ import annotations

from collections.abc import Iterable
from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .storage import LevelStore

#: Vertices of the largest graph that a search takes; larger ones are split or refused.
MAX_VERTICES = 256


@dataclass(frozen=True)
class Graph:
    """A simple undirected graph; ``masks[v]`` has bit u set for each neighbour u of v."""

    n: int
    masks: tuple[int, ...]
    name: str = "g"

    @classmethod
    def of(cls, n: int, edges: Iterable[tuple[int, int]], name: str = "g") -> Graph:
        masks = [0] * n
        for u, v in edges:
            if u != v:
                masks[u] |= 1 << v
                masks[v] |= 1 << u
        return cls(n, tuple(masks), name)

    def edges(self) -> list[tuple[int, int]]:
        return [(u, v) for u in range(self.n) for v in bits(self.masks[u]) if u < v]

    @property
    def m(self) -> int:
        return sum(x.bit_count() for x in self.masks) // 2

    @property
    def words(self) -> int:
        """64-bit words of a vertex set: one up to 64 vertices, else four."""
        return 1 if self.n <= 64 else 4

    def table(self) -> np.ndarray:
        """Neighbour masks as words x n."""
        low = (1 << 64) - 1
        return np.array([[m >> 64 * w & low for m in self.masks] for w in range(self.words)], np.uint64)

    def add(self, pairs: Iterable[tuple[int, int]]) -> Graph:
        return Graph.of(self.n, [*self.edges(), *pairs], self.name)

    def induced(self, keep: Iterable[int]) -> tuple[Graph, list[int]]:
        """The subgraph on ``keep``, relabelled, and the old label of each new vertex."""
        old = sorted(keep)
        place = {v: k for k, v in enumerate(old)}
        edges = [(place[u], place[v]) for u in old for v in bits(self.masks[u]) if u < v and v in place]
        return Graph.of(len(old), edges, self.name), old


def bits(mask: int) -> list[int]:
    out = []
    while mask:
        low = mask & -mask
        out.append(low.bit_length() - 1)
        mask ^= low
    return out


def mask_of(vertices: Iterable[int]) -> int:
    out = 0
    for v in vertices:
        out |= 1 << v
    return out


def normalize_edges(raw: DataFrame, a: str = "a", b: str = "b", graph: Column | None = None, bounded: bool = False) -> tuple[DataFrame, DataFrame]:
    """(edges, vertices) of a raw pair table: loops, repeats, directions and nulls removed, labels ranked per graph.

    Numeric labels are ranked as numbers, text as text. ``graph`` names each row's graph;
    without it the table is one graph, whose labels are ranked by all tasks unless ``bounded``
    tells that they are few whatever the size of the tables.
    """
    store = None if graph is not None or bounded else LevelStore(raw.sparkSession, "labels")
    graph = F.lit("g") if graph is None else graph
    pairs = raw.select(graph.cast("string").alias("graph_id"), F.least(a, b).alias("a"), F.greatest(a, b).alias("b"))
    pairs = pairs.where("graph_id is not null and a is not null and b is not null and a <> b").distinct()
    if store is not None:
        pairs = store.write(pairs, 0, 0)
    ends = pairs.select("graph_id", F.explode(F.array("a", "b")).alias("label")).distinct()
    vertices = ranked(ends, store) if store is not None else ends.withColumn("vid", F.row_number().over(Window.partitionBy("graph_id").orderBy("label")) - 1)
    left = vertices.select("graph_id", F.col("label").alias("a"), F.col("vid").alias("u"))
    right = vertices.select("graph_id", F.col("label").alias("b"), F.col("vid").alias("v"))
    edges = pairs.join(left, ["graph_id", "a"]).join(right, ["graph_id", "b"]).select("graph_id", "u", "v")
    return edges, vertices.select("graph_id", "vid", F.col("label").cast("string").alias("label"))


def ranked(ends: DataFrame, store: LevelStore) -> DataFrame:
    """Adds ``vid``, the rank of each (distinct) label of one graph of any size.

    Ranges of labels are ranked by tasks, then shifted; they are written, so that counting
    and ranking see the same ones.
    """
    spark = ends.sparkSession
    parts = max(int(spark.conf.get("spark.sql.shuffle.partitions")), spark.sparkContext.defaultParallelism)
    ranges = store.write(ends.repartitionByRange(parts, "label").withColumn("part", F.spark_partition_id()), 0, 1)
    sizes = ranges.groupBy("part").agg(F.count("*").alias("n"))
    before = F.coalesce(F.sum("n").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    starts = F.broadcast(sizes.select("part", before.alias("before")))
    place = F.row_number().over(Window.partitionBy("part").orderBy("label")) - 1
    return ranges.withColumn("place", place).join(starts, "part").select("graph_id", "label", (F.col("before") + F.col("place")).cast("int").alias("vid"))


def graph_from_rows(rows: Iterable, name: str = "g", n: int | None = None) -> Graph:
    pairs = [(int(r.u), int(r.v)) for r in rows]
    size = max((max(p) for p in pairs), default=-1) + 1
    return Graph.of(max(size, n or 0), pairs, name)


def degrees(edges: DataFrame) -> DataFrame:
    """(graph_id, vid, degree)."""
    return edges.select("graph_id", F.explode(F.array("u", "v")).alias("vid")).groupBy("graph_id", "vid").agg(F.count("*").alias("degree"))


def adjacency_masks(edges: DataFrame) -> DataFrame:
    """(graph_id, vid, nbr): neighbour set of each vertex as one long; fails on a graph of more than 64 vertices."""
    both = edges.select("graph_id", "u", "v").unionByName(edges.select("graph_id", F.col("v").alias("u"), F.col("u").alias("v")))
    return both.groupBy("graph_id", F.col("u").alias("vid")).agg(F.bit_or(F.expr("if(v < 64 and u < 64, shiftleft(1L, v), raise_error('a mask of one word holds 64 vertices'))")).alias("nbr"))


def profile(edges: DataFrame) -> DataFrame:
    """(graph_id, n, m, least degree, largest degree)."""
    return degrees(edges).groupBy("graph_id").agg(F.count("*").alias("n"), (F.sum("degree") / 2).cast("long").alias("m"), F.min("degree").alias("min_degree"), F.max("degree").alias("max_degree"))
