"""SQL functions: vectorised degree and feasibility, per-group width, table functions."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..graph import Graph
from ..operators import kernels, local, orders
from ..operators.search import Walk
from ..plans.options import Options
from ..sources import named


def degree_udf(graph: Graph):
    """degree_of(s, v) for one graph of at most 64 vertices."""
    table = graph.table()

    @F.pandas_udf("int")
    def degree_of(s: pd.Series, v: pd.Series) -> pd.Series:
        every = kernels.degrees_remove(s.to_numpy(np.int64).view(np.uint64)[None], table)
        return pd.Series(every[v.to_numpy(np.int64), np.arange(len(s))].astype(np.int32))

    return degree_of


def feasible_udf(graph: Graph, k: int):
    """is_feasible(s, v): whether v may go after s under target k."""
    table = graph.table()

    @F.pandas_udf("boolean")
    def is_feasible(s: pd.Series, v: pd.Series) -> pd.Series:
        sets, at = s.to_numpy(np.int64).view(np.uint64), v.to_numpy(np.int64)
        degree = kernels.degrees_remove(sets[None], table)[at, np.arange(len(s))]
        return pd.Series((degree <= k) & (sets >> at.astype(np.uint64) & np.uint64(1) == 0))

    return is_feasible


@F.pandas_udf(T.IntegerType())
def local_treewidth(u: pd.Series, v: pd.Series) -> int:
    """Width of the graph whose edges are a group's rows; any integer labels."""
    labels = {x: k for k, x in enumerate(sorted(set(u) | set(v)))}
    graph = Graph.of(len(labels), [(labels[a], labels[b]) for a, b in zip(u, v)])
    width = local.solve(graph).width
    return -1 if width is None else width


@F.pandas_udf(T.ArrayType(T.LongType()))
def edges_to_masks(u: pd.Series, v: pd.Series) -> list:
    """Neighbour masks, one long per vertex, of a group's edges (at most 64 vertices)."""
    size = int(max(u.max(), v.max())) + 1
    graph = Graph.of(size, zip(u.tolist(), v.tolist()))
    return [m - (1 << 64) if m >> 63 else m for m in graph.masks]


@F.udtf(returnType=T.StructType([T.StructField("u", T.IntegerType()), T.StructField("v", T.IntegerType())]))
class named_graph:  # noqa: N801
    """Edges of a graph given by a formula: named_graph('queen', 5, 0)."""

    def eval(self, kind: str, a: int, b: int):
        two = kind in ("grid", "torus", "kneser")
        for u, v in (named.KINDS[kind](a, b) if two else named.KINDS[kind](a)).edges():
            yield u, v


@F.udtf(returnType=T.StructType([T.StructField("k", T.IntegerType()), T.StructField("level", T.IntegerType()), T.StructField("expanded", T.LongType()), T.StructField("kept", T.LongType())]))
class treewidth_levels:  # noqa: N801
    """Level counts of the walk for one target: treewidth_levels('queen', 5, 0, 18)."""

    def eval(self, kind: str, a: int, b: int, k: int):
        two = kind in ("grid", "torus", "kneser")
        graph = named.KINDS[kind](a, b) if two else named.KINDS[kind](a)
        for x in Walk(graph, Options()).decide(k)[1]:
            yield x.k, x.level, x.expanded, x.kept


@F.udtf(returnType=T.StructType([T.StructField("pos", T.IntegerType()), T.StructField("vid", T.IntegerType()), T.StructField("deg", T.IntegerType())]))
class elimination_orders:  # noqa: N801
    """An order of least width of a graph given by a formula."""

    def eval(self, kind: str, a: int, b: int):
        two = kind in ("grid", "torus", "kneser")
        graph = named.KINDS[kind](a, b) if two else named.KINDS[kind](a)
        _, order = orders.elimination_order(graph)
        yield from ((k, v, d) for k, (v, d) in enumerate(zip(order, orders.order_degrees(graph, order))))


class _Rows:
    """Collects the edges of one partition of a table argument; rows have u and v."""

    def __init__(self):
        self.name, self.edges = None, []

    def add(self, row) -> None:
        self.name = row["graph_id"]
        self.edges.append((row["u"], row["v"]))

    def graph(self) -> Graph:
        return Graph.of(max((v for e in self.edges for v in e), default=-1) + 1, self.edges, str(self.name))


@F.udtf(returnType=T.StructType([T.StructField("graph_id", T.StringType()), T.StructField("k", T.IntegerType()), T.StructField("level", T.IntegerType()), T.StructField("expanded", T.LongType()), T.StructField("kept", T.LongType())]))
class table_levels:  # noqa: N801
    """Level counts of each graph of an edge table for one target: table_levels(TABLE(edges) PARTITION BY (graph_id), 3)."""

    def __init__(self):
        self.rows, self.k = _Rows(), 0

    def eval(self, row: T.Row, k: int):
        self.rows.add(row)
        self.k = k

    def terminate(self):
        for x in Walk(self.rows.graph(), Options()).decide(self.k)[1]:
            yield self.rows.name, x.k, x.level, x.expanded, x.kept


@F.udtf(returnType=T.StructType([T.StructField("graph_id", T.StringType()), T.StructField("pos", T.IntegerType()), T.StructField("vid", T.IntegerType()), T.StructField("deg", T.IntegerType())]))
class table_orders:  # noqa: N801
    """An order of least width of each graph of an edge table: table_orders(TABLE(edges) PARTITION BY graph_id)."""

    def __init__(self):
        self.rows = _Rows()

    def eval(self, row: T.Row):
        self.rows.add(row)

    def terminate(self):
        graph = self.rows.graph()
        _, order = orders.elimination_order(graph)
        yield from ((self.rows.name, k, v, d) for k, (v, d) in enumerate(zip(order, orders.order_degrees(graph, order))))


def _row_degrees(masks: pd.Series, s: pd.Series, v: pd.Series) -> np.ndarray:
    """Degree of each row's vertex in its own graph (at most 64 vertices) after its own set is removed."""
    size = max((len(m) for m in masks), default=0)
    table = np.zeros((size, 1, len(s)), np.uint64)
    for k, m in enumerate(masks):
        table[: len(m), 0, k] = np.asarray(m, np.int64).view(np.uint64)
    return kernels.degrees_remove(s.to_numpy(np.int64).view(np.uint64)[None], table)[v.to_numpy(np.int64), np.arange(len(s))]


@F.pandas_udf(T.IntegerType())
def degree_of(masks: pd.Series, s: pd.Series, v: pd.Series) -> pd.Series:
    return pd.Series(_row_degrees(masks, s, v).astype(np.int32))


@F.pandas_udf(T.BooleanType())
def is_feasible(masks: pd.Series, s: pd.Series, v: pd.Series, k: pd.Series) -> pd.Series:
    outside = s.to_numpy(np.int64).view(np.uint64) >> v.to_numpy(np.uint64) & np.uint64(1) == 0
    return pd.Series((_row_degrees(masks, s, v) <= k.to_numpy(np.int64)) & outside)


def register(spark: SparkSession) -> None:
    """Make the functions known to SQL of a session."""
    spark.udf.register("local_treewidth", local_treewidth)
    spark.udf.register("edges_to_masks", edges_to_masks)
    spark.udf.register("degree_of", degree_of)
    spark.udf.register("is_feasible", is_feasible)
    for name, table in (("named_graph", named_graph), ("treewidth_levels", treewidth_levels), ("elimination_orders", elimination_orders), ("table_levels", table_levels), ("table_orders", table_orders)):
        spark.udtf.register(name, table)
