"""Widths, orders and decompositions of edge tables."""

from __future__ import annotations

from collections.abc import Callable, Iterable
from dataclasses import fields

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_schema
from pyspark.sql.types import ArrayType, LongType, StructField, StructType

from .graph import MAX_VERTICES, Graph
from .operators import bounds, local, measures, orders, prep, reduce
from .operators.search import RUN_SCHEMA, LevelTooWide, Run, Walk
from .plans.options import Options
from .storage import LevelStore

RUN_FIELDS = [f.name for f in fields(Run) if f.name != "levels"]


def graph_of(edges: DataFrame, name: str | None = None, limit: int = MAX_VERTICES * (MAX_VERTICES - 1) // 2) -> Graph:
    """One graph of an edge table on the driver; refuses more edges than the largest graph can have."""
    some = edges.where(F.col("graph_id") == name) if name is not None else edges
    rows = some.select("u", "v").limit(limit + 1).collect()
    if len(rows) > limit:
        raise ValueError("too many edges for one search; split the graph first")
    size = max((r.v for r in rows), default=-1) + 1
    return Graph.of(size, [(r.u, r.v) for r in rows], name or "g")


def packed(edges: DataFrame) -> DataFrame:
    """(graph_id, pairs): the edges of each graph as a sorted array of u * 2**32 + v."""
    return edges.select("graph_id", F.shiftleft(F.col("u").cast("long"), 32).bitwiseOR(F.col("v").cast("long")).alias("p")).groupBy("graph_id").agg(F.array_sort(F.collect_set("p")).alias("pairs"))


def unpacked(pairs, name: str = "g") -> Graph:
    values = np.asarray(pairs, np.int64)
    u, v = values >> 32, values & 0xFFFFFFFF
    return Graph.of(int(v.max()) + 1 if len(v) else 0, zip(u.tolist(), v.tolist()), name)


def per_graph(edges: DataFrame, function: Callable[[Graph], Iterable[tuple]], schema: str) -> DataFrame:
    """Rows of a function of each graph, graph_id in front. The function doesn't see the name: equal graphs are one call.

    Equal edge lists meet by one grouping; each distinct graph is a row of an Arrow batch.
    """
    graphs = packed(edges)
    distinct = graphs.groupBy("pairs").agg(F.count("*").alias("copies")).select("pairs")
    rows = ArrayType(StructType.fromDDL(schema))
    names = rows.elementType.names
    out = StructType([StructField("pairs", ArrayType(LongType())), StructField("rows", rows)])
    arrow = to_arrow_schema(out).field("rows").type

    def run(batches):
        for batch in batches:
            for j in range(batch.num_rows):
                pairs = batch.column("pairs").slice(j, 1)
                found = [dict(zip(names, r)) for r in function(unpacked(pairs[0].values))]
                yield pa.RecordBatch.from_arrays([pairs, pa.array([found], arrow)], ["pairs", "rows"])

    solved = spread(distinct, "pairs").mapInArrow(run, out)
    return graphs.join(solved, "pairs").select("graph_id", F.inline("rows"))


def spread(frame: DataFrame, *keys: str) -> DataFrame:
    """Partitioned by keys for costly work on few bytes, which adaptive coalescing would put into one task.

    The grouping that follows uses this exchange, so it is not one more.
    """
    spark = frame.sparkSession
    parts = max(int(spark.conf.get("spark.sql.shuffle.partitions")), spark.sparkContext.defaultParallelism)
    return frame.repartition(parts, *keys)


def batch_widths(edges: DataFrame, options: Options | None = None, preprocess: bool = True) -> DataFrame:
    """Runs of many graphs, each distinct one solved once, in one task.

    A graph that meets a level of over ``task_limit`` states has status 'deferred' and its
    bounds; treewidth() walks those on the cluster.
    """
    options = options or Options()
    schema = RUN_SCHEMA.split(", ", 1)[1]

    def one(graph: Graph):
        if not preprocess and graph.n > MAX_VERTICES:
            run = Run(graph.name, graph.n, graph.m, 0, None, bounds.mmw(graph), status="too_large")
        else:
            try:
                run = local.solve(graph, options) if preprocess else Walk(graph, options).width()
            except LevelTooWide:
                run = Run(graph.name, graph.n, graph.m, 0, None, bounds.mmw(graph), status="deferred", opts=options.json())
        return [tuple(getattr(run, f) for f in RUN_FIELDS[1:])]

    return per_graph(edges, one, schema)


def treewidth(edges: DataFrame, options: Options | None = None, preprocess: bool = True) -> DataFrame:
    """Runs of all graphs: solved in tasks, and those too wide for a task by distributed walks, one after the other.

    Which way a graph goes depends on its own levels, not on how many others there are.
    """
    spark, options = edges.sparkSession, options or Options()
    store = LevelStore(spark, "runs")
    done = store.write(batch_widths(edges, options, preprocess), 0, 0)
    runs = []
    for row in done.where("status = 'deferred'").select("graph_id").toLocalIterator():
        graph = graph_of(edges, row.graph_id)
        runs.append(local.solve(graph, options, spark) if preprocess else Walk(graph, options, spark).width())
    return done.where("status <> 'deferred'").unionByName(measures.runs_frame(spark, runs)) if runs else done


def exact_widths(runs: DataFrame) -> DataFrame:
    """(graph_id, width) of runs; one whose width is not exact stops the query, as a row without a width looks like a result."""
    said = F.concat(F.lit("no exact width of graph "), "graph_id", F.lit(": "), "status", F.lit(", at least "), F.col("lower_bound").cast("string"))
    found = F.when((F.col("status") == "exact") & F.col("width").isNotNull(), F.col("width").cast("long")).otherwise(F.raise_error(said).cast("long"))
    return runs.select("graph_id", found.alias("width"))


def decide(spark: SparkSession, graph: Graph, k: int, options: Options | None = None) -> tuple[DataFrame, DataFrame]:
    """(one row with the answer, level counts) of one walk."""
    walk = Walk(graph, options, spark)
    good, levels, cut = walk.decide(k)
    if walk.store is not None:
        walk.store.drop()
    answer = spark.createDataFrame([(graph.name, k, good, cut)], "graph_id string, k int, feasible boolean, cut boolean")
    return answer, measures.levels_frame(spark, levels)


def elimination_orders(edges: DataFrame, options: Options | None = None, method: str = "levels") -> DataFrame:
    """(graph_id, pos, vid, deg): an order of least width of each graph."""

    def one(graph: Graph):
        _, order = orders.elimination_order(graph, options, method)
        return [(k, v, d) for k, (v, d) in enumerate(zip(order, orders.order_degrees(graph, order)))]

    return per_graph(edges, one, "pos int, vid int, deg int")


def decompositions(edges: DataFrame, options: Options | None = None) -> DataFrame:
    """(graph_id, bag_id, parent, verts): a tree decomposition of least width of each graph."""

    def one(graph: Graph):
        _, order = orders.elimination_order(graph, options)
        return orders.tree_decomposition(graph, order)

    return per_graph(edges, one, "bag_id int, parent int, verts array<int>")


def pieces(edges: DataFrame, rules: tuple[str, ...] = tuple(prep.RULES)) -> DataFrame:
    """(graph_id, piece_id, n, m) after splitting at safe separators."""
    return per_graph(edges, lambda g: [(k, p.n, p.m) for k, (p, _) in enumerate(prep.split(g, rules)[0])], "piece_id long, n int, m long")


def separators(edges: DataFrame, rules: tuple[str, ...] = tuple(prep.RULES)) -> DataFrame:
    """(graph_id, sep_id, kind, verts, safe): the separators that splitting used."""
    return per_graph(edges, lambda g: [(k, kind, verts, True) for k, (kind, verts) in enumerate(prep.split(g, rules)[1])], "sep_id long, kind string, verts array<int>, safe boolean")


def lower_bounds(edges: DataFrame, rule: str = "min") -> DataFrame:
    return per_graph(edges, lambda g: [(bounds.mmw(g, rule),)], "bound int")


def upper_bounds(edges: DataFrame, rule: str = "fill") -> DataFrame:
    return per_graph(edges, lambda g: [(bounds.greedy_order(g, rule)[0],)], "bound int")


def max_cliques(edges: DataFrame) -> DataFrame:
    return per_graph(edges, lambda g: [(c := reduce.max_clique(g), len(c))], "verts array<int>, size int")


def disjoint_paths(edges: DataFrame) -> DataFrame:
    """(graph_id, u, v, n_paths) of all pairs that aren't adjacent; work is shared by (graph, u)."""
    ends = edges.groupBy("graph_id").agg(F.max("v").alias("top"))
    blocks = ends.select("graph_id", F.explode(F.sequence(F.lit(0), F.col("top"))).alias("block"))
    shared = edges.join(blocks, "graph_id")

    def run(key: tuple, rows: pd.DataFrame) -> pd.DataFrame:
        graph = Graph.of(int(rows["v"].max()) + 1, zip(rows["u"].tolist(), rows["v"].tolist()), str(key[0]))
        u = int(key[1])
        out = [(graph.name, u, v, reduce.disjoint_paths(graph, u, v)) for v in range(u + 1, graph.n) if not graph.masks[u] >> v & 1]
        return pd.DataFrame(out, columns=["graph_id", "u", "v", "n_paths"])

    return spread(shared, "graph_id", "block").groupBy("graph_id", "block").applyInPandas(run, "graph_id string, u int, v int, n_paths int")


def forced_edges(edges: DataFrame, paths: DataFrame, k: int) -> DataFrame:
    """Edges with those that a width of at most k forces."""
    return edges.select("graph_id", "u", "v").unionByName(paths.where(F.col("n_paths") >= k + 1).select("graph_id", "u", "v")).distinct()
