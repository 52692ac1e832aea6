"""Many graphs and many targets in one frontier: graph and target are part of the key."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Observation, SparkSession, Window
from pyspark.sql import functions as F

from ..graph import Graph, mask_of
from ..storage import LevelStore
from . import kernels
from .reduce import max_clique

U64 = np.uint64


def _expand(batches):
    """Feasible supersets; each row carries its graph, so a batch may mix graphs of up to 64 vertices."""
    for batch in batches:
        if not batch.num_rows:
            continue
        out = []
        k, n, s, clique = (np.asarray(batch.column(c)).astype(np.int64) for c in ("k", "n", "s", "clique"))
        lengths = np.asarray(batch.column("nbr").value_lengths()).astype(np.int64)
        flat = np.asarray(batch.column("nbr").flatten()).astype(np.int64).view(U64)
        starts = np.concatenate([[0], np.cumsum(lengths)])
        for a in range(0, batch.num_rows, kernels.BLOCK):
            rows = np.arange(a, min(a + kernels.BLOCK, batch.num_rows))
            top = int(lengths[rows].max())
            table = np.zeros((top, 1, len(rows)), U64)
            for v in range(top):
                have = lengths[rows] > v
                table[v, 0, have] = flat[starts[rows[have]] + v]
            sets = s[rows].view(U64)[None]
            closed = sets[0] | clique[rows].view(U64)
            degree = kernels.degrees_remove(sets, table)
            for v in range(top):
                good = (lengths[rows] > v) & (degree[v] <= k[rows]) & (closed >> U64(v) & U64(1) == 0)
                hit = rows[good]
                out.append((hit, (s[hit].view(U64) | U64(1) << U64(v)).view(np.int64)))
        at, new = (np.concatenate([x[j] for x in out]) for j in range(2))
        g = batch.column("g").take(pa.array(at))
        yield pa.RecordBatch.from_arrays([g, pa.array(k[at]), pa.array(n[at]), pa.array(new)], ["g", "k", "n", "s"])


def _walk(graphs: DataFrame, targets: DataFrame) -> DataFrame:
    """(g, k, feasible) of every target (g, k) of every graph (g, n, nbr, clique): levels advance all of them at once."""
    store = LevelStore(graphs.sparkSession, "many")
    front = targets.join(graphs.select("g", "n"), "g").select("g", "k", "n", F.lit(0).cast("long").alias("s"))
    front = store.write(front, 0, 0)
    found = front.where("k >= n - 1").select("g", "k")
    level = 0
    while True:
        open_rows = front.where(F.lit(level) < F.col("n") - F.col("k") - 1).join(graphs.select("g", "nbr", "clique"), "g").select("g", "k", "n", "s", "nbr", "clique")
        new = open_rows.mapInArrow(_expand, "g string, k long, n long, s long").groupBy("g", "k", "n", "s").agg(F.count("*").alias("ways")).drop("ways")
        level += 1
        seen = Observation()
        front = store.write(new.observe(seen, F.count(F.lit(1)).alias("n")), 0, level)
        found = found.unionByName(front.where(F.lit(level) == F.col("n") - F.col("k") - 1).select("g", "k").distinct())
        if not seen.get["n"]:
            break
    answers = targets.join(found.distinct().withColumn("feasible", F.lit(True)), ["g", "k"], "left").select("g", "k", F.coalesce("feasible", F.lit(False)).alias("feasible"))
    answers = LevelStore(graphs.sparkSession, "answers").write(answers, 0, 0)
    store.drop()
    return answers


def _cliques(batches):
    """Adds the mask and size of each graph's first maximum clique; its vertices are never removed."""
    for batch in batches:
        low = (1 << 64) - 1
        masks = [mask_of(max_clique(Graph(len(x), tuple(m & low for m in x)))) for x in batch.column("nbr").to_pylist()]
        yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in ("g", "n", "nbr")), pa.array([m - (1 << 64) if m >> 63 else m for m in masks], pa.int64()), pa.array([m.bit_count() for m in masks], pa.int64())], ["g", "n", "nbr", "clique", "size"])


def decide_many(spark: SparkSession, wanted: list[tuple[Graph, int, int]]) -> DataFrame:
    """(g, k, feasible) of several targets of a few driver-side graphs; with a clique no larger than k + 1 of each."""
    graphs = {g.name: g for g, _, _ in wanted}
    signed = lambda m: m - (1 << 64) if m >> 63 else m
    if any(g.n > 64 for g in graphs.values()):
        raise ValueError("at most 64 vertices")
    table = spark.createDataFrame([(g.name, g.n, [signed(m) for m in g.masks], 0) for g in graphs.values()], "g string, n long, nbr array<long>, clique long")
    return _walk(table, spark.createDataFrame([(g.name, k) for g, k, _ in wanted], "g string, k long"))


def widths_many(edges: DataFrame) -> DataFrame:
    """(graph_id, width) of all graphs of an edge table.

    The frontier holds each graph at its current target, from its maximum clique's size less
    one on; graphs whose walk dies go on with the next target. Graphs of more than 64
    vertices, which one word can't hold, are solved by api.treewidth; their width is null
    where it is not known.
    """
    from .. import api
    from ..graph import adjacency_masks

    spark = edges.sparkSession
    wide = F.max("v").over(Window.partitionBy("graph_id")) >= 64
    marked = edges.select("graph_id", "u", "v", wide.alias("wide"))
    narrow = marked.where(~F.col("wide"))
    masks = adjacency_masks(narrow)
    graphs = masks.groupBy("graph_id").agg(F.count("*").alias("n"), F.array_sort(F.collect_list(F.struct("vid", "nbr"))).alias("x")).select(F.col("graph_id").alias("g"), "n", F.col("x.nbr").alias("nbr"))
    store = LevelStore(spark, "graphs")
    graphs = store.write(graphs.mapInArrow(_cliques, "g string, n long, nbr array<long>, clique long, size long"), 0, 0)
    todo = graphs.select("g", F.greatest(F.col("size") - 1, F.lit(1)).alias("k"))
    done = None
    while True:
        answers = _walk(graphs, todo)
        good = answers.where("feasible").select(F.col("g").alias("graph_id"), F.col("k").alias("width"))
        done = good if done is None else done.unionByName(good)
        todo = answers.where("not feasible").select("g", (F.col("k") + 1).alias("k"))
        if not todo.limit(1).count():
            break
    large = marked.where("wide").select("graph_id", "u", "v")
    if large.limit(1).count():
        done = done.unionByName(api.treewidth(large).select("graph_id", F.col("width").cast("long").alias("width")))
    return done
