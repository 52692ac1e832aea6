"""Cost and accuracy measures."""

from __future__ import annotations

from collections.abc import Iterable
from dataclasses import fields

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..graph import Graph, bits
from .search import LEVEL_SCHEMA, RUN_SCHEMA, Level, Run

INFINITE = 1 << 30


def runs_frame(spark: SparkSession, runs: Iterable[Run]) -> DataFrame:
    names = [f.name for f in fields(Run) if f.name != "levels"]
    return spark.createDataFrame([tuple(getattr(r, n) for n in names) for r in runs], RUN_SCHEMA)


def levels_frame(spark: SparkSession, levels: Iterable[Level]) -> DataFrame:
    names = [f.name for f in fields(Level)]
    return spark.createDataFrame([tuple(getattr(x, n) for n in names) for x in levels], LEVEL_SCHEMA)


def compare(a: DataFrame, b: DataFrame) -> DataFrame:
    """Speed-up and state ratio of two sets of runs of the same graphs (b over a)."""
    left = a.select("graph_id", F.col("seconds").alias("a_s"), F.col("explored").alias("a_n"), F.col("width").alias("a_width"))
    right = b.select("graph_id", F.col("seconds").alias("b_s"), F.col("explored").alias("b_n"), F.col("width").alias("b_width"))
    both = left.join(right, "graph_id", "full")
    return both.select("graph_id", "a_width", "b_width", (F.col("b_s") / F.col("a_s")).alias("time_ratio"), (F.col("b_n") / F.col("a_n")).alias("state_ratio"))


def ablation(runs: DataFrame, switch: str, value: str = "explored") -> DataFrame:
    """One row per graph and one column per setting of an option."""
    return runs.withColumn("setting", F.get_json_object("opts", f"$.{switch}")).groupBy("graph_id").pivot("setting").agg(F.max(value))


def explored_share(levels: DataFrame) -> DataFrame:
    """Each level's share of its graph's explored states, and the running total."""
    from pyspark.sql import Window

    whole = Window.partitionBy("graph_id")
    run = whole.orderBy("k", "level").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return levels.select("graph_id", "k", "level", "expanded", F.sum("expanded").over(run).alias("running"), (F.col("expanded") / F.sum("expanded").over(whole)).alias("share"))


def bloom_audit(exact: DataFrame, filtered: DataFrame, keys: list[str]) -> DataFrame:
    """(distinct, kept, lost, rate) of a level under the filter."""
    lost = exact.select(*keys).distinct().join(filtered.select(*keys).distinct(), keys, "left_anti").agg(F.count("*").alias("lost"))
    return exact.select(*keys).distinct().agg(F.count("*").alias("distinct")).crossJoin(lost).select("distinct", (F.col("distinct") - F.col("lost")).alias("kept"), "lost", (F.col("lost") / F.col("distinct")).alias("rate"))


def traces(graph: Graph, removed: int) -> tuple[list[list[int]], list[int]]:
    """(per vertex outside the set, the neighbour-list lengths its search reads in turn; the degrees)."""
    out, degrees = [], []
    for v in range(graph.n):
        if removed >> v & 1:
            continue
        seen, stack, reads, degree = 1 << v, [v], [], 0
        while stack:
            u = stack.pop()
            reads.append(graph.masks[u].bit_count())
            new = graph.masks[u] & ~seen
            seen |= new
            degree += (new & ~removed).bit_count()
            stack.extend(bits(new & removed))
        out.append(reads)
        degrees.append(degree)
    return out, degrees


def lockstep_steps(lanes: list[list[list[int]]], x: int, y: int) -> int:
    """Steps that a group of lanes takes in lockstep under an (x, y) loop.

    Each lane works through its vertices (outer), the reads of each search (middle) and the
    neighbours of each read (inner). One round offers x inner steps and then a middle step,
    y times over, and then an outer step; INFINITE offers as many as any lane needs. A step
    is paid by the whole group.
    """
    outer = np.zeros(len(lanes), int)
    middle = np.zeros(len(lanes), int)
    inner = np.array([lane[0][0] if lane else 0 for lane in lanes])
    done = np.array([not lane for lane in lanes])
    steps = 0

    def reading() -> np.ndarray:
        return ~done & (inner > 0)

    def popping() -> np.ndarray:
        return np.array([not d and i == 0 and m + 1 < len(lane[o]) for d, i, m, o, lane in zip(done, inner, middle, outer, lanes)])

    def next_vertex() -> np.ndarray:
        return np.array([not d and i == 0 and m + 1 >= len(lane[o]) for d, i, m, o, lane in zip(done, inner, middle, outer, lanes)])

    while not done.all():
        turn = 0
        while turn < y:
            turn += 1
            count = 0
            while count < x and reading().any():
                inner[reading()] -= 1
                steps += 1
                count += 1
            ready = popping()
            if not ready.any() and (y >= INFINITE or not reading().any()):
                if y >= INFINITE and reading().any():
                    continue
                break
            steps += 1
            for k in np.flatnonzero(ready):
                middle[k] += 1
                inner[k] = lanes[k][outer[k]][middle[k]]
        steps += 1
        for k in np.flatnonzero(next_vertex()):
            outer[k] += 1
            middle[k] = 0
            if outer[k] >= len(lanes[k]):
                done[k] = True
            else:
                inner[k] = lanes[k][outer[k]][0]
    return steps


def degree_machine(graph: Graph, sets: list[int], x: int, y: int, width: int = 32) -> tuple[list[list[int]], list[int]]:
    """(degrees of the vertices outside each set, steps of each group of lanes) under an (x, y) loop."""
    made = [traces(graph, s) for s in sets]
    steps = [lockstep_steps([t[0] for t in made[a : a + width]], x, y) for a in range(0, len(made), width)]
    return [t[1] for t in made], steps


def divergence(graph: Graph, sets: list[int], width: int = 32) -> dict[str, int]:
    """Lockstep cost of the plain loops by source: steps that lanes need, waits for longer neighbour lists, waits for longer searches."""
    useful = lists = searches = 0
    for a in range(0, len(sets), width):
        lanes = [traces(graph, s)[0] for s in sets[a : a + width]]
        useful += sum(sum(reads) + len(reads) for lane in lanes for reads in lane)
        for at in range(max(map(len, lanes), default=0)):
            here = [lane[at] if at < len(lane) else [] for lane in lanes]
            longest = max(map(len, here))
            for turn in range(longest):
                most = max(reads[turn] if turn < len(reads) else 0 for reads in here)
                for reads in here:
                    if turn < len(reads):
                        lists += most - reads[turn]
                    else:
                        searches += most + 1
    return {"useful": useful, "waits_for_lists": lists, "waits_for_searches": searches}


def lockstep_cost(graph: Graph, sets: list[int], settings: dict[str, tuple[int, int]], width: int = 32) -> dict[str, int]:
    """Summed group steps of all states for several loop shapes."""
    lanes = [traces(graph, s)[0] for s in sets]
    return {name: sum(lockstep_steps(lanes[a : a + width], x, y) for a in range(0, len(lanes), width)) for name, (x, y) in settings.items()}


SHAPES = {"1,1": (1, 1), "inf,inf": (INFINITE, INFINITE), "1,inf": (1, INFINITE), "inf,1": (INFINITE, 1), "3,2": (3, 2)}
