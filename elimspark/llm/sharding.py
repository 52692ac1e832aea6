"""Sharding by longest-processing-time scheduling, exact and distributed.

Documents that must stay together form groups; the groups, longest first, each go to the
shard with the least load, taken from a heap (equal loads: the lower shard). The schedule
depends on the groups only through how many have each size, so one task runs it over the
table of sizes: a few groups of a size leave the heap one by one; many groups of a size
fill the shards in a pattern that repeats, which is written down as (ranks, pattern)
instead of being walked. Groups then find their shard by their rank inside their size.

The size table has at most sqrt(2 * total size) rows, since the sizes differ.

A group's size is the sum over its documents of max(1, length of the text). Groups of one
size are ranked by a fixed scramble of their least doc_id, then by that id, then by group.

Edge cases: empty and null texts count 1; a null key makes a document a group of its own;
repeated rows of one key stay together; an empty table gives no rows; shards without
documents are allowed.
"""

from __future__ import annotations

import heapq

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import Scratch, spread_id

SHARDS = 16
RANK_BITS = 6


def schedule(sizes: list[tuple[int, int]], shards: int) -> list[tuple[int, int, int, list[int]]]:
    """(size, first rank, end rank, pattern) for (size, groups) pairs in falling order of size.

    The group of rank r goes to pattern[(r - first rank) % len(pattern)].
    """
    loads = np.zeros(shards, dtype=object)
    out = []
    for size, count in sizes:
        if count <= 4 * shards:
            heap = [(int(load), j) for j, load in enumerate(loads)]
            heapq.heapify(heap)
            pattern = []
            for _ in range(count):
                load, j = heap[0]
                pattern.append(j)
                heapq.heapreplace(heap, (load + size, j))
            for load, j in heap:
                loads[j] = load
            out.append((size, 0, count, pattern))
            continue
        # Between two neighbouring loads only the shards below take groups, each once per `size` of load.
        order = sorted(range(shards), key=lambda j: (loads[j], j))
        rank = 0
        for i in range(1, shards + 1):
            low = loads[order[i - 1]]
            active = order[:i]
            phases = sorted(active, key=lambda j: ((loads[j] - low) % size, j))
            if i < shards:
                high = loads[order[i]]
                # Group slots of shard j with low <= load < high, as loads stand at `low` or just above.
                slots = sum(_slots(loads[j], low, high, size) for j in active)
            else:
                slots = count
            take = min(slots, count - rank)
            if take > 0:
                out.append((size, rank, rank + take, phases))
                rounds, rest = divmod(take, i)
                for k, j in enumerate(phases):
                    loads[j] += size * (rounds + (k < rest))
                rank += take
            if rank == count:
                break
            # Order among equals at the next level: loads have moved, the sorted places of the others haven't.
            order = sorted(active, key=lambda j: (loads[j], j)) + order[i:]
    return out


def _slots(load: int, low: int, high: int, size: int) -> int:
    """Multiples load + i * size (i >= 0) in [low, high)."""
    first = load if load >= low else load + -(-(low - load) // size) * size
    return max(0, -(-(high - first) // size))


def assign(documents: DataFrame, key: Column, shards: int = SHARDS) -> DataFrame:
    """(doc_id, group_size, shard) of every row; rows with equal ``key`` share a shard."""
    spark = documents.sparkSession
    scratch = Scratch(spark, "sharding")
    length = F.greatest(F.lit(1), F.coalesce(F.length("text"), F.lit(0))).cast("long")
    rows = documents.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(key, F.xxhash64(F.lit("alone"), *documents.columns)).alias("key"), length.alias("len"))
    rows = scratch.keep(rows, "rows")
    groups = rows.groupBy("key").agg(F.sum("len").alias("size"), F.min("doc_id").alias("lead"))
    cell = F.shiftright(spread_id(F.col("lead")), 31 - RANK_BITS).alias("cell")
    groups = scratch.keep(groups.select("key", "size", "lead", cell), "groups")
    cells = groups.groupBy("size", "cell").agg(F.count("*").alias("n"))
    before = F.coalesce(F.sum("n").over(Window.partitionBy("size").orderBy("cell").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    starts = cells.select("size", "cell", before.alias("before"))
    inside = F.row_number().over(Window.partitionBy("size", "cell").orderBy(spread_id(F.col("lead")), F.col("lead").asc_nulls_first(), "key"))
    ranked = groups.join(starts, ["size", "cell"]).select("key", "size", (F.col("before") + inside - 1).alias("rank"))

    def plan(table: pd.DataFrame) -> pd.DataFrame:
        table = table.sort_values("size", ascending=False)
        runs = schedule(list(zip(table["size"].tolist(), table["n"].tolist())), shards)
        return pd.DataFrame({"size": [r[0] for r in runs], "low": [r[1] for r in runs], "high": [r[2] for r in runs], "pattern": [r[3] for r in runs]})

    histogram = groups.groupBy("size").agg(F.count("*").alias("n")).withColumn("one", F.lit(1))
    runs = histogram.groupBy("one").applyInPandas(plan, "size long, low long, high long, pattern array<int>")
    pick = F.element_at("pattern", (F.pmod(F.col("rank") - F.col("low"), F.size("pattern").cast("long")) + 1).cast("int"))
    placed = ranked.join(runs, "size").where("rank >= low and rank < high").select("key", F.col("size").alias("group_size"), pick.cast("long").alias("shard"))
    return rows.join(placed, "key").select("doc_id", "group_size", "shard")
