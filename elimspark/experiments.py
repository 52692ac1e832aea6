"""The experiments on the given tables and named graphs: python -m elimspark.experiments E1 ... --data FOLDER.

Each prints one JSON line per row. E1 general, E2 adjacency tiers, E3 one process, E4
capacity, E5 work size by tier, E6 contraction bound, E7 loop shapes, E8 Bloom filter, E9
preprocessing, E10 switches, E11 other methods, E12 orders, E13 batches of graphs.
"""

from __future__ import annotations

import argparse
import json
import random
import statistics
import sys
import time
from collections.abc import Callable, Iterator

import numpy as np
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from . import api
from .graph import Graph, mask_of
from .operators import bounds, local, measures, orders, prep
from .operators.dedup import BloomBits, bloom_fpr
from .operators.search import Run, Walk, states
from .plans.options import Options
from .sources import builders as b
from .sources import named

Row = dict


def row_of(run: Run, **more) -> Row:
    return {"graph": run.graph_id, "n": run.n, "m": run.m, "width": run.width, "status": run.status, "lower_bound": run.lower_bound, "explored": run.explored, "sec": round(run.seconds, 3), "states_per_s": round(run.states_per_s)} | more


def table_graphs(spark: SparkSession, folder: str) -> list[Graph]:
    made = {"nation2": b.nation(spark, folder, 2), "nation3": b.nation(spark, folder, 3), "brand2": b.brand(spark, folder, 2), "embed16": b.embedding(spark, folder, 16, 2), "embed24": b.embedding(spark, folder, 24, 2), "letter": b.letter(spark, folder, "en", 60)}
    return [Graph(g.n, g.masks, name) for name, (edges, _) in made.items() for g in [api.graph_of(edges)]]


def anchors() -> list[Graph]:
    return [named.queen(5), named.queen(6), named.queen(7), named.mycielski(4), named.mcgee(), named.unitary_polar()]


def general(spark: SparkSession, folder: str, options: Options | None = None) -> Iterator[Row]:
    for g in table_graphs(spark, folder) + anchors():
        yield row_of(Walk(g, options, spark).width())


def tiers(spark: SparkSession, folder: str) -> Iterator[Row]:
    for tier in ("literal", "broadcast", "join"):
        for g in (table_graphs(spark, folder)[5], named.queen(6)):
            yield row_of(Walk(g, Options(adjacency=tier, local_limit=1000), spark).width(), tier=tier)


def one_process(spark: SparkSession, folder: str) -> Iterator[Row]:
    for g in table_graphs(spark, folder) + anchors():
        alone, cluster = local.sequential(g), Walk(g, Options(local_limit=100_000), spark).width()
        yield row_of(cluster, sequential_sec=round(alone.seconds, 3), speed_up=round(alone.seconds / max(cluster.seconds, 1e-9), 2), same=alone.explored == cluster.explored)


def capacity(spark: SparkSession, folder: str) -> Iterator[Row]:
    wide, bipartite = api.graph_of(b.coactive(spark, folder, 256)[0]), api.graph_of(b.partsupp(spark, folder, 24, 24)[0])
    for g, caps in ((table_graphs(spark, folder)[4], (1_000, 10_000, 100_000)), (named.torus(5, 5), (1_000, 10_000, 100_000)), (bipartite, (1_000, 10_000)), (wide, (300, 1_000))):
        for cap in caps:
            run = Walk(g, Options(capacity=cap), spark).width()
            yield row_of(run, capacity=cap, candidate_k=run.candidate_k, overflow_k=run.overflow_k)


def repeated(jobs: dict[tuple, Callable[[], float]], times: int = 4, seed: int = 1) -> dict[tuple, tuple[float, float]]:
    """Mean and deviation of several runs of each job, in random order."""
    order = [key for key in jobs for _ in range(times)]
    random.Random(seed).shuffle(order)
    seen: dict[tuple, list[float]] = {}
    for key in order:
        seen.setdefault(key, []).append(jobs[key]())
    return {k: (statistics.mean(v), statistics.pstdev(v)) for k, v in seen.items()}


def work_size(spark: SparkSession, folder: str) -> Iterator[Row]:
    """Blocks of states on the driver's processes, and by adjacency tier on the cluster; mean of four runs in random order."""
    graphs = [named.queen(7), named.unitary_polar(), named.mcgee()]
    jobs = {(g.name, "driver", rows): (lambda g=g, r=rows: Walk(g, Options(batch_rows=r), spark).width().seconds) for g in graphs for rows in (1024, 4096, 8192, 32_768)}
    jobs |= {("queen6_6", tier, rows): (lambda t=tier, r=rows: Walk(named.queen(6), Options(adjacency=t, batch_rows=r, local_limit=4_000), spark).width().seconds) for tier in ("literal", "broadcast", "join") for rows in (1024, 8192)}
    for (name, tier, rows), (mean, spread) in repeated(jobs).items():
        yield {"graph": name, "tier": tier, "batch_rows": rows, "mean_sec": round(mean, 3), "deviation": round(spread, 3)}


def contraction(spark: SparkSession, folder: str) -> Iterator[Row]:
    for g in [*table_graphs(spark, folder)[3:], named.queen(5), named.queen(6), named.mycielski(4)]:
        plain = local.sequential(g)
        for impl in ("explicit", "implicit"):
            for rule in ("min", "second"):
                run = local.sequential(g, Options(mmw=rule, mmw_impl=impl))
                yield row_of(run, mmw=rule, impl=impl, state_ratio=round(run.explored / max(1, plain.explored), 3), time_ratio=round(run.seconds / max(plain.seconds, 1e-9), 2))


def loop_shapes(spark: SparkSession, folder: str) -> Iterator[Row]:
    for g, k, level in ((table_graphs(spark, folder)[5], 8, None), (named.queen(5), 18, None), (named.queen(6), 25, None), (named.queen(7), 35, 2), (named.unitary_polar(), 53, 2)):
        keep: dict = {}
        Walk(g, Options()).decide(k, keep, 1, level)
        level = len(keep) // 2 if level is None else level
        sets = [mask_of(s) for s in states(keep[level])]
        yield {"graph": g.name, "states": len(sets)} | measures.lockstep_cost(g, sets, measures.SHAPES)


def bloom(spark: SparkSession, folder: str) -> Iterator[Row]:
    g = named.mycielski(4)
    exact = local.sequential(g)
    keys = np.unique(np.random.default_rng(0).integers(0, 1 << 62, 200_000, dtype=np.uint64))[None]
    for size in (4, 8, 16, 24):
        for hashes in (3, 7, 11, 17):
            held = BloomBits(keys.shape[1], size, hashes)
            held.add_each(keys[:, ::2])
            seen = 1 - float(held.missing(keys[:, 1::2]).mean())
            run = local.sequential(g, Options(dedup="bloom", bloom_bits=size, bloom_hashes=hashes))
            yield {"bits_per_item": size, "hashes": hashes, "rate_half_full": seen, "formula_half_full": bloom_fpr(keys.shape[1] / 2, held.size, hashes), "formula_full": bloom_fpr(1, size, hashes), "dropped": sum(x.dropped_bloom for x in run.levels), "width": run.width, "exact_width": exact.width}


def preprocessing(spark: SparkSession, folder: str) -> Iterator[Row]:
    sets = {"nation1": b.nation(spark, folder, 1)[0], "brand1": b.brand(spark, folder, 1)[0], "brand2": b.brand(spark, folder, 2)[0]}
    lines = b.docline(spark, folder, 80)[0]
    sets["docline80"] = prep.relabelled(lines, prep.components(lines))
    for name, edges in sets.items():
        for stop in range(1, len(prep.RULES) + 1):
            rules = tuple(prep.RULES)[:stop]
            got = api.pieces(edges, rules).agg(F.count("*").alias("pieces"), F.max("n").alias("largest")).first()
            yield {"graph": name, "rules": rules[-1], "pieces": got.pieces, "largest": got.largest}


def switches(spark: SparkSession, folder: str) -> Iterator[Row]:
    for g in [table_graphs(spark, folder)[3], table_graphs(spark, folder)[5], named.queen(5)]:
        for name, options in {"all": Options(), "clique none": Options(clique="none", k0=0), "clique greedy": Options(clique="greedy"), "forced edges": Options(augment=True), "forced edges and their clique": Options(augment=True, clique_on="augmented"), "no early stop": Options(early_stop=False)}.items():
            yield row_of(local.sequential(g, options), setting=name)


def methods(spark: SparkSession, folder: str) -> Iterator[Row]:
    for g in (table_graphs(spark, folder)[3], table_graphs(spark, folder)[5]):
        width, visited = local.subset_dp(g)
        best, expanded = local.branch_and_bound(g)
        positive, met = local.positive_instances(g)
        run = local.sequential(g)
        yield {"graph": g.name, "deepening_states": run.explored, "subset_states": visited, "branch_states": expanded, "feasible_parts": met, "width": run.width, "agree": run.width == width == best == positive, "lower": bounds.mmw(g, "second"), "greedy": bounds.greedy_order(g)[0]}


def order_recovery(spark: SparkSession, folder: str) -> Iterator[Row]:
    for g in [*table_graphs(spark, folder)[3:], named.queen(5), named.mycielski(4)]:
        for method in ("levels", "parents", "rerun"):
            began = time.time()
            run, order = orders.elimination_order(g, Options(), method)
            bags = orders.tree_decomposition(g, order)
            yield {"graph": g.name, "method": method, "width": run.width, "order_width": orders.order_width(g, order), "valid": orders.check_decomposition(g, bags), "sec": round(time.time() - began, 3)}


def batches(spark: SparkSession, folder: str) -> Iterator[Row]:
    lines = b.docline(spark, folder, 80)[0]
    for name, edges in {"userstep": b.userstep(spark, folder)[0], "docline80": prep.relabelled(lines, prep.components(lines)), "benchword": b.benchword(spark, folder)[0]}.items():
        began = time.time()
        got = api.batch_widths(edges).groupBy("status").agg(F.count("*").alias("graphs"), F.max("width").alias("width"), F.sum("explored").alias("explored")).collect()
        for r in got:
            yield {"batch": name, "status": r.status, "graphs": r.graphs, "largest_width": r.width, "explored": r.explored, "sec": round(time.time() - began, 2)}


EXPERIMENTS = {"E1": general, "E2": tiers, "E3": one_process, "E4": capacity, "E5": work_size, "E6": contraction, "E7": loop_shapes, "E8": bloom, "E9": preprocessing, "E10": switches, "E11": methods, "E12": order_recovery, "E13": batches}


def main(arguments: list[str]) -> None:
    parser = argparse.ArgumentParser()
    parser.add_argument("names", nargs="+")
    parser.add_argument("--data", default="/root/testdata/sf0.01")
    chosen = parser.parse_args(arguments)
    spark = SparkSession.builder.getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    for name in chosen.names if chosen.names != ["all"] else EXPERIMENTS:
        for row in EXPERIMENTS[name](spark, chosen.data):
            print(json.dumps({"experiment": name} | row), flush=True)


if __name__ == "__main__":
    main(sys.argv[1:])
