"""Width by iterative deepening over sets of removed vertices.

For a target k the walk goes level by level: level i holds the sets of i vertices that can
be removed in some order without ever meeting a current degree above k. A level is
expanded, infeasible candidates fall inside the kernel, and equal sets become one. Small
levels run on the driver with the same kernel; beyond ``local_limit`` states a level is a
DataFrame (s0.., last, ways) in the shared folder, and one level is one plan:
scan, expansion in Arrow batches, partial aggregation, one exchange, final aggregation.
Frontier columns: ``s0``.. the set, ``last`` the last four removed vertices, ``ways`` how
many sets it came from.
"""

from __future__ import annotations

import itertools
import time
import uuid
from collections.abc import Iterator
from contextlib import contextmanager
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Observation, SparkSession
from pyspark.sql import functions as F

from ..graph import MAX_VERTICES, Graph, bits
from ..plans.options import Options
from ..storage import LevelStore
from . import bounds, crew, kernels, reduce
from .dedup import sift_rows

U64 = np.uint64
#: States from which a level that is kept goes to the store.
KEEP_LOCAL = 100_000
#: States of one task, about, when a level moves from the driver to the cluster; later levels follow their partitions.
TASK_STATES = 1 << 14


@dataclass
class Level:
    """Counts and costs of one level of one walk.

    ``bytes`` is the level's size in memory or in the store; what a distributed level
    shuffled and spilled and its longest task over the median one are in the last three.
    """

    graph_id: str
    k: int
    level: int
    expanded: int
    generated: int
    feasible: int
    kept: int
    dropped_capacity: int = 0
    dropped_bloom: int = 0
    pruned_mmw: int = 0
    seconds: float = 0.0
    bytes: int = 0
    shuffle_bytes: int = 0
    spill_bytes: int = 0
    skew: float = 1.0


@dataclass
class Run:
    """Result of a width search."""

    graph_id: str
    n: int
    m: int
    clique: int
    width: int | None = None
    lower_bound: int = 0
    candidate_k: int | None = None
    overflow_k: int | None = None
    status: str = "exact"
    explored: int = 0
    seconds: float = 0.0
    prep_seconds: float = 0.0
    opts: str = ""
    levels: list[Level] = field(default_factory=list)

    @property
    def states_per_s(self) -> float:
        return self.explored / self.seconds if self.seconds else 0.0


RUN_SCHEMA = "graph_id string, n int, m long, clique int, width int, lower_bound int, candidate_k int, overflow_k int, status string, explored long, seconds double, prep_seconds double, opts string"
LEVEL_SCHEMA = "graph_id string, k int, level int, expanded long, generated long, feasible long, kept long, dropped_capacity long, dropped_bloom long, pruned_mmw long, seconds double, bytes long, shuffle_bytes long, spill_bytes long, skew double"


def row_hash(sets: np.ndarray) -> np.ndarray:
    """Spark's xxhash64 of the words of each set, so that driver and cluster order states alike."""
    p1, p2, p3, p4, p5 = (U64(x) for x in (0x9E3779B185EBCA87, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0x85EBCA77C2B2AE63, 0x27D4EB2F165667C5))
    turn = lambda x, r: x << U64(r) | x >> U64(64 - r)
    h = np.full(sets.shape[1], 42, U64)
    for word in sets:
        h = h + p5 + U64(8)
        h ^= turn(word * p2, 31) * p1
        h = turn(h, 27) * p1 + p4
        h = (h ^ h >> U64(33)) * p2
        h = (h ^ h >> U64(29)) * p3
        h ^= h >> U64(32)
    return h.view(np.int64)


def level_arrays(batches: list[pa.RecordBatch], names: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(sets, last, ways) of Arrow batches of a level."""
    table = pa.Table.from_batches(batches)
    sets = np.stack([np.asarray(table.column(s)).astype(np.int64).view(U64) for s in names])
    return sets, np.asarray(table.column("last")).astype(np.int32), np.asarray(table.column("ways")).astype(np.int64)


@contextmanager
def measured(spark: SparkSession, row: Level) -> Iterator[None]:
    """Adds to a level what the jobs of the block shuffled and spilled, and their longest task over the median one."""
    context = spark.sparkContext
    group = f"elimspark-{uuid.uuid4().hex}"
    before = {k: context.getLocalProperty(k) for k in ("spark.jobGroup.id", "spark.job.description", "spark.job.interruptOnCancel")}
    context.setJobGroup(group, f"level {row.level} at {row.k}")
    try:
        yield
    finally:
        for k, v in before.items():
            context.setLocalProperty(k, v)
    context._jsc.sc().listenerBus().waitUntilEmpty()
    store, tracker = context._jsc.sc().statusStore(), context.statusTracker()
    quantiles = context._gateway.new_array(context._jvm.double, 2)
    quantiles[0], quantiles[1] = 0.5, 1.0
    for job in tracker.getJobIdsForGroup(group):
        info = tracker.getJobInfo(job)
        for stage in info.stageIds if info else ():
            data = store.lastStageAttempt(stage)
            if data.status().toString() != "COMPLETE":
                continue
            row.shuffle_bytes += data.shuffleWriteBytes()
            row.spill_bytes += data.diskBytesSpilled()
            times = store.taskSummary(stage, data.attemptId(), quantiles)
            if not times.isEmpty():
                half, top = (times.get().executorRunTime().apply(j) for j in (0, 1))
                row.skew = max(row.skew, top / max(half, 1.0))


class LevelTooWide(Exception):
    """A task's walk met a level beyond its limit."""


class Walk:
    """Walks of one graph, on the driver or on the cluster."""

    def __init__(self, graph: Graph, options: Options | None = None, spark: SparkSession | None = None):
        self.graph, self.o, self.spark = graph, options or Options(), spark
        if graph.n > MAX_VERTICES:
            raise ValueError(f"{graph.n} vertices; at most {MAX_VERTICES}, split the graph first")
        if self.o.dedup == "none" and graph.n > 9:
            raise ValueError("without duplicate removal at most 9 vertices")
        self.clique = reduce.clique_mask(graph, self.o.clique)
        self.paths = reduce.all_disjoint_paths(graph) if self.o.augment or self.o.clique_on == "augmented" else {}
        self.names = [f"s{w}" for w in range(graph.words)]
        self.store: LevelStore | None = None

    def target(self, k: int) -> tuple[Graph, int]:
        """Graph and clique for a target."""
        graph = reduce.augment(self.graph, self.paths, k) if self.paths else self.graph
        if self.o.clique_on == "augmented":
            return graph, reduce.clique_mask(graph, self.o.clique)
        return graph, self.clique

    def decide(self, k: int, keep: dict | None = None, every: int = 1, most: int | None = None) -> tuple[bool, list[Level], bool]:
        """(is the width at most k, level counts, was a level cut).

        ``keep`` gets the frontiers by level: the last level and each that is a multiple of
        ``every`` levels before it; with every=0 the last level alone. ``most`` ends the walk early.
        """
        graph, clique = self.target(k)
        n, size = graph.n, clique.bit_count()
        rounds = n - k - 1 if self.o.early_stop else n - size
        rounds = min(rounds, n - size)
        sets = np.zeros((graph.words, 1), U64)
        front: tuple | DataFrame = (sets, np.zeros(1, np.int32), np.ones(1, np.int64))
        count, levels, cut = 1, [], False
        if size > k + 1 and most is None:
            # A clique of k + 2 vertices refutes the target by itself.
            return False, levels, cut
        rounds = max(0, rounds if most is None else min(rounds, most))
        held = lambda level: keep is not None and (level == rounds or every > 0 and (rounds - level) % every == 0)
        if held(0):
            keep[0] = front
        for level in range(rounds):
            began = time.time()
            row = Level(graph.name, k, level, count, count * (n - level - size), 0, 0)
            if isinstance(front, tuple) and (self.spark is None or count <= self.o.local_limit):
                front = self._local(front, graph, k, clique, row)
            else:
                front = self._spread(front, graph, k, clique, row)
            count = row.kept
            if self.o.capacity is not None and count > self.o.capacity:
                front, cut = self._cut(front, count), True
                row.dropped_capacity, row.kept, count = count - self.o.capacity, self.o.capacity, self.o.capacity
            row.seconds = time.time() - began
            levels.append(row)
            if held(level + 1):
                keep[level + 1] = front = self._kept(front, k, level) if count > KEEP_LOCAL else front
            if self.store is not None and level > 0 and not held(level):
                self.store.drop(k, level - 1)
            if not count:
                return False, levels, cut
            if not isinstance(front, tuple) and count <= self.o.local_limit // 2:
                front = self._gather(front)
        return True, levels, cut

    def _kept(self, front, k: int, level: int):
        """A level that is kept goes to the store, where there is one."""
        if not isinstance(front, tuple) or self.spark is None:
            return front
        if self.store is None:
            self.store = LevelStore(self.spark)
        return self.store.write(self.frame(front), k, level)

    def _local(self, front: tuple, graph: Graph, k: int, clique: int, row: Level) -> tuple:
        kernel = "prefix" if self.o.kernel == "expr" else self.o.kernel
        if self.spark is None and row.expanded > self.o.task_limit:
            raise LevelTooWide(f"level {row.level} of {graph.name} at {k}")
        if self.spark is not None and row.expanded >= 2 * crew.SLAB and self.o.dedup != "none":
            found, row.pruned_mmw = crew.expand(front[0], front[1], graph.table(), k, clique, kernel, (self.o.mmw, self.o.mmw_impl), self.o.block(graph.n))
            sets, last, ways = kernels.fold_runs(found)
        else:
            bound = bounds.state_bound(k, self.o.mmw, self.o.mmw_impl)
            sets, last, ways, row.pruned_mmw = kernels.expand(front[0], front[1], graph.table(), k, clique, kernel, bound, self.o.block(graph.n))
            if self.o.dedup != "none":
                sets, last, ways = kernels.fold(sets, last, ways)
        row.feasible = int(ways.sum())
        if self.o.dedup == "bloom" and len(ways):
            shards, items = self.filters(row.expanded)
            h = row_hash(sets)
            shard = np.mod(h, shards)
            order = np.lexsort((*sets.view(np.int64)[::-1], h, shard))
            out = list(sift_rows([(shard[order], sets[:, order], last[order], ways[order])], items, self.o.bloom_bits, self.o.bloom_hashes))
            sets, last, ways, lost = (np.concatenate([x[j] for x in out], -1) for j in range(4))
            row.dropped_bloom = int(lost.sum())
            sets, last, ways = kernels.fold(sets, last, ways)
        row.kept = sets.shape[1]
        row.bytes = sets.nbytes + last.nbytes + ways.nbytes
        return sets, last, ways

    @staticmethod
    def filters(expanded: int) -> tuple[int, int]:
        """(Bloom filters, items of each) of a level: by the states it expands, wherever it runs."""
        shards = max(1, -(-4 * expanded // (1 << 20)))
        return shards, max(1 << 10, -(-4 * expanded // shards))

    def schema(self) -> str:
        return ", ".join(f"{s} long" for s in self.names) + ", last int, ways long"

    def frame(self, front: tuple) -> DataFrame:
        sets, last, ways = front
        table = pa.table({**{s: pa.array(sets[w].view(np.int64)) for w, s in enumerate(self.names)}, "last": pa.array(last), "ways": pa.array(ways)})
        return self.spark.createDataFrame(table)

    def _gather(self, frame: DataFrame) -> tuple:
        table = frame.toArrow()
        sets = np.stack([np.asarray(table.column(s)).astype(np.int64).view(U64) for s in self.names])
        return sets, np.asarray(table.column("last")).astype(np.int32), np.asarray(table.column("ways")).astype(np.int64)

    def expanded(self, frame: DataFrame, graph: Graph, k: int, clique: int) -> DataFrame:
        """Feasible candidates of a level: no shuffle."""
        options, names = self.o, self.names
        if options.kernel == "expr":
            from ..functions.bits import expand_frame

            return expand_frame(frame, graph, k, clique)
        table = graph.table()
        tier, block = options.adjacency, options.block(graph.n)
        held = self.spark.sparkContext.broadcast(table) if tier == "broadcast" else None
        if tier == "join":
            row = self.spark.createDataFrame([(bytes(table.tobytes()),)], "adj binary")
            frame = frame.crossJoin(F.broadcast(row))

        def run(batches):
            bound = bounds.state_bound(k, options.mmw, options.mmw_impl)
            # Several batches at once, sorted: sets that share a prefix share work, and repeats meet before the shuffle.
            waiting, rows = [], 0
            for batch in itertools.chain(batches, [None]):
                if batch is not None and batch.num_rows:
                    waiting.append(batch)
                    rows += batch.num_rows
                if not waiting or batch is not None and rows < TASK_STATES:
                    continue
                here = table if tier == "literal" else held.value if tier == "broadcast" else np.frombuffer(waiting[0].column("adj")[0].as_py(), U64).reshape(len(names), -1)
                sets, last, _ = level_arrays(waiting, names)
                waiting, rows = [], 0
                order = np.lexsort(sets)
                out, last, ways, _ = kernels.expand(sets[:, order], last[order], here, k, clique, options.kernel, bound, block)
                if options.combine:
                    out, last, ways = kernels.fold(out, last, ways)
                yield pa.RecordBatch.from_arrays([*(pa.array(out[w].view(np.int64)) for w in range(len(names))), pa.array(last), pa.array(ways)], [*names, "last", "ways"])

        return frame.mapInArrow(run, self.schema())

    def parts(self, count: int) -> int:
        """Tasks for ``count`` states: one per TASK_STATES, at most those of the session's shuffles or cores."""
        most = max(int(self.spark.conf.get("spark.sql.shuffle.partitions")), 2 * self.spark.sparkContext.defaultParallelism)
        return self.o.partitions or max(1, min(most, -(-count // TASK_STATES)))

    def deduplicated(self, candidates: DataFrame, expected: int) -> DataFrame:
        """One row per set: the one shuffle of a level."""
        if self.o.dedup == "none":
            return candidates
        parts = self.parts(expected)
        if self.o.dedup == "exact":
            if self.o.partitions:
                candidates = candidates.repartition(parts, *self.names)
            return candidates.groupBy(*self.names).agg(F.min("last").alias("last"), F.sum("ways").alias("ways"))
        names, options = self.names, self.o
        shards, items = self.filters(expected)

        def run(batches):
            read = ((np.asarray(b.column("shard")), *level_arrays([b], names)) for b in batches if b.num_rows)
            for sets, last, ways, lost in sift_rows(read, items, options.bloom_bits, options.bloom_hashes):
                yield pa.RecordBatch.from_arrays([*(pa.array(sets[w].view(np.int64)) for w in range(len(names))), pa.array(last), pa.array(ways), pa.array(lost)], [*names, "last", "ways", "lost"])

        hashed = candidates.withColumn("h", F.xxhash64(*names)).withColumn("shard", F.pmod("h", F.lit(shards)))
        sorted_rows = hashed.repartition(min(parts, shards), "shard").sortWithinPartitions("shard", "h", *names, "last").drop("h")
        return sorted_rows.mapInArrow(run, self.schema() + ", lost long")

    def _spread(self, front, graph: Graph, k: int, clique: int, row: Level) -> DataFrame:
        if self.store is None:
            self.store = LevelStore(self.spark)
        if isinstance(front, tuple):
            front = self.frame(front).repartition(self.parts(row.expanded))
        new = self.deduplicated(self.expanded(front, graph, k, clique), row.expanded)
        # Counted while it is written: by the tasks of the write alone, each of which counts once.
        seen = Observation()
        lost = F.sum("lost") if "lost" in new.columns else F.lit(0).cast("long")
        new = new.observe(seen, F.count(F.lit(1)).alias("kept"), F.sum("ways").alias("feasible"), F.max(lost).alias("lost") if "lost" not in new.columns else lost.alias("lost"))
        with measured(self.spark, row):
            kept = self.store.write(new.select(*self.names, "last", "ways"), k, row.level)
        counts = seen.get
        row.kept, row.feasible, row.dropped_bloom = counts["kept"], counts["feasible"] or 0, counts["lost"] or 0
        row.bytes = self.store.bytes(k, row.level)
        return kept

    def _cut(self, front, count: int):
        """The capacity's states with the least hashes, the same ones wherever the level is."""
        most = self.o.capacity
        if isinstance(front, tuple):
            stay = np.sort(np.lexsort((*front[0].view(np.int64)[::-1], row_hash(front[0])))[:most])
            return front[0][:, stay], front[1][stay], front[2][stay]
        keyed = front.select(F.xxhash64(*self.names).alias("h"), *self.names)
        # 4,096 counts find the bucket of the last state that stays; only that bucket is sorted.
        bucket = F.shiftright("h", 52)
        left = most
        for b, here in sorted((r.b, r.n) for r in keyed.groupBy(bucket.alias("b")).agg(F.count("*").alias("n")).collect()):
            if left <= here:
                break
            left -= here
        order = ["h", *self.names]
        last = keyed.where(bucket == b).orderBy(*order).limit(left).agg(F.max(F.struct(*order)).alias("x")).first().x
        limit = F.struct(*[F.lit(v).cast("long").alias(c) for c, v in zip(order, last)])
        return front.where(F.struct(F.xxhash64(*self.names).alias("h"), *self.names) <= limit)

    def width(self, keep: dict | None = None, every: int = 1) -> Run:
        """Try k after k until a walk survives; ``keep`` gets its frontiers, see decide()."""
        g, began = self.graph, time.time()
        run = Run(g.name, g.n, g.m, self.clique.bit_count(), opts=self.o.json())
        if not g.n or not g.m:
            run.width, run.seconds = (0 if g.n else -1), time.time() - began
            return run
        k = max(0, run.clique - 1) if self.o.k0 == "clique" else int(self.o.k0)
        run.lower_bound = max(0, run.clique - 1)
        try:
            while True:
                if self.o.k_max is not None and k > self.o.k_max:
                    run.status, run.candidate_k = "lower_bound", k
                    break
                if run.overflow_k is not None:
                    # A level was cut at a smaller target: its refutation is not certain, so the search ends.
                    run.status, run.candidate_k = "lower_bound", k
                    break
                held = {} if keep is not None else None
                good, levels, cut = self.decide(k, held, every)
                run.levels += levels
                run.explored += sum(x.expanded for x in levels)
                if cut:
                    run.overflow_k = k
                if good:
                    run.width = run.lower_bound = k
                    run.status = "exact_after_overflow" if cut else "exact_whp" if self.o.dedup == "bloom" else "exact"
                    if keep is not None:
                        keep.update(held)
                    break
                if not cut:
                    run.lower_bound = k + 1
                k += 1
        finally:
            if self.store is not None and keep is None:
                self.store.drop()
        run.seconds = time.time() - began
        return run


def width_of(graph: Graph, options: Options | None = None, spark: SparkSession | None = None) -> Run:
    return Walk(graph, options, spark).width()


def states(front: tuple) -> list[list[int]]:
    """Vertex lists of a driver-side frontier."""
    return [bits(sum(int(front[0][w, i]) << 64 * w for w in range(len(front[0])))) for i in range(front[0].shape[1])]
