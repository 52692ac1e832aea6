"""Set algebra in Catalyst: degrees without Python, inside generated code."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..graph import Graph, bits


def signed(mask: int) -> int:
    """A 64-bit mask as a signed long."""
    return mask - (1 << 64) if mask >> 63 else mask


def members(mask: Column) -> Column:
    """Sorted vertices of a set column (one long)."""
    every = F.sequence(F.lit(0), F.lit(63))
    return F.filter(every, lambda v: F.getbit(mask, v) == 1)


def has(mask: Column, v: int) -> Column:
    return mask.bitwiseAND(F.lit(signed(1 << v))) != 0


def reach_expr(s: Column, v: int, graph: Graph) -> Column:
    """Set met from v through s: rounds of adding the neighbours of met vertices in s, until nothing is new."""
    table = F.array(*[F.lit(signed(m)) for m in graph.masks])

    def grow(met: Column, _: Column) -> Column:
        # Neighbours of every met vertex inside s, as one fold over the vertices.
        return F.aggregate(F.sequence(F.lit(0), F.lit(graph.n - 1)), met, lambda acc, u: F.when(F.getbit(met.bitwiseAND(s), u) == 1, acc.bitwiseOR(F.element_at(table, u + 1))).otherwise(acc))

    rounds = F.sequence(F.lit(1), F.greatest(F.bit_count(s), F.lit(1)))
    return F.aggregate(rounds, F.lit(signed(graph.masks[v])).cast("long"), grow)


def degree_expr(s: Column, v: int, graph: Graph) -> Column:
    """|Q(s, v)|: vertices outside s that v reaches directly or through s. Graphs of at most 64 vertices."""
    outside = reach_expr(s, v, graph).bitwiseAND(F.bitwise_not(s)).bitwiseAND(F.lit(signed((1 << 64) - 1 & ~(1 << v))))
    return F.bit_count(outside)


def degree_frame(frame: DataFrame, graph: Graph) -> DataFrame:
    """Rows (s0, v, degree) for every set of a frame and every vertex outside it."""
    choices = F.array(*[F.when(~has(F.col("s0"), v), F.struct(F.lit(v).alias("v"), degree_expr(F.col("s0"), v, graph).alias("degree"))) for v in range(graph.n)])
    return frame.select("s0", F.explode(choices).alias("c")).where("c is not null").select("s0", "c.v", "c.degree")


def expand_frame(frame: DataFrame, graph: Graph, k: int, clique: int = 0) -> DataFrame:
    """Feasible supersets by one vertex, as expressions only: (s0, last, ways)."""
    free = [v for v in range(graph.n) if not clique >> v & 1]
    s = F.col("s0")
    choices = F.array(*[F.when(~has(s, v) & (degree_expr(s, v, graph) <= k), F.lit(v)) for v in free])
    chosen = frame.select("s0", "last", F.explode(F.filter(choices, lambda x: x.isNotNull())).alias("v"))
    return chosen.select(s.bitwiseOR(F.expr("shiftleft(1L, v)")).alias("s0"), F.expr("shiftleft(last, 8) | v").alias("last"), F.lit(1).cast("long").alias("ways"))


def vertex_list(mask: int) -> list[int]:
    return bits(mask)
