"""Which graphs are solved in tasks and which by distributed walks, and why."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..graph import MAX_VERTICES, profile
from .options import Options

#: Graphs up to this many vertices can't leave their task: a level has at most C(20, 10) states.
TASK_VERTICES = 20


@dataclass
class SearchPlan:
    """Routes of an edge table's graphs."""

    options: Options
    graphs: int
    larger: int = 0
    refused: int = 0

    def explain(self) -> str:
        o = self.options
        return "\n".join((
            f"graphs: {self.graphs}",
            f"in tasks: all, each distinct one once; {self.larger} have over {TASK_VERTICES} vertices and leave their task for a walk on the cluster if a level passes {o.task_limit} states",
            f"beyond {MAX_VERTICES} vertices: {self.refused}, split first, refused if a piece stays that large",
            f"level: scan -> expand[{o.kernel}, k, clique={o.clique}, mmw={o.mmw}] -> fold in task={o.combine} -> exchange(set) -> {o.dedup}",
        ))


def plan(edges: DataFrame, options: Options) -> SearchPlan:
    """One row of counts, whatever the number of graphs."""
    over = lambda least: F.coalesce(F.sum((F.col("n") > least).cast("long")), F.lit(0))
    total = profile(edges).agg(F.count("*").alias("n"), over(TASK_VERTICES).alias("larger"), over(MAX_VERTICES).alias("refused")).first()
    return SearchPlan(options, total.n, total.larger, total.refused)
