"""Readers and writers of edge tables and results, and a data source of named graphs."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from ..graph import normalize_edges
from . import named


def read_edges(spark: SparkSession, path: str, fmt: str = "text") -> tuple[DataFrame, DataFrame]:
    """(edges, vertices) of an edge list.

    'text' takes two labels a line; 'dimacs' lines like ``e 1 2`` or ``p edge``; 'gr' lines
    ``1 2`` after a ``p tw`` line; 'csv' and 'json' columns a and b; lines of other form are comments.
    """
    if fmt == "csv":
        raw = spark.read.schema("a string, b string").option("header", True).csv(path)
    elif fmt == "json":
        raw = spark.read.schema("a string, b string").json(path)
    elif fmt == "parquet":
        raw = spark.read.parquet(path).select("a", "b")
    else:
        pattern = r"^\s*e\s+(\d+)\s+(\d+)" if fmt == "dimacs" else r"^\s*(\d+)\s+(\d+)\s*$" if fmt == "gr" else r"^\s*([^\s#]+)\s+(\S+)\s*$"
        cast = "long" if fmt in ("dimacs", "gr") else "string"
        lines = spark.read.text(path).where(F.col("value").rlike(pattern))
        raw = lines.select(F.regexp_extract("value", pattern, 1).cast(cast).alias("a"), F.regexp_extract("value", pattern, 2).cast(cast).alias("b"))
    return normalize_edges(raw)


def save_runs(runs: DataFrame, path: str, fmt: str = "parquet") -> None:
    runs.write.mode("overwrite").format(fmt).save(path)


def export_graph(edges: DataFrame, path: str, fmt: str = "gr") -> None:
    """Edge lines as text: 'gr' (from 1, one graph) or 'dot' (edges of all graphs)."""
    line = F.concat_ws(" ", (F.col("u") + 1).cast("string"), (F.col("v") + 1).cast("string")) if fmt == "gr" else F.concat("graph_id", F.lit("_"), "u", F.lit(" -- "), "graph_id", F.lit("_"), "v", F.lit(";"))
    edges.select(line.alias("value")).write.mode("overwrite").text(path)


class NamedGraphSource(DataSource):
    """spark.read.format("named_graph").option("kind", "queen").option("a", 5).load()"""

    @classmethod
    def name(cls) -> str:
        return "named_graph"

    def schema(self) -> str:
        return "graph_id string, u int, v int"

    def reader(self, schema) -> DataSourceReader:
        return NamedGraphReader(self.options)


class NamedGraphReader(DataSourceReader):
    def __init__(self, options):
        self.kind = options["kind"]
        self.arguments = [int(options[x]) for x in ("a", "b") if x in options]

    def partitions(self) -> list[InputPartition]:
        return [InputPartition(k) for k in range(4)]

    def read(self, partition):
        graph = named.KINDS[self.kind](*self.arguments)
        for u, v in graph.edges():
            if u % 4 == partition.value:
                yield graph.name, u, v
