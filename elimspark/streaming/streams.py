"""Streaming construction of graphs from events."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..graph import Graph, normalize_edges
from ..operators import local

EVENT_SCHEMA = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def read_events(spark: SparkSession, folder: str, files_per_trigger: int | None = None, pattern: str = "events.parquet") -> DataFrame:
    """The events table as a stream of files; times become instants."""
    reader = spark.readStream.schema(EVENT_SCHEMA).option("pathGlobFilter", pattern).option("recursiveFileLookup", True)
    if files_per_trigger:
        reader = reader.option("maxFilesPerTrigger", files_per_trigger)
    return reader.parquet(folder).withColumn("ts", F.col("ts").cast("timestamp"))


def windows(events: DataFrame, length: str = "1 minute", slide: str | None = None, late: str = "10 minutes") -> DataFrame:
    """Users per tumbling or sliding window; events later than ``late`` are dropped by the watermark."""
    cut = F.window("ts", length, slide) if slide else F.window("ts", length)
    return events.withWatermark("ts", late).groupBy(cut.alias("w")).agg(F.collect_set("user_id").alias("users"))


def coactive_pairs(events: DataFrame, length: str = "1 minute", late: str = "10 minutes") -> DataFrame:
    """Pairs of users with an event in the same window, each once per window."""
    users = windows(events, length, late=late)
    a = users.select(F.col("w.start").alias("start"), "users", F.explode("users").alias("a"))
    return a.select("start", "a", F.explode("users").alias("b")).where("a < b")


def near_pairs(events: DataFrame, seconds: int, late: str = "10 minutes") -> DataFrame:
    """Pairs of users with events within some seconds of each other: a stream-stream interval join."""
    # Stream joins need an equality: equal time buckets, the right side also in the two next to its own.
    bucket = lambda c: F.floor(F.unix_timestamp(c) / seconds)
    left = events.select(F.col("user_id").alias("a"), F.col("ts").alias("ta")).withWatermark("ta", late).withColumn("cell", bucket("ta"))
    right = events.select(F.col("user_id").alias("b"), F.col("ts").alias("tb")).withWatermark("tb", late)
    right = right.withColumn("near", F.explode(F.array(bucket("tb") - 1, bucket("tb"), bucket("tb") + 1)))
    near = F.expr(f"cell = near and a < b and tb >= ta - interval {seconds} seconds and tb <= ta + interval {seconds} seconds")
    return left.join(right, near).select("a", "b", "ta")


def sessions(events: DataFrame, gap: str = "30 minutes", late: str = "10 minutes") -> DataFrame:
    return events.withWatermark("ts", late).groupBy("user_id", F.session_window("ts", gap).alias("s")).agg(F.count("*").alias("events"), F.collect_set("event_type").alias("kinds"))


def distinct_edges(events: DataFrame, late: str = "10 minutes") -> DataFrame:
    """(minute, a, b): users with an event in the same minute, each pair once per minute.

    Repeats go before the join, by user and minute, so the join's state holds one row each.
    """

    def once(user: str) -> DataFrame:
        seen = events.select(F.col("user_id").alias(user), F.date_trunc("minute", "ts").alias(f"m{user}"), F.col("ts").alias(f"t{user}"))
        return seen.withWatermark(f"t{user}", late).dropDuplicatesWithinWatermark([user, f"m{user}"])

    near = F.expr("ma = mb and a < b and tb >= ta - interval 60 seconds and tb <= ta + interval 60 seconds")
    return once("a").join(once("b"), near).select(F.col("ma").alias("minute"), "a", "b")


def _step_widths(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
    """Keeps a user's transition graph and last event type; emits the width when it changes."""
    last, width, pairs = state.get if state.exists else ("", -1, "")
    edges = {tuple(p.split(">")) for p in pairs.split("|") if p}
    for frame in frames:
        for kind in frame.sort_values(["ts", "event_id"])["event_type"]:
            if last and kind != last:
                edges.add((min(last, kind), max(last, kind)))
            last = kind
    names = sorted({x for e in edges for x in e})
    graph = Graph.of(len(names), [(names.index(a), names.index(b)) for a, b in edges])
    now = local.solve(graph).width if edges else 0
    state.update((last, now, "|".join(f"{a}>{b}" for a, b in sorted(edges))))
    if now != width:
        yield pd.DataFrame({"user_id": [key[0]], "edges": [len(edges)], "width": [now]})


def user_widths(events: DataFrame) -> DataFrame:
    """(user_id, edges, width) whenever a user's transition graph changes its width."""
    return events.select("user_id", "event_id", "ts", "event_type").groupBy("user_id").applyInPandasWithState(_step_widths, "user_id long, edges long, width long", "last string, width long, pairs string", "update", GroupStateTimeout.NoTimeout)


def solve_batches(pairs: DataFrame, sink: Callable[[DataFrame, int], None]):
    """Widths of each micro-batch's graph, handed to a sink; all available data, then stop."""
    from ..api import batch_widths
    from ..operators.prep import components, relabelled

    def each(batch: DataFrame, number: int) -> None:
        edges = normalize_edges(batch.select("a", "b"))[0].persist()
        if edges.limit(1).count():
            sink(batch_widths(relabelled(edges, components(edges))), number)
        edges.unpersist()

    return pairs.writeStream.foreachBatch(each).trigger(availableNow=True).start()
