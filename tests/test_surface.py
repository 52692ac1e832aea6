"""SQL functions, readers and writers, streaming."""

import shutil

import pytest
from pyspark.sql import functions as F

from elimspark import api
from elimspark.functions import udfs
from elimspark.graph import normalize_edges
from elimspark.operators import local
from elimspark.sources import builders, io, named
from elimspark.streaming import streams

SMALL = "/root/testdata/sf0.001"


def test_sql_functions(spark):
    udfs.register(spark)
    named.edge_frame(spark, named.cycle(5), named.complete(4)).createOrReplaceTempView("edges")
    got = {r.graph_id: r.w for r in spark.sql("select graph_id, local_treewidth(u, v) as w from edges group by graph_id").collect()}
    assert got == {"C5": 2, "K4": 3}
    assert spark.sql("select * from named_graph('queen', 4, 0)").count() == named.queen(4).m
    levels = spark.sql("select * from treewidth_levels('cycle', 6, 0, 2)").collect()
    assert levels[0].expanded == 1
    order = spark.sql("select * from elimination_orders('grid', 3, 3)").collect()
    assert len(order) == 9 and max(r.deg for r in order) == 3
    masks = spark.sql("select edges_to_masks(u, v) as m from edges where graph_id = 'K4'").first().m
    assert masks == [14, 13, 11, 7]


def test_vectorised_degree(spark):
    g = named.grid(3, 3)
    frame = spark.createDataFrame([(0, 4), (16, 1), (18, 0)], "s long, v int")
    from elimspark.operators.orders import reached

    got = [r.d for r in frame.select(udfs.degree_udf(g)("s", "v").alias("d")).collect()]
    assert got == [reached(g, s, v).bit_count() for s, v in ((0, 4), (16, 1), (18, 0))]
    fine = [r.f for r in frame.select(udfs.feasible_udf(g, 4)("s", "v").alias("f")).collect()]
    assert fine == [d <= 4 for d in got]


@pytest.mark.parametrize("fmt", ["text", "dimacs", "gr", "csv", "json", "parquet"])
def test_readers(spark, tmp_path, fmt):
    path = str(tmp_path / "in")
    lines = {"text": ["# c", "x y", "y z"], "dimacs": ["c x", "p edge 3 2", "e 1 2", "e 2 3"], "gr": ["p tw 3 2", "1 2", "2 3"]}
    if fmt in lines:
        spark.createDataFrame([(x,) for x in lines[fmt]], "value string").write.text(path)
    else:
        writer = spark.createDataFrame([("x", "y"), ("y", "z")], "a string, b string").write
        writer.option("header", True).csv(path) if fmt == "csv" else writer.format(fmt).save(path)
    edges, _ = io.read_edges(spark, path, fmt)
    assert sorted((r.u, r.v) for r in edges.collect()) == [(0, 1), (1, 2)]


def test_writers_and_source(spark, tmp_path):
    edges = named.edge_frame(spark, named.cycle(5))
    io.export_graph(edges, str(tmp_path / "g"))
    back, _ = io.read_edges(spark, str(tmp_path / "g"), "gr")
    assert api.graph_of(back).masks == named.cycle(5).masks
    for fmt in ("parquet", "json", "csv", "orc"):
        io.save_runs(api.batch_widths(edges), str(tmp_path / fmt), fmt)
    assert spark.read.parquet(str(tmp_path / "parquet")).first().width == 2
    spark.dataSource.register(io.NamedGraphSource)
    assert spark.read.format("named_graph").option("kind", "queen").option("a", 5).load().count() == named.queen(5).m


@pytest.fixture
def stream_folder(tmp_path):
    (tmp_path / "in").mkdir()
    shutil.copy(f"{SMALL}/events.parquet", tmp_path / "in/events.parquet")
    return str(tmp_path / "in")


def drained(frame, name, mode="append"):
    query = frame.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True).start()
    query.awaitTermination(120)
    return query


def test_streaming_pairs_and_batches(spark, stream_folder):
    events = streams.read_events(spark, stream_folder)
    drained(streams.coactive_pairs(events), "pairs")
    batch = builders.load(spark, SMALL, "events").select("user_id", F.date_trunc("minute", F.col("ts").cast("timestamp")).alias("m"), F.col("ts").cast("timestamp").alias("ts"))
    latest = batch.agg(F.max("ts")).first()[0]
    seen = batch.select("user_id", "m").distinct()
    want = {(r.m, r.a, r.b) for r in seen.withColumnRenamed("user_id", "a").join(seen.withColumnRenamed("user_id", "b"), "m").where("a < b").collect()}
    got = {(r.start, r.a, r.b) for r in spark.table("pairs").collect()}
    assert got <= want and {x for x in want if (latest - x[0]).total_seconds() > 700} <= got
    out = []
    query = streams.solve_batches(streams.coactive_pairs(events), lambda runs, n: out.extend(runs.collect()))
    query.awaitTermination(120)
    assert out and all(r.status == "exact" for r in out)


def test_streaming_state_matches_batch(spark, stream_folder):
    drained(streams.user_widths(streams.read_events(spark, stream_folder)), "widths", "update")
    got = {r.user_id: r.width for r in spark.table("widths").groupBy("user_id").agg(F.max("width").alias("width")).collect()}
    edges, _ = builders.userstep(spark, SMALL)
    assert got == {int(r.graph_id): r.width for r in api.batch_widths(edges).collect()}


def test_streaming_windows_sessions_and_joins(spark, stream_folder):
    events = streams.read_events(spark, stream_folder)
    drained(streams.sessions(events), "sessions_out")
    assert spark.table("sessions_out").count() > 0
    drained(streams.windows(events, "1 hour", "30 minutes"), "sliding")
    assert spark.table("sliding").count() > 0
    drained(streams.near_pairs(events, 60), "near")
    rows = builders.load(spark, SMALL, "events").select("user_id", F.col("ts").cast("timestamp").alias("ts")).collect()
    want = sum(1 for x in rows for y in rows if x.user_id < y.user_id and abs((x.ts - y.ts).total_seconds()) <= 60)
    assert spark.table("near").count() == want
    drained(streams.distinct_edges(events), "once")
    pairs = [(r.minute, r.a, r.b) for r in spark.table("once").collect()]
    minute = lambda r: r.ts.replace(second=0, microsecond=0)
    assert sorted(pairs) == sorted({(minute(x), x.user_id, y.user_id) for x in rows for y in rows if x.user_id < y.user_id and minute(x) == minute(y)})


def test_normalized_labels_keep_order(spark):
    edges, vertices = normalize_edges(spark.createDataFrame([("b", "a"), ("c", "b")], "a string, b string"))
    assert [r.label for r in vertices.orderBy("vid").collect()] == ["a", "b", "c"]
    assert local.sequential(api.graph_of(edges)).width == 1


def test_functions_of_tables_and_rows(spark):
    from elimspark.functions import udfs
    from elimspark.operators import orders

    udfs.register(spark)
    graphs = {g.name: g for g in (named.cycle(6), named.grid(3, 3))}
    named.edge_frame(spark, *graphs.values()).createOrReplaceTempView("some_edges")
    found = spark.sql("select * from table_orders(table(some_edges) partition by graph_id)").collect()
    for name, g in graphs.items():
        order = [r.vid for r in sorted((r for r in found if r.graph_id == name), key=lambda r: r.pos)]
        assert sorted(order) == list(range(g.n)) and orders.order_width(g, order) == local.sequential(g).width
    levels = spark.sql("select * from table_levels(table(some_edges) partition by (graph_id), 3)").collect()
    assert {r.graph_id for r in levels} == set(graphs) and all(r.expanded for r in levels)
    row = spark.sql("select graph_id, degree_of(m, 3L, 2) d, is_feasible(m, 3L, 2, 1) f from (select graph_id, edges_to_masks(u, v) m from some_edges group by graph_id)").collect()
    assert {r.graph_id: (r.d, r.f) for r in row} == {n: (orders.reached(g, 3, 2).bit_count(), orders.reached(g, 3, 2).bit_count() <= 1) for n, g in graphs.items()}
