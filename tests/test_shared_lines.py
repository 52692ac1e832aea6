"""Queries of documents that share lines, where components are large or hard."""

import random
from itertools import combinations

import numpy as np
import pytest
from pyspark.sql.classic.dataframe import DataFrame

import __spark_entry__ as entry
from elimspark import api
from elimspark.graph import Graph
from elimspark.operators import bounds, covers, local, prep
from elimspark.sources import builders, named


def documents(spark, folder, edges):
    """One line of 90 signs for each group of documents."""
    held = {}
    for k, pair in enumerate(edges):
        for v in pair:
            held.setdefault(v, []).append(f"{k:090d}")
    spark.createDataFrame([(v, "\n".join(x)) for v, x in held.items()], "doc_id long, text string").write.parquet(f"{folder}/documents.parquet")


def test_a_width_that_was_not_found_is_no_row(spark, tmp_path, monkeypatch):
    """There was a row without a width."""
    documents(spark, tmp_path, named.cycle(5).edges())
    monkeypatch.setattr(covers, "solve", lambda *_: (None, 3, "too_large"))
    with pytest.raises(Exception, match="no exact width of graph g/0: too_large, at least 3"):
        entry.queries()["tw_docline80_batch"](spark, str(tmp_path)).collect()


def test_a_graph_that_left_its_task_is_no_row(spark):
    runs = api.batch_widths(named.edge_frame(spark, named.queen(5), named.cycle(5)), api.Options(task_limit=20))
    assert {r.status for r in runs.collect()} == {"deferred", "exact"}
    with pytest.raises(Exception, match="no exact width of graph queen5_5: deferred"):
        api.exact_widths(runs).collect()


def random_cover(seed):
    """(lines, vertices, graph) of a few lines and documents."""
    rng = random.Random(seed)
    n = rng.randint(4, 12)
    held = {tuple(sorted(rng.sample(range(n), rng.choice([2, 2, 3, 3, 4])))) for _ in range(rng.randint(1, 12))}
    place = {v: k for k, v in enumerate(sorted({v for x in held for v in x}))}
    rows = np.array([(k, place[v]) for k, x in enumerate(sorted(held)) for v in x])
    return rows[:, 0], rows[:, 1], Graph.of(len(place), {(place[a], place[b]) for x in held for a, b in combinations(x, 2)})


@pytest.mark.parametrize("seed", range(200))
def test_covers_give_what_their_graphs_give(seed):
    lines, vertices, graph = random_cover(seed)
    width, low = covers.Cover(lines, vertices).greedy()
    true = local.subset_dp(graph)[0]
    assert width == bounds.greedy_order(graph, "degree")[0] and low <= true
    assert sorted(covers.Cover(lines, vertices).simplicial()) == [v for v in range(graph.n) if prep.is_clique(graph, graph.masks[v])]
    masks, weights = covers.Cover(lines, vertices).kernel()
    assert not masks or covers.Search(masks, weights, 1 << 20).width(0, graph.n) == local.subset_dp(covers.expanded(masks, weights))[0]
    if len(prep.parts_without(graph, 0)) == 1:
        assert covers.solve(lines, vertices) == (true, true, "exact")


def test_a_cover_that_leaves_its_task_is_walked(spark):
    """A budget of one state: the search gives up, the walk of the cluster takes over."""
    edges = named.queen(5).edges()
    cover = spark.createDataFrame([(k, v) for k, pair in enumerate(edges) for v in pair], "line int, vid int")
    assert covers.solve(*np.array([(k, v) for k, pair in enumerate(edges) for v in pair]).T, api.Options(task_limit=1))[2] == "deferred"
    row = covers.widths(cover, api.Options(task_limit=1)).first()
    assert (row.graph_id, row.width, row.status) == ("g/0", 18, "exact")


def test_a_large_graph_whose_bounds_meet_has_its_width(spark, tmp_path):
    """300 vertices in a prism, and a clique of six: there was a row without a width."""
    prism = [(a + k, a + (k + 1) % 150) for a in (0, 150) for k in range(150)] + [(k, k + 150) for k in range(150)]
    documents(spark, tmp_path, [*prism, (0, 300, 301, 302, 303, 304)])
    assert list(map(tuple, entry.queries()["tw_docline80_batch"](spark, str(tmp_path)).collect())) == [("g/0", 5)]


@pytest.fixture(scope="module")
def crowd(spark, tmp_path_factory):
    """A line of 3,000 documents, some of which hold others; odd rows beside them."""
    folder = tmp_path_factory.mktemp("crowd")
    rows = [(k, "x" * 90 + "\n" + "x" * 90) for k in range(3000)] + [(0, "y" * 90), (5000, "y" * 90), (5000, "z" * 90), (5001, "z" * 90 + "\n" + "x" * 80), (5002, "x" * 80)]
    spark.createDataFrame(rows + [(None, "x" * 90), (6000, None), (6001, "")], "doc_id long, text string").write.parquet(f"{folder}/documents.parquet")
    return str(folder)


def test_a_line_of_many_documents(spark, crowd):
    """4.5 million pairs, but 3,004 memberships."""
    assert list(map(tuple, entry.queries()["greedy_degree_docline80"](spark, crowd).collect())) == [("g/0", 2999)]
    assert list(map(tuple, entry.queries()["tw_docline80_batch"](spark, crowd).collect())) == [("g/0", 2999)]
    assert sorted(r.vid for r in entry.queries()["simplicial_vertices"](spark, crowd).collect()) == [*range(1, 3000), 3001]
    assert entry.queries()["edges_docline80"](spark, crowd).count() == 3000 * 2999 // 2 + 2


@pytest.mark.parametrize("pairs", [4, 64, 1 << 22])
def test_each_pair_comes_once(spark, monkeypatch, pairs):
    """Lines that overlap, in one row of work or several, and no pair in any shuffle."""
    monkeypatch.setattr(builders, "PAIRS", pairs)
    rng = random.Random(pairs)
    rows = sorted({(k, v) for k in range(40) for v in rng.sample(range(60), rng.randint(2, 20))})
    edges = builders.cover_edges(spark.createDataFrame(rows, "line int, vid int"))
    want = {p for k in range(40) for p in combinations(sorted(v for x, v in rows if x == k), 2)}
    assert sorted((r.u, r.v) for r in edges.collect()) == sorted(want)
    plan = edges._jdf.queryExecution().executedPlan().toString()
    assert "Exchange" not in plan[: plan.index("MapInArrow")]


def test_work_of_a_long_line_is_small(spark, monkeypatch):
    """A line's documents went to each row of work from its first one on: 4.5 million memberships here."""
    monkeypatch.setattr(builders, "PAIRS", 1 << 12)
    sent = []
    monkeypatch.setattr(DataFrame, "mapInArrow", lambda work, *_: sent.append(work) or work.selectExpr("0 as u", "array(0) as v"))
    builders.cover_edges(spark.range(3000).selectExpr("0 as line", "int(id) as vid"))
    sizes = [f"coalesce(size({c}), 0)" for c, kind in sent[0].dtypes if kind.startswith("array")]
    assert 3000 <= sent[0].selectExpr(f"sum({' + '.join(sizes)})").first()[0] <= 3000 * (3000 / 64 + 2)
