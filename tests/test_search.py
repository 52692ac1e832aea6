"""The search, its variants and baselines against each other, theory and published counts."""

import random

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from elimspark import api
from elimspark.functions import bits as fbits
from elimspark.graph import Graph, mask_of
from elimspark.operators import bounds, kernels, local, measures, orders, prep, reduce
from elimspark.operators.dedup import BloomBits, bloom_fpr
from elimspark.operators.many import decide_many
from elimspark.operators.search import Walk, states, width_of
from elimspark.plans.options import Options
from elimspark.sources import named


def gnp(n, p, seed):
    rng = random.Random(seed)
    return Graph.of(n, [(u, v) for u in range(n) for v in range(u) if rng.random() < p])


graphs = st.builds(gnp, st.integers(1, 8), st.sampled_from([0.15, 0.3, 0.5, 0.8]), st.integers(0, 10**6))


@settings(max_examples=60, deadline=None)
@given(graphs)
def test_all_exact_methods_agree(g):
    width = local.brute_orders(g) if g.m else 0
    assert local.sequential(g).width == local.solve(g).width == width
    assert local.subset_dp(g)[0] == local.branch_and_bound(g)[0] == width
    assert bounds.mmw(g) <= width and bounds.mmw(g, "second") <= width <= bounds.greedy_order(g)[0]
    assert bounds.degeneracy(g) <= width <= bounds.greedy_order(g, "degree")[0]
    assert local.width_at_most_2(g) == (width <= 2)
    assert local.positive_instances(g)[0] == width
    assert [local.width_at_most(g, k)[0] for k in (1, 2, 3, 4)] == [width <= k for k in (1, 2, 3, 4)]


@settings(max_examples=25, deadline=None)
@given(graphs, st.integers(0, 10**6))
def test_kernels_and_expressions_give_the_same_degrees(g, seed):
    rng = random.Random(seed)
    sets = np.array([[mask_of(v for v in range(g.n) if rng.random() < 0.5) for _ in range(40)]], np.uint64)
    table = g.table()
    want = np.array([[orders.reached(g, int(s), v).bit_count() for s in sets[0]] for v in range(g.n)])
    outside = np.array([[not int(s) >> v & 1 for s in sets[0]] for v in range(g.n)])
    for name, kernel in kernels.KERNELS.items():
        assert (kernel(sets, table)[outside] == want[outside]).all(), name
    own = kernels.degrees_remove(sets, np.repeat(table.T[:, :, None], 40, 2))
    assert (own[outside] == want[outside]).all()
    assert all(measures.traces(g, int(s))[1] == [want[v, i] for v in range(g.n) if outside[v, i]] for i, s in enumerate(sets[0]))


@settings(max_examples=30, deadline=None)
@given(graphs)
def test_switches_never_change_the_width(g):
    width = local.sequential(g).width
    for options in (Options(clique="none", k0=0), Options(clique="greedy"), Options(early_stop=False), Options(augment=True), Options(augment=True, clique_on="augmented"), Options(mmw="min"), Options(mmw="second"), Options(mmw="second", mmw_impl="implicit"), Options(kernel="parts"), Options(kernel="search"), Options(dedup="none")):
        assert local.sequential(g, options).width == width, options


@settings(max_examples=30, deadline=None)
@given(st.builds(gnp, st.integers(8, 13), st.sampled_from([0.15, 0.25]), st.integers(0, 10**6)))
def test_splitting_keeps_the_width(g):
    width = local.sequential(g).width if g.m else 0
    for stop in range(1, len(prep.RULES) + 1):
        parts, _ = prep.split(g, tuple(prep.RULES)[:stop])
        assert max((local.sequential(p).width for p, _ in parts if p.m), default=0) == width
    assert local.solve(g).width == width
    rest, low, _ = prep.reduce_simplicial(g)
    assert max(low, local.sequential(rest).width if rest.m else 0) == width


@settings(max_examples=30, deadline=None)
@given(graphs)
def test_orders_and_decompositions_are_valid(g):
    for method in ("levels", "parents", "rerun"):
        run, order = orders.elimination_order(g, method=method)
        assert sorted(order) == list(range(g.n)) and orders.order_width(g, order) == max(run.width, 0)
    bags = orders.tree_decomposition(g, order)
    assert orders.check_decomposition(g, bags) and max(len(b) for _, _, b in bags) - 1 == max(run.width, 0)


@pytest.mark.parametrize(("graph", "width"), [(named.complete(6), 5), (named.cycle(9), 2), (named.path(12), 1), (named.grid(3, 3), 3), (named.grid(4, 4), 4), (Graph.of(5, []), 0), (Graph.of(1, []), 0), (Graph.of(6, [(u, v) for u in range(3) for v in range(3, 6)]), 3)])
def test_known_widths(graph, width):
    assert local.sequential(graph).width == local.solve(graph).width == width


@pytest.mark.parametrize(("graph", "width", "explored"), [(named.queen(5), 18, 3_134), (named.queen(6), 25, 35_973), (named.mycielski(4), 10, 97_765)])
def test_published_counts(graph, width, explored):
    run = local.sequential(graph)
    assert (run.width, run.explored) == (width, explored)
    # Forced edges leave every count as it is.
    again = local.sequential(graph, Options(augment=True))
    assert (again.width, again.explored) == (width, explored)


def test_contraction_bound_prunes_states():
    plain, pruned = local.sequential(named.queen(5)), local.sequential(named.queen(5), Options(mmw="second"))
    assert pruned.explored < plain.explored and pruned.width == plain.width
    assert sum(x.pruned_mmw for x in pruned.levels) > 0
    same = local.sequential(named.queen(5), Options(mmw="second", mmw_impl="implicit"))
    assert same.explored == pruned.explored


@settings(max_examples=40, deadline=None)
@given(graphs)
def test_disjoint_paths_equal_least_separators(g):
    from itertools import combinations

    for (u, v), count in reduce.all_disjoint_paths(g).items():
        others = [w for w in range(g.n) if w not in (u, v)]
        cut = next(k for k in range(len(others) + 1) if any(not any(p >> u & 1 and p >> v & 1 for p in prep.parts_without(g, mask_of(c))) for c in combinations(others, k)))
        assert count == cut


def test_cliques():
    for seed in range(20):
        g = gnp(9, 0.6, seed)
        from itertools import combinations

        best = next(list(c) for k in range(9, 0, -1) for c in combinations(range(9), k) if prep.is_clique(g, mask_of(c)))
        assert reduce.max_clique(g) == best and len(reduce.greedy_clique(g)) <= len(best)


def test_large_graphs_use_four_words():
    for n in (64, 65, 256):
        assert local.solve(named.path(n)).width == 1
    assert Graph.of(256, [(0, 255)]).table().shape == (4, 256)
    tree = Graph.of(70, [(k, k - 1) for k in range(1, 70)] + [(0, 69)])
    assert local.solve(tree).width == 2
    with pytest.raises(ValueError):
        Walk(named.path(257))
    dense = Graph.of(70, [e for e in named.complete(70).edges() if e not in ((0, 1), (2, 3), (4, 65))])
    run = local.sequential(dense, Options(clique="none", k0=65))
    assert dense.words == 4 and (run.width, local.sequential(dense, Options(kernel="parts")).width) == (68, 68)


def test_capacity_statuses():
    g = gnp(16, 0.35, 5)
    exact = local.sequential(g)
    tight = width_of(g, Options(capacity=5))
    assert tight.status in ("lower_bound", "exact_after_overflow") and tight.lower_bound <= exact.width
    if tight.status == "exact_after_overflow":
        assert tight.width == exact.width
    else:
        assert tight.width is None and tight.candidate_k == tight.overflow_k + 1
    assert width_of(g, Options(capacity=10**6)).status == "exact"
    assert width_of(g, Options(k_max=1)).status == "lower_bound"


def test_bloom_is_one_sided_and_near_its_formula():
    rng = np.random.default_rng(1)
    keys = np.unique(rng.integers(0, 1 << 62, 60_000, dtype=np.uint64))[None]
    for size, hashes in ((4, 3), (8, 6), (24, 17)):
        held = BloomBits(keys.shape[1], size, hashes)
        half = keys.shape[1] // 2
        held.add_each(keys[:, :half])
        assert not held.missing(keys[:, :half]).any()
        rate = 1 - held.missing(keys[:, half:]).mean()
        expected = bloom_fpr(half, held.size, hashes)
        assert abs(rate - expected) <= 3 * np.sqrt(expected * (1 - expected) / half) + 0.1 * expected + 1e-4
    assert 5e-6 < bloom_fpr(1, 24, 17) < 2e-5
    assert local.sequential(named.mycielski(4), Options(dedup="bloom")).width >= 10


def test_lockstep_shapes():
    g = named.queen(4)
    keep: dict = {}
    Walk(g, Options()).decide(11, keep)
    sets = [mask_of(x) for x in states(keep[1])]
    cost = measures.lockstep_cost(g, sets, measures.SHAPES)
    single = measures.lockstep_cost(g, sets, measures.SHAPES, width=1)
    assert set(cost) == set(measures.SHAPES) and all(single[k] >= cost[k] / 32 for k in cost)
    assert cost["1,1"] >= cost["inf,inf"]
    for x, y in measures.SHAPES.values():
        degrees, _ = measures.degree_machine(g, sets, x, y)
        assert degrees == [[orders.reached(g, m, v).bit_count() for v in range(g.n) if not m >> v & 1] for m in sets]
    assert measures.divergence(g, sets, 1)["waits_for_lists"] == measures.divergence(g, sets, 1)["waits_for_searches"] == 0


def test_distributed_levels_equal_local_ones(spark):
    g = gnp(10, 0.35, 2)
    want = local.sequential(g)
    for options in (Options(), Options(adjacency="broadcast"), Options(adjacency="join", kernel="parts", partitions=3)):
        got = Walk(g, options.but(local_limit=0), spark).width()
        assert (got.width, got.explored) == (want.width, want.explored)
        assert [(x.k, x.level, x.kept, x.feasible) for x in got.levels] == [(x.k, x.level, x.kept, x.feasible) for x in want.levels]
    bloom = Walk(g, Options(local_limit=0, dedup="bloom"), spark).width()
    assert bloom.width >= want.width and bloom.status == "exact_whp"
    capped = Walk(g, Options(local_limit=0, capacity=9), spark).width()
    assert all(x.kept <= 9 for x in capped.levels)
    run, order = orders.elimination_order(g, Options(local_limit=0), "levels", spark)
    assert orders.order_width(g, order) == run.width == want.width


def test_expression_kernel_level(spark):
    g = gnp(7, 0.4, 3)
    walk = Walk(g, Options(kernel="expr", local_limit=0), spark)
    assert walk.width().width == local.sequential(g).width
    rows = fbits.degree_frame(spark.createDataFrame([(5,), (0,)], "s0 long"), g).collect()
    assert all(r.degree == orders.reached(g, r.s0, r.v).bit_count() for r in rows)


def test_one_exchange_per_level(spark):
    g = named.queen(4)
    walk = Walk(g, Options(local_limit=0), spark)
    front = walk.frame((np.zeros((1, 1), np.uint64), np.zeros(1, np.int32), np.ones(1, np.int64)))
    level = walk.deduplicated(walk.expanded(front, g, 11, walk.clique), 1_000_000)
    plan = level._jdf.queryExecution().toString().split("== Physical Plan ==")[1]
    assert plan.count("Exchange hashpartitioning") == 1 and plan.count("HashAggregate") == 2 and "MapInArrow" in plan


def test_many_graphs_and_targets_at_once(spark):
    some = [gnp(n, 0.4, n) for n in (4, 5, 6, 7)]
    some = [Graph(g.n, g.masks, f"g{k}") for k, g in enumerate(some)]
    rows = decide_many(spark, [(g, k, 0) for g in some for k in range(1, g.n)]).collect()
    got = {g.name: min(r.k for r in rows if r.g == g.name and r.feasible) for g in some}
    assert got == {g.name: max(1, local.brute_orders(g)) for g in some}


def test_api_routes_and_frames(spark):
    edges = named.edge_frame(spark, named.queen(4), named.cycle(6), named.grid(5, 5))
    runs = {r.graph_id: r for r in api.treewidth(edges).collect()}
    assert {k: r.width for k, r in runs.items()} == {"queen4_4": 11, "C6": 2, "grid5x5": 5}
    assert all(r.lower_bound == r.width and r.status == "exact" for r in runs.values())
    got = api.decompositions(edges.where("graph_id = 'C6'")).collect()
    assert max(len(r.verts) for r in got) == 3
    assert api.pieces(named.edge_frame(spark, named.path(9))).count() == 8
    from elimspark.plans.planner import plan

    assert "1 have over 20 vertices" in plan(edges, Options()).explain()
    assert named.queen_edges(spark, 5).count() == named.queen(5).m


def test_components_and_elimination(spark):
    from elimspark.graph import normalize_edges

    raw = spark.createDataFrame([(1, 2), (2, 1), (2, 3), (7, 7), (8, 9), (None, 3)], "a long, b long")
    edges, vertices = normalize_edges(raw)
    assert sorted((r.u, r.v) for r in edges.collect()) == [(0, 1), (1, 2), (3, 4)] and vertices.count() == 5
    assert sorted((r.vid, r.component) for r in prep.components(edges).collect()) == [(0, 0), (1, 0), (2, 0), (3, 3), (4, 3)]
    assert sorted((r.u, r.v) for r in orders.eliminate(edges, 1).collect()) == [(0, 2), (3, 4)]
    long = named.edge_frame(spark, named.path(200))
    assert {r.component for r in prep.components(long).collect()} == {0}


def counts(run):
    return [(x.k, x.level, x.expanded, x.feasible, x.kept, x.dropped_bloom, x.dropped_capacity) for x in run.levels]


@pytest.mark.parametrize("options", [Options(), Options(dedup="bloom", bloom_bits=4, bloom_hashes=3), Options(capacity=30), Options(dedup="bloom", bloom_bits=4, bloom_hashes=3, capacity=30), Options(mmw="min")])
def test_no_result_depends_on_where_a_level_runs(spark, options):
    g = gnp(10, 0.4, 5)
    first, *others = (Walk(g, options.but(local_limit=limit), spark).width() for limit in (10**6, 20))
    for run in others:
        assert (run.width, run.status, run.candidate_k, run.explored) == (first.width, first.status, first.candidate_k, first.explored)
        assert [c[:5] + c[6:] for c in counts(run)] == [c[:5] + c[6:] for c in counts(first)]
        assert sum(x.dropped_bloom for x in run.levels) == sum(x.dropped_bloom for x in first.levels)
    assert all(x.kept <= (options.capacity or 10**9) for x in first.levels)


def test_row_hash_is_that_of_the_cluster(spark):
    from pyspark.sql import functions as F

    from elimspark.operators.search import row_hash

    sets = np.random.default_rng(0).integers(0, 1 << 63, (4, 50)).astype(np.uint64) * np.uint64(3)
    for words in (1, 4):
        frame = spark.createDataFrame([tuple(int(x) for x in c) for c in sets[:words].view(np.int64).T], ", ".join(f"s{w} long" for w in range(words)))
        assert [r.h for r in frame.select(F.xxhash64(*frame.columns).alias("h")).collect()] == row_hash(sets[:words]).tolist()


@settings(max_examples=20, deadline=None)
@given(st.integers(0, 10**6), st.integers(1, 40), st.integers(1, 300))
def test_a_chain_of_filters_inserts_one_by_one(seed, items, step):
    from elimspark.operators.dedup import BloomChain

    keys = np.random.default_rng(seed).integers(0, 200, 150).astype(np.uint64)[None]
    one, some = BloomChain(items, 4, 3), BloomChain(items, 4, 3)
    single = [bool(one.sift(keys[:, j : j + 1])[0]) for j in range(keys.shape[1])]
    assert some.sift(keys, step).tolist() == single


def test_crew_and_one_process_agree(spark):
    from elimspark.operators import crew

    g = named.mycielski(4)
    old, crew.SLAB = crew.SLAB, 256
    try:
        many = Walk(g, Options(), spark).width()
    finally:
        crew.SLAB = old
    assert counts(many) == counts(local.sequential(g)) and many.explored == 97_765


def test_a_wide_graph_leaves_its_task_however_many_there_are(spark):
    wide = gnp(24, 0.25, 1)
    graphs = [Graph(wide.n, wide.masks, "wide"), *(Graph(named.cycle(5).n, named.cycle(5).masks, f"c{k}") for k in range(70))]
    edges = named.edge_frame(spark, *graphs)
    options = Options(task_limit=20)
    assert [r.graph_id for r in api.batch_widths(edges, options).where("status = 'deferred'").collect()] == ["wide"]
    runs = {r.graph_id: r for r in api.treewidth(edges, options).collect()}
    assert len(runs) == 71 and runs["wide"].width == local.solve(wide).width and runs["c69"].width == 2


def test_more_vertices_than_a_word(spark):
    from elimspark.graph import adjacency_masks
    from elimspark.operators.many import widths_many

    edges = named.edge_frame(spark, Graph.of(70, [(0, v) for v in range(1, 70)], "star"), named.cycle(66), named.grid(4, 4))
    assert {r.graph_id: r.width for r in widths_many(edges).collect()} == {"star": 1, "C66": 2, "grid4x4": 4}
    with pytest.raises(Exception, match="64 vertices"):
        adjacency_masks(edges).collect()


@pytest.mark.parametrize(("method", "gaps"), [("levels", {4}), ("parents", {1}), ("rerun", set())])
def test_kept_levels_and_orders_on_both_sides(spark, method, gaps):
    g = gnp(10, 0.3, 4)
    keep: dict = {}
    walk = Walk(g, Options(), spark)
    run = walk.width(keep, {"levels": 4, "parents": 1, "rerun": 0}[method])
    kept = sorted(keep)
    assert {b - a for a, b in zip(kept, kept[1:])} <= gaps and kept[-1] == g.n - run.width - 1
    for spark_or_none, limit in ((None, 10**6), (spark, 15)):
        run, order = orders.elimination_order(g, Options(local_limit=limit), method, spark_or_none)
        assert sorted(order) == list(range(g.n)) and orders.order_width(g, order) == run.width


def test_levels_are_measured(spark):
    run = Walk(named.queen(4), Options(local_limit=0), spark).width()
    assert all(x.bytes > 0 and x.shuffle_bytes > 0 and x.skew >= 1 for x in run.levels if x.kept)
