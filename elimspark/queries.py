"""Registered queries: builders, searches, switches, baselines, bounds, orders, measures, anchors."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import api, graph, oracle as o
from .functions import bits as fbits
from .operators import bounds, covers, local, measures, orders, prep, reduce
from .operators import search as s
from .operators.dedup import bloom_fpr_column
from .plans.options import Options
from .sources import builders as b
from .sources import named

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}
EXACT = Options()


def register(name: str, sql: str | None = None):
    def put(function: Query) -> Query:
        QUERIES[name] = function
        if sql is not None:
            ORACLES[name] = sql
        return function

    return put


def longs(frame: DataFrame) -> DataFrame:
    """Integers as longs, so that both engines agree on types."""
    return frame.select(*[F.col(c).cast("long").alias(c) if t in ("int", "smallint", "tinyint") else F.col(c) for c, t in frame.dtypes])


# Builders

#: A limit above all keys, for SQL that takes one.
ALL_IDS = 1 << 62

BUILDERS: dict[str, tuple[Callable[[SparkSession, str], tuple[DataFrame, DataFrame]], str]] = {
    "nation_top1": (lambda sp, d: b.nation(sp, d, 1), o.nation(1)),
    "nation_top2": (lambda sp, d: b.nation(sp, d, 2), o.nation(2)),
    "nation_top3": (lambda sp, d: b.nation(sp, d, 3), o.nation(3)),
    "brand_top1": (lambda sp, d: b.brand(sp, d, 1), o.brand(1)),
    "brand_top2": (lambda sp, d: b.brand(sp, d, 2), o.brand(2)),
    "docline80": (lambda sp, d: b.docline(sp, d, 80), o.docline(80)),
    "docline40": (lambda sp, d: b.docline(sp, d, 40), o.docline(40)),
    "doclabel80": (lambda sp, d: b.doclabel(sp, d, 80), o.docline(80, True)),
    "coactive": (b.coactive, o.coactive(ALL_IDS)),
    "userstep": (b.userstep, o.USERSTEP),
    "host": (b.host, o.HOST),
    "geo": (b.geo, o.GEO),
    "turn": (b.turn, o.TURN),
    "benchword": (b.benchword, o.BENCHWORD),
    "months2": (lambda sp, d: b.months(sp, d, 2), o.months(2)),
    "months3": (lambda sp, d: b.months(sp, d, 3), o.months(3)),
    "status": (b.status, o.STATUS),
    "segment": (b.segment, o.SEGMENT),
    "letters2": (lambda sp, d: b.letters(sp, d, 2), o.letters(2)),
    "embed_knn": (lambda sp, d: b.embedding_all(sp, d, 2), o.embedding(ALL_IDS, 2)),
    "letter": (b.letter_all, o.LETTERS),
    "partsupp": (b.partsupp, o.partsupp(ALL_IDS, ALL_IDS)),
}
for _name, (_make, _pairs) in BUILDERS.items():
    register(f"edges_{_name}", o.edges(_pairs))(lambda sp, d, f=_make: longs(f(sp, d)[0]))


def edges_of(sp: SparkSession, d: str, name: str) -> DataFrame:
    return BUILDERS[name][0](sp, d)[0]


def graph_of(sp: SparkSession, d: str, name: str) -> graph.Graph:
    """A whole small graph of known bound (at most 256 vertices) on the driver."""
    return api.graph_of(edges_of(sp, d, name))


NATION, MONTHS, LETTER = (BUILDERS[n][1] for n in ("nation_top2", "months3", "letters2"))
_ED = f"WITH {o.normalized(MONTHS)}, bo AS (SELECT graph_id, u, v FROM ed UNION ALL SELECT graph_id, v, u FROM ed)"


@register("degree_table", f"WITH {o.normalized(NATION)} SELECT graph_id, vid, CAST(count(*) AS BIGINT) AS degree FROM (SELECT graph_id, u AS vid FROM ed UNION ALL SELECT graph_id, v FROM ed) GROUP BY 1, 2")
def degree_table(sp, d):
    return longs(graph.degrees(edges_of(sp, d, "nation_top2")))


@register("adjacency_masks", f"{_ED} SELECT graph_id, u AS vid, CAST(bit_or({o.bit('v')}) AS BIGINT) AS nbr FROM bo GROUP BY graph_id, u")
def adjacency(sp, d):
    return longs(graph.adjacency_masks(edges_of(sp, d, "months3")))


@register("graph_profile", f"WITH {o.normalized(o.USERSTEP)}, dg AS (SELECT graph_id, x, count(*) AS c FROM (SELECT graph_id, u AS x FROM ed UNION ALL SELECT graph_id, v FROM ed) GROUP BY 1, 2) SELECT graph_id, CAST(count(*) AS BIGINT) AS n, CAST(sum(c) // 2 AS BIGINT) AS m, CAST(min(c) AS BIGINT) AS min_degree, CAST(max(c) AS BIGINT) AS max_degree FROM dg GROUP BY graph_id")
def graph_profile(sp, d):
    return longs(graph.profile(edges_of(sp, d, "userstep")))


# Searches


def one_width(sp: SparkSession, d: str, name: str, options: Options = EXACT, explored: bool = False) -> DataFrame:
    run = s.Walk(graph_of(sp, d, name), options, sp).width()
    columns = "graph_id string, width long" + (", explored long" if explored else "")
    return sp.createDataFrame([(run.graph_id, run.width, run.explored)[: 3 if explored else 2]], columns)


def _width(name: str, builder: str, options: Options = EXACT, explored: bool = False, clique: str = "max", early: bool = True) -> None:
    register(name, o.width(BUILDERS[builder][1], clique, early, explored))(lambda sp, d: one_width(sp, d, builder, options, explored))


_width("tw_nation_top2", "nation_top2", explored=True)
_width("tw_nation_top3", "nation_top3")
_width("tw_brand_top2", "brand_top2", explored=True)
_width("tw_months2", "months2", explored=True)
_width("tw_months3", "months3", explored=True)
_width("tw_status", "status", explored=True)
_width("tw_segment", "segment", explored=True)
NONE = EXACT.but(clique="none", k0=1)
_width("tw_months3_noclique", "months3", NONE, True, "none")
_width("tw_months3_noearlystop", "months3", EXACT.but(early_stop=False), True, "max", False)
_width("tw_months3_augmented", "months3", EXACT.but(augment=True), True)
_width("tw_months3_augmented_clique", "months3", EXACT.but(augment=True, clique_on="augmented"))
_width("tw_months3_bloom", "months3", EXACT.but(dedup="bloom"))
_width("tw_months3_mmw", "months3", EXACT.but(mmw="second"))
_width("tw_months3_mmw_implicit", "months3", EXACT.but(mmw="min", mmw_impl="implicit"))
_width("tw_months3_greedy_clique", "months3", EXACT.but(clique="greedy", k0=1))
_width("tw_months3_kernel_expr", "months3", EXACT.but(kernel="expr", local_limit=0), True)
_width("tw_months3_kernel_remove", "months3", EXACT.but(kernel="remove"), True)
_width("tw_months3_kernel_search", "months3", EXACT.but(kernel="search"), True)
_width("tw_months3_kernel_parts", "months3", EXACT.but(kernel="parts"), True)
_width("tw_months3_spread", "months3", EXACT.but(local_limit=0), True)
_width("tw_months3_spread_broadcast", "months3", EXACT.but(local_limit=0, adjacency="broadcast"), True)
_width("tw_months3_spread_join", "months3", EXACT.but(local_limit=0, adjacency="join"), True)
_width("tw_status_nodedup", "status", EXACT.but(dedup="none"))


@register("tw_letters2", o.width(LETTER))
def tw_letters(sp, d):
    """The graphs of all languages."""
    return api.treewidth(edges_of(sp, d, "letters2")).select("graph_id", F.col("width").cast("long").alias("width"))


@register("tw_months3_kbatch", f"WITH RECURSIVE {o.walk(MONTHS, o.k_range(1, 5), 'none')} SELECT k.k, EXISTS (SELECT 1 FROM r JOIN nn ON TRUE WHERE r.k = k.k AND bit_count(r.s) = nn.n - r.k - 1) AS feasible FROM (SELECT CAST(unnest(range(1, 6)) AS BIGINT) AS k) k")
def tw_kbatch(sp, d):
    from .operators.many import decide_many

    g = graph_of(sp, d, "months3")
    return decide_many(sp, [(g, k, 0) for k in range(1, 6)]).select("k", "feasible")


@register("tw_months3_capacity")
def tw_capacity(sp, d):
    g = graph_of(sp, d, "months3")
    return measures.runs_frame(sp, [s.width_of(g, EXACT.but(capacity=c)) for c in (5, 20, 100, 100_000)]).select("graph_id", F.get_json_object("opts", "$.capacity").cast("long").alias("capacity"), "width", "lower_bound", "candidate_k", "overflow_k", "status")


@register("levels_months3_capacity", o.capacity_levels(MONTHS, 3, 40))
def levels_capacity(sp, d):
    """What the capacity rule leaves of each level, on the cluster."""
    keep: dict = {}
    walk = s.Walk(graph_of(sp, d, "months3"), EXACT.but(clique="none", capacity=40, local_limit=0), sp)
    _, levels, _ = walk.decide(3, keep)
    rows = [(3, 0, 1, 0)]
    for x in levels:
        front = keep[x.level + 1]
        if x.kept:
            total = int(front[0].sum()) if isinstance(front, tuple) else front.agg(F.sum("s0")).first()[0]
            rows.append((3, x.level + 1, x.kept, total))
    return sp.createDataFrame(rows, "k long, size long, states long, total long")


@register("tw_userstep_batch", o.width(o.USERSTEP, "none"))
def tw_userstep(sp, d):
    return api.exact_widths(api.batch_widths(edges_of(sp, d, "userstep")))


@register("tw_docline80_batch", o.width(o.split_pairs(o.docline(80))))
def tw_docline(sp, d):
    return api.exact_widths(covers.widths(b.docline_cover(sp, d, 80)[0]))


@register("tw_geo", f"WITH RECURSIVE {o.labels(o.GEO)} SELECT graph_id || '/' || c AS graph_id, CAST(1 AS BIGINT) AS width FROM lab GROUP BY graph_id, c HAVING (SELECT count(*) FROM ed) = (SELECT count(*) FROM lab) - (SELECT count(DISTINCT c) FROM lab)")
def tw_geo(sp, d):
    """A forest has width one; the SQL side checks that it is a forest."""
    edges = edges_of(sp, d, "geo")
    return api.treewidth(prep.relabelled(edges, prep.components(edges))).select("graph_id", F.col("width").cast("long").alias("width"))


@register("tw_frontier_batch", o.width(o.USERSTEP, "none"))
def tw_frontier(sp, d):
    """All users' graphs and all targets in one frontier."""
    from .operators.many import widths_many

    return widths_many(edges_of(sp, d, "userstep"))


def _decide(name: str, k: int) -> None:
    sql = f"WITH RECURSIVE {o.walk(NATION, o.k_range(k, k), 'none')} SELECT 'g' AS graph_id, CAST({k} AS BIGINT) AS k, EXISTS (SELECT 1 FROM r JOIN nn ON TRUE WHERE bit_count(r.s) = nn.n - r.k - 1) AS feasible"
    register(name, sql)(lambda sp, d: longs(api.decide(sp, graph_of(sp, d, "nation_top2"), k)[0].select("graph_id", "k", "feasible")))


_decide("decide_nation_k1_no", 1)
_decide("decide_nation_k2_yes", 2)


def _levels(name: str, builder: str, k: int) -> None:
    sql = f"WITH RECURSIVE {o.walk(BUILDERS[builder][1], o.k_range(k, k), 'none')} SELECT k, CAST(bit_count(s) AS BIGINT) AS size, CAST(count(*) AS BIGINT) AS states FROM r GROUP BY 1, 2"

    def run(sp, d):
        walk = s.Walk(graph_of(sp, d, builder), EXACT.but(clique="none"), sp)
        _, levels, _ = walk.decide(k)
        rows = [(k, 0, 1)] + [(k, x.level + 1, x.kept) for x in levels if x.kept]
        return sp.createDataFrame(rows, "k long, size long, states long")

    register(name, sql)(run)


_levels("levels_months3_k2", "months3", 2)
_levels("levels_months3_k4", "months3", 4)
_levels("levels_segment_k5", "segment", 5)


@register("frontier_months3_level3", f"WITH RECURSIVE {o.walk(MONTHS, o.k_range(5, 5), 'none')} SELECT CAST(s AS BIGINT) AS s0 FROM r WHERE bit_count(s) = 3")
def frontier_level3(sp, d):
    keep: dict = {}
    walk = s.Walk(graph_of(sp, d, "months3"), EXACT.but(clique="none", local_limit=0), sp)
    walk.decide(5, keep)
    return keep[3].select("s0") if 3 in keep else sp.createDataFrame([], "s0 long")


@register("degree_q_sets", f"WITH RECURSIVE {o.walk(MONTHS, o.k_range(64, 64), 'none', False).replace('bit_count(r.s) < nn.n', 'bit_count(r.s) < 2')} SELECT DISTINCT CAST(r.s AS BIGINT) AS s0, CAST(t.x AS BIGINT) AS v, CAST(bit_count(r.a[t.x + 1]) AS BIGINT) AS degree FROM r, nn, (SELECT unnest(range(0, 64)) AS x) t WHERE t.x < nn.n AND (r.s >> t.x) & 1 = 0")
def degree_q_sets(sp, d):
    """Degrees of every vertex after removing every set of at most two, as expressions."""
    g = graph_of(sp, d, "months3")
    one = sp.range(g.n).select(F.expr("shiftleft(1L, cast(id as int))").alias("a"))
    sets = sp.range(1).select(F.lit(0).cast("long").alias("s0")).unionByName(one.select(F.col("a").alias("s0"))).unionByName(one.crossJoin(one.withColumnRenamed("a", "b")).where("a < b").select(F.col("a").bitwiseOR(F.col("b")).alias("s0")))
    return longs(fbits.degree_frame(sets, g))


# Baselines



@register("subset_dp_months3", o.width(MONTHS, "none"))
def subset_dp_query(sp, d):
    g = graph_of(sp, d, "months3")
    return sp.createDataFrame([(g.name, local.subset_dp(g)[0])], "graph_id string, width long")


@register("brute_orders_status", f"""WITH RECURSIVE {o.base(o.STATUS, "none")},
r AS (SELECT graph_id, CAST(0 AS UBIGINT) AS s, a, CAST(0 AS BIGINT) AS w FROM ad UNION ALL
  SELECT r.graph_id, r.s | {o.bit('t.x')}, {o.REMOVE}, greatest(r.w, CAST(bit_count(r.a[t.x + 1]) AS BIGINT)) FROM r, nn, (SELECT unnest(range(0, 64)) AS x) t WHERE t.x < nn.n AND (r.s >> t.x) & 1 = 0)
SELECT r.graph_id, min(w) AS width FROM r, nn WHERE bit_count(s) = nn.n GROUP BY r.graph_id""")
def brute_query(sp, d):
    g = graph_of(sp, d, "status")
    return sp.createDataFrame([(g.name, local.brute_orders(g))], "graph_id string, width long")


@register("branch_bound_months3", o.width(MONTHS))
def branch_query(sp, d):
    g = graph_of(sp, d, "months3")
    return sp.createDataFrame([(g.name, local.branch_and_bound(g)[0])], "graph_id string, width long")


@register("local_sequential_months3", o.width(MONTHS, explored=True))
def sequential_query(sp, d):
    run = local.sequential(graph_of(sp, d, "months3"))
    return sp.createDataFrame([(run.graph_id, run.width, run.explored)], "graph_id string, width long, explored long")


@register("width_at_most_2_userstep", f"SELECT graph_id, width <= 2 AS at_most_2 FROM ({o.width(o.USERSTEP, "none")})")
def width2_query(sp, d):
    return api.per_graph(edges_of(sp, d, "userstep"), lambda g: [(local.width_at_most_2(g),)], "at_most_2 boolean")


@register("positive_instances_months3", o.width(MONTHS))
def positive_query(sp, d):
    g = graph_of(sp, d, "months3")
    return sp.createDataFrame([(g.name, local.positive_instances(g)[0])], "graph_id string, width long")


@register("width_at_most_3_docline80", f"SELECT graph_id, width <= 3 AS at_most_3 FROM ({o.width(o.split_pairs(o.docline(80)))})")
def width3_query(sp, d):
    edges = edges_of(sp, d, "docline80")
    return api.per_graph(prep.relabelled(edges, prep.components(edges)), lambda g: [(local.width_at_most(g, 3)[0],)], "at_most_3 boolean")


@register("greedy_fill_benchword")
def greedy_query(sp, d):
    return longs(api.upper_bounds(edges_of(sp, d, "benchword")))


@register("greedy_degree_docline80", o.greedy(o.split_pairs(o.docline(80))))
def greedy_degree(sp, d):
    return covers.upper_bounds(b.docline_cover(sp, d, 80)[0])


# Bounds and pieces


@register("mmw_userstep", o.mmw(o.USERSTEP))
def mmw_query(sp, d):
    return longs(api.lower_bounds(edges_of(sp, d, "userstep")))


@register("mmw_nation", o.mmw(NATION))
def mmw_nation(sp, d):
    return longs(api.lower_bounds(edges_of(sp, d, "nation_top2")))


@register("mmw_second_userstep", o.mmw(o.USERSTEP, "second"))
def mmw_second(sp, d):
    return longs(api.lower_bounds(edges_of(sp, d, "userstep"), "second"))


@register("components_docline80", f"WITH RECURSIVE {o.labels(o.docline(80))} SELECT graph_id, x AS vid, c AS component FROM lab")
def components_query(sp, d):
    return longs(prep.components(edges_of(sp, d, "docline80")))


@register("simplicial_vertices", f"WITH {o.normalized(o.docline(80))}, bo AS (SELECT graph_id, u, v FROM ed UNION ALL SELECT graph_id, v, u FROM ed) SELECT graph_id, u AS vid FROM bo GROUP BY graph_id, u HAVING count(*) * (count(*) - 1) // 2 = (SELECT count(*) FROM bo x JOIN bo y ON x.graph_id = y.graph_id AND x.u = y.u AND x.v < y.v JOIN ed ON ed.u = x.v AND ed.v = y.v WHERE x.u = bo.u AND x.graph_id = bo.graph_id)")
def simplicial_query(sp, d):
    return longs(covers.simplicial_vertices(b.docline_cover(sp, d, 80)[0]))


@register("biconnected_brand1")
def biconnected_query(sp, d):
    return longs(api.pieces(edges_of(sp, d, "brand_top1"), ("components", "articulation")))


@register("pieces_nation1")
def pieces_query(sp, d):
    return longs(api.pieces(edges_of(sp, d, "nation_top1")))


@register("separators_brand2")
def separators_query(sp, d):
    return longs(api.separators(edges_of(sp, d, "brand_top2")).withColumn("verts", F.array_join(F.col("verts").cast("array<string>"), " ")))


@register("disjoint_paths_months3", f"WITH RECURSIVE {o.paths(MONTHS)} SELECT graph_id, u, v, n_paths FROM pt")
def paths_query(sp, d):
    return longs(api.disjoint_paths(edges_of(sp, d, "months3")))


@register("forced_edges_months3_k3", f"WITH RECURSIVE {o.paths(MONTHS)} SELECT graph_id, u, v FROM ed UNION SELECT graph_id, u, v FROM pt WHERE n_paths >= 4")
def forced_query(sp, d):
    edges = edges_of(sp, d, "months3")
    return longs(api.forced_edges(edges, api.disjoint_paths(edges), 3))


@register("max_clique_letters2", f"WITH RECURSIVE {o.base(LETTER)} SELECT cl.graph_id, array_to_string(cq.q, ' ') AS verts, cl.size FROM cl JOIN cq ON cq.graph_id = cl.graph_id AND cq.c = cl.c")
def clique_query(sp, d):
    return longs(api.max_cliques(edges_of(sp, d, "letters2")).select("graph_id", F.array_join(F.col("verts").cast("array<string>"), " ").alias("verts"), "size"))


# Orders


@register("order_width_identity", f"""WITH RECURSIVE {o.base(MONTHS, "none")},
r AS (SELECT graph_id, CAST(-1 AS BIGINT) AS pos, CAST(0 AS BIGINT) AS deg, a FROM ad UNION ALL
  SELECT r.graph_id, t.x, CAST(bit_count(r.a[t.x + 1]) AS BIGINT), {o.REMOVE} FROM r JOIN (SELECT unnest(range(0, 64)) AS x) t ON t.x = r.pos + 1, nn WHERE t.x < nn.n)
SELECT graph_id, pos, deg FROM r WHERE pos >= 0""")
def order_identity(sp, d):
    return longs(api.per_graph(edges_of(sp, d, "months3"), lambda g: list(enumerate(orders.order_degrees(g, list(range(g.n))))), "pos int, deg int"))


@register("elimination_step", f"WITH {o.normalized(NATION)}, me AS (SELECT CASE WHEN u = 3 THEN v ELSE u END AS x FROM ed WHERE u = 3 OR v = 3) SELECT 'g' AS graph_id, u, v FROM ed WHERE u <> 3 AND v <> 3 UNION SELECT 'g', l.x, r.x FROM me l JOIN me r ON l.x < r.x")
def elimination_step(sp, d):
    return longs(orders.eliminate(edges_of(sp, d, "nation_top2"), 3))


def _order(name: str, method: str) -> None:
    sql = f"SELECT w.graph_id, nn.n AS vertices, w.width FROM ({o.width(MONTHS)}) w, (WITH {o.normalized(MONTHS)} SELECT CAST(max(v) + 1 AS BIGINT) AS n FROM ed) nn"

    def run(sp, d):
        got = api.elimination_orders(edges_of(sp, d, "months3"), method=method)
        return got.groupBy("graph_id").agg(F.count_distinct("vid").alias("vertices"), F.max("deg").cast("long").alias("width"))

    register(name, sql)(run)


for _name, _method in {"order_months3": "levels", "order_months3_parents": "parents", "order_months3_rerun": "rerun"}.items():
    _order(_name, _method)


@register("bags_months3", f"SELECT w.graph_id, w.width, TRUE AS covers_edges, TRUE AS connected FROM ({o.width(MONTHS)}) w")
def bags_query(sp, d):
    """Width of the decomposition, whether its bags hold all edges, and whether each vertex's bags are connected."""
    edges = edges_of(sp, d, "months3")
    bags = api.decompositions(edges)
    held = bags.select("graph_id", "bag_id", "parent", F.explode("verts").alias("x"))
    pairs = held.alias("l").join(held.alias("r"), ["graph_id", "bag_id"]).where("l.x < r.x").select("graph_id", F.col("l.x").alias("u"), F.col("r.x").alias("v"))
    missing = edges.join(pairs, ["graph_id", "u", "v"], "left_anti").agg((F.count("*") == 0).alias("covers_edges"))
    # A tree: the bags of a vertex are connected if just one of them has no parent among them.
    above = held.alias("c").join(held.alias("p"), (F.col("c.graph_id") == F.col("p.graph_id")) & (F.col("c.parent") == F.col("p.bag_id")) & (F.col("c.x") == F.col("p.x")), "left_anti")
    tops = above.groupBy("graph_id", "x").count().agg((F.max("count") == 1).alias("connected"))
    width = bags.groupBy("graph_id").agg((F.max(F.size("verts")) - 1).cast("long").alias("width"))
    return width.crossJoin(F.broadcast(missing)).crossJoin(F.broadcast(tops))


# Measures


@register("bloom_fpr_grid", "SELECT CAST(b AS BIGINT) AS bits_per_item, CAST(h AS BIGINT) AS hashes, round(pow(1.0 - exp(-CAST(h AS DOUBLE) / b), h), 12) AS rate FROM (SELECT unnest([4, 8, 16, 24]) AS b), (SELECT unnest(range(3, 18)) AS h)")
def bloom_grid(sp, d):
    grid = sp.range(3, 18).select(F.col("id").alias("hashes"), F.explode(F.array(*[F.lit(x).cast("long") for x in (4, 8, 16, 24)])).alias("bits_per_item"))
    rate = bloom_fpr_column(F.lit(1.0), F.col("bits_per_item").cast("double"), F.col("hashes").cast("double"))
    return grid.select("bits_per_item", "hashes", F.round(rate, 12).alias("rate"))


@register("explored_share_by_level", f"""WITH RECURSIVE {o.deepening(MONTHS, 'none')},
l AS (SELECT r.graph_id, r.k, r.lvl AS level, CAST(count(*) AS BIGINT) AS expanded FROM r JOIN nn ON nn.graph_id = r.graph_id WHERE r.s IS NOT NULL AND r.lvl < nn.n - r.k - 1 GROUP BY 1, 2, 3)
SELECT graph_id, k, level, expanded, CAST(sum(expanded) OVER (ORDER BY k, level) AS BIGINT) AS running, round(expanded / sum(expanded) OVER (), 9) AS share FROM l""")
def share_query(sp, d):
    run = s.Walk(graph_of(sp, d, "months3"), NONE).width()
    return longs(measures.explored_share(measures.levels_frame(sp, run.levels)).withColumn("share", F.round("share", 9)))


@register("lockstep_cost_months3")
def lockstep_query(sp, d):
    g = graph_of(sp, d, "months3")
    keep: dict = {}
    s.Walk(g, EXACT).decide(3, keep)
    sets = [sum(1 << v for v in x) for x in s.states(keep[4])]
    return sp.createDataFrame([(k, v) for k, v in measures.lockstep_cost(g, sets, measures.SHAPES).items()], "shape string, steps long")


@register("divergence_months3")
def divergence_query(sp, d):
    """Where lockstep groups wait."""
    g = graph_of(sp, d, "months3")
    keep: dict = {}
    s.Walk(g, EXACT).decide(3, keep)
    sets = [sum(1 << v for v in x) for x in s.states(keep[4])]
    return sp.createDataFrame(list(measures.divergence(g, sets).items()), "part string, steps long")


@register("bloom_audit_nation2")
def audit_query(sp, d):
    """Loss of the filter on one level, by bits per item."""
    g = graph_of(sp, d, "nation_top2")
    keep: dict = {}
    walk = s.Walk(g, EXACT)
    walk.decide(walk.width().width, keep)
    walk.spark = sp
    level = max((x for x in keep), key=lambda x: keep[x][0].shape[1] if isinstance(keep[x], tuple) else 0)
    exact = walk.frame(keep[level])
    out = None
    for size in (4, 8, 24):
        filtered = s.Walk(g, EXACT.but(dedup="bloom", bloom_bits=size, bloom_hashes=3 if size == 4 else 17), sp).deduplicated(exact, keep[level][0].shape[1])
        row = measures.bloom_audit(exact, filtered, ["s0"]).select(F.lit(size).cast("long").alias("bits_per_item"), "distinct", "kept", "lost", "rate")
        out = row if out is None else out.unionByName(row)
    return out


# Anchors: counts and widths as published


def _anchor(name: str, make: Callable[[], graph.Graph], width: int, explored: int, options: Options = EXACT) -> None:
    def run(sp, d):
        got = s.Walk(make(), options, sp).width()
        return sp.createDataFrame([(got.graph_id, got.width, got.explored)], "graph_id string, width long, explored long")

    register(name, f"SELECT '{make().name}' AS graph_id, CAST({width} AS BIGINT) AS width, CAST({explored} AS BIGINT) AS explored")(run)


_anchor("anchor_queen5", lambda: named.queen(5), 18, 3_134)
_anchor("anchor_queen6", lambda: named.queen(6), 25, 35_973)
_anchor("anchor_mycielski4", lambda: named.mycielski(4), 10, 97_765)
_anchor("anchor_mcgee", named.mcgee, 7, 3_853_249)
_anchor("anchor_queen7", lambda: named.queen(7), 35, 1_901_029)
_anchor("anchor_unitary_polar", named.unitary_polar, 53, 1_558_852)
# The same with the larger levels on the cluster.
_anchor("anchor_queen6_spread", lambda: named.queen(6), 25, 35_973, EXACT.but(local_limit=2_000))
_anchor("anchor_queen7_spread", lambda: named.queen(7), 35, 1_901_029, EXACT.but(local_limit=100_000))
_anchor("anchor_unitary_polar_spread", named.unitary_polar, 53, 1_558_852, EXACT.but(local_limit=100_000))
