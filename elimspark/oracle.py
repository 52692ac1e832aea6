"""SQL texts that compute the same results by other principles, for the correctness gate.

Graph searches are recursive queries that carry the remaining graph as a list of masks and
remove vertices from it one by one; the engine's own kernels never store that graph in a
frontier.
"""

from __future__ import annotations

BIT = "(CAST(1 AS UBIGINT) << CAST({} AS INTEGER))"
ALL = "CAST(18446744073709551615 AS UBIGINT)"


def bit(x: str) -> str:
    return f"(CAST(1 AS UBIGINT) << ({x}))"


def normalized(pairs: str) -> str:
    """CTEs ending in ed(graph_id, u, v) from a query of (g, a, b)."""
    return f"""raw AS ({pairs}),
pr AS (SELECT DISTINCT CAST(g AS VARCHAR) AS g, least(a, b) AS a, greatest(a, b) AS b FROM raw WHERE a <> b),
vt AS (SELECT g, x, row_number() OVER (PARTITION BY g ORDER BY x) - 1 AS id FROM (SELECT g, a AS x FROM pr UNION SELECT g, b FROM pr)),
ed AS (SELECT pr.g AS graph_id, CAST(l.id AS BIGINT) AS u, CAST(r.id AS BIGINT) AS v FROM pr JOIN vt l ON l.g = pr.g AND l.x = pr.a JOIN vt r ON r.g = pr.g AND r.x = pr.b)"""


def strongest(pairs: str, top: int, graph: str = "'g'") -> str:
    g = "g, " if graph != "'g'" else ""
    return f"""SELECT {graph} AS g, a, b FROM (
  SELECT {g}a, b, row_number() OVER (PARTITION BY {g}a ORDER BY w DESC, b) AS rk FROM (SELECT {g}a, b, w FROM ({pairs}) UNION ALL SELECT {g}b, a, w FROM ({pairs}))
) WHERE rk <= {top}"""


def nation(top: int) -> str:
    return strongest(
        """SELECT least(c_nationkey, s_nationkey) AS a, greatest(c_nationkey, s_nationkey) AS b, count(*) AS w
        FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN supplier ON l_suppkey = s_suppkey
        WHERE c_nationkey <> s_nationkey GROUP BY 1, 2""",
        top,
    )


def brand(top: int) -> str:
    return strongest(
        """SELECT x.p_brand AS a, y.p_brand AS b, count(*) AS w
        FROM (SELECT DISTINCT l_orderkey, p_brand FROM lineitem JOIN part ON l_partkey = p_partkey) x
        JOIN (SELECT DISTINCT l_orderkey, p_brand FROM lineitem JOIN part ON l_partkey = p_partkey) y ON x.l_orderkey = y.l_orderkey AND x.p_brand < y.p_brand
        GROUP BY 1, 2""",
        top,
    )


def embedding(size: int, top: int) -> str:
    e = "CAST({}.embedding AS DOUBLE[])"
    return strongest(f"SELECT x.vec_id AS a, y.vec_id AS b, round(list_cosine_similarity({e.format('x')}, {e.format('y')}), 6) AS w FROM embeddings x, embeddings y WHERE x.vec_id < y.vec_id AND y.vec_id < {size}", top)


def letter(lang: str, count: int) -> str:
    return f"""SELECT 'g' AS g, a, b FROM (
      SELECT least(x, y) AS a, greatest(x, y) AS b, count(*) AS w FROM (
        SELECT run[i] AS x, run[i + 1] AS y FROM (
          SELECT run, unnest(range(1, length(run))) AS i FROM (SELECT unnest(regexp_extract_all(lower(text), '[a-z]+')) AS run FROM documents WHERE lang = '{lang}')))
      WHERE x <> y GROUP BY 1, 2 ORDER BY w DESC, a, b LIMIT {count})"""


def letters(top: int) -> str:
    """Per language, each letter and its most frequent neighbours."""
    return strongest(
        """SELECT g, least(x, y) AS a, greatest(x, y) AS b, count(*) AS w FROM (
          SELECT g, run[i] AS x, run[i + 1] AS y FROM (
            SELECT g, run, unnest(range(1, length(run))) AS i FROM (SELECT coalesce(lang, 'null') AS g, unnest(regexp_extract_all(lower(text), '[a-z]+')) AS run FROM documents)))
        WHERE x <> y GROUP BY 1, 2, 3""",
        top,
        "g",
    )


def months(top: int) -> str:
    """Months of orders and of their shipments."""
    return strongest(
        """SELECT least(x, y) AS a, greatest(x, y) AS b, count(*) AS w FROM (
          SELECT date_part('month', o_orderdate) AS x, date_part('month', l_shipdate) AS y FROM orders JOIN lineitem ON l_orderkey = o_orderkey)
        WHERE x <> y GROUP BY 1, 2""",
        top,
    )


STATUS = "SELECT 'g' AS g, 's' || o_orderstatus AS a, 'p' || o_orderpriority AS b FROM orders"
SEGMENT = "SELECT 'g' AS g, 's' || c_mktsegment AS a, 'p' || o_orderpriority AS b FROM orders JOIN customer ON o_custkey = c_custkey"
LETTERS = """SELECT DISTINCT g, run[i] AS a, run[i + 1] AS b FROM (
  SELECT g, run, unnest(range(1, length(run))) AS i FROM (SELECT coalesce(lang, 'null') AS g, unnest(regexp_extract_all(lower(text), '[a-z]+')) AS run FROM documents))"""


def docline(length: int, good: bool = False) -> str:
    keep = " WHERE doc_id IN (SELECT doc_id FROM labels WHERE quality = 1)" if good else ""
    held = f"(SELECT DISTINCT doc_id, line FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS line FROM documents{keep}) WHERE length(line) > {length})"
    return f"SELECT 'g' AS g, x.doc_id AS a, y.doc_id AS b FROM {held} x JOIN {held} y ON x.line = y.line AND x.doc_id < y.doc_id"


def coactive(users: int) -> str:
    seen = f"(SELECT DISTINCT user_id, date_trunc('minute', ts) AS m FROM events WHERE user_id < {users})"
    return f"SELECT 'g' AS g, x.user_id AS a, y.user_id AS b FROM {seen} x JOIN {seen} y ON x.m = y.m AND x.user_id < y.user_id"


USERSTEP = "SELECT user_id AS g, event_type AS a, lead(event_type) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS b FROM events"
GEO = "SELECT 'g' AS g, r_name AS a, n_name AS b FROM region JOIN nation ON r_regionkey = n_regionkey"
HOST = """SELECT 'g' AS g, regexp_extract(url, '^[a-z]+://([^/]+)', 1) AS a, unnest(regexp_extract_all(html, 'href="([^"]*)"', 1)) AS b FROM pages"""


def partsupp(parts: int, suppliers: int) -> str:
    return f"SELECT 'g' AS g, 'p' || l_partkey AS a, 's' || l_suppkey AS b FROM lineitem WHERE l_partkey < {parts} AND l_suppkey < {suppliers}"


def words(graph: str, table: str) -> str:
    return f"""SELECT g, w[i] AS a, w[i + 1] AS b FROM (
      SELECT g, w, unnest(range(1, len(w))) AS i FROM (SELECT {graph} AS g, list_filter(string_split_regex(lower(text), '[^a-z]+'), lambda x: x <> '') AS w FROM {table}))"""


TURN = words("conv_id || '/' || turn", "conversations")
BENCHWORD = words("item_id", "benchmark")


def edges(pairs: str) -> str:
    return f"WITH {normalized(pairs)} SELECT graph_id, u, v FROM ed"


REMOVE = f"list_transform(r.a, lambda m, i: CASE WHEN i = t.x + 1 THEN CAST(0 AS UBIGINT) WHEN (m >> t.x) & 1 = 1 THEN (m | r.a[t.x + 1]) & ({ALL} - (({bit('t.x')}) | {bit('CAST(i - 1 AS BIGINT)')})) ELSE m END)"


#: Every clique of every graph, grown by rising vertices, and the first largest one; cl(graph_id, c, size).
CLIQUES = f"""ng AS (SELECT graph_id, u, bit_or({bit('v')}) AS m FROM bo GROUP BY graph_id, u),
cq AS (SELECT graph_id, [u] AS q, {bit('u')} AS c, u AS top, m FROM ng UNION ALL
  SELECT cq.graph_id, list_append(cq.q, ng.u), cq.c | {bit('ng.u')}, ng.u, cq.m & ng.m FROM cq JOIN ng ON ng.graph_id = cq.graph_id AND ng.u > cq.top AND (cq.m >> ng.u) & 1 = 1),
cl AS (SELECT graph_id, c, CAST(len(q) AS BIGINT) AS size FROM (SELECT *, row_number() OVER (PARTITION BY graph_id ORDER BY len(q) DESC, q) AS rk FROM cq) WHERE rk = 1)"""
NO_CLIQUE = "cl AS (SELECT graph_id, CAST(0 AS UBIGINT) AS c, CAST(0 AS BIGINT) AS size FROM nn)"


def base(pairs: str, clique: str = "max") -> str:
    """CTEs bo (both directions), nn(graph_id, n), ad(graph_id, a: masks by vertex), cl(graph_id, c, size)."""
    return f"""{normalized(pairs)},
bo AS (SELECT graph_id, u, v FROM ed UNION ALL SELECT graph_id, v, u FROM ed),
nn AS (SELECT graph_id, max(u) + 1 AS n FROM bo GROUP BY graph_id),
ad AS (SELECT graph_id, list(m ORDER BY u) AS a FROM (SELECT graph_id, u, bit_or({bit('v')}) AS m FROM bo GROUP BY graph_id, u) GROUP BY graph_id),
{CLIQUES if clique == "max" else NO_CLIQUE}"""


def grow(more: str = "") -> str:
    """Feasible supersets by one vertex of the rows of r (graph_id, k, s, a)."""
    return f"""FROM r JOIN nn ON nn.graph_id = r.graph_id JOIN cl ON cl.graph_id = r.graph_id, (SELECT unnest(range(0, 64)) AS x) t
  WHERE t.x < nn.n AND ((r.s | cl.c) >> t.x) & 1 = 0 AND bit_count(r.a[t.x + 1]) <= r.k{more}"""


def walk(pairs: str, ks: str, clique: str = "max", early: bool = True) -> str:
    """CTEs with r(graph_id, k, s, a): every feasible set of every target; nn(graph_id, n); cl(graph_id, c, size)."""
    depth = "nn.n - r.k - 1" if early else "nn.n"
    return f"""{base(pairs, clique)},
r AS (
  SELECT ad.graph_id, CAST(k.k AS BIGINT) AS k, CAST(0 AS UBIGINT) AS s, ad.a FROM ad, ({ks}) k(k)
  UNION
  SELECT r.graph_id, r.k, r.s | {bit('t.x')}, {REMOVE} {grow(f" AND bit_count(r.s) < {depth}")}
)"""


def k_range(low: int, high: int) -> str:
    return f"SELECT unnest(range({low}, {high + 1}))"


def deepening(pairs: str, clique: str = "max", early: bool = True) -> str:
    """As walk, for rising targets from the clique's size less one, at least 1: the next target starts where a walk died.

    A row without a set marks the level of each graph's walk. If no set is left beside it
    and the walk was not at its end, it starts the next target.
    """
    depth = "nn.n - {k} - 1" if early else "nn.n - cl.size"
    return f"""{base(pairs, clique)},
r AS (
  SELECT ad.graph_id, greatest(cl.size - 1, 1) AS k, CASE WHEN z.z = 1 THEN CAST(0 AS UBIGINT) END AS s, ad.a, CAST(0 AS BIGINT) AS lvl
  FROM ad JOIN cl ON cl.graph_id = ad.graph_id, (SELECT unnest([0, 1]) AS z) z
  UNION ALL
  SELECT y.graph_id, CASE WHEN y.s IS NULL AND y.c = 1 THEN y.k + 1 ELSE y.k END, CASE WHEN z.z = 1 THEN CAST(0 AS UBIGINT) ELSE y.s END,
         y.a, CASE WHEN y.s IS NULL AND y.c = 1 THEN 0 ELSE y.lvl END
  FROM (SELECT x.*, count(*) OVER (PARTITION BY x.graph_id) AS c FROM (
      SELECT r.graph_id, r.k, r.s | {bit('t.x')} AS s, any_value({REMOVE}) AS a, max(r.lvl) + 1 AS lvl {grow(f" AND r.s IS NOT NULL AND r.lvl < {depth.format(k='r.k')}")} GROUP BY 1, 2, 3
      UNION ALL
      SELECT r.graph_id, r.k, NULL, r.a, r.lvl + 1 FROM r WHERE r.s IS NULL
    ) x) y JOIN nn ON nn.graph_id = y.graph_id JOIN cl ON cl.graph_id = y.graph_id, (SELECT unnest([0, 1]) AS z) z
  WHERE CASE WHEN y.s IS NULL AND y.c = 1 THEN y.lvl - 1 < {depth.format(k='y.k')} ELSE z.z = 0 END
)"""


def width(pairs: str, clique: str = "max", early: bool = True, explored: bool = False) -> str:
    goal = "nn.n - r.k - 1" if early else "nn.n - cl.size"
    more = f", CAST(count(*) FILTER (r.s IS NOT NULL AND r.lvl < {goal}) AS BIGINT) AS explored" if explored else ""
    return f"""WITH RECURSIVE {deepening(pairs, clique, early)}
SELECT r.graph_id, CAST(max(r.k) AS BIGINT) AS width{more} FROM r JOIN nn ON nn.graph_id = r.graph_id JOIN cl ON cl.graph_id = r.graph_id GROUP BY r.graph_id"""


def _times(x: str, factor: int) -> str:
    return f"CAST((CAST({x} AS UHUGEINT) * CAST('{factor}' AS UHUGEINT)) % CAST('{1 << 64}' AS UHUGEINT) AS UBIGINT)"


def _plus(x: str, term: int) -> str:
    return f"CAST((CAST({x} AS UHUGEINT) + CAST('{term}' AS UHUGEINT)) % CAST('{1 << 64}' AS UHUGEINT) AS UBIGINT)"


def hashed(s: str) -> str:
    """The 64-bit hash of a set, as an unsigned number in the order of the signed one."""
    p1, p2, p3, p4, p5 = 0x9E3779B185EBCA87, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0x85EBCA77C2B2AE63, 0x27D4EB2F165667C5
    turn = lambda x, r: f"({_times(x, 1 << r)} | ({x} >> {64 - r}))"
    steps = (
        _times("x", p2),
        _times(turn("x", 31), p1),
        f"xor(x, CAST('{(42 + p5 + 8) % (1 << 64)}' AS UBIGINT))",
        _plus(_times(turn("x", 27), p1), p4),
        _times("xor(x, x >> 33)", p2),
        _times("xor(x, x >> 29)", p3),
        f"xor(xor(x, x >> 32), CAST('{1 << 63}' AS UBIGINT))",
    )
    out = f"[{s}]"
    for step in steps:
        out = f"list_transform({out}, lambda x: {step})"
    return f"{out}[1]"


def capacity_levels(pairs: str, k: int, most: int) -> str:
    """(k, size, states, total): what is left of each level of one walk of at most ``most`` states a level, and the sum of its sets."""
    return f"""WITH RECURSIVE {base(pairs, "none")},
r AS (
  SELECT ad.graph_id, CAST({k} AS BIGINT) AS k, CAST(0 AS UBIGINT) AS s, ad.a FROM ad
  UNION ALL
  SELECT graph_id, k, s, a FROM (SELECT *, row_number() OVER (PARTITION BY graph_id ORDER BY {hashed('s')}) AS place FROM (
    SELECT r.graph_id, r.k, r.s | {bit('t.x')} AS s, any_value({REMOVE}) AS a {grow(" AND bit_count(r.s) < nn.n - r.k - 1")} GROUP BY 1, 2, 3)) WHERE place <= {most}
)
SELECT k, CAST(bit_count(s) AS BIGINT) AS size, CAST(count(*) AS BIGINT) AS states, CAST(sum(s) AS BIGINT) AS total FROM r GROUP BY 1, 2"""


def paths(pairs: str) -> str:
    """CTEs with pt(graph_id, u, v, n_paths): the least vertex cut of each pair that is not adjacent, over all vertex subsets."""
    return f"""{base(pairs, "none")},
sb AS (SELECT ad.graph_id, nn.n, CAST(x.x AS UBIGINT) AS c, ad.a FROM ad JOIN nn ON nn.graph_id = ad.graph_id, (SELECT unnest(range(0, 65536)) AS x) x WHERE x.x < (1 << CAST(nn.n AS INTEGER))),
st AS (SELECT graph_id, n, c, a, CAST(u.u AS BIGINT) AS u, {bit('u.u')} AS m FROM sb, (SELECT unnest(range(0, 16)) AS u) u WHERE u.u < n AND (c >> u.u) & 1 = 0),
fl AS (SELECT graph_id, n, c, a, u, m, 0 AS step FROM st UNION ALL
  SELECT graph_id, n, c, a, u, more, step + 1 FROM (SELECT *, list_reduce(list_prepend(m, list_transform(a, lambda y, i: CASE WHEN (m >> CAST(i - 1 AS BIGINT)) & 1 = 1 THEN y ELSE CAST(0 AS UBIGINT) END)), lambda y, z: y | z) & ({ALL} - c) AS more FROM fl) WHERE more <> m),
lt AS (SELECT graph_id, c, u, arg_max(m, step) AS m FROM fl GROUP BY 1, 2, 3),
pt AS (SELECT lt.graph_id, lt.u, CAST(v.v AS BIGINT) AS v, CAST(min(bit_count(lt.c)) AS BIGINT) AS n_paths FROM lt JOIN nn ON nn.graph_id = lt.graph_id JOIN ad ON ad.graph_id = lt.graph_id, (SELECT unnest(range(0, 16)) AS v) v
  WHERE v.v > lt.u AND v.v < nn.n AND (ad.a[lt.u + 1] >> v.v) & 1 = 0 AND (lt.c >> v.v) & 1 = 0 AND (lt.m >> v.v) & 1 = 0 GROUP BY 1, 2, 3)"""


def greedy(pairs: str) -> str:
    """Width of the order that removes a vertex of least degree, lowest first, again and again."""
    return f"""WITH RECURSIVE {base(pairs, "none")},
st AS (
  SELECT graph_id, a, list_transform(a, lambda m: TRUE) AS live, CAST(0 AS BIGINT) AS best FROM ad
  UNION ALL
  SELECT graph_id, list_transform(a, lambda m, i: CASE WHEN i = v THEN CAST(0 AS UBIGINT) WHEN (m >> (v - 1)) & 1 = 1 THEN (m | a[v]) & ({ALL} - ({bit('v - 1')} | {bit('CAST(i - 1 AS BIGINT)')})) ELSE m END),
    list_transform(live, lambda x, i: x AND i <> v), greatest(best, d)
  FROM (SELECT graph_id, a, live, best, CAST(list_position(deg, list_min(deg)) AS BIGINT) AS v, list_min(deg) AS d
    FROM (SELECT graph_id, a, live, best, list_transform(a, lambda m, i: CASE WHEN live[i] THEN CAST(bit_count(m) AS BIGINT) ELSE 1000 END) AS deg FROM st WHERE list_contains(live, TRUE)))
)
SELECT graph_id, max(best) AS bound FROM st GROUP BY graph_id"""


def component_graphs(pairs: str) -> str:
    """Pairs of each component as a graph of its own, named g/least id."""
    return f"""SELECT ed.graph_id || '/' || lab.c AS g, ed.u AS a, ed.v AS b FROM ed JOIN lab ON lab.graph_id = ed.graph_id AND lab.x = ed.u"""


def labels(pairs: str) -> str:
    """CTEs with lab(graph_id, x, c): the least vertex of each vertex's component."""
    return f"""{normalized(pairs)},
bo AS (SELECT graph_id, u, v FROM ed UNION SELECT graph_id, v, u FROM ed),
reach AS (SELECT DISTINCT graph_id, u AS x, u AS y FROM bo UNION SELECT reach.graph_id, reach.x, bo.v FROM reach JOIN bo ON bo.graph_id = reach.graph_id AND bo.u = reach.y),
lab AS (SELECT graph_id, x, min(y) AS c FROM reach GROUP BY graph_id, x)"""


def split_pairs(pairs: str) -> str:
    """The pairs of the components of a graph, as graphs of their own."""
    inner = component_graphs(pairs)
    return f"WITH RECURSIVE {labels(pairs)} {inner}"


MMW = f"""WITH RECURSIVE {{norm}},
bo AS (SELECT graph_id, u, v FROM ed UNION ALL SELECT graph_id, v, u FROM ed),
ad AS (SELECT graph_id, list(m ORDER BY u) AS a FROM (SELECT graph_id, u, bit_or({bit('v')}) AS m FROM bo GROUP BY graph_id, u) GROUP BY graph_id),
st AS (
  SELECT graph_id, a, list_transform(a, lambda m: TRUE) AS live, CAST(0 AS BIGINT) AS best FROM ad
  UNION ALL
  SELECT graph_id,
    list_transform(a, lambda m, i: CASE
      WHEN i = v THEN CAST(0 AS UBIGINT)
      WHEN u > 0 AND i = u THEN (m | a[v]) & ({ALL} - ({bit('v - 1')} | {bit('u - 1')}))
      WHEN (m >> (v - 1)) & 1 = 1 THEN (m | CASE WHEN u > 0 THEN {bit('greatest(u, 1) - 1')} ELSE CAST(0 AS UBIGINT) END) & ({ALL} - {bit('v - 1')})
      ELSE m END),
    list_transform(live, lambda x, i: x AND i <> v),
    greatest(best, d)
  FROM (
    SELECT graph_id, a, live, best, v, d,
      coalesce(list_position(near, list_min(list_filter(near, lambda x: x < 1000))), 0) AS u
    FROM (
      SELECT graph_id, a, live, best, v, d,
        list_transform(a, lambda m, i: CASE WHEN (a[v] >> CAST(i - 1 AS BIGINT)) & 1 = 1 THEN CAST(bit_count(m) AS BIGINT) ELSE 1000 END) AS near
      FROM (
        SELECT graph_id, a, live, best, CAST(list_position(deg, list_min(deg)) AS BIGINT) AS v, list_min(deg) AS d
        FROM (SELECT graph_id, a, live, best, list_transform(a, lambda m, i: CASE WHEN live[i] THEN CAST(bit_count(m) AS BIGINT) ELSE 1000 END) AS deg FROM st WHERE len(list_filter(live, lambda x: x)) > 1)
      )
    )
  )
)
SELECT graph_id, CAST(max(best) AS BIGINT) AS bound FROM st GROUP BY graph_id"""


def mmw(pairs: str, rule: str = "min") -> str:
    text = MMW.format(norm=normalized(pairs))
    return text.replace("list_min(deg) AS d", "list_sort(deg)[2] AS d") if rule == "second" else text
