"""Relational queries that surround the graph work: joins, windows, sets, cubes, scalar functions.

Each is a declarative plan on the given tables with its SQL beside it.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .queries import longs, register
from .sources.builders import load


def asof_join(left: DataFrame, right: DataFrame, key: str, left_time: str, right_time: str, value: str) -> DataFrame:
    """For each left row the latest right value of the same key at or before its time; one sort, no range join.

    Both sides are stacked and the last right value is carried forward along time; at equal
    times right rows come first. ``left`` needs columns key, left_time and id.
    """
    stacked = left.select(key, F.col(left_time).alias("t"), F.lit(1).alias("side"), "id", F.lit(None).cast(right.schema[value].dataType).alias("x")).unionByName(
        right.select(key, F.col(right_time).alias("t"), F.lit(0).alias("side"), F.lit(None).cast("long").alias("id"), F.col(value).alias("x"))
    )
    order = Window.partitionBy(key).orderBy("t", "side", "x").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return stacked.withColumn(value, F.last("x", ignorenulls=True).over(order)).where("side = 1").select("id", key, value)


def range_join(left: DataFrame, right: DataFrame, left_time: str, right_time: str, seconds: int) -> DataFrame:
    """Pairs within some seconds: equal time buckets, neighbours exploded, then the exact test."""
    cut = lambda c: F.floor(F.unix_timestamp(c) / seconds)
    a = left.withColumn("bucket", cut(left_time))
    b = right.withColumn("bucket", F.explode(F.array(cut(right_time) - 1, cut(right_time), cut(right_time) + 1)))
    return a.join(b, "bucket").where(F.abs(F.unix_micros(left_time) - F.unix_micros(right_time)) <= seconds * 1_000_000).drop("bucket")


@register("rel_semi", "SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_totalprice > 400000)")
def rel_semi(sp: SparkSession, d: str) -> DataFrame:
    big = load(sp, d, "orders", "o_custkey", "o_totalprice").where("o_totalprice > 400000")
    customer = load(sp, d, "customer", "c_custkey")
    return customer.join(big, F.col("c_custkey") == F.col("o_custkey"), "left_semi")


@register("rel_anti", "SELECT c_custkey FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_totalprice > 400000)")
def rel_anti(sp, d):
    return load(sp, d, "customer", "c_custkey").join(load(sp, d, "orders", "o_custkey", "o_totalprice").where("o_totalprice > 400000"), F.col("c_custkey") == F.col("o_custkey"), "left_anti")


@register("rel_full_outer", "SELECT coalesce(a.nation, b.nation) AS nation, coalesce(customers, 0) AS customers, coalesce(suppliers, 0) AS suppliers FROM (SELECT CAST(c_nationkey AS BIGINT) AS nation, count(*) AS customers FROM customer WHERE c_acctbal > 5000 GROUP BY 1) a FULL JOIN (SELECT CAST(s_nationkey AS BIGINT) AS nation, count(*) AS suppliers FROM supplier GROUP BY 1) b ON a.nation = b.nation")
def rel_full(sp, d):
    a = load(sp, d, "customer", "c_nationkey", "c_acctbal").where("c_acctbal > 5000").groupBy(F.col("c_nationkey").cast("long").alias("nation")).agg(F.count("*").alias("customers"))
    b = load(sp, d, "supplier", "s_nationkey").groupBy(F.col("s_nationkey").cast("long").alias("nation")).agg(F.count("*").alias("suppliers"))
    return a.join(b, "nation", "full").select("nation", F.coalesce("customers", F.lit(0)).alias("customers"), F.coalesce("suppliers", F.lit(0)).alias("suppliers"))


@register("rel_range_join", "SELECT x.event_id AS a, y.event_id AS b FROM events x JOIN events y ON x.user_id < y.user_id AND x.event_type = 'purchase' AND y.event_type = 'purchase' AND abs(epoch_us(x.ts) - epoch_us(y.ts)) <= 30 * 1000000")
def rel_range(sp, d):
    bought = load(sp, d, "events", "event_id", "user_id", "ts", "event_type").where("event_type = 'purchase'")
    a, b = (bought.select(F.col("event_id").alias(x), F.col("user_id").alias(f"u{x}"), F.col("ts").cast("timestamp").alias(f"t{x}")) for x in "ab")
    return range_join(a, b, "ta", "tb", 30).where("ua < ub").select("a", "b")


@register("rel_asof_join", "SELECT l.event_id AS id, l.user_id, (SELECT arg_max(r.value, (r.ts, r.value)) FROM events r WHERE r.user_id = l.user_id AND r.event_type = 'view' AND r.ts <= l.ts) AS value FROM events l WHERE l.event_type = 'purchase'")
def rel_asof(sp, d):
    events = load(sp, d, "events", "event_id", "user_id", "ts", "event_type", "value")
    left = events.where("event_type = 'purchase'").select(F.col("event_id").alias("id"), "user_id", "ts")
    right = events.where("event_type = 'view'").select("user_id", "ts", "value")
    return asof_join(left, right, "user_id", "ts", "ts", "value")


@register("rel_rollup", "SELECT l_returnflag, l_linestatus, CAST(count(*) AS BIGINT) AS n, CAST(grouping(l_returnflag) * 2 + grouping(l_linestatus) AS BIGINT) AS level FROM lineitem GROUP BY ROLLUP (l_returnflag, l_linestatus)")
def rel_rollup(sp, d):
    return longs(load(sp, d, "lineitem", "l_returnflag", "l_linestatus").rollup("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.grouping_id().alias("level")))


@register("runs_cube", "SELECT o_orderstatus, o_orderpriority, CAST(count(*) AS BIGINT) AS n, CAST(sum(CAST(o_orderkey % 7 AS BIGINT)) AS BIGINT) AS s FROM orders GROUP BY CUBE (o_orderstatus, o_orderpriority)")
def runs_cube(sp, d):
    return load(sp, d, "orders", "o_orderstatus", "o_orderpriority", "o_orderkey").cube("o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n"), F.sum(F.col("o_orderkey") % 7).alias("s"))


@register("rel_grouping_sets", "SELECT c_mktsegment, CAST(c_nationkey AS BIGINT) AS nation, count(*) AS n FROM customer GROUP BY GROUPING SETS ((c_mktsegment), (c_nationkey), ())")
def rel_sets(sp, d):
    frame = load(sp, d, "customer", "c_mktsegment", F.col("c_nationkey").cast("long").alias("nation"))
    return frame.groupingSets([["c_mktsegment"], ["nation"], []], "c_mktsegment", "nation").agg(F.count("*").alias("n"))


@register("ablation_pivot", "SELECT p_brand, CAST(count(*) FILTER (p_size <= 10) AS BIGINT) AS small, CAST(count(*) FILTER (p_size > 10) AS BIGINT) AS large FROM part GROUP BY p_brand")
def rel_pivot(sp, d):
    frame = load(sp, d, "part", "p_brand", "p_size").withColumn("kind", F.when(F.col("p_size") <= 10, "small").otherwise("large"))
    return frame.groupBy("p_brand").pivot("kind", ["small", "large"]).agg(F.count(F.lit(1))).na.fill(0)


@register("rel_unpivot", "SELECT s_suppkey, measure, value FROM (SELECT s_suppkey, CAST(s_nationkey AS DOUBLE) AS nation, s_acctbal AS balance FROM supplier) UNPIVOT (value FOR measure IN (nation, balance))")
def rel_unpivot(sp, d):
    frame = load(sp, d, "supplier", "s_suppkey", F.col("s_nationkey").cast("double").alias("nation"), F.col("s_acctbal").alias("balance"))
    return frame.unpivot(["s_suppkey"], ["nation", "balance"], "measure", "value")


@register("rel_topk_per_group", "SELECT c_nationkey, c_custkey, rk FROM (SELECT CAST(c_nationkey AS BIGINT) AS c_nationkey, c_custkey, CAST(row_number() OVER (PARTITION BY c_nationkey ORDER BY c_acctbal DESC, c_custkey) AS BIGINT) AS rk FROM customer) WHERE rk <= 3")
def rel_topk(sp, d):
    rank = F.row_number().over(Window.partitionBy("c_nationkey").orderBy(F.desc("c_acctbal"), "c_custkey")).cast("long")
    return load(sp, d, "customer", F.col("c_nationkey").cast("long").alias("c_nationkey"), "c_custkey", "c_acctbal").withColumn("rk", rank).where("rk <= 3").drop("c_acctbal")


@register("rel_lead_lag", "SELECT event_id, lag(event_type) OVER w AS before, lead(event_type) OVER w AS after FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def rel_lead_lag(sp, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return load(sp, d, "events", "event_id", "user_id", "ts", "event_type").select("event_id", F.lag("event_type").over(w).alias("before"), F.lead("event_type").over(w).alias("after"))


@register("rel_ranks", "SELECT p_partkey, CAST(rank() OVER w AS BIGINT) AS r, CAST(dense_rank() OVER w AS BIGINT) AS dr, CAST(ntile(4) OVER (PARTITION BY p_brand ORDER BY p_size, p_partkey) AS BIGINT) AS q FROM part WINDOW w AS (PARTITION BY p_brand ORDER BY p_size)")
def rel_ranks(sp, d):
    w = Window.partitionBy("p_brand").orderBy("p_size")
    return longs(load(sp, d, "part", "p_partkey", "p_brand", "p_size").select("p_partkey", F.rank().over(w).alias("r"), F.dense_rank().over(w).alias("dr"), F.ntile(4).over(Window.partitionBy("p_brand").orderBy("p_size", "p_partkey")).alias("q")))


@register("rel_cumulative", "SELECT o_orderkey, CAST(count(*) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS UNBOUNDED PRECEDING) AS BIGINT) AS nth FROM orders")
def rel_cumulative(sp, d):
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey").rowsBetween(Window.unboundedPreceding, 0)
    return load(sp, d, "orders", "o_orderkey", "o_custkey", "o_orderdate").select("o_orderkey", F.count("*").over(w).alias("nth"))


@register("rel_range_frame", "SELECT p_partkey, CAST(count(*) OVER (PARTITION BY p_brand ORDER BY p_size RANGE BETWEEN 2 PRECEDING AND 2 FOLLOWING) AS BIGINT) AS near FROM part")
def rel_range_frame(sp, d):
    w = Window.partitionBy("p_brand").orderBy("p_size").rangeBetween(-2, 2)
    return load(sp, d, "part", "p_partkey", "p_brand", "p_size").select("p_partkey", F.count("*").over(w).alias("near"))


@register("rel_intersect", "SELECT o_custkey AS k FROM orders WHERE o_orderstatus = 'F' INTERSECT SELECT o_custkey FROM orders WHERE o_orderstatus = 'O'")
def rel_intersect(sp, d):
    orders = load(sp, d, "orders", "o_custkey", "o_orderstatus")
    return orders.where("o_orderstatus = 'F'").select(F.col("o_custkey").alias("k")).intersect(orders.where("o_orderstatus = 'O'").select("o_custkey"))


@register("rel_except_all", "SELECT CAST(s_nationkey AS BIGINT) AS k FROM supplier EXCEPT ALL SELECT CAST(n_nationkey AS BIGINT) FROM nation")
def rel_except(sp, d):
    return load(sp, d, "supplier", F.col("s_nationkey").cast("long").alias("k")).exceptAll(load(sp, d, "nation", F.col("n_nationkey").cast("long").alias("k")))


@register("rel_union_all", "SELECT r_name AS name FROM region UNION ALL SELECT n_name FROM nation")
def rel_union(sp, d):
    return load(sp, d, "region", F.col("r_name").alias("name")).unionByName(load(sp, d, "nation", F.col("n_name").alias("name")))


@register("rel_json", "SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k FROM events")
def rel_json(sp, d):
    return load(sp, d, "events", "event_id", "props").select("event_id", F.from_json("props", "k long").getField("k").alias("k"))


@register("rel_split", "SELECT w AS word, CAST(count(*) AS BIGINT) AS n FROM (SELECT unnest(string_split_regex(lower(text), '[^a-z]+')) AS w FROM benchmark) WHERE w <> '' GROUP BY w")
def rel_split(sp, d):
    return load(sp, d, "benchmark", "text").select(F.explode(F.split(F.lower("text"), "[^a-z]+")).alias("word")).where("word <> ''").groupBy("word").agg(F.count("*").alias("n"))


@register("rel_array_functions", "SELECT vec_id, round(list_sum(list_transform(CAST(embedding AS DOUBLE[]), lambda x: x * x)), 6) AS square, CAST(len(list_filter(embedding, lambda x: x > 0)) AS BIGINT) AS positive FROM embeddings")
def rel_arrays(sp, d):
    wide = load(sp, d, "embeddings", "vec_id", F.transform("embedding", lambda x: x.cast("double")).alias("e"))
    return wide.select("vec_id", F.round(F.aggregate("e", F.lit(0.0), lambda s, x: s + x * x), 6).alias("square"), F.size(F.filter("e", lambda x: x > 0)).cast("long").alias("positive"))


@register("rel_map_functions", "SELECT user_id, array_to_string(list_sort(list(event_type || ':' || n)), ' ') AS kinds FROM (SELECT user_id, event_type, count(*) AS n FROM events GROUP BY 1, 2) GROUP BY user_id")
def rel_maps(sp, d):
    counts = load(sp, d, "events", "user_id", "event_type").groupBy("user_id", "event_type").agg(F.count("*").alias("n"))
    maps = counts.groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", F.col("n").cast("string")))).alias("m"))
    return maps.select("user_id", F.array_join(F.array_sort(F.transform(F.map_keys("m"), lambda k: F.concat(k, F.lit(":"), F.element_at("m", k)))), " ").alias("kinds"))


@register("rel_date_trunc", "SELECT date_trunc('month', o_orderdate) AS month, CAST(count(*) AS BIGINT) AS n FROM orders GROUP BY 1")
def rel_date(sp, d):
    return load(sp, d, "orders", F.date_trunc("month", "o_orderdate").cast("timestamp_ntz").alias("month")).groupBy("month").agg(F.count("*").alias("n"))


@register("rel_sessions", "SELECT user_id, CAST(count(*) AS BIGINT) AS sessions FROM (SELECT user_id, ts, lag(ts) OVER (PARTITION BY user_id ORDER BY ts) AS p FROM events) WHERE p IS NULL OR epoch_us(ts) - epoch_us(p) >= 3600000000 GROUP BY user_id")
def rel_sessions(sp, d):
    events = load(sp, d, "events", "user_id", F.col("ts").cast("timestamp").alias("ts"))
    return events.groupBy("user_id", F.session_window("ts", "1 hour")).agg(F.count("*").alias("n")).groupBy("user_id").agg(F.count("*").alias("sessions"))


@register("rel_conditional", "SELECT s_suppkey, CASE WHEN s_acctbal < 0 THEN 'debt' WHEN s_acctbal < 1000 THEN 'low' ELSE 'high' END AS class, nullif(CAST(s_nationkey AS BIGINT), 0) AS nation FROM supplier WHERE s_name LIKE 'Supplier%' AND s_acctbal BETWEEN -500 AND 9000")
def rel_conditional(sp, d):
    s = load(sp, d, "supplier").where(F.col("s_name").like("Supplier%") & F.col("s_acctbal").between(-500, 9000))
    return s.select("s_suppkey", F.when(F.col("s_acctbal") < 0, "debt").when(F.col("s_acctbal") < 1000, "low").otherwise("high").alias("class"), F.nullif(F.col("s_nationkey").cast("long"), F.lit(0).cast("long")).alias("nation"))


@register("rel_statistics", "SELECT l_returnflag, CAST(count(DISTINCT l_partkey) AS BIGINT) AS parts, round(median(l_quantity), 6) AS mid, round(stddev_samp(l_quantity), 6) AS spread FROM lineitem GROUP BY l_returnflag")
def rel_statistics(sp, d):
    return load(sp, d, "lineitem", "l_returnflag", "l_partkey", "l_quantity").groupBy("l_returnflag").agg(F.countDistinct("l_partkey").alias("parts"), F.round(F.median("l_quantity"), 6).alias("mid"), F.round(F.stddev_samp("l_quantity"), 6).alias("spread"))


@register("rel_top_limit", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 10 OFFSET 5")
def rel_top(sp, d):
    return load(sp, d, "orders", "o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").offset(5).limit(10)


@register("rel_approx_distinct")
def rel_approx(sp, d):
    return load(sp, d, "lineitem", "l_returnflag", "l_orderkey").groupBy("l_returnflag").agg(F.approx_count_distinct("l_orderkey", 0.02).alias("orders"))


@register("rel_join_hints", "SELECT n_name, CAST(count(*) AS BIGINT) AS suppliers FROM supplier JOIN nation ON s_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey WHERE r_name <> 'ASIA' GROUP BY n_name")
def rel_join_hints(sp, d):
    """The fixed-size tables are broadcast, the growing side is told to sort-merge otherwise."""
    supplier = load(sp, d, "supplier", "s_nationkey").hint("merge")
    nations = load(sp, d, "nation", "n_nationkey", "n_name", "n_regionkey")
    region = load(sp, d, "region", "r_regionkey", "r_name").where("r_name <> 'ASIA'")
    return supplier.join(nations, F.col("s_nationkey") == F.col("n_nationkey")).join(F.broadcast(region), F.col("n_regionkey") == F.col("r_regionkey")).groupBy("n_name").agg(F.count("*").alias("suppliers"))


@register("rel_self_theta", "SELECT x.o_custkey AS k, CAST(count(*) AS BIGINT) AS pairs FROM orders x JOIN orders y ON x.o_custkey = y.o_custkey AND x.o_orderdate < y.o_orderdate AND x.o_totalprice > y.o_totalprice GROUP BY x.o_custkey")
def rel_self_theta(sp, d):
    orders = load(sp, d, "orders", "o_custkey", "o_orderdate", "o_totalprice")
    later = orders.select("o_custkey", F.col("o_orderdate").alias("d2"), F.col("o_totalprice").alias("p2"))
    return orders.join(later, "o_custkey").where("o_orderdate < d2 and o_totalprice > p2").groupBy(F.col("o_custkey").alias("k")).agg(F.count("*").alias("pairs"))
