"""Graphs built from the given tables. Each returns (edges, vertices); see FIXTURES.md for the definitions.

Every builder reads only the columns it needs; nothing is collected.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..graph import normalize_edges, ranked
from ..storage import LevelStore

Tables = tuple[DataFrame, DataFrame]


def load(spark: SparkSession, folder: str, name: str, *columns: str) -> DataFrame:
    frame = spark.read.parquet(f"{folder}/{name}.parquet")
    return frame.select(*columns) if columns else frame


def strongest(pairs: DataFrame, top: int) -> DataFrame:
    """Pairs (a, b, w) that one of the ends ranks among its ``top`` partners: weight first, then the partner."""
    keys = [c for c in pairs.columns if c not in ("a", "b", "w")]
    ends = F.array(F.struct("a", "b"), F.struct(F.col("b").alias("a"), F.col("a").alias("b")))
    both = pairs.select(*keys, "w", F.explode(ends).alias("e")).select(*keys, "e.a", "e.b", "w")
    return best(both, top, *keys).select(*keys, "a", "b")


def best(both: DataFrame, top: int, *keys: str) -> DataFrame:
    """Rows (a, b, w) that rank among the ``top`` of their a (of their graph, where there is a key)."""
    rank = F.row_number().over(Window.partitionBy(*keys, "a").orderBy(F.desc("w"), "b"))
    return both.withColumn("rank", rank).where(F.col("rank") <= top).drop("rank")


def nation(spark: SparkSession, folder: str, top: int) -> Tables:
    """Nations and their strongest trade partners (customer nation with supplier nation)."""
    items = load(spark, folder, "lineitem", "l_orderkey", "l_suppkey")
    orders = load(spark, folder, "orders", "o_orderkey", "o_custkey")
    customer = load(spark, folder, "customer", "c_custkey", F.col("c_nationkey").alias("x"))
    supplier = load(spark, folder, "supplier", "s_suppkey", F.col("s_nationkey").alias("y"))
    joined = items.join(orders, items.l_orderkey == orders.o_orderkey).join(customer, orders.o_custkey == customer.c_custkey).join(supplier, items.l_suppkey == supplier.s_suppkey)
    pairs = joined.where("x <> y").groupBy(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b")).agg(F.count("*").alias("w"))
    return normalize_edges(strongest(pairs, top), bounded=True)


def brand(spark: SparkSession, folder: str, top: int) -> Tables:
    """Brands and the brands that most orders hold with them."""
    items = load(spark, folder, "lineitem", "l_orderkey", "l_partkey").join(load(spark, folder, "part", "p_partkey", "p_brand"), F.col("l_partkey") == F.col("p_partkey"))
    held = items.select("l_orderkey", "p_brand").distinct()
    pairs = held.withColumnRenamed("p_brand", "a").join(held.withColumnRenamed("p_brand", "b"), "l_orderkey").where("a < b").groupBy("a", "b").agg(F.count("*").alias("w"))
    return normalize_edges(strongest(pairs, top), bounded=True)


def embedding(spark: SparkSession, folder: str, size: int, top: int) -> Tables:
    """The first ``size`` vectors and their nearest ones by cosine, rounded to six digits. ``size`` is the graph's and bounds the pairs."""
    some = load(spark, folder, "embeddings", "vec_id", "embedding").where(F.col("vec_id") < size)
    wide = some.select("vec_id", F.transform("embedding", lambda x: x.cast("double")).alias("e"))
    norm = wide.withColumn("norm", F.sqrt(F.aggregate("e", F.lit(0.0), lambda s, x: s + x * x)))
    left, right = (norm.select(F.col("vec_id").alias(i), F.col("e").alias(f"e{i}"), F.col("norm").alias(f"n{i}")) for i in "ab")
    dot = F.aggregate(F.zip_with("ea", "eb", lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)
    pairs = left.crossJoin(right).where("a < b").select("a", "b", F.round(dot / (F.col("na") * F.col("nb")), 6).alias("w"))
    return normalize_edges(strongest(pairs, top))


#: Vectors of a block; a task holds two blocks, and cosines of SLICE rows at a time.
BLOCK, SLICE = 4096, 256


def nearest_in_block(ids: np.ndarray, unit: np.ndarray, other_ids: np.ndarray, other: np.ndarray, top: int) -> pd.DataFrame:
    """(a, b, w): for each of ``ids`` its ``top`` best in another block, least id first among equals."""
    order = np.argsort(other_ids, kind="stable")
    other_ids, other = other_ids[order], other[order]
    out = []
    for at in range(0, len(ids), SLICE):
        w = np.round(unit[at : at + SLICE] @ other.T, 6)
        w[(ids[at : at + SLICE, None] == other_ids[None, :]) | np.isnan(w)] = -np.inf
        least = np.partition(w, -min(top, w.shape[1]), axis=1)[:, -min(top, w.shape[1])]
        row, col = np.nonzero((w >= least[:, None]) & (w > -np.inf))
        found = pd.DataFrame({"a": ids[at + row], "b": other_ids[col], "w": w[row, col]}).sort_values(["a", "w", "b"], ascending=[True, False, True])
        out.append(found[found.groupby("a").cumcount() < top])
    return pd.concat(out)


def embedding_all(spark: SparkSession, folder: str, top: int, block: int = BLOCK) -> Tables:
    """As embedding, over all vectors: each pair of blocks is one task's work and leaves ``top`` rows a vector.

    Vectors of length zero have no cosine and no nearest ones.
    """
    some = load(spark, folder, "embeddings", "vec_id", "embedding").where("vec_id is not null and embedding is not null")
    blocks = max(1, -(-some.count() // block))
    mine = F.pmod(F.xxhash64("vec_id"), F.lit(blocks)).cast("int")
    others = F.sequence(F.lit(0), F.lit(blocks - 1))
    # Each unordered pair of blocks (i <= j) gets the rows of both.
    spread = some.select(mine.alias("block"), "vec_id", F.col("embedding").cast("array<float>").alias("embedding"), F.explode(others).alias("with"))
    spread = spread.select(F.least("block", "with").alias("i"), F.greatest("block", "with").alias("j"), "block", "vec_id", "embedding")

    def run(key: tuple, rows: pd.DataFrame) -> pd.DataFrame:
        wide = np.stack(rows["embedding"].to_numpy()).astype(np.float64)
        with np.errstate(invalid="ignore", divide="ignore"):
            wide /= np.sqrt((wide * wide).sum(axis=1, keepdims=True))
        ids, own = rows["vec_id"].to_numpy(np.int64), rows["block"].to_numpy()
        sides = [(ids[own == x], wide[own == x]) for x in key]
        turns = [(0, 1), (1, 0)] if key[0] != key[1] else [(0, 0)]
        found = [nearest_in_block(*sides[x], *sides[y], top) for x, y in turns if len(sides[x][0]) and len(sides[y][0])]
        return pd.concat(found) if found else pd.DataFrame({"a": [], "b": [], "w": []})

    near = spread.groupBy("i", "j").applyInPandas(run, "a long, b long, w double")
    return normalize_edges(best(near, top).select("a", "b"))


def letter(spark: SparkSession, folder: str, lang: str, count: int) -> Tables:
    """The most frequent pairs of adjacent different letters in one language's texts."""
    text = load(spark, folder, "documents", "text", "lang").where(F.col("lang") == lang)
    runs = text.select(F.explode(F.regexp_extract_all(F.lower("text"), F.lit("([a-z]{2,})"), F.lit(1))).alias("run"))
    words = runs.groupBy("run").agg(F.count("*").alias("n"))
    spots = words.select("n", "run", F.explode(F.sequence(F.lit(1), F.length("run") - 1)).alias("i"))
    letters = spots.select("n", F.expr("substring(run, i, 1)").alias("x"), F.expr("substring(run, i + 1, 1)").alias("y")).where("x <> y")
    pairs = letters.groupBy(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b")).agg(F.sum("n").alias("w"))
    return normalize_edges(pairs.orderBy(F.desc("w"), "a", "b").limit(count), bounded=True)


def letter_all(spark: SparkSession, folder: str) -> Tables:
    """Per language, all pairs of adjacent different letters; a null language is a graph named null."""
    text = load(spark, folder, "documents", "text", "lang")
    runs = text.select(F.coalesce("lang", F.lit("null")).alias("g"), F.explode(F.regexp_extract_all(F.lower("text"), F.lit("([a-z]{2,})"), F.lit(1))).alias("run")).distinct()
    spots = runs.select("g", "run", F.explode(F.sequence(F.lit(1), F.length("run") - 1)).alias("i"))
    return normalize_edges(spots.select("g", F.expr("substring(run, i, 1)").alias("a"), F.expr("substring(run, i + 1, 1)").alias("b")), graph=F.col("g"))


def letters(spark: SparkSession, folder: str, top: int) -> Tables:
    """Per language, each letter and its most frequent neighbours in all texts."""
    text = load(spark, folder, "documents", "text", "lang")
    runs = text.select(F.coalesce("lang", F.lit("null")).alias("g"), F.explode(F.regexp_extract_all(F.lower("text"), F.lit("([a-z]{2,})"), F.lit(1))).alias("run"))
    words = runs.groupBy("g", "run").agg(F.count("*").alias("n"))
    spots = words.select("g", "n", "run", F.explode(F.sequence(F.lit(1), F.length("run") - 1)).alias("i"))
    pairs = spots.select("g", "n", F.expr("substring(run, i, 1)").alias("x"), F.expr("substring(run, i + 1, 1)").alias("y")).where("x <> y")
    pairs = pairs.groupBy("g", F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b")).agg(F.sum("n").alias("w"))
    return normalize_edges(strongest(pairs, top), graph=F.col("g"))


def months(spark: SparkSession, folder: str, top: int) -> Tables:
    """Months of orders and of their shipments, each with the months that most items join it to."""
    orders = load(spark, folder, "orders", "o_orderkey", F.month("o_orderdate").alias("x"))
    items = load(spark, folder, "lineitem", "l_orderkey", F.month("l_shipdate").alias("y"))
    joined = orders.join(items, F.col("o_orderkey") == F.col("l_orderkey")).where("x <> y")
    return normalize_edges(strongest(joined.groupBy(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b")).agg(F.count("*").alias("w")), top), bounded=True)


def status(spark: SparkSession, folder: str) -> Tables:
    """States of orders and their priorities."""
    rows = load(spark, folder, "orders", "o_orderstatus", "o_orderpriority").distinct()
    return normalize_edges(rows.select(F.concat(F.lit("s"), "o_orderstatus").alias("a"), F.concat(F.lit("p"), "o_orderpriority").alias("b")), bounded=True)


def segment(spark: SparkSession, folder: str) -> Tables:
    """Market segments of customers and priorities of their orders."""
    orders = load(spark, folder, "orders", "o_custkey", "o_orderpriority")
    rows = orders.join(load(spark, folder, "customer", "c_custkey", "c_mktsegment"), F.col("o_custkey") == F.col("c_custkey"))
    return normalize_edges(rows.select(F.concat(F.lit("s"), "c_mktsegment").alias("a"), F.concat(F.lit("p"), "o_orderpriority").alias("b")).distinct(), bounded=True)


def shared_lines(documents: DataFrame, length: int) -> Tables:
    """(cover, vertices): line and vid of documents that hold the same line of more than ``length`` signs.

    Lines in equal sets of documents are one. Lines are numbered from the most documents down.
    """
    spark = documents.sparkSession
    held = documents.select("doc_id", F.explode(F.split("text", "\n")).alias("line")).where(F.length("line") > length).where("doc_id is not null")
    sets = held.groupBy("line").agg(F.array_sort(F.collect_set("doc_id")).alias("docs")).where("size(docs) > 1").select("docs").distinct()
    lines, labels = LevelStore(spark, "lines"), LevelStore(spark, "labels")
    sets = lines.write(sets.select(F.lit("g").alias("graph_id"), F.struct((-F.size("docs")).alias("n"), "docs").alias("label")), 0, 0)
    shared = ranked(sets, lines).select(F.col("vid").alias("line"), F.explode("label.docs").alias("label"))
    shared = lines.write(shared, 0, 2)
    vertices = ranked(shared.select(F.lit("g").alias("graph_id"), "label").distinct(), labels)
    cover = lines.write(shared.join(vertices, "label").select("line", "vid"), 0, 3)
    return cover, vertices.select("graph_id", "vid", F.col("label").cast("string").alias("label"))


#: Pairs of documents, at most, that one row of work holds, and about as many in one Arrow batch.
PAIRS, BATCH = 1 << 22, 1 << 17


def cover_edges(cover: DataFrame) -> DataFrame:
    """(graph_id, u, v), each pair once: by the line of most documents that holds both.

    A line's documents are cut into blocks, and two blocks are one row of work, with the lines before it
    that each document holds; so a task holds two blocks, and no pair is shuffled. A document
    leaves Python once a row of work, with all its partners in one array, which the JVM unfolds: that is
    cheaper than pairs that cross as rows.
    """
    spark = cover.sparkSession
    own = cover.groupBy("vid").agg(F.collect_list("line").alias("own"))
    known = cover.join(own, "vid").select("line", F.struct("vid", F.expr("filter(own, x -> x < line)").alias("before")).alias("m"))
    lines = known.groupBy("line").agg(F.array_sort(F.collect_list("m")).alias("m"))
    side = math.isqrt(PAIRS)
    last = F.floor((F.size("m") - 1) / side).cast("int")
    work = lines.select("line", "m", F.explode(F.sequence(F.lit(0), last)).alias("i"), last.alias("last"))
    work = work.select("line", "m", "i", F.explode(F.sequence("i", "last")).alias("j"))
    block = lambda k: F.slice("m", F.col(k) * side + 1, F.lit(side))
    work = work.select("line", "i", "j", block("i").alias("us"), F.when(F.col("i") < F.col("j"), block("j")).alias("vs"))

    def run(batches):
        us, vs, held = [], [], 0
        for batch in batches:
            for k in range(batch.num_rows):
                sides = [batch.column(x).slice(k, 1) for x in ("us", "vs")]
                sides = [x.flatten() for x in sides if x.null_count == 0]
                for u, v in block_pairs(*[(x.field("vid").to_numpy(), x.field("before")) for x in sides]):
                    us.append(u)
                    vs.append(v)
                    held += len(v)
                    if held >= BATCH:
                        yield pair_batch(us, vs)
                        us, vs, held = [], [], 0
        if us:
            yield pair_batch(us, vs)

    parts = max(int(spark.conf.get("spark.sql.shuffle.partitions")), spark.sparkContext.defaultParallelism)
    pairs = work.repartition(parts, "line", "i", "j").mapInArrow(run, "u int, v array<int>")
    return pairs.select("u", F.explode("v").alias("v")).select(F.lit("g").alias("graph_id"), "u", "v")


def pair_batch(us: list[int], vs: list[np.ndarray]) -> pa.RecordBatch:
    ends = np.cumsum([0, *map(len, vs)], dtype=np.int32)
    return pa.RecordBatch.from_arrays([pa.array(us, pa.int32()), pa.ListArray.from_arrays(pa.array(ends), pa.array(np.concatenate(vs)))], ["u", "v"])


Block = tuple[np.ndarray, pa.ListArray]


def block_pairs(left: Block, right: Block | None = None) -> Iterator[tuple[int, np.ndarray]]:
    """(u, partners) of each document of a block with all of another block, or with all after it in its own, without those that share a line before."""
    (us, before), (vs, theirs) = left, right or left
    others = theirs.flatten().to_numpy()
    owner = np.repeat(np.arange(len(vs)), theirs.value_lengths().to_numpy())
    order = np.argsort(others, kind="stable")
    found, first = np.unique(others[order], return_index=True)
    holders = dict(zip(found.tolist(), np.split(owner[order], first[1:])))
    mine, ends = before.flatten().to_numpy(), np.cumsum(before.value_lengths().to_numpy())
    for i, (u, end, start) in enumerate(zip(us.tolist(), ends.tolist(), [0, *ends.tolist()])):
        at = 0 if right else i + 1
        v = vs[at:]
        shared = [holders[x] for x in mine[start:end].tolist() if x in holders]
        if any(len(x) > (not right) for x in shared):
            free = np.ones(len(vs), bool)
            for x in shared:
                free[x] = False
            v = v[free[at:]]
        if len(v):
            yield u, v


def docline_cover(spark: SparkSession, folder: str, length: int) -> Tables:
    return shared_lines(load(spark, folder, "documents", "doc_id", "text"), length)


def docline(spark: SparkSession, folder: str, length: int) -> Tables:
    cover, vertices = docline_cover(spark, folder, length)
    return cover_edges(cover), vertices


def doclabel(spark: SparkSession, folder: str, length: int) -> Tables:
    """As docline, among documents labelled as good."""
    good = load(spark, folder, "labels", "doc_id", "quality").where("quality = 1")
    cover, vertices = shared_lines(load(spark, folder, "documents", "doc_id", "text").join(good, "doc_id", "left_semi"), length)
    return cover_edges(cover), vertices


def coactive(spark: SparkSession, folder: str, users: int | None = None) -> Tables:
    """Users (those below a limit, if one is given) with an event in the same minute."""
    seen = load(spark, folder, "events", "user_id", F.date_trunc("minute", "ts").alias("minute"))
    seen = (seen if users is None else seen.where(F.col("user_id") < users)).distinct()
    return normalize_edges(seen.withColumnRenamed("user_id", "a").join(seen.withColumnRenamed("user_id", "b"), "minute").where("a < b"))


def userstep(spark: SparkSession, folder: str) -> Tables:
    """Per user, the event types that follow one another."""
    events = load(spark, folder, "events", "event_id", "ts", "user_id", "event_type")
    after = F.lead("event_type").over(Window.partitionBy("user_id").orderBy("ts", "event_id"))
    return normalize_edges(events.select("user_id", F.col("event_type").alias("a"), after.alias("b")), graph=F.col("user_id"))


def partsupp(spark: SparkSession, folder: str, parts: int | None = None, suppliers: int | None = None) -> Tables:
    """Parts and their suppliers (keys below the limits, if any are given): a bipartite graph."""
    rows = load(spark, folder, "lineitem", "l_partkey", "l_suppkey")
    for column, limit in (("l_partkey", parts), ("l_suppkey", suppliers)):
        rows = rows if limit is None else rows.where(F.col(column) < limit)
    return normalize_edges(rows.select(F.concat(F.lit("p"), "l_partkey").alias("a"), F.concat(F.lit("s"), "l_suppkey").alias("b")))


def host(spark: SparkSession, folder: str) -> Tables:
    """Hosts of pages and the targets of their links."""
    pages = load(spark, folder, "pages", "url", "html")
    target = F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1)))
    return normalize_edges(pages.select(F.regexp_extract("url", "^[a-z]+://([^/]+)", 1).alias("a"), target.alias("b")))


def adjacent_words(graph: Column, text: Column, frame: DataFrame) -> DataFrame:
    words = F.filter(F.split(F.lower(text), "[^a-z]+"), lambda w: w != "")
    rows = frame.select(graph.cast("string").alias("g"), words.alias("w")).where("size(w) > 1")
    return rows.select("g", F.explode(F.arrays_zip(F.slice("w", F.lit(1), F.size("w") - 1).alias("a"), F.slice("w", F.lit(2), F.size("w") - 1).alias("b"))).alias("p")).select("g", "p.a", "p.b")


def turn(spark: SparkSession, folder: str) -> Tables:
    """Per turn of a conversation, words that follow one another."""
    rows = load(spark, folder, "conversations", "conv_id", "turn", "text")
    return normalize_edges(adjacent_words(F.concat_ws("/", F.col("conv_id").cast("string"), F.col("turn").cast("string")), F.col("text"), rows), graph=F.col("g"))


def benchword(spark: SparkSession, folder: str) -> Tables:
    """Per benchmark item, words that follow one another."""
    rows = load(spark, folder, "benchmark", "item_id", "text")
    return normalize_edges(adjacent_words(F.col("item_id"), F.col("text"), rows), graph=F.col("g"))


def geo(spark: SparkSession, folder: str) -> Tables:
    """Regions and their nations."""
    region, nations = load(spark, folder, "region", "r_regionkey", "r_name"), load(spark, folder, "nation", "n_regionkey", "n_name")
    return normalize_edges(region.join(nations, F.col("r_regionkey") == F.col("n_regionkey")).select(F.col("r_name").alias("a"), F.col("n_name").alias("b")), bounded=True)
