"""Line deduplication by a sharded minimal perfect hash over distinct line hashes.

keep_first(), which the query uses: of each line (trimmed, not empty) the first occurrence
stays, by least doc_id (null before all), then position; every other one goes, also inside
one document. One aggregation over 64-bit line hashes finds the lines that occur more than
once and the document of the first occurrence; the perfect hash of a shard holds the hash
and that document at its indexes, and only lines that occur once are not in it. Rows that
share a doc_id are ordered by a hash of their text; of equal rows one is the first.

deduplicate(), a rule with a bound, which empties documents of boilerplate only: a line
that stands in more than ``max_docs`` documents leaves all of them. The number of documents per line is found by one aggregation over
64-bit line hashes; the hashes are spread over shards, and each shard gets a minimal
perfect hash (levels of bit arrays: a key settles on the first level where it has a place
to itself, its index is the rank of that bit), with a compact array of 32-bit
fingerprints and one of document counts at these indexes. Documents probe the arrays by
hash; lines are never joined, compared or carried.

The arrays of all shards together are broadcast if they have at most ``LOCAL_BYTES``, a
size that is known before; otherwise hashes are routed to the shard that holds them, each
shard answers its probes from its arrays, and the answers return to the documents. Both
ways give the same rows.

Edge cases: null and empty texts have no lines and stay as they are; null doc_ids and
repeated rows are documents like others (repeated rows count each); the counts hold as
32-bit integers.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Observation, Window
from pyspark.sql import functions as F

from .common import U64, Scratch, mix64

MAX_DOCS, SHARD_KEYS, LOCAL_BYTES, GAMMA, LEVELS = 10, 1 << 20, 64 << 20, 1.5, 48
SALTS = 4
#: Lines that one task looks up.
PROBES = 1 << 22


class PerfectHash:
    """Minimal perfect hash of distinct 64-bit keys, as bit arrays by level."""

    def __init__(self, levels: list[np.ndarray], rest: np.ndarray):
        self.levels, self.rest = levels, rest
        counts = [np.concatenate([[0], np.cumsum(np.bitwise_count(bits), dtype=np.int64)]) for bits in levels]
        self.ranks = counts
        self.bases = np.concatenate([[0], np.cumsum([c[-1] for c in counts])]).astype(np.int64)

    @classmethod
    def build(cls, keys: np.ndarray) -> PerfectHash:
        """Levels are tried until every key has a place; the few left after LEVELS are listed, sorted."""
        levels = []
        left = keys.astype(U64)
        for level in range(LEVELS):
            if not len(left):
                break
            size = max(64, int(GAMMA * len(left)) + 63 & ~63)
            place = cls.place(left, level, size)
            alone = np.bincount(place, minlength=size) == 1
            levels.append(np.packbits(alone, bitorder="little").view(U64))
            left = left[~alone[place]]
        return cls(levels, np.sort(left))

    @staticmethod
    def place(keys: np.ndarray, level: int, size: int) -> np.ndarray:
        return (mix64(keys + U64((level + 1) * 0x9E3779B97F4A7C15 & (1 << 64) - 1)) % U64(size)).astype(np.int64)

    def index(self, keys: np.ndarray) -> np.ndarray:
        """Index of each key in 0 .. n - 1; -1 for a key that is seen to be foreign."""
        out = np.full(len(keys), -1, np.int64)
        todo = np.arange(len(keys))
        keys = keys.astype(U64)
        for level, bits in enumerate(self.levels):
            if not len(todo):
                return out
            place = self.place(keys[todo], level, 64 * len(bits))
            word, bit = place >> 6, (place & 63).astype(U64)
            hit = (bits[word] >> bit & U64(1)).astype(bool)
            below = np.bitwise_count(bits[word] & ((U64(1) << bit) - U64(1))).astype(np.int64)
            out[todo[hit]] = (self.bases[level] + self.ranks[level][word] + below)[hit]
            todo = todo[~hit]
        if len(todo) and len(self.rest):
            at = np.minimum(np.searchsorted(self.rest, keys[todo]), len(self.rest) - 1)
            out[todo] = np.where(self.rest[at] == keys[todo], self.bases[-1] + at, -1)
        return out

    def blob(self) -> bytes:
        head = np.array([len(self.levels), *map(len, self.levels), len(self.rest)], np.int64)
        return head.tobytes() + b"".join(x.tobytes() for x in [*self.levels, self.rest])

    @classmethod
    def of_blob(cls, blob: bytes) -> PerfectHash:
        n = int(np.frombuffer(blob, np.int64, 1)[0])
        sizes = np.frombuffer(blob, np.int64, n + 1, 8)
        words = np.frombuffer(blob, U64, offset=8 * (n + 2))
        ends = np.concatenate([[0], np.cumsum(sizes)])
        return cls([words[a:b] for a, b in zip(ends[:n], ends[1 : n + 1])], words[ends[n] : ends[n + 1]])


def fingerprint(keys: np.ndarray) -> np.ndarray:
    return (mix64(keys.astype(U64) ^ U64(0xD6E8FEB86659FD93)) >> U64(32)).astype(np.uint32)


class Shard:
    """Perfect hash, fingerprints and counts of one shard."""

    def __init__(self, function: PerfectHash, prints: np.ndarray, counts: np.ndarray):
        self.function, self.prints, self.counts = function, prints, counts

    @classmethod
    def build(cls, keys: np.ndarray, counts: np.ndarray) -> Shard:
        function = PerfectHash.build(keys)
        at = function.index(keys)
        prints, held = np.empty(len(keys), np.uint32), np.empty(len(keys), np.uint32)
        prints[at], held[at] = fingerprint(keys), np.minimum(counts, 0xFFFFFFFF)
        return cls(function, prints, held)

    def probe(self, keys: np.ndarray) -> np.ndarray:
        """Count of each key, 0 for a key that the fingerprint shows to be foreign."""
        if not len(self.prints):
            return np.zeros(len(keys), np.int64)
        at = self.function.index(keys)
        good = (at >= 0) & (self.prints[at] == fingerprint(keys))
        return np.where(good, self.counts[at], 0).astype(np.int64)

    def blob(self) -> bytes:
        return np.int64(len(self.prints)).tobytes() + self.prints.tobytes() + self.counts.tobytes() + self.function.blob()

    @classmethod
    def of_blob(cls, blob: bytes) -> Shard:
        n = int(np.frombuffer(blob, np.int64, 1)[0])
        prints, counts = np.frombuffer(blob, np.uint32, n, 8), np.frombuffer(blob, np.uint32, n, 8 + 4 * n)
        return cls(PerfectHash.of_blob(bytes(blob[8 + 8 * n :])), prints, counts)


class Firsts:
    """Perfect hash of the repeated lines of one shard, their hashes and owners (the row that keeps its first one)."""

    def __init__(self, function: PerfectHash, keys: np.ndarray, owners: np.ndarray):
        self.function, self.keys, self.owners = function, keys, owners

    @classmethod
    def build(cls, keys: np.ndarray, owners: np.ndarray) -> Firsts:
        function = PerfectHash.build(keys)
        at = function.index(keys)
        held, owner = np.empty(len(keys), U64), np.empty(len(keys), np.int64)
        held[at], owner[at] = keys, owners
        return cls(function, held, owner)

    def probe(self, keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(is the line repeated, its owner)."""
        if not len(self.keys):
            return np.zeros(len(keys), bool), np.zeros(len(keys), np.int64)
        at = self.function.index(keys)
        return (at >= 0) & (self.keys[at] == keys), self.owners[at]

    def blob(self) -> bytes:
        return np.int64(len(self.keys)).tobytes() + self.keys.tobytes() + self.owners.tobytes() + self.function.blob()

    @classmethod
    def of_blob(cls, blob: bytes) -> Firsts:
        n = int(np.frombuffer(blob, np.int64, 1)[0])
        return cls(PerfectHash.of_blob(bytes(blob[8 + 16 * n :])), np.frombuffer(blob, U64, n, 8), np.frombuffer(blob, np.int64, n, 8 + 8 * n))


def later_ones(rows: np.ndarray, hashes: np.ndarray) -> np.ndarray:
    """Which of the lines, in order, have stood before in the same row."""
    order = np.lexsort((hashes, rows))
    again = np.zeros(len(rows), bool)
    again[order[1:]] = (rows[order[1:]] == rows[order[:-1]]) & (hashes[order[1:]] == hashes[order[:-1]])
    return again


def line_array(text: Column) -> Column:
    return F.split(F.coalesce(text.cast("string"), F.lit("")), "\n")


def bare_line(line: Column) -> Column:
    """A line without white space (ASCII) at its ends."""
    return F.btrim(line, F.lit(" \t\n\x0b\f\r"))


def line_hashes(lines: Column) -> Column:
    """Hash of each line without its outer white space, 0 for a blank line."""
    return F.transform(F.transform(lines, bare_line), lambda x: F.when(x == "", F.lit(0).cast("long")).otherwise(F.xxhash64(x)))


def build_shards(hashes: DataFrame, shards: int) -> DataFrame:
    """(shard, keys, blob) from a column ``hashes`` with the distinct line hashes of each document."""
    counted = hashes.select(F.explode("hashes").alias("hash")).where("hash <> 0").groupBy("hash").agg(F.count("*").alias("docs"))

    def build(table: pd.DataFrame) -> pd.DataFrame:
        shard = Shard.build(table["hash"].to_numpy(np.int64).view(U64), table["docs"].to_numpy(np.int64))
        return pd.DataFrame({"shard": [int(table["shard"].iloc[0])], "n": [len(table)], "blob": [shard.blob()]})

    return counted.withColumn("shard", F.pmod(F.col("hash"), F.lit(shards)).cast("int")).groupBy("shard").applyInPandas(build, "shard int, n long, blob binary")


def deduplicate(documents: DataFrame, max_docs: int = MAX_DOCS, local_bytes: int = LOCAL_BYTES, shard_keys: int = SHARD_KEYS) -> DataFrame:
    """(doc_id, kept_text, lines, dropped) of every row; the blank lines between stay."""
    spark = documents.sparkSession
    scratch = Scratch(spark, "lines")
    base = documents.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    hashes = base.select(line_hashes(line_array(F.col("text"))).alias("all")).select(F.array_distinct("all").alias("hashes"))
    total = hashes.select(F.explode("hashes").alias("hash")).agg(F.approx_count_distinct("hash", 0.02)).first()[0]
    shards = max(1, -(-total // shard_keys))
    arrays = scratch.keep(build_shards(hashes, shards), "arrays")
    size = arrays.agg(F.coalesce(F.sum(F.length("blob")), F.lit(0))).first()[0]
    if size <= local_bytes:
        held = spark.sparkContext.broadcast({r.shard: bytes(r.blob) for r in arrays.toLocalIterator()})

        def probe(batches):
            tables = {k: Shard.of_blob(b) for k, b in held.value.items()}
            for batch in batches:
                column = batch.column("hashes")
                flat = np.asarray(column.flatten()).astype(np.int64)
                counts = np.zeros(len(flat), np.int64)
                owner = np.mod(flat, shards)
                for k, table in tables.items():
                    mine = np.flatnonzero((owner == k) & (flat != 0))
                    if len(mine):
                        counts[mine] = table.probe(flat[mine].view(U64))
                lengths = np.asarray(column.value_lengths()).astype(np.int64)
                ends = np.concatenate([[0], np.cumsum(lengths)]).astype(np.int32)
                yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("text"), pa.ListArray.from_arrays(pa.array(ends), pa.array(counts > max_docs))], ["doc_id", "text", "common"])

        source = base.select("doc_id", "text", line_hashes(line_array(F.col("text"))).alias("hashes"))
        marked = source.mapInArrow(probe, "doc_id long, text string, common array<boolean>")
        return _keep(marked, F.col("common"))
    numbered = scratch.keep(base.withColumn("row", F.monotonically_increasing_id()), "rows")
    asked = numbered.select("row", F.posexplode(line_hashes(line_array(F.col("text")))).alias("at", "hash")).where("hash <> 0")
    # Arrays go to SALTS tasks each, so a line of very many documents doesn't go to one task.
    probes = asked.select(F.pmod("hash", F.lit(shards)).cast("int").alias("shard"), F.pmod("row", F.lit(SALTS)).cast("int").alias("salt"), F.lit(1).alias("kind"), "row", "at", "hash", F.lit(None).cast("binary").alias("blob"))
    nothing = [F.lit(None).cast(t).alias(n) for n, t in (("row", "long"), ("at", "int"), ("hash", "long"))]
    copies = arrays.select("shard", F.explode(F.array(*[F.lit(k) for k in range(SALTS)])).alias("salt"), F.lit(0).alias("kind"), *nothing, "blob")
    routed = probes.unionByName(copies).repartition("shard", "salt").sortWithinPartitions("shard", "salt", "kind")

    def answer(batches):
        table = None
        for batch in batches:
            kinds = np.asarray(batch.column("kind"))
            edges = [*np.flatnonzero(kinds == 0), batch.num_rows]
            spans = [(None, 0, edges[0])] + [(k, k + 1, n) for k, n in zip(edges, edges[1:])]
            for k, a, b in spans:
                if k is not None:
                    table = Shard.of_blob(batch.column("blob")[int(k)].as_py())
                if b > a:
                    part = batch.slice(a, b - a)
                    counts = table.probe(np.asarray(part.column("hash")).astype(np.int64).view(U64))
                    yield part.select(["row", "at"]).filter(pa.array(counts > max_docs))

    gone_lines = routed.mapInArrow(answer, "row long, at int")
    dropped = gone_lines.groupBy("row").agg(F.collect_set("at").alias("gone"))
    joined = numbered.join(dropped, "row", "left")
    gone = F.coalesce(F.col("gone"), F.array().cast("array<int>"))
    flags = F.transform(line_array(F.col("text")), lambda x, k: F.array_contains(gone, k))
    return _keep(joined.select("doc_id", "text", flags.alias("common")), F.col("common"))


def keep_first(documents: DataFrame, local_bytes: int = LOCAL_BYTES, shard_keys: int = SHARD_KEYS) -> DataFrame:
    """(doc_id, kept_text, lines, dropped) of every row: one occurrence of each line stays; blank lines stay."""
    spark = documents.sparkSession
    scratch = Scratch(spark, "lines")
    base = documents.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    place = F.coalesce("doc_id", F.lit(-(1 << 63)).cast("long"))
    if base.select(place.alias("place")).groupBy("place").count().where("count > 1").limit(1).count():
        # Ids repeat: rows are told apart by their text's hash, and equal rows by a number.
        parts = [place, F.xxhash64("text"), F.col("text")]
        base = scratch.keep(base.withColumn("copy", F.row_number().over(Window.partitionBy(*parts).orderBy("text"))), "rows")
        place = F.struct(place.alias("id"), F.xxhash64("text").alias("hash"), F.col("copy"))
        stamp = lambda c: F.xxhash64(c["id"], c["hash"], c["copy"])
    else:
        stamp = lambda c: c
    lines = line_hashes(line_array(F.col("text")))
    each = base.select(place.alias("place"), F.explode(lines).alias("hash")).where("hash <> 0")
    seen = Observation()
    counted = each.groupBy("hash").agg(F.count("*").alias("n"), F.min("place").alias("place")).observe(seen, F.coalesce(F.sum("n"), F.lit(0)).alias("lines"))
    repeated = counted.where("n > 1")
    repeated = scratch.keep(repeated.select("hash", stamp(F.col("place")).alias("owner")), "repeated")
    shards = max(1, -(-repeated.count() // shard_keys))

    def build(table: pd.DataFrame) -> pd.DataFrame:
        shard = Firsts.build(table["hash"].to_numpy(np.int64).view(U64), table["owner"].to_numpy(np.int64))
        return pd.DataFrame({"shard": [int(table["shard"].iloc[0])], "blob": [shard.blob()]})

    owner = F.pmod(F.col("hash"), F.lit(shards)).cast("int")
    arrays = scratch.keep(repeated.withColumn("shard", owner).groupBy("shard").applyInPandas(build, "shard int, blob binary"), "arrays")
    size = arrays.agg(F.coalesce(F.sum(F.length("blob")), F.lit(0))).first()[0]
    if size <= local_bytes:
        held = spark.sparkContext.broadcast({r.shard: bytes(r.blob) for r in arrays.toLocalIterator()})

        def probe(batches):
            tables = {k: Firsts.of_blob(b) for k, b in held.value.items()}
            for batch in batches:
                column = batch.column("hashes")
                flat = np.asarray(column.flatten()).astype(np.int64)
                lengths = np.asarray(column.value_lengths()).astype(np.int64)
                rows = np.repeat(np.arange(len(lengths)), lengths)
                stamps = np.asarray(batch.column("stamp")).astype(np.int64)
                gone = np.zeros(len(flat), bool)
                shard = np.mod(flat, shards)
                for k, table in tables.items():
                    mine = np.flatnonzero((shard == k) & (flat != 0))
                    hit, owners = table.probe(flat[mine].view(U64))
                    mine, owners = mine[hit], owners[hit]
                    gone[mine] = (owners != stamps[rows[mine]]) | later_ones(rows[mine], flat[mine])
                ends = np.concatenate([[0], np.cumsum(lengths)]).astype(np.int32)
                yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("text"), pa.ListArray.from_arrays(pa.array(ends), pa.array(gone))], ["doc_id", "text", "common"])

        source = base.select("doc_id", "text", stamp(place).alias("stamp"), lines.alias("hashes"))
        return _keep(source.mapInArrow(probe, "doc_id long, text string, common array<boolean>"), F.col("common"))
    # Lines go to the shard that may hold them, from as many tasks a shard as keep PROBES lines in each.
    salts = max(1, -(-seen.get["lines"] // (shards * PROBES)))
    marked = base.select("doc_id", "text", stamp(place).alias("row"))
    asked = marked.select("row", F.posexplode(lines).alias("at", "hash")).where("hash <> 0")
    probes = asked.select(owner.alias("shard"), F.pmod(F.xxhash64("row"), F.lit(salts)).cast("int").alias("salt"), F.lit(1).alias("kind"), "row", "at", "hash", F.lit(None).cast("binary").alias("blob"))
    nothing = [F.lit(None).cast(t).alias(n) for n, t in (("row", "long"), ("at", "int"), ("hash", "long"))]
    copies = arrays.select("shard", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))).alias("salt"), F.lit(0).alias("kind"), *nothing, "blob")
    # The lines of a row that are equal come one after the other, first position first.
    routed = probes.unionByName(copies).repartition("shard", "salt").sortWithinPartitions("shard", "salt", "kind", "row", "hash", "at")

    def answer(batches):
        table, place, last = None, None, None
        for batch in batches:
            kinds = np.asarray(batch.column("kind"))
            cells = np.stack([np.asarray(batch.column("shard")), np.asarray(batch.column("salt"))], 1)
            edges = sorted({0, batch.num_rows, *np.flatnonzero(np.diff(kinds) | (np.diff(cells, axis=0) != 0).any(1)) + 1})
            for a, b in zip(edges, edges[1:]):
                if kinds[a] == 0:
                    table, place = Firsts.of_blob(batch.column("blob")[int(a)].as_py()), tuple(cells[a])
                    continue
                if place != tuple(cells[a]):  # no line of this shard repeats
                    continue
                part = batch.slice(a, b - a)
                row, hashes = (np.asarray(part.column(c)).astype(np.int64) for c in ("row", "hash"))
                hit, owners = table.probe(hashes.view(U64))
                again = np.zeros(len(row), bool)
                again[1:] = (row[1:] == row[:-1]) & (hashes[1:] == hashes[:-1])
                again[0] = last == (row[0], hashes[0])
                last = (row[-1], hashes[-1])
                yield part.select(["row", "at"]).filter(pa.array(hit & (again | (owners != row))))

    dropped = routed.mapInArrow(answer, "row long, at int").groupBy("row").agg(F.collect_set("at").alias("gone"))
    joined = marked.join(dropped, "row", "left")
    gone = F.coalesce(F.col("gone"), F.array().cast("array<int>"))
    flags = F.transform(line_array(F.col("text")), lambda x, k: F.array_contains(gone, k))
    return _keep(joined.select("doc_id", "text", flags.alias("common")), F.col("common"))


def _keep(marked: DataFrame, common: Column) -> DataFrame:
    lines = line_array(F.col("text"))
    pairs = F.arrays_zip(lines.alias("line"), common.alias("common"))
    kept = F.transform(F.filter(pairs, lambda p: ~p["common"]), lambda p: p["line"])
    filled = F.size(F.filter(lines, lambda x: bare_line(x) != "")).cast("long")
    dropped = F.size(F.filter(common, lambda c: c)).cast("long")
    text = F.when(F.col("text").isNull(), F.lit(None)).otherwise(F.array_join(kept, "\n"))
    return marked.select("doc_id", text.alias("kept_text"), filled.alias("lines"), dropped.alias("dropped"))
