"""Near-duplicate groups by MinHash.

Each text becomes the set of its word triples (lower case, letters and digits only; a
text of one or two words is one shingle). ``HASHES`` multiply-add-shift functions, a
universal family, give the minima; ``BANDS`` bands of four minima give candidates. Documents
that share a band are compared by the whole signature, and those whose signatures agree
in at least ``THRESHOLD`` of the places are linked; groups are the connected components.

No bucket is cut. Equal contents are folded to one representative before banding, buckets
with the same members are compared once, and a large bucket is searched breadth first:
each found document is compared with those not yet reached, which gives the components of
the full comparison without all pairs.

Edge cases: null and empty texts (no letter or digit) and null doc_ids belong to no group;
rows that repeat a doc_id are one node; input columns other than doc_id and text are ignored.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import ALNUM, U64, Scratch, Words, mix64, ngram_hashes, text_arrays
from .components import connected_components

HASHES, BANDS, SHINGLE, THRESHOLD = 128, 32, 3, 0.45
ROWS = HASHES // BANDS
_rng = np.random.default_rng(20240607)
MULTIPLY = _rng.integers(0, 1 << 63, HASHES, dtype=U64) * U64(2) + U64(1)
ADD = _rng.integers(0, 1 << 63, HASHES, dtype=U64) * U64(2)


def signatures(texts: pa.Array, shingle: int = SHINGLE) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(rows with words, 32-bit minima, content hash) of a slice of lower-cased texts."""
    words = Words(texts, ALNUM)
    hashes, first = ngram_hashes(words, shingle)
    owner = words.doc[first] if len(first) else first
    short = np.flatnonzero((words.per_doc > 0) & (words.per_doc < shingle))
    if len(short):
        whole = np.array([mix64(words.hashes[words.first[d] : words.first[d + 1]] * U64(3)).sum(dtype=U64) for d in short], U64)
        order = np.argsort(np.concatenate([owner, short]), kind="stable")
        hashes, owner = np.concatenate([hashes, mix64(whole)])[order], np.concatenate([owner, short])[order]
    if not len(owner):
        return np.zeros(0, np.int64), np.zeros((0, HASHES), np.uint32), np.zeros(0, np.int64)
    begins = np.concatenate([[0], np.flatnonzero(np.diff(owner)) + 1])
    docs = owner[begins]
    keys = hashes >> U64(32)
    out = np.empty((len(docs), HASHES), np.uint32)
    work = np.empty_like(keys)
    for k in range(HASHES):
        np.multiply(keys, MULTIPLY[k], out=work)
        np.add(work, ADD[k], out=work)
        out[:, k] = np.minimum.reduceat(work, begins) >> U64(32)
    place = np.arange(len(words.hashes), dtype=U64) - np.repeat(words.first[:-1], words.per_doc).astype(U64)
    mixed = mix64(words.hashes ^ mix64(place + U64(1)))
    sums = np.concatenate([np.zeros(1, U64), np.cumsum(mixed, dtype=U64)])
    content = mix64(sums[words.first[docs + 1]] - sums[words.first[docs]] + words.per_doc[docs].astype(U64))
    return docs, out, content.view(np.int64)


def band_keys(minima: np.ndarray) -> np.ndarray:
    """One 64-bit key per band; the band's number is part of it."""
    wide = minima.astype(U64).reshape(len(minima), BANDS, ROWS)
    key = np.broadcast_to(np.arange(BANDS, dtype=U64) + U64(1), wide.shape[:2]).copy()
    for r in range(ROWS):
        key = mix64(key ^ (wide[:, :, r] + U64(0x9E3779B97F4A7C15)))
    return key.view(np.int64)


def _sign(batches):
    for batch in batches:
        for start, stop, texts in text_arrays(batch, "text"):
            rows, minima, content = signatures(texts)
            if not len(rows):
                continue
            ids = batch.column("doc_id").slice(start, stop - start).take(pa.array(rows))
            keys = band_keys(minima)
            yield pa.RecordBatch.from_arrays(
                [ids, pa.array(content), pa.FixedSizeBinaryArray.from_buffers(pa.binary(2 * HASHES), len(rows), [None, pa.py_buffer((minima & 0xFFFF).astype(np.uint16).tobytes())]).cast(pa.binary()), pa.ListArray.from_arrays(pa.array(np.arange(0, len(rows) * BANDS + 1, BANDS, dtype=np.int32)), pa.array(keys.ravel()))],
                ["doc_id", "content", "minima", "bands"],
            )


def bucket_links(minima: np.ndarray, ids: np.ndarray, threshold: float) -> list[tuple[int, int]]:
    """Links that span the components of one bucket: breadth first over its members."""
    need = int(np.ceil(threshold * HASHES - 1e-9))
    distinct, inverse = np.unique(minima, axis=0, return_inverse=True)
    inverse = inverse.ravel()
    least = np.full(len(distinct), np.iinfo(np.int64).max)
    np.minimum.at(least, inverse, ids)
    links = [(int(i), int(least[k])) for i, k in zip(ids, inverse) if i != least[k]]
    left = np.arange(len(distinct))
    while len(left):
        queue, left = [left[0]], left[1:]
        while queue and len(left):
            here = queue.pop()
            close = (distinct[left] == distinct[here]).sum(axis=1) >= need
            found = left[close]
            links += [(int(least[here]), int(least[f])) for f in found]
            queue.extend(found)
            left = left[~close]
    return links


def _compare(threshold: float):
    need = int(np.ceil(threshold * HASHES - 1e-9))

    def emit(buckets: np.ndarray, ids: np.ndarray, minima: np.ndarray):
        begins = np.concatenate([[0], np.flatnonzero(np.diff(buckets)) + 1])
        sizes = np.diff(np.concatenate([begins, [len(buckets)]]))
        pairs = begins[sizes == 2]
        same = (minima[pairs] == minima[pairs + 1]).sum(axis=1) >= need
        u, v = list(ids[pairs[same]]), list(ids[pairs[same] + 1])
        for b, n in zip(begins[sizes > 2], sizes[sizes > 2]):
            for x, y in bucket_links(minima[b : b + n], ids[b : b + n], threshold):
                u.append(x)
                v.append(y)
        return pa.RecordBatch.from_arrays([pa.array(np.asarray(u, np.int64)), pa.array(np.asarray(v, np.int64))], ["u", "v"])

    def run(batches):
        held: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
        for batch in batches:
            if not batch.num_rows:
                continue
            buckets, ids = (np.asarray(batch.column(c)) for c in ("bucket", "rep"))
            minima = np.frombuffer(b"".join(batch.column("minima").to_pylist()), np.uint16).reshape(len(ids), HASHES)
            if held and held[-1][0][-1] != buckets[-1] or not held and buckets[0] != buckets[-1]:
                cut = int(np.flatnonzero(buckets != buckets[-1])[-1]) + 1
                done = [*held, (buckets[:cut], ids[:cut], minima[:cut])]
                yield emit(*(np.concatenate([x[k] for x in done]) for k in range(3)))
                held = [(buckets[cut:], ids[cut:], minima[cut:])]
            else:
                held.append((buckets, ids, minima))
        if held:
            yield emit(*(np.concatenate([x[k] for x in held]) for k in range(3)))

    return run


def near_duplicate_groups(documents: DataFrame, threshold: float = THRESHOLD) -> DataFrame:
    """(doc_id, group_id) of every document in a group of two or more; group_id is the least doc_id."""
    spark = documents.sparkSession
    scratch = Scratch(spark, "minhash")
    texts = documents.select(F.col("doc_id").cast("long").alias("doc_id"), F.lower(F.col("text").cast("string")).alias("text")).where("doc_id is not null and text is not null")
    signed = scratch.keep(texts.mapInArrow(_sign, "doc_id long, content long, minima binary, bands array<long>"), "signed")
    folded = signed.groupBy("content").agg(F.min("doc_id").alias("rep"))
    exact = signed.select("doc_id", "content").join(folded, "content").where("doc_id <> rep").select(F.col("doc_id").alias("u"), F.col("rep").alias("v"))
    # A doc_id that repeats with other texts is its own representative more than once; each content keeps its signature.
    reps = scratch.keep(signed.join(folded, (signed.content == folded.content) & (signed.doc_id == folded.rep), "left_semi").dropDuplicates(["doc_id", "content"]), "reps")
    members = reps.select("doc_id", F.explode("bands").alias("band")).groupBy("band").agg(F.array_sort(F.collect_set("doc_id")).alias("ids")).where(F.size("ids") > 1)
    buckets = members.groupBy(F.xxhash64("ids").alias("bucket"), F.size("ids").alias("n")).agg(F.first("ids").alias("ids"))
    listed = buckets.select("bucket", F.explode("ids").alias("rep"))
    compared = listed.join(reps.select(F.col("doc_id").alias("rep"), "minima"), "rep").select("bucket", "rep", "minima")
    near = compared.repartition("bucket").sortWithinPartitions("bucket").mapInArrow(_compare(threshold), "u long, v long")
    groups = connected_components(exact.unionByName(near), scratch)
    return groups.select(F.col("node").alias("doc_id"), F.col("component").alias("group_id"))


def keep_one(documents: DataFrame, groups: DataFrame) -> DataFrame:
    """One document of each group, the one with the least doc_id, and every document outside groups.

    Of rows that repeat a doc_id the least text stays; rows with a null doc_id all stay.
    """
    dropped = groups.where("doc_id <> group_id").select("doc_id")
    left = documents.join(dropped, "doc_id", "left_anti")
    repeated = documents.where("doc_id is not null").groupBy("doc_id").count().where("count > 1").select("doc_id")
    if not repeated.limit(1).count():
        return left.select(*documents.columns)
    once = left.join(repeated, "doc_id", "left_anti")
    rank = F.row_number().over(Window.partitionBy("doc_id").orderBy(F.xxhash64("text"), "text"))
    more = left.join(repeated, "doc_id", "left_semi").withColumn("__rank", rank).where("__rank = 1").drop("__rank")
    return once.unionByName(more).select(*documents.columns)
