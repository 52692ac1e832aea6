"""Mixing sources to target weights by systematic sampling.

A document of source s is expected ``total * weight(s) / rows(s)`` times in the mix. The
expected copies are summed along a fixed order of the source's documents, an offset from
[0, 1) is added, and a document is emitted once for each integer that its interval of the
running sum passes. So each count is off by less than one copy, for documents and sources.
The offset of a source is drawn by a hash of the seed and the source: a source that expects
less than one copy has its share of a chance, and the same seed gives the same mix.

The order is a fixed scramble of doc_id (ties: doc_id, then text), so the running sum is a
sum over (source, order bucket) plus a short window inside the bucket: a source as large
as all others together is still spread over all tasks.

Sums are exact: copies are counted in units of 1/(rows(s) * sum of weights), with no
rounding per source. Weights are whole numbers for that: as they are if all are whole and at
most ``UNITS``, else in units of 1/``UNITS`` of the largest.

Edge cases: a null source is a source of its own; sources of weight zero or without a
target are left out; null doc_ids sort first; repeated rows are documents like others; an
empty table gives an empty mix.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import spread_id

#: Order buckets of a source; window tasks hold a bucket each.
BUCKET_BITS = 10
SEED, UNITS = 42, 10**12


def drawn(source: Column, seed: int) -> Column:
    """The offset of a source, in units of 2**-28."""
    return F.conv(F.substring(F.md5(F.concat(F.lit(f"{seed}:"), source)), 1, 7), 16, 10).cast("decimal(19,0)")


def mix(documents: DataFrame, weight: Column, total: int | None = None, offset: float | None = None, carry: bool = True, seed: int = SEED) -> DataFrame:
    """The mix: rows of ``documents``, repeated, with ``copy`` (1, 2, ...).

    ``weight`` is the target of a row's source, an expression over ``source`` (any unit;
    targets of the sources that occur are scaled to sum to one). ``total`` is the size of
    the mix, that of the input by default. With carry=False only doc_id, source and copy
    stay. An input column ``copy`` is replaced. A given ``offset`` replaces the drawn ones
    and has each source's copies rounded to a whole number first.
    """
    source = F.coalesce(F.concat(F.lit("s"), F.col("source").cast("string")), F.lit("-")).alias("__mix_s")
    bucket = F.shiftright(spread_id(F.col("doc_id")), 31 - BUCKET_BITS).alias("__mix_b")
    cells = documents.groupBy(source, bucket).agg(F.count("*").alias("__mix_here"), F.first("source").alias("source"))
    before = F.sum("__mix_here").over(Window.partitionBy("__mix_s").orderBy("__mix_b").rowsBetween(Window.unboundedPreceding, -1))
    rows = F.sum("__mix_here").over(Window.partitionBy("__mix_s"))
    cells = cells.select("__mix_s", "__mix_b", F.coalesce(before, F.lit(0)).alias("__mix_before"), rows.alias("__mix_rows"), F.coalesce(weight.cast("double"), F.lit(0.0)).alias("__mix_w"), "__mix_here")
    cells = cells.where("__mix_w > 0")
    per_source = cells.groupBy("__mix_s").agg(F.first("__mix_w").alias("w"), F.sum("__mix_here").alias("n"))
    top = per_source.agg(F.max("w").alias("__mix_top"), F.bool_and((F.col("w") == F.floor("w")) & (F.col("w") <= UNITS)).alias("__mix_whole"))
    units = lambda w: F.when(F.col("__mix_whole"), w).otherwise(F.greatest(F.round(w / F.col("__mix_top") * UNITS), F.lit(1.0))).cast("decimal(19,0)")
    whole = per_source.crossJoin(top).groupBy("__mix_top", "__mix_whole").agg(F.sum("w").alias("__mix_all"), F.sum(units(F.col("w"))).alias("__mix_units"), F.sum("n").alias("__mix_n"))
    size = F.col("__mix_n") if total is None else F.lit(total)
    # Copies up to a place of a source are (place * times + shift) div parts.
    if offset is None:
        times = size.cast("decimal(19,0)") * units(F.col("__mix_w"))
        parts = F.col("__mix_rows").cast("decimal(19,0)") * F.col("__mix_units").cast("decimal(19,0)")
        share, whole_offset = parts * drawn(F.col("__mix_s"), seed), F.lit(1 << 28).cast("decimal(10,0)")
        shift = (share - share % whole_offset) / whole_offset
    else:
        times = F.floor(size * F.col("__mix_w") / F.col("__mix_all") + 0.5)
        parts = F.col("__mix_rows")
        shift = F.floor(F.lit(offset) * F.col("__mix_rows"))
    # One row per source and bucket; Spark broadcasts it only below its own size limit.
    numbers = [c.cast("decimal(38,0)").alias(n) for c, n in ((times, "__mix_times"), (parts, "__mix_parts"), (shift, "__mix_shift"))]
    starts = cells.crossJoin(whole).select("__mix_s", "__mix_b", "__mix_before", *numbers)

    columns = [c for c in (documents.columns if carry else ("doc_id", "source")) if c != "copy"]
    tie = F.xxhash64(*documents.columns).alias("__mix_tie")
    base = documents.select(*columns, source, bucket, tie)
    order = Window.partitionBy("__mix_s", "__mix_b").orderBy(spread_id(F.col("doc_id")), F.col("doc_id").asc_nulls_first(), "__mix_tie")
    placed = base.join(starts, ["__mix_s", "__mix_b"]).withColumn("__mix_place", F.col("__mix_before") + F.row_number().over(order))
    passed = "(__mix_times * cast({} as decimal(19,0)) + __mix_shift) div __mix_parts"
    copies = F.expr(passed.format("__mix_place")) - F.expr(passed.format("(__mix_place - 1)"))
    counted = placed.withColumn("__mix_copies", copies.cast("long")).where("__mix_copies > 0")
    return counted.select(*columns, F.explode(F.sequence(F.lit(1).cast("long"), F.col("__mix_copies"))).alias("copy"))
