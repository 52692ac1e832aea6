"""The corpus pipeline: toxicity, near duplicates, benchmark leaks, source mix, shards.

Each stage takes what the stage before kept, as (spark, docs, sf_dir), and returns a
DataFrame; run() writes each stage as Parquet in the shared folder and reads it again.
All stages but the last return the columns of documents; the last adds the shard.

Odd rows, in every stage: an empty table gives an empty one; null and empty texts hold no
term, no copy, no test item, and so stay; rows without a doc_id stay (the mix may repeat or
leave them out like others); repeated rows are rows like others but for near duplicates,
where of the rows of one doc_id one stays (the least hash of the text, ties by the text),
and of a group of copies the least doc_id; columns beyond those of documents are
carried unchanged whatever their names. Texts are looked at whole, however long.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from elimspark.llm import decontam, minhash, mixing, sharding, toxicity
from elimspark.llm.common import Scratch, released
from elimspark.llm.queries import source_weight, table

SHARDS = sharding.SHARDS


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the lexicon rejects go; it is learned on the labelled documents.

    A text without words scores 0 and stays; rows are judged one by one.
    """
    lexicon, cut = toxicity.learn(spark, docs, table(spark, sf_dir, "labels"))
    return toxicity.keep_clean(docs, lexicon, cut)


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near copies stays, the one with the least doc_id.

    Null ids and texts without a letter or digit belong to no group and stay; of the rows of
    one doc_id, one stays.
    """
    return minhash.keep_one(docs, minhash.near_duplicate_groups(docs))


def drop_benchmark_leaks(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold a test item, within its edit budget, go.

    Null test items and those without a letter or digit are nothing to look for.
    """
    return decontam.without_leaks(docs, table(spark, sf_dir, "benchmark"))


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents are repeated or left out so that sources have their target weights.

    A null source is a source; ties of the fixed order go by doc_id, then by the whole row.
    An input column ``copy`` is carried as it is.
    """
    held = "__copy"
    while held in docs.columns:
        held += "_"
    if "copy" in docs.columns:
        mixed = mixing.mix(docs.withColumnRenamed("copy", held), source_weight())
        return mixed.select(*[F.col(held).alias("copy") if c == "copy" else F.col(c) for c in docs.columns])
    return mixing.mix(docs, source_weight()).select(*docs.columns)


def assign_shards(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """(doc_id, group_size, shard); the copies of a document stay together, ties go to the lowest shard."""
    return sharding.assign(docs, F.xxhash64("doc_id", "text"), SHARDS)


STAGES = [
    ("toxicity", drop_toxic),
    ("near_duplicates", drop_near_duplicates),
    ("decontamination", drop_benchmark_leaks),
    ("mixing", mix_sources),
    ("sharding", assign_shards),
]

#: Learned lexicons, minimum hashing, components and bit-parallel distances have no SQL form.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    scratch = Scratch(spark, "pipeline")
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES:
        before = docs
        # A stage's own tables, and its input, are done with when its result is written.
        with released(spark, keep=scratch.root):
            docs = scratch.keep(stage(spark, before, sf_dir), name)
        if name != STAGES[0][0]:
            scratch.drop(before)
    return docs
