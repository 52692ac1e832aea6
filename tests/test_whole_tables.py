"""Builders over whole tables: no key is left out."""

import datetime

import numpy as np
import pytest

import __spark_entry__ as entry
from elimspark.sources import builders

SMALL = "/root/testdata/sf0.001"


@pytest.mark.parametrize("block", [64, 4096])
def test_all_vectors_get_their_nearest(spark, block):
    want = sorted(map(tuple, builders.embedding(spark, SMALL, 1 << 40, 2)[0].collect()))
    edges, vertices = builders.embedding_all(spark, SMALL, 2, block)
    assert sorted(map(tuple, edges.collect())) == want
    assert vertices.count() == spark.read.parquet(f"{SMALL}/embeddings.parquet").count()


def test_equal_vectors_and_ties(spark, tmp_path):
    rng = np.random.default_rng(3)
    some = [rng.normal(size=8).astype("float32").tolist() for _ in range(6)]
    rows = [(k, some[k % 6]) for k in range(60)]
    spark.createDataFrame(rows, "vec_id long, embedding array<float>").write.parquet(str(tmp_path / "embeddings.parquet"))
    want = sorted(map(tuple, builders.embedding(spark, str(tmp_path), 60, 3)[0].collect()))
    assert sorted(map(tuple, builders.embedding_all(spark, str(tmp_path), 3, 7)[0].collect())) == want


def test_no_user_part_or_language_is_left_out(spark, tmp_path):
    folder = str(tmp_path)
    stamp = datetime.datetime(2024, 1, 1, 0, 0, 10)
    spark.createDataFrame([(k, stamp) for k in (1, 300, 5000)], "user_id long, ts timestamp").write.parquet(f"{folder}/events.parquet")
    spark.createDataFrame([(1, 2), (19_999, 999)], "l_partkey long, l_suppkey long").write.parquet(f"{folder}/lineitem.parquet")
    spark.createDataFrame([("ab", "en"), ("xyz", "fr"), ("qr", None)], "text string, lang string").write.parquet(f"{folder}/documents.parquet")
    got = {n: sorted(map(tuple, entry.queries()[f"edges_{n}"](spark, folder).collect())) for n in ("coactive", "partsupp", "letter")}
    assert got == {"coactive": [("g", 0, 1), ("g", 0, 2), ("g", 1, 2)], "partsupp": [("g", 0, 2), ("g", 1, 3)], "letter": [("en", 0, 1), ("fr", 0, 1), ("fr", 1, 2), ("null", 0, 1)]}
