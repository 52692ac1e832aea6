"""op1_mixing keeps expected copies exact and draws each source's offset."""

import hashlib
from collections import Counter
from fractions import Fraction
from math import floor

import duckdb
from pyspark.sql import functions as F

from elimspark.llm import mixing, queries

FOLDER = "/root/testdata/sf0.01"


def test_small_sources_meet_their_targets_together(docs):
    rows = [(k, "a", "en", f"host{k}") for k in range(2000)]
    weight = F.expr("cast(substring(source, 5) as int) % 4 + 1").cast("double")
    got = Counter(r.doc_id % 4 + 1 for r in mixing.mix(docs(rows), weight).collect())
    for w in (1, 2, 3, 4):  # 500 sources each expect 0.4 w copies
        assert abs(got[w] - 200 * w) < 60


def test_copies_are_exact_and_follow_the_seed(docs):
    rows = [(k, "a", "en", f"s{k % 7}") for k in range(150)]
    weights = {f"s{k}": 0.1 * (k + 1) for k in range(7)}
    weight = F.expr("0.1D * (cast(substring(source, 2) as int) + 1)")
    for seed in (1, 2):
        got = Counter(r.source for r in mixing.mix(docs(rows), weight, total=1001, seed=seed).collect())
        for s, w in weights.items():
            offset = Fraction(int(hashlib.md5(f"{seed}:s{s}".encode()).hexdigest()[:7], 16), 1 << 28)
            assert got[s] == floor(Fraction(1001 * round(10 * w), 28) + offset)


def test_query_equals_exact_sql(spark):
    con = duckdb.connect()
    con.execute(f"create view documents as select * from '{FOLDER}/documents.parquet'")
    got = queries.op1_mixing(spark, FOLDER).select("doc_id", "source", "copy").collect()
    assert sorted(map(tuple, got)) == sorted(con.execute(queries.OP1_SQL).fetchall())
