"""op5_line_dedup keeps one occurrence of each line, and only one."""

from collections import Counter

import duckdb
import pytest

from elimspark.llm import lines, queries

FOLDER = "/root/testdata/sf0.01"


@pytest.mark.parametrize("local", [1 << 26, 0])
def test_first_line_stays(docs, local):
    rows = [(7, "a\n\n b\na"), (3, "b \nc"), (None, "menu\nc\nmenu"), (9, "menu"), (8, None), (10, ""), *[(k, "same\ntext") for k in range(20, 35)]]
    got = {r.doc_id: (r.kept_text, r.lines, r.dropped) for r in lines.keep_first(docs(rows), local_bytes=local, shard_keys=2).collect()}
    assert got[None] == ("menu\nc", 3, 1) and got[3] == ("b ", 2, 1) and got[7] == ("a\n", 3, 2) and got[9] == ("", 1, 1)
    assert got[8] == (None, 0, 0) and got[10] == ("", 0, 0) and got[20] == ("same\ntext", 2, 0) and got[34] == ("", 2, 2)
    assert lines.keep_first(docs(rows).limit(0), local_bytes=local).count() == 0


@pytest.mark.parametrize("local", [1 << 26, 0])
def test_repeated_ids_keep_one(docs, local):
    rows = [(None, "x\ny"), (None, "x\nz"), (1, "p\nx"), (1, "p\nx"), (1, "q\np")]
    frame = docs(rows, extra=["copy", "place", "row"])
    kept = Counter(x for r in lines.keep_first(frame, local_bytes=local, shard_keys=1).collect() for x in r.kept_text.split("\n") if x)
    assert kept == {"x": 1, "y": 1, "z": 1, "p": 1, "q": 1}


def test_query_equals_a_plain_ranking(spark):
    con = duckdb.connect()
    con.execute(f"create view documents as select * from '{FOLDER}/documents.parquet'")
    got = queries.op5_line_dedup(spark, FOLDER).select("doc_id", "kept_text", "lines", "dropped").collect()
    assert sorted(map(tuple, got)) == sorted(con.execute(queries.OP5_SQL).fetchall())
