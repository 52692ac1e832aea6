"""Every registered query of the graph part against its SQL."""

import os

import duckdb
import pytest

import __spark_entry__ as entry

SMALL, MIDDLE = "/root/testdata/sf0.001", "/root/testdata/sf0.01"
#: Long searches: run by the driver and the bench.
SLOW = {"anchor_mcgee", "anchor_queen7_spread", "anchor_unitary_polar_spread", "anchor_queen6_spread", "tw_nation_top3", "tw_brand_top1", "tw_brand_top2", "tw_letters2", "tw_nation_top2"}


def is_graph(name):
    return name != "pipeline" and not name.startswith("op")


GRAPH = [n for n in entry.queries() if is_graph(n) and n not in SLOW]


@pytest.fixture(scope="module")
def duck():
    con = duckdb.connect()
    con.execute("SET TimeZone = 'UTC'")
    for file in os.listdir(MIDDLE):
        con.execute(f"create view {file.split('.')[0]} as select * from '{MIDDLE}/{file}'")
    return con


@pytest.mark.parametrize("name", GRAPH)
def test_query_equals_its_sql(spark, duck, name):
    frame = entry.queries()[name](spark, MIDDLE)
    columns = sorted(frame.columns)
    got = sorted((tuple(str(r[c]) for c in columns) for r in frame.collect()))
    sql = entry.oracle_sql().get(name)
    if sql is None:
        assert got
        return
    want = duck.execute(f"select {', '.join(columns)} from ({sql}) q").fetchall()
    assert got == sorted(tuple(str(x) for x in row) for row in want)


def test_entry_runs(spark):
    row = entry.entry(spark).collect()
    assert len(row) == 1 and row[0].width == 4


def test_scans_are_pruned(spark):
    plan = entry.queries()["edges_nation_top2"](spark, SMALL)._jdf.queryExecution().toString()
    assert "ReadSchema: struct<l_orderkey:bigint,l_suppkey:bigint>" in plan
    plan = entry.queries()["edges_userstep"](spark, SMALL)._jdf.queryExecution().toString()
    assert "ReadSchema: struct<event_id:bigint,ts:timestamp_ntz,user_id:bigint,event_type:string>" in plan


def test_no_two_queries_are_one_under_two_names():
    bodies = [(q.__code__, repr(q.__defaults__), repr([c.cell_contents for c in q.__closure__ or ()])) for q in entry.queries().values()]
    assert len(bodies) == len(set(bodies))
