"""Experiments run over whole levels."""

from elimspark import experiments as e
from elimspark.operators import local, measures
from elimspark.operators.search import Walk
from elimspark.plans.options import Options
from elimspark.sources import named


def test_loop_shapes_take_all_states_of_a_level(monkeypatch):
    g = named.queen(6)
    keep: dict = {}
    Walk(g, Options()).decide(25, keep)
    whole = len(e.states(keep[len(keep) // 2]))
    assert whole > 512
    monkeypatch.setattr(e, "table_graphs", lambda spark, folder: [named.queen(4)] * 6)
    monkeypatch.setattr(measures, "lockstep_cost", lambda g, sets, shapes: {"seen": len(sets)})
    seen = {r["graph"]: r["seen"] for r in e.loop_shapes(None, "")}
    assert seen["queen6_6"] == whole and seen["queen7_7"] > 512


def test_implicit_bound_runs_on_every_graph(monkeypatch):
    run = local.sequential(named.queen(4))
    run.explored = 50_000
    monkeypatch.setattr(e, "table_graphs", lambda spark, folder: [])
    monkeypatch.setattr(local, "sequential", lambda g, options=None: run)
    assert [r["impl"] for r in e.contraction(None, "")] == ["explicit", "explicit", "implicit", "implicit"] * 3
