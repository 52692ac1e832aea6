"""The filters by a Python judge: what travels to Python and back, and what Python holds at once."""

import tracemalloc

import pyarrow as pa
import pytest
from elimspark.llm import decontam, toxicity
from elimspark.llm.common import verdicts

ITEM = "the seventh planet of the outer ring has three moons of ice"
ROWS = [(k, ("plain words of document number " + str(k) + " ") * 40) for k in range(300)] + [(300, f"before, {ITEM.upper()}! after"), (301, None), (302, ""), (303, "stupid idiot moron scum")]


def sent_and_received(frame):
    """Bytes to and from Python in the frame's plan; the frame is run."""
    plan = frame._jdf.queryExecution().executedPlan()
    frame._jdf.collect()
    todo, sums = [plan], [0, 0]
    while todo:
        node = todo.pop()
        for k, name in enumerate(("pythonDataSent", "pythonDataReceived")):
            if (found := node.metrics().get(name)).isDefined():
                sums[k] += found.get().value()
        children = node.children()
        todo += [children.apply(k) for k in range(children.size())]
    return sums


@pytest.mark.parametrize("name", ["toxicity", "decontamination"])
def test_only_the_text_travels_and_bits_come_back(spark, docs, name, tmp_path):
    docs(ROWS).coalesce(1).write.parquet(f"{tmp_path}/documents")
    frame = spark.read.parquet(f"{tmp_path}/documents")
    bench = spark.createDataFrame([(1, ITEM)], "item_id long, text string")
    kept = toxicity.keep_clean(frame, toxicity.SEED, 1.0) if name == "toxicity" else decontam.without_leaks(frame, bench)
    gone = 303 if name == "toxicity" else 300
    assert sorted(map(tuple, kept.collect())) == sorted(tuple(r) for r in frame.collect() if r.doc_id != gone)
    text = sum(len(t or "") for _, t in ROWS)
    sent, received = sent_and_received(kept)
    assert 0.9 * text < sent < 1.2 * text
    assert 0 < received < 0.05 * text


def test_items_in_many_slices_drop_the_same_rows(spark, docs):
    frame = docs(ROWS)
    bench = spark.createDataFrame([(1, ITEM), (2, "no row holds this passage about ferries and lighthouses"), (3, "stupid idiot moron scum")], "item_id long, text string")
    whole, cut = (decontam.without_leaks(frame, bench, limit=limit) for limit in (decontam.PIECE_LIMIT, 1))
    assert len(decontam.item_slices(bench, 1)) == 3
    kept = sorted(r.doc_id for r in cut.collect())
    assert kept == sorted(r.doc_id for r in whole.collect())
    assert kept == [k for k, _ in ROWS if k not in (300, 303)]


def test_python_holds_the_strings_of_one_slice():
    texts = pa.array(["я" * 5000, None] * 2000)  # 20 MB of UTF-8
    tracemalloc.start()
    got = verdicts(lambda text: not text, texts)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert got.to_pylist() == [False, True] * 2000
    assert peak < 6 << 20
