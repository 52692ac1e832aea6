"""The ten text operators against brute force, and their edge cases."""

import random
import string
from collections import Counter

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from elimspark.llm import ann, decontam, html, langid, lines, minhash, mixing, queries, sharding, suffix, toxicity
from elimspark.llm.components import connected_components
from elimspark.llm.common import NONSPACE, Scratch, Words

WORDS = ["".join(random.Random(k).choices(string.ascii_lowercase, k=3 + k % 6)) for k in range(4000)]
#: Names that operators use inside; inputs may have them too.
CLASH = ["group_id", "copy", "shard", "key", "row", "text_", "rank", "count", "u", "v", "bucket", "size"]
EDGE = [(None, "alpha beta gamma delta"), (1, None), (2, ""), (3, " \n\t "), (4, "é" * 50_000), (5, "one"), (5, "one"), (6, "one"), (7, "x " * 3000), (8, "x " * 3000)]


def prose(seed, n=120):
    return " ".join(random.Random(seed).choices(WORDS, k=n))


def edited(text, seed, share=0.04):
    rng = random.Random(seed)
    return " ".join(rng.choice(WORDS) if rng.random() < share else w for w in text.split())


# 1 mixing


def test_mixing_counts_are_within_one_copy(docs):
    rows = [(k, prose(k, 5), "en", "a" if k % 4 else "b") for k in range(400)]
    weight = F.when(F.col("source") == "a", 1.0).otherwise(3.0)
    got = mixing.mix(docs(rows), weight, total=1000).collect()
    by = Counter(r.source for r in got)
    assert by == {"a": 250, "b": 750}
    copies = Counter(r.doc_id for r in got)
    for k, _, _, source in rows:
        expected = 250 / 300 if source == "a" else 750 / 100
        assert abs(copies[k] - expected) < 1


def test_mixing_equals_a_plain_running_sum(docs):
    rows = [(k * 7919 % 10_007, prose(k, 3), "en", f"s{k % 3}") for k in range(90)]
    weight = F.when(F.col("source") == "s0", 2.0).otherwise(1.0)
    got = Counter(r.doc_id for r in mixing.mix(docs(rows), weight, offset=0.25).collect())
    spread = lambda i: (i % 2147483647 * 1103515245 + 12345) % 2**31
    want = Counter()
    for s, goal in (("s0", 45), ("s1", 23), ("s2", 23)):
        mine = sorted((r[0] for r in rows if r[3] == s), key=lambda i: (spread(i), i))
        for place, i in enumerate(mine, 1):
            n = len(mine)
            want[i] += (goal * place + n // 4) // n - (goal * (place - 1) + n // 4) // n
    assert got == +want


def test_mixing_edges(docs):
    frame = docs([(*r, "en", None) for r in EDGE], extra=CLASH)
    got = mixing.mix(frame, F.lit(1.0))
    assert got.count() == len(EDGE) and set(frame.columns) <= set(got.columns)
    assert mixing.mix(docs([(1, "a", "en", "s")]), F.lit(0.0)).count() == 0
    assert mixing.mix(docs([(1, "a")]).limit(0), F.lit(1.0)).count() == 0


# 2 language


@pytest.fixture(scope="module")
def small_model():
    pieces = ["▁", "▁a", "a", "b", "ab", "ba", "▁ab", "c"]
    return langid.train(pieces, {"x": Counter({"abab": 5, "ba": 2}), "y": Counter({"cc": 4, "a": 1})}), pieces


def test_forward_sums_all_segmentations(small_model):
    model, pieces = small_model

    def brute(word, column):
        if not word:
            return 1.0
        total = 0.0
        for k in range(1, len(word) + 1):
            head = word[:k]
            p = model.table[pieces.index(head), column] if head in pieces else langid.SMOOTH if k == 1 else 0.0
            total += p * brute(word[k:], column)
        return total

    for word in ("abab", "ba", "cc", "abz", "aabbaab"):
        got = np.exp(model.score([word])[0])
        assert got == pytest.approx([brute(langid.MARK + word, 0), brute(langid.MARK + word, 1)], rel=1e-9)


def test_language_held_out_accuracy(spark):
    frame = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    even, odd = frame.where("doc_id % 2 = 0"), frame.where("doc_id % 2 = 1")
    model = langid.fit(even, limit=30)
    got = langid.identify(odd, model).join(odd.select("doc_id", "lang"), "doc_id")
    assert got.where("predicted = lang").count() / got.count() > 0.97


def test_language_edges(docs, small_model):
    got = langid.identify(docs(EDGE, extra=CLASH), small_model[0]).collect()
    assert len(got) == len(EDGE)
    assert {r.predicted for r in got if r.words == 0} == {"und"}
    assert langid.identify(docs(EDGE), langid.train(["a"], {})).where("predicted <> 'und'").count() == 0
    assert langid.identify(docs(EDGE).limit(0), small_model[0]).count() == 0


def test_long_words_are_scored_whole_and_trained(small_model):
    model, pieces = small_model
    long = "ab" * 2000
    few, many = model.score([long, "ab"]), model.score([long] * 20 + ["ab"])
    assert np.allclose(few[0], many[0]) and np.isfinite(few).all() and few[0, 0] > few[0, 1]
    # The chance of a word of unknown signs is that of its signs; training on it leaves a proper table.
    trained = langid.train(["a", "b", langid.MARK], {"x": Counter({"ж" * 300: 100, "a" * 900 + "b": 3}), "y": Counter({"b": 2})})
    assert np.isfinite(trained.table).all() and trained.table[0, 0] > 100 * trained.table[1, 0]


def test_all_pieces_of_the_vocabulary_are_used():
    import os

    if not os.path.exists(langid.VOCABULARY):
        pytest.skip("no vocabulary file here")
    assert max(map(len, langid.vocabulary())) == langid.Lattice(langid.vocabulary()).longest > 12
    with pytest.raises(FileNotFoundError):
        langid.vocabulary("/nowhere.model")


# 3 html

PAGE = "<html><head><title>T</title></head><body><nav><ul><li><a href='/'>home</a></li><li><a href='/x'>more</a></li></ul></nav><div class='ad'>buy now</div><{0}><h1>Head line</h1><p>{1}</p><p>{2}</p></{0}><footer>&copy; all rights</footer></body></html>"


@pytest.fixture(scope="module")
def html_model():
    pages = [PAGE.format("article", prose(k, 40 + k % 30) + ".", prose(k + 500, 30) + ", yes.") for k in range(60)]
    return html.fit_forest(html.Forest(pages))


def test_html_content_without_the_marking_tag(html_model):
    page = PAGE.format("div", "First part, long and clear. " * 8, "Second part, as long. " * 6)
    text, nodes, kept = html.extract_texts([page], html_model)[0]
    assert text.startswith("Head line\nFirst part") and "Second part" in text
    assert not any(w in text for w in ("home", "buy", "rights")) and kept == 3 and nodes == 8


def test_html_marginals_equal_enumeration():
    forest = html.Forest(["<div><p>a b<b>c</b></p><p>d</p></div>"])
    n = len(forest.tags)
    rng = np.random.default_rng(0)
    unary, edge = rng.normal(size=n), rng.normal(size=(2, 2))
    weights = np.zeros(2)
    ones, pairs, whole = np.zeros(n), np.zeros((2, 2)), 0.0
    del weights
    for code in range(1 << n):
        state = [code >> k & 1 for k in range(n)]
        p = np.exp(sum(unary[k] for k in range(n) if state[k]) + sum(edge[state[forest.parent[k]], state[k]] for k in range(1, n)))
        whole += p
        ones += p * np.array(state)
        for k in range(1, n):
            pairs[state[forest.parent[k]], state[k]] += p
    got, joint, total = html.marginals(forest, unary, edge)
    assert got == pytest.approx(ones / whole) and joint == pytest.approx(pairs / whole) and total == pytest.approx(np.log(whole))


def test_html_edges(spark, html_model):
    rows = [(None, "<p>a</p>"), (1, None), (2, ""), (3, "plain text only"), (4, "<div>" * 3000 + "deep"), (5, "</p></div><b>x"), (5, "</p></div><b>x"), (6, "<script>var a = '<p>no</p>'"), (7, "<p a='>'>q<")]
    frame = spark.createDataFrame(rows, "page_id long, html string").withColumn("content", F.lit(1))
    got = html.extract(frame, html_model).collect()
    assert len(got) == len(rows)
    assert all(r.content == "" for r in got if r.page_id in (1, 2, 6))
    free = {r.page_id: r.content for r in html.extract(frame, None).collect()}
    assert free[3] == "plain text only" and free[4] == "deep" and free[5] == "x"
    assert html.extract(frame.limit(0), None).count() == 0


def test_html_works_on_bounded_bytes_at_once(spark, html_model, monkeypatch):
    """Pages of any length: no step holds more than the limit, or one page; the result is that of each page alone."""
    pages = [PAGE.format("div", prose(k, 30) + ".", "<b>x</b>" * (60_000 if k % 9 == 4 else 400)) for k in range(40)] + [None, ""]
    held, parse = [], html.extract_texts
    monkeypatch.setattr(html, "extract_texts", lambda group, model: held.append([len(p) for p in group]) or parse(group, model))
    batch = pa.RecordBatch.from_arrays([pa.array(range(len(pages)), pa.int64()), pa.array(pages)], ["page_id", "html"])
    got = pa.Table.from_batches(html.extractor(html_model, 1 << 16)(iter([batch.slice(0, 3), batch.slice(3)])))
    assert all(sum(h) <= 1 << 16 or len(h) == 1 for h in held) and sum(map(len, held)) == len(pages)
    assert got.column("page_id").to_pylist() == list(range(len(pages)))
    assert [tuple(r.values())[1:] for r in got.to_pylist()] == [parse([p or ""], html_model)[0] for p in pages]
    frame = spark.createDataFrame([(k, p) for k, p in enumerate(pages)], "page_id long, html string")
    assert sorted(tuple(r) for r in html.extract(frame, html_model).collect()) == [tuple(r.values()) for r in got.to_pylist()]


def test_html_learns_from_the_marked_pages_of_least_scrambled_id(spark):
    rows = [(k % 25 if k else None, PAGE.format("article" if k % 3 else "div", prose(k, 30) + ".", prose(k + 90, 9))) for k in range(60)]
    frame = spark.createDataFrame(rows, "page_id long, html string")
    marked = frame.where("page_id is not null and html like '%<article>%'").select("*", F.xxhash64("page_id").alias("a"), F.xxhash64("html").alias("b"))
    want = html.fit_forest(html.Forest([r.html for r in marked.orderBy("a", "page_id", "b", "html").limit(7).collect()]))
    got = html.fit(frame, 7)
    assert all(np.array_equal(x, y) for x, y in zip(got, want))
    assert html.fit(frame.where("html not like '%<article>%'")) is None


@pytest.mark.parametrize("page", ["<a " * 8000, "<a '" * 8000 + ">", '<a ">"' * 8000, "<script " * 8000, "<b>" * 4000 + "</i>" * 4000, "<b>" * 4000 + "<p>x</p>" * 4000, "<b><div>" + "<i>" * 4000 + "</b>" * 4000, "<!" * 8000, "<div>" * 20_000])
def test_html_parsing_is_linear(page):
    import time

    began = time.perf_counter()
    html.parse(page)
    assert time.perf_counter() - began < 0.5


def test_html_tokens_and_repairs():
    assert list(html.tokens("a<b x='>'>c</b><!-- <p> --><br/>d<script>1<2</script>e < f <1> <p 'q>r")) == [
        ("text", "a", ""), ("open", "b", " x='>'"), ("text", "c", ""), ("close", "b", ""), ("open", "br", "/"), ("text", "d", ""), ("text", "e < f <1> ", ""), ("open", "p", " 'q"), ("text", "r", ""),
    ]
    parents, tags, _, texts = html.parse("<ul><li>a<li>b<i>c</ul>d<p>e<div>f</p>g")
    assert [(t, tags[p] if p >= 0 else "", x) for p, t, x in zip(parents, tags, texts)][1:] == [("ul", "#root", ""), ("li", "ul", ""), ("#", "li", "a"), ("li", "ul", ""), ("#", "li", "b"), ("i", "li", ""), ("#", "i", "c"), ("#", "#root", "d"), ("p", "#root", ""), ("#", "p", "e"), ("div", "#root", ""), ("#", "div", "f"), ("#", "div", "g")]


# 4 near duplicates


def jaccard(a, b):
    cut = lambda t: {tuple(t.split()[k : k + 3]) for k in range(len(t.split()) - 2)}
    return len(cut(a) & cut(b)) / len(cut(a) | cut(b))


def test_minhash_groups_match_brute_force(docs):
    rows = [(k, prose(k)) for k in range(60)]
    rows += [(100 + k, edited(prose(k), k, 0.03)) for k in range(30)] + [(200 + k, prose(k).upper() + "!") for k in range(10)]
    got = {r.doc_id: r.group_id for r in minhash.near_duplicate_groups(docs(rows)).collect()}
    for i, (a, x) in enumerate(rows):
        for b, y in rows[i + 1 :]:
            j = jaccard(x, y.lower().rstrip("!"))
            if j >= 0.6:
                assert got.get(a) == got.get(b) is not None
            elif j < 0.2 and a < 100 and b < 100:
                assert got.get(a, -1) != got.get(b, -2)


def test_signature_estimates_jaccard():
    a, b = prose(1, 400), edited(prose(1, 400), 9, 0.1)
    _, minima, _ = minhash.signatures(pa.array([a, b], pa.large_string()))
    assert abs((minima[0] == minima[1]).mean() - jaccard(a, b)) < 0.12


def test_bucket_search_equals_all_pairs():
    rng = np.random.default_rng(3)
    base = rng.integers(0, 60_000, (4, minhash.HASHES)).astype(np.uint16)
    rows = np.repeat(base, 10, axis=0)
    rows[rng.random(rows.shape) < 0.35] = 1
    ids = rng.permutation(1000)[:40].astype(np.int64)
    need = int(np.ceil(0.45 * minhash.HASHES - 1e-9))

    def parts(links):
        up = {int(i): int(i) for i in ids}
        for a, b in links:
            x, y = up[a], up[b]
            up = {k: (y if v == x else v) for k, v in up.items()}
        return {frozenset(k for k in up if up[k] == v) for v in up.values()}

    every = [(int(ids[i]), int(ids[j])) for i in range(40) for j in range(i) if (rows[i] == rows[j]).sum() >= need]
    assert parts(minhash.bucket_links(rows, ids, 0.45)) == parts(every)


def test_components(spark):
    rng = random.Random(5)
    edges = [(a, a + 1) for a in range(0, 40)] + [(rng.randrange(100, 160), rng.randrange(100, 160)) for _ in range(40)] + [(7, 7), (None, 3)]
    got = {r.node: r.component for r in connected_components(spark.createDataFrame(edges, "u long, v long"), Scratch(spark, "t")).collect()}
    up = {}

    def find(x):
        while up.setdefault(x, x) != x:
            x = up[x]
        return x

    for a, b in edges:
        if a is not None and a != b:
            x, y = find(a), find(b)
            up[max(x, y)] = min(x, y)
    assert got == {x: find(x) for x in up}


def test_minhash_edges_and_keep_one(docs):
    frame = docs([*EDGE, (9, prose(1)), (10, prose(1)), (10, prose(1)), (11, prose(2))], extra=CLASH)
    groups = minhash.near_duplicate_groups(frame)
    assert {(r.doc_id, r.group_id) for r in groups.collect()} == {(5, 5), (6, 5), (7, 7), (8, 7), (9, 9), (10, 9)}
    kept = minhash.keep_one(frame, groups)
    assert kept.columns == frame.columns
    assert sorted((r.doc_id if r.doc_id is not None else -1) for r in kept.select("doc_id").collect()) == [-1, 1, 2, 3, 4, 5, 7, 9, 11]
    assert minhash.near_duplicate_groups(frame.limit(0)).count() == 0


# 5 lines


@pytest.mark.parametrize("local", [1 << 26, 0])
def test_lines_against_counting(docs, local):
    rng = random.Random(2)
    rows = [(k, "\n".join(rng.choice(["  menu ", "", prose(rng.randrange(40), 4)]) for _ in range(12))) for k in range(80)]
    rows += [(None, "menu"), (90, None), (91, ""), (92, "menu\nmenu"), (93, "z" * 100_000)]
    frame = docs(rows, extra=CLASH)
    count = Counter(x for _, t in rows if t for x in {s.strip() for s in t.split("\n")} if x)
    got = {r.doc_id: r for r in lines.deduplicate(frame, max_docs=5, local_bytes=local, shard_keys=16).collect()}
    assert len(got) == len(rows)
    for k, t in rows:
        want = None if t is None else "\n".join(s for s in t.split("\n") if count[s.strip()] <= 5)
        assert got[k].kept_text == want
    assert lines.deduplicate(frame.limit(0), local_bytes=local).count() == 0


@pytest.mark.parametrize("n", [0, 1, 7, 5000])
def test_perfect_hash_is_minimal_and_perfect(n):
    keys = np.random.default_rng(n).integers(0, 1 << 63, n, dtype=np.uint64)
    keys = np.unique(keys)
    function = lines.PerfectHash.of_blob(lines.PerfectHash.build(keys).blob())
    assert sorted(function.index(keys)) == list(range(len(keys)))
    shard = lines.Shard.of_blob(lines.Shard.build(keys, np.arange(len(keys))).blob())
    assert list(shard.probe(keys)) == list(range(len(keys)))
    assert not shard.probe(keys + np.uint64(1)).any() or n < 2


# 6 suffixes


def brute_passages(texts, length):
    seen = Counter(tuple(w[i : i + length]) for w in texts for i in range(len(w) - length + 1))
    out = []
    for d, w in enumerate(texts):
        spans = []
        for i in range(len(w) - length + 1):
            if seen[tuple(w[i : i + length])] > 1:
                if spans and i <= spans[-1][1]:
                    spans[-1][1] = i + length
                else:
                    spans.append([i, i + length])
        out += [(d, a, b) for a, b in spans]
    return sorted(out)


def test_suffix_passages_match_brute_force(docs):
    rng = random.Random(11)
    shared = [prose(900 + k, rng.choice([49, 50, 51, 75, 140])) for k in range(12)]
    rows = []
    for k in range(60):
        parts = [prose(k, rng.randrange(5, 80))] + [rng.choice(shared) + " " + prose(1000 + 7 * k + j, rng.randrange(0, 30)) for j in range(rng.randrange(3))]
        rows.append((k, " ".join(parts)))
    rows += [(60, "same word " * 100), (61, edited(shared[0] + " " + shared[4], 3, 0.02)), (62, "q " * 49), (63, "r " * 51)]
    got = sorted(tuple(r) for r in suffix.repeated_passages(docs(rows, extra=CLASH)).collect())
    assert got == brute_passages([t.split() for _, t in rows], suffix.LENGTH)


def test_deep_shallow_sorts():
    rng = np.random.default_rng(4)
    text = rng.integers(0, 2, 3000)
    text[1000:1400] = text[200:600]
    text[2000:2300] = text[300:600]
    text[2150] = 5
    starts = np.arange(2900)
    order, common = suffix.deep_shallow(text, starts, 60, 9)
    keys = [tuple(text[s : s + 60]) for s in starts[order]]
    assert keys == sorted(tuple(text[s : s + 60]) for s in starts)
    for a, b, c in zip(keys, keys[1:], common[1:]):
        assert c == next((i for i in range(60) if a[i] != b[i]), 60)


def test_window_minima():
    keys = np.random.default_rng(1).integers(0, 9, 200).astype(np.uint64)
    assert [int(k) for k in suffix.window_minima(keys, 7)] == [i + int(np.argmin(keys[i : i + 7])) for i in range(194)]


def test_suffix_edges(docs):
    text = prose(3, 60)
    got = sorted(tuple(r) for r in suffix.repeated_passages(docs([*EDGE, (None, text), (20, text)], extra=CLASH)).fillna({"doc_id": -1}).collect())
    assert got == [(-1, 0, 60), (7, 0, 3000), (8, 0, 3000), (20, 0, 60)]
    assert suffix.repeated_passages(docs(EDGE).limit(0)).count() == 0


# 7 decontamination


def test_myers_equals_dynamic_programme():
    rng = random.Random(8)
    for _ in range(200):
        p = "".join(rng.choices("abc", k=rng.randrange(1, 90)))
        t = "".join(rng.choices("abc", k=rng.randrange(0, 120)))
        assert decontam.myers(p, t, 1000) == decontam.semi_global(p, t)


def test_leaks_match_brute_force(docs, spark):
    rng = random.Random(6)
    items = [(k, prose(3000 + k, 12 + k)) for k in range(8)] + [(8, None), (9, "Alpha, beta"), (10, ""), (11, "one"), (12, "eta gam"), (13, "?!")]
    rows = []
    for k in range(40):
        body = prose(k, 30)
        if k % 2:
            text = list(items[k % 8][1])
            for _ in range(rng.randrange(0, 9)):
                text[rng.randrange(len(text))] = rng.choice("abcdexyz ")
            body += "  " + "".join(text).upper() + ". " + prose(k + 77, 10)
        rows.append((k, body))
    rows += EDGE
    frame = docs(rows, extra=CLASH)
    bench = spark.createDataFrame(items, "item_id long, text string").withColumn("doc_id", F.lit(5))
    clean = lambda t: " ".join(t.lower().replace(".", " ").replace(",", " ").replace("?", "").replace("!", "").split())
    want = set()
    for i, t in items:
        if t and clean(t) and len(clean(t)) < decontam.SHORT:
            want |= {(k, i, 0) for k, body in rows if body and f" {clean(t)} " in f" {clean(body)} "}
        elif t and clean(t):
            for k, body in rows[:40]:
                d = decontam.semi_global(clean(t), clean(body))
                if d <= decontam.budget(len(clean(t))):
                    want.add((k, i, d))
    assert want
    for limit in (decontam.PIECE_LIMIT, 100):
        assert {tuple(r) for r in decontam.leaks(frame, bench, limit=limit).collect()} == want
    # The four last rows with a word of a short item share ids with others.
    kept = decontam.without_leaks(frame, bench)
    assert kept.columns == frame.columns and kept.count() == len(rows) - len({k for k, i, _ in want if i < 8}) - 4
    assert decontam.leaks(frame, bench.limit(0)).count() == 0 and decontam.leaks(frame.limit(0), bench).count() == 0


# 8 sharding


def plain_schedule(sizes, shards):
    loads, out = [0] * shards, []
    for s in sizes:
        j = loads.index(min(loads))
        loads[j] += s
        out.append(j)
    return out


@pytest.mark.parametrize("seed", range(12))
def test_schedule_equals_the_heap(seed):
    rng = random.Random(seed)
    shards = rng.choice([1, 2, 5, 16])
    sizes = sorted({rng.choice([rng.randrange(1, 30), rng.randrange(1, 5000)]) for _ in range(8)}, reverse=True)
    table = [(s, rng.choice([1, 3, 40, 900])) for s in sizes]
    flat = [s for s, n in table for _ in range(n)]
    got = []
    for size, low, high, pattern in sharding.schedule(table, shards):
        got += [pattern[r % len(pattern)] for r in range(high - low)]
    assert got == plain_schedule(flat, shards)


def test_sharding_edges(docs):
    frame = docs(EDGE, extra=CLASH)
    got = sharding.assign(frame, F.xxhash64("doc_id"), 3).collect()
    assert len(got) == len(EDGE)
    assert len({r.shard for r in got if r.doc_id == 5}) == 1
    assert sharding.assign(frame, F.lit(None).cast("long"), 3).count() == len(EDGE)
    assert sharding.assign(frame.limit(0), F.xxhash64("doc_id")).count() == 0


# 9 neighbours


def test_neighbours_recall(spark):
    frame = spark.read.parquet("/root/testdata/sf0.1/embeddings.parquet")
    rows = frame.orderBy("vec_id").collect()
    v = np.array([r.embedding for r in rows], float)
    v /= np.linalg.norm(v, axis=1, keepdims=True)
    likeness = v @ v.T
    np.fill_diagonal(likeness, -9)
    want = {(i, int(j)) for i in range(len(v)) for j in np.argsort(-likeness[i])[:10]}
    got = {(r.vec_id, r.neighbour_id) for r in ann.neighbours(frame, cell=64).collect()}
    assert len(want & got) / len(want) > 0.9


def test_nearest_asks_for_every_fiftieth_id_and_reads_all_rows(spark):
    frame = spark.read.parquet("/root/testdata/sf0.1/embeddings.parquet")
    rows = frame.orderBy("vec_id").collect()
    v = np.array([r.embedding for r in rows], float)
    v /= np.linalg.norm(v, axis=1, keepdims=True)
    want = {}
    for q in range(0, len(v), 50):
        likeness = np.round(v @ v[q], 6)
        near = sorted((-x, i) for i, x in enumerate(likeness) if i != q)[:10]
        want |= {(q, k): (i, -x) for k, (x, i) in enumerate(near, 1)}
    got = {(r.vec_id, r["rank"]): (r.neighbour_id, r.similarity) for r in queries.op9_nearest(spark, "/root/testdata/sf0.1").collect()}
    assert {k: i for k, (i, _) in got.items()} == {k: i for k, (i, _) in want.items()}
    assert all(got[k][1] == pytest.approx(want[k][1], abs=2e-6) for k in want)


def test_neighbours_equal_their_sql_and_brute_force_however_the_table_is_cut(spark):
    """Ties, copies, repeated and negative ids, vectors of any length and a search of many parts."""
    import duckdb

    rng = np.random.default_rng(5)
    v = rng.normal(size=(900, 24)).astype(np.float32)
    v[300:600] = v[:300] * rng.choice([1e-12, 0.5, 3.0, 1e12], size=(300, 1)).astype(np.float32)
    v[600:640] = 1.0
    ids = [int(k) for k in np.arange(900) - 200]
    rows = list(zip(ids, v.tolist())) + [(0, [-5.0] * 24), (50, [9.0] * 24), (-100, (v[7] + 1).tolist()), (1001, [0.0] * 24), (1050, [float("inf")] * 24), (1100, [None] * 24), (1150, [1.0]), (None, [1.0] * 24)]
    frame = spark.createDataFrame(rows, "vec_id long, embedding array<float>").coalesce(1)
    con = duckdb.connect()
    con.register("embeddings", frame.toArrow())
    want = sorted(con.execute(f"select vec_id, rank, neighbour_id, similarity from ({queries.OP9_SQL})").fetchall())
    assert len(want) == 10 * sum(k % 50 == 0 for k in ids)
    for cut in ({}, {"cell": 16, "part_bytes": 4096}):
        got = ann.neighbours(frame, every=50, **cut)
        assert sorted(map(tuple, got.select("vec_id", "rank", "neighbour_id", "similarity").collect())) == want
    everything = {(r.vec_id, r["rank"]): r.neighbour_id for r in ann.neighbours(frame).collect()}
    assert len(everything) == 9000 and all(everything[i, k] == n for i, k, n, _ in want)


def test_codes_bound_inner_products():
    rng = np.random.default_rng(0)
    base, query = rng.normal(size=(500, 100)).astype(np.float32), rng.normal(size=(20, 100)).astype(np.float32)
    turn = ann.rotation(100)
    guess, bound = ann.Codes(base, turn).estimate(query, turn, 3.0)
    inside = np.abs(guess - query @ base.T) <= bound
    assert inside.mean() > 0.99


def test_neighbours_edges(spark):
    rows = [(None, [1.0, 0.0]), (1, None), (2, [0.0, 0.0]), (3, [1.0, None]), (4, [float("nan"), 1.0]), (5, [1.0, 0.0]), (5, [1.0, 0.0]), (6, [1.0, 0.1]), (7, [0.0, 1.0]), (8, [1.0, 2.0, 3.0]), (9, []), (10, [1.0, 0.1])]
    frame = spark.createDataFrame(rows, "vec_id long, embedding array<float>").withColumn("rank", F.lit(1)).withColumn("cells", F.lit(2))
    got = {(r.vec_id, r.rank): r.neighbour_id for r in ann.neighbours(frame, k=2).collect()}
    assert got == {(5, 1): 6, (5, 2): 10, (6, 1): 10, (6, 2): 5, (7, 1): 6, (7, 2): 10, (10, 1): 6, (10, 2): 5}
    assert ann.neighbours(frame.limit(0)).count() == 0
    assert ann.neighbours(frame.where("vec_id = 7")).count() == 0


# 10 toxicity


def test_folding_and_matching():
    m = toxicity.Matcher({"idiot": 2.0, "vile*": 3.0, "clown": 1.0}, ["clown fish"])
    assert m.scan("You 1d10t, IDİOT іdiot")[1] == 3
    assert m.scan("idiotic")[1] == 0 and m.scan("vilest viles")[:2] == (6.0, 2)
    assert m.scan("clown fish and cl0wn-fish, clown")[:2] == (1.0, 1)
    assert m.scan("clown​")[1] == 1 and m.scan("")[0] == 0


def naive_scan(lexicon, exceptions, text):
    folded = f" {toxicity.fold(text)} "
    spots = {}
    for term, weight in lexicon.items():
        key = " " + toxicity.bare(term.rstrip("*"))
        for k in range(len(folded)):
            if folded.startswith(key, k) and (term.endswith("*") or folded[k + len(key)] == " "):
                spots[k] = max(spots.get(k, 0), weight)
    for phrase in exceptions:
        key = " " + toxicity.bare(phrase)
        for k in range(len(folded)):
            if folded.startswith(key, k) and folded[k + len(key)] == " ":
                spots = {s: w for s, w in spots.items() if not k <= s < k + len(key)}
    return sum(spots.values()), len(spots)


def test_scan_equals_naive_search():
    rng = random.Random(1)
    lexicon = {"ab": 1.0, "ab*": 0.5, "abba": 3.0, "b a": 2.0, "cab*": 4.0}
    for _ in range(300):
        text = "".join(rng.choices("abc  4", k=40))
        got = toxicity.Matcher(lexicon, ["ab ca", "bb"]).scan(text)
        assert (pytest.approx(got[0]), got[1]) == naive_scan(lexicon, ["ab ca", "bb"], text)


def test_toxicity_learns_held_out_terms(docs, spark):
    rng = random.Random(3)
    rows, labels = [], []
    for k in range(500):
        words = prose(k, 80).split()
        if k % 3 == 0:
            for _ in range(4):
                words.insert(rng.randrange(80), "zorblax" + rng.choice(WORDS)[:3])
        rows.append((k, " ".join(words)))
        labels.append((k, 1, int(k % 3 == 0)))
    frame, known = docs(rows), spark.createDataFrame(labels[:300], "doc_id long, quality int, toxic int")
    lexicon, cut = toxicity.learn(spark, frame, known)
    held = {r.doc_id: r.rejected for r in toxicity.score(frame, lexicon, cut).where("doc_id >= 300").collect()}
    wrong = [k for k in held if held[k] != (k % 3 == 0)]
    assert len(wrong) <= 0.05 * len(held)
    kept = toxicity.keep_clean(frame, lexicon, cut)
    rejected = {r.doc_id for r in toxicity.score(frame, lexicon, cut).where("rejected").collect()}
    assert kept.columns == frame.columns and {r.doc_id for r in kept.collect()} == set(range(500)) - rejected


def test_toxicity_edges(docs, spark):
    frame = docs(EDGE, extra=CLASH)
    got = toxicity.score(frame, toxicity.SEED, toxicity.DEFAULT_CUT).collect()
    assert len(got) == len(EDGE) and not any(r.rejected for r in got)
    none = spark.createDataFrame([], "doc_id long, quality int, toxic int")
    assert toxicity.learn(spark, frame, none) == (toxicity.SEED, toxicity.DEFAULT_CUT)
    assert toxicity.keep_clean(frame, toxicity.SEED, 1.0).count() == len(EDGE)


def test_words_split_like_python():
    texts = ["a  b\nc", "", "é ü x", " lead", "tail "]
    words = Words(pa.array(texts, pa.large_string()), NONSPACE)
    raw = "".join(texts).encode()
    got = [[] for _ in texts]
    for d, a, b in zip(words.doc, words.starts, words.ends):
        got[d].append(raw[a:b].decode())
    assert got == [t.split() for t in texts]


def test_signs_at_word_ends_are_punctuation_or_letters():
    m = toxicity.Matcher({"idiot": 2.0, "bass": 4.0, "shit": 1.0}, ["trash can"])
    assert [m.scan(t) for t in ("idiot!", "idiot!!! no", "ba$$", "$hit|", "idi0t$", "ba$$!")] == [(2.0, 1, 1), (2.0, 1, 2), (4.0, 1, 1), (1.0, 1, 1), (2.0, 1, 1), (4.0, 1, 1)]
    assert toxicity.Matcher({"trash": 6.0}, ["trash can"]).scan("trash can!") == (0.0, 0, 2)


def test_toxicity_scores_an_empty_table(docs):
    assert toxicity.score(docs([(1, "a")]).limit(0), toxicity.SEED, 1.0).count() == 0


def test_equal_stamps_are_told_apart_by_words(monkeypatch):
    text = np.array([1, 2, 3, 4, 1, 2, 3, 5, 1, 2, 3, 4] + [0] * 4)
    monkeypatch.setattr(suffix, "mix64", lambda x: x * np.uint64(0))
    order, common = suffix.deep_shallow(text, np.array([0, 4, 8]), 4, 2)
    assert sorted(common.tolist()) == [0, 3, 4] and text[np.array([0, 4, 8])[order][-1] + 3] == 5
