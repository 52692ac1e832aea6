"""The pipeline's stages, each against its own definition on its own input."""

from collections import Counter

import corpus_pipeline as cp
from elimspark.llm import decontam, minhash, toxicity

FOLDER = "/root/testdata/sf0.001"


def test_stages_and_run(spark):
    docs = spark.read.parquet(f"{FOLDER}/documents.parquet")
    columns, stage = docs.columns, {}
    for name, function in cp.STAGES:
        before = docs.collect()
        docs = spark.createDataFrame(function(spark, docs, FOLDER).collect() or [], docs.schema if name != "sharding" else "doc_id long, group_size long, shard long")
        stage[name] = (before, docs.collect())
        if name != "sharding":
            assert docs.columns == columns
    lexicon, cut = toxicity.learn(spark, spark.read.parquet(f"{FOLDER}/documents.parquet"), spark.read.parquet(f"{FOLDER}/labels.parquet"))
    matcher = toxicity.Matcher(lexicon)
    before, after = stage["toxicity"]
    good = [r.doc_id for r in before if (lambda s: round(toxicity.score_of(s[0], s[2]), 6) < cut)(matcher.scan(r.text))]
    assert sorted(good) == sorted(r.doc_id for r in after)

    before, after = stage["near_duplicates"]
    groups = {r.doc_id: r.group_id for r in minhash.near_duplicate_groups(spark.createDataFrame(before)).collect()}
    assert sorted(r.doc_id for r in after) == sorted(r.doc_id for r in before if groups.get(r.doc_id, r.doc_id) == r.doc_id)

    before, after = stage["decontamination"]
    items = [(r.item_id, r.text) for r in spark.read.parquet(f"{FOLDER}/benchmark.parquet").collect()]
    import re

    plain = lambda t: re.sub(r"[\W_]+", " ", t.lower()).strip()
    pieces = decontam.Pieces([(i, plain(t)) for i, t in items if plain(t)])
    assert sorted(r.doc_id for r in after) == sorted(r.doc_id for r in before if not pieces.search(plain(r.text)))

    before, after = stage["mixing"]
    assert abs(len(after) - len(before)) <= 20 and {r.doc_id for r in after} <= {r.doc_id for r in before}

    before, after = stage["sharding"]
    assert Counter(r.doc_id for r in after) == Counter(r.doc_id for r in before)
    assert all(len(s) == 1 for s in [{r.shard for r in after if r.doc_id == d} for d in {r.doc_id for r in after}])
    assert sorted(tuple(r) for r in cp.run(spark, FOLDER).collect()) == sorted(tuple(r) for r in after)


def test_queries_match_their_sql(spark):
    import duckdb

    from elimspark.llm import queries

    con = duckdb.connect()
    for name in ("documents", "benchmark", "labels", "embeddings", "pages"):
        con.execute(f"create view {name} as select * from '{FOLDER}/{name}.parquet'")
    for name, sql in queries.ORACLES.items():
        frame = queries.QUERIES[name](spark, FOLDER)
        columns = sorted(frame.columns)
        want = con.execute(f"select {', '.join(columns)} from ({sql})").fetchall()
        assert sorted(map(tuple, frame.select(*columns).collect()), key=str) == sorted(want, key=str), name


ODD = [(None, "alpha beta gamma delta", "en", None), (None, None, None, None), (1, None, "en", "s1"), (2, "", None, "s2"), (3, " \n\t ", "en", "s1"), (4, "é" * 200_000, "fr", "s1"), (5, "one", "en", "s1"), (5, "one", "en", "s1"), (6, "one", "en", "s2"), (7, "x " * 3000, "en", "s1"), (8, "x " * 3000, "en", "s2"), (9, "stupid idiot moron! " * 5, "en", "s3")]


def test_stages_take_odd_rows_empty_tables_and_clashing_columns(spark, docs):
    """Each stage keeps the columns of its input and doesn't crash; what it drops is told by its docstring."""
    names = ["copy", "shard", "row", "__plain", "toxic", "group_id", "size", "key"]
    frame = docs(ODD, extra=names)
    for name, function in cp.STAGES:
        got = function(spark, frame, FOLDER)
        rows = got.collect()
        ids = Counter(r.doc_id for r in rows)
        assert function(spark, frame.limit(0), FOLDER).count() == 0, name
        if name == "sharding":
            assert ids == Counter(r[0] for r in ODD)
            continue
        assert got.columns == frame.columns, name
        if name == "toxicity":
            assert ids == Counter(r[0] for r in ODD if r[0] != 9)
        elif name == "near_duplicates":
            # Of equal texts and of rows that share an id one stays; rows without an id or a word all stay.
            assert ids == Counter({None: 2, 1: 1, 2: 1, 3: 1, 4: 1, 5: 1, 7: 1, 9: 1})
        elif name == "decontamination":
            assert ids == Counter(r[0] for r in ODD)
        else:
            assert abs(len(rows) - len(ODD)) <= 4


def triples(text):
    import re

    words = re.findall(r"[^\W_]+", (text or "").lower())
    return {" ".join(words[k : k + 3]) for k in range(max(1, len(words) - 2))} if words else set()


def scrambled(i):
    return (i % 2147483647 * 1103515245 + 12345) % 2**31


def test_later_stages_equal_brute_force(spark):
    """All pairs by Jaccard, all items in all texts, plain running sums and a plain schedule."""
    import hashlib
    import heapq
    import re
    from fractions import Fraction

    docs = spark.read.parquet(f"{FOLDER}/documents.parquet")
    rows = {r.doc_id: r for r in docs.collect()}

    kept = {r.doc_id for r in cp.drop_near_duplicates(spark, docs, FOLDER).collect()}
    sets = {i: triples(r.text) for i, r in rows.items()}
    likeness = lambda a, b: len(sets[a] & sets[b]) / max(1, len(sets[a] | sets[b]))
    pairs = [(a, b, likeness(a, b)) for a in rows for b in rows if a < b and sets[a] and sets[b]]
    assert not [p for p in pairs if p[2] >= 0.65 and p[0] in kept and p[1] in kept]
    near = {x for a, b, j in pairs if j >= 0.3 for x in (a, b)}
    assert set(rows) - kept <= near and any(p[2] >= 0.65 for p in pairs)

    plain = lambda t: re.sub(r"[\W_]+", " ", t.lower()).strip()
    items = [plain(r.text) for r in spark.read.parquet(f"{FOLDER}/benchmark.parquet").collect()]
    leaks = {i for i, r in rows.items() if any(decontam.myers(t, plain(r.text), decontam.budget(len(t))) is not None for t in items)}
    got = {r.doc_id for r in cp.drop_benchmark_leaks(spark, docs, FOLDER).collect()}
    assert got == set(rows) - leaks and leaks

    weight = lambda s: int(m[0]) % 4 + 1 if (m := re.search(r"\d{1,9}$", s or "")) else 1
    by: dict = {}
    for i, r in rows.items():
        by.setdefault(r.source, []).append(i)
    whole = sum(weight(s) for s in by)
    want = Counter()
    for s, ids in by.items():
        step = Fraction(len(rows) * weight(s), len(ids) * whole)
        draw = int(hashlib.md5(f"42:s{s}".encode()).hexdigest()[:7], 16)
        total = Fraction(len(ids) * whole * draw // (1 << 28), len(ids) * whole)
        for i in sorted(ids, key=lambda i: (scrambled(i), i)):
            want[i] += int(total + step) - int(total)
            total += step
    mixed = cp.mix_sources(spark, docs, FOLDER)
    assert Counter(r.doc_id for r in mixed.collect()) == +want

    groups = sorted(((n * max(1, len(rows[i].text or "")), i) for i, n in (+want).items()), key=lambda g: (-g[0], scrambled(g[1]), g[1]))
    loads = [(0, s) for s in range(cp.SHARDS)]
    shard = {}
    for size, i in groups:
        load, s = heapq.heappop(loads)
        shard[i] = (size, s)
        heapq.heappush(loads, (load + size, s))
    assert {r.doc_id: (r.group_size, r.shard) for r in cp.assign_shards(spark, mixed, FOLDER).collect()} == shard
