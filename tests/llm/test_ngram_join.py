"""The prefix-tree join against all pairs."""

import random
import re


def brute(rows, width=4, percent=85):
    sets = {}
    for i, t in rows:
        w = re.findall(r"[^\x20\x09-\x0D]+", (t or "").translate({c: c + 32 for c in range(65, 91)}))
        sets[i] = {tuple(w[k : k + width]) for k in range(len(w) - width + 1)} or ({tuple(w)} if w else set())
    ids = sorted(sets)
    root = {i: i for i in ids}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a in ids:
        for b in ids:
            if a < b and sets[a] and sets[b] and 100 * len(sets[a] & sets[b]) >= percent * len(sets[a] | sets[b]):
                x, y = sorted((find(a), find(b)))
                root[y] = x
    return {i: (len(sets[i]), find(i)) for i in ids}


def corpus(seed=5, n=160):
    rng = random.Random(seed)
    vocab = [f"w{k}" for k in range(400)]
    passage = " ".join(rng.choice(vocab) for _ in range(30))
    rows = [(1, None), (2, ""), (3, " \t\n"), (4, "One two"), (5, "one TWO"), (6, "one two three"), (7, "É a b c d"), (8, "é a b c d")]
    for k in range(n):
        base = [rng.choice(vocab) for _ in range(rng.randint(5, 90))]
        text = " ".join(base) + (" " + passage if k % 3 == 0 else "")
        rows.append((10 + 40 * k, text))
        for c in range(rng.choice([0, 0, 0, 1, 2, 5]) if k else 30):
            words = text.split()
            for _ in range(rng.randint(0, 3)):
                words[rng.randrange(len(words))] = rng.choice(vocab)
            rows.append((11 + 40 * k + c, "  ".join(words)))
    rng.shuffle(rows)
    return rows


def run(spark, rows, **more):
    from gapselect.llm.ngram_join import link_components

    data = spark.createDataFrame([(i, t, 1, 2) for i, t in rows], "doc_id long, text string, node int, n int").repartition(5)
    return {r.doc_id: (r.n_shingles, r.component_id) for r in link_components(data, **more).collect()}


def test_against_all_pairs(spark):
    rows = corpus()
    assert run(spark, rows) == brute(rows)


def test_other_parameters(spark):
    rows = corpus(9, 60)
    assert run(spark, rows, width=3, percent=60, pivots=1, turns=1) == brute(rows, 3, 60)


def test_empty(spark):
    assert run(spark, []) == {}
    assert run(spark, [(1, None), (2, "alone")]) == {1: (0, 1), 2: (1, 2)}


def test_table(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text")
    rows = [tuple(r) for r in docs.collect()]
    assert run(spark, rows) == brute(rows)


def test_one_of_each(spark):
    from gapselect.llm.ngram_join import one_of_each

    rows = corpus(11, 40)
    out = one_of_each(spark.createDataFrame(rows, "doc_id long, text string"))
    want = brute(rows)
    assert {r.doc_id for r in out.collect()} == {i for i, (_, c) in want.items() if i == c} and out.columns == ["doc_id", "text"]


def test_one_of_each_decides_by_row(spark):
    from gapselect.llm.ngram_join import one_of_each

    a = " ".join(f"a{k}" for k in range(40))
    b = " ".join(f"b{k}" for k in range(40))
    rows = [(1, a), (1, a), (1, b), (2, b + " more"), (0, a + " more"), (5, None), (5, ""), (None, a), (7, "alone here")]
    out = one_of_each(spark.createDataFrame([(i, t, "x") for i, t in rows], "doc_id long, text string, component_id string").repartition(4))
    assert sorted(((r.doc_id, r.text) for r in out.collect()), key=str) == sorted([(0, a + " more"), (1, b), (5, None), (5, ""), (7, "alone here")], key=str)


def test_hot_group_in_blocks(spark, monkeypatch):
    """Groups and trees of many blocks give the links of all pairs."""
    from gapselect.llm import ngram_join

    monkeypatch.setattr(ngram_join, "BLOCK", 4)
    monkeypatch.setattr(ngram_join, "TREES", 6)
    rows = corpus(13, 50)
    assert run(spark, rows) == brute(rows)


def test_tree_walk(monkeypatch):
    """One walk of all queries over sorted paths gives the link test of every pair."""
    import numpy as np

    from gapselect.llm import ngram_join

    rng = random.Random(2)
    for percent, cells in ((50, 1 << 24), (80, 1 << 24), (85, 200)):
        monkeypatch.setattr(ngram_join, "_CELLS", cells)
        base = set(rng.sample(range(40), 20))
        sets = [sorted(base - set(rng.sample(range(40), rng.randint(0, 8))) | set(rng.sample(range(60), rng.randint(0, 3)))) for _ in range(70)]
        paths, queries = sorted(x for x in sets[:60] if x), [x for x in sets[60:] if x]
        tree = ngram_join.PrefixTree([np.array(p, np.int64) for p in paths], np.array([len(p) for p in paths]))
        got = tree.walk([np.array(q, np.int64) for q in queries], np.array([len(q) for q in queries]), percent)
        for i, p in enumerate(paths):
            for k, q in enumerate(queries):
                assert got[i, k] == (100 * len(set(p) & set(q)) >= percent * len(set(p) | set(q)))


def test_components_of_links(spark):
    from gapselect.llm.ngram_join import components_of_links

    links = [(i, i + 3) for i in range(60)] + [(200, 201), (201, 200), (300, 300)]
    df = spark.createDataFrame(links, "a long, b long").repartition(4)
    want = {i: i % 3 for i in range(63)} | {200: 200, 201: 200, 300: 300}
    for per_task in (5, 1000):
        got = {r.node: r.component for r in components_of_links(df, per_task).collect()}
        assert {k: v for k, v in got.items() if k != 300} == {k: v for k, v in want.items() if k != 300}


def test_components(spark):
    from gapselect.llm.components import connected_components

    edges = [(1, 2), (2, 3), (5, 4), (6, 6), (9, 8), (8, 7), (7, 10), (3, 1), (3, 1)] + [(100 + i, 101 + i) for i in range(40)]
    got = {r.node: r.component for r in connected_components(spark.createDataFrame(edges, "u long, v long")).collect()}
    assert got == {1: 1, 2: 1, 3: 1, 4: 4, 5: 4, 7: 7, 8: 7, 9: 7, 10: 7} | {100 + i: 100 for i in range(41)}
    assert connected_components(spark.createDataFrame([], "u string, v string")).count() == 0


def test_members_that_fit_no_other_leave_their_group(spark):
    """Paths of 20 steps at 85 percent share 19 of them to link, so none can first meet at
    step 17 or 18; one that is shorter can."""
    from gapselect.llm.ngram_join import _able_to_link

    rows = [(k, 20, t, left) for t, left in ((7, 17), (8, 18), (9, 19)) for k in range(50)] + [(50, 17, 8, 17), (51, 20, 10, 20)]
    kept = _able_to_link(spark.createDataFrame(rows, "node long, n long, token long, left int"), 85)
    assert set(kept.columns) == {"node", "n", "token", "left"}
    counts = {r["token"]: r["count"] for r in kept.groupBy("token").count().collect()}
    assert counts == {8: 51, 9: 50}


def test_written_tables_are_broadcast_by_their_rows_not_their_files(spark):
    from gapselect.llm.common import SENT_BYTES, written

    rows = spark.range(60_000).selectExpr("id AS node", "sequence(1L, 50L) AS tokens")
    large, small = written(rows), written(spark.range(100).withColumnRenamed("id", "node"))
    plan = large.join(spark.range(1_000_000).withColumnRenamed("id", "node"), "node")
    assert "Broadcast" not in plan._jdf.queryExecution().executedPlan().toString() and 60_000 * 50 * 8 > SENT_BYTES
    assert "Broadcast" in small.join(spark.range(10_000_000).withColumnRenamed("id", "node"), "node")._jdf.queryExecution().executedPlan().toString()
    assert large.count() == 60_000


def test_small_tables_go_in_few_tasks(spark):
    """Exchanges of many partitions leave a small table in a task a core, not in all of them."""
    from gapselect.llm.ngram_join import _able_to_link

    conf = {"spark.sql.shuffle.partitions": "64", "spark.sql.adaptive.coalescePartitions.enabled": "false", "spark.sql.autoBroadcastJoinThreshold": "-1"}
    held = {k: spark.conf.get(k) for k in conf}
    rows = [(k, 20, t, 19) for t in range(40) for k in range(50)]
    try:
        for k, v in conf.items():
            spark.conf.set(k, v)
        kept = _able_to_link(spark.createDataFrame(rows, "node long, n long, token long, left int"), 85)
        assert kept.rdd.getNumPartitions() == spark.sparkContext.defaultParallelism and kept.count() == len(rows)
    finally:
        for k, v in held.items():
            spark.conf.set(k, v)
