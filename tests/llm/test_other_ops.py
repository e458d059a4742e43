"""URL rules with aliases, preference pairs, token attribution, training order, pipeline."""

import random
import zlib

import numpy as np
import pytest


def test_urls_and_aliases(spark):
    from gapselect.llm.url_rules import UrlRule, judge_urls

    link = '<link href="{}" rel="canonical">'
    move = '<META http-equiv=refresh content="0; url={}">'
    pages = [
        (1, "https://a.example.com/de/x", None),  # own block
        (2, "http://b.example.com/", link.format("https://a.example.com/de/x")),  # alias of a blocked page
        (3, "http://c.example.com/p?utm_source=q", move.format("http://b.example.com/?gclid=1")),  # two steps away
        (4, "http://d.example.com/fr/1", link.format("http://a.example.com/de/y")),  # own allow stays
        (5, "http://A.Example.COM/de/y#x", None),
        (6, "http://e.net/x/y", link.format("../up")),
        (7, "http://f.net/x", link.format("/root") + link.format("http://good.org/")),  # allow comes first
        (8, "http://f.net/root", move.format("http://a.example.com/de/x2")),
        (9, None, link.format("http://a.example.com/de/x")), (10, "no scheme", None), (11, "http://", None),
        (12, "http://x.example.org/es/1", None), (13, "http://sub.org/", None), (14, "http://notorg/", None), (15, "http://q.com", None),
        (16, "http://g.net/", link.format("//a.example.com/de/x")), (2, "http://b.example.com/", link.format("https://a.example.com/de/x")),
    ]
    df = spark.createDataFrame([(i, u, h, "x", 1) for i, u, h in pages], "page_id long, url string, html string, host string, rule int")
    rows = judge_urls(df).collect()
    assert len(rows) == len(pages)
    got = {r.page_id: (r.host, r.path, r.rule, r.verdict) for r in rows}
    assert got[1] == ("a.example.com", "/de/x", "com/de/", "block")
    assert got[2][2:] == (None, "block") and got[3][2:] == (None, "block") and got[16][2:] == (None, "block")
    assert got[4][2:] == ("com/fr/", "allow") and got[5] == ("a.example.com", "/de/y", "com/de/", "block")
    assert got[6][3] == "allow" and got[7][2:] == (None, "allow") and got[8][2:] == (None, "allow")
    assert got[9] == got[10] == ("", "", None, "allow") and got[11][:2] == ("", "")
    assert got[12][2:] == ("example.org/es/", "block") and got[13][2:] == ("org/", "allow") and got[14][2] is None
    assert got[15] == ("q.com", "", None, "allow")
    assert {r.verdict for r in judge_urls(df, rules=(UrlRule("block", "net"),), default="allow").filter("page_id = 6").collect()} == {"block"}
    assert judge_urls(df.filter("page_id < 0")).count() == 0


def test_alias_classes_against_brute_force(spark):
    from gapselect.llm.url_rules import judge_urls

    rng = random.Random(1)
    hosts = ["a.net", "b.org", "c.com/de", "d.com/fr", "e.net", "f.net"]
    urls = [f"http://{rng.choice(hosts)}/p{k}" for k in range(120)]
    pages = [(k, u, f'<link rel="canonical" href="{rng.choice(urls)}">' if rng.random() < 0.5 else "") for k, u in enumerate(urls)]
    root = {u: u for u in urls}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for _, u, h in pages:
        if h:
            root[find(u)] = find(h.split('href="')[1][:-2])

    def own(u):
        return "allow" if ".org/" in u or "com/fr/" in u else "block" if "com/de/" in u else None

    want = {}
    for k, u, _ in pages:
        said = {own(v) for v in urls if find(v) == find(u)} - {None}
        want[k] = own(u) or ("allow" if "allow" in said else "block" if said else "allow")
    got = judge_urls(spark.createDataFrame(pages, "page_id long, url string, html string"))
    assert {r.page_id: r.verdict for r in got.collect()} == want


def test_preference_pairs(spark):
    from gapselect.llm.preference import preference_pairs, swapped_replies

    schema = "pair_id long, turn long, role string, text string, n int"
    c = [(1, 0, "user", "hi", 0), (1, 1, "assistant", "good", 0), (2, 0, "user", "same", 0), (3, 0, None, None, 0), (3, 1, "assistant", "x", 0), (5, 0, "user", "only chosen", 0)]
    r = [(1, 0, "user", "hi", 0), (1, 1, "assistant", "bad", 0), (1, 2, "user", "?", 0), (2, 0, "user", "same", 0), (3, 0, "", "", 0), (6, 0, "user", "only rejected", 0)]
    got = {x.pair_id: x for x in preference_pairs(spark.createDataFrame(c, schema), spark.createDataFrame(r, schema)).collect()}
    assert got[1].prompt == "<|im_start|>user\nhi<|im_end|>\n" and got[1].n_prompt_turns == 1
    assert got[1].chosen == "<|im_start|>assistant\ngood<|im_end|>\n" and got[1].rejected.endswith("user\n?<|im_end|>\n")
    assert [tuple(m) for m in got[1].rejected_mask] == [(36, 1), (29, 0)] and sum(m.chars for m in got[1].chosen_mask) == len(got[1].chosen)
    assert got[2].chosen == got[2].rejected == "" and got[2].n_prompt_turns == 1
    assert got[3].n_prompt_turns == 1 and got[3].rejected == ""
    assert got[5].prompt == "" and got[5].rejected == "" and got[6].chosen == ""
    empty = spark.createDataFrame([], "conv_id long, turn long, role string, text string")
    assert preference_pairs(*swapped_replies(empty)).count() == 0


@pytest.mark.parametrize("rule", ["start", "end", "split"])
def test_attribution(spark, rule):
    tokenizers = pytest.importorskip("tokenizers")
    from gapselect.llm.attribution import attribute_tokens
    from gapselect.llm.coding import default_vocabulary

    path = default_vocabulary()
    texts = [(1, "Hello wörld\n\nsecond line 中文字\n"), (2, None), (3, ""), (4, "\U0001F600\U0001F601 x\n" * 3), (4, "a\r\n  b")]
    ref = tokenizers.Tokenizer.from_file(path)
    df = spark.createDataFrame([(i, t, 1) for i, t in texts], "doc_id long, text string, section int")
    rows = attribute_tokens(df, path, rule=rule).collect()
    want = sorted((i, len((t or "").split("\n")), len(ref.encode(t or "").ids)) for i, t in texts)
    assert sum(w[1] for w in want) == len(rows)
    assert sum(r.n_tokens for r in rows) == pytest.approx(sum(w[2] for w in want))
    for r in [r for r in rows if r.doc_id == 1]:  # ascii, and letters that are one token each
        spans = ref.encode(texts[0][1]).offsets
        share = {"start": lambda a, b: r.start <= a < r.end, "end": lambda a, b: r.start <= b - 1 < r.end, "split": lambda a, b: max(0, min(b, r.end) - max(a, r.start)) / max(1, b - a)}[rule]
        assert r.n_tokens == pytest.approx(sum(share(a, b) for a, b in spans))
    assert attribute_tokens(df.filter("doc_id < 0"), path, rule=rule).count() == 0
    long = "a longer line of text\n" * 20_000
    much = attribute_tokens(spark.createDataFrame([(1, long)], "doc_id long, text string"), path, rule=rule).collect()
    assert len(much) == 20_001 and sum(r.n_tokens for r in much) == pytest.approx(len(ref.encode(long).ids))


def test_attribution_fields(spark):
    from gapselect.llm.attribution import attribute_tokens, field_text
    from gapselect.llm.coding import default_vocabulary

    df = spark.createDataFrame([(1, "title here", "body of it"), (2, None, "x")], "doc_id long, title string, body string")
    text, spans = field_text(["title", "body"])
    got = attribute_tokens(df.select("doc_id", text.alias("text"), spans.alias("s")), default_vocabulary(), "s").collect()
    assert [(r.doc_id, r.name, r.n_tokens) for r in sorted(got)] == [(1, "title", 2), (1, "body", 3), (2, "title", 0), (2, "body", 1)]


def test_feistel():
    from gapselect.llm.training_order import Feistel

    for n in (1, 2, 3, 7, 64, 1000, 4097):
        f = Feistel(n, 5)
        slots = f.slot(np.arange(n))
        assert sorted(slots.tolist()) == list(range(n)) and (f.sequence(slots) == np.arange(n)).all()
    assert (Feistel(1000, 5).slot(np.arange(1000)) != Feistel(1000, 6).slot(np.arange(1000))).any()


def test_training_order(spark, sf, tmp_path):
    from gapselect.llm.bpe import fast_ids
    from gapselect.llm.coding import default_vocabulary
    from gapselect.llm.training_order import read_sequences, write_order

    path = default_vocabulary()
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    folder = f"file://{tmp_path}/out"
    rows = sorted(write_order(docs, path, folder, length=64, per_shard=50).collect())
    assert [r.slot for r in rows] == list(range(len(rows)))
    stored = read_sequences(folder, [r.slot for r in rows], 64, 50)
    assert all(zlib.crc32(s.tobytes()) == r.ids_crc32 and r.offset == r.slot % 50 * 128 and r["shard"] == r.slot // 50 for s, r in zip(stored, rows))
    assert not [p for p in (tmp_path / "out").iterdir() if not p.name.endswith(".bin")]
    text = {r.doc_id: r.text for r in docs.collect()}
    tokens = {d: [*fast_ids(path)(t).tolist(), 50256] for d, t in text.items()}
    assert sum(r.n_tokens for r in rows) == sum(map(len, tokens.values()))
    assert {d for r in rows for d in r.doc_ids} == set(text)
    for r, s in list(zip(rows, stored))[::7]:  # what a sequence holds is a cut of its documents, in order
        joined = ",".join(str(x) for d in r.doc_ids for x in tokens[d])
        assert ",".join(str(x) for x in s[: r.n_tokens]) in joined
    empty = spark.createDataFrame([], "doc_id long, text string")
    assert write_order(empty, path, f"file://{tmp_path}/none").count() == 0
    odd = spark.createDataFrame([(1, None), (2, ""), (2, ""), (None, "x")], "doc_id long, text string").coalesce(1)
    assert [(r.n_tokens, r.doc_ids) for r in write_order(odd, path, f"file://{tmp_path}/odd").collect()] == [(5, [1, 2, 2, None])]


def test_pipeline(spark, sf):
    import corpus_pipeline
    from test_ngram_join import brute

    from gapselect.llm.exact_dedup import exact_groups
    from gapselect.llm.quality import quality_rules

    assert [n for n, _ in corpus_pipeline.STAGES] == ["quality_rules", "exact_dedup", "ngram_jaccard_join", "best_fit_packing"]
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    good = {r.doc_id for r in quality_rules(docs).filter("kept").collect()}
    first = {r.doc_id for r in exact_groups(docs.filter(docs.doc_id.isin(list(good)))).filter("kept").collect()}
    rows = [(r.doc_id, r.text) for r in docs.collect() if r.doc_id in first]
    want = {i for i, (_, c) in brute(rows, 5, 80).items() if i == c}
    assert {r.doc_id for r in corpus_pipeline.run(spark, sf).collect()} == want
    step = docs
    for _, f in corpus_pipeline.STAGES[:-1]:
        step = f(spark, step, sf)
        assert step.columns == docs.columns
