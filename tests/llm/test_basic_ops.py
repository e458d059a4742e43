"""Brute-force checks of exact dedup, quality rules, coding and the ring."""

import hashlib
import re
import zlib
from collections import Counter

import pytest

TEXTS = [
    (1, "a  b\tc"), (2, "a b c"), (3, None), (4, ""), (5, "x " * 30), (6, "one two three four five six seven eight " * 3),
    (7, "Über den Wörtern ### | <b> $5 & more\n\nline\nline\n line"), (8, "<|endoftext|>é中文\U0001F600 it's  \n"), (8, "same id twice"),
    (None, "null id"), (10, "z" * 3000), (11, "x " * 30), (12, "l\nl\nl\n" * 10),
]


def frame(spark, rows=TEXTS):
    # clashing and nested extra columns that no operator may trip over
    data = [(i, t, "row", [1], None) for i, t in rows]
    return spark.createDataFrame(data, "doc_id long, text string, row string, size array<int>, `a.b` string")


def words(t):
    return re.findall(r"[^\x20\x09-\x0D]+", t or "")


def repeats(w):
    wins = Counter(tuple(w[i : i + 8]) for i in range(len(w) - 7))
    return len({i + k for i in range(len(w) - 7) if wins[tuple(w[i : i + 8])] > 1 for k in range(8)})


def test_exact_dedup(spark):
    from gapselect.llm.exact_dedup import drop_copies, exact_groups

    rows = TEXTS + [(2, "a b c")]
    got = exact_groups(frame(spark, rows), digest=True).collect()
    norm = [re.sub(r"[\x20\x09-\x0D]+", " ", t or "") for _, t in rows]
    size = Counter(norm)
    assert len(got) == len(rows)
    want = Counter((i, size[n], hashlib.sha256(n.encode()).hexdigest()) for (i, _), n in zip(rows, norm))
    assert Counter((r.doc_id, r.group_size, r.text_sha256) for r in got) == want
    kept = [r for r in got if r.kept]
    assert len(kept) == len(size)
    assert {r.keep_id for r in got if r.text_sha256 == hashlib.sha256(b"a b c").hexdigest()} == {1}
    lazy = exact_groups(frame(spark, rows)).collect()
    assert Counter((r.doc_id, r.keep_id, r.group_size, r.kept) for r in lazy) == Counter((r.doc_id, r.keep_id, r.group_size, r.kept) for r in got)
    left = drop_copies(frame(spark))
    assert left.columns == frame(spark).columns
    assert left.count() == len({re.sub(r"[\x20\x09-\x0D]+", " ", t or "") for _, t in TEXTS})
    assert exact_groups(frame(spark, [])).count() == 0


def test_drop_copies_decides_by_row(spark):
    from gapselect.llm.exact_dedup import drop_copies

    rows = [(1, "t"), (1, "t"), (2, "u"), (3, "t"), (2, "w"), (None, "u"), (None, None), (None, "")]
    out = drop_copies(frame(spark, rows).repartition(3))
    assert sorted((r.doc_id, r.text) for r in out.filter("doc_id IS NOT NULL").collect()) == [(1, "t"), (2, "u"), (2, "w")]
    assert out.filter("doc_id IS NULL").count() == 1 and out.columns == frame(spark).columns


def test_quality(spark):
    from gapselect.llm.quality import filter_quality, quality_rules

    got = {(r.doc_id, r.n_words, r.word_chars): r for r in quality_rules(frame(spark)).collect()}
    assert len(got) == len(TEXTS)
    for i, t in TEXTS:
        w = words(t)
        lines = [x for x in (t or "").split("\n") if words(x)]
        r = got[(i, len(w), sum(map(len, w)))]
        assert r.n_symbols == len(re.findall(r"[#*$%&|<>]", t or ""))
        assert r.n_dup_lines == len(lines) - len(set(lines))
        assert r.n_repeat_words == repeats(w)
        assert r.base_failed == (len(w) < 20 or 100 * repeats(w) > 30 * len(w))
        assert not (r.base_failed and r.kept)
    out = filter_quality(frame(spark))
    assert out.columns == frame(spark).columns
    assert quality_rules(frame(spark, [])).count() == 0 and filter_quality(frame(spark, [])).count() == 0


def verdict(text):
    """Whether the threshold table keeps a text, counted by hand."""
    from gapselect.llm.quality import STOP_WORDS

    w = words(text)
    lines = [x for x in (text or "").split("\n") if words(x)]
    if len(w) < 20 or 100 * repeats(w) > 30 * len(w):
        return False
    return (
        2 <= sum(map(len, w)) / len(w) <= 14
        and len(re.findall(r"[#*$%&|<>]", text)) / len(w) <= 0.10
        and (len(lines) - len(set(lines))) / len(lines) <= 0.35
        and sum(x.lower() in STOP_WORDS for x in w) / len(w) >= 0.02
        and max(map(len, w)) <= 1000
    )


def test_quality_verdict(spark, sf):
    from gapselect.llm.quality import filter_quality, quality_rules

    plain = " ".join(f"the word{k}" for k in range(20))
    rows = [
        (1, plain), (2, plain + " x" * 100), (3, plain + " #" * 5), (4, plain.replace("the ", "qq ")), (5, plain + " " + "z" * 1001),
        (6, plain + "\nsame\nsame\nsame"), (7, plain + "\nsame\nsame"), (8, " ".join("ab" * 8 + str(k) for k in range(30)) + " the"), (9, None), (10, "the " * 30),
    ]
    rows += [(100 + r.doc_id, r.text) for r in spark.read.parquet(f"{sf}/documents.parquet").collect()]
    got = {r.doc_id: r.kept for r in quality_rules(frame(spark, rows)).collect()}
    assert got == {i: verdict(t) for i, t in rows} and len({got[k] for k in range(1, 11)}) == 2
    assert {r.doc_id for r in filter_quality(frame(spark, rows)).collect()} == {i for i, keep in got.items() if keep}


def test_quality_on_table(spark, sf):
    from gapselect.llm.quality import quality_rules

    docs = spark.read.parquet(f"{sf}/documents.parquet")
    texts = {r.doc_id: r.text for r in docs.collect()}
    for r in quality_rules(docs).collect():
        w = words(texts[r.doc_id])
        assert (r.n_words, r.n_repeat_words) == (len(w), repeats(w))


def test_codec(spark):
    tokenizers = pytest.importorskip("tokenizers")
    from gapselect.llm.coding import decode_documents, default_vocabulary, encode_documents

    path = default_vocabulary()
    ref = tokenizers.Tokenizer.from_file(path)
    got = decode_documents(encode_documents(frame(spark), path), path).collect()
    want = Counter()
    for i, t in TEXTS:
        ids = ref.encode(t or "", add_special_tokens=False).ids
        want[(i, b"".join(x.to_bytes(4, "little") for x in ids), ref.decode(ids, skip_special_tokens=False))] += 1
    assert Counter((r.doc_id, bytes(r.ids), r.text) for r in got) == want


def test_backtracking_against_library():
    tokenizers = pytest.importorskip("tokenizers")
    import random

    from gapselect.llm.bpe import coder, fast_ids
    from gapselect.llm.coding import default_vocabulary

    path = default_vocabulary()
    ref, own, fast = tokenizers.Tokenizer.from_file(path), coder(path), fast_ids(path)
    rng = random.Random(3)
    texts = ["".join(rng.choice("abcdefgh  'éß中\n\t1.") for _ in range(rng.randint(0, 80))) for _ in range(3000)]
    texts += ["a" * 4000, " " * 7000 + "x", "1" * 3000, "<|endoftext|>" * 3]
    for t, e in zip(texts, ref.encode_batch(texts, add_special_tokens=False)):
        assert own.encode(t) == e.ids == list(fast(t))


def test_ring(spark):
    from gapselect.llm.ring import ring_shards

    rows = TEXTS + [(100 + i, "hot") for i in range(200)] + [(1000 + i, f"t{i}") for i in range(300)]
    got = ring_shards(frame(spark, rows), shards=7, virtual=8).collect()
    assert Counter((r.doc_id, r.size, r.text_crc32) for r in got) == Counter((i, len((t or "").encode()) + 16, zlib.crc32((t or "").encode())) for i, t in rows)
    per = Counter(r["shard"] for r in got)
    assert max(per.values()) - min(per.values()) <= 1 and len(per) == 7
    for s in per:
        assert sorted(r.slot for r in got if r["shard"] == s) == list(range(per[s]))
    assert ring_shards(frame(spark, [])).count() == 0
    tied = [(7, "same"), (7, "same"), (7, None), (7, None), (None, "same")] * 3
    again = ring_shards(frame(spark, tied), shards=4, virtual=4).collect()
    assert sorted(Counter(r["shard"] for r in again).values()) == [3, 4, 4, 4]


def test_ring_moves_little():
    """When a ninth shard joins, about a ninth of the rows have to move; with slack few more do."""
    import random
    from bisect import bisect_left

    from gapselect.llm.ring import moved_share, ring_points, walk

    rng, rows = random.Random(1), 40_000
    at = sorted(rng.randrange(-(1 << 63), 1 << 63) for _ in range(rows))

    def placed(shards, room):
        points = ring_points(shards, 64)
        counts = [0] * (len(points) + 1)
        for x in at:
            counts[bisect_left([p for p, _ in points], x)] += 1
        return walk([*points, points[0]], counts, [room] * shards)

    free = moved_share(placed(8, rows), placed(9, rows), rows)  # nothing overflows
    assert 0.5 / 9 <= free <= 2 / 9
    tight = moved_share(placed(8, rows * 5 // 32), placed(9, rows * 5 // 36), rows)  # a quarter of room to spare
    assert free <= tight <= 3 / 9
