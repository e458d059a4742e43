"""Packing: rules of the pieces, bounds, and results of the exchange."""

import random
import zlib
from collections import defaultdict

import pytest


def test_best_fit_and_bound():
    from gapselect.llm.packing import best_fit, lower_bound

    rng = random.Random(2)
    for _ in range(200):
        cap = rng.choice([10, 17, 64])
        counts = defaultdict(int)
        for _ in range(rng.randint(0, 120)):
            counts[rng.randint(1, cap)] += rng.randint(1, 4)
        placed, bins = best_fit(dict(counts), cap)
        used, seen = defaultdict(list), defaultdict(list)
        for size, rank, n, first, offset in placed:
            for k in range(n):
                used[first + k].append((offset, size))
                seen[size].append(rank + k)
        assert {s: sorted(r) for s, r in seen.items()} == {s: list(range(c)) for s, c in counts.items()}
        assert sorted(used) == list(range(bins))
        for items in used.values():
            at = 0
            for offset, size in sorted(items):
                assert offset == at
                at += size
            assert at <= cap
        assert lower_bound(dict(counts), cap) <= bins


def test_bound_beats_volume():
    from gapselect.llm.packing import lower_bound

    assert lower_bound({6: 5}, 10) == 5  # volume alone says 3
    assert lower_bound({4: 6, 7: 3}, 10) == 6  # 7s stand alone, two 4s a bin
    assert lower_bound({}, 10) == 0


@pytest.mark.parametrize("parts,capacity", [(6, 64), (1, 1024)])
def test_pack(spark, sf, parts, capacity):
    tokenizers = pytest.importorskip("tokenizers")
    from gapselect.llm.coding import default_vocabulary
    from gapselect.llm.packing import pack

    path, report = default_vocabulary(), {}
    texts = [(r.doc_id, r.text) for r in spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text").collect()]
    texts += [(-1, None), (-2, ""), (-3, "twice"), (-3, "twice"), (None, "no id")]
    df = spark.createDataFrame([(i, t, "x", 1) for i, t in texts], "doc_id long, text string, length string, part int").repartition(parts)
    rows = pack(df, path, capacity, fan_in=2, report=report).collect()
    ref = tokenizers.Tokenizer.from_file(path)
    want = defaultdict(int)
    for i, t in texts:
        ids = [*ref.encode(t or "", add_special_tokens=False).ids, 2]
        at = piece = 0
        while at < len(ids):
            to = at + (len(ids) - at) % capacity if (len(ids) - at) % capacity else at + capacity
            want[(i, piece, at, to - at, zlib.crc32(b"".join(x.to_bytes(4, "little") for x in ids[at:to])))] += 1
            at, piece = to, piece + 1
    got, bins = defaultdict(int), defaultdict(list)
    for r in rows:
        got[(r.doc_id, r.piece, r.start, r.length, r.ids_crc32)] += 1
        bins[r.sequence_id].append((r.offset, r.length))
    assert got == want
    for items in bins.values():
        at = 0
        for offset, length in sorted(items):
            assert offset == at
            at += length
        assert at <= capacity
    assert len(bins) == report["bins"] and report["bound"] <= len(bins) <= 1.02 * report["bound"] + 1


def test_empty(spark):
    from gapselect.llm.coding import default_vocabulary
    from gapselect.llm.packing import pack

    assert pack(spark.createDataFrame([], "doc_id long, text string"), default_vocabulary()).count() == 0
