"""Gradients, invariants and learning of the model; baselines against brute force."""

from dataclasses import replace

import numpy as np
import pytest

from gapselect.baselines.knn import _gap, _mode, distances, knn_impute, mode_impute
from gapselect.baselines.markov import chi2_critical, grow_shrink
from gapselect.model.fit import fit_all, load_model, mlp_fit_predict, ridge_solve, save_model
from gapselect.model.gnn import GnnConfig, MultiplexModel, fit_predict, inputs
from gapselect.model.multiplex import Band
from gapselect.operators import prep
from gapselect.spec import FeatureSpec, band, widen

TINY = GnnConfig(hidden=5, epochs=30, rate=1e-2)


def test_gradient():
    b = Band(4, 1, 3)
    rng = np.random.default_rng(0)
    for cfg in (TINY, replace(TINY, layers=3), replace(TINY, cross=False)):
        model = MultiplexModel(b, 3, 1, 4, cfg)
        x = rng.normal(size=(3, len(b), 4))
        rows, y = np.array([0, 3, 7, 9]), rng.normal(size=4)
        _, g = model.gradients(x, rows, y)
        for name, p in model.params.items():
            flat, got = p.reshape(-1), g[name].reshape(-1)
            for i in rng.choice(flat.size, min(6, flat.size), replace=False):
                old, eps = flat[i], 1e-6
                flat[i] = old + eps
                up = model.gradients(x, rows, y)[0]
                flat[i] = old - eps
                down = model.gradients(x, rows, y)[0]
                flat[i] = old
                assert got[i] == pytest.approx((up - down) / (2 * eps), abs=1e-5)


def test_neighbour_mean_paths_agree():
    a, b = Band(7, 1, 4), Band(7, 1, 4, dense=0)
    h = np.random.default_rng(1).normal(size=(len(a), 3)).astype(np.float32)
    assert np.allclose(a.mean(h), b.mean(h), atol=1e-5) and np.allclose(a.mean_back(h), b.mean_back(h), atol=1e-5)
    assert len(Band(20, 1, 3)) == 1350


def labels(n, groups, seed=0):
    rng = np.random.default_rng(seed)
    w = rng.random((groups, n))
    return {g: {m: float(sum(w[g, j] for j in range(n) if m >> j & 1)) for m in band(n, 1, 3)} for g in range(groups)}


def test_label_flow():
    """Labels of other subgroups reach a model only through the observed channel."""
    mine, other = labels(5, 2), labels(5, 2)
    other[1] = dict(zip(other[1], reversed(list(other[1].values()))))
    cfg = replace(TINY, level_max=3)
    assert (fit_predict(5, 2, 0, mine, cfg)[1] == fit_predict(5, 2, 0, other, cfg)[1]).all()
    seen = replace(cfg, label_channel="observed")
    assert not np.allclose(fit_predict(5, 2, 0, mine, seen)[1], fit_predict(5, 2, 0, other, seen)[1])


def test_hidden_labels_stay_hidden():
    b = Band(4, 1, 2)
    x = inputs(b, 2, {0: {1: 5.0, 2: 7.0}, 1: {1: 3.0}}, replace(TINY, label_channel="observed"), 0, np.array([b.at[1]]), (0.0, 1.0))
    assert x[0, b.at[1], 4:].tolist() == [0, 0] and x[0, b.at[2], 4:].tolist() == [7, 1] and x[1, b.at[1], 4:].tolist() == [3, 1]


def test_learning():
    known = labels(6, 2)
    full = {g: dict(known[g]) for g in known}
    hidden = [m for m in known[0] if m & 1 and m.bit_count() == 3]
    for m in hidden[::2]:
        del known[0][m]
    masks, out = fit_predict(6, 2, 0, known, GnnConfig(hidden=16, epochs=300, rate=1e-2, level_max=3))
    at = {int(m): v for m, v in zip(masks, out)}
    error = np.mean([(at[m] - full[0][m]) ** 2 for m in hidden[::2]])
    assert error < 0.3 * np.var(list(full[0].values()))
    trace = []
    fit_predict(6, 2, 0, known, replace(TINY, level_max=3), trace)
    assert trace[-1] < trace[0]
    assert (fit_predict(6, 2, 0, {0: {}, 1: {1: 2.0, 2: 4.0}}, TINY)[1] == 3.0).all()


def test_joint_mode_learns_from_all():
    cfg = replace(TINY, level_max=3, label_channel="joint")
    assert np.isfinite(fit_predict(5, 2, 0, labels(5, 2), cfg)[1]).all()


def test_mlp_and_ridge():
    known = labels(6, 1)[0]
    m, y = np.array(sorted(known)), np.array([known[k] for k in sorted(known)])
    assert np.abs(ridge_solve(6, m, y, m, 1e-9) - y).max() < 1e-5
    out = mlp_fit_predict(6, m, y, m, 0, 0, epochs=300, rate=5e-3)
    assert np.corrcoef(out, y)[0, 1] > 0.95


def test_fit_all_and_model_store(spark, tmp_path):
    known = labels(4, 2)
    rows = [(g, m, v) for g in known for m, v in known[g].items()]
    out = fit_all(spark.createDataFrame(rows, "sg int, mask long, mi double"), 4, 2, replace(TINY, level_max=3))
    assert out.count() == 2 * 14
    model = MultiplexModel(Band(4, 1, 3), 2, 0, 4, TINY)
    save_model(model.params, spark, f"{tmp_path}/m")
    back = load_model(spark, f"{tmp_path}/m")
    assert all(np.allclose(back[k], v) for k, v in model.params.items())


def test_distributed_is_the_model_of_one_task(spark, monkeypatch):
    from gapselect.model import distributed, fit

    known = labels(5, 3)
    for m in (1, 3, 7, 28):
        del known[0][m]
    known[2] = {1: 0.5}
    frame = spark.createDataFrame([(g, m, v) for g, d in known.items() for m, v in d.items()], "sg int, mask long, mi double")
    cfg = GnnConfig(hidden=4, epochs=7, rate=1e-2, level_max=3)
    monkeypatch.setattr(distributed, "BLOCK", 4)
    out, losses = distributed.fit_distributed(frame, 5, 3, cfg)
    got = {(r["sg"], r["mask"]): r["mi"] for r in out.collect()}
    assert losses[-1] < losses[0] and len(got) == 3 * 25
    for g in range(3):
        masks, want = fit_predict(5, 3, g, known, cfg)
        assert np.allclose([got[g, int(m)] for m in masks], want, atol=1e-4)
    monkeypatch.setattr(fit, "MOST_LABELS", 10)
    handed = {(r["sg"], r["mask"]): r["mi"] for r in fit_all(frame, 5, 3, cfg).collect()}
    assert handed.keys() == got.keys() and all(abs(handed[k] - got[k]) < 1e-4 for k in got)


def test_neighbourhood_means():
    from gapselect.model.distributed import Neighbourhood

    for inter, intra in ((True, True), (True, False), (False, True)):
        whole, part = Band(7, 2, 4, inter, intra), Neighbourhood(np.array([3, 21, 85]), 1, 7, 2, 4, inter, intra)
        at = [whole.at[int(m)] for m in part.masks]
        assert np.allclose(part.first, whole.mean(whole.bits())[at], atol=1e-5) and np.allclose(part.degree, whole.degree[at])
        h = np.random.default_rng(3).normal(size=(len(whole), 2))
        for m in (3, 21, 85):
            assert np.allclose(part.mean(h[at])[np.searchsorted(part.masks, m)], whole.mean(h)[whole.at[m]], atol=1e-5)


def test_distances():
    a = np.array([0x123, 0x103], np.int64)
    d = np.array([0x123, 0x321, 0x003], np.int64)
    zero2, zero3 = np.zeros(2, np.int64), np.zeros(3, np.int64)
    full = widen(0b111)
    assert distances(a, zero2, d, zero3, "mismatch", full).tolist() == [[0, 2, 2], [1, 3, 1]]
    assert distances(a, zero2, d, zero3, "ignore", full).tolist() == [[0, 2, 0], [0, 2, 0]]
    assert _gap(np.array([0x9]), np.array([0x6])).tolist() == [1]
    assert _mode(np.array([2, 3, 3]), np.array([4, 1, 9]), 5) == 2 and _mode(np.array([2, 1]), np.array([1, 1]), 2) == 1


def test_knn_against_rows(spark):
    spec = FeatureSpec(("a", "b", "c"))
    rng = np.random.default_rng(2)
    rows = [(int(i % 2), *(int(x) for x in rng.integers(1, 4, 2)), None if i % 2 else int(rng.integers(1, 4)), int(rng.integers(0, 2))) for i in range(80)]
    df = spark.createDataFrame(rows, "sg int, a int, b int, c int, y int")
    packed = prep.pack(prep.encode(df, spec), spec)
    got = {(r["a"], r["b"], r["y"]): r["c"] for r in prep.unpack(knn_impute(packed, spec, 5), spec).filter("sg = 1").collect()}
    donors = sorted((r[1] | r[2] << 4 | r[3] << 8, r) for r in rows if r[0] == 0)
    for a, b, y in got:
        near = sorted(donors, key=lambda d: ((d[1][1] != a) + (d[1][2] != b) + 1, d[0]))[:5]
        votes = np.bincount([d[1][3] for d in near], minlength=4)
        assert got[a, b, y] == votes.argmax()
    modes = prep.unpack(mode_impute(packed, spec), spec)
    assert modes.filter("c = 0").count() == 0


def test_markov(spark):
    assert chi2_critical(1, 0.05) == pytest.approx(3.84, abs=0.15) and chi2_critical(10, 0.05) == pytest.approx(18.31, abs=0.1)
    rng = np.random.default_rng(3)
    rows = []
    for i in range(800):
        a, b, c, d = (int(x) for x in rng.integers(0, 2, 4))
        rows.append((0, a, b, c, d, a if rng.random() < 0.9 else b))
    spec = FeatureSpec(("a", "b", "c", "d"))
    df = spark.createDataFrame(rows, "sg int, a int, b int, c int, d int, y int")
    found = grow_shrink(prep.pack(prep.encode(df, spec), spec), spec, dict.fromkeys("abcd", 2), {0: 800}, 2)
    assert found[0] & 1 and not found[0] & 0b1000


def test_inputs_are_averaged_once(monkeypatch):
    """The codes are the same in every lattice and epoch: their means are made once, and no
    gradient goes back to them."""
    calls = {"mean": 0, "back": 0}
    for name, key in (("mean", "mean"), ("mean_back", "back")):
        def count(self, h, f=getattr(Band, name), key=key):
            calls[key] += 1
            return f(self, h)

        monkeypatch.setattr(Band, name, count)
    labels = {g: {m: float(m % 7) for m in Band(5, 1, 3).masks.tolist()} for g in range(3)}
    fit_predict(5, 3, 0, labels, GnnConfig(hidden=4, epochs=10, level_max=3, keep_best=False))
    assert calls == {"mean": 12, "back": 10}, calls  # the codes, a layer an epoch, the predictions


def _random_cells(seed: int, rows: int, n: int, groups: int, states: int, holes: float = 0.0):
    """(sg, c0, c1) of distinct cells whose subgroups lack features, and their donors."""
    rng = np.random.default_rng(seed)
    codes, sg = rng.integers(1, states + 1, (rows, n)), rng.integers(0, groups, rows)
    for g in range(groups):
        codes[np.ix_(sg == g, rng.random(n) < 0.3)] = 0
    codes[rng.random(codes.shape) < holes] = 0
    words = [sum(codes[:, j].astype(np.int64) << 4 * (j % 15) for j in range(w, min(n, w + 15))) + np.zeros(rows, np.int64) for w in (0, 15)]
    donors, at = np.unique(np.stack(words), axis=1, return_inverse=True)
    return np.unique(np.stack([sg, *words]), axis=1), donors, np.bincount(at.ravel())


@pytest.mark.parametrize("how", ["mismatch", "ignore"])
@pytest.mark.parametrize("seed", range(6))
def test_search_by_pattern_gives_the_nearest(monkeypatch, seed, how):
    """Same fills as comparing all cells, with and without comparing what is left over."""
    from gapselect.baselines import knn
    from gapselect.spec import widen

    n, k = (5, 9, 17)[seed % 3], 1 + seed
    (sg, c0, c1), (d0, d1), dn = _random_cells(seed, 900, n, 4, 2 + seed, 0.01 * (seed % 2))
    kinds, kind = np.unique(knn._lacking(d0, d1, n), return_inverse=True)
    patterns = {int(p): np.flatnonzero(kind == i) for i, p in enumerate(kinds)}
    limits = {0: widen(3), 2: widen((1 << n) - 2)} if seed > 2 else {}
    shared = (n, how, limits, widen((1 << n) - 1), k)
    want = knn._fill_by_scan(c0, c1, sg, d0, d1, dn, *shared)
    for choices in (knn.comb, lambda a, b: 0):
        monkeypatch.setattr(knn, "comb", choices)
        monkeypatch.setattr(knn, "PAIRS", 100)
        got = knn._fill_by_pattern(c0, c1, sg, d0, d1, dn, patterns, *shared)
        assert all((a == b).all() for a, b in zip(want, got))


def test_search_compares_few_pairs(monkeypatch):
    """Distinct cells in tens of thousands are not compared with one another."""
    from gapselect.baselines import knn
    from gapselect.spec import widen

    met, real = [0], knn.nearest

    def counted(c0, c1, d0, *rest):
        met[0] += len(c0) * len(d0)
        return real(c0, c1, d0, *rest)

    monkeypatch.setattr(knn, "nearest", counted)
    (sg, c0, c1), (d0, d1), dn = _random_cells(3, 30_000, 10, 3, 4)
    kinds, kind = np.unique(knn._lacking(d0, d1, 10), return_inverse=True)
    patterns = {int(p): np.flatnonzero(kind == i) for i, p in enumerate(kinds)}
    out = knn._fill_by_pattern(c0, c1, sg, d0, d1, dn, patterns, 10, "mismatch", {}, widen(1023), 5)
    assert not knn._lacking(*out, 10).any() and met[0] < len(c0) * len(d0) / 50
