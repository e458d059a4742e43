"""Queries and operators do the whole job: no row, donor, member or set is left out."""

import numpy as np
import pytest

from gapselect.baselines import knn, markov
from gapselect.operators import prep, sampling
from gapselect.plans.durable import durable
from gapselect.queries import QUERIES, learned
from gapselect.spec import FeatureSpec


def test_theta_join_takes_every_part(spark, sf, tmp_path):
    """Parts with high keys are compared as well, against a nested loop."""
    for t, key in (("part", "p_partkey"), ("lineitem", "l_partkey")):
        df = spark.read.parquet(f"{sf}/{t}.parquet")
        df.withColumn(key, df[key] + 350).write.parquet(f"{tmp_path}/{t}.parquet")
    got = sorted((r["a"], r["b"]) for r in QUERIES["join_theta_dist"](spark, str(tmp_path)).collect())
    rows = [
        (r["p_partkey"], r["p_size"] % 2, (r["p_type"], (r["p_size"] - 1) // 10, r["p_partkey"] % 1000 // 200, int(r["p_brand"][6:]) % 9))
        for r in spark.read.parquet(f"{tmp_path}/part.parquet").collect()
    ]
    want = sorted((i, j) for i, g, x in rows if g == 0 for j, h, y in rows if h == 1 and sum(a != b for a, b in zip(x, y)) <= 1)
    assert max(i for i, _, _ in rows) > 400 and got == want


@pytest.fixture(scope="module")
def wide(spark):
    """1,300 donors in one bucket of the constant feature ``d``; 60 receivers lack ``e``."""
    spec = FeatureSpec(("a", "b", "c", "d", "e"))
    rng = np.random.default_rng(5)
    rows = [(0, a, b, c, 1, int(rng.integers(1, 8)), 0) for a in range(9) for b in range(9) for c in range(9) for _ in range(2)]
    rows += [(1, *(int(x) for x in rng.integers(0, 9, 3)), 1, None, 0) for _ in range(60)]
    df = spark.createDataFrame(rows, "sg int, a int, b int, c int, d int, e int, y int")
    return durable(prep.pack(prep.encode(df, spec), spec)), spec


def filled(df):
    return sorted(tuple(r) for r in df.select("sg", "c0", "c1", "y", "n").collect())


@pytest.mark.parametrize("block", [4096, 200])
def test_hashed_neighbours_see_the_whole_bucket(wide, monkeypatch, block):
    packed, spec = wide
    seed = next(s for s in range(99) if np.random.default_rng(s).choice(5, 1, replace=False)[0] == 3)
    monkeypatch.setattr(knn, "BLOCK", block, raising=False)
    got = filled(knn.knn_impute(packed, spec, 5, method="bit_sampling", bands=1, band_size=1, seed=seed))
    assert got == filled(knn.knn_impute(packed, spec, 5)) and all(c0 >> 16 & 0xF for _, c0, *_ in got)


def test_blankets_grow_past_six_members(spark):
    rng = np.random.default_rng(6)
    spec = FeatureSpec(tuple("abcdefgh"))
    rows = [(0, *map(int, x), int(x.sum())) for x in rng.integers(0, 2, (4000, 8))]
    packed = prep.pack(prep.encode(spark.createDataFrame(rows, f"sg int, {', '.join(f'{f} int' for f in spec.features)}, y int"), spec), spec)
    assert markov.grow_shrink(packed, spec, dict.fromkeys(spec.features, 2), {0: 4000}, 9) == {0: 255}


def test_blankets_lose_every_needless_member(monkeypatch):
    """Two noisy copies of the target join first; the two features that make it replace both."""
    spec = FeatureSpec(tuple("abxz"))
    bits = [0.0, 0.6, 0.5, 0.8, 0.4, 0.7, 0.7, 0.9, 0.4, 0.7, 0.7, 0.85, 1.0, 1.0, 1.0, 1.0]
    monkeypatch.setattr(markov, "_mi", lambda cells, spec, masks: {(0, m): bits[m] for m in masks if m})
    assert markov.grow_shrink(None, spec, dict.fromkeys("abxz", 2), {0: 1000}, 2) == {0: 0b1100}


def test_robustness_is_of_the_model(monkeypatch):
    seen = {}
    monkeypatch.setattr(learned.ex, "robustness", lambda spark, sf, views, *a, **b: seen.update(views=views, a=a, b=b))
    QUERIES["exp_robustness"](None, "")
    assert seen["views"] == ("v_staff", "v_device", "v_credit") and not seen["a"] and set(seen["b"]) == {"cfg"}


@pytest.mark.parametrize("name, call, views", [("exp_effectiveness", "effectiveness", 5), ("exp_sampling", "sampling_distance", 3), ("exp_closure", "closure", 3)])
def test_experiments_take_whole_views(monkeypatch, name, call, views):
    seen = {}
    monkeypatch.setattr(learned.ex, call, lambda spark, sf, views, *a, **b: seen.update(views=views, a=a, b=b))
    QUERIES[name](None, "")
    assert len(seen["views"]) == views and not seen["a"] and set(seen["b"]) <= {"cfg", "seeds"} and len(seen["b"].get("seeds", "all")) == 3


@pytest.mark.parametrize("axis, values", [("features", 3), ("groups", 3), ("missing", 4), ("budget", 5)])
def test_times_take_the_whole_axis(monkeypatch, axis, values):
    seen = {}
    monkeypatch.setattr(learned.ex, "times", lambda spark, sf, vary, values, **b: seen.update(values=values, b=b))
    QUERIES[f"exp_time_{axis}"](None, "")
    assert len(seen["values"]) == values and set(seen["b"]) == {"cfg"}


def test_sharing_takes_every_way(monkeypatch):
    seen = {}
    monkeypatch.setattr(learned.ex, "sharing_times", lambda spark, sf, sizes, groups, **b: seen.update(sizes=sizes, groups=groups, b=b))
    QUERIES["exp_sharing"](None, "")
    assert max(seen["sizes"]) == 10 and len(seen["groups"]) == 2 and not seen["b"]


@pytest.mark.parametrize("name", ["mb_blanket_logic15", "mb_topk_logic15", "gnn_joint", "gnn_observed", "gnn_ablation_edges", "gnn_distributed"])
def test_methods_take_every_feature(monkeypatch, name):
    class Seen(Exception):
        pass

    def problem(spark, sf, view, p=0.2, seed=0, m=3, n=None, **rest):
        raise Seen(n)

    monkeypatch.setattr(learned.ex, "problem", problem)
    with pytest.raises(Seen) as said:
        QUERIES[name](None, "")
    assert said.value.args == (None,)


def test_unsettled_blankets_are_flagged(wide, monkeypatch):
    packed, spec = wide
    found = iter([{0: 1, 1: 1}, {0: 3, 1: 1}, {0: 3, 1: 1}])
    monkeypatch.setattr(markov, "grow_shrink", lambda *a: next(found))
    assert not markov.markov_blanket(packed, spec, max_iter=1)[2]["settled"]
    assert markov.markov_blanket(packed, spec, max_iter=2)[2]["settled"]


@pytest.mark.parametrize("columns", [None, {0: 31, 1: 0b00111}])
def test_neighbours_beyond_the_shipped_size(wide, monkeypatch, columns):
    packed, spec = wide
    want = filled(knn.knn_impute(packed, spec, 5, columns=columns))
    monkeypatch.setattr(knn, "MOST_DONORS", 10)
    monkeypatch.setattr(knn, "BLOCK", 400)
    assert filled(knn.knn_impute(packed, spec, 5, columns=columns)) == want


def test_walkers_fill_the_budget(spark):
    available = {0: 0x7FFF, 1: 0x0FFF}
    got = sampling.walk_sample(spark, available, 0.25, 0, 1, 3, walkers=4, burn_in=50).collect()
    for sg, a in available.items():
        mine = [r["mask"] for r in got if r["sg"] == sg]
        assert len(mine) == len(set(mine)) == sampling.budget_of(0.25, sampling.universe_size(a, 1, 3))


def test_sampling_reads_its_view_once(spark, sf, monkeypatch):
    seen, made = [], learned.ex.view
    monkeypatch.setattr(learned.ex, "view", lambda *a: seen.append(a[2]) or made(*a))
    got = learned.ex.sampling_distance(spark, sf, ("v_device",), budgets=(0.5,), seeds=(0,), n=5, high=2)
    assert seen == ["v_device"] and got.count() == 4


def test_rates_and_seeds_share_the_complete_view(spark, sf, monkeypatch):
    from gapselect import experiments as ex
    from gapselect.queries.learned import QUICK

    seen, made = [], ex.view
    monkeypatch.setattr(ex, "view", lambda *a: seen.append(a[2]) or made(*a))
    assert ex.effectiveness(spark, sf, ("v_device",), ("knn", "ridge"), seeds=(0, 1), cfg=QUICK, n=6).count() == 8
    assert ex.robustness(spark, sf, ("v_device",), (0.2, 0.4), ("ridge",), cfg=QUICK, n=6).count() == 4
    assert seen == ["v_device", "v_device"]


def test_blanket_steps_count_the_sets_of_each_subgroup(spark, wide, monkeypatch):
    """A set of one subgroup's blanket is not counted in the others, and no row is made for it."""
    packed, spec = wide
    asked, real = [], markov.lattice_mi
    monkeypatch.setattr(markov, "lattice_mi", lambda *a, **b: asked.append(b["only"]) or real(*a, **b))
    got = markov._mi(packed, spec, markov._asked({0: {1, 3}, 1: {4}}))
    assert set(got) == {(0, 1), (0, 3), (1, 4)} and asked == [{0: [1, 3], 1: [4]}]
