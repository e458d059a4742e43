"""Worked examples, structural counts, invariants and brute-force checks of the engine."""

from collections import Counter
from math import log2

import numpy as np
import pytest
from pyspark.sql import functions as F

from gapselect.functions.numbers import clogc
from gapselect.operators import lattice as lat
from gapselect.operators import mi as info
from gapselect.operators import prep, sampling, topk
from gapselect.operators.missing import detect_missing, plant_missing
from gapselect.plans.sharing import block_count, covering_blocks, plan_sharing
from gapselect.spec import FeatureSpec, band, check_request, widen
from gapselect.views import GROUPS, SPECS, view

SPEC = FeatureSpec(("a", "b", "c", "d"))


@pytest.fixture(scope="module")
def small(spark):
    rng = np.random.default_rng(4)
    rows = []
    for i in range(600):
        a, b, c = (int(x) for x in rng.integers(0, 3, 3))
        rows.append((i % 3, a, b, None if i % 3 == 1 else c, None if rng.random() < 0.1 else int(rng.integers(0, 2)), (a + b) % 2 if rng.random() < 0.8 else int(rng.integers(0, 2))))
    return spark.createDataFrame(rows, "sg int, a int, b int, c int, d int, y int")


def brute_mi(rows, cols):
    n = len(rows)
    f, y, fy = Counter(tuple(r[c] for c in cols) for r in rows), Counter(r["y"] for r in rows), Counter((tuple(r[c] for c in cols), r["y"]) for r in rows)
    return sum(c / n * log2(c * n / (f[k[0]] * y[k[1]])) for k, c in fy.items())


def test_worked_table(spark):
    """Twelve patients, 6/2/1/3 of history and readmission: 0.168591 bits, 0.116858 nats."""
    from gapselect.queries.methods import FAMILY, READMITTED

    assert Counter(zip(FAMILY, READMITTED)) == {("Yes", "Yes"): 6, ("Yes", "No"): 2, ("No", "Yes"): 1, ("No", "No"): 3}
    df = spark.createDataFrame([(0, f, y) for f, y in zip(FAMILY, READMITTED)], "sg int, f string, y string")
    bits = info.joint_mi_direct(df, ["f"]).first()["mi"]
    assert bits == pytest.approx(0.168591, abs=1e-6) and bits * 0.6931471805599453 == pytest.approx(0.116858, abs=1e-6)
    spec = FeatureSpec(("f",))
    assert info.lattice_mi(prep.pack(prep.encode(df, spec), spec), spec, [1]).first()["mi"] == pytest.approx(bits, abs=1e-12)


def test_xor(spark):
    df = spark.createDataFrame([(0, a, b, a ^ b) for a in (0, 1) for b in (0, 1)], "sg int, a int, b int, y int")
    assert info.joint_mi_direct(df, ["a", "b"]).first()["mi"] == pytest.approx(1)
    assert info.co_information(df, ["a", "b"]).first()["co_information"] == pytest.approx(-1)
    assert info.co_information(df, ["a"]).first()["co_information"] == pytest.approx(info.joint_mi_direct(df, ["a"]).first()["mi"])


@pytest.mark.parametrize("sharing", ["none", "grouping_sets", "cuboid", "rollup", "blocks"])
def test_mi_by_every_sharing(small, sharing):
    packed = prep.pack(prep.encode(small, SPEC), SPEC)
    got = {(r["sg"], r["mask"]): r["mi"] for r in info.lattice_mi(packed, SPEC, band(4, 1, 4), sharing).collect()}
    rows = [r.asDict() for r in small.collect()]
    assert len(got) == 3 * 15
    for (sg, mask), value in got.items():
        assert value == pytest.approx(brute_mi([r for r in rows if r["sg"] == sg], SPEC.names_of(mask)), abs=1e-9)


def test_closure_and_bounds(small):
    packed = prep.pack(prep.encode(small, SPEC), SPEC)
    mi = info.lattice_mi(packed, SPEC, band(4, 1, 4))
    assert {r["accuracy"] for r in topk.closure_accuracy(mi, 4).collect()} == {1.0}
    broken = mi.withColumn("mi", -F.col("mi"))
    assert max(r["accuracy"] for r in topk.closure_accuracy(broken, 4, strict=True).collect()) < 0.5


def test_complete_case_can_break_closure(small):
    packed = prep.pack(prep.encode(small, SPEC), SPEC)
    rows = [r.asDict() for r in small.collect() if r["d"] is not None and r["sg"] == 0]
    got = info.lattice_mi(packed, SPEC, [SPEC.mask_of(["a", "d"])], null_policy="complete_case").filter("sg = 0").first()
    assert got["n"] == len(rows) and got["mi"] == pytest.approx(brute_mi(rows, ["a", "d"]), abs=1e-9)


def test_chain_rule_is_free_of_order(small):
    h = [info.chain_rule(small, list(o)).orderBy("sg").collect() for o in (("a", "b", "y"), ("y", "b", "a"), ("b", "a", "y"))]
    joint = info.entropy(small, ["a", "b", "y"]).orderBy("sg").collect()
    for other in h:
        assert [r["h"] for r in other] == pytest.approx([r["h"] for r in joint])


def test_missing(small):
    got = {r["sg"]: (r["miss_mask"], r["avail_mask"]) for r in detect_missing(small, SPEC).collect()}
    assert got == {0: (0, 15), 1: (4, 11), 2: (0, 15)}
    packed = prep.pack(prep.encode(small, SPEC), SPEC)
    hidden = prep.unpack(prep.hide(packed, {2: 0b1001}), SPEC)
    assert hidden.filter("sg = 2").agg(F.max("a"), F.max("d"), F.min("b")).first()[:] == (0, 0, 1)
    mi = info.lattice_mi(packed, SPEC, band(4, 2, 2))
    assert {r["mask"] for r in info.computable(mi, {1: 4}).filter("sg = 1").collect()} == {3, 9, 10}


@pytest.mark.parametrize("p", [0.2, 0.3, 0.4, 0.5])
def test_planting(p):
    for name, spec in SPECS.items():
        for seed in range(20):
            made = plant_missing(spec, GROUPS[name], p, seed)
            assert all(made.values())
            both = (1 << spec.n) - 1
            for m in made.values():
                both &= m
                assert spec.n - m.bit_count() >= 3
            assert both == 0
    with pytest.raises(ValueError):
        plant_missing(SPEC, 1, p, 0)


def test_lattice_counts(spark):
    assert lat.lattice_size(4) == {"nodes": 15, "inter": 28, "intra": 18, "cross": 0}
    assert lat.lattice_size(20, 4)["cross"] == 6 * 1048575
    four = lat.nodes(spark, 4)
    inter = {tuple(r) for r in lat.inter_edges(four, 4).collect()}
    intra = {tuple(r) for r in lat.intra_edges(four, 4).collect()}
    assert len(inter) == 28 and len(intra) == 18
    assert {b for a, b in intra if a == 3} | {a for a, b in intra if b == 3} == {5, 9, 6, 10}
    assert {low for up, low in inter if up == 7} == {3, 5, 6}
    assert {tuple(r) for r in lat.cross_edges(four.filter("mask IN (1, 5)"), 3).collect()} == {(m, i, j) for m in (1, 5) for i, j in ((0, 1), (0, 2), (1, 2))}
    big = lat.nodes(spark, 26, 1, 2)
    assert big.count() == 26 + 325
    names = lat.decode(F.lit(5), ("x", "y", "z"))
    assert spark.range(1).select(names.alias("n"), lat.encode_set(names, ("x", "y", "z")).alias("m"), lat.to_bits(F.lit(5).cast("long"), 4).alias("b")).first()[:] == (["x", "z"], 5, "0101")


def test_neighbour_mean(spark):
    values = {m: float((m * 37) % 101) for m in range(1, 64)}
    df = spark.createDataFrame(list(values.items()), "mask long, value double")
    got = {r["mask"]: r["mean"] for r in lat.neighbour_mean(df, 6).collect()}
    for m in values:
        near = [o for o in values if abs(o.bit_count() - m.bit_count()) == 1 and (o & m) in (o, m)]
        near += [o for o in values if o.bit_count() == m.bit_count() > 1 and (o & m).bit_count() == m.bit_count() - 1]
        assert got[m] == pytest.approx(np.mean([values[o] for o in near]))


def test_walk_law():
    """Sets of the computable cube are visited alike; missing bits never."""
    avail, seen = 0b1011011, Counter()
    for seed in range(300):
        for m, _ in sampling.walk(avail, 5, seed, 0, 1, 5, burn_in=40):
            assert m & ~avail == 0 and 1 <= m.bit_count()
            seen[m] += 1
    size = sampling.universe_size(avail, 1, 5)
    assert len(seen) == size
    mean = sum(seen.values()) / size
    assert sum((c - mean) ** 2 / mean for c in seen.values()) < 120  # 30 degrees of freedom, walks are correlated
    assert len(sampling.walk(avail, 10, 1, 0, 3, 3)) == 10
    assert all(m.bit_count() == 3 for m, _ in sampling.walk(avail, 10, 1, 0, 3, 3))
    with pytest.raises(RuntimeError):
        sampling.walk(avail, 31, 1, 0, 1, 5, max_steps=50)
    with pytest.raises(ValueError):
        sampling.budget_of(0, 10)


def test_full_budget_is_enumeration(spark):
    got = {(r["sg"], r["mask"]) for r in sampling.walk_sample(spark, {0: 0b1110, 1: 0b0111}, 1.0, 0, 1, 2).collect()}
    assert got == {(g, m) for g, a in ((0, 0b1110), (1, 0b0111)) for m in band(4, 1, 2, a)}
    assert got == {tuple(r) for r in sampling.universe(spark, {0: 0b1110, 1: 0b0111}, 4, 1, 2).collect()}


def test_measures(spark):
    true = spark.createDataFrame([(0, r, m) for r, m in ((1, 7), (2, 11), (3, 13))], "sg int, rank int, mask long")
    assert topk.ndcg_at_k(true, true, 3).first()["value"] == pytest.approx(1) and topk.precision_at_k(true, true, 3).first()["value"] == 1
    pred = spark.createDataFrame([(0, 1, 14), (0, 2, 7), (0, 3, 19)], "sg int, rank int, mask long")
    assert topk.precision_at_k(pred, true, 3).first()["value"] == pytest.approx(1 / 3)
    assert topk.ndcg_at_k(pred, true, 3).first()["value"] == pytest.approx((1 / log2(3)) / sum(1 / log2(i + 1) for i in (1, 2, 3)))
    none = spark.createDataFrame([(0, 1, 99)], "sg int, rank int, mask long")
    assert topk.precision_at_k(none, true, 3).first()["value"] == 0 == topk.ndcg_at_k(none, true, 3).first()["value"]
    pop = spark.createDataFrame([(0, m, m / 10) for m in range(1, 11)], "sg int, mask long, mi double")
    assert topk.tv_l1(pop, pop).first()["tv"] == 0
    assert topk.tv_l1(pop.filter("mask = 1"), pop).first()["tv"] == pytest.approx(1.8)
    assert topk.tv_l1(pop.filter("mask = 1"), pop, half=True).first()["tv"] == pytest.approx(0.9)


def test_topk_ties(spark):
    df = spark.createDataFrame([(0, m, 0.5) for m in (12, 3, 10, 5)] + [(0, 7, 0.9)], "sg int, mask long, mi double")
    assert [r["mask"] for r in topk.topk(df, 2, 3).orderBy("rank").collect()] == [3, 5, 10]


def test_request_errors():
    with pytest.raises(ValueError):
        FeatureSpec(("a", "sg"))
    with pytest.raises(ValueError):
        FeatureSpec(("a", "y"))
    with pytest.raises(ValueError):
        FeatureSpec(tuple(f"f{i}" for i in range(31)))
    for m, k in ((0, 1), (5, 1), (2, 0)):
        with pytest.raises(ValueError):
            check_request(SPEC, m, k)
    with pytest.raises(ValueError):
        band(4, 3, 2)


def test_too_many_states(spark):
    df = spark.range(40).select((F.col("id") % 2).cast("int").alias("sg"), F.col("id").alias("a"), (F.col("id") % 2).alias("y"))
    with pytest.raises(ValueError, match="40 states"):
        prep.encode(df, FeatureSpec(("a",)))


def test_packing_of_thirty_features(spark):
    spec = FeatureSpec(tuple(f"f{i}" for i in range(30)))
    row = {f"f{i}": i % 9 for i in range(30)} | {"sg": 0, "y": 1}
    df = spark.createDataFrame([tuple(row.values()), tuple((row | {f"f{i}": None for i in range(0, 30, 2)}).values())], ", ".join(f"{k} int" for k in row))
    words = {f: list(range(9)) for f in spec.features} | {"y": [1]}
    out = prep.unpack(prep.pack(prep.encode(df, spec, words), spec), spec).collect()
    assert [out[0][f"f{i}"] for i in range(30)] == [i % 9 + 1 for i in range(30)]
    assert [out[1][f"f{i}"] for i in range(30)] == [0 if i % 2 == 0 else i % 9 + 1 for i in range(30)]
    assert widen(1 | 1 << 15) == (0xF, 0xF)


def test_bins(spark):
    df = spark.createDataFrame([(float(x),) for x in range(100)] + [(None,)], "x double")
    assert Counter(r[0] for r in df.select(prep.bin_edges(F.col("x"), [10, 50])).collect()) == {0: 11, 1: 40, 2: 49, None: 1}
    exact = prep.bin_depth(df.filter("x IS NOT NULL"), "x", 7, exact=True).groupBy("x_bin").count().collect()
    assert sorted(r["count"] for r in exact) == [14] * 5 + [15] * 2
    near = prep.bin_depth(df, "x", 4).groupBy("x_bin").count().collect()
    assert all(24 <= r["count"] <= 26 for r in near if r["x_bin"] is not None)
    assert prep.bin_width(spark.createDataFrame([(1.0,), (1.0,)], "x double"), "x", 3).select("x_bin").distinct().first()[0] == 0


def test_covering_blocks():
    masks = band(9, 1, 3)
    blocks = covering_blocks(9, masks, 5)
    assert sorted(m for _, own in blocks for m in own) == masks
    assert all(m & ~b == 0 and b.bit_count() <= 5 for b, own in blocks for m in own)
    assert block_count(15, 3, 6) < 100


def test_plan_choice(small):
    packed = prep.pack(prep.encode(small, SPEC), SPEC)
    assert plan_sharing(packed, band(4, 1, 4), 4)["sharing"] == "rollup"
    assert plan_sharing(packed, band(4, 1, 2), 4)["sharing"] in ("cuboid", "blocks")


def test_physical_plan(spark, sf):
    """No Python before the counts, one exchange on rows, sets never join rows."""
    spec = SPECS["v_logic15"].head(6)
    words = {f: [0, 1, 2, 3] for f in (*spec.features, "y")}
    packed = prep.pack(prep.encode(view(spark, sf, "v_logic15"), spec, words), spec)
    plan = info.lattice_mi(packed, spec, band(6, 1, 3), "cuboid")
    counts, _ = info.lattice_counts(packed, spec, band(6, 1, 3), "cuboid", q=4)
    text = counts._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in text and "Pandas" not in text and "Join" not in text
    assert text.count("Exchange hashpartitioning") == 2
    scan = view(spark, sf, "v_device").select("sg", "tax_max")._jdf.queryExecution().executedPlan().toString()
    assert "l_comment" not in scan and "ReadSchema" in scan
    assert plan.count() == 4 * 41


def test_bound_pruning(small):
    packed = prep.pack(prep.encode(small, SPEC), SPEC)
    three = info.lattice_mi(packed, SPEC, band(4, 3, 3))
    upper = None
    for m in band(4, 2, 2):
        b = three.filter(F.col("mask").bitwiseAND(F.lit(m)) == m).groupBy("sg").agg(F.min("mi").alias("bound")).withColumn("mask", F.lit(m).cast("long"))
        upper = b if upper is None else upper.unionByName(b)
    pairs = info.lattice_mi(packed, SPEC, band(4, 2, 2))
    got = topk.bounded_topk(upper, lambda w: pairs.join(w, ["sg", "mask"], "left_semi"), 2, 2)
    assert sorted(map(tuple, got.select("sg", "rank", "mask").collect())) == sorted(map(tuple, topk.topk(pairs, 2, 2).select("sg", "rank", "mask").collect()))


def test_singles_mislead(spark, sf):
    """The winner of the logic view holds two features that carry nothing alone."""
    spec = SPECS["v_logic15"]
    packed = prep.pack(prep.encode(view(spark, sf.replace("0.001", "0.01"), "v_logic15"), spec), spec)
    best = topk.topk(info.lattice_mi(packed, spec, band(15, 3, 3), "blocks"), 3, 1).collect()
    assert {tuple(spec.names_of(r["mask"])) for r in best} == {("x2", "x3", "r0")}
    single = topk.topk(info.lattice_mi(packed, spec, band(15, 1, 1)), 1, 15).filter(F.col("mask").isin(spec.mask_of(["x2"]), spec.mask_of(["x3"]))).collect()
    assert all(r["score"] < 0.01 for r in single)


def test_clogc(spark):
    assert spark.range(1).select(clogc(F.lit(0)), clogc(F.lit(8)), clogc(F.lit(1))).first()[:] == (0.0, 24.0, 0.0)


def test_near_pairs_are_made_once_and_not_exchanged(spark):
    from gapselect.operators.joins import near_pairs

    rows = [(k, k % 2, k % 3 // 2, k % 5 // 3, k // 7 % 2) for k in range(60)]
    left = spark.createDataFrame(rows, "id long, p int, q int, r int, s int")
    out = near_pairs(left, left, [["p", "q"], ["r", "s"]], "id", 1)
    want = sorted((x[0], y[0]) for x in rows for y in rows if sum(u != v for u, v in zip(x[1:], y[1:])) <= 1)
    assert sorted(map(tuple, out.collect())) == want
    assert "Aggregate" not in out._jdf.queryExecution().executedPlan().toString()


def test_blocks_sum_sets_where_their_cells_are(small, monkeypatch):
    """Values of blocks are those of the cuboid, with sets of each subgroup as well, and no
    cell of a set is a row."""
    spec = FeatureSpec(("a", "b", "c", "d"))
    packed = prep.pack(prep.encode(small, spec), spec)
    masks = band(spec.n, 1, 3)
    only = {0: masks[::2], 1: masks[1::3]}
    monkeypatch.setattr(info, "counts_blocks", None)
    for some in (None, only):
        want, got = ({(r["sg"], r["mask"]): r for r in info.lattice_mi(packed, spec, masks, how, "miller_madow", only=some).collect()} for how in ("cuboid", "blocks"))
        assert want.keys() == got.keys() and want
        assert all(got[k]["n"] == want[k]["n"] and abs(got[k]["mi"] - want[k]["mi"]) < 1e-9 for k in want)


@pytest.mark.parametrize("only", [None, {0: [1, 3, 7, 44], 1: [2, 6, 28]}])
def test_small_sets_are_counted_inside_tasks(spark, sf, only):
    """Same constructs as from block cells, of rows and of weighted cells, and no row for each set or block."""
    from gapselect.baselines.knn import cells_of
    from gapselect.queries.base import prepared

    packed, spec = prepared(spark, sf, "v_device", 6)
    masks = band(6, 1, 3) if only is None else sorted({m for own in only.values() for m in own})
    want = sorted(map(tuple, info.lattice_mi(packed, spec, masks, "blocks", only=only).collect()))
    for rows in (packed, cells_of(packed)):
        got = info.lattice_mi(rows, spec, masks, only=only)
        assert "Generate" not in got._jdf.queryExecution().executedPlan().toString()
        assert [r[:3] + r[4:] for r in want] == [r[:3] + r[4:] for r in sorted(map(tuple, got.collect()))]
        assert [r[3] for r in sorted(map(tuple, got.collect()))] == pytest.approx([r[3] for r in want], abs=1e-12)
