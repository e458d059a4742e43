"""Ways of sharing counts: equal results, and plans that do not grow with the number of sets."""

import re

import numpy as np
import pytest
from pyspark.sql import functions as F

from gapselect import experiments as ex
from gapselect.operators import mi as info
from gapselect.operators import prep
from gapselect.plans.durable import durable
from gapselect.spec import FeatureSpec, band

WAYS = ("none", "grouping_sets", "cuboid", "blocks", "rollup")
#: Seventeen features: sets reach into the second word.
SPEC = FeatureSpec(tuple("abcdefghijklmnopq"))
MASKS = [1, 3, 1 << 16, 1 << 16 | 5, 1 << 14 | 1 << 15, 0b1111, (1 << 17) - 1]


@pytest.fixture(scope="module")
def packed(spark):
    """2,000 rows with nulls in features and target, in three subgroups of which one is null."""
    rng = np.random.default_rng(7)
    rows = [((0, 3, None)[int(g)], *(int(v) or None for v in x), int(y) or None) for g, y, *x in rng.integers(0, 4, (2000, 19)) if g < 3]
    df = spark.createDataFrame(rows, f"sg int, {', '.join(f'{f} int' for f in SPEC.features)}, y int")
    return durable(prep.pack(prep.encode(df, SPEC), SPEC))


def counted(packed, way, masks=MASKS, q=3):
    return sorted((tuple(r) for r in info.lattice_counts(packed, SPEC, masks, way, q=q)[0].select("sg", "mask", "k0", "k1", "n1", "n2", "n3").collect()), key=lambda r: (r[0] is None, r[0] or 0, *r[1:]))


@pytest.mark.parametrize("way", ["none", "grouping_sets"])
@pytest.mark.parametrize("chunk", [1 << 18, 100])
def test_counts_are_those_of_the_cuboid(packed, monkeypatch, way, chunk):
    monkeypatch.setattr(info, "COUNTED", chunk)
    got = counted(packed, way)
    assert got == counted(packed, "cuboid") and {r[1] for r in got} == set(MASKS) and any(r[4:] == (0, 0, 0) for r in got)


def test_weighted_cells(packed):
    heavy = packed.withColumn("n", (F.col("c0") % 5).cast("long"))
    want = counted(heavy, "cuboid")
    assert counted(heavy, "none") == want and counted(heavy, "grouping_sets") == want


def test_no_rows(packed):
    assert counted(packed.filter("y > 9"), "none") == []


def executed(df):
    return df._jdf.queryExecution().executedPlan().toString()


def test_unshared_plan_does_not_grow_with_the_sets(packed):
    plan = executed(info.counts_unshared(packed, band(10, 1, 3), 3))
    assert len(re.findall(r"Exchange hashpartitioning", plan)) == 1 and "Union" not in plan


def test_equal_rows_are_combined_before_they_are_expanded(packed):
    plan = executed(info.counts_grouping_sets(packed, band(10, 1, 1), 3, SPEC))
    assert "HashAggregate" in plan[plan.index("Expand") :]


def test_rows_are_made_once_for_all_sizes(spark, sf, monkeypatch):
    made, totals = [], {}
    view, lattice_mi = ex.view, info.lattice_mi

    def seen(packed, spec, masks, way, **more):
        out = lattice_mi(packed, spec, masks, way, **more)
        totals.setdefault((spec.n, packed.select("sg").distinct().count()), []).append({(r["sg"], r["mask"]): r["mi"] for r in out.collect()})
        return out

    monkeypatch.setattr(ex, "view", lambda spark, sf, name, g: made.append(g) or view(spark, sf, name, g))
    monkeypatch.setattr(info, "lattice_mi", seen)
    rows = ex.sharing_times(spark, sf, (3, 4), (2, 4)).collect()
    assert made == [2, 4] and [(r["n"], r["groups"], r["sharing"], r["constructs"]) for r in rows] == [(n, g, w, g * k) for n, k in ((3, 7), (4, 14)) for g in (2, 4) for w in WAYS]
    for (n, g), found in totals.items():
        spec = ex.SPECS["v_scale"].head(n)
        alone = prep.pack(prep.encode(view(spark, sf, "v_scale", g), spec), spec)
        want = {(r["sg"], r["mask"]): r["mi"] for r in lattice_mi(alone, spec, band(n, 1, 3), "cuboid").collect()}
        assert len(found) == len(WAYS) and all(x == pytest.approx(want, abs=1e-9) for x in found)


def test_timed_stages_make_the_values(spark, sf, monkeypatch):
    """A count alone would drop the entropies from the plan; a value that fails has to be met."""
    lattice_mi = info.lattice_mi
    monkeypatch.setattr(info, "lattice_mi", lambda *a, **b: lattice_mi(*a, **b).withColumn("mi", F.expr("CAST(raise_error('made') AS DOUBLE)")))
    with pytest.raises(Exception, match="made"):
        ex.sharing_times(spark, sf, (3,), (2,), ways=("cuboid",))
