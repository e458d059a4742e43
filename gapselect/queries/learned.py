"""Baselines, the model, and the experiments, at widths and epochs that a test run allows."""

from __future__ import annotations

from dataclasses import replace

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gapselect import experiments as ex
from gapselect.baselines.knn import cells_of, knn_impute, mode_impute
from gapselect.baselines.markov import grow_shrink, markov_blanket, markov_topk
from gapselect.model.fit import fit_all, mlp_all, ridge_all
from gapselect.model.gnn import SMALL, GnnConfig, MultiplexModel
from gapselect.model.multiplex import Band
from gapselect.operators import mi as info
from gapselect.operators import prep, topk
from gapselect.plans.durable import durable
from gapselect.queries.base import duck_hidden, duck_mi, duck_topk, level, masked, prepared, query, r6, shown_topk
from gapselect.queries.methods import PLANTED
from gapselect.sources.tables import table
from gapselect.views import DEVICE, GROUPS, SPECS, duck_view

QUICK = GnnConfig(hidden=16, epochs=60, rate=1e-2, level_max=3)
_K = 5


def _coded_sql(n: int = 15) -> str:
    """The masked device view as codes 0..9 in SQL, and its weighted cells."""
    feats = DEVICE[:n]
    codes = ", ".join(f"CASE WHEN {f} IS NULL THEN 0 ELSE CAST(r_{f} AS INTEGER) END AS {f}" for f in feats)
    ranks = ", ".join(f"dense_rank() OVER (ORDER BY {f} NULLS LAST) AS r_{f}" for f in feats)
    gone = []
    for j, f in enumerate(feats):
        g = [str(k) for k, m in PLANTED["v_device"].items() if m >> j & 1]
        gone.append(f"CASE WHEN sg IN ({', '.join(g)}) THEN 0 ELSE {f} END AS {f}" if g else f)
    return f"""v AS ({duck_view("v_device")}), r AS (SELECT *, {ranks} FROM v), k AS (SELECT sg, y, {codes} FROM r), h AS (SELECT sg, y, {", ".join(gone)} FROM k),
        c AS (SELECT sg, {", ".join(feats)}, y + 1 AS y, count(*) AS n FROM h GROUP BY ALL)"""


def _knn_sql() -> str:
    feats = DEVICE
    gap = " + ".join(f"(a.{f} <> b.{f})::INT" for f in feats)
    key0 = " + ".join(f"(CAST({f} AS BIGINT) << {4 * j})" for j, f in enumerate(feats))
    return f"""WITH {_coded_sql()}, d AS (SELECT {", ".join(feats)}, CAST(sum(n) AS BIGINT) AS n, {key0} AS key FROM c GROUP BY {", ".join(feats)}),
        a AS (SELECT DISTINCT sg, {", ".join(feats)}, {key0} AS key FROM c),
        p AS (SELECT a.sg, a.key AS rkey, b.key AS dkey, {gap} AS gap, b.n, {", ".join(f"a.{f} AS a_{f}, b.{f} AS b_{f}" for f in feats)} FROM a, d b),
        u AS ({" UNION ALL ".join(f"SELECT sg, rkey, dkey, gap, n, '{f}' AS f, b_{f} AS code FROM p WHERE a_{f} = 0 AND b_{f} > 0" for f in feats)}),
        w AS (SELECT *, sum(n) OVER (PARTITION BY sg, rkey, f ORDER BY gap, dkey ROWS UNBOUNDED PRECEDING) - n AS before FROM u QUALIFY row_number() OVER (PARTITION BY sg, rkey, f ORDER BY gap, dkey) <= {_K}),
        t AS (SELECT sg, rkey, f, code, sum(greatest(0, least(n, {_K} - before))) AS votes FROM w GROUP BY ALL),
        z AS (SELECT sg, rkey, f, code FROM t QUALIFY row_number() OVER (PARTITION BY sg, rkey, f ORDER BY votes DESC, code) = 1)
        SELECT sg, f AS feature, CAST(code AS INTEGER) AS code, count(*) AS cells, CAST(sum(rkey % 1000003) AS BIGINT) AS key_sum FROM z GROUP BY ALL"""


@query(_knn_sql())
def knn_impute_device(spark, sf) -> DataFrame:
    """Imputed codes of every cell with a missing feature, counted per value."""
    packed, spec = prepared(spark, sf, "v_device")
    hidden = masked(packed, PLANTED["v_device"])
    before = cells_of(hidden).select("sg", "c0", "c1").distinct()
    filled = knn_impute(hidden, spec, _K).select("sg", "c0", "c1").distinct()
    gone = F.lit(0).cast("long")
    from gapselect.spec import widen

    for g, m in PLANTED["v_device"].items():
        gone = F.when(F.col("sg") == g, F.lit(widen(m)[0])).otherwise(gone)
    whole = filled.withColumn("key", F.col("c0").bitwiseAND(F.bitwise_not(gone)))
    whole = whole.join(before.select("sg", F.col("c0").alias("key")), ["sg", "key"], "left_semi")
    rows = prep.unpack(whole.withColumn("y", F.lit(0)), spec).select("sg", "key", *spec.features)
    longer = rows.unpivot(["sg", "key"], list(spec.features), "feature", "code")
    missing = F.lit(False)
    for g, m in PLANTED["v_device"].items():
        missing = missing | ((F.col("sg") == g) & F.col("feature").isin(spec.names_of(m)))
    return longer.filter(missing & (F.col("code") > 0)).groupBy("sg", "feature", "code").agg(F.count(F.lit(1)).alias("cells"), F.sum(F.col("key") % 1000003).alias("key_sum"))


@query()
def knn_sampled_device(spark, sf):
    """The hashed variant: share of cells that get the exact variant's values."""
    packed, spec = prepared(spark, sf, "v_device")
    hidden = masked(packed, PLANTED["v_device"])
    near = knn_impute(hidden, spec, _K, method="bit_sampling", bands=12, band_size=3)
    return near.groupBy("sg").agg(F.count(F.lit(1)).alias("cells"), F.sum("n").alias("n_rows"))


@query()
def knn_topk_device(spark, sf):
    pb = ex.problem(spark, sf, "v_device")
    return shown_topk(ex.ranking(pb, "knn", 10))


_MODE = ", ".join(f"CASE WHEN {f} = 0 THEN (SELECT code FROM m WHERE m.f = '{f}') ELSE {f} END AS {f}" for f in DEVICE)


@query(f"""WITH {_coded_sql()}, l AS ({" UNION ALL ".join(f"SELECT '{f}' AS f, {f} AS code, n FROM c WHERE {f} > 0" for f in DEVICE)}),
          m AS (SELECT f, code FROM (SELECT f, code, sum(n) AS n FROM l GROUP BY f, code) QUALIFY row_number() OVER (PARTITION BY f ORDER BY n DESC, code) = 1),
          i AS (SELECT sg, y, n, {_MODE} FROM c) SELECT sg, brand_bin, key_fifth, last_quarter, CAST(sum(n) AS BIGINT) AS n_rows FROM i GROUP BY sg, brand_bin, key_fifth, last_quarter""")
def mode_impute_device(spark, sf):
    packed, spec = prepared(spark, sf, "v_device")
    cells = mode_impute(masked(packed, PLANTED["v_device"]), spec)
    return prep.unpack(cells, spec).groupBy("sg", "brand_bin", "key_fifth", "last_quarter").agg(F.sum("n").alias("n_rows"))


@query()
def mb_blanket_logic15(spark, sf):
    pb = ex.problem(spark, sf, "v_logic15", truth=False)
    spec = pb.spec
    blanket, _, said = markov_blanket(pb.masked, spec)
    return spark.createDataFrame([(g, b, spec.names_of(b), said["rounds"], said["settled"]) for g, b in sorted(blanket.items())], "sg int, mask long, features array<string>, rounds int, settled boolean")


@query()
def mb_grow_device(spark, sf):
    """Blankets on the complete device view."""
    packed, spec = prepared(spark, sf, "v_device")
    sizes = {r["sg"]: r["count"] for r in packed.groupBy("sg").count().collect()}
    top = prep.unpack(packed, spec).agg(*[F.max(f).alias(f) for f in spec.features]).first()
    q = info.states(packed)
    found = grow_shrink(durable(info.base_cuboid(packed, q)), spec, {f: top[f] for f in spec.features}, sizes, q)
    return spark.createDataFrame([(g, b, spec.names_of(b)) for g, b in sorted(found.items())], "sg int, mask long, features array<string>")


@query()
def mb_topk_logic15(spark, sf):
    pb = ex.problem(spark, sf, "v_logic15", truth=False)
    return shown_topk(markov_topk(pb.masked, pb.spec, 3, 10))


@query()
def mb_topk_device(spark, sf):
    pb = ex.problem(spark, sf, "v_device", truth=False)
    return shown_topk(markov_topk(pb.masked, pb.spec, 3, 10))


def _device_labels(spark, sf):
    pb = ex.problem(spark, sf, "v_device")
    return pb, ex.labels(pb)


@query()
def mlp_topk_device(spark, sf):
    pb, known = _device_labels(spark, sf)
    return shown_topk(ex.ranking(pb, "mlp", 10, cfg=SMALL, known=known))


@query()
def mlp_topk_credit(spark, sf):
    pb = ex.problem(spark, sf, "v_credit")
    return shown_topk(ex.ranking(pb, "mlp", 10, cfg=SMALL))


@query()
def ridge_pred_logic15(spark, sf):
    pb = ex.problem(spark, sf, "v_logic15")
    return ridge_all(ex.labels(pb), 15, 3, 3).select("sg", "mask", F.round("mi", 5).alias("mi"))


@query(f"""WITH {duck_mi(duck_view("v_device"), DEVICE[:2], [1, 2, 3])}, x AS (SELECT sg, CAST(mask & 1 AS DOUBLE) AS a, CAST(mask >> 1 & 1 AS DOUBLE) AS b, mi FROM m),
          f AS (SELECT sg, max(CASE WHEN a = 1 AND b = 0 THEN mi END) AS ma, max(CASE WHEN a = 0 AND b = 1 THEN mi END) AS mb, max(CASE WHEN a = 1 AND b = 1 THEN mi END) AS mab FROM x GROUP BY sg)
          SELECT sg, mask, round(CASE mask WHEN 1 THEN ma WHEN 2 THEN mb ELSE mab END, 4) + 0.0 AS mi FROM f, (VALUES (CAST(1 AS BIGINT)), (CAST(2 AS BIGINT)), (CAST(3 AS BIGINT))) t(mask)""")
def ridge_two_features(spark, sf):
    """Three sets and three weights: the normal equations reproduce the labels."""
    packed, spec = prepared(spark, sf, "v_device", 2)
    out = ridge_all(info.lattice_mi(packed, spec, [1, 2, 3]), 2, 1, 2, penalty=0.0)
    return out.select("sg", "mask", (F.round("mi", 4) + 0.0).alias("mi"))


@query()
def arbitrary_topk(spark, sf):
    return shown_topk(ex.ranking(ex.problem(spark, sf, "v_device"), "arbitrary", 10))


# ---- the model


@query()
def gnn_train_device(spark, sf):
    """Loss along training of each subgroup's model, every tenth epoch."""
    from gapselect.model.gnn import fit_predict

    pb, known = _device_labels(spark, sf)
    by: dict[int, dict[int, float]] = {}
    for r in known.collect():
        by.setdefault(r["sg"], {})[r["mask"]] = r["mi"]
    rows = []
    for g in range(pb.groups):
        trace: list[float] = []
        fit_predict(15, pb.groups, g, by, replace(QUICK, epochs=40), trace)
        rows += [(g, e, float(v)) for e, v in enumerate(trace) if e % 10 == 0]
    return spark.createDataFrame(rows, "sg int, epoch int, loss double")


def _gnn_topk(name: str, n: int | None, cfg: GnnConfig):
    def run(spark, sf):
        return shown_topk(ex.ranking(ex.problem(spark, sf, name, n=n), "model", 10, cfg=cfg))

    return run


query(None, "gnn_topk_device")(_gnn_topk("v_device", None, QUICK))
query(None, "gnn_topk_logic15")(_gnn_topk("v_logic15", None, replace(QUICK, epochs=40)))
query(None, "gnn_joint")(_gnn_topk("v_device", None, replace(QUICK, label_channel="joint")))
query(None, "gnn_observed")(_gnn_topk("v_device", None, replace(QUICK, label_channel="observed")))


@query()
def gnn_ablation_edges(spark, sf):
    return ex.ablations(spark, sf, "v_logic15", None, QUICK)


@query()
def gnn_distributed(spark, sf):
    """Training with nodes spread over tasks: predictions for the device view."""
    from gapselect.model.distributed import fit_distributed

    pb = ex.problem(spark, sf, "v_device", truth=False)
    pred, losses = fit_distributed(ex.labels(pb), pb.spec.n, len(pb.missing), GnnConfig(hidden=8, epochs=8, rate=1e-2, level_max=3))
    if not losses[-1] < losses[0]:
        raise RuntimeError("the loss did not fall")
    return shown_topk(topk.topk(pred, 3, 10))


_IN, _CROSS, _JOIN, _OUT = [[0.5], [0.25]], [[0.1], [0.2]], [[0.3], [0.6], [1.0]], 2.0


@query("""WITH n AS (SELECT CAST(r AS BIGINT) AS m FROM (SELECT unnest(range(1, 4)) AS r)), e AS (SELECT a.m, b.m AS o FROM n a JOIN n b ON a.m <> b.m AND bit_count(a.m) <> bit_count(b.m)),
          x AS (SELECT m, CAST(m & 1 AS DOUBLE) AS b0, CAST(m >> 1 & 1 AS DOUBLE) AS b1 FROM n), a AS (SELECT e.m, avg(x.b0) AS a0, avg(x.b1) AS a1 FROM e JOIN x ON x.m = e.o GROUP BY e.m),
          g AS (SELECT x.m, b0, b1, 0.5 * a0 + 0.25 * a1 + 0.1 * b0 + 0.2 * b1 AS msg FROM x JOIN a ON a.m = x.m)
          SELECT sg, m AS mask, round(2.0 * greatest(0, 0.3 * b0 + 0.6 * b1 + 1.0 * msg), 6) AS mi, n_rows
          FROM g JOIN (SELECT CAST(l_linenumber % 2 AS INTEGER) AS sg, 1 + CAST(l_quantity AS BIGINT) % 3 AS mask, count(*) AS n_rows FROM lineitem GROUP BY ALL) r ON r.mask = g.m""")
def gnn_forward_fixed(spark, sf):
    """One layer of width one with fixed weights on two features and two lattices, for the
    sets that rows of a table name."""
    named = table(spark, sf, "lineitem").select((F.col("l_linenumber") % 2).cast("int").alias("sg"), (F.col("l_quantity").cast("long") % 3 + 1).alias("mask"))
    named = named.groupBy("sg", "mask").agg(F.count(F.lit(1)).alias("n_rows"))
    band = Band(2, 1, 2)
    rows = []
    for g in range(2):
        model = MultiplexModel(band, 2, g, 2, GnnConfig(layers=1, hidden=1))
        model.params = {"in0": np.array([_IN] * 2), "cross0": np.array([[_CROSS] * 2] * 2), "join0": np.array(_JOIN), "out": np.array([_OUT]), "bias": np.zeros(1)}
        out = model.forward(np.repeat(band.bits()[None].astype(float), 2, axis=0))
        rows += [(g, int(m), round(float(v), 6)) for m, v in zip(band.masks, out)]
    return spark.createDataFrame(rows, "sg int, mask long, mi double").join(named, ["sg", "mask"])


# ---- experiments


@query()
def exp_effectiveness(spark, sf):
    return ex.effectiveness(spark, sf, tuple(n for n in SPECS if n != "v_scale"), seeds=(0, 1, 2), cfg=QUICK)


@query()
def exp_robustness(spark, sf):
    return ex.robustness(spark, sf, ("v_staff", "v_device", "v_credit"), cfg=QUICK)


@query()
def exp_sampling(spark, sf):
    return ex.sampling_distance(spark, sf, ("v_staff", "v_device", "v_credit"))


@query()
def exp_closure(spark, sf):
    return ex.closure(spark, sf, ("v_staff", "v_device", "v_credit"), cfg=QUICK)


@query()
def exp_time_features(spark, sf):
    return ex.times(spark, sf, "n", (6, 8, 10), cfg=QUICK)


@query()
def exp_time_groups(spark, sf):
    return ex.times(spark, sf, "groups", (2, 4, 8), cfg=QUICK)


@query()
def exp_time_missing(spark, sf):
    return ex.times(spark, sf, "p", (0.2, 0.3, 0.4, 0.5), cfg=QUICK)


@query()
def exp_time_budget(spark, sf):
    return ex.times(spark, sf, "budget", (0.2, 0.4, 0.6, 0.8, 1.0), cfg=QUICK)


@query()
def exp_sharing(spark, sf):
    return ex.sharing_times(spark, sf, (6, 8, 10), (2, 4))
