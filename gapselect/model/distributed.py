"""Full-batch training with nodes spread over tasks, for bands that no task holds.

A node's state after the first layer depends on its set alone: the mean of its neighbours'
binary codes has a closed form. So a task that holds some labelled sets makes the sets within
``layers - 1`` steps of them itself and needs nothing from other tasks: an epoch is one map
without an exchange, and one gradient vector per task, summed in two steps. Sets are dealt by
ranges of masks and taken ``BLOCK`` at a time, so memory is bounded by the neighbourhood of
a block. Weights, optimiser, validation sets and the choice of the best epoch are those of
the model inside one task, and so are the results up to the order of sums.
"""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from gapselect.model.gnn import Adam, GnnConfig, MultiplexModel
from gapselect.model.multiplex import Band
from gapselect.operators.lattice import degree, nodes
from gapselect.plans.durable import durable

#: Labelled sets whose neighbourhoods a task holds at once.
BLOCK = 256


def input_means(spark, n: int, low: int, high: int) -> DataFrame:
    """(mask, bits, mean): binary code and its in-lattice neighbour mean, in closed form
    where the band is the whole lattice, else by exchange over XOR keys."""
    base = nodes(spark, n, low, high)
    bit = F.transform(F.sequence(F.lit(0), F.lit(n - 1)), lambda j: F.when(F.call_function("bit_get", F.col("mask"), j) == 1, 1.0).otherwise(0.0))
    level, deg = F.col("level"), degree(F.col("level"), n, low, high)
    down = F.when(level > low, 1).otherwise(0)
    up = F.when(level < high, 1).otherwise(0)
    side = F.when(level > 1, 1).otherwise(0)
    # How many neighbours hold bit j: children keep it unless it was dropped, parents and
    # exchanges may bring it.
    own = down * (level - 1) + up * (n - level) + side * (level - 1) * (n - level)
    other = up * 1 + side * level
    mean = F.transform(F.col("bits"), lambda b: F.when(b > 0, own).otherwise(other) / F.greatest(deg, F.lit(1)))
    return base.withColumn("bits", bit).withColumn("mean", mean).select("mask", "level", "bits", "mean")


class Neighbourhood(Band):
    """The sets of a band within ``steps`` of ``masks``, with degrees of the whole band."""

    def __init__(self, masks: np.ndarray, steps: int, n: int, low: int, high: int, inter: bool = True, intra: bool = True):
        self.n, self.dense = n, None
        low, high = max(1, low), min(n, high)
        turns = [1 << j for j in range(n)] if inter else []
        swaps = [1 << a | 1 << b for a in range(n) for b in range(a)] if intra else []

        def edges(of):
            for x in turns:
                to, was = of ^ x, np.bitwise_count(of)
                size = was + np.where(of & x, -1, 1)
                yield np.flatnonzero((size >= low) & (size <= high)), to
            for x in swaps:
                yield np.flatnonzero((np.bitwise_count(of & x) == 1) & (np.bitwise_count(of) > 1)), of ^ x

        here = np.unique(np.asarray(masks, np.int64))
        for _ in range(steps):
            here = np.unique(np.concatenate([here, *(to[i] for i, to in edges(here))]))
        self.masks = here
        start, end = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)]
        for i, to in edges(here):
            k = np.minimum(np.searchsorted(here, to[i]), len(here) - 1)
            inside = here[k] == to[i]
            start.append(i[inside]), end.append(k[inside])
        start, end = np.concatenate(start), np.concatenate(end)
        order = np.argsort(start, kind="stable")
        self.flat, self.starts = end[order], np.searchsorted(start[order], np.arange(len(here) + 1))
        level = np.bitwise_count(here).astype(float)
        down, up, side = (level > low) * float(inter), (level < high) * float(inter), (level > 1) * float(intra)
        self.degree = np.maximum(1, down * level + up * (n - level) + side * level * (n - level))
        own, other = down * (level - 1) + up * (n - level) + side * (level - 1) * (n - level), up + side * level
        self.first = np.where(self.bits() > 0, own[:, None], other[:, None]) / self.degree[:, None]


def _held(labels: DataFrame, cfg: GnnConfig) -> DataFrame:
    """(sg, mask, mi, held): validation sets as ``split_validation`` picks them. Where the
    coins hold all sets of a subgroup or none, which takes a few dozen sets at most, every
    fifth is held."""
    if not 0 < cfg.validation < 1:
        raise ValueError("the share of validation sets must be between 0 and 1")
    text = F.concat_ws("|", F.lit("v"), F.lit(str(cfg.seed)), F.col("sg").cast("string"), F.col("mask").cast("string"))
    coin = F.conv(F.substring(F.md5(text), 1, 8), 16, 10).cast("long") % 10_000
    marked = durable(labels.select(F.col("sg").cast("int").alias("sg"), F.col("mask").cast("long").alias("mask"), "mi").withColumn("held", coin < 10_000 * cfg.validation))
    odd = [r["sg"] for r in marked.groupBy("sg").agg(F.min("held").alias("a"), F.max("held").alias("b")).filter("a = b").select("sg").collect()]
    if not odd:
        return marked
    fifth = (F.row_number().over(Window.partitionBy("sg").orderBy("mask")) - 1) % 5 == 4
    return marked.filter(~F.col("sg").isin(odd)).unionByName(marked.filter(F.col("sg").isin(odd)).withColumn("held", fifth))


def fit_distributed(labels: DataFrame, n: int, groups: int, cfg: GnnConfig) -> tuple[DataFrame, list[float]]:
    """(predictions (sg, mask, mi) of all band sets, losses per epoch, summed over models):
    one model per subgroup, trained together; per epoch one map over labelled sets."""
    if cfg.label_channel != "none":
        raise ValueError("labels as inputs need the model inside one task")
    spark = labels.sparkSession
    low, high = max(1, cfg.level_min), cfg.level_max or n
    level = F.bit_count(F.col("mask"))
    marked = durable(_held(labels.filter((level >= low) & (level <= high)), cfg))
    train = F.when(~F.col("held"), F.col("mi"))
    stats = {r["sg"]: r for r in marked.groupBy("sg").agg(F.avg(train).alias("m"), F.stddev_pop(train).alias("s"), F.count(train).alias("train"), F.count(F.lit(1)).alias("k")).collect()}
    rest = labels.agg(F.coalesce(F.avg("mi"), F.lit(0.0))).first()[0]
    known = [g for g in range(groups) if g in stats and stats[g]["k"] > 1]
    scale = {g: (stats[g]["m"], stats[g]["s"] or 1.0) for g in known}
    count = {g: (stats[g]["train"], stats[g]["k"] - stats[g]["train"]) for g in known}
    entry = F.struct("sg", "mi", "held")
    parts = max(spark.sparkContext.defaultParallelism, marked.count() // 20_000 + 1)
    rows = durable(marked.groupBy("mask").agg(F.collect_list(entry).alias("y")).repartitionByRange(parts, "mask").sortWithinPartitions("mask"))  # an entry per subgroup at most

    def model(g: int, band, params=None):
        out = MultiplexModel(band, groups, g, n, cfg)
        out.params = params or out.params
        return out

    params = {g: model(g, None).params for g in known}
    opt = {g: Adam(params[g], cfg.rate, cfg.decay) for g in known}
    names = {g: sorted(params[g]) for g in known}

    def around(masks):
        band = Neighbourhood(masks, cfg.layers - 1, n, low, high, cfg.inter, cfg.intra)
        return band, np.repeat(band.bits()[None].astype(float), groups, axis=0)

    def one_pass(now):
        """Per model (loss, error, gradient): sums over its training and validation sets."""

        def step(frames):
            total = {g: {k: np.zeros_like(v) for k, v in now[g].items()} for g in known}
            loss, error = dict.fromkeys(known, 0.0), dict.fromkeys(known, 0.0)
            for pdf in frames:
                for i in range(0, len(pdf), BLOCK):
                    part = pdf.iloc[i : i + BLOCK]
                    band, x = around(part["mask"].to_numpy())
                    at = np.searchsorted(band.masks, part["mask"].to_numpy())
                    for g in known:
                        mine = [(k, e["mi"], e["held"]) for k, y in zip(at, part["y"]) for e in y if e["sg"] == g]
                        if not mine:
                            continue
                        where, y, held = (np.array(c) for c in zip(*mine))
                        z, net = (y - scale[g][0]) / scale[g][1], model(g, band, now[g])
                        if held.any():
                            error[g] += float(((net.forward(x)[where[held]] - z[held]) ** 2).sum())
                        if not held.all():
                            here = int((~held).sum())
                            mse, grad = net.gradients(x, where[~held], z[~held])
                            loss[g] += mse * here
                            for k in grad:
                                total[g][k] += grad[k] * here
            for g in known:
                yield pd.DataFrame({"sg": [g], "loss": [loss[g]], "error": [error[g]], "g": [np.concatenate([total[g][k].ravel() for k in names[g]]).tolist()]})

        def add(frames):
            sums: dict[int, list] = {}
            for pdf in frames:
                for g, one, two, v in zip(pdf["sg"], pdf["loss"], pdf["error"], pdf["g"]):
                    old = sums.get(g, [0.0, 0.0, 0.0])
                    sums[g] = [old[0] + one, old[1] + two, old[2] + np.asarray(v)]
            for g, (one, two, v) in sums.items():
                yield pd.DataFrame({"sg": [int(g)], "loss": [one], "error": [two], "g": [v.tolist()]})

        out = "sg int, loss double, error double, g array<double>"
        sent = rows.mapInPandas(step, out).repartition(math.isqrt(parts - 1) + 1).mapInPandas(add, out).collect()
        return {g: (sum(r["loss"] for r in sent if r["sg"] == g), sum(r["error"] for r in sent if r["sg"] == g), np.sum([r["g"] for r in sent if r["sg"] == g], axis=0)) for g in known}

    losses, best, kept = [], dict.fromkeys(known, math.inf), {}
    for epoch in range(cfg.epochs + 1 if known else 0):
        got = one_pass({g: {k: v.copy() for k, v in params[g].items()} for g in known})
        # This pass has seen the weights that the epoch before left.
        if cfg.keep_best and epoch and (epoch % 5 == 0 or epoch == cfg.epochs):
            for g in known:
                if count[g][1] and got[g][1] / count[g][1] < best[g]:
                    best[g], kept[g] = got[g][1] / count[g][1], {k: v.copy() for k, v in params[g].items()}
        if epoch == cfg.epochs:
            break
        losses.append(sum(got[g][0] / max(1, count[g][0]) for g in known))
        for g in known:
            cut = np.split(got[g][2] / max(1, count[g][0]), np.cumsum([params[g][k].size for k in names[g]])[:-1])
            opt[g].step(params[g], {k: c.reshape(params[g][k].shape) for k, c in zip(names[g], cut)})
    final = {g: kept.get(g, params[g]) for g in known}

    def predict(frames):
        for pdf in frames:
            for i in range(0, len(pdf), BLOCK):
                masks = pdf["mask"].to_numpy()[i : i + BLOCK]
                band, x = around(masks)
                at = np.searchsorted(band.masks, masks)
                for g in range(groups):
                    out = model(g, band, final[g]).forward(x)[at] * scale[g][1] + scale[g][0] if g in final else np.full(len(masks), rest)
                    yield pd.DataFrame({"sg": np.int32(g), "mask": masks, "mi": out})

    return nodes(spark, n, low, high).select("mask").mapInPandas(predict, "sg int, mask long, mi double"), losses
