"""The experiments: accuracy against baselines, robustness, sampling, closure, time, sharing.

All algorithms of one run see the same masked view; truth is MI on the complete view. Timed
stages end in an action on a small result; time is never part of a compared value.
"""

from __future__ import annotations

import time
from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass, field, replace
from functools import cached_property
from threading import Lock

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gapselect.baselines.knn import Pool, knn_impute, pool_of
from gapselect.baselines.markov import markov_topk
from gapselect.model.fit import fit_all, mlp_all, ridge_all
from gapselect.model.gnn import SMALL, GnnConfig
from gapselect.operators import mi as info
from gapselect.operators import sampling, topk
from gapselect.operators.missing import plant_missing
from gapselect.operators.prep import encode, hide, pack
from gapselect.plans.durable import durable, stored
from gapselect.sources.formats import roundtrip
from gapselect.spec import FeatureSpec, band, widen
from gapselect.views import GROUPS, SPECS, view


@dataclass
class Problem:
    """One masked view: what algorithms see, what is true, what is missing."""

    spec: FeatureSpec
    groups: int
    missing: dict[int, int]
    masked: DataFrame
    truth: DataFrame
    m: int
    complete: DataFrame | None = None
    filled: dict[int, DataFrame] = field(default_factory=dict)

    @cached_property
    def pool(self) -> Pool:
        """Cells and donors of the masked view, made once for all imputations."""
        return pool_of(self.masked)

    @property
    def available(self) -> dict[int, int]:
        return sampling.available_of(self.missing, self.spec.n)


#: Views are made one by one: each fills all cores, and two at a time would shuffle their rows at once.
_MAKING = Lock()


def complete(spark: SparkSession, sf: str, name: str, m: int = 3, n: int | None = None, groups: int | None = None, sharing: str = "auto", truth: bool = True) -> tuple[DataFrame, DataFrame | None]:
    """The packed view before anything is hidden, and its MI: the same for all rates and seeds. Rows are joined once."""
    spec = SPECS[name] if n is None else SPECS[name].head(n)
    with _MAKING:
        raw = stored(view(spark, sf, name, groups).select(spec.group, *spec.features, spec.target))  # coding reads it twice
        packed = stored(pack(encode(raw, spec), spec))
    return packed, durable(info.lattice_mi(packed, spec, band(spec.n, m, m), sharing)) if truth else None


def problem(spark: SparkSession, sf: str, name: str, p: float = 0.2, seed: int = 0, m: int = 3, n: int | None = None, groups: int | None = None, sharing: str = "auto", truth: bool = True, made: tuple[DataFrame, DataFrame | None] | None = None) -> Problem:
    """``made`` is what :func:`complete` gave, if it is known."""
    spec = SPECS[name] if n is None else SPECS[name].head(n)
    g = groups or GROUPS[name]
    packed, full = made or complete(spark, sf, name, m, n, groups, sharing, truth)
    missing = plant_missing(spec, g, p, seed, m)
    return Problem(spec, g, missing, hide(packed, missing), full, m, packed)


def labels(pb: Problem, budget: float = 1.0, seed: int = 0, low: int = 1, high: int | None = None, sharing: str = "auto", sampler: str = "walk") -> DataFrame:
    """(sg, mask, mi) of the sampled computable sets. The sample is drawn first, and only its sets are counted, each in its own subgroup;
    sets that hold a feature their subgroup lacks are never counted."""
    high = high or pb.m
    only = {g: band(pb.spec.n, low, high, a) for g, a in pb.available.items()}
    if budget < 1.0:
        spark = pb.masked.sparkSession
        if sampler == "walk":
            picked = sampling.walk_sample(spark, pb.available, budget, seed, low, high)
        else:
            picked = sampling.arbitrary_sample(sampling.universe(spark, pb.available, pb.spec.n, low, high), budget, seed)
        only = {g: [] for g in only}
        for r in picked.select("sg", "mask").collect():  # sets, not rows
            only[r["sg"]].append(r["mask"])
    only = {g: sorted(own) for g, own in only.items()}
    masks = sorted(set().union(*only.values()))
    return durable(info.lattice_mi(pb.masked, pb.spec, masks, sharing, only=only).select("sg", "mask", "mi"))


def imputed(pb: Problem, k: int = 5) -> DataFrame:
    """Cells of the masked view, filled from nearest neighbours; made once per problem."""
    if k not in pb.filled:
        pb.filled[k] = stored(knn_impute(pb.masked, pb.spec, k, pool=pb.pool))
    return pb.filled[k]


def knn_scores(pb: Problem, k: int = 5) -> DataFrame:
    return info.lattice_mi(imputed(pb, k), pb.spec, band(pb.spec.n, pb.m, pb.m))


ALGORITHMS = ("model", "knn", "markov", "mlp", "ridge")


def ranking(pb: Problem, algorithm: str, k: int, seed: int = 0, budget: float = 1.0, cfg: GnnConfig = SMALL, known: DataFrame | None = None) -> DataFrame:
    """(sg, rank, mask, score) of the best k sets by one algorithm."""
    if algorithm == "knn":
        return topk.topk(knn_scores(pb), pb.m, k)
    if algorithm == "markov":
        return markov_topk(pb.masked, pb.spec, pb.m, k, first=imputed(pb), pool=pb.pool)
    known = labels(pb, budget, seed) if known is None else known
    cfg = replace(cfg, seed=seed, level_max=cfg.level_max or pb.m)
    if algorithm == "model":
        predicted = fit_all(known, pb.spec.n, pb.groups, cfg)
    elif algorithm == "mlp":
        predicted = mlp_all(known, pb.spec.n, pb.m, pb.m, seed, cfg.epochs, cfg.rate)
    elif algorithm == "ridge":
        predicted = ridge_all(known, pb.spec.n, pb.m, pb.m)
    elif algorithm == "arbitrary":
        universe = pb.truth.select("sg", "mask")
        order = F.conv(F.substring(F.md5(F.concat_ws("|", F.lit(str(seed)), "sg", "mask")), 1, 8), 16, 10).cast("double")
        return topk.topk(universe.withColumn("mi", order), pb.m, k)
    else:
        raise ValueError(f"unknown algorithm {algorithm}")
    return topk.topk(durable(predicted), pb.m, k)


def score(pred: DataFrame, pb: Problem, ks=(5, 10)) -> list[tuple[int, float, float]]:
    """(K, nDCG, precision), means over subgroups."""
    out = []
    true = durable(topk.topk(pb.truth, pb.m, max(ks)))
    pred = durable(pred)
    for k in ks:
        t, p = true.filter(F.col("rank") <= k), pred.filter(F.col("rank") <= k)
        n = topk.ndcg_at_k(p, t, k).agg(F.avg("value")).first()[0]
        c = topk.precision_at_k(p, t, k).agg(F.avg("value")).first()[0]
        out.append((k, float(n), float(c)))
    return out


_EFFECT = "view string, p double, seed int, algorithm string, k int, ndcg double, precision double"


#: Runs whose jobs share the cluster; each is a chain of small jobs on sets.
AT_ONCE = 4


def _together(f, runs: list) -> list:
    with ThreadPoolExecutor(AT_ONCE) as pool:
        return list(pool.map(lambda r: f(*r), runs))


def _completes(spark, sf, views, m: int = 3, n: int | None = None) -> dict[str, tuple]:
    return dict(zip(views, _together(lambda name: complete(spark, sf, name, m, n), [(name,) for name in views])))


def effectiveness(spark, sf, views, algorithms=ALGORITHMS, p: float = 0.2, seeds=(0,), m: int = 3, budget: float = 1.0, cfg: GnnConfig = SMALL, n: int | None = None, made: dict[str, tuple] | None = None) -> DataFrame:
    made = made or _completes(spark, sf, views, m, n)

    def one(name, seed):
        pb = problem(spark, sf, name, p, seed, m, n, made=made[name])
        known = labels(pb, budget, seed)
        return [(name, p, seed, a, *r) for a in algorithms for r in score(ranking(pb, a, 10, seed, budget, cfg, known), pb)]

    rows = sum(_together(one, [(name, seed) for name in views for seed in seeds]), [])
    return spark.createDataFrame(rows, _EFFECT)


def summary(runs: DataFrame) -> DataFrame:
    """(view, algorithm, k, measure, mean, stddev, runs) over seeds."""
    longer = runs.unpivot(["view", "algorithm", "k", "seed"], ["ndcg", "precision"], "measure", "value")
    return longer.groupBy("view", "algorithm", "k", "measure").agg(F.avg("value").alias("mean"), F.stddev_samp("value").alias("stddev"), F.count(F.lit(1)).alias("runs"))


def robustness(spark, sf, views, rates=(0.2, 0.3, 0.4, 0.5), algorithms=("model", "knn"), cfg: GnnConfig = SMALL, n: int | None = None) -> DataFrame:
    """(view, algorithm, k, measure, delta, skipped): mean relative drop along p."""
    made = _completes(spark, sf, views, n=n)

    def one(name, p):
        return effectiveness(spark, sf, (name,), algorithms, p, cfg=cfg, n=n, made=made)

    runs = None
    for part in _together(one, [(name, p) for name in views for p in rates]):
        runs = part if runs is None else runs.unionByName(part)
    longer = runs.unpivot(["view", "algorithm", "k", "p"], ["ndcg", "precision"], "measure", "value")
    return topk.relative_drop(longer, ["view", "algorithm", "k", "measure"])


def sampling_distance(spark, sf, views, budgets=(0.25, 0.5, 0.75, 1.0), seeds=(0, 1, 2), n: int | None = None, high: int = 3) -> DataFrame:
    """L1 distances of sampled to population MI, of walk and uniform draws. The population
    is every set of the band on the complete view, as well as the computable sets alone."""
    def one(name):
        pb = problem(spark, sf, name, n=n, m=high, truth=False)
        spec = pb.spec
        every = durable(info.lattice_mi(pb.complete, spec, band(spec.n, 1, high)).select("sg", "mask", "mi"))
        can = info.computable(every, pb.missing)
        picked = None
        for b in budgets:
            for seed in seeds:
                walked = sampling.walk_sample(spark, pb.available, b, seed, 1, high).select("sg", "mask", F.lit("walk").alias("sampler"))
                drawn = sampling.arbitrary_sample(sampling.universe(spark, pb.available, spec.n, 1, high), b, seed).select("sg", "mask", F.lit("arbitrary").alias("sampler"))
                some = walked.unionByName(drawn).withColumns({"budget": F.lit(float(b)), "seed": F.lit(seed)})
                picked = some if picked is None else picked.unionByName(some)
        by = ("budget", "seed", "sampler")
        sample = durable(picked.join(every, ["sg", "mask"]))
        out = []
        for what, population in (("all", every), ("computable", can)):
            means = topk.tv_l1(sample, population, by=by).groupBy(*by).agg(F.avg("tv").alias("tv"))
            out += [(name, r["budget"], r["seed"], r["sampler"], what, r["tv"]) for r in means.collect()]
        return out

    rows = sum(_together(one, [(name,) for name in views]), [])
    return spark.createDataFrame(rows, "view string, budget double, seed int, sampler string, population string, tv double")


def closure(spark, sf, views, p: float = 0.2, seed: int = 0, high: int = 4, n: int | None = None, cfg: GnnConfig = SMALL) -> DataFrame:
    """Share of edges on which predictions keep upward closure, per upper level."""
    def one(name):
        pb = problem(spark, sf, name, p, seed, 3, n, truth=False)
        pred = durable(fit_all(labels(pb, 1.0, seed, 1, high), pb.spec.n, pb.groups, replace(cfg, seed=seed, level_max=high)))
        return topk.closure_accuracy(pred, pb.spec.n).groupBy("level").agg((F.sum(F.col("accuracy") * F.col("edges")) / F.sum("edges")).alias("accuracy")).withColumn("view", F.lit(name))

    out = None
    for part in _together(one, [(name,) for name in views]):
        out = part if out is None else out.unionByName(part)
    return out.select("view", "level", "accuracy")


def _timed(f) -> float:
    start = time.perf_counter()
    f()
    return time.perf_counter() - start


def times(spark, sf, vary: str, values, n: int = 10, groups: int = 4, p: float = 0.2, budget: float = 0.6, m: int = 3, cfg: GnnConfig = SMALL, algorithms=("model", "knn")) -> DataFrame:
    """Seconds of training and inference, and of imputation and its MI, along one axis."""
    rows = []
    for v in values:
        now = {"n": n, "groups": groups, "p": p, "budget": budget} | {vary: v}
        pb = problem(spark, sf, "v_scale", now["p"], 0, m, now["n"], now["groups"], truth=False)
        pb.masked.count()
        spent = {}
        if "model" in algorithms:
            def run():
                known = labels(pb, now["budget"], 0)
                topk.topk(fit_all(known, pb.spec.n, pb.groups, replace(cfg, level_max=m)), m, 10).count()

            spent["model"] = _timed(run)
        if "knn" in algorithms:
            spent["knn"] = _timed(lambda: topk.topk(knn_scores(pb), m, 10).count())
        rows += [(vary, float(v), a, s) for a, s in spent.items()]
    return spark.createDataFrame(rows, "axis string, value double, algorithm string, seconds double")


def sharing_times(spark, sf, sizes=(6, 8), groups=(4,), high: int = 3, ways=("none", "grouping_sets", "cuboid", "blocks", "rollup")) -> DataFrame:
    """Seconds of MI precomputation per way of sharing counts, and stored constructs. The rows
    of a number of subgroups are made once: a size takes its first features of them."""
    spec, rows = SPECS["v_scale"].head(max(sizes)), []
    made = {}
    for g in groups:
        raw = roundtrip(view(spark, sf, "v_scale", g).select(spec.group, *spec.features, spec.target), "parquet")
        made[g] = roundtrip(pack(encode(raw, spec), spec), "parquet")
    for n in sizes:
        first = widen((1 << n) - 1)
        for g in groups:
            packed = made[g].withColumns({f"c{k}": F.col(f"c{k}").bitwiseAND(F.lit(w)) for k, w in enumerate(first)})
            masks = band(n, 1, high)
            q = info.states(packed)
            for way in ways:
                got = []
                # the sum makes every value: a count alone would leave the entropies out of the plan
                spent = _timed(lambda: got.append(info.lattice_mi(packed, spec.head(n), masks, way, q=q).agg(F.count(F.lit(1)), F.sum("mi")).first()[0]))
                rows.append((n, g, way, spent, got[0]))
    return spark.createDataFrame(rows, "n int, groups int, sharing string, seconds double, constructs long")


def ablations(spark, sf, name: str = "v_logic15", n: int | None = 8, cfg: GnnConfig = SMALL) -> DataFrame:
    pb = problem(spark, sf, name, 0.2, 0, 3, n)
    known = labels(pb)
    variants = {
        "literal": cfg, "no_cross": replace(cfg, cross=False), "no_intra": replace(cfg, intra=False), "no_inter": replace(cfg, inter=False),
        "one_layer": replace(cfg, layers=1), "three_layers": replace(cfg, layers=3), "observed": replace(cfg, label_channel="observed"), "joint": replace(cfg, label_channel="joint"),
    }
    rows = [(v, *r) for v, c in variants.items() for r in score(ranking(pb, "model", 10, cfg=c, known=known), pb)]
    return spark.createDataFrame(rows, "variant string, k int, ndcg double, precision double")
