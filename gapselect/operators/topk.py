"""Rankings of feature sets, and measures of them. Ties fall to the smaller mask."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def topk(scores: DataFrame, m: int, k: int, score: str = "mi", digits: int = 9) -> DataFrame:
    """(sg, rank, mask, score) of the best ``k`` sets of ``m`` features per subgroup; the
    rank filter is pushed below the shuffle as a group limit."""
    w = Window.partitionBy("sg").orderBy(F.desc(F.round(score, digits)), "mask")
    ranked = scores.filter(F.bit_count("mask") == m).withColumn("rank", F.row_number().over(w)).filter(F.col("rank") <= k)
    return ranked.select("sg", "rank", "mask", F.col(score).alias("score"))


def hybrid(predicted: DataFrame, exact: DataFrame) -> DataFrame:
    """Exact values where they are known, predictions elsewhere: (sg, mask, mi)."""
    e = exact.select("sg", "mask", F.col("mi").alias("exact"))
    return predicted.join(e, ["sg", "mask"], "full").select("sg", "mask", F.coalesce("exact", "mi").alias("mi"))


def bounded_topk(upper: DataFrame, scores_of, m: int, k: int) -> DataFrame:
    """Top-K with closure pruning: ``upper`` (sg, mask, bound) holds sets of ``m`` with the
    least MI of a counted superset; the ``k`` highest bounds are scored first, and only
    sets whose bound reaches the k-th score found are scored at all."""
    upper = upper.withColumn("bound", F.round("bound", 9))  # as ranks are, so that a tie is never cut
    w = Window.partitionBy("sg").orderBy(F.desc("bound"), "mask")
    first = upper.withColumn("r", F.row_number().over(w)).filter(F.col("r") <= k)
    seen = scores_of(first.select("sg", "mask"))
    floor = seen.groupBy("sg").agg(F.min("mi").alias("floor"))
    rest = upper.join(floor, "sg").filter(F.col("bound") >= F.round("floor", 9)).select("sg", "mask")
    return topk(scores_of(rest), m, k)


def precision_at_k(pred: DataFrame, true: DataFrame, k: int) -> DataFrame:
    """(sg, value): found members of the true top-K over K."""
    hit = true.select("sg", "mask").join(pred.select("sg", "mask", F.lit(1).alias("hit")), ["sg", "mask"], "left")
    return hit.groupBy("sg").agg((F.coalesce(F.sum("hit"), F.lit(0)) / F.least(F.lit(k), F.count(F.lit(1)))).alias("value"))


def ndcg_at_k(pred: DataFrame, true: DataFrame, k: int) -> DataFrame:
    """(sg, value): binary gain 1 / log2(rank + 1) over its ideal."""
    hits = true.select("sg", "mask", F.col("rank").alias("ideal")).join(pred.select("sg", "mask", "rank"), ["sg", "mask"], "left")
    gain = F.coalesce(F.sum(F.when(F.col("rank") <= k, 1 / F.log2(F.col("rank") + 1))), F.lit(0.0))
    return hits.groupBy("sg").agg((gain / F.sum(1 / F.log2(F.col("ideal") + 1))).alias("value"))


def mi_range(scores: DataFrame, digits: int = 9) -> DataFrame:
    """(sg, low, high) of scores rounded as ranks are: the order in which a sum was taken
    must not make a range."""
    x = F.round("mi", digits)
    return scores.groupBy("sg").agg(F.min(x).alias("low"), F.max(x).alias("high"))


def histogram(scores: DataFrame, edges: DataFrame, bins: int = 20, by: tuple[str, ...] = (), digits: int = 9) -> DataFrame:
    """(by, sg, bin, p): shares in equal widths of ``edges`` (sg, low, high); a range below
    the last digit is one bin."""
    x = scores.join(edges, "sg")
    width = F.round(F.col("high") - F.col("low"), digits)
    share = F.round((F.round("mi", digits) - F.col("low")) * bins / width, 6)
    place = F.when(width > 0, F.greatest(F.lit(0), F.least(F.floor(share), F.lit(bins - 1)))).otherwise(0).cast("int")
    counts = x.groupBy(*by, "sg", place.alias("bin")).agg(F.count(F.lit(1)).alias("c"))
    return counts.withColumn("p", F.col("c") / F.sum("c").over(Window.partitionBy(*by, "sg"))).select(*by, "sg", "bin", "p")


def tv_l1(sample: DataFrame, population: DataFrame, bins: int = 20, half: bool = False, by: tuple[str, ...] = ()) -> DataFrame:
    """(by, sg, tv): L1 distance of the two histograms over the population's range, for
    every combination of the sample's columns ``by``."""
    edges = mi_range(population)
    a, b = histogram(sample, edges, bins, by), histogram(population, edges, bins)
    keys = sample.select(*by, "sg").distinct()
    b = keys.join(b, "sg") if by else b
    both = a.withColumnRenamed("p", "ps").join(b.withColumnRenamed("p", "pp"), [*by, "sg", "bin"], "full")
    gap = F.sum(F.abs(F.coalesce("ps", F.lit(0.0)) - F.coalesce("pp", F.lit(0.0))))
    return both.groupBy(*by, "sg").agg((gap / 2 if half else gap).alias("tv"))


def relative_drop(values: DataFrame, by: list[str] = ()) -> DataFrame:
    """Mean of consecutive relative drops of ``value`` along ``p``; zero bases are skipped
    and counted."""
    w = Window.partitionBy(*by).orderBy("p")
    steps = values.withColumn("before", F.lag("value").over(w)).filter("before IS NOT NULL")
    drop = F.when(F.col("before") != 0, (F.col("before") - F.col("value")) / F.col("before"))
    return steps.groupBy(*by).agg(F.avg(drop).alias("delta"), F.count_if(F.col("before") == 0).alias("skipped"))


def closure_accuracy(scores: DataFrame, n: int, by_level: bool = True, strict: bool = False) -> DataFrame:
    """Share of inter-level edges whose upper set scores at least its lower set."""
    each = scores.select("sg", F.col("mask").alias("upper"), F.bit_count("mask").cast("int").alias("level"), F.col("mi").alias("hi"), F.explode(F.sequence(F.lit(0), F.lit(n - 1))).alias("j"))
    bit = F.call_function("shiftleft", F.lit(1).cast("long"), F.col("j"))
    down = each.filter(F.col("upper").bitwiseAND(bit) != 0).withColumn("mask", F.col("upper").bitwiseXOR(bit))
    both = down.join(scores.select("sg", "mask", F.col("mi").alias("lo")), ["sg", "mask"])
    ok = F.col("hi") > F.col("lo") if strict else F.col("hi") >= F.col("lo") - 1e-9
    keys = ["sg", "level"] if by_level else ["sg"]
    return both.groupBy(*keys).agg(F.avg(F.when(ok, 1.0).otherwise(0.0)).alias("accuracy"), F.count(F.lit(1)).alias("edges"))


def test_masks(universe: DataFrame, sampled: DataFrame) -> DataFrame:
    """Sets with a missing feature and computable sets that were not sampled: all that has
    no label."""
    return universe.join(sampled, ["sg", "mask"], "left_anti")


def regression_error(pred: DataFrame, truth: DataFrame) -> DataFrame:
    """(sg, mse, mae, corr, spearman): errors of predicted scores, their correlation, and
    that of their ranks (the mean rank of ties)."""
    both = pred.select("sg", "mask", F.col("mi").alias("p")).join(truth.select("sg", "mask", F.col("mi").alias("t")), ["sg", "mask"])

    def place(c: str):
        same = F.count(F.lit(1)).over(Window.partitionBy("sg", c))
        return F.rank().over(Window.partitionBy("sg").orderBy(c)) + (same - 1) / 2

    both = both.withColumns({"p": F.round("p", 9), "t": F.round("t", 9)}).withColumns({"rp": place("p"), "rt": place("t")})
    gap = F.col("p") - F.col("t")
    return both.groupBy("sg").agg(F.avg(gap**2).alias("mse"), F.avg(F.abs(gap)).alias("mae"), F.corr("p", "t").alias("corr"), F.corr("rp", "rt").alias("spearman"))
