"""Nodes and edges of subgroup lattices and of the multiplex graph, as bit arithmetic.

Edges are implicit: a neighbour is an XOR away. Edge tables exist for small lattices; sums
over neighbours never need them.
"""

from __future__ import annotations

from math import comb

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from gapselect.spec import band

_GENERATED = 24  # up to this many features the band is filtered from a range, beyond it listed


def nodes(spark: SparkSession, n: int, low: int = 1, high: int | None = None) -> DataFrame:
    """(mask, level) of the band."""
    high = n if high is None else high
    if n <= _GENERATED:
        made = spark.range(1, 1 << n).select(F.col("id").alias("mask"), F.bit_count("id").cast("int").alias("level"))
        return made.filter(F.col("level").between(low, high))
    return spark.createDataFrame([(m, m.bit_count()) for m in band(n, low, high)], "mask long, level int")


def to_bits(mask: Column, n: int) -> Column:
    return F.lpad(F.bin(mask), n, "0")


def decode(mask: Column, features: tuple[str, ...]) -> Column:
    return F.filter(F.array(*[F.when(mask.bitwiseAND(F.lit(1 << j)) != 0, F.lit(f)) for j, f in enumerate(features)]), lambda x: x.isNotNull())


def encode_set(names: Column, features: tuple[str, ...]) -> Column:
    out = F.lit(0).cast("long")
    for j, f in enumerate(features):
        out = out + F.when(F.array_contains(names, f), F.lit(1 << j)).otherwise(0)
    return out


def _bit(j: Column) -> Column:
    return F.call_function("shiftleft", F.lit(1).cast("long"), j)


def _steps(n: int) -> Column:
    return F.explode(F.sequence(F.lit(0), F.lit(n - 1)))


def inter_edges(band_nodes: DataFrame, n: int) -> DataFrame:
    """(upper, lower): one feature dropped; lower ends stay inside the band."""
    down = band_nodes.select(F.col("mask").alias("upper"), _steps(n).alias("j"))
    held = down.filter(F.col("upper").bitwiseAND(_bit(F.col("j"))) != 0)
    cut = held.select("upper", F.col("upper").bitwiseXOR(_bit(F.col("j"))).alias("lower"))
    return cut.join(band_nodes.select(F.col("mask").alias("lower")), "lower", "left_semi").select("upper", "lower")


def intra_edges(band_nodes: DataFrame, n: int) -> DataFrame:
    """(src, dst), src < dst: one feature exchanged for another, some feature shared."""
    wide = band_nodes.filter("level > 1").select(F.col("mask").alias("src"), _steps(n).alias("j"))
    drop = wide.filter(F.col("src").bitwiseAND(_bit(F.col("j"))) != 0).select("src", "j", _steps(n).alias("k"))
    swap = drop.filter((F.col("src").bitwiseAND(_bit(F.col("k"))) == 0))
    return swap.select("src", F.col("src").bitwiseXOR(_bit(F.col("j")).bitwiseOR(_bit(F.col("k")))).alias("dst")).filter("src < dst")


def cross_edges(band_nodes: DataFrame, groups: int) -> DataFrame:
    """(mask, i, j): the same set in two lattices, i < j; each pair is an edge type."""
    pairs = F.filter(F.flatten(F.transform(F.sequence(F.lit(0), F.lit(groups - 1)), lambda i: F.transform(F.sequence(F.lit(0), F.lit(groups - 1)), lambda j: F.struct(i.alias("i"), j.alias("j"))))), lambda p: p["i"] < p["j"])
    return band_nodes.select("mask", F.explode(pairs).alias("p")).select("mask", "p.i", "p.j")


def lattice_size(n: int, groups: int = 1, low: int = 1, high: int | None = None) -> dict[str, int]:
    """Counts of nodes and of edges by kind, from binomials."""
    high = n if high is None else high
    levels = range(low, high + 1)
    return {
        "nodes": groups * sum(comb(n, k) for k in levels),
        "inter": groups * sum(comb(n, k) * k for k in levels if k - 1 >= low),
        "intra": groups * sum(comb(n, k) * k * (n - k) // 2 for k in levels if k > 1),
        "cross": comb(groups, 2) * sum(comb(n, k) for k in levels),
    }


def degree(level: Column, n: int, low: int = 1, high: int | None = None) -> Column:
    """Neighbours of a node inside the band."""
    high = n if high is None else high
    down = F.when(level > low, level).otherwise(0)
    up = F.when(level < high, n - level).otherwise(0)
    side = F.when(level > 1, level * (n - level)).otherwise(0)
    return down + up + side


def neighbour_reduce(values: DataFrame, n: int, how: str = "mean", value: str = "value") -> DataFrame:
    """(mask, out): sum, mean or max of a value over the inter and intra neighbours a set has
    in ``values``: the reducer of a generic update. Neighbours of a node go out as rows, as
    maxima cannot be taken back as sums are in :func:`neighbour_mean`."""
    reduce = {"sum": F.sum, "mean": F.avg, "max": F.max}[how]
    steps = F.sequence(F.lit(0), F.lit(n - 1))
    at = F.col("mask")
    one = F.transform(steps, lambda j: at.bitwiseXOR(_bit(j)))
    two = F.flatten(F.transform(steps, lambda a: F.transform(F.filter(steps, lambda b: (at.bitwiseAND(_bit(a)) != 0) & (at.bitwiseAND(_bit(b)) == 0)), lambda b: at.bitwiseXOR(_bit(a)).bitwiseXOR(_bit(b)))))
    to = F.explode(F.concat(one, F.when(F.bit_count(at) > 1, two).otherwise(F.array().cast("array<bigint>"))))
    sent = values.select(to.alias("to"), F.col(value).cast("double").alias("v")).groupBy(F.col("to").alias("mask")).agg(reduce("v").alias("out"))
    return values.select("mask").join(sent, "mask")


def neighbour_mean(values: DataFrame, n: int, value: str = "value") -> DataFrame:
    """(mask, mean of the value over inter and intra neighbours) of the full lattice.

    With D = sum over children (levels below) and U = sum over parents, the exchange sum is
    ``U(D) - level * value``: three n-way explodes instead of n squared.
    """

    def toggled(df: DataFrame, want_set: bool) -> DataFrame:
        each = df.select("mask", "v", _steps(n).alias("j"))
        held = F.col("mask").bitwiseAND(_bit(F.col("j"))) != 0
        to = each.filter(held if want_set else ~held)
        return to.select(F.col("mask").bitwiseXOR(_bit(F.col("j"))).alias("mask"), "v").groupBy("mask").agg(F.sum("v").alias("v"))

    base = values.select("mask", F.col(value).cast("double").alias("v"))
    from_children = toggled(base, False).withColumnRenamed("v", "d")  # a node sends to its supersets
    from_parents = toggled(base, True).withColumnRenamed("v", "u")
    via_zero = base.unionByName(base.sparkSession.createDataFrame([(0, 0.0)], "mask long, v double"))
    side = toggled(toggled(via_zero, True), False).withColumnRenamed("v", "s")  # down then up again
    level = F.bit_count("mask").cast("int")
    out = base.join(from_children, "mask", "left").join(from_parents, "mask", "left").join(side, "mask", "left").withColumn("level", level)
    intra = F.when(F.col("level") > 1, F.coalesce("s", F.lit(0.0)) - F.col("level") * F.col("v")).otherwise(0.0)
    down = F.when(F.col("level") > 1, F.coalesce("d", F.lit(0.0))).otherwise(0.0)
    total = down + F.coalesce("u", F.lit(0.0)) + intra
    deg = degree(F.col("level"), n)
    return out.select("mask", "level", F.when(deg > 0, total / deg).otherwise(0.0).alias("mean"))
