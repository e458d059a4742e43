"""Joins that Spark has no operator for, as equi-joins on a derived key."""

from __future__ import annotations

from functools import reduce
from itertools import combinations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def asof(left: DataFrame, right: DataFrame, key: str, time: str, values: list[str]) -> DataFrame:
    """Each left row with the values of the last right row of its key at or before it: one
    shuffle by key of both sides together, one running last value."""
    names = left.columns
    a = left.select(*names, F.lit(1).alias("__side"), *[F.lit(None).cast(right.schema[v].dataType).alias(f"__{v}") for v in values])
    b = right.select(*[F.col(c) if c in (key, time) else F.lit(None).cast(left.schema[c].dataType).alias(c) for c in names], F.lit(0).alias("__side"), *[F.col(v).alias(f"__{v}") for v in values])
    w = Window.partitionBy(key).orderBy(time, "__side").rowsBetween(Window.unboundedPreceding, 0)
    seen = F.last(F.when(F.col("__side") == 0, F.struct(*[F.col(f"__{v}").alias(v) for v in values])), ignorenulls=True).over(w)
    out = a.unionByName(b).withColumn("__m", seen).filter("__side = 1")
    return out.select(*names, *[F.col(f"__m.{v}").alias(v) for v in values])


def interval_join(left: DataFrame, right: DataFrame, key: str, time: str, seconds: int) -> DataFrame:
    """Pairs of one key with ``left.time < right.time <= left.time + seconds``. Time is cut
    into slots of that length, so a left row meets two slots, not the key's whole history."""
    slot = F.floor(F.unix_timestamp(time) / seconds)
    a = left.select(*[F.col(c).alias(f"l_{c}") for c in left.columns], F.explode(F.array(slot, slot + 1)).alias("__s"))
    b = right.select(*[F.col(c).alias(f"r_{c}") for c in right.columns], slot.alias("__t"))
    after = F.col(f"r_{time}") > F.col(f"l_{time}")
    until = F.col(f"r_{time}") <= F.col(f"l_{time}") + F.make_dt_interval(secs=F.lit(seconds))
    return a.join(b, (F.col(f"l_{key}") == F.col(f"r_{key}")) & (F.col("__s") == F.col("__t")) & after & until).drop("__s", "__t")


def range_join(left: DataFrame, bins: DataFrame, value: str, low: str, high: str, most: int = 10_000) -> DataFrame:
    """Rows with the bin ``low < value <= high`` they fall in. Up to ``most`` bins go to all
    tasks; more are joined by the slots of a grid that their narrowest width gives."""
    few = bins.limit(most + 1).count()
    inside = (F.col(value) > F.col(low)) & (F.col(value) <= F.col(high))
    if few <= most:
        return left.join(F.broadcast(bins), inside)
    grid = bins.agg(F.min(F.col(high) - F.col(low))).first()[0]
    cut = bins.withColumn("__s", F.explode(F.sequence(F.floor(F.col(low) / grid), F.floor(F.col(high) / grid))))
    return left.withColumn("__v", F.floor(F.col(value) / grid)).join(cut, (F.col("__v") == F.col("__s")) & inside).drop("__v", "__s")


def near_pairs(left: DataFrame, right: DataFrame, parts: list[list[str]], key: str, most: int) -> DataFrame:
    """(a, b) of rows that differ in at most ``most`` columns, where ``parts`` splits the
    columns into more than ``most`` groups: all but ``most`` groups must agree, and are the
    join key, so with groups of one column every pair that meets is a result. The first groups
    left out that fit make the pair, so none comes twice and no pairs are exchanged. A row with
    a null is near to none. Few rows make many pairs: the left ones are dealt to all cores, and
    the right ones of a key are cut into as many shares, which may lie in different tasks."""
    if len(parts) <= most:
        raise ValueError("more parts than differences are needed")
    cols = [c for p in parts for c in p]
    cores = left.sparkSession.sparkContext.defaultParallelism
    a = left.select(key, *cols).na.drop(subset=cols).repartition(4 * cores, key).withColumn("__s", F.explode(F.sequence(F.lit(0), F.lit(cores - 1)))).alias("a")
    b = right.select(key, *cols).na.drop(subset=cols).withColumn("__s", F.pmod(F.hash(key), F.lit(cores))).alias("b")

    def same(groups) -> Column:
        return reduce(lambda x, y: x & y, [F.col(f"a.{c}") == F.col(f"b.{c}") for i in sorted(groups) for c in parts[i]], F.lit(True))

    out, tried = None, []
    for free in map(set, combinations(range(len(parts)), most)):
        meet = (F.col("a.__s") == F.col("b.__s")) & same(set(range(len(parts))) - free)
        if sum(len(parts[i]) for i in free) > most:
            meet = meet & (sum([F.when(F.col(f"a.{c}") != F.col(f"b.{c}"), 1).otherwise(0) for i in free for c in parts[i]], F.lit(0)) <= most)
        for before in tried:
            meet = meet & ~same(free - before)
        tried.append(free)
        hit = a.join(b, meet).select(F.col(f"a.{key}").alias("a"), F.col(f"b.{key}").alias("b"))
        out = hit if out is None else out.unionByName(hit)
    return out
