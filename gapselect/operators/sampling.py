"""Choice of lattice nodes under a budget: lazy random walk, uniform draws, strata.

All coins are md5 digits of (seed, subgroup, step), so a sample is the same whatever the
partitioning, retries included. A walk is sequential by nature; subgroups and walkers are
the parallel unit.
"""

from __future__ import annotations

import hashlib
from math import comb

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from gapselect.spec import band


def _coin(*parts) -> int:
    return int(hashlib.md5("|".join(map(str, parts)).encode()).hexdigest()[:12], 16)


def universe_size(available: int, low: int, high: int) -> int:
    bits = available.bit_count()
    return sum(comb(bits, k) for k in range(max(1, low), min(high, bits) + 1))


def budget_of(budget: float | int, size: int) -> int:
    """A count, or a rate of the computable universe for floats up to 1."""
    wanted = round(budget * size) if isinstance(budget, float) and budget <= 1 else int(budget)
    if wanted < 1:
        raise ValueError("the budget is empty")
    return min(wanted, size)


def walk(available: int, budget: int, seed: int, sg: int, low: int, high: int, lazy: float = 0.5, burn_in: int = 0, max_steps: int = 2_000_000, walker: int = 0) -> list[tuple[int, int]]:
    """First visits (mask, step) of one chain. Illegal moves are held, which keeps the law
    uniform; a band of one level swaps two bits instead of turning one."""
    bits = [j for j in range(60) if available >> j & 1]
    low, high = max(1, low), min(high, len(bits))
    key = (seed, sg, walker)
    at, start = 0, 0
    while not low <= at.bit_count() <= high:
        at = sum(1 << b for k, b in enumerate(bits) if _coin(*key, "s", start, k) % 2)
        start += 1
        if start > 500:
            at = sum(1 << b for b in bits[:low])
    seen: dict[int, int] = {} if burn_in else {at: 0}
    for step in range(1, max_steps + 1):
        if len(seen) >= budget:
            return list(seen.items())
        if _coin(*key, "z", step) % 1_000_000 >= lazy * 1_000_000:
            if low == high:
                on, off = [b for b in bits if at >> b & 1], [b for b in bits if not at >> b & 1]
                if off:
                    at ^= 1 << on[_coin(*key, "a", step) % len(on)] | 1 << off[_coin(*key, "b", step) % len(off)]
            else:
                to = at ^ 1 << bits[_coin(*key, "m", step) % len(bits)]
                if low <= to.bit_count() <= high:
                    at = to
        if step > burn_in:
            seen.setdefault(at, step)
    if len(seen) >= budget:
        return list(seen.items())
    raise RuntimeError(f"the walk saw {len(seen)} of {budget} sets in {max_steps} steps")


def walk_sample(spark: SparkSession, available: dict[int, int], budget: float | int, seed: int = 0, low: int = 1, high: int = 3, lazy: float = 0.5, burn_in: int = 0, walkers: int = 1) -> DataFrame:
    """(sg, mask, step) per subgroup. Near the whole universe a chain would be a coupon
    collector; from 95 % on the universe is listed and a coin leaves sets out. Several
    walkers go in step until their union holds the budget, so each may walk that far."""
    rows = [(sg, w, a) for sg, a in available.items() for w in range(walkers)]

    def run(key, pdf: pd.DataFrame) -> pd.DataFrame:
        sg, w, a = (int(pdf[c].iloc[0]) for c in ("sg", "walker", "available"))
        size = universe_size(a, low, high)
        b = budget_of(budget, size)
        if b >= 0.95 * size:
            every = sorted(band(60, low, high, a), key=lambda m: (_coin(seed, sg, "u", m), m))[:b]
            out = [(m, k) for k, m in enumerate(every)]
        else:
            out = walk(a, b, seed, sg, low, high, lazy, burn_in, walker=w)
        return pd.DataFrame([(sg, m, s) for m, s in out], columns=["sg", "mask", "step"])

    frame = spark.createDataFrame(rows, "sg int, walker int, available long")
    made = frame.groupBy("sg", "walker").applyInPandas(run, "sg int, mask long, step long")
    if walkers == 1:
        return made
    wanted = {sg: budget_of(budget, universe_size(a, low, high)) for sg, a in available.items()}
    most = F.create_map(*[F.lit(x) for pair in wanted.items() for x in pair])[F.col("sg")]
    union = made.groupBy("sg", "mask").agg(F.min("step").alias("step"))
    rank = F.row_number().over(Window.partitionBy("sg").orderBy("step", "mask"))
    return union.withColumn("r", rank).filter(F.col("r") <= most).drop("r")


def arbitrary_sample(universe: DataFrame, budget: float | int, seed: int = 0) -> DataFrame:
    """(sg, mask): uniform without replacement, by the order of an md5 coin per node."""
    coin = F.md5(F.concat_ws("|", F.lit(str(seed)), F.col("sg").cast("string"), F.col("mask").cast("string")))
    w = Window.partitionBy("sg")
    ranked = universe.select("sg", "mask", F.row_number().over(w.orderBy(coin, "mask")).alias("r"), F.count(F.lit(1)).over(w).alias("u"))
    most = F.least(F.round(F.lit(float(budget)) * F.col("u")).cast("long"), F.col("u")) if isinstance(budget, float) else F.lit(int(budget))
    return ranked.filter(F.col("r") <= most).select("sg", "mask")


def stratified_sample(universe: DataFrame, rate: float, seed: int = 0) -> DataFrame:
    """The same within every (subgroup, level)."""
    coin = F.md5(F.concat_ws("|", F.lit(str(seed)), F.col("sg").cast("string"), F.col("mask").cast("string")))
    w = Window.partitionBy("sg", F.bit_count("mask"))
    ranked = universe.select("sg", "mask", F.row_number().over(w.orderBy(coin, "mask")).alias("r"), F.count(F.lit(1)).over(w).alias("u"))
    return ranked.filter(F.col("r") <= F.ceil(F.lit(rate) * F.col("u"))).select("sg", "mask")


def universe(spark: SparkSession, available: dict[int, int], n: int, low: int, high: int) -> DataFrame:
    """(sg, mask) of all computable sets in the band."""
    from gapselect.operators.lattice import nodes

    frame = spark.createDataFrame(list(available.items()), "sg int, available long")
    every = nodes(spark, n, low, high).select("mask")
    return every.join(F.broadcast(frame), F.col("mask").bitwiseAND(F.bitwise_not("available")) == 0).select("sg", "mask")


def available_of(missing: dict[int, int], n: int) -> dict[int, int]:
    return {sg: (1 << n) - 1 & ~m for sg, m in missing.items()}
