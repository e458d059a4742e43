"""Features that are null in every row of a subgroup: detection, profiles, planting."""

from __future__ import annotations

import hashlib

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gapselect.spec import FeatureSpec


def coin(salt: str, key: str, first: int = 0, digits: int = 8) -> int:
    return int(hashlib.md5(f"{salt}|{key}".encode()).hexdigest()[first : first + digits], 16)


def detect_missing(df: DataFrame, spec: FeatureSpec) -> DataFrame:
    """(sg, miss_mask, avail_mask) in one pass: a bit is missing where no row has a value."""
    counts = df.groupBy(F.col(spec.group).alias("sg")).agg(*[F.count(f).alias(f) for f in spec.features])
    bits = [F.when(F.col(f) == 0, F.lit(1 << j).cast("long")).otherwise(F.lit(0).cast("long")) for j, f in enumerate(spec.features)]
    miss = bits[0]
    for b in bits[1:]:
        miss = miss.bitwiseOR(b)
    return counts.select("sg", miss.alias("miss_mask"), F.lit((1 << spec.n) - 1).bitwiseAND(F.bitwise_not(miss)).alias("avail_mask"))


def null_profile(df: DataFrame, spec: FeatureSpec) -> DataFrame:
    """(sg, feature, nulls, n_rows) in long form."""
    counts = df.groupBy(F.col(spec.group).alias("sg")).agg(F.count(F.lit(1)).alias("n_rows"), *[F.count_if(F.col(f).isNull()).alias(f) for f in spec.features])
    return counts.unpivot(["sg", "n_rows"], list(spec.features), "feature", "nulls")


def plant_missing(spec: FeatureSpec, groups: int, p: float, seed: int, m: int = 3) -> dict[int, int]:
    """miss_mask per subgroup: each feature is hidden with probability ``p`` by an md5 coin,
    then repaired so that every feature is present somewhere, every subgroup lacks at
    least one, and ``m`` stay available in each."""
    if groups < 2:
        raise ValueError("with one subgroup a feature cannot be both missing and present")
    toss = {(g, j): coin(str(seed), f"{g}|{f}") for g in range(groups) for j, f in enumerate(spec.features)}
    gone = {g: {j for j in range(spec.n) if toss[g, j] % 10_000 < 10_000 * p} for g in range(groups)}
    for j in range(spec.n):
        if all(j in gone[g] for g in gone):
            gone[max(gone, key=lambda g: toss[g, j])].discard(j)
    for g in gone:
        if not gone[g]:
            free = [j for j in range(spec.n) if any(j not in gone[h] for h in gone if h != g)]
            gone[g].add(min(free, key=lambda j: toss[g, j]))
        while spec.n - len(gone[g]) < m:
            gone[g].discard(max(gone[g], key=lambda j: toss[g, j]))
    bad = any(all(j in gone[g] for g in gone) for j in range(spec.n)) or not all(gone.values())
    if bad:
        raise ValueError("no missingness fits both constraints")
    return {g: sum(1 << j for j in gone[g]) for g in gone}


def realised_rate(missing: dict[int, int], n: int) -> float:
    return sum(m.bit_count() for m in missing.values()) / (n * len(missing))


def plant_random_missing(df: DataFrame, spec: FeatureSpec, key: str, p: float, seed: int) -> DataFrame:
    """Each cell becomes null with probability ``p``, by an md5 coin of the row's key."""
    limit = int(10_000 * p)

    def cell(f: str):
        digits = F.substring(F.md5(F.concat_ws("|", F.lit(str(seed)), F.lit(f), F.col(key).cast("string"))), 1, 8)
        return F.when(F.conv(digits, 16, 10).cast("long") % 10_000 >= limit, F.col(f)).alias(f)

    return df.select(*[cell(c) if c in spec.features else F.col(c) for c in df.columns])
