"""Choice of how lattice counts are shared, made before the plan is built."""

from __future__ import annotations

from itertools import combinations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def covering_blocks(n: int, masks: list[int], size: int) -> list[tuple[int, list[int]]]:
    """Greedy cover: blocks of at most ``size`` features, each with the sets it answers.

    Sets are handed out once. A block starts from the largest open set and takes on the
    features that occur most in sets it would complete.
    """
    left = sorted(set(masks), key=lambda m: (-m.bit_count(), m))
    out = []
    while left:
        block = left[0]
        while block.bit_count() < min(size, n):
            gain = {j: 0.0 for j in range(n) if not block >> j & 1}
            for m in left:
                out_of = m & ~block
                k = out_of.bit_count()
                if 0 < k <= size - block.bit_count():
                    for j in gain:
                        if out_of >> j & 1:
                            gain[j] += 1.0 / 4**k
            best = max(gain, key=lambda j: (gain[j], -j), default=None)
            if best is None or not gain[best]:
                break
            block |= 1 << best
        mine = [m for m in left if m & ~block == 0]
        out.append((block, mine))
        done = set(mine)
        left = [m for m in left if m not in done]
    return out


def plan_sharing(packed: DataFrame, masks: list[int], n: int) -> dict:
    """Which sharing to use and why: from rows, distinct cells (a sketch) and the sets."""
    row = packed.agg(F.count(F.lit(1)).alias("rows"), F.approx_count_distinct(F.struct("sg", "c0", "c1")).alias("cells"), F.max("y").alias("states")).first()
    deepest = max(m.bit_count() for m in masks)
    full = len(masks) >= (1 << n) - 1
    if full and deepest == n:
        choice, why = "rollup", "all levels are wanted: each set from a counted superset"
    elif row["cells"] * 4 <= row["rows"]:
        choice, why = "cuboid", "cells are a quarter of the rows or fewer"
    elif deepest <= 4:
        choice, why = "blocks", "cells do not compress; sets are small, so blocks bound them"
    elif len(masks) <= 64:
        choice, why = "grouping_sets", "few sets"
    else:
        choice, why = "cuboid", "large sets beyond blocks"
    return {"sharing": choice, "why": why, "n_rows": row["rows"], "n_cells": row["cells"], "n_sets": len(masks), "n_states": row["states"] or 1}


def block_count(n: int, level: int, size: int) -> int:
    return len(covering_blocks(n, [sum(1 << j for j in c) for c in combinations(range(n), level)], size))
