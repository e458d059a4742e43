"""Connected components over edge tables, by alternating stars of shrinking height.

Each round turns neighbourhoods into stars around their smallest member; the work per
round is two grouped minima and two joins, all on edges, so nothing of a component's size
is ever in one task. Rounds end when the edges repeat themselves; there are about
``log(n)`` of them. Every round is written to the shared folder, so lost executors cost
one round at most. Minima are written on their own, so that the rows that join them are
exchanged anew and those of a hot node are split.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gapselect.llm.common import durable, written


def _seal(edges: DataFrame) -> tuple[DataFrame, tuple]:
    kept = durable(edges)
    return kept, tuple(kept.agg(F.count(F.lit(1)), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first())


def connected_components(edges: DataFrame, most_rounds: int = 100) -> DataFrame:
    """(node, component) of every node of the edges (u, v); component is its smallest
    node. Loops and repeated edges are ignored; no edges give no rows."""
    turned = edges.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).filter("u > v").distinct()
    now, mark = _seal(turned)
    for _ in range(most_rounds):
        if not mark[0]:
            break
        both = now.unionByName(now.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = written(both.groupBy("u").agg(F.min("v").alias("m")).withColumn("m", F.least("u", "m")))
        large = written(both.join(least, "u").filter("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct())
        low = written(large.groupBy("u").agg(F.min("v").alias("m")))
        small = large.join(low, "u")
        small = small.filter("v != m").select(F.col("v").alias("u"), F.col("m").alias("v")).unionByName(low.select("u", F.col("m").alias("v")))
        now, seen = _seal(small.filter("u > v").distinct())
        if seen == mark:
            break
        mark = seen
    else:
        raise RuntimeError("components did not settle")
    return now.select(F.col("u").alias("node"), F.col("v").alias("component")).unionByName(
        now.select(F.col("v").alias("node"), F.col("v").alias("component")).distinct()
    )
