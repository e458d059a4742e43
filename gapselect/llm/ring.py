"""Sharding by a consistent-hash ring with virtual nodes and bounded loads.

Shards own ``virtual`` points each on a ring of 64-bit positions; a document's position
is the hash of its text, so equal texts sit together. Each shard holds a fixed number of
rows at most. Walking clockwise, a row goes to the shard of the next point that still has
room; what overflows a full shard continues clockwise. With capacities that add up to the
row count (the ``rows`` law), counts differ by one at most and a row moves only if it
overflows or its arc changes hands.

The walk runs on arcs, not on rows. Documents are ordered by position with a range sort;
rank intervals of arcs are known from one count per arc (``shards * virtual`` numbers);
the walk over these gives a table of rank intervals ``(first rank, shard, first slot)`` of
at most arcs + shards rows; each row then finds its interval by its rank. A hot text is
just a long interval: it is split over sort partitions by id and over shards by capacity.

Defined results: null text has no bytes and the checksum of the empty string; repeated
rows are placed each; no rows give no rows; extra columns are not read.
"""

from __future__ import annotations

import bisect
import hashlib

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from gapselect.llm.common import as_text, durable

SHARDS, VIRTUAL = 40, 64


def ring_points(shards: int, virtual: int) -> list[tuple[int, int]]:
    """(position, shard) in ring order; positions are signed 64-bit."""

    def at(s: int, v: int) -> int:
        return int.from_bytes(hashlib.blake2b(f"{s}/{v}".encode(), digest_size=8).digest(), "big", signed=True)

    return sorted((at(s, v), s) for s in range(shards) for v in range(virtual))


def walk(points: list[tuple[int, int]], counts: list[int], room: list[int]) -> list[tuple[int, int, int, int]]:
    """Intervals (first rank, rows, shard, first slot) of the bounded-load walk.

    ``counts[k]`` rows end at point k. Two turns are enough: after the first, only rows
    that wrapped around the ring's end are still carried.
    """
    left, used = list(room), [0] * len(room)
    carried: list[tuple[int, int]] = []  # (first rank, rows) that found the shards so far full
    out = []
    rank = 0
    for turn in (0, 1):
        for k, (_, shard) in enumerate(points):
            waiting = carried
            if not turn and counts[k]:
                waiting = [*carried, (rank, counts[k])]
                rank += counts[k]
            carried = []
            for first, n in waiting:
                put = min(n, left[shard])
                if put:
                    out.append((first, put, shard, used[shard]))
                    left[shard] -= put
                    used[shard] += put
                if n > put:
                    carried.append((first + put, n - put))
            if turn and not carried:
                return sorted(out)
    if carried:
        raise ValueError("capacities are smaller than the number of rows")
    return sorted(out)


def ring_shards(docs: DataFrame, shards: int = SHARDS, virtual: int = VIRTUAL, slack: int = 0, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """id, size, text_crc32, shard, slot. ``slack`` rows more per shard than an even
    share loosen the bound (fewer rows overflow, counts differ by up to ``slack`` more)."""
    text = as_text(text_col)
    spark = docs.sparkSession
    rows = docs.select(
        F.col(id_col).alias("id"), (F.octet_length(text) + 16).cast("long").alias("size"),
        F.crc32(F.encode(text, "UTF-8")).cast("long").alias("crc"), F.xxhash64(text).alias("at"),
    )
    points = ring_points(shards, virtual)
    ends = [p for p, _ in points]
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    ordered = durable(
        rows.repartitionByRange(parts, "at", "id").sortWithinPartitions("at", "id", "size", "crc")
        .withColumn("row", F.monotonically_increasing_id())
    )
    part, place = F.shiftright("row", 33).cast("int"), F.col("row").bitwiseAND(F.lit((1 << 33) - 1))
    arc = interval(ends, F.col("at"))
    counted = ordered.groupBy(part.alias("part"), arc.alias("arc")).agg(F.count(F.lit(1)).alias("n"))
    by_part = {r["part"]: r["n"] for r in counted.groupBy("part").agg(F.sum("n").alias("n")).collect()}
    by_arc = {r["arc"]: r["n"] for r in counted.groupBy("arc").agg(F.sum("n").alias("n")).collect()}
    total = sum(by_part.values())
    base, offsets = 0, [0] * (max(by_part, default=0) + 1)
    for p in sorted(by_part):
        offsets[p], base = base, base + by_part[p]
    # Rows beyond the last point wrap to the first; in rank order they come last, so they
    # are one arc more, owned by the first point's shard.
    counts = [by_arc.get(k, 0) for k in range(len(points) + 1)]
    room = [total // shards + (s < total % shards) + slack for s in range(shards)]
    pieces = walk([*points, points[0]], counts, room)
    rank = F.get(F.lit(offsets), part) + place
    firsts = [p[0] for p in pieces]
    k = interval([f - 1 for f in firsts[1:]], F.col("rank")) if pieces else F.lit(0)
    placed = ordered.withColumn("rank", rank).withColumn("k", k)
    return placed.select(
        F.col("id").alias(id_col), "size", F.col("crc").alias("text_crc32"),
        F.get(F.lit([p[2] for p in pieces] or [0]), F.col("k")).alias("shard"),
        (F.get(F.lit([p[3] for p in pieces] or [0]), F.col("k")).cast("long") + F.col("rank") - F.get(F.lit(firsts or [0]), F.col("k"))).alias("slot"),
    )


def interval(ends: list[int], x: Column) -> Column:
    """Number of ``ends`` (ascending) that are below ``x``, by binary search over a literal
    table of fixed size."""
    if not ends:
        return F.lit(0)
    table = F.lit(sorted(set(ends)))

    def halve(s: Column, _: Column) -> Column:
        mid = F.shiftright(s["lo"] + s["hi"], 1)
        below = F.get(table, mid) < x
        return F.when(s["lo"] >= s["hi"], s).otherwise(
            F.struct(F.when(below, mid + 1).otherwise(s["lo"]).alias("lo"), F.when(below, s["hi"]).otherwise(mid).alias("hi"))
        )

    return F.aggregate(
        F.sequence(F.lit(1), F.lit(len(ends).bit_length())),
        F.struct(F.lit(0).alias("lo"), F.lit(len(set(ends))).alias("hi")),
        halve,
        lambda s: s["lo"],
    )


def moved_share(before: list[tuple[int, int, int, int]], after: list[tuple[int, int, int, int]], total: int) -> float:
    """Share of ranks whose shard differs between two walks over the same ranks."""
    starts_a, starts_b = [p[0] for p in before], [p[0] for p in after]
    cuts = sorted({*starts_a, *starts_b, total})
    moved = 0
    for lo, hi in zip(cuts, cuts[1:]):
        a = before[bisect.bisect_right(starts_a, lo) - 1][2]
        b = after[bisect.bisect_right(starts_b, lo) - 1][2]
        moved += (hi - lo) * (a != b)
    return moved / max(1, total)
