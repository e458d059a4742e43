"""Best-fit packing with bound-certified repacking.

Documents become pieces of at most ``capacity`` tokens (longer ones are cut, the first
piece taking what is left over). Each scan task is one packing partition and keeps its
pieces as a histogram over lengths: at most ``capacity`` numbers, however many documents.
Best-fit decreasing runs on histograms, many equal bins at a time. Dual-feasible
functions give a lower bound on the bins of a partition; a partition whose count meets
its bound is certified and done. Partitions with a gap exchange their documents:
``fan_in`` of them pool their histograms and best-fit decreasing runs again, level by
level, until all are certified or one pool is left. If the certified counts together
still exceed the bound of the whole input (each may round up), one last pool holds all.

Only histograms and placement intervals move while plans are made. Pieces themselves are
matched once with the placement intervals of their own partition, by length and by rank
within the length, so a length that a third of all documents share is one interval, not
one hot group.

Defined results: a null or empty text is one piece, the end token alone; repeated rows
are packed each; an empty table gives no rows; extra columns are not read.
"""

from __future__ import annotations

import zlib
from collections import defaultdict

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gapselect.llm.bpe import fast_ids
from gapselect.llm.coding import slices
from gapselect.llm.common import as_text, durable

CAPACITY, END_ID, FAN_IN = 1024, 2, 8
_POOLED = 15  # the level number of the pool that holds all


def best_fit(counts: dict[int, int], capacity: int) -> tuple[list[tuple[int, int, int, int, int]], int]:
    """Placements (length, first rank, pieces, first bin, offset) and the number of bins.

    Piece ``first rank + i`` of that length goes to bin ``first bin + i``. Bins with equal
    free space are handled as intervals, so the work depends on the number of different
    lengths, not of pieces.
    """
    free: dict[int, list[tuple[int, int]]] = defaultdict(list)
    open_sizes = 0  # bit f is set while some bin has f tokens free
    placed, bins = [], 0
    for size in sorted(counts, reverse=True):
        rank, left = 0, counts[size]
        while left:
            fitting = open_sizes >> size
            if fitting:
                space = size + (fitting & -fitting).bit_length() - 1
                start, n = free[space].pop()
            else:
                space, start, n = capacity, bins, max(1, left // (capacity // size))
                bins += n
            each = min(space // size, left)
            m = min(n, left // each)
            for k in range(each):
                placed.append((size, rank, m, start, capacity - space + k * size))
                rank += m
            left -= m * each
            if m < n:
                free[space].append((start + m, n - m))
            rest = space - each * size
            if rest:
                free[rest].append((start, m))
                open_sizes |= 1 << rest
            open_sizes = open_sizes | 1 << space if free[space] and space < capacity else open_sizes & ~(1 << space)
    return placed, bins


def lower_bound(counts: dict[int, int], capacity: int, most_k: int = 24) -> int:
    """The best of two families of dual-feasible functions.

    The first counts a piece that leaves less than ``e`` as a whole bin, forgets pieces
    below ``e`` and takes the rest at size, for every ``e`` up to half a bin. The second
    rounds ``(k + 1) * size`` down to whole bins and spreads these over ``k``.
    """
    if not counts:
        return 0
    sizes = np.array(sorted(counts), np.int64)
    n = np.array([counts[s] for s in sizes], np.int64)
    best = -(-int((sizes * n).sum()) // capacity)
    for e in [int(s) for s in sizes if 2 * s <= capacity]:
        large, middle = sizes > capacity - e, (sizes >= e) & (sizes <= capacity - e)
        best = max(best, int(n[large].sum()) - (-int((sizes * n)[middle].sum()) // capacity))
    best = max(best, int(n[2 * sizes > capacity].sum()))
    for k in range(1, most_k + 1):
        scaled = (k + 1) * sizes
        value = np.where(scaled % capacity == 0, sizes * k, scaled // capacity * capacity)
        best = max(best, -(-int((value * n).sum()) // (capacity * k)))
    return best


def token_pieces(docs: DataFrame, vocabulary: str, capacity: int = CAPACITY, end_id: int = END_ID, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(part, doc_id, piece, start, length, ids_crc32, rank): rank counts pieces of one
    length within the scan task ``part``."""

    def run(batches):
        from pyspark import TaskContext

        ids_of, part = fast_ids(vocabulary), TaskContext.get().partitionId()
        seen: dict[int, int] = defaultdict(int)
        end = np.array([end_id], np.uint32)
        for b in slices(batches, 1):
            rows = []
            for doc, text in zip(b.column(0).to_pylist(), b.column(1).to_pylist()):
                ids = np.concatenate([ids_of(text), end]).astype("<u4")
                at, piece = 0, 0
                while at < len(ids):
                    to = at + ((len(ids) - at) % capacity or capacity)
                    rows.append((part, doc, piece, at, to - at, zlib.crc32(ids[at:to].tobytes()), seen[to - at]))
                    seen[to - at] += 1
                    at, piece = to, piece + 1
            cols = list(zip(*rows)) or [[]] * 7
            kinds = (pa.int32(), pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.int64())
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds)], names=["part", "doc_id", "piece", "start", "length", "ids_crc32", "rank"])

    schema = "part int, doc_id long, piece int, start long, length long, ids_crc32 long, rank long"
    return docs.select(F.col(id_col).cast("long").alias("doc_id"), as_text(text_col).alias("text")).mapInArrow(run, schema)


_PLAN = "pool long, length long, first_rank long, n long, first_bin long, offset long, bins long, bound long"


def plan_pools(hist: DataFrame, capacity: int) -> DataFrame:
    """Placements of every pool of (pool, length, n); a row without length carries the
    pool's bins and bound."""

    def run(key, rows: pd.DataFrame) -> pd.DataFrame:
        counts = dict(zip(rows["length"].tolist(), rows["n"].tolist()))
        placed, bins = best_fit(counts, capacity)
        out = pd.DataFrame(placed, columns=["length", "first_rank", "n", "first_bin", "offset"], dtype="int64")
        total = pd.DataFrame({"length": [-1], "first_rank": [0], "n": [0], "first_bin": [0], "offset": [0], "bins": [bins], "bound": [lower_bound(counts, capacity)]})
        out = pd.concat([out, total], ignore_index=True)
        out["pool"] = key[0]
        return out[["pool", "length", "first_rank", "n", "first_bin", "offset", "bins", "bound"]].fillna(0).astype("int64")

    summed = hist.groupBy("pool", "length").agg(F.sum("n").cast("long").alias("n"))
    return summed.groupBy("pool").applyInPandas(run, _PLAN)


def certified_plan(hist: DataFrame, capacity: int = CAPACITY, fan_in: int = FAN_IN) -> tuple[DataFrame, DataFrame, dict]:
    """(placements with level, (part, level, pool) of every partition, report) of the
    histogram (part, length, n)."""
    spark = hist.sparkSession
    whole = dict(map(tuple, hist.groupBy("length").agg(F.sum("n").cast("long")).collect()))  # at most `capacity` numbers
    bound = lower_bound(whole, capacity)
    last = hist.agg(F.max("part")).first()[0] or 0
    level, span, open_parts = 0, 1, hist.select("part").distinct()
    plans, homes, report = [], [], {"bound": bound, "levels": []}
    while True:
        pool = F.floor(F.col("part") / span).cast("long")
        made = durable(plan_pools(hist.join(open_parts, "part", "left_semi").withColumn("pool", pool), capacity))
        ends = made.filter("length = -1")
        done = ends.select("pool") if span > last else ends.filter("bins = bound").select("pool")
        at = open_parts.withColumn("pool", pool).join(done, "pool", "left_semi").withColumn("level", F.lit(level))
        homes.append(at.select("part", "level", "pool"))
        plans.append(made.join(done, "pool", "left_semi").withColumn("level", F.lit(level)))
        tally = ends.agg(F.count(F.lit(1)), F.sum(F.when(F.col("bins") == F.col("bound"), 1).otherwise(0)), F.sum("bins"), F.sum("bound")).first()
        report["levels"].append(dict(zip(("pools", "certified", "bins", "bound"), tally)))
        if span > last or tally[0] == tally[1]:
            break
        open_parts = durable(open_parts.withColumn("pool", pool).join(done, "pool", "left_anti").select("part"))
        level, span = level + 1, span * fan_in
    plan, home = plans[0], homes[0]
    for p, h in zip(plans[1:], homes[1:]):
        plan, home = plan.unionByName(p), home.unionByName(h)
    bins = plan.filter("length = -1").agg(F.coalesce(F.sum("bins"), F.lit(0))).first()[0]
    if bins > bound and (placed := best_fit(whole, capacity))[1] < bins:
        bins = placed[1]
        rows = [(0, *p, 0, 0) for p in placed[0]]
        plan = spark.createDataFrame(pd.DataFrame(rows, columns=_PLAN.replace(" long", "").split(", ")), _PLAN).withColumn("level", F.lit(_POOLED))
        home = hist.select("part").distinct().withColumns({"level": F.lit(_POOLED), "pool": F.lit(0).cast("long")})
    return plan.filter("length >= 0"), home, report | {"bins": bins}


def _by_part(plan: DataFrame, hist: DataFrame, home: DataFrame) -> DataFrame:
    """Placements cut at the borders of partitions: ranks become the partition's own."""

    def cut(key, parts: pd.DataFrame, rows: pd.DataFrame) -> pd.DataFrame:
        parts, rows = parts.sort_values("part"), rows.sort_values("first_rank")
        ends = np.cumsum(parts["n"].to_numpy())
        base = ends - parts["n"].to_numpy()
        first = rows["first_rank"].to_numpy()
        stop = first + rows["n"].to_numpy()
        a, b = np.searchsorted(ends, first, "right"), np.searchsorted(base, stop, "left")
        k = np.repeat(np.arange(len(rows)), b - a)
        p = np.arange(len(k)) - np.repeat(np.cumsum(b - a) - (b - a), b - a) + a[k]
        lo, hi = np.maximum(first[k], base[p]), np.minimum(stop[k], ends[p])
        return pd.DataFrame({
            "part": parts["part"].to_numpy()[p], "length": key[2], "first_rank": lo - base[p], "n": hi - lo,
            "first_bin": rows["first_bin"].to_numpy()[k] + lo - first[k], "offset": rows["offset"].to_numpy()[k], "level": key[0], "pool": key[1],
        })

    keys = ["level", "pool", "length"]
    out = "part int, length long, first_rank long, n long, first_bin long, offset long, level int, pool long"
    return hist.join(home, "part").groupBy(*keys).cogroup(plan.groupBy(*keys)).applyInPandas(cut, out)


def pack(docs: DataFrame, vocabulary: str, capacity: int = CAPACITY, end_id: int = END_ID, fan_in: int = FAN_IN, id_col: str = "doc_id", text_col: str = "text", report: dict | None = None) -> DataFrame:
    """doc_id, piece, start, length, ids_crc32, sequence_id, offset of every piece."""
    pieces = durable(token_pieces(docs, vocabulary, capacity, end_id, id_col, text_col))
    hist = durable(pieces.groupBy("part", "length").agg(F.count(F.lit(1)).alias("n")))
    plan, home, said = certified_plan(hist, capacity, fan_in)
    if report is not None:
        report |= said

    def place(rows: pd.DataFrame, cuts: pd.DataFrame) -> pd.DataFrame:
        rows, cuts = rows.sort_values(["length", "rank"]), cuts.sort_values(["length", "first_rank"])
        width = int(max(rows["rank"].max() if len(rows) else 0, cuts["first_rank"].max() if len(cuts) else 0)) + 1
        k = np.searchsorted((cuts["length"] * width + cuts["first_rank"]).to_numpy(), (rows["length"] * width + rows["rank"]).to_numpy(), "right") - 1
        c = cuts.iloc[k].reset_index(drop=True)
        rows = rows.reset_index(drop=True)
        rows["sequence_id"] = c["level"].astype("int64") * (1 << 58) + c["pool"] * (1 << 36) + c["first_bin"] + rows["rank"] - c["first_rank"]
        rows["offset"] = c["offset"]
        return rows[["doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset"]]

    out = "doc_id long, piece int, start long, length long, ids_crc32 long, sequence_id long, offset long"
    cuts = _by_part(plan, hist, home)
    return pieces.groupBy("part").cogroup(cuts.groupBy("part")).applyInPandas(place, out).withColumnRenamed("doc_id", id_col)
