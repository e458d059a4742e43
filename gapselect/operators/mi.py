"""Entropies and joint mutual information of feature sets, per subgroup.

Joint MI is ``H(F) + H(Y) - H(F, Y)``. With counts only three sums of ``c log c`` are
needed per set, so all ways of sharing work below differ only in how the counts of a set
are obtained; the step from counts to MI is the same plan.
"""

from __future__ import annotations

import json
from math import prod

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from gapselect.functions.numbers import clogc
from gapselect.plans.durable import durable
from gapselect.plans.sharing import covering_blocks, plan_sharing
from gapselect.spec import PER_WORD, FeatureSpec, widen

_KEYS = ["sg", "mask", "k0", "k1"]
#: Sets that are carried inside the plan as one literal array; longer lists go as chunks.
CHUNK = 4096
_SET = "struct<m:bigint,w0:bigint,w1:bigint>"


def states(packed: DataFrame) -> int:
    return packed.agg(F.max("y")).first()[0] or 1


def _by_state(q: int) -> list[Column]:
    return [F.sum(F.when(F.col("y") == s, F.col("n")).otherwise(0)).alias(f"n{s}") for s in range(1, q + 1)]


def _resum(q: int) -> list[Column]:
    return [F.sum(f"n{s}").alias(f"n{s}") for s in range(1, q + 1)]


def base_cuboid(packed: DataFrame, q: int) -> DataFrame:
    """Distinct feature cells with one count per target state: the only shuffle whose input
    is the data, combined before it leaves a task. Cells that carry a weight ``n`` count so."""
    weighted = packed if "n" in packed.columns else packed.withColumn("n", F.lit(1).cast("long"))
    return weighted.groupBy("sg", "c0", "c1").agg(*_by_state(q))


def _sets(masks: list[int]) -> list[dict]:
    return [dict(zip(("m", "w0", "w1"), (m, *widen(m)))) for m in masks]


def _array(values: list, kind: str) -> Column:
    """A literal array, made by one call; the optimizer reads the text once for the plan."""
    return F.from_json(F.lit(json.dumps(values)), kind)


def _zipped(masks: list[int]) -> Column:
    return _array(_sets(masks), f"array<{_SET}>")


def _masks_column(masks: list[int]) -> Column:
    return F.explode(_zipped(masks))


def expand(cells: DataFrame, masks: list[int], q: int, only: dict[int, list[int]] | None = None) -> DataFrame:
    """Counts of every set's own cells from cells of supersets; with ``only`` the sets of
    each subgroup."""
    counts = [f"n{s}" for s in range(1, q + 1)]
    parts = []
    for i in range(0, len(masks), CHUNK):
        some = masks[i : i + CHUNK]
        if only is None:
            wide = cells.select("sg", "c0", "c1", *counts, _masks_column(some).alias("w"))
        else:
            here, each = set(some), F.lit(None)
            for g, own in only.items():
                own = [m for m in own if m in here]
                if own:
                    each = F.when(F.col("sg") == g, _zipped(own)).otherwise(each)
            wide = cells.select("sg", "c0", "c1", *counts, F.explode(each).alias("w"))
        keyed = wide.select("sg", F.col("w.m").alias("mask"), F.col("c0").bitwiseAND(F.col("w.w0")).alias("k0"), F.col("c1").bitwiseAND(F.col("w.w1")).alias("k1"), *counts)
        parts.append(keyed.groupBy(*_KEYS).agg(*_resum(q)))
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def counts_unshared(packed: DataFrame, masks: list[int], q: int) -> DataFrame:
    """Nothing shared: every set is counted from the rows alone, one pass over them for every
    set. A task reads its rows once, takes the passes over them in memory and hands on the
    cells of each set."""
    n, states = max(masks).bit_length(), q + 1  # state 0: rows whose target is null or beyond q
    second, weighted = n > PER_WORD, "n" in packed.columns
    # the state goes in the four bits that the first word leaves free: columns cost time on their way to Python
    state = F.when(F.col("y").between(1, q), F.col("y")).otherwise(0).cast("long")
    sent = packed.select("sg", F.col("c0").bitwiseOR(F.shiftleft(state, 4 * PER_WORD)).alias("c0"), *["c1"] * second, *["n"] * weighted)
    out = f"sg {packed.schema['sg'].dataType.simpleString()}, mask long, k0 long, k1 long, {', '.join(f'n{s} long' for s in range(1, q + 1))}"

    def cells(m: int, groups: int, sg, y, c0, c1, codes, w) -> tuple:
        """Subgroup, key words and counts by state of every cell of a set."""
        w0, w1 = widen(m)
        own = [j for j in range(n) if m >> j & 1]
        wide = [int(codes[j].max()) + 1 for j in own]
        if w is None and groups * prod(wide) * states <= 4 * len(y) + 10_000:
            at = sg.astype(np.int64)
            for j, b in zip(own, wide):
                at *= b
                at += codes[j]
            at *= states
            at += y
            by = np.bincount(at, minlength=groups * prod(wide) * states).reshape(-1, states)
            hit = np.flatnonzero(by.any(axis=1))
            g, *values = np.unravel_index(hit, (groups, *wide))
            words = [np.zeros(len(hit), np.int64), np.zeros(len(hit), np.int64)]
            for j, v in zip(own, values):
                words[j // PER_WORD] |= v << 4 * (j % PER_WORD)
            return g, *words, by[hit]
        k0, k1 = c0 & w0, c1 & w1
        order = np.lexsort((k1, k0, sg))
        g, k0, k1 = sg[order], k0[order], k1[order]
        first = np.flatnonzero(np.concatenate([[True], (g[1:] != g[:-1]) | (k0[1:] != k0[:-1]) | (k1[1:] != k1[:-1])]))
        held = np.ones(len(y), np.int64) if w is None else w[order]
        by = np.stack([np.add.reduceat(np.where(y[order] == s, held, 0), first) for s in range(states)], axis=1)
        return g[first], k0[first], k1[first], by

    def count(batches):
        waiting, size = [], 0

        def counted():
            rows = pa.Table.from_batches(waiting)
            found = rows.column("sg").combine_chunks().dictionary_encode("encode")
            sg, (c0, *more) = found.indices.to_numpy(), (rows.column(c).to_numpy() for c in rows.column_names[1:])
            y, c0 = c0 >> 4 * PER_WORD & 0xF, c0 & (1 << 4 * PER_WORD) - 1
            c1, w = more[0] if second else np.zeros_like(c0), more[-1].astype(np.int64) if weighted else None
            codes = [((c0 if j < PER_WORD else c1) >> 4 * (j % PER_WORD) & 0xF).astype(np.uint8) for j in range(n)]
            made, room = [], COUNTED
            for i, m in enumerate(masks):
                g, k0, k1, by = cells(m, len(found.dictionary), sg, y, c0, c1, codes, w)
                made.append((g, np.full(len(g), m, np.int64), k0, k1, *by.T[1:]))
                room -= len(g)
                if room <= 0 or i == len(masks) - 1:
                    g, *rest = (np.concatenate(x) for x in zip(*made))
                    yield pa.RecordBatch.from_arrays([found.dictionary.take(pa.array(g)), *map(pa.array, rest)], ["sg", "mask", "k0", "k1", *(f"n{s}" for s in range(1, q + 1))])
                    made, room = [], COUNTED

        for b in batches:
            waiting.append(b)
            size += b.num_rows
            if size >= COUNTED:
                yield from counted()
                waiting, size = [], 0
        if size:
            yield from counted()

    return sent.mapInArrow(count, out).groupBy(*_KEYS).agg(*_resum(q))


def counts_cuboid(packed: DataFrame, masks: list[int], q: int, only: dict[int, list[int]] | None = None) -> DataFrame:
    return expand(base_cuboid(packed, q), masks, q, only)


def _block_cells(packed: DataFrame, masks: list[int], q: int, n: int, block_size: int, only: dict[int, list[int]] | None) -> tuple[DataFrame, list[tuple[int, list[int]]]]:
    """Cells of features in overlapping blocks so that every set lies in one, and (block,
    its sets) by the number in column ``block``. With ``only`` each subgroup has blocks
    for its own sets."""
    weight = F.col("n") if "n" in packed.columns else F.lit(1).cast("long")
    each, blocks = F.lit(None), []
    for g, own in ({None: masks} if only is None else only).items():
        some = covering_blocks(n, own, block_size)
        here = _array([{"i": len(blocks) + i, **w} for i, w in enumerate(_sets([b for b, _ in some]))], "array<struct<i:int,w0:bigint,w1:bigint>>")
        blocks += some
        if some:
            each = here if g is None else F.when(F.col("sg") == g, here).otherwise(each)
    rows = packed.select("sg", "y", "c0", "c1", weight.alias("n"), F.explode(each).alias("w"))
    cells = rows.select("sg", "y", "n", F.col("w.i").alias("block"), F.col("c0").bitwiseAND(F.col("w.w0")).alias("c0"), F.col("c1").bitwiseAND(F.col("w.w1")).alias("c1"))
    return cells.groupBy("sg", "block", "c0", "c1").agg(*_by_state(q)), blocks


def counts_blocks(packed: DataFrame, masks: list[int], q: int, n: int, block_size: int = 6, only: dict[int, list[int]] | None = None) -> DataFrame:
    """Each block has a cuboid of bounded size, so the shuffle does not grow with the rows."""
    cells, blocks = _block_cells(packed, masks, q, n, block_size, only)
    counts = [f"n{s}" for s in range(1, q + 1)]
    inside = F.get(_array([_sets(own) for _, own in blocks], f"array<array<{_SET}>>"), F.col("block"))  # a block's sets by its number
    wide = cells.select("sg", "c0", "c1", *counts, F.explode(inside).alias("w"))
    keyed = wide.select("sg", F.col("w.m").alias("mask"), F.col("c0").bitwiseAND(F.col("w.w0")).alias("k0"), F.col("c1").bitwiseAND(F.col("w.w1")).alias("k1"), *counts)
    return keyed.groupBy(*_KEYS).agg(*_resum(q))


def constructs_blocks(packed: DataFrame, masks: list[int], q: int, n: int, block_size: int = 6, only: dict[int, list[int]] | None = None, log_base: str = "2") -> DataFrame:
    """What :func:`constructs` gives, without cells of sets as rows: one task holds a block of
    a subgroup (at most 9 ** ``block_size`` cells) and sums up all its sets."""
    cells, blocks = _block_cells(packed, masks, q, n, block_size, only)
    counts, log = [f"n{s}" for s in range(1, q + 1)], np.log2 if log_base == "2" else np.log

    def xlogx(x: np.ndarray) -> float:
        x = x[x > 0]
        return float((x * log(x)).sum())

    def run(key, pdf: pd.DataFrame) -> pd.DataFrame:
        block, own = blocks[int(key[1])]
        by = pdf[counts].to_numpy(np.float64).T
        total = by.sum(axis=1)
        size, s_y = total.sum(), xlogx(total)
        codes = {j: pdf[f"c{j // PER_WORD}"].to_numpy() >> 4 * (j % PER_WORD) & 0xF for j in range(n) if block >> j & 1}
        wide = {j: int(c.max()) + 1 for j, c in codes.items()}
        out = []
        for m in own:
            at, bins = np.zeros(len(pdf), np.int64), 1
            for j, c in codes.items():
                if m >> j & 1:
                    at, bins = at * wide[j] + c, bins * wide[j]
            if bins > 4 * len(pdf) + 10_000:
                at = np.unique(at, return_inverse=True)[1]
            both = np.stack([np.bincount(at, x) for x in by])
            each = both.sum(axis=0)
            out.append((int(key[0]), m, int(size), xlogx(each), s_y, xlogx(both), int((each > 0).sum()), int((total > 0).sum()), int((both > 0).sum())))
        got = pd.DataFrame(out, columns=["sg", "mask", "n", "h_f", "h_y", "h_fy", "cells_f", "cells_y", "cells_fy"])
        for h in ("h_f", "h_y", "h_fy"):
            got[h] = log(size) - got[h] / size
        return got

    return cells.groupBy("sg", "block").applyInPandas(run, "sg int, mask long, n long, h_f double, h_y double, h_fy double, cells_f long, cells_y int, cells_fy long")


#: Bytes of counts that a task may hold, and rows that it counts at a time.
MOST_COUNTS, COUNTED = 64 << 20, 1 << 18


def shape_of(packed: DataFrame, n: int) -> tuple[int, int, list[int]]:
    """Target states, subgroups, and codes of every feature with null, in one pass."""
    fields = [F.shiftright(F.col(f"c{j // PER_WORD}"), 4 * (j % PER_WORD)).bitwiseAND(F.lit(0xF)) for j in range(n)]
    row = packed.agg(F.max("y"), F.approx_count_distinct("sg"), *[F.max(f) for f in fields]).first()
    return row[0] or 1, row[1], [int(x or 0) + 1 for x in row[2:]]


def _layout(masks: list[int], q: int, bins: list[int]) -> dict[int, int]:
    """Counts that each set has: its cells times the target states."""
    return {m: q * prod(b for j, b in enumerate(bins) if m >> j & 1) for m in masks}


def constructs_in_tasks(packed: DataFrame, masks: list[int], q: int, bins: list[int], only: dict[int, list[int]] | None = None, log_base: str = "2") -> DataFrame:
    """What :func:`constructs` gives for sets of few cells: a task counts all sets of its rows in
    arrays and hands on only these, so no row is made per set or block. Counts of a subgroup
    come together in parts of about a megabyte."""
    n, log = len(bins), np.log2 if log_base == "2" else np.log
    sizes = _layout(masks, q, bins)
    lists = {None: sorted(masks)} if only is None else {g: sorted(own) for g, own in only.items()}

    def by_prefix(own):  # a set after those it begins with
        return sorted(own, key=lambda m: [j for j in range(n) if m >> j & 1])

    parts: dict[int | None, list[list[int]]] = {}
    for g, own in lists.items():
        parts[g], room = [], 0
        for m in by_prefix(own):
            if room < sizes[m]:
                parts[g].append([])
                room = 1 << 17
            parts[g][-1].append(m)
            room -= sizes[m]
    weighted = "n" in packed.columns
    names = ["sg", "y", "c0", "c1"] + ["n"] * weighted

    def count(batches):
        held: dict[int, dict[int, np.ndarray]] = {}
        waiting, size = [], 0

        def add():
            cols = [np.concatenate([b.column(c).to_numpy(zero_copy_only=False) for b in waiting]).astype(np.int64) for c in names]
            for g in np.unique(cols[0]):
                own = parts.get(None, parts.get(int(g), []))
                rows = np.flatnonzero(cols[0] == g)
                y, c0, c1, *w = (c[rows] for c in cols[1:])
                codes = [(c0 if j < PER_WORD else c1) >> 4 * (j % PER_WORD) & 0xF for j in range(n)]
                total = held.setdefault(int(g), {})
                path: list[tuple[int, np.ndarray]] = [(-1, y - 1)]  # features so far, with the place of each row
                for m in (m for part in own for m in part):
                    bits = [j for j in range(n) if m >> j & 1]
                    keep = 0
                    while keep < min(len(path) - 1, len(bits) - 1) and path[keep + 1][0] == bits[keep]:
                        keep += 1
                    del path[keep + 1 :]
                    for j in bits[keep:]:
                        path.append((j, path[-1][1] * bins[j] + codes[j]))
                    got = np.bincount(path[-1][1], *w, minlength=sizes[m]).astype(np.int64)
                    total[m] = total[m] + got if m in total else got

        for b in batches:
            waiting.append(b)
            size += b.num_rows
            if size >= COUNTED:
                add()
                waiting, size = [], 0
        if size:
            add()
        for g, total in held.items():
            for i, part in enumerate(parts.get(None, parts.get(g, []))):
                yield pa.RecordBatch.from_pylist([{"sg": g, "part": i, "counts": np.concatenate([total[m] for m in part]).tobytes()}], pa.schema([("sg", pa.int32()), ("part", pa.int32()), ("counts", pa.binary())]))

    def xlogx(x: np.ndarray) -> float:
        x = x[x > 0]
        return float((x * log(x)).sum())

    def run(key, pdf: pd.DataFrame) -> pd.DataFrame:
        g, own = int(key[0]), parts.get(None, parts.get(int(key[0])))[int(key[1])]
        every = np.zeros(sum(sizes[m] for m in own), np.int64)
        for x in pdf["counts"]:
            every += np.frombuffer(x, np.int64)
        out, at = [], 0
        for m in own:
            both = every[at : at + sizes[m]].astype(np.float64).reshape(q, -1)
            at += sizes[m]
            each, total = both.sum(axis=0), both.sum(axis=1)
            size = total.sum()
            out.append((g, m, int(size), *[log(size) - xlogx(x) / size for x in (each, total, both)], int((each > 0).sum()), int((total > 0).sum()), int((both > 0).sum())))
        return pd.DataFrame(out, columns=["sg", "mask", "n", "h_f", "h_y", "h_fy", "cells_f", "cells_y", "cells_fy"])

    counted = packed.select(*names).mapInArrow(count, "sg int, part int, counts binary")
    return counted.groupBy("sg", "part").applyInPandas(run, "sg int, mask long, n long, h_f double, h_y double, h_fy double, cells_f long, cells_y int, cells_fy long")


def counts_rollup(packed: DataFrame, masks: list[int], q: int, n: int) -> DataFrame:
    """Level by level downward: every set from one set with a feature more, which has
    already been counted; of these the one with the fewest cells."""
    wanted = set(masks)
    levels = sorted({m.bit_count() for m in wanted}, reverse=True)
    cells = base_cuboid(packed, q)
    top = levels[0]
    need = {top: sorted(m for m in wanted if m.bit_count() == top)}
    now = durable(expand(cells, need[top], q))
    out = now
    counts = [f"n{s}" for s in range(1, q + 1)]
    for level in range(top - 1, levels[-1] - 1, -1):
        children = sorted(m for m in wanted if m.bit_count() == level)
        sizes = {r["mask"]: r["n"] for r in now.groupBy("mask").agg(F.count(F.lit(1)).alias("n")).collect()}  # one number per set
        plan: dict[int, list[int]] = {}
        alone = []
        for c in children:
            parents = [c | 1 << j for j in range(n) if not c >> j & 1 and (c | 1 << j) in sizes]
            plan.setdefault(min(parents, key=lambda p: (sizes[p], p)), []).append(c) if parents else alone.append(c)
        made = None
        if plan:
            pick = F.lit(None)
            for p, cs in plan.items():
                pick = F.when(F.col("mask") == p, _zipped(cs)).otherwise(pick)
            wide = now.select("sg", "k0", "k1", *counts, F.explode(pick).alias("w"))
            made = wide.select("sg", F.col("w.m").alias("mask"), F.col("k0").bitwiseAND(F.col("w.w0")).alias("k0"), F.col("k1").bitwiseAND(F.col("w.w1")).alias("k1"), *counts).groupBy(*_KEYS).agg(*_resum(q))
        if alone:
            extra = expand(cells, alone, q)
            made = extra if made is None else made.unionByName(extra)
        now = durable(made)
        out = out.unionByName(now)
    return out


def counts_grouping_sets(packed: DataFrame, masks: list[int], q: int, spec: FeatureSpec) -> DataFrame:
    """All sets as one GROUPING SETS query, in chunks of 64. Equal rows are combined before
    they are expanded."""
    from gapselect.operators.prep import unpack

    rows = unpack(base_cuboid(packed, q).withColumn("y", F.lit(None)), spec)
    parts = []
    for i in range(0, len(masks), 64):
        chunk = masks[i : i + 64]
        cols = [F.col(f) for f in spec.features]
        sets = [[F.col("sg"), *[cols[j] for j in range(spec.n) if m >> j & 1]] for m in chunk]
        out = rows.groupingSets(sets, F.col("sg"), *cols).agg(F.grouping_id().alias("gid"), *_resum(q))
        # grouping_id: one bit per column, first column highest, set where it is rolled away
        mask = F.lit(0).cast("long")
        for j in range(spec.n):
            mask = mask.bitwiseOR(F.when(F.shiftright("gid", spec.n - 1 - j).bitwiseAND(F.lit(1)) == 0, F.lit(1 << j).cast("long")).otherwise(F.lit(0).cast("long")))
        words = [F.lit(0).cast("long"), F.lit(0).cast("long")]
        for j, f in enumerate(spec.features):
            words[j // 15] = words[j // 15].bitwiseOR(F.coalesce(F.shiftleft(F.col(f).cast("long"), 4 * (j % 15)), F.lit(0).cast("long")))
        parts.append(out.select("sg", mask.alias("mask"), words[0].alias("k0"), words[1].alias("k1"), *[f"n{s}" for s in range(1, q + 1)]))
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def constructs(counts: DataFrame, q: int, log_base: str = "2", null_policy: str = "category", n: int = 30) -> DataFrame:
    """(sg, mask, n, h_f, h_y, h_fy, cells_f, cells_y, cells_fy): entropies from counts."""
    if null_policy == "complete_case":
        for j in range(n):
            held = F.shiftright(F.col(f"k{j // 15}"), 4 * (j % 15)).bitwiseAND(F.lit(0xF)) == 0
            counts = counts.filter(~((F.col("mask").bitwiseAND(F.lit(1 << j)) != 0) & held))
    elif null_policy != "category":
        raise ValueError(f"unknown null policy {null_policy}")
    each = [F.col(f"n{s}") for s in range(1, q + 1)]
    c = sum(each[1:], each[0])
    sums = [F.sum(f"n{s}").alias(f"n{s}") for s in range(1, q + 1)]
    both = sum([clogc(e, log_base) for e in each[1:]], clogc(each[0], log_base))
    filled = sum([F.when(e > 0, 1).otherwise(0) for e in each[1:]], F.when(each[0] > 0, 1).otherwise(0))
    some = counts.groupBy("sg", "mask").agg(
        F.sum(c).alias("n"), F.sum(clogc(c, log_base)).alias("s_f"), F.sum(both).alias("s_fy"), *sums, F.count(F.lit(1)).alias("cells_f"), F.sum(filled).alias("cells_fy")
    )
    s_y = sum([clogc(F.col(f"n{s}"), log_base) for s in range(2, q + 1)], clogc(F.col("n1"), log_base))
    cells_y = sum([F.when(F.col(f"n{s}") > 0, 1).otherwise(0) for s in range(2, q + 1)], F.when(F.col("n1") > 0, 1).otherwise(0))
    top = clogc(F.col("n"), log_base) / F.col("n")
    return some.select(
        "sg", "mask", "n", (top - F.col("s_f") / F.col("n")).alias("h_f"), (top - s_y / F.col("n")).alias("h_y"), (top - F.col("s_fy") / F.col("n")).alias("h_fy"),
        "cells_f", cells_y.alias("cells_y"), "cells_fy",
    )


def mi_from(built: DataFrame, estimator: str = "plugin", log_base: str = "2") -> DataFrame:
    """(sg, mask, level, mi, n): plug-in, Miller-Madow corrected, normalised by H(Y), or the
    G statistic ``2 N ln(2) I``."""
    raw = F.greatest(F.col("h_f") + F.col("h_y") - F.col("h_fy"), F.lit(0.0))
    unit = F.log(F.lit(2.0)) if log_base == "2" else F.lit(1.0)
    value = {
        "plugin": raw,
        "miller_madow": F.greatest(raw + (F.col("cells_f") + F.col("cells_y") - F.col("cells_fy") - 1) / (2 * F.col("n") * unit), F.lit(0.0)),
        "normalised": F.when(F.col("h_y") > 0, raw / F.col("h_y")).otherwise(F.lit(0.0)),
        "g": 2 * F.col("n") * raw * unit,
    }[estimator]
    return built.select("sg", F.col("mask").cast("long").alias("mask"), F.bit_count("mask").cast("int").alias("level"), value.alias("mi"), "n")


def _size(masks: list[int], block_size: int | None = None) -> int:
    """Features a block: small sets fill small cuboids, which stay in a task's memory."""
    deepest = max(m.bit_count() for m in masks)
    return max(block_size or {1: 2, 2: 4}.get(deepest, 6), deepest)


def lattice_counts(packed: DataFrame, spec: FeatureSpec, masks: list[int], sharing: str = "auto", block_size: int | None = None, q: int | None = None, only: dict[int, list[int]] | None = None) -> tuple[DataFrame, int]:
    """Counts of every set's cells. ``auto`` lets :func:`plan_sharing` choose, by the pass
    that also finds the number of target states. ``only`` (sets of each subgroup) restricts
    what is counted."""
    if sharing == "auto":
        plan = plan_sharing(packed, masks, spec.n)
        sharing, q = plan["sharing"], q or plan["n_states"]
    q = q or states(packed)
    if only is not None and sharing not in ("cuboid", "blocks"):
        counts, _ = lattice_counts(packed, spec, masks, sharing, block_size, q)
        wanted = F.lit(False)
        for g, own in only.items():
            wanted = F.when(F.col("sg") == g, F.col("mask").isin(own)).otherwise(wanted)
        return counts.filter(wanted), q
    if sharing == "none":
        return counts_unshared(packed, masks, q), q
    if sharing == "cuboid":
        return counts_cuboid(packed, masks, q, only), q
    if sharing == "rollup":
        return counts_rollup(packed, masks, q, spec.n), q
    if sharing == "blocks":
        return counts_blocks(packed, masks, q, spec.n, _size(masks, block_size), only), q
    if sharing == "grouping_sets":
        return counts_grouping_sets(packed, masks, q, spec), q
    raise ValueError(f"unknown sharing {sharing}")


def lattice_mi(packed: DataFrame, spec: FeatureSpec, masks: list[int], sharing: str = "auto", estimator: str = "plugin", log_base: str = "2", null_policy: str = "category", only: dict[int, list[int]] | None = None, q: int | None = None, shape: tuple[int, int, list[int]] | None = None) -> DataFrame:
    """``shape`` is what :func:`shape_of` gives, if it is known."""
    if sharing == "auto" and null_policy == "category":
        seen, groups, bins = shape or shape_of(packed, spec.n)
        q = q or seen
        own = masks if only is None else [m for some in only.values() for m in some]
        sizes = _layout(masks, q, bins)
        if q >= seen and 8 * sum(sizes[m] for m in own) * (groups if only is None else 1) <= MOST_COUNTS:
            return mi_from(constructs_in_tasks(packed, masks, q, bins, only, log_base), estimator, log_base)
    if sharing == "auto":
        plan = plan_sharing(packed, masks, spec.n)
        sharing, q = plan["sharing"], q or plan["n_states"]
    if sharing == "blocks" and null_policy == "category" and _size(masks) <= 6:
        return mi_from(constructs_blocks(packed, masks, q or states(packed), spec.n, _size(masks), only, log_base), estimator, log_base)
    counts, q = lattice_counts(packed, spec, masks, sharing, q=q, only=only)
    return mi_from(constructs(counts, q, log_base, null_policy, spec.n), estimator, log_base)


def computable(mi: DataFrame, missing: dict[int, int]) -> DataFrame:
    """Rows whose set holds no feature that its subgroup lacks."""
    lacking = F.lit(0).cast("long")
    for sg, m in missing.items():
        lacking = F.when(F.col("sg") == sg, F.lit(m).cast("long")).otherwise(lacking)
    return mi.filter(F.col("mask").bitwiseAND(lacking) == 0)


def joint_mi_direct(df: DataFrame, cols: list[str], target: str = "y", by: str = "sg") -> DataFrame:
    """The double sum ``p(f, y) log p(f, y) / (p(f) p(y))``: a cross-check of the sums."""
    from pyspark.sql import Window

    joint = df.groupBy(by, *cols, target).agg(F.count(F.lit(1)).alias("c"))
    over = joint.withColumns({
        "cf": F.sum("c").over(Window.partitionBy(by, *cols)), "cy": F.sum("c").over(Window.partitionBy(by, target)), "n": F.sum("c").over(Window.partitionBy(by)),
    })
    return over.groupBy(by).agg(F.sum(F.col("c") / F.col("n") * F.log2(F.col("c") * F.col("n") / (F.col("cf") * F.col("cy")))).alias("mi"))


def entropy(df: DataFrame, cols: list[str], by: str = "sg") -> DataFrame:
    cells = df.groupBy(by, *cols).agg(F.count(F.lit(1)).alias("c"))
    return cells.groupBy(by).agg((F.log2(F.sum("c")) - F.sum(clogc(F.col("c"))) / F.sum("c")).alias("h"))


def cond_entropy(df: DataFrame, f: str, given: list[str], by: str = "sg") -> DataFrame:
    """H(f | given) by the chain rule."""
    return entropy(df, [*given, f], by).withColumnRenamed("h", "a").join(entropy(df, given, by).withColumnRenamed("h", "b"), by).select(by, (F.col("a") - F.col("b")).alias("h"))


def chain_rule(df: DataFrame, order: list[str], by: str = "sg") -> DataFrame:
    """H of all columns rebuilt from one singleton and conditionals; same for any order."""
    out = entropy(df, order[:1], by)
    for k in range(1, len(order)):
        step = cond_entropy(df, order[k], order[:k], by).withColumnRenamed("h", "more")
        out = out.join(step, by).select(by, (F.col("h") + F.col("more")).alias("h"))
    return out


def co_information(df: DataFrame, cols: list[str], target: str = "y", by: str = "sg") -> DataFrame:
    """Signed sum of joint entropies over all subsets of features and target: equals MI for
    one feature, and is another quantity beyond (it can be negative)."""
    names = [*cols, target]
    total = None
    for m in range(1, 1 << len(names)):
        part = [c for j, c in enumerate(names) if m >> j & 1]
        h = entropy(df, part, by).select(by, ((-1.0) ** (len(part) + 1) * F.col("h")).alias("h"))
        total = h if total is None else total.unionByName(h)
    return total.groupBy(by).agg(F.sum("h").alias("co_information"))
