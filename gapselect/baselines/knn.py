"""Imputation baselines on packed cells: nearest neighbours, modes, a hashed variant.

Rows that agree in all features are one cell with a weight, so the nested loop runs over
cells, not rows. Distance is the number of features that differ; null is a state of its own
(``mismatch``) or is left out on either side (``ignore``). Donors of a feature are cells in
which it is present; neighbours come in order of (distance, donor cell), the last one cut
to what is missing of ``k``; the mode of their values is taken, ties to the smallest code.
All imputed values come from original data.
"""

from __future__ import annotations

from dataclasses import dataclass
from itertools import combinations
from math import comb
from urllib.parse import unquote, urlparse

import numpy as np
import pandas as pd
from pyarrow import fs, parquet
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gapselect.plans.durable import stored
from gapselect.spec import PER_WORD, FeatureSpec, widen

#: Donor cells that a task holds at a time; more are gone through in blocks of so many.
MOST_DONORS = 1_000_000
#: Cells of one side of a bucket that meet in one group.
BLOCK = 4096
_LOW = np.int64(0x1111111111111111)


def cells_of(packed: DataFrame) -> DataFrame:
    n = F.sum("n") if "n" in packed.columns else F.count(F.lit(1))
    return packed.groupBy("sg", "c0", "c1", "y").agg(n.cast("long").alias("n"))


def _gap(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    x = a ^ b
    x = (x | x >> 1 | x >> 2 | x >> 3) & _LOW
    return np.bitwise_count(x.astype(np.uint64)).astype(np.int32)


def _held(a: np.ndarray) -> np.ndarray:
    return (a | a >> 1 | a >> 2 | a >> 3) & _LOW


def distances(c0, c1, d0, d1, how: str, within: tuple[int, int]) -> np.ndarray:
    """Receivers x donors."""
    out = 0
    for c, d, w in ((c0, d0, within[0]), (c1, d1, within[1])):
        c, d = c[:, None] & np.int64(w), d[None, :] & np.int64(w)
        if how == "mismatch":
            out = out + _gap(c, d)
        elif how == "ignore":
            x = c ^ d
            x = (x | x >> 1 | x >> 2 | x >> 3) & _LOW & _held(c) & _held(d)
            out = out + np.bitwise_count(x.astype(np.uint64)).astype(np.int32)
        else:
            raise ValueError(f"unknown null distance {how}")
    return out


#: Receivers and donors compared at a time: their distances stay in a core's cache.
TILE = (24, 8192)


def nearest(c0, c1, d0, d1, how: str, within: tuple[int, int], absents: list[np.ndarray], k: int) -> list[tuple[np.ndarray, np.ndarray]]:
    """For every set of ``absent`` donors (distances, donors) of the ``k`` nearest others of
    each receiver, in order of (distance, donor); 255 where there are fewer. Distances are
    bytes and made once; tile by tile the smallest is taken ``k`` times, the first of
    equal ones."""
    if how not in ("mismatch", "ignore"):
        raise ValueError(f"unknown null distance {how}")
    out = [(np.full((len(c0), k), 255, np.uint8), np.zeros((len(c0), k), np.int64)) for _ in absents]
    words = [(c & np.int64(w), d & np.int64(w)) for c, d, w in ((c0, d0, within[0]), (c1, d1, within[1])) if w]
    closed = [np.where(x, 255, 0).astype(np.uint8) for x in absents]
    for i in range(0, len(c0), TILE[0]):
        rows = slice(i, min(len(c0), i + TILE[0]))
        at = np.arange(rows.stop - i)
        for j in range(0, len(d0), TILE[1]):
            cols = slice(j, min(len(d0), j + TILE[1]))
            total = np.zeros((len(at), cols.stop - j), np.uint8)
            for c, d in words:
                a, b = c[rows, None], d[None, cols]
                x = a ^ b
                x |= x >> 1
                x |= x >> 2
                x &= _LOW
                if how == "ignore":
                    x &= _held(a)
                    x &= _held(b)
                total += np.bitwise_count(x.view(np.uint64))
            for (best, who), shut in zip(out, closed):
                dist = total | shut[None, cols]
                found, found_who = [best[rows]], [who[rows]]
                for _ in range(min(k, dist.shape[1])):
                    pick = dist.argmin(axis=1)
                    value = dist[at, pick]
                    if (value >= found[0][:, -1]).all():  # nothing nearer than what is held
                        break
                    found.append(value[:, None])
                    found_who.append(pick[:, None] + j)
                    dist[at, pick] = 255
                if len(found) > 1:
                    found, found_who = np.concatenate(found, axis=1), np.concatenate(found_who, axis=1)
                    order = np.argsort(found, axis=1, kind="stable")[:, :k]
                    best[rows], who[rows] = np.take_along_axis(found, order, 1), np.take_along_axis(found_who, order, 1)
    return out


#: Null patterns up to which donors are searched by pattern; data of more is compared cell by cell.
MOST_PATTERNS = 64
#: Pairs (receiver, donor) kept between two clean-ups of a search.
PAIRS = 4_000_000
_END = np.iinfo(np.int64).max


def _code(c0: np.ndarray, c1: np.ndarray, j: int) -> np.ndarray:
    return (c0 if j < PER_WORD else c1) >> 4 * (j % PER_WORD) & 0xF


def _lacking(c0: np.ndarray, c1: np.ndarray, n: int) -> np.ndarray:
    """Mask of the null features of each cell."""
    out = np.zeros(len(c0), np.int64)
    for j in range(n):
        out |= (_code(c0, c1, j) == 0).astype(np.int64) << j
    return out


def _firsts(sorted_ids: np.ndarray) -> np.ndarray:
    """Place of each element within its run of equal ones."""
    start = np.flatnonzero(np.r_[True, sorted_ids[1:] != sorted_ids[:-1]]) if len(sorted_ids) else np.zeros(0, np.int64)
    return np.arange(len(sorted_ids)) - np.repeat(start, np.diff(np.r_[start, len(sorted_ids)]))


class _Class:
    """Donors of one null pattern before receivers of another. Features held by both sides are
    laid out in one word; all others add the same ``base`` to every distance."""

    def __init__(self, lacks: int, gone: int, within: int, n: int, how: str):
        self.serves = [j for j in range(n) if gone >> j & 1 and not lacks >> j & 1]
        self.base = (within & (gone ^ lacks)).bit_count() if how == "mismatch" else 0
        self.shared = [j for j in range(n) if (within & ~gone & ~lacks) >> j & 1]

    def meet(self, who: np.ndarray, r: tuple, d: tuple) -> None:
        """The donors ``who`` of ``d`` before the receivers ``r``; compared in shared features."""
        self.who, w = who, widen(sum(1 << j for j in self.shared))
        self.cells, self.mine = tuple(x[who] & np.int64(y) for x, y in zip(d, w)), tuple(x & np.int64(y) for x, y in zip(r, w))
        bits = [int(max(_code(*x, j).max(initial=0) for x in (self.cells, self.mine))).bit_length() for j in self.shared]
        self.at = len(who).bit_length()
        self.fits = sum(bits) + max(self.at, len(r[0]).bit_length()) < 63
        self.words, self.fields, shift = [np.zeros(len(r[0]), np.int64), np.zeros(len(who), np.int64)], [], 0
        for j, b in zip(self.shared, bits if self.fits else ()):
            for word, cells in zip(self.words, (self.mine, self.cells)):
                word |= _code(*cells, j) << shift
            self.fields.append((1 << b) - 1 << shift)
            shift += b

    def scan(self, rows: np.ndarray, how: str, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(receiver, distance, donor) of the ``k`` nearest donors, in shared features."""
        ((far, near),) = nearest(self.mine[0][rows], self.mine[1][rows], *self.cells, how, (-1, -1), [np.zeros(len(self.who), bool)], k)
        a, b = np.nonzero(far < 255)
        return rows[a], far[a, b].astype(np.int64), near[a, b]

    def at_distance(self, t: int, rows: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
        """(receiver, donor) that differ in ``t`` shared features: the ``k`` first donors of each
        receiver. Whoever differs in ``t`` features agrees in all others, so for each choice of
        others only the ``k`` first donors with the same values are looked up; of these fewer
        than ``k`` are nearer, and those were found before."""
        at, low = self.at, np.int64((1 << self.at) - 1)
        here = len(rows).bit_length()
        low_r, most = np.int64((1 << here) - 1), np.full(len(rows), _END)
        donors, wants = self.words[1] << at | np.arange(len(self.who)), self.words[0][rows] << here | np.arange(len(rows))
        x = np.full(len(donors) + 1, _END)
        open_, size, held = [], 0, np.zeros(0, np.int64)

        def clean(held):
            q = np.sort(np.concatenate([held, *open_]))
            q = q[np.r_[True, q[1:] != q[:-1]]] if len(q) else q
            if t:
                a, b = rows[q >> at], q & low
                gap = sum(_gap(self.mine[w][a], self.cells[w][b]) for w in (0, 1))
                q = q[gap == t]
            q = q[_firsts(q >> at) < k]
            full = np.flatnonzero(_firsts(q >> at) == k - 1)
            most[q[full] >> at] = q[full] & low
            return q

        every = sum(self.fields)
        for differ in combinations(self.fields, t):
            keep = every - sum(differ)
            x[:-1] = donors & np.int64(keep << at | int(low))
            x[:-1].sort()
            y = np.sort(wants & np.int64(keep << here | int(low_r)))
            who, key = y & low_r, y >> here
            place = np.searchsorted(x, key << at)
            for _ in range(k):
                found = x[place]
                ok = np.flatnonzero((found >> at == key) & ((found & low) < most[who]))
                if not len(ok):
                    break
                who, key, place = who[ok], key[ok], place[ok] + 1
                open_.append(who << at | found[ok] & low)
                size += len(ok)
            if size > PAIRS:
                held, size = clean(held), 0
                open_.clear()
        q = clean(held)
        return rows[q >> at], q & low


#: Bits of a key that hold a donor's number; its distance lies above.
_NUMBER = 48


class _Search:
    """Receivers that lack the features ``gone`` and, for each of these, their ``k`` nearest
    donors so far: keys (distance, number of the donor in the order of cells), codes, weights."""

    def __init__(self, c0: np.ndarray, c1: np.ndarray, gone: int, n: int, how: str, within: tuple[int, int], k: int):
        if how not in ("mismatch", "ignore"):
            raise ValueError(f"unknown null distance {how}")
        self.gone, self.n, self.how, self.k = gone, n, how, k
        self.within = sum(1 << j for j in range(n) if within[j // PER_WORD] >> 4 * (j % PER_WORD) & 0xF)
        held = [np.int64(w & h) for w, h in zip(within, widen(~gone & (1 << n) - 1))]
        self.limits, self.r = within, (c0 & held[0], c1 & held[1])
        self.best = {j: (np.full((len(c0), k), _END), np.zeros((len(c0), k), np.uint8), np.zeros((len(c0), k), np.uint8)) for j in range(n) if gone >> j & 1}
        self.classes: dict[int, _Class] = {}
        self.done: dict[int, np.ndarray] = {}
        self.scans: dict[int, np.ndarray] = {}

    def _open(self, j: int, before: int) -> np.ndarray:
        """Receivers whose ``k`` are not full with keys below ``before``."""
        key, _, weight = self.best[j]
        return (weight * (key < before)).sum(axis=1) < self.k

    def _class(self, lacks: int) -> _Class:
        if lacks not in self.classes:
            self.classes[lacks] = _Class(lacks, self.gone, self.within, self.n, self.how)
        return self.classes[lacks]

    def wants(self, distance: int, kinds: set[int] | None) -> bool:
        """Whether donors of these null patterns can be met at this distance."""
        if kinds is None:
            return distance == 0
        able = [self._class(p) for p in kinds]
        able = {j for c in able if 0 <= distance - c.base <= len(c.shared) for j in c.serves}
        return any(self._open(j, distance << _NUMBER).any() for j in able)

    def start(self) -> None:
        self.scans = {}

    def meet(self, distance: int, start: int, d: tuple, dn: np.ndarray, patterns: dict[int, np.ndarray]) -> None:
        """Donors at ``distance`` in one block, whose first has the number ``start``. Receivers
        that are few against a block's choices are compared with all donors of a pattern
        instead, in all blocks of the round, and are then done with the pattern."""
        for p, who in patterns.items():
            c = self._class(p)
            t = distance - c.base
            if not c.serves or not 0 <= t <= len(c.shared):
                continue
            done = self.done.setdefault(p, np.zeros(len(self.r[0]), bool))
            if p in self.scans:
                rows = self.scans[p]
            else:  # a pattern that is scanned is scanned from its first block of the round on
                rows = np.flatnonzero(~done & np.any([self._open(j, distance << _NUMBER) for j in c.serves], axis=0))
                choices = comb(len(c.shared), t)
                few = len(rows) * len(who) <= 4 * choices * (len(rows) + len(who))
                self.scans[p] = rows = rows if few else None
            if rows is None:
                rows = np.flatnonzero(~done & np.any([self._open(j, distance << _NUMBER | start) for j in c.serves], axis=0))
            if not len(rows):
                continue
            c.meet(who, self.r, d)
            if self.scans[p] is not None or not c.fits:
                a, far, b = c.scan(rows, self.how, self.k)
                ok = far >= t if self.scans[p] is not None else far == t
                a, far, b = a[ok], far[ok], b[ok]
            else:
                a, b = c.at_distance(t, rows, self.k)
                far = np.full(len(a), t)
            self._add(c.serves, a, far + c.base, c.who[b], start, d, dn)

    def meet_all(self, start: int, d: tuple, dn: np.ndarray) -> None:
        """All donors of a block, whatever they lack."""
        for j in self.best:
            ((far, near),) = nearest(*self.r, *d, self.how, self.limits, [_code(*d, j) == 0], self.k)
            a, b = np.nonzero(far < 255)
            self._add([j], a, far[a, b].astype(np.int64), near[a, b], start, d, dn)

    def end(self) -> None:
        for p, rows in self.scans.items():
            if rows is not None:
                self.done[p][rows] = True

    def _add(self, serves: list[int], a: np.ndarray, far: np.ndarray, who: np.ndarray, start: int, d: tuple, dn: np.ndarray) -> None:
        if not len(a):
            return
        k, key = self.k, far << _NUMBER | who + start
        order = np.lexsort((key, a))
        order = order[_firsts(a[order]) < k]
        a, key, who = a[order], key[order], who[order]
        rows, at = np.unique(a, return_inverse=True)
        place, used = _firsts(a), np.minimum(dn[who], k)
        for j in serves:
            wide = [np.full((len(rows), 2 * k), _END), np.zeros((len(rows), 2 * k), np.uint8), np.zeros((len(rows), 2 * k), np.uint8)]
            for new, old, values in zip(wide, self.best[j], (key, _code(d[0][who], d[1][who], j), used)):
                new[:, :k] = old[rows]
                new[at, k + place] = values
            first = np.argsort(wide[0], axis=1)[:, :k]
            for new, old in zip(wide, self.best[j]):
                old[rows] = np.take_along_axis(new, first, 1)

    def modes(self) -> dict[int, np.ndarray]:
        """For every feature the mode of the nearest donors (0 without donors)."""
        out = {}
        for j, (_, code, weight) in self.best.items():
            w = weight.astype(np.int64)
            used = np.clip(self.k - (np.cumsum(w, axis=1) - w), 0, w)
            at = np.arange(len(code))[:, None] * 10 + code
            votes = np.bincount(at.ravel(), used.ravel(), len(code) * 10).reshape(-1, 10)[:, 1:]
            out[j] = np.where(votes.any(axis=1), votes.argmax(axis=1) + 1, 0)
        return out


def _mode(codes: np.ndarray, weights: np.ndarray, k: int) -> int:
    before = np.cumsum(weights) - weights
    used = np.clip(k - before, 0, weights)
    votes = np.bincount(codes, used, minlength=10)
    return int(votes[1:].argmax()) + 1 if votes[1:].any() else 0


class _Donors:
    """Blocks (number of the first, cells, weights, places by null pattern) of donors in the
    order of cells. One block stays in memory, more are read again for every round."""

    def __init__(self, parts, n: int):
        self.parts, self.n, self.kinds, self.only = parts, n, None, None

    def __iter__(self):
        if self.only is not None:
            yield from self.only
            return
        start, kinds, block = 0, set(), None
        for d0, d1, dn in self.parts():
            lacks, kind = np.unique(_lacking(d0, d1, self.n), return_inverse=True)
            order, ends = np.argsort(kind, kind="stable"), np.cumsum(np.bincount(kind, minlength=len(lacks)))
            patterns = dict(zip(map(int, lacks), np.split(order, ends[:-1])))
            kinds |= set(patterns)
            block = start, (d0, d1), dn, patterns
            yield block
            start += len(d0)
        if block is None or block[0] == 0:
            self.only = [block] if block else []
        self.kinds = kinds

    def patterns(self) -> set[int] | None:
        """Null patterns of all donors; None where they are too many to be searched by."""
        if self.kinds is None:
            for _ in self:
                pass
        return self.kinds if len(self.kinds) <= MOST_PATTERNS else None


def _fill(c0, c1, sg, donors: _Donors, kinds: set[int] | None, n: int, how: str, limits: dict, default: tuple[int, int], k: int) -> tuple[np.ndarray, np.ndarray]:
    """Cells with the modes of their nearest donors. Distances are gone through upward, and at
    each one block by block, until no receiver wants more; blocks cost no more work than all
    donors at once would."""
    out, found = [c0.copy(), c1.copy()], []
    lacks = _lacking(c0, c1, n)
    for g in np.unique(sg):
        w = limits.get(int(g), default)
        for gone in np.unique(lacks[sg == g]):
            rows = np.flatnonzero((sg == g) & (lacks == gone))
            if not gone:
                continue
            # Receivers that agree within the limits have the same neighbours.
            seen, back = np.unique(np.stack([c0[rows] & w[0], c1[rows] & w[1]]), axis=1, return_inverse=True)
            found.append((rows, back, _Search(seen[0], seen[1], int(gone), n, how, w, k)))
    for distance in range(n + 1):
        some = [s for *_, s in found if s.wants(distance, kinds)]
        for s in some:
            s.start()
        for start, d, dn, patterns in donors if some else ():
            for s in some:
                s.meet_all(start, d, dn) if kinds is None else s.meet(distance, start, d, dn, patterns)
        for s in some:
            s.end()
    for rows, back, s in found:
        for j, modes in s.modes().items():
            out[j // PER_WORD][rows] |= modes[back].astype(np.int64) << 4 * (j % PER_WORD)
    return out[0], out[1]


def _fill_by_pattern(c0, c1, sg, d0, d1, dn, patterns: dict[int, np.ndarray], *shared) -> tuple[np.ndarray, np.ndarray]:
    return _fill(c0, c1, sg, _Donors(lambda: [(d0, d1, dn)], shared[0]), set(patterns), *shared)


def _fill_by_scan(c0, c1, sg, d0, d1, dn, *shared) -> tuple[np.ndarray, np.ndarray]:
    return _fill(c0, c1, sg, _Donors(lambda: [(d0, d1, dn)], shared[0]), None, *shared)


@dataclass
class Pool:
    """Cells that are imputed, subgroup by subgroup, and the files of all donors in the order
    of their cells."""

    cells: DataFrame
    donors: list[str]


def pool_of(packed: DataFrame) -> Pool:
    """Cells and donors of ``packed``, written once for any number of imputations."""
    # Receivers of a subgroup lie in few tasks, each of which goes through the donors for them.
    cells = stored(cells_of(packed).repartitionByRange(2 * packed.sparkSession.sparkContext.defaultParallelism, "sg", F.xxhash64("c0", "c1")))
    donors = stored(cells.groupBy("c0", "c1").agg(F.sum("n").alias("n")).orderBy("c0", "c1"))
    return Pool(cells, sorted(donors.inputFiles(), key=lambda f: f.rsplit("/", 1)[-1]))


def _read(files: list[str], most: int):
    """(c0, c1, n) of the donors in the order of files, about ``most`` at a time."""
    some, size = [], 0
    for f in files:
        uri = urlparse(f)
        place, path = (fs.LocalFileSystem(), unquote(uri.path)) if uri.scheme in ("", "file") else fs.FileSystem.from_uri(f)
        with place.open_input_file(path) as file:
            for batch in parquet.ParquetFile(file).iter_batches(min(most, 1 << 17), columns=["c0", "c1", "n"]):
                some.append([x.to_numpy() for x in batch.columns])
                size += batch.num_rows
                if size >= most:
                    yield tuple(np.concatenate(x) for x in zip(*some))
                    some, size = [], 0
    if size:
        yield tuple(np.concatenate(x) for x in zip(*some))


#: Receivers that are searched for at once.
AT_ONCE = 250_000


def _gathered(frames):
    """Batches put together to ``AT_ONCE`` rows: a search looks at all donors once for each."""
    some, size = [], 0
    for pdf in frames:
        some.append(pdf)
        size += len(pdf)
        if size >= AT_ONCE:
            yield pd.concat(some, ignore_index=True)
            some, size = [], 0
    if size:
        yield pd.concat(some, ignore_index=True)


def knn_impute(packed: DataFrame, spec: FeatureSpec, k: int = 5, null_distance: str = "mismatch", columns: dict[int, int] | int | None = None, method: str = "exact", bands: int = 8, band_size: int = 3, seed: int = 0, pool: Pool | None = None) -> DataFrame:
    """Cells (sg, c0, c1, y, n) with every null filled where a donor exists. ``columns``
    restricts the distance to a mask, one for all or one per subgroup. ``pool`` is what
    :func:`pool_of` gives, if it is known."""
    full = (1 << spec.n) - 1
    limits = {g: widen(m) for g, m in columns.items()} if isinstance(columns, dict) else {}
    default = widen(columns if isinstance(columns, int) else full)
    if method == "bit_sampling":
        return _sampled(cells_of(packed), spec, k, null_distance, bands, band_size, seed)
    pool = pool or pool_of(packed)
    files, most = pool.donors, MOST_DONORS

    def run(frames):
        donors = _Donors(lambda: _read(files, most), spec.n)
        for pdf in _gathered(frames):
            c0, c1, sg = (pdf[c].to_numpy() for c in ("c0", "c1", "sg"))
            out0, out1 = _fill(c0, c1, sg, donors, donors.patterns(), spec.n, null_distance, limits, default, k)
            yield pdf.assign(c0=out0, c1=out1)

    return pool.cells.mapInPandas(run, "sg int, c0 long, c1 long, y byte, n long")


def _sampled(cells: DataFrame, spec: FeatureSpec, k: int, how: str, bands: int, band_size: int, seed: int) -> DataFrame:
    """Near-linear variant: cells that agree on a sampled set of features meet in a band, and
    every donor met there is ranked exactly. Cells without a donor keep their nulls."""
    rng = np.random.default_rng(seed)
    picks = [sum(1 << int(j) for j in rng.choice(spec.n, min(band_size, spec.n), replace=False)) for _ in range(bands)]
    return _by_buckets(cells, spec, k, how, picks, {}, widen((1 << spec.n) - 1))


def _by_buckets(cells: DataFrame, spec: FeatureSpec, k: int, how: str, picks: list[int], limits: dict[int, tuple[int, int]], default: tuple[int, int]) -> DataFrame:
    """Each receiver against all donors that agree with it on the features of a pick; an empty
    pick brings all cells together. Both sides of a bucket are cut into blocks of about
    ``BLOCK`` cells, every pair of blocks is one group, and the best ``k`` of the groups merge."""
    keys = ["band", "k0", "k1"]
    words = F.explode(F.arrays_zip(F.sequence(F.lit(0), F.lit(len(picks) - 1)).alias("band"), F.lit([widen(p)[0] for p in picks]).alias("w0"), F.lit([widen(p)[1] for p in picks]).alias("w1")))

    def keyed(df: DataFrame) -> DataFrame:
        return df.withColumn("w", words).select(*df.columns, F.col("w.band").alias("band"), F.col("c0").bitwiseAND(F.col("w.w0")).alias("k0"), F.col("c1").bitwiseAND(F.col("w.w1")).alias("k1"))

    fields = []
    for j in range(spec.n):
        col, shift = f"c{j // PER_WORD}", 4 * (j % PER_WORD)
        fields.append(F.shiftright(F.col(col), shift).bitwiseAND(F.lit(0xF)))
    any_null = sum([F.when(f == 0, 1).otherwise(0) for f in fields[1:]], F.when(fields[0] == 0, 1).otherwise(0)) > 0
    need = keyed(cells.filter(any_null).select("sg", "c0", "c1").distinct())
    donors = keyed(cells.groupBy("c0", "c1").agg(F.sum("n").alias("n"))).withColumnsRenamed({"c0": "d0", "c1": "d1"})
    blocks = F.ceil(F.count(F.lit(1)) / BLOCK)
    grid = need.groupBy(*keys).agg(blocks.alias("rs")).join(donors.groupBy(*keys).agg(blocks.alias("ds")), keys)
    wants = need.join(grid, keys).withColumn("r", F.pmod(F.hash("sg", "c0", "c1"), "rs")).withColumn("d", F.explode(F.sequence(F.lit(0), F.col("ds") - 1)))
    haves = donors.join(grid, keys).withColumn("d", F.pmod(F.hash("d0", "d1"), "ds")).withColumn("r", F.explode(F.sequence(F.lit(0), F.col("rs") - 1)))
    haves = haves.toDF(*haves.columns)
    names = ["sg", "c0", "c1", "j", "d", "d0", "d1", "code", "w"]

    def meet(key, want: pd.DataFrame, have: pd.DataFrame) -> pd.DataFrame:
        """Best ``k`` donors per feature of two blocks."""
        out = []
        d0, d1, dn = (have.sort_values(["d0", "d1"])[c].to_numpy() for c in ("d0", "d1", "n"))
        for i in range(0, len(want) if len(have) else 0, 256):
            part = want.iloc[i : i + 256]
            c0, c1, sg = (part[c].to_numpy() for c in ("c0", "c1", "sg"))
            for g in np.unique(sg):
                rows = np.flatnonzero(sg == g)
                dist = distances(c0[rows], c1[rows], d0, d1, how, limits.get(int(g), default))
                for j in range(spec.n):
                    shift = 4 * (j % PER_WORD)
                    own, there = (c0, d0) if j < PER_WORD else (c1, d1)
                    lacking = np.flatnonzero((own[rows] >> shift & 0xF) == 0)
                    donor = np.flatnonzero(there >> shift & 0xF) if len(lacking) else lacking
                    if not len(donor):
                        continue
                    most = min(len(donor), k)
                    for r in lacking:
                        d = dist[r, donor]
                        near = np.flatnonzero(d <= np.partition(d, most - 1)[most - 1])
                        near = near[np.argsort(d[near], kind="stable")][:most]
                        x = donor[near]
                        one = np.ones(most, np.int64)
                        out.append(np.stack([g * one, c0[rows[r]] * one, c1[rows[r]] * one, j * one, d[near], d0[x], d1[x], there[x] >> shift & 0xF, dn[x]]))
        return pd.DataFrame(np.concatenate(out, axis=1).T if out else np.empty((0, len(names)), np.int64), columns=names)

    group = [*keys, "r", "d"]
    met = wants.groupBy(*group).cogroup(haves.groupBy(*group)).applyInPandas(meet, "sg int, c0 long, c1 long, j int, d int, d0 long, d1 long, code int, w long")
    votes = met.groupBy("sg", "c0", "c1", "j").agg(F.slice(F.sort_array(F.collect_set(F.struct("d", "d0", "d1", "code", "w"))), 1, k).alias("v"))

    def pick(v: pd.Series) -> pd.Series:
        return v.map(lambda x: _mode(np.array([e["code"] for e in x]), np.array([e["w"] for e in x]), k))

    choose = F.pandas_udf(pick, "int")
    chosen = votes.select("sg", "c0", "c1", "j", choose("v").alias("code"))
    add = [F.coalesce(F.bit_or(F.when(F.floor(F.col("j") / PER_WORD) == w, F.call_function("shiftleft", F.col("code").cast("long"), 4 * (F.col("j") % PER_WORD)))), F.lit(0)).alias(f"a{w}") for w in (0, 1)]
    patch = chosen.groupBy("sg", "c0", "c1").agg(*add)
    out = cells.join(patch, ["sg", "c0", "c1"], "left")
    return out.select("sg", *[F.col(f"c{w}").bitwiseOR(F.coalesce(f"a{w}", F.lit(0))).alias(f"c{w}") for w in (0, 1)], "y", "n")


def mode_impute(packed: DataFrame, spec: FeatureSpec) -> DataFrame:
    """Control: every null gets the most frequent code of its feature over all rows."""
    from gapselect.operators.prep import unpack

    cells = cells_of(packed)
    longer = unpack(cells, spec).select("n", *spec.features).unpivot(["n"], list(spec.features), "f", "code").filter("code > 0")
    counts = longer.groupBy("f", "code").agg(F.sum("n").alias("n"))
    best = {r["f"]: -r["m"]["code"] for r in counts.groupBy("f").agg(F.max(F.struct("n", (-F.col("code")).alias("code"))).alias("m")).collect()}
    out = cells
    for w in (0, 1):
        value = F.col(f"c{w}")
        for j, f in enumerate(spec.features[w * PER_WORD : (w + 1) * PER_WORD]):
            fill = F.when(F.shiftright(F.col(f"c{w}"), 4 * j).bitwiseAND(F.lit(0xF)) == 0, F.lit(best.get(f, 0) << 4 * j)).otherwise(F.lit(0))
            value = value.bitwiseOR(fill.cast("long"))
        out = out.withColumn(f"c{w}", value)
    return out
