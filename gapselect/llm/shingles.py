"""Word shingles of whole texts as 64-bit fingerprints, computed on Arrow buffers.

Words are runs of bytes outside ``[\\x20\\x09-\\x0D]`` of the UTF-8 text with
A-Z lower-cased; both rules touch ASCII only, so byte work equals code-point
work. A text with fewer words than the shingle width has one shingle, the whole
sequence; a null, empty or blank text has none.

Fingerprints are 64 bits wide: two different shingles of the same pair of texts
collide with probability below ``n**2 / 2**64`` (about 1e-14 for texts of 500
words), which is the only inexactness in what is built on them.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa

_CHUNK_BYTES = 1 << 20
_BASE = np.uint64(0x9E3779B97F4A7C15)
_BASE_INVERSE = np.uint64(pow(0x9E3779B97F4A7C15, -1, 1 << 64))


def mix(x: np.ndarray) -> np.ndarray:
    """Finaliser of the public splitmix64 generator, element by element."""
    x = x.copy()
    x ^= x >> np.uint64(30)
    x *= np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(27)
    x *= np.uint64(0x94D049BB133111EB)
    x ^= x >> np.uint64(31)
    return x


_BYTE_VALUE = mix((np.arange(256, dtype=np.uint64) + np.uint64(1)) * _BASE)
_BYTE_VALUE[ord("A") : ord("Z") + 1] = _BYTE_VALUE[ord("a") : ord("z") + 1]
_IS_SPACE = np.zeros(256, bool)
_IS_SPACE[[0x20, *range(0x09, 0x0E)]] = True
_POWERS: dict[str, np.ndarray] = {"up": np.ones(1, np.uint64), "down": np.ones(1, np.uint64)}


def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    if len(_POWERS["up"]) < n + 1:
        for name, base in (("up", _BASE), ("down", _BASE_INVERSE)):
            steps = np.full(n + 1, base, np.uint64)
            steps[0] = 1
            _POWERS[name] = np.multiply.accumulate(steps)
    return _POWERS["up"], _POWERS["down"]


def text_buffers(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(bytes, offsets) of a string array; nulls have length 0."""
    if pa.types.is_large_string(column.type):
        column = column.cast(pa.string())
    if column.null_count:
        column = column.fill_null("")
    if not len(column):
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    _, offsets, data = column.buffers()
    offsets = np.frombuffer(offsets, np.int32)[column.offset : column.offset + len(column) + 1].astype(np.int64)
    raw = np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)
    return raw[offsets[0] : offsets[-1]], offsets - offsets[0]


def chunks(offsets: np.ndarray, most: int = _CHUNK_BYTES) -> Iterator[tuple[int, int]]:
    """Ranges of whole texts of about ``most`` bytes."""
    i, n = 0, len(offsets) - 1
    while i < n:
        j = max(i + 1, int(np.searchsorted(offsets, offsets[i] + most, "right")) - 1)
        yield i, j
        i = j


def word_hashes(raw: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(hash of each word, first word of each text as n+1 positions)."""
    size, n = len(raw), len(offsets) - 1
    if not size:
        return np.zeros(0, np.uint64), np.zeros(n + 1, np.int64)
    space = _IS_SPACE[raw]
    first = np.zeros(size + 1, bool)
    first[offsets] = True
    before = np.empty(size, bool)
    before[0] = True
    before[1:] = space[:-1]
    starts = np.flatnonzero(~space & (before | first[:-1]))
    after = np.empty(size, bool)
    after[-1] = True
    after[:-1] = space[1:]
    ends = np.flatnonzero(~space & (after | first[1:])) + 1
    up, down = _powers(size)
    total = np.zeros(size + 1, np.uint64)
    np.cumsum(_BYTE_VALUE[raw] * up[:size], out=total[1:])
    words = mix((total[ends] - total[starts]) * down[starts] + (ends - starts).astype(np.uint64))
    return words, np.searchsorted(starts, offsets)


def shingle_sets(column: pa.Array, width: int) -> Iterator[tuple[int, np.ndarray]]:
    """(row, sorted distinct fingerprints) of every text of the column."""
    raw, offsets = text_buffers(column)
    weights = mix(np.arange(1, width + 1, dtype=np.uint64) * _BASE) | np.uint64(1)
    for i, j in chunks(offsets):
        words, at = word_hashes(raw[offsets[i] : offsets[j]], offsets[i : j + 1] - offsets[i])
        joined = np.zeros(max(0, len(words) - width + 1), np.uint64)
        for k in range(width if len(joined) else 0):
            joined += words[k : k + len(joined)] * weights[k]
        joined = mix(joined)
        for row in range(i, j):
            a, b = at[row - i], at[row - i + 1]
            if b - a >= width:
                found = np.sort(joined[a : b - width + 1])
                keep = np.empty(len(found), bool)
                keep[0] = True
                np.not_equal(found[1:], found[:-1], out=keep[1:])
                yield row, found[keep]
            elif b > a:
                whole = (words[a:b] * weights[: b - a]).sum(dtype=np.uint64) + np.uint64(b - a)
                yield row, mix(np.array([whole], np.uint64))
            else:
                yield row, np.zeros(0, np.uint64)
