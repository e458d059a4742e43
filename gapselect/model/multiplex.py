"""The multiplex graph of a level band inside one task: node order and neighbour means."""

from __future__ import annotations

import numpy as np

from gapselect.spec import band


class Band:
    """Nodes of ``low..high`` features and the mean over in-lattice neighbours.

    Edges are XOR arithmetic; up to ``dense`` nodes the row-normalised adjacency is one
    matrix, beyond that neighbours are gathered in blocks, so memory stays
    ``block * degree * width``.
    """

    first = None  # neighbour means of the binary codes, where they are known beforehand

    def __init__(self, n: int, low: int, high: int, inter: bool = True, intra: bool = True, dense: int = 2500):
        self.n, self.masks = n, np.array(band(n, low, high), np.int64)
        at = {int(m): i for i, m in enumerate(self.masks)}
        near: list[list[int]] = []
        for m in map(int, self.masks):
            on, off = [j for j in range(n) if m >> j & 1], [j for j in range(n) if not m >> j & 1]
            here = [at[m ^ 1 << j] for j in range(n) if (m ^ 1 << j) in at] if inter else []
            if intra and len(on) > 1:
                here += [at[m ^ (1 << a | 1 << b)] for a in on for b in off]
            near.append(here)
        self.degree = np.array([max(1, len(x)) for x in near], np.float32)
        self.dense = None
        if len(near) <= dense:
            self.dense = np.zeros((len(near), len(near)))  # as wide as states, else every product would convert it
            for i, x in enumerate(near):
                self.dense[i, x] = 1
        else:
            self.flat = np.concatenate([np.array(x, np.int64) for x in near])
            self.starts = np.cumsum([0, *map(len, near)])
        self.at = at

    def __len__(self) -> int:
        return len(self.masks)

    def _sum(self, h: np.ndarray) -> np.ndarray:
        if self.dense is not None:
            return self.dense @ h
        out = np.zeros_like(h)
        for i in range(0, len(self), 512):
            j = min(len(self), i + 512)
            a, b = self.starts[i], self.starts[j]
            if b > a:
                sizes = np.diff(self.starts[i : j + 1])
                rows = np.flatnonzero(sizes)
                out[i + rows] = np.add.reduceat(h[self.flat[a:b]], (self.starts[i:j] - a)[rows], axis=0)
        return out

    def mean(self, h: np.ndarray) -> np.ndarray:
        return self._sum(h) / self.degree[:, None]

    def mean_back(self, g: np.ndarray) -> np.ndarray:
        """The transposed mean: adjacency is symmetric, degrees divide first."""
        return self._sum(g / self.degree[:, None])

    def bits(self) -> np.ndarray:
        return (self.masks[:, None] >> np.arange(self.n) & 1).astype(np.float32)
