"""Message passing on the multiplex graph, one regressor per subgroup, in numpy.

For the model of subgroup i every lattice j has its own in-lattice matrix, every ordered
pair its own cross matrix, and each layer one joining matrix. A node's message is the mean
of its in-lattice neighbours times the former plus same-set nodes of the other lattices
times the latter; own state and message are joined and passed through a rectifier. Only
labelled nodes of subgroup i enter the loss; all nodes of the band send messages.
"""

from __future__ import annotations

import hashlib
from dataclasses import dataclass

import numpy as np

from gapselect.model.multiplex import Band


@dataclass(frozen=True)
class GnnConfig:
    layers: int = 2
    hidden: int = 128
    epochs: int = 1000
    rate: float = 1e-3
    decay: float = 5e-4
    validation: float = 0.2
    seed: int = 0
    level_min: int = 1
    level_max: int | None = None
    label_channel: str = "none"  # none: literal; observed: labels of all subgroups are inputs; joint: one model for all
    cross: bool = True
    inter: bool = True
    intra: bool = True
    keep_best: bool = True


PAPER = GnnConfig()
SMALL = GnnConfig(hidden=24, epochs=120, rate=5e-3)


def _start(seed: tuple, shape: tuple[int, ...]) -> np.ndarray:
    rng = np.random.default_rng(int(hashlib.md5("|".join(map(str, seed)).encode()).hexdigest()[:12], 16))
    bound = np.sqrt(6.0 / (shape[-2] + shape[-1])) if len(shape) > 1 else np.sqrt(6.0 / (shape[0] + 1))
    return rng.uniform(-bound, bound, shape)


class Adam:
    """Moments with bias correction; decay joins the gradient."""

    def __init__(self, params: dict[str, np.ndarray], rate: float, decay: float):
        self.rate, self.decay, self.t = rate, decay, 0
        self.m = {k: np.zeros_like(v) for k, v in params.items()}
        self.v = {k: np.zeros_like(v) for k, v in params.items()}

    def step(self, params: dict[str, np.ndarray], grads: dict[str, np.ndarray]) -> None:
        self.t += 1
        for k, p in params.items():
            g = grads[k] + self.decay * p
            self.m[k] = 0.9 * self.m[k] + 0.1 * g
            self.v[k] = 0.999 * self.v[k] + 0.001 * g * g
            p -= self.rate * (self.m[k] / (1 - 0.9**self.t)) / (np.sqrt(self.v[k] / (1 - 0.999**self.t)) + 1e-8)


class MultiplexModel:
    def __init__(self, band: Band, groups: int, target: int, width_in: int, cfg: GnnConfig):
        self.band, self.groups, self.target, self.cfg = band, groups, target, cfg
        self.params: dict[str, np.ndarray] = {}
        d = width_in
        for t in range(cfg.layers):
            key = (cfg.seed, target, t)
            self.params[f"in{t}"] = np.stack([_start((*key, "in", j), (d, cfg.hidden)) for j in range(groups)])
            self.params[f"cross{t}"] = np.stack([np.stack([_start((*key, "x", k, j), (d, cfg.hidden)) for j in range(groups)]) for k in range(groups)])
            self.params[f"join{t}"] = _start((*key, "join"), (d + cfg.hidden, cfg.hidden))
            d = cfg.hidden
        self.params["out"] = _start((cfg.seed, target, "out"), (d,))
        self.params["bias"] = np.zeros(1)

    def _outputs(self, t: int) -> list[int]:
        return [self.target] if t == self.cfg.layers - 1 else list(range(self.groups))

    def forward(self, x: np.ndarray, keep: list | None = None) -> np.ndarray:
        """Predictions for all band nodes of the target subgroup; x is (groups, nodes, width)."""
        h = x
        for t in range(self.cfg.layers):
            new = np.zeros((self.groups, h.shape[1], self.cfg.hidden))
            saved = []
            for j in self._outputs(t):
                a = self.band.mean(h[j]) if t or self.band.first is None else self.band.first
                m = a @ self.params[f"in{t}"][j]
                if self.cfg.cross:
                    for k in range(self.groups):
                        if k != j:
                            m = m + h[k] @ self.params[f"cross{t}"][k, j]
                both = np.concatenate([h[j], m], axis=1)
                new[j] = np.maximum(both @ self.params[f"join{t}"], 0)
                saved.append((j, a, both))
            if keep is not None:
                keep.append((h, saved, new))
            h = new
        return h[self.target] @ self.params["out"] + self.params["bias"][0]

    def gradients(self, x: np.ndarray, rows: np.ndarray, y: np.ndarray) -> tuple[float, dict[str, np.ndarray]]:
        """Mean squared error over labelled rows and its gradient."""
        keep: list = []
        gap = self.forward(x, keep)[rows] - y
        g = {k: np.zeros_like(v) for k, v in self.params.items()}
        up = np.zeros(x.shape[1])
        up[rows] = 2 * gap / len(rows)
        last = keep[-1][2][self.target]
        g["out"], g["bias"][0] = last.T @ up, up.sum()
        dh = np.zeros_like(keep[-1][2])
        dh[self.target] = np.outer(up, self.params["out"])
        for t in range(self.cfg.layers - 1, -1, -1):
            h, saved, new = keep[t]
            below = np.zeros(h.shape)
            d = h.shape[2]
            for j, a, both in saved:
                delta = dh[j] * (new[j] > 0)
                g[f"join{t}"] += both.T @ delta
                back = delta @ self.params[f"join{t}"].T
                dm = back[:, d:]
                g[f"in{t}"][j] += a.T @ dm
                if t:  # inputs have no gradient
                    below[j] += back[:, :d]
                    below[j] += self.band.mean_back(dm @ self.params[f"in{t}"][j].T)
                if self.cfg.cross:
                    for k in range(self.groups):
                        if k != j:
                            g[f"cross{t}"][k, j] += h[k].T @ dm
                            if t:
                                below[k] += dm @ self.params[f"cross{t}"][k, j].T
            dh = below
        return float((gap**2).mean()), g


def split_validation(masks: np.ndarray, seed: int, sg: int, share: float) -> np.ndarray:
    """True for validation nodes, by an md5 coin of (seed, sg, mask)."""
    return np.array([int(hashlib.md5(f"v|{seed}|{sg}|{m}".encode()).hexdigest()[:8], 16) % 10_000 < 10_000 * share for m in masks], bool)


def inputs(band: Band, groups: int, labels: dict[int, dict[int, float]], cfg: GnnConfig, target: int, hidden_rows: np.ndarray, scale: tuple[float, float]) -> np.ndarray:
    """Binary codes, in ``observed`` mode with the value and a flag of observed labels; of
    the target subgroup ``hidden_rows`` are never shown."""
    x = np.repeat(band.bits()[None].astype(float), groups, axis=0)
    if cfg.label_channel != "observed":
        return x
    more = np.zeros((groups, len(band), 2))
    for j in range(groups):
        for m, v in labels.get(j, {}).items():
            i = band.at.get(m)
            if i is not None:
                more[j, i] = ((v - scale[0]) / scale[1], 1.0)
    more[target, hidden_rows] = 0
    return np.concatenate([x, more], axis=2)


def fit_predict(n: int, groups: int, target: int, labels: dict[int, dict[int, float]], cfg: GnnConfig, trace: list | None = None) -> tuple[np.ndarray, np.ndarray]:
    """(masks, predictions) of one subgroup's model. Labels are standardised inside."""
    band = Band(n, cfg.level_min, cfg.level_max or n, cfg.inter, cfg.intra)
    mine = {m: v for m, v in labels.get(target, {}).items() if m in band.at}
    if len(mine) < 2:  # nothing to learn from: the mean of the other subgroups
        rest = [v for j in labels for v in labels[j].values()]
        return band.masks, np.full(len(band), float(np.mean(rest)) if rest else 0.0)
    masks = np.array(sorted(mine), np.int64)
    rows, y = np.array([band.at[int(m)] for m in masks]), np.array([mine[int(m)] for m in masks])
    held = split_validation(masks, cfg.seed, target, cfg.validation)
    if held.all() or not held.any():
        held = np.arange(len(masks)) % 5 == 4
    mean, sd = float(y[~held].mean()), float(y[~held].std()) or 1.0
    z = (y - mean) / sd
    joint = [target] if cfg.label_channel != "joint" else sorted(labels)
    model = MultiplexModel(band, groups, target, n + 2 * (cfg.label_channel == "observed"), cfg)
    opt = Adam(model.params, cfg.rate, cfg.decay)
    rng = np.random.default_rng(cfg.seed * 1000 + target)
    never = rows[held]
    best, kept = np.inf, None
    shown = inputs(band, groups, labels, cfg, target, never, (mean, sd))
    if cfg.label_channel != "observed":  # the same codes in every lattice and epoch
        band.first = band.mean(shown[0])
    for epoch in range(cfg.epochs):
        train = np.flatnonzero(~held)
        if cfg.label_channel == "observed":  # what is to be predicted in this step is hidden in this step
            drop = train[rng.random(len(train)) < 0.5]
            drop = drop if len(drop) else train
            x = inputs(band, groups, labels, cfg, target, np.concatenate([never, rows[drop]]), (mean, sd))
            train = drop
        else:
            x = shown
        loss, g = model.gradients(x, rows[train], z[train])
        if len(joint) > 1:
            for j in joint:
                if j != target and labels[j]:
                    ms = [m for m in sorted(labels[j]) if m in band.at]
                    other = MultiplexModel.__new__(MultiplexModel)
                    other.__dict__ = {**model.__dict__, "target": j}
                    _, gj = other.gradients(x, np.array([band.at[m] for m in ms]), (np.array([labels[j][m] for m in ms]) - mean) / sd)
                    g = {k: g[k] + gj[k] for k in g}
        opt.step(model.params, g)
        if cfg.keep_best and (epoch % 5 == 4 or epoch == cfg.epochs - 1):
            error = float(((model.forward(shown)[rows[held]] - z[held]) ** 2).mean())
            if error < best:
                best, kept = error, {k: v.copy() for k, v in model.params.items()}
        if trace is not None:
            trace.append(loss)
    if kept is not None:
        model.params = kept
    final = inputs(band, groups, labels, cfg, target, np.zeros(0, np.int64), (mean, sd)) if cfg.label_channel == "observed" else shown
    return band.masks, model.forward(final) * sd + mean
