"""Training and inference as Spark jobs: one task per subgroup's model.

The labels of all subgroups are the model's input and are counted first: they are sets
times subgroups, not rows, and ``MOST_LABELS`` of them fit a task. Beyond that the band is
too large for one task and ``fit_distributed`` spreads nodes instead.
"""

from __future__ import annotations

from collections import defaultdict

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gapselect.model.gnn import GnnConfig, fit_predict

MOST_LABELS = 2_000_000
_OUT = "sg int, mask long, mi double"


def _checked(labels: DataFrame) -> list:
    rows = labels.select(F.col("sg").cast("int"), F.col("mask").cast("long"), "mi").limit(MOST_LABELS + 1).collect()
    if len(rows) > MOST_LABELS:
        raise ValueError(f"more than {MOST_LABELS} labels: restrict the level band or the budget")
    return rows


def fit_all(labels: DataFrame, n: int, groups: int, cfg: GnnConfig) -> DataFrame:
    """(sg, mask, mi): predictions of every band node by its subgroup's own model."""
    if cfg.label_channel == "none" and labels.limit(MOST_LABELS + 1).count() > MOST_LABELS:
        from gapselect.model.distributed import fit_distributed

        return fit_distributed(labels, n, groups, cfg)[0]
    by: dict[int, dict[int, float]] = defaultdict(dict)
    for r in _checked(labels):
        by[r["sg"]][r["mask"]] = r["mi"]
    shared = dict(by)

    def run(key, pdf: pd.DataFrame) -> pd.DataFrame:
        masks, out = fit_predict(n, groups, int(key[0]), shared, cfg)
        return pd.DataFrame({"sg": int(key[0]), "mask": masks, "mi": out})

    frame = labels.sparkSession.range(groups).select(F.col("id").cast("int").alias("sg"))
    return frame.repartition(groups, "sg").groupBy("sg").applyInPandas(run, _OUT)


def mlp_fit_predict(n: int, masks: np.ndarray, y: np.ndarray, wanted: np.ndarray, seed: int, sg: int, hidden=(64, 64), epochs: int = 1000, rate: float = 1e-3, decay: float = 5e-4) -> np.ndarray:
    """Two rectified layers on binary codes, same optimiser and selection as the model."""
    from gapselect.model.gnn import Adam, _start, split_validation

    def bits(m):
        return (np.asarray(m, np.int64)[:, None] >> np.arange(n) & 1).astype(float)

    sizes = (n, *hidden, 1)
    p = {f"w{k}": _start((seed, sg, "mlp", k), (sizes[k], sizes[k + 1])) for k in range(len(sizes) - 1)} | {f"b{k}": np.zeros(sizes[k + 1]) for k in range(len(sizes) - 1)}
    opt, depth = Adam(p, rate, decay), len(sizes) - 1

    def forward(x):
        acts = [x]
        for k in range(depth):
            x = x @ p[f"w{k}"] + p[f"b{k}"]
            x = np.maximum(x, 0) if k < depth - 1 else x
            acts.append(x)
        return acts

    held = split_validation(masks, seed, sg, 0.2)
    if held.all() or not held.any():
        held = np.arange(len(masks)) % 5 == 4
    mean, sd = float(y[~held].mean()), float(y[~held].std()) or 1.0
    x, z = bits(masks), (y - mean) / sd
    best, kept = np.inf, None
    for epoch in range(epochs):
        acts = forward(x[~held])
        up = 2 * (acts[-1] - z[~held][:, None]) / max(1, (~held).sum())
        g = {}
        for k in range(depth - 1, -1, -1):
            g[f"w{k}"], g[f"b{k}"] = acts[k].T @ up, up.sum(axis=0)
            up = (up @ p[f"w{k}"].T) * (acts[k] > 0) if k else None
        opt.step(p, g)
        if epoch % 5 == 4 or epoch == epochs - 1:
            error = float(((forward(x[held])[-1][:, 0] - z[held]) ** 2).mean())
            if error < best:
                best, kept = error, {k: v.copy() for k, v in p.items()}
    p = kept or p
    return forward(bits(wanted))[-1][:, 0] * sd + mean


def _per_group(labels: DataFrame, n: int, low: int, high: int, solve) -> DataFrame:
    from gapselect.spec import band

    wanted = np.array(band(n, low, high), np.int64)

    def run(key, pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("mask")
        out = solve(int(key[0]), pdf["mask"].to_numpy(), pdf["mi"].to_numpy(), wanted)
        return pd.DataFrame({"sg": int(key[0]), "mask": wanted, "mi": out})

    return labels.select(F.col("sg").cast("int").alias("sg"), "mask", "mi").groupBy("sg").applyInPandas(run, _OUT)


def mlp_all(labels: DataFrame, n: int, low: int, high: int, seed: int = 0, epochs: int = 1000, rate: float = 1e-3) -> DataFrame:
    return _per_group(labels, n, low, high, lambda sg, m, y, w: mlp_fit_predict(n, m, y, w, seed, sg, epochs=epochs, rate=rate))


def ridge_solve(n: int, masks: np.ndarray, y: np.ndarray, wanted: np.ndarray, penalty: float = 1e-3) -> np.ndarray:
    """Linear in the bits, in closed form; the constant is not penalised."""

    def design(m):
        return np.concatenate([np.ones((len(m), 1)), (np.asarray(m, np.int64)[:, None] >> np.arange(n) & 1).astype(float)], axis=1)

    x = design(masks)
    pull = penalty * np.eye(n + 1)
    pull[0, 0] = 0
    return design(wanted) @ np.linalg.solve(x.T @ x + pull + 1e-12 * np.eye(n + 1), x.T @ y)


def ridge_all(labels: DataFrame, n: int, low: int, high: int, penalty: float = 1e-3) -> DataFrame:
    return _per_group(labels, n, low, high, lambda sg, m, y, w: ridge_solve(n, m, y, w, penalty))


def save_model(params: dict[str, np.ndarray], spark, path: str) -> None:
    """Weights as rows (name, shape, values): readable by any engine."""
    rows = [(k, list(v.shape), [float(x) for x in v.ravel()]) for k, v in params.items()]
    spark.createDataFrame(rows, "name string, shape array<int>, values array<double>").write.mode("overwrite").json(path)


def load_model(spark, path: str) -> dict[str, np.ndarray]:
    rows = spark.read.schema("name string, shape array<int>, values array<double>").json(path).collect()
    return {r["name"]: np.array(r["values"]).reshape(r["shape"]) for r in rows}
