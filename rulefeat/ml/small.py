"""Learners for many small blocks at once: each block's rows go to one task, so thousands of trials are one job.

For tables whose blocks are large, ml/learners.py has distributed ones.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..storage import ship_package

CLIP = 1e-15


def _softmax(z: np.ndarray) -> np.ndarray:
    e = np.exp(z - z.max(axis=1, keepdims=True))
    return e / e.sum(axis=1, keepdims=True)


def softmax_l1(x: np.ndarray, y: np.ndarray, classes: int, penalty: float = 1.0, steps: int = 400):
    """Multinomial logistic regression with an l1 penalty on the summed loss, by accelerated proximal gradients; intercepts are free. Returns probabilities of new rows as a function."""
    n, p = x.shape
    one = np.eye(classes)[y]
    a = np.hstack([x, np.ones((n, 1))])
    rate = 1.0 / (0.5 * np.linalg.norm(a, 2) ** 2 / n + 1e-9)
    w, v, t = (np.zeros((p + 1, classes)),) * 2 + (1.0,)
    for _ in range(steps):
        step = v - rate * a.T @ (_softmax(a @ v) - one) / n
        new = np.vstack([np.sign(step[:p]) * np.maximum(0, np.abs(step[:p]) - rate * penalty / n), step[p:]])
        t, old = (1 + np.sqrt(1 + 4 * t * t)) / 2, t
        v, moved, w = new + (old - 1) / t * (new - w), np.abs(new - w).max(), new
        if moved < 1e-6:
            break
    return lambda z: _softmax(np.hstack([z, np.ones((len(z), 1))]) @ w)


def perceptron(x: np.ndarray, y: np.ndarray, classes: int, hidden=(30, 30), epochs: int = 150, patience: int = 12, seed: int = 7):
    """Two hidden layers of 30 by adaptive steps on batches, stopped early on a seventh of the rows."""
    rng = np.random.default_rng(seed)
    order = rng.permutation(len(x))
    held, own = order[: max(1, len(x) // 7)], order[max(1, len(x) // 7) :]
    sizes = [x.shape[1], *hidden, classes]
    layers = [[rng.normal(0, np.sqrt(2 / a), (a, b)), np.zeros(b)] for a, b in zip(sizes, sizes[1:])]
    first, second, turn = ([[np.zeros_like(m) for m in layer] for layer in layers] for _ in range(2)), None, 0
    first, second = first
    best, kept, waited = np.inf, [[m.copy() for m in layer] for layer in layers], 0

    def forward(z):
        seen = [z]
        for i, (w, b) in enumerate(layers):
            z = z @ w + b
            z = np.maximum(z, 0) if i < len(layers) - 1 else _softmax(z)
            seen.append(z)
        return seen

    for _ in range(epochs):
        rng.shuffle(own)
        for start in range(0, len(own), 64):
            rows = own[start : start + 64]
            seen = forward(x[rows])
            d, turn = (seen[-1] - np.eye(classes)[y[rows]]) / len(rows), turn + 1
            for i in range(len(layers) - 1, -1, -1):
                grads = (seen[i].T @ d, d.sum(axis=0))
                d = (d @ layers[i][0].T) * (seen[i] > 0)
                for k, g in enumerate(grads):
                    first[i][k] = 0.9 * first[i][k] + 0.1 * g
                    second[i][k] = 0.999 * second[i][k] + 0.001 * g * g
                    layers[i][k] -= 0.004 * (first[i][k] / (1 - 0.9**turn)) / (np.sqrt(second[i][k] / (1 - 0.999**turn)) + 1e-8)
        loss = -np.log(np.maximum(CLIP, forward(x[held])[-1][np.arange(len(held)), y[held]])).mean()
        if loss < best - 1e-4:
            best, kept, waited = loss, [[m.copy() for m in layer] for layer in layers], 0
        elif (waited := waited + 1) >= patience:
            break
    layers[:] = kept
    return lambda z: forward(z)[-1]


LEARNERS = {"logistic": softmax_l1, "perceptron": perceptron}


def score_blocks(rows: DataFrame, keys: list[str], classes: int, learners=("logistic", "perceptron")) -> DataFrame:
    """rows(keys..., part, label, features) to (keys..., learner, metric, value): for each block a fit on its rows of part 'train', scored on those of part 'test'.

    A block without rows of either part has no scores.
    """
    ship_package(rows.sparkSession)
    kinds = dict(rows.select(*keys).dtypes)

    def fit(block: pd.DataFrame) -> pd.DataFrame:
        x, y, train = np.stack(block["features"].to_numpy()).astype(float), block["label"].to_numpy(int), (block["part"] == "train").to_numpy()
        out = []
        if train.any() and not train.all():
            for name in learners:
                p = LEARNERS[name](x[train], y[train], classes)(x[~train])
                right = np.clip(p[np.arange(len(p)), y[~train]], CLIP, 1 - CLIP)
                out += [(name, "log_loss", float(-np.log(right).mean())), (name, "accuracy", float((p.argmax(axis=1) == y[~train]).mean()))]
        made = pd.DataFrame(out, columns=["learner", "metric", "value"])
        for i, k in enumerate(keys):
            made.insert(i, k, block[k].iloc[0])
        return made

    return rows.groupBy(*keys).applyInPandas(fit, ", ".join(f"{k} {kinds[k]}" for k in keys) + ", learner string, metric string, value double")


def features_by_block(records: DataFrame, columns: list[str], features: DataFrame, block: str, *kept: str) -> DataFrame:
    """records(block, columns..., kept...) with the 0/1 features of their own block: (keys of features..., block, kept..., features). features(…, block, feature_id, f1, v1, f2, v2) has a budget's rows a block."""
    others = [c for c in features.columns if c not in ("feature_id", "size", "f1", "v1", "f2", "v2", block)]
    lists = features.groupBy(*others, block).agg(F.array_sort(F.collect_list(F.struct("feature_id", "f1", "v1", "f2", "v2"))).alias("__wanted"))
    values = records.select(block, *kept, F.array(*[F.col(f"`{c}`").cast("string") for c in columns]).alias("__values"))
    holds = lambda f: F.coalesce((F.get("__values", f["f1"] - 1) == f["v1"]) & (f["f2"].isNull() | (F.get("__values", f["f2"] - 1) == f["v2"])), F.lit(False)).cast("double")
    return values.join(lists, block).select(*others, block, *kept, F.transform("__wanted", holds).alias("features"))
