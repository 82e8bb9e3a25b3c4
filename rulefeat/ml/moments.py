"""Linear models from matrices of products: one pass over the data for any number of splits, folds and penalties.

Every row belongs to one of a few cells by a hash. A task adds up, for each cell, the products of all columns of a design (with a one and the response); the sums over cells that
make up a training set, a fold or a test set are sums of such matrices. What follows costs nothing that grows with the rows.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..storage import ROWS_PER_BATCH, materialise, release, settings, ship_package

#: Bytes of all cells' matrices together at most; they go to the driver.
MOST = 1 << 29


def moments(df: DataFrame, columns: list[Column], response: Column, cell: Column, cells: int) -> np.ndarray:
    """[cells, p + 2, p + 2]: for each cell the products of (1, columns, response), summed over its rows. Rows with a null or NaN don't count."""
    p = len(columns) + 2
    if p * p * 8 * cells > MOST:
        raise ValueError(f"{len(columns)} columns in {cells} cells: screen the columns first")
    ship_package(df.sparkSession)
    values = F.array(F.lit(1.0), *[c.cast("double") for c in columns], response.cast("double"))
    wide = df.select(cell.cast("int").alias("cell"), values.alias("x")).where(~F.exists("x", lambda v: v.isNull() | F.isnan(v)))

    def partial(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums: dict[int, np.ndarray] = {}
        for batch in batches:
            if batch.num_rows:
                of, x = batch.column(0).to_numpy(), batch.column(1).flatten().to_numpy().reshape(batch.num_rows, p)
                for c in np.unique(of).tolist():
                    own = x[of == c]
                    sums[c] = sums.get(c, 0) + own.T @ own
        for c, m in sums.items():
            yield pa.RecordBatch.from_arrays([pa.array([c], pa.int32()), pa.array([m.tobytes()], pa.binary())], ["cell", "m"])

    def total(rows: pa.Table) -> pa.Table:
        m = sum(np.frombuffer(r.as_py(), float) for r in rows.column("m"))
        return pa.table({"cell": pa.array([rows.column("cell")[0].as_py()], pa.int32()), "m": pa.array([m.tobytes()], pa.binary())})

    out = np.zeros((cells, p, p))
    with settings(df.sparkSession, {ROWS_PER_BATCH: "2000"}):
        # a task sends one matrix a cell; they are added up in two steps, so that a reducer holds the square root of the tasks' number
        parts = materialise(wide.mapInArrow(partial, "cell int, m binary"), "moments")
        step = parts.groupBy("cell", F.spark_partition_id() % 32).applyInArrow(total, "cell int, m binary").groupBy("cell").applyInArrow(total, "cell int, m binary")
        for r in step.collect():
            out[r["cell"]] = np.frombuffer(r["m"], float).reshape(p, p)
    release(parts)
    return out


def _standard(m: np.ndarray):
    """Means, deviations, correlation-like matrix of the columns and their products with the response, all by row."""
    n = m[0, 0]
    mean = m[0, 1:] / n
    cov = m[1:, 1:] / n - np.outer(mean, mean)
    dev = np.sqrt(np.maximum(np.diag(cov), 0))
    dev[dev < 1e-9 * (1 + np.abs(mean))] = np.inf  # constant columns stay out
    return mean, dev, cov[:-1, :-1] / np.outer(dev[:-1], dev[:-1]), cov[:-1, -1] / dev[:-1]


def lasso(m: np.ndarray, penalties: list[float], sweeps: int = 200, tol: float = 1e-6) -> list[np.ndarray]:
    """Coefficients (intercept first) for falling penalties on standardised columns, by coordinate descent over the active columns, from the matrix alone."""
    mean, dev, gram, xy = _standard(m)
    b, out, active = np.zeros(len(xy)), [], np.zeros(0, int)
    usable = np.isfinite(dev[:-1])
    scale = max(1e-12, np.abs(xy).max(initial=0))
    for penalty in penalties:
        for _ in range(30):
            for _ in range(sweeps):
                moved = 0.0
                grad = xy - gram @ b if len(active) else xy
                for j in active.tolist():
                    new = grad[j] + b[j]
                    new = np.sign(new) * max(0.0, abs(new) - penalty)
                    if (d := new - b[j]) != 0.0:
                        grad = grad - d * gram[:, j]
                        b[j], moved = new, max(moved, abs(d))
                if moved < tol * scale:
                    break
            late = np.flatnonzero(usable & (np.abs(xy - gram @ b) > penalty * (1 + 1e-6) + 1e-12) & (b == 0))
            late = late[~np.isin(late, active)]
            if not len(late):
                break
            active = np.union1d(active, late)
        w = b / dev[:-1]
        out.append(np.r_[mean[-1] - w @ mean[:-1], w])
    return out


def error(m: np.ndarray, w: np.ndarray) -> float:
    """Mean squared error of coefficients on the rows behind a matrix."""
    e = np.r_[-w, 1.0]
    return float(e @ m @ e / m[0, 0])


def path(m: np.ndarray, n: int = 12, least: float = 1e-3) -> list[float]:
    """Falling penalties from the least one that leaves no column."""
    _, _, _, xy = _standard(m)
    return (np.abs(xy).max(initial=1e-12) * np.geomspace(1.0, least, n)).tolist()


def lasso_by_cv(cells: np.ndarray, train: list[int], folds: int = 5) -> tuple[np.ndarray, float]:
    """(coefficients, penalty) with the penalty of least error over folds of the training cells."""
    whole = cells[train].sum(axis=0)
    penalties, errors = path(whole), 0
    for f in range(folds):
        out = [c for i, c in enumerate(train) if i % folds == f]
        if out and len(out) < len(train):
            held = cells[out].sum(axis=0)
            if held[0, 0]:
                errors = errors + np.array([error(held, w) * held[0, 0] for w in lasso(whole - held, penalties)])
    at = int(np.argmin(errors)) if not np.isscalar(errors) else len(penalties) - 1
    return lasso(whole, penalties[: at + 1])[-1], penalties[at]


def least_squares(m: np.ndarray, chosen: list[int]) -> np.ndarray:
    """Coefficients (intercept first, zero where not chosen) of the least-squares fit of some columns."""
    at = [0, *[c + 1 for c in chosen]]
    w = np.zeros(len(m) - 1)
    w[at] = np.linalg.lstsq(m[np.ix_(at, at)], m[at, -1], rcond=1e-10)[0]
    return w


def forward(m: np.ndarray, terms: int, price: float = 3.0) -> list[int]:
    """Columns by forward selection on the error, then pruned by generalised cross validation at `price` a term."""
    chosen: list[int] = []
    mean, dev, gram, xy = _standard(m)
    n, total = m[0, 0], m[-1, -1] / m[0, 0] - (m[0, -1] / m[0, 0]) ** 2
    left, basis = xy.copy(), gram.copy()
    spare = np.where(np.isfinite(dev[:-1]), np.diag(basis), 0.0)
    for _ in range(terms):  # pivoted elimination: each step takes the column that explains most of what is left
        gain = np.where(spare > 1e-8, left**2 / np.maximum(spare, 1e-8), 0.0)
        j = int(np.argmax(gain))
        if gain[j] < 1e-9 * max(total, 1e-12):
            break
        chosen.append(j)
        column = basis[:, j] / basis[j, j]
        left = left - column * left[j]
        basis = basis - np.outer(column, basis[j])
        spare = np.diag(basis).copy()
    score = lambda k: error(m, least_squares(m, chosen[:k])) / (1 - min(0.99, (1 + price * k) / n)) ** 2
    return chosen[: min(range(len(chosen) + 1), key=score)]
