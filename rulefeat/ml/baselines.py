"""Encodings and interaction methods to compare with."""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.ml.functions import array_to_vector
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..storage import ROWS_PER_BATCH, materialise, settings, ship_package
from . import moments


def all_pairs(p: int, most: int = 50_000) -> list[tuple[int, int]]:
    """Every pair of p features; guarded, as their number grows with the square."""
    if p * (p - 1) // 2 > most:
        raise ValueError(f"{p * (p - 1) // 2} interactions: screen them instead")
    return list(combinations(range(1, p + 1), 2))


def marginal_screen(df: DataFrame, columns, response: str, k: int) -> DataFrame:
    """(f1, f2, strength): the k products of two columns that correlate most with the response.

    Each task adds up three matrices of products over its rows (of products, of their squares, and with the response), and one small aggregate adds those; constant products have no strength.
    Records without the response or a column don't count.
    """
    p = len(columns)
    all_pairs(p)
    ship_package(df.sparkSession)

    def partial(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums, n, s, q = np.zeros((3, p, p)), 0, 0.0, 0.0
        for batch in batches:
            rows = np.stack([c.to_numpy(zero_copy_only=False) for c in batch.columns], axis=1)
            x, r = rows[:, :p], rows[:, p]
            sums += np.stack([x.T @ x, (x * x).T @ (x * x), (x * r[:, None]).T @ x])
            n, s, q = n + len(r), s + float(r.sum()), q + float((r * r).sum())
        if n:
            a, b = np.triu_indices(p, 1)
            yield pa.RecordBatch.from_arrays(
                [pa.array((a + 1).astype(np.int32)), pa.array((b + 1).astype(np.int32)), *[pa.array(m[a, b]) for m in sums], pa.array(np.full(len(a), n, np.int64)), pa.array(np.full(len(a), s)), pa.array(np.full(len(a), q))],
                ["f1", "f2", "x", "xx", "xr", "n", "r", "rr"],
            )

    shift = df.agg(*[F.avg(F.col(c).cast("double")).alias(f"m{i}") for i, c in enumerate([response])]).first()[0] or 0.0
    wide = df.select(*[F.col(c).cast("double").alias(f"c{i}") for i, c in enumerate(columns)], (F.col(response).cast("double") - F.lit(float(shift))).alias("r")).dropna()
    with settings(df.sparkSession, {ROWS_PER_BATCH: "20000"}):  # numbers only
        parts = materialise(wide.mapInArrow(partial, "f1 int, f2 int, x double, xx double, xr double, n long, r double, rr double"), "screen")
    total = parts.groupBy("f1", "f2").agg(*[F.sum(c).alias(c) for c in ("x", "xx", "xr", "n", "r", "rr")])
    over = F.sqrt((F.col("n") * F.col("xx") - F.col("x") * F.col("x")) * (F.col("n") * F.col("rr") - F.col("r") * F.col("r")))
    strength = F.abs(F.try_divide(F.col("n") * F.col("xr") - F.col("x") * F.col("r"), over))
    return total.select("f1", "f2", F.when(~F.isnan(strength), strength).alias("strength")).where("strength IS NOT NULL").orderBy(F.round("strength", 7).desc(), "f1", "f2").limit(k)


def hierarchy_screen(pairs: DataFrame, mains: DataFrame, mode: str = "strong") -> DataFrame:
    """pairs(f1, f2, ...) whose parents are among mains(f): both of them, or either."""
    a = mains.select(F.col("f").alias("f1")).distinct()
    b = mains.select(F.col("f").alias("f2")).distinct()
    if mode == "strong":
        return pairs.join(a, "f1", "left_semi").join(b, "f2", "left_semi").select(*pairs.columns)
    if mode != "weak":
        raise ValueError(f"mode {mode!r}")
    left = pairs.join(a, "f1", "left_semi").select(*pairs.columns)
    return left.unionByName(pairs.join(a, "f1", "left_anti").join(b, "f2", "left_semi").select(*pairs.columns))


def scales(df: DataFrame, columns) -> dict[str, tuple[float, float]]:
    """Mean and deviation of each column that isn't constant, of a few columns at once: the engine compiles no aggregate of very many."""
    out, columns = {}, list(columns)
    for start in range(0, len(columns), 16):
        few = columns[start : start + 16]
        row = df.agg(*[f(c).alias(f"{n}_{i}") for i, c in enumerate(few) for n, f in (("m", F.avg), ("s", F.stddev_samp))]).first()
        out |= {c: (row[f"m_{i}"], row[f"s_{i}"]) for i, c in enumerate(few) if row[f"s_{i}"]}
    return out


def standardised(df: DataFrame, columns) -> DataFrame:
    """Columns less their means over their deviations (constant ones become 0)."""
    by = scales(df, columns)
    return df.withColumns({c: (F.col(c) - F.lit(by[c][0])) / F.lit(by[c][1]) if c in by else F.lit(0.0) for c in columns})


def design(df: DataFrame, columns, pairs, response: str) -> DataFrame:
    """features = the columns and the products of the pairs; label = the response."""
    x = [F.col(c).cast("double") for c in columns] + [F.col(columns[a - 1]) * F.col(columns[b - 1]) for a, b in pairs]
    return df.select("*", array_to_vector(F.array(*x)).alias("features"), F.col(response).cast("double").alias("label"))


class Design:
    """Columns, a response and cells of a table; matrices of products of any pairs besides the columns, each made by one pass and remembered."""

    def __init__(self, df: DataFrame, columns, response: str, cell: str, cells: int):
        self.df, self.columns, self.response, self.cell, self.cells = df, list(columns), response, cell, cells
        self.known: dict[tuple, np.ndarray] = {}

    def of(self, pairs=(), extra=()) -> np.ndarray:
        """Moments of the columns, the products of pairs of ordinals, and extra column expressions."""
        key = tuple(pairs) if not extra else None
        if key is None or key not in self.known:
            x = [F.col(c) for c in self.columns] + [F.col(self.columns[a - 1]) * F.col(self.columns[b - 1]) for a, b in pairs] + list(extra)
            got = moments.moments(self.df, x, F.col(self.response), F.col(self.cell), self.cells)
            if key is None:
                return got
            if len(self.known) > 8:
                self.known.clear()
            self.known[key] = got
        return self.known[key]


#: Main effects whose products an iterated fit lets in at most, the strongest; and products that screens keep.
MOST_ACTIVE, SCREENED = 40, 100


def _scored(cells: np.ndarray, train, test) -> tuple[float, int, np.ndarray]:
    w, _ = moments.lasso_by_cv(cells, train)
    return moments.error(cells[test].sum(axis=0), w), int((w[1:] != 0).sum()), w


def _actives(w: np.ndarray, p: int, most: int = MOST_ACTIVE) -> list[int]:
    """Ordinals of the main effects that are in, the strongest first up to `most`, then sorted."""
    strong = [i + 1 for i in np.argsort(-np.abs(w[1 : p + 1]), kind="stable").tolist() if w[i + 1] != 0]
    return sorted(strong[:most])


def main_effects(d: Design, train, test) -> tuple[float, int]:
    return _scored(d.of(), train, test)[:2]


def with_pairs(d: Design, train, test, pairs) -> tuple[float, int]:
    """Lasso over the columns and the products of given pairs; its penalty, like those of all methods here, is chosen by folds of the training cells."""
    return _scored(d.of(pairs), train, test)[:2]


def iterated(d: Design, train, test, rounds: int = 2) -> tuple[float, int]:
    """Fit, add the products of the active mains, fit again."""
    pairs: list = []
    for _ in range(rounds):
        *_, w = _scored(d.of(pairs), train, test)
        new = list(combinations(_actives(w, len(d.columns)), 2))
        if new == pairs:
            break
        pairs = new
    return with_pairs(d, train, test, pairs)


def screened(d: Design, train, test, part: DataFrame, k: int = SCREENED) -> tuple[float, int]:
    """Lasso over the mains and the k products that correlate most with the response in the training part."""
    return with_pairs(d, train, test, sorted((r["f1"], r["f2"]) for r in marginal_screen(part, d.columns, d.response, k).collect()))


def backtracked(d: Design, train, test, steps: int = 5) -> tuple[float, int]:
    """Along a path of falling penalties, the products of the features active so far become candidates. Built from the method's name alone."""
    pairs: list = []
    seen: set[int] = set()
    p = len(d.columns)
    for penalty in moments.path(d.of()[train].sum(axis=0), steps, 1e-2)[1:]:
        w = moments.lasso(d.of(pairs)[train].sum(axis=0), [penalty])[0]
        used = [f for c, pair in zip(w[p + 1 :], pairs) if c for f in pair]
        seen |= set([*_actives(w, p), *used][:MOST_ACTIVE])
        pairs = sorted(combinations(sorted(seen)[:MOST_ACTIVE], 2))
    return with_pairs(d, train, test, pairs)


def hierarchical(d: Design, train, test, part: DataFrame, k: int = 2 * SCREENED, rounds: int = 5) -> tuple[float, int]:
    """Strong hierarchy by alternation: of the screened products those stay whose parents are both in the fit that has them; fits go on until none leaves.

    The constraint holds in the model that comes out; it is not the joint optimum over all products.
    """
    p = len(d.columns)
    pairs = sorted((r["f1"], r["f2"]) for r in marginal_screen(part, d.columns, d.response, k).collect())
    for _ in range(rounds):
        *_, w = _scored(d.of(pairs), train, test)
        mains = {i + 1 for i in range(p) if w[i + 1]}
        left = [q for q, c in zip(pairs, w[p + 1 :]) if q[0] in mains and q[1] in mains and c]
        if left == [q for q, c in zip(pairs, w[p + 1 :]) if c]:
            break
        pairs = [q for q in pairs if q[0] in mains and q[1] in mains]
    return with_pairs(d, train, test, pairs)


def reluctant(d: Design, train, test, part: DataFrame, k: int = SCREENED) -> tuple[float, int]:
    """Fit the mains; screen products on what the fit leaves; fit again with those."""
    *_, w = _scored(d.of(), train, test)
    fitted = F.lit(float(w[0])) + sum((F.col(c) * float(b) for c, b in zip(d.columns, w[1:]) if b), F.lit(0.0))
    left = part.withColumn("__left", F.col(d.response) - fitted)
    return with_pairs(d, train, test, sorted((r["f1"], r["f2"]) for r in marginal_screen(left, d.columns, "__left", k).collect()))


def splines(d: Design, train, test, part: DataFrame, terms: int = 20, knots: int = 4) -> tuple[float, int]:
    """Adaptive regression splines: hinges at quantiles of single columns by forward selection, then products of the hinges that are in, pruned by generalised cross validation."""
    cuts = part.stat.approxQuantile(d.columns, [(i + 1) / (knots + 1) for i in range(knots)], 0.01)
    hinges = [F.greatest(F.lit(0.0), F.lit(float(s)) * (F.col(c) - F.lit(q))) for c, qs in zip(d.columns, cuts) for q in sorted(set(qs)) for s in (1, -1)]
    bare = Design(d.df, [], d.response, d.cell, d.cells)
    first = moments.forward(bare.of(extra=hinges)[train].sum(axis=0), terms)
    chosen = [hinges[i] for i in first]
    cells = bare.of(extra=[*chosen, *[a * b for a, b in combinations(chosen, 2)]])
    both = moments.forward(cells[train].sum(axis=0), terms)
    w = moments.least_squares(cells[train].sum(axis=0), both)
    return moments.error(cells[test].sum(axis=0), w), len(both)


def strongest(model, p: int, most: int) -> list[int]:
    """Ordinals of the columns with the largest coefficients of a classifier over all classes."""
    w = np.abs(model.coefficientMatrix.toArray()).max(axis=0)[:p]
    return sorted(int(i) + 1 for i in np.argsort(-w, kind="stable")[:most])


def random_intersections(df: DataFrame, key_items: str, label: str, positive: str, draws: int = 200, depth: int = 3, seed: int = 7) -> DataFrame:
    """Item sets that survive the intersection of `depth` random records of one class: (items, hits). The records drawn are few by parameter."""
    rows = df.where(F.col(label) == positive).select(key_items).orderBy(F.rand(seed)).limit(draws * depth)
    grouped = rows.withColumn("g", F.monotonically_increasing_id() % draws).groupBy("g").agg(F.collect_list(key_items).alias("sets"))
    common = grouped.select(F.aggregate(F.slice("sets", 2, F.size("sets")), F.col("sets")[0], lambda a, b: F.array_intersect(a, b)).alias("items"))
    return common.where(F.size("items") > 0).groupBy(F.array_sort("items").alias("items")).agg(F.count(F.lit(1)).alias("hits"))
