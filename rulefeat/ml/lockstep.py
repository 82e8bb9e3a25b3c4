"""Learners of many designs over one table that go ahead together: each round is one job that gives the losses and gradients of all of them.

The table is packed once into blocks of codes and numbers. A design says how a matrix comes out of these (label codes, 0/1 slots, rules, numbers), so folds with different cuts and
numbers of intervals share the table. The steps are taken on the driver, on coefficients only; a round sends each task's sums, not rows.
"""

from __future__ import annotations

import pickle
import zlib
from collections.abc import Generator, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..operators.bits import Bits
from ..operators.cube import Cube
from ..operators.items import value_of
from ..plans.pair_plans import HELD
from ..storage import BLOCK_READS, BLOCK_WRITES, ROWS_PER_BATCH, materialise, settings, ship_package

CLIP = 1e-15
#: Rows that are packed at once; a block has those of one part.
ROWS = 16_000
#: Steps of the logistic learner at most, steps of one perceptron fit, and the size of its hidden layers.
STEPS, BURST, HIDDEN = 60, 15, (30, 30)


@dataclass
class Packed:
    """Blocks (part, n, data) of a table. A code of a categorical column is the place among its values, of a continuous one among its edges; null has the last code."""

    blocks: DataFrame
    categorical: list[str]
    continuous: list[str]
    values: dict[str, list[str]]
    edges: dict[str, np.ndarray]
    classes: int

    def place(self, column: str) -> int:
        return [*self.categorical, *self.continuous].index(column)

    def table(self, column: str, cuts: list[float] | None, known: list[str] | None = None) -> list[str | None]:
        """The item value of each code: of a categorical column itself, of a continuous one its interval by the cuts; None for null."""
        if column in self.edges:
            edges = self.edges[column]
            return [f"b{np.searchsorted(sorted(cuts), e) + 1}" for e in edges] + [f"b{len(cuts) + 1}", None]
        return [*self.values[column], None]

    def opened(self):
        m, q = len(self.categorical) + len(self.continuous), len(self.continuous)

        def opened(batches):
            for batch in batches:
                for part, n, data in zip(*(batch.column(i) for i in range(3))):
                    n, raw = n.as_py(), data.as_buffer()
                    small = np.frombuffer(raw, np.uint8, 2 * n).reshape(2, n)
                    yield part.as_py(), small[0], small[1].astype(int), np.frombuffer(raw, np.int16, m * n, 2 * n).reshape(m, n), np.frombuffer(raw, np.float32, q * n, 2 * n + 2 * m * n).reshape(q, n)

        return opened


def pack(df: DataFrame, label: str, part: str, draw: str, categorical, continuous, values: dict[str, list[str]], edges: dict[str, list[float]], classes: int, scales: dict[str, tuple[float, float]] | None = None) -> Packed:
    """df with an integer `label`, an integer `part` and a column `draw` that is true for rows held out of a perceptron's steps.

    With scales (mean and deviation of each column that isn't constant) the learners' numbers are standardised; the edges are of the columns as they are.
    """
    ship_package(df.sparkSession)
    categorical, continuous = list(categorical), list(continuous)
    edges = {c: np.unique(np.array(edges.get(c, []), float)) for c in continuous}
    places = [{v: i for i, v in enumerate(values[c])} for c in categorical]
    cuts, m = [edges[c] for c in continuous], len(categorical)
    shifts = None if scales is None else [scales.get(c, (0.0, np.inf)) for c in continuous]
    wide = df.where(F.col(label).isNotNull()).select(
        F.col(part).cast("int").alias("p"), F.col(draw).cast("int").alias("d"), F.col(label).cast("int").alias("y"), *[value_of(c).alias(f"c{i}") for i, c in enumerate(categorical)],
        *[F.col(f"`{c}`").cast("double").alias(f"n{i}") for i, c in enumerate(continuous)],
    )

    def packed(held: list[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        block = pa.Table.from_batches(held).combine_chunks().to_batches()[0]
        of, n = block.column(0).to_numpy(), block.num_rows
        codes, numbers = np.empty((m + len(cuts), n), np.int16), np.empty((len(cuts), n), np.float32)
        for i, table in enumerate(places):
            own = block.column(3 + i).dictionary_encode()
            at = np.array([*(table[v] for v in own.dictionary.to_pylist()), len(table)], np.int16)
            codes[i] = at[own.indices.fill_null(len(own.dictionary)).to_numpy(zero_copy_only=False)]
        for i, cut in enumerate(cuts):
            x = block.column(3 + m + i).fill_null(np.nan).to_numpy(zero_copy_only=False)
            codes[m + i] = np.where(np.isnan(x), len(cut) + 1, np.searchsorted(cut, x))
            numbers[i] = np.nan_to_num(x if shifts is None else (x - shifts[i][0]) / shifts[i][1])
        small = np.stack([block.column(1).to_numpy(), block.column(2).to_numpy()]).astype(np.uint8)
        for p in np.unique(of).tolist():
            rows = of == p
            data = small[:, rows].tobytes() + codes[:, rows].tobytes() + numbers[:, rows].tobytes()
            yield pa.RecordBatch.from_pydict({"part": pa.array([p], pa.int32()), "n": pa.array([int(rows.sum())], pa.int32()), "data": pa.array([data], pa.binary())})

    def blocks(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, rows = [], 0
        for batch in batches:
            if batch.num_rows:
                held.append(batch)
                rows += batch.num_rows
            if rows >= ROWS:
                yield from packed(held)
                held, rows = [], 0
        if held:
            yield from packed(held)

    kept = materialise(wide.mapInArrow(blocks, "part int, n int, data binary"), "blocks", options=BLOCK_WRITES)
    cores = df.sparkSession.sparkContext.defaultParallelism
    return Packed(kept.coalesce(cores), categorical, continuous, values, edges, classes)


def cube(packed: Packed, names: list[str], parts) -> Cube | None:
    """Counts of all items and pairs of codes in these parts, where a task can hold the counters."""
    columns, wanted = [*packed.categorical, *packed.continuous], sorted(parts)
    widths = [len(packed.table(c, [])) - 1 for c in columns]
    ends, classes, n_parts = np.cumsum([0, *widths]), packed.classes, max(wanted) + 1
    width = int(ends[-1])
    if n_parts * classes * width**2 > HELD:
        return None
    opened = packed.opened()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows, pairs = np.zeros((n_parts, classes)), np.zeros((n_parts, classes, width, width))
        for part, _, y, codes, _ in opened(batches):
            if part not in wanted:
                continue
            hot = np.zeros((len(y), width), np.float32)
            for i, (first, w) in enumerate(zip(ends, widths)):
                known = np.flatnonzero(codes[i] < w)
                hot[known, first + codes[i][known]] = 1
            for c in np.unique(y).tolist():
                own = hot[y == c]
                rows[part, c] += len(own)
                pairs[part, c] += own.T @ own  # exact: a block has fewer than 2^24 rows
        yield pa.RecordBatch.from_pydict({"rows": pa.array([rows.tobytes()], pa.binary()), "pairs": pa.array([zlib.compress(pairs.tobytes(), 1)], pa.binary())})

    spark, rows, pairs = packed.blocks.sparkSession, 0.0, 0.0
    with settings(spark, BLOCK_READS):
        for r in packed.blocks.mapInArrow(run, "rows binary, pairs binary").collect():  # one a core
            rows, pairs = rows + np.frombuffer(r["rows"]), pairs + np.frombuffer(zlib.decompress(r["pairs"]))
    return Cube(spark, rows.reshape(n_parts, classes), pairs.reshape(n_parts, classes, width, width), names, dict(zip(columns, ends.tolist())))


@dataclass
class Design:
    """Columns of a matrix and the parts that it is learnt and tested on. A column is ('number', place), ('code', place, table) or ('rule', [(place, table), ...]) with 0/1 tables."""

    columns: list[tuple]
    train: frozenset
    test: frozenset

    @staticmethod
    def taken(rows: np.ndarray, codes: np.ndarray, numbers: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """What matrix() wants of some rows of a block; codes as the engine's own integers, as a column of the matrix is looked up by them."""
        return codes.take(rows, axis=1).astype(np.intp), numbers.take(rows, axis=1)

    def matrix(self, codes: np.ndarray, numbers: np.ndarray, kind=np.float32) -> np.ndarray:
        out = np.empty((codes.shape[1], len(self.columns)), kind, order="F")
        for i, (what, *rest) in enumerate(self.columns):
            if what == "number":
                out[:, i] = numbers[rest[0]]
            elif what == "code":
                rest[1].astype(kind).take(codes[rest[0]], out=out[:, i], mode="clip")  # no code lies outside
            elif len(rest[0]) == 1:
                ((place, table),) = rest[0]
                table.astype(kind).take(codes[place], out=out[:, i], mode="clip")
            else:
                (place, table), *more = rest[0]
                held = table.take(codes[place])
                for place, table in more:
                    held = held & table.take(codes[place])
                out[:, i] = held
        return out


@dataclass
class Ones:
    """A design over Bits: their features as 0/1 columns, null as 0."""

    p: int
    train: frozenset
    test: frozenset

    @staticmethod
    def taken(rows: np.ndarray, ones: np.ndarray, known: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        return ones[rows], known[rows]

    def matrix(self, ones: np.ndarray, known: np.ndarray, kind=np.float32) -> np.ndarray:
        return np.unpackbits(ones, axis=1, count=self.p).astype(kind)


@dataclass
class Model:
    design: int
    columns: np.ndarray
    kind: str


def _softmax(z: np.ndarray) -> np.ndarray:
    most = z[..., 0]
    for c in range(1, z.shape[-1]):  # few classes: along the rows, not along the classes of each
        most = np.maximum(most, z[..., c])
    e = np.exp(z - most[..., None])
    total = e[..., 0].copy()
    for c in range(1, z.shape[-1]):
        total += e[..., c]
    e /= total[..., None]
    return e


def _layers(w: np.ndarray, sizes: list[int]) -> list[tuple[np.ndarray, np.ndarray]]:
    out, at = [], 0
    for a, b in zip(sizes, sizes[1:]):
        out.append((w[at : at + a * b].reshape(a, b), w[at + a * b : at + a * b + b]))
        at += a * b + b
    return out


#: Columns that nobody wants between two ranges of a matrix's columns, up to which these are one.
GAP = 16


class Spans:
    """Some columns of a matrix as few ranges of neighbours, in which those that aren't wanted count for nothing: no product needs a copy of the columns."""

    def __init__(self, columns: np.ndarray):
        order = np.unique(columns)
        runs = np.split(order, np.flatnonzero(np.diff(order) > GAP) + 1) if len(order) else []
        self.ranges = [(int(r[0]), int(r[-1]) + 1) for r in runs]
        whole = np.concatenate([np.arange(a, b) for a, b in self.ranges]) if runs else order
        self.places, self.width = np.searchsorted(whole, columns), len(whole)

    def times(self, x: np.ndarray, w: np.ndarray) -> np.ndarray:
        wide, out, at = np.zeros((self.width, w.shape[1]), w.dtype), None, 0
        wide[self.places] = w
        for a, b in self.ranges:
            z, at = x[:, a:b] @ wide[at : at + b - a], at + b - a
            out = z if out is None else np.add(out, z, out=out)
        return np.zeros((len(x), w.shape[1]), w.dtype) if out is None else out

    def sums(self, x: np.ndarray, back: np.ndarray) -> np.ndarray:
        return np.concatenate([np.zeros((0, back.shape[1]), back.dtype), *(x[:, a:b].T @ back for a, b in self.ranges)])[self.places]


def _forward(x: np.ndarray, layers: list, spans: Spans | None = None) -> list[np.ndarray]:
    """The values of each layer, x first; with spans those are the columns of x that the first layer sees."""
    seen = [x]
    for i, (w, b) in enumerate(layers):
        z = spans.times(x, w) if spans and not i else seen[-1] @ w
        z += b
        if i < len(layers) - 1:
            with np.errstate(over="ignore"):  # an infinite one becomes 0
                np.exp(np.negative(z, out=z), out=z)
            z += 1
            np.reciprocal(z, out=z)
        seen.append(z if i < len(layers) - 1 else _softmax(z))
    return seen


def _backward(seen: list[np.ndarray], layers: list, back: np.ndarray, spans: Spans | None = None) -> np.ndarray:
    """The gradient over all weights, from that over the last layer's sums."""
    grads, one = [], np.ones(len(back), back.dtype)
    for k in range(len(layers) - 1, -1, -1):
        grads.append(np.concatenate([(spans.sums(seen[0], back) if spans and not k else seen[k].T @ back).ravel(), one @ back]))
        if k:
            back = back @ layers[k][0].T
            back *= seen[k]
            back -= back * seen[k]
    return np.concatenate(grads[::-1])


#: Cells of a table of several columns' codes, each a sum for every model.
CELLS = 1024


class Tables:
    """What logistic models of Designs need of a block, without their matrices: a column of codes gives each row an entry of a table of scores, and takes the row's residual into one of sums.

    Columns of few codes share a table. Only numbers and rules over two tables stay columns. With two classes the score is that of class 1 less that of class 0.
    """

    def __init__(self, packed: Packed, designs: list[Design], models: dict[int, Model]):
        self.models, self.two, self.classes = models, packed.classes == 2, packed.classes
        self.designs = designs
        size = {packed.place(c): len(packed.table(c, [])) for c in [*packed.categorical, *packed.continuous]}
        used = sorted({p for m in models.values() for j in m.columns for p in self._places(designs[m.design].columns[j])}, key=lambda p: size[p])
        self.groups: list[list[int]] = []
        for p in used:
            if not self.groups or np.prod([size[q] for q in self.groups[-1]], dtype=float) * size[p] > CELLS:
                self.groups.append([])
            self.groups[-1].append(p)
        self.shapes = [tuple(size[p] for p in g) for g in self.groups]
        of = {p: g for g, own in enumerate(self.groups) for p in own}
        self.crossed: list[list[tuple]] = []  # rules over two tables, once each
        self.kinds: list[dict[int, tuple]] = []  # of each design, by column: number, table with its entries, or rule
        seen: dict[tuple, int] = {}
        for d in designs:
            kinds = {}
            for j, (what, *rest) in enumerate(d.columns):
                if what == "number":
                    kinds[j] = ("number", rest[0])
                    continue
                held = [(rest[0], rest[1])] if what == "code" else rest[0]
                if any(p not in of for p, _ in held):
                    continue  # of no model
                if len({of[p] for p, _ in held}) == 1:
                    g = of[held[0][0]]
                    entries = np.ones(self.shapes[g])
                    for p, table in held:
                        at = self.groups[g].index(p)
                        entries = entries * np.asarray(table, float).reshape([-1 if i == at else 1 for i in range(len(self.groups[g]))])
                    kinds[j] = ("table", g, entries.ravel())
                else:
                    key = tuple((p, table.tobytes()) for p, table in held)
                    if key not in seen:
                        seen[key] = len(self.crossed)
                        self.crossed.append(held)
                    kinds[j] = ("rule", seen[key])
            self.kinds.append(kinds)
        self.numbers = len(packed.continuous)

    @staticmethod
    def _places(column: tuple) -> list[int]:
        what, *rest = column
        return [] if what == "number" else [rest[0]] if what == "code" else [p for p, _ in rest[0]]

    def spread(self, w: dict[int, np.ndarray]) -> list[np.ndarray]:
        """Coefficients as scores: (rows of) each table, then numbers, rules and the one, by model and class."""
        width = 1 if self.two else self.classes
        out = [np.zeros((int(np.prod(s)), len(self.models), width)) for s in self.shapes] + [np.zeros((n, len(self.models), width)) for n in (self.numbers, len(self.crossed), 1)]
        for i, (name, m) in enumerate(self.models.items()):
            own = w[name][:, 1:] - w[name][:, :1] if self.two else w[name]
            for j, coefficient in zip(m.columns.tolist(), own):
                what, at, *entries = self.kinds[m.design][j]
                if what == "table":
                    out[at][:, i] += entries[0][:, None] * coefficient
                else:
                    out[len(self.shapes) + (what == "rule")][at, i] += coefficient
            out[-1][0, i] = own[-1]
        return [x.astype(np.float32) for x in out]

    def gathered(self, sums: list[np.ndarray]) -> dict[int, np.ndarray]:
        """Sums laid out as spread() does, as each model's gradient."""
        out = {}
        for i, (name, m) in enumerate(self.models.items()):
            rows = []
            for j in m.columns.tolist():
                what, at, *entries = self.kinds[m.design][j]
                rows.append(entries[0] @ sums[at][:, i] if what == "table" else sums[len(self.shapes) + (what == "rule")][at, i])
            g = np.array([*rows, sums[-1][0, i]])
            out[name] = np.hstack([-g, g]) if self.two else g
        return out

    def sums(self, wanted: set[int]):
        """per_block(scores, block) and finish() of Lockstep._sums(), for the wanted models: residuals summed as spread() lays coefficients out, under the key 'tables'."""
        groups, shapes, crossed, classes, many, width = self.groups, self.shapes, self.crossed, self.classes, len(self.models), 1 if self.two else self.classes
        learnt = {p for i in wanted for p in self.designs[self.models[i].design].train}
        parts = {p: np.array([at for at, (i, m) in enumerate(self.models.items()) if i in wanted and p in self.designs[m.design].train]) for p in learnt}

        def per_block(scores, block):
            part, _, y, codes, numbers = block
            if part not in parts:
                return
            own = parts[part]
            cells = [np.ravel_multi_index([codes[p] for p in g], s) for g, s in zip(groups, shapes)]
            local = [np.ascontiguousarray(t[:, own]).reshape(len(t), len(own) * width) for t in scores]
            z = np.repeat(local[-1], len(y), axis=0)
            for cell, table in zip(cells, local):
                z += table.take(cell, axis=0)
            z += numbers.T @ local[-3]
            held = np.empty((len(crossed), len(y)), np.float32)
            for i, ((p, table), *more) in enumerate(crossed):
                one = table.take(codes[p])
                for q, other in more:
                    one = one & other.take(codes[q])
                held[i] = one
            z += held.T @ local[-2]
            if classes == 2:
                with np.errstate(over="ignore"):
                    r = 1 / (1 + np.exp(-z))
                r -= y[:, None]
            else:
                r = _softmax(z.reshape(len(y), -1, classes))
                r[np.arange(len(y)), :, y] -= 1
                r = r.reshape(len(y), -1)
            columns = np.ascontiguousarray(r.T, float)
            made = [np.stack([np.bincount(cell, c, int(np.prod(s))) for c in columns], axis=1) for cell, s in zip(cells, shapes)] + [(numbers @ r).astype(float), (held @ r).astype(float), r.sum(axis=0, dtype=float)[None]]
            yield ("part", part), [m.reshape(len(m), len(own), width) for m in made]

        def finish(total: dict) -> dict:
            out, made = {k: v for k, v in total.items() if not isinstance(k, tuple)}, None
            for (_, part), new in ((k, v) for k, v in total.items() if isinstance(k, tuple)):
                made = made or [np.zeros((len(m), many, width)) for m in new]
                for t, m in zip(made, new):
                    t[:, parts[part]] += m
            return out | {"tables": made} if made else out

        return per_block, finish


def _loss(p: np.ndarray, y: np.ndarray) -> float:
    return float(-np.log(np.clip(p[np.arange(len(y)), y].astype(float), CLIP, 1 - CLIP)).sum())


def probabilities(x: np.ndarray, model: Model, w: np.ndarray, classes: int) -> np.ndarray:
    x = x[:, model.columns]
    if model.kind == "logistic":
        return _softmax(x @ w[:-1] + w[-1])
    return _forward(x, _layers(w, [x.shape[1], *HIDDEN, classes]))[-1]


class Lockstep:
    """scaled: whether the logistic learner's penalty is on coefficients of columns brought to one deviation, or on those of the columns as they are."""

    def __init__(self, packed: Packed | Bits, designs: list[Design | Ones], scaled: bool = True):
        self.packed, self.designs, self.spark, self.scaled = packed, designs, packed.blocks.sparkSession, scaled
        self.classes = packed.classes
        self.shared = self.spark.sparkContext.broadcast(designs)
        self.tables: Tables | None = None

    def _sums(self, per_block, given, finish=None) -> dict:
        """Totals by key of what per_block(designs, given, block) yields as (key, arrays), of all blocks; finish() makes less of a task's own."""
        opened, shared, sent = self.packed.opened(), self.shared, self.spark.sparkContext.broadcast(given)

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            total: dict = {}
            for block in opened(batches):
                for key, new in per_block(shared.value, sent.value, block):
                    total[key] = [a + b for a, b in zip(total[key], new)] if key in total else new
            total = finish(total) if finish else total
            yield pa.RecordBatch.from_pydict({"sums": pa.array([pickle.dumps(total)], pa.binary())})

        out: dict = {}
        with settings(self.spark, BLOCK_READS):
            rows = self.packed.blocks.mapInArrow(run, "sums binary").collect()  # one a core
        for r in rows:
            for key, new in pickle.loads(r["sums"]).items():
                out[key] = [a + b for a, b in zip(out[key], new)] if key in out else new
        sent.unpersist()
        return out

    def moments(self) -> dict:
        """For each design that has rows: products of its columns (a one last) over its training rows, and the rows of each class."""
        classes = self.classes

        def per_block(designs, _, block):
            part, _, y, codes, numbers = block
            for i, d in enumerate(designs):
                if part in d.train:
                    x = d.matrix(codes, numbers)
                    sums = np.append(x.sum(axis=0, dtype=float), len(y))
                    products = np.empty((len(sums), len(sums)))
                    products[:-1, :-1], products[-1], products[:, -1] = x.T @ x, sums, sums
                    yield i, [products, np.bincount(y, minlength=classes).astype(float)]

        return self._sums(per_block, None)

    def evaluate(self, models: list[Model], asked: dict[int, tuple[str, np.ndarray]]) -> dict:
        """(rows, loss, gradient) of each model asked for, summed over its training rows; asked has 'all' (rows), 'own' (those not held out), or 'held' (held out; no gradient).

        The loss of logistic models over Packed isn't asked for by their steps, and is 0.
        """
        classes = self.classes
        given, plain, spans = {}, {}, {}
        for i, (what, w) in asked.items():
            if models[i].kind == "logistic" and isinstance(self.packed, Packed):
                plain[i] = w
                continue
            given.setdefault(models[i].design, []).append((i, models[i], what, w.astype(np.float32)))
            if models[i].kind != "logistic":
                spans[i] = Spans(models[i].columns)

        def per_block(designs, given, block):
            part, draw, y, codes, numbers = block
            taken: dict = {}  # by kind of rows: their labels, and what the designs' matrices are made of
            for d, wanted in given.items():
                if part not in designs[d].train:
                    continue
                together = [g for g in wanted if g[1].kind == "logistic"]
                if together:
                    x = designs[d].matrix(codes, numbers)
                    w = np.zeros((x.shape[1] + 1, len(together), classes), np.float32)
                    for j, (_, model, _, own) in enumerate(together):
                        w[np.append(model.columns, -1), j] = own
                    p = _softmax((x @ w[:-1].reshape(x.shape[1], -1) + w[-1].reshape(-1)).reshape(len(y), -1, classes))
                    losses = [_loss(p[:, j], y) for j in range(len(together))]
                    p[np.arange(len(y)), :, y] -= 1
                    gradient, ends = (x.T @ p.reshape(len(y), -1)).reshape(x.shape[1], -1, classes), p.sum(axis=0, dtype=float)
                    for j, (i, model, _, _) in enumerate(together):
                        yield i, [len(y), losses[j], np.vstack([gradient[model.columns, j], ends[j]]).astype(float)]
                for kind in sorted({what for _, model, what, _ in wanted if model.kind != "logistic"}):
                    if kind not in taken:
                        rows = np.flatnonzero(draw == (kind == "held"))
                        taken[kind] = y[rows], designs[d].taken(rows, codes, numbers)
                    t, own_rows = taken[kind]
                    x, every = designs[d].matrix(*own_rows), np.arange(len(t))
                    for i, model, what, own in wanted:
                        if model.kind == "logistic" or what != kind:
                            continue
                        layers = _layers(own, [len(model.columns), *HIDDEN, classes])
                        seen = _forward(x, layers, spans[i])
                        loss = _loss(seen[-1], t)
                        if what == "held":
                            yield i, [len(t), loss, 0.0]
                            continue
                        back = seen[-1]
                        back[every, t] -= 1
                        yield i, [len(t), loss, _backward(seen, layers, back, spans[i]).astype(float)]

        if not plain:
            return self._sums(per_block, given)
        if self.tables is None or not set(plain) <= set(self.tables.models):
            self.tables, self.last = Tables(self.packed, self.designs, {i: models[i] for i in plain}), {}
        self.last |= plain  # models that are done keep their place, but no part is learnt for them
        sums, finish = self.tables.sums(set(plain))

        def together(designs, given, block):
            yield from per_block(designs, given[0], block)
            yield from sums(given[1], block)

        got = self._sums(together, (given, self.tables.spread(self.last)), finish)
        gradients, rows = self.tables.gathered(got.pop("tables")), self.rows
        return got | {i: [int(rows[models[i].design].sum()), 0.0, gradients[i]] for i in plain}

    def fit(self, models: list[Model], seed: int = 7, bursts: int = 3) -> dict[int, np.ndarray]:
        """Coefficients of each model that has training rows: (columns and a one) x classes of a logistic one, a flat vector of a perceptron."""
        moments, going, asked, done = self.moments(), {}, {}, {}
        self.rows, self.tables = {d: counts for d, (_, counts) in moments.items()}, None
        learnt = [i for i, m in enumerate(models) if m.design in moments]
        if plain := [i for i in learnt if models[i].kind == "logistic"]:
            going["logistic"] = logistic({i: self._of(moments[models[i].design], models[i].columns) for i in plain}, scaled=self.scaled)
        going |= {i: self._alone(i, perceptron(len(models[i].columns), self.classes, seed, bursts)) for i in learnt if i not in plain}
        for name, one in going.items():
            asked[name] = next(one)
        while asked:
            got = self.evaluate(models, {i: a for of in asked.values() for i, a in of.items()})
            got = {i: (loss / max(rows, 1), gradient / max(rows, 1)) for i, (rows, loss, gradient) in got.items()}
            for name in list(asked):
                try:
                    asked[name] = going[name].send({i: got[i] for i in asked[name]})
                except StopIteration as end:
                    done |= end.value
                    del asked[name]
        return done

    @staticmethod
    def _alone(i: int, steps: Generator) -> Generator:
        """One model's requests and answers as those of a group."""
        asked = next(steps)
        while True:
            try:
                asked = steps.send((yield {i: asked})[i])
            except StopIteration as end:
                return {i: end.value}

    @staticmethod
    def _of(moments: list[np.ndarray], columns: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        keep = np.append(columns, len(moments[0]) - 1)
        return moments[0][np.ix_(keep, keep)], moments[1]

    def tally(self, models: list[Model], fitted: dict[int, np.ndarray]) -> dict:
        """(rows, loss, rows by truth and prediction) of each model, over its test rows."""
        classes = self.classes

        def per_block(designs, given, block):
            part, _, y, codes, numbers = block
            for d in sorted({m.design for m, _ in given.values()}):
                if part in designs[d].test:
                    x = designs[d].matrix(codes, numbers, float)
                    for i, (model, w) in given.items():
                        if model.design == d:
                            p = probabilities(x, model, w, classes)
                            yield i, [len(y), _loss(p, y), np.bincount(y * classes + p.argmax(axis=1), minlength=classes * classes).reshape(classes, classes)]

        return self._sums(per_block, {i: (models[i], w) for i, w in fitted.items()})

    def auc(self, models: list[Model], fitted: dict[int, np.ndarray]) -> dict[int, float]:
        """Area under the curve of the probability of class 1 over the test rows, ties half, of the models that have rows of both classes there."""
        opened, shared, classes = self.packed.opened(), self.shared, self.classes
        sent = self.spark.sparkContext.broadcast({i: (models[i], w) for i, w in fitted.items()})

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for part, _, y, codes, numbers in opened(batches):
                for d in sorted({m.design for m, _ in sent.value.values()}):
                    if part in shared.value[d].test:
                        x = shared.value[d].matrix(codes, numbers, float)
                        for i, (model, w) in sent.value.items():
                            if model.design == d:
                                s = probabilities(x, model, w, classes)[:, 1]
                                yield pa.RecordBatch.from_pydict({"model": pa.array(np.full(len(y), i, np.int32)), "s": pa.array(s), "pos": pa.array((y == 1).astype(np.int64))})

        with settings(self.spark, BLOCK_READS):
            scored = materialise(self.packed.blocks.mapInArrow(run, "model int, s double, pos long"), "scores")
        return {r["model"]: r["auc"] for r in ranked(scored).where("auc IS NOT NULL").collect()}


#: Scores that a task sorts at once, about.
SORTED = 1 << 20


def ranked(scored: DataFrame) -> DataFrame:
    """(model, auc) of scored(model, s, pos) with s from 0 to 1; a task sorts thousandths of the scores, whose totals are added up apart."""
    ship_package(scored.sparkSession)
    placed = scored.select(F.col("model").cast("int").alias("model"), F.floor(F.col("s") * 1000).cast("int").alias("cell"), "s", F.col("pos").cast("long").alias("pos"))
    dealt = placed.repartition(max(scored.sparkSession.sparkContext.defaultParallelism, scored.count() // SORTED), "model", "cell")

    def inside(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = [[c.to_numpy() for c in b.columns] for b in batches if b.num_rows]
        if not held:
            return
        model, cell, s, pos = (np.concatenate(x) for x in zip(*held))
        order = np.lexsort((s, cell, model))
        model, cell, s, pos = (x[order] for x in (model, cell, s, pos))
        new = np.append(True, (model[1:] != model[:-1]) | (cell[1:] != cell[:-1]))
        first, group = np.flatnonzero(np.append(True, new[1:] | (s[1:] != s[:-1]))), np.flatnonzero(new)
        p, n = np.add.reduceat(pos, first), np.add.reduceat(1 - pos, first)  # of each different score
        at = np.searchsorted(first, group)
        before = np.cumsum(n) - n
        before -= np.repeat(before[at], np.diff(np.append(at, len(first))))
        sums = [np.add.reduceat(x, at) for x in (p * (2 * before + n), p, n)]
        yield pa.RecordBatch.from_arrays([pa.array(x) for x in (model[group], cell[group], *sums)], ["model", "cell", "wins", "pos", "neg"])

    with settings(scored.sparkSession, {ROWS_PER_BATCH: "100000"}):  # numbers only
        cells = materialise(dealt.mapInArrow(inside, "model int, cell int, wins long, pos long, neg long"), "cells")
    below = F.coalesce(F.sum("neg").over(W.partitionBy("model").orderBy("cell").rowsBetween(W.unboundedPreceding, -1)), F.lit(0))
    wins = F.sum(F.col("wins") + 2 * F.col("pos") * F.col("below"))
    return cells.withColumn("below", below).groupBy("model").agg(F.try_divide(wins.cast("double"), 2.0 * F.sum("pos") * F.sum("neg")).alias("auc"))


class Counted(Lockstep):
    """The same learners on the driver, over tables of few different records with how often each occurs: (records, labels, draws, times) to learn from and to be tested on. A budget's number of them."""

    def __init__(self, tables: list[tuple[tuple, tuple]], classes: int, scaled: bool = True):
        self.records, self.classes, self.scaled = tables, classes, scaled

    def moments(self) -> dict:
        out = {}
        for i, ((x, y, _, times), _) in enumerate(self.records):
            if len(y):
                one = np.column_stack([x, np.ones(len(y))])
                out[i] = [one.T @ (one * times[:, None]), np.bincount(y, times, self.classes)]
        return out

    def evaluate(self, models: list[Model], asked: dict[int, tuple[str, np.ndarray]]) -> dict:
        out = {}
        for i, (what, w) in asked.items():
            x, y, draw, times = self.records[models[i].design][0]
            if what != "all":
                rows = draw == (what == "held")
                x, y, times = x[rows], y[rows], times[rows]
            x, many = x[:, models[i].columns], float(times.sum())
            layers = _layers(w, [x.shape[1], *HIDDEN, self.classes]) if models[i].kind == "perceptron" else [(w[:-1], w[-1])]
            seen = _forward(x, layers)
            loss = -float(times @ np.log(np.clip(seen[-1][np.arange(len(y)), y], CLIP, 1 - CLIP)))
            back = seen[-1].copy()
            back[np.arange(len(y)), y] -= 1
            back *= times[:, None]
            if models[i].kind == "perceptron":
                out[i] = [many, loss, 0.0 if what == "held" else _backward(seen, layers, back)]
            else:
                out[i] = [many, loss, np.vstack([x.T @ back, back.sum(axis=0)])]
        return out

    def tally(self, models: list[Model], fitted: dict[int, np.ndarray]) -> dict:
        out = {}
        for i, w in fitted.items():
            x, y, _, times = self.records[models[i].design][1]
            if len(y):
                p = probabilities(x, models[i], w, self.classes)
                loss = -float(times @ np.log(np.clip(p[np.arange(len(y)), y], CLIP, 1 - CLIP)))
                out[i] = [float(times.sum()), loss, np.bincount(y * self.classes + p.argmax(axis=1), times, self.classes**2).reshape(self.classes, -1)]
        return out


def logistic(moments: dict[int, tuple[np.ndarray, np.ndarray]], penalty: float = 1.0, steps: int = STEPS, sweeps: int = 40, tolerance: float = 1e-10, scaled: bool = True) -> Generator:
    """Multinomial logistic regressions (by number: products of columns with a one last, rows of each class) with an l1 penalty on the summed loss, of columns brought to one deviation if scaled; intercepts are free.

    Accelerated proximal steps in the metric of the columns' products, which bounds the curvature anywhere; the step's own lasso is solved by coordinates, of all models at once.
    """
    names, width = list(moments), max(len(p) for p, _ in moments.values()) - 1
    classes, many = len(next(iter(moments.values()))[1]), len(names)
    mean, by, metric, cost = np.zeros((many, width)), np.ones((many, width)), np.zeros((many, width, width)), np.zeros((many, 1))
    used, b, size = np.zeros((many, width), bool), np.zeros((many, classes)), [len(p) - 1 for p, _ in moments.values()]
    for i, (products, counts) in enumerate(moments.values()):
        n, p = products[-1, -1], size[i]
        mean[i, :p] = products[-1, :-1] / n
        scale = np.sqrt(np.maximum(np.diag(products)[:-1] / n - mean[i, :p] ** 2, 0) * n / max(n - 1, 1))
        used[i, :p] = scale > 1e-7 * (1 + np.abs(mean[i, :p]))
        by[i, :p] = np.where(used[i, :p] & scaled, scale, 1.0)
        metric[i, :p, :p] = 0.5 * (products[:-1, :-1] / n - np.outer(mean[i, :p], mean[i, :p])) / np.outer(by[i, :p], by[i, :p])
        cost[i], b[i] = penalty / n, np.log(np.maximum(counts, 0.5) / n)
    metric[:, np.arange(width), np.arange(width)] = np.where(used, metric[:, np.arange(width), np.arange(width)] + 1e-8, 1.0)
    w, v, vb, t, live = np.zeros((many, width, classes)), np.zeros((many, width, classes)), b.copy(), np.ones(many), np.arange(many)

    def raw(i: int, w: np.ndarray, b: np.ndarray) -> np.ndarray:
        own = w[: size[i]] / by[i, : size[i], None]
        return np.vstack([own, b - mean[i, : size[i]] @ own])

    for _ in range(steps):
        got = yield {names[i]: ("all", raw(i, v[i], vb[i])) for i in live}
        residual, ends = np.zeros((len(live), width, classes)), np.zeros((len(live), classes))  # residual: slope of the bound at `new`
        for at, i in enumerate(live):
            g, p = got[names[i]][1], size[i]
            residual[at, :p], ends[at] = (g[:-1] - np.outer(mean[i, :p], g[-1])) / by[i, :p, None], g[-1]
        new, held, open_, price = v[live], metric[live], used[live], cost[live]
        places = np.flatnonzero(open_.any(axis=0))
        for _ in range(sweeps):
            moved = np.zeros(len(live))
            for j in places:
                curve, old = held[:, j, j, None], new[:, j]
                z = old - residual[:, j] / curve
                step = np.where(open_[:, j, None], np.sign(z) * np.maximum(0, np.abs(z) - price / curve) - old, 0.0)
                residual += held[:, j, :, None] * step[:, None]
                new[:, j] += step
                moved = np.maximum(moved, (step * step * curve).max(axis=1))
            if (moved < tolerance).all():
                break
        nb = vb[live] - ends / 0.5
        gap, gap_b = new - w[live], nb - b[live]
        slope = held @ gap
        back = ((v[live] - new) * slope).sum(axis=(1, 2)) + 0.5 * ((vb[live] - nb) * gap_b).sum(axis=1) > 0
        t[live] = np.where(back, 1.0, t[live])
        later = (1 + np.sqrt(1 + 4 * t[live] ** 2)) / 2
        ahead = (t[live] - 1) / later
        v[live], vb[live], t[live] = new + ahead[:, None, None] * gap, nb + ahead[:, None] * gap_b, later
        w[live], b[live] = new, nb
        live = live[(gap * slope).sum(axis=(1, 2)) + 0.5 * (gap_b**2).sum(axis=1) >= 10 * tolerance]
        if not len(live):
            break
    return {name: raw(i, w[i], b[i]) for i, name in enumerate(names)}


def perceptron(width: int, classes: int, seed: int, bursts: int, patience: int = 2) -> Generator:
    """Two hidden layers; fits of BURST steps, each begun where the last one ended, go on while the log-loss on the held-out rows falls."""
    rng, sizes = np.random.default_rng(seed), [width, *HIDDEN, classes]
    w = np.concatenate([rng.uniform(-2.4, 2.4, a * b + b) / np.sqrt(a) for a, b in zip(sizes, sizes[1:])])
    best, kept, waited = np.inf, w, 0
    for _ in range(bursts):
        w = yield from _descend(w, BURST)
        loss, _ = yield "held", w
        if loss < best - 1e-4:
            best, kept, waited = loss, w, 0
        elif (waited := waited + 1) >= patience:
            break
    return kept


def _descend(w: np.ndarray, steps: int, memory: int = 10) -> Generator:
    """Limited-memory quasi-Newton steps with a halving search."""
    loss, g = yield "own", w
    pairs: list[tuple[np.ndarray, np.ndarray]] = []
    for _ in range(steps):
        q, alphas = g.copy(), []
        for s, y in reversed(pairs):
            alphas.append((s @ q) / (s @ y))
            q -= alphas[-1] * y
        q *= (pairs[-1][0] @ pairs[-1][1]) / (pairs[-1][1] @ pairs[-1][1]) if pairs else 1 / max(np.linalg.norm(g), 1e-12)
        for (s, y), a in zip(pairs, reversed(alphas)):
            q += (a - (y @ q) / (s @ y)) * s
        size, slope = 1.0, -(g @ q)
        for _ in range(12):
            new_loss, new_g = yield "own", w - size * q
            if new_loss <= loss + 1e-4 * size * slope:
                break
            size /= 2
        else:
            return w
        s, y = -size * q, new_g - g
        if s @ y > 1e-10 * (y @ y):
            pairs = [*pairs, (s, y)][-memory:]
        fell, w, loss, g = loss - new_loss, w + s, new_loss, new_g
        if fell <= 1e-6 * abs(loss):
            break
    return w
