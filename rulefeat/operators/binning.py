"""Supervised discretisation: one cut a round, at the quantile of an interval that gains most."""

from __future__ import annotations

import zlib
from collections.abc import Generator, Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions.measures import entropy_term
from ..storage import ROWS_PER_BATCH, materialise, release, settings, ship_package
from .ranges import summed
from .sampling import numbered

#: Cells of the approximate path; distinct values (times classes) of a feature up to which one task finds all its cuts; edges of all features that may be sent to the tasks.
CELLS, IN_TASK, EDGES = 10_000, 2_000_000, 20_000_000
#: Counters of a grid that a task holds, and values between its edges that are looked up at once.
GRID_COUNTERS, LOOKED_UP = 2_000_000, 5_000_000


def histogram(df: DataFrame, features, label: str, cells: int | None = None) -> DataFrame:
    """(f, value, y, n): counts of each distinct value by class, or of `cells` cells between approximate quantiles where a feature has more values.

    A cell stands for its largest value; it holds 1.2 times its share of the records at most (beside those of one value), so a quantile is off by no more ranks than that.
    Records without value or label, and NaN, don't count.
    """
    if cells:
        return _cell_counts(df, list(features), label, cells)
    parts = [F.struct(F.lit(i).alias("f"), F.col(f"`{c}`").cast("double").alias("value")) for i, c in enumerate(features, 1)]
    long = df.where(F.col(label).isNotNull()).select(F.col(label).cast("string").alias("y"), F.explode(F.array(*parts)).alias("p")).select("p.f", "p.value", "y").where("value IS NOT NULL AND NOT isnan(value)")
    return long.groupBy("f", "value", "y").agg(F.count(F.lit(1)).alias("n"))


def _cell_counts(df: DataFrame, features: list[str], label: str, cells: int) -> DataFrame:
    """Edges by one aggregate (a row to the driver), then counts by cell in each task's arrays, which are added up by one small shuffle."""
    if cells * len(features) > EDGES:
        raise ValueError(f"{len(features)} features of {cells} cells: fewer cells, or fewer features at once")
    ship_package(df.sparkSession)
    clean = [F.when(~F.isnan(F.col(f"`{c}`").cast("double")), F.col(f"`{c}`").cast("double")).alias(f"v{i}") for i, c in enumerate(features, 1)]
    wide = df.where(F.col(label).isNotNull()).select(F.col(label).cast("string").alias("y"), *clean)
    shares = ", ".join(repr(i / cells) + "D" for i in range(1, cells + 1))
    row = wide.agg(*[F.expr(f"percentile_approx(v{i}, array({shares}), {10 * cells})").alias(f"e{i}") for i in range(1, len(features) + 1)]).first()
    edges = df.sparkSession.sparkContext.broadcast([np.unique(np.array(e or [], float)) for e in row])

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tables, classes = edges.value, {}
        for batch in batches:
            y = batch.column(0).dictionary_encode()
            at = np.array([classes.setdefault(c, len(classes)) for c in y.dictionary.to_pylist()], np.int64)[y.indices.to_numpy()]
            for i, cuts in enumerate(tables, 1):
                held = batch.column(i)
                known = np.asarray(held.is_valid())
                place = np.searchsorted(cuts, held.drop_null().to_numpy())
                key, n = np.unique(at[known] * len(cuts) + np.minimum(place, max(0, len(cuts) - 1)), return_counts=True)
                names = np.array(list(classes), object)
                if len(key):
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(key), i, np.int32)), pa.array(cuts[key % len(cuts)]), pa.array(names[key // len(cuts)], pa.string()), pa.array(n.astype(np.int64))], ["f", "value", "y", "n"])

    with settings(df.sparkSession, {ROWS_PER_BATCH: "100000"}):  # numbers only
        return materialise(wide.mapInArrow(count, "f int, value double, y string, n long").groupBy("f", "value", "y").agg(F.sum("n").alias("n")), "cells")


def interval_candidates(weights: np.ndarray, parts: int) -> list[int]:
    """Places of the interior quantiles: the value at rank ceil(j m / parts), without the last place."""
    ends = np.cumsum(weights)
    ranks = [-(-j * int(ends[-1]) // parts) for j in range(1, parts)]
    return sorted({p for p in np.searchsorted(ends, ranks).tolist() if p < len(weights) - 1})


def _part(counts: np.ndarray) -> np.ndarray:
    """n times the entropy of the class counts along the last axis."""
    n = counts.sum(axis=-1)
    with np.errstate(divide="ignore", invalid="ignore"):
        inner = np.where(counts > 0, counts * np.log(counts), 0.0).sum(axis=-1)
        return np.where(n > 0, n * np.log(np.maximum(n, 1)), 0.0) - inner


def fit_cuts(values: np.ndarray, counts: np.ndarray, k: int, parts: int, min_gain: float = 0.0) -> list[tuple[float, float]]:
    """(cut, gain of all cuts so far) in the order of choice; values ascend, counts has a row of class counts for each.

    Of equal gains the lower cut wins. The search ends at k intervals, where no interval can be split, or where a cut adds less than min_gain.
    """
    n = counts.sum()
    if not n:
        return []
    total = float(_part(counts.sum(axis=0)))
    spans, loss, out = [(0, len(values))], {(0, len(values)): total}, []
    while len(spans) < k:
        best = None
        left = sum(loss.values())
        for lo, hi in spans:
            own = counts[lo:hi]
            running = np.cumsum(own, axis=0)
            for p in interval_candidates(own.sum(axis=1), parts):
                a, b = float(_part(running[p])), float(_part(running[-1] - running[p]))
                gain = round((total - (left - loss[lo, hi] + a + b)) / n, 12)
                if best is None or gain > best[0]:
                    best = (gain, lo, lo + p + 1, hi, a, b)
        if best is None or (out and best[0] - out[-1][1] < min_gain) or (not out and best[0] < min_gain):
            break
        gain, lo, mid, hi, a, b = best
        spans = sorted([s for s in spans if s != (lo, hi)] + [(lo, mid), (mid, hi)])
        del loss[lo, hi]
        loss |= {(lo, mid): a, (mid, hi): b}
        out.append((float(values[mid - 1]), gain))
    return out


def cut_rounds(whole: np.ndarray, k: int, parts: int, min_gain: float = 0.0) -> Generator:
    """fit_cuts() by ranks, of a feature with these class counts: a round asks for ranks (from 1), is sent {rank: (value, records up to it, their class counts)}, and the cuts are returned."""
    last, out = int(whole.sum()), []
    if not last:
        return out
    upto, spans = {0: np.zeros(len(whole)), last: whole}, {(0, last): None}  # an interval is (rank before it, last rank), with its candidates
    part = lambda a, b: float(_part(upto[b] - upto[a]))
    for _ in range(k - 1):
        wanted = {(lo, hi): [lo + -(-j * (hi - lo) // parts) for j in range(1, parts)] for (lo, hi), found in spans.items() if found is None}
        if wanted:
            got = yield sorted({r for ranks in wanted.values() for r in ranks})
            upto |= {end: counts for _, end, counts in got.values()}
            spans |= {s: sorted({got[r][:2] for r in ranks if got[r][1] < s[1]}) for s, ranks in wanted.items()}
        total, loss, best = part(0, last), {s: part(*s) for s in spans}, None
        left = sum(loss.values())
        for lo, hi in sorted(spans):
            for value, end in spans[lo, hi]:
                gain = round((total - (left - loss[lo, hi] + part(lo, end) + part(end, hi))) / last, 12)
                if best is None or gain > best[0]:
                    best = (gain, value, lo, end, hi)
        if best is None or best[0] - (out[-1][1] if out else 0.0) < min_gain:
            break
        gain, value, lo, end, hi = best
        del spans[lo, hi]
        spans |= {(lo, end): None, (end, hi): None}
        out.append((float(value), gain))
    return out


def _all_rounds(going: dict, look_up) -> dict:
    """The cuts of each of the cut_rounds(), where look_up({name: ranks}) -> {name: {rank: ...}} answers all of a round at once."""
    done, asked = {}, {}

    def step(name, sent):
        try:
            asked[name] = going[name].send(sent)
        except StopIteration as end:
            done[name] = end.value

    for name in going:
        step(name, None)
    while asked:
        now = dict(asked)
        asked.clear()
        got = look_up(now)
        for name in now:
            step(name, got[name])
    return done


def fit_cuts_by_ranges(counts: DataFrame, k: int, parts: int, min_gain: float = 0.0) -> dict[int, list[tuple[float, float]]]:
    """fit_cuts() of counts(f, value, y, n) of any number of values, as {f: cuts}: running class counts along the values, made range by range, are stored once;
    then a round is one job that looks up the quantiles of the intervals that are new in it (a few rows a feature)."""
    spark = counts.sparkSession
    classes = [r["y"] for r in counts.select("y").distinct().orderBy("y").collect()]
    wide = counts.groupBy("f", "value").agg(F.sum("n").alias("n"), *[F.sum(F.when(F.col("y") == c, F.col("n")).otherwise(0)).alias(f"n{i}") for i, c in enumerate(classes)])
    along = materialise(summed(wide, [F.col("f"), F.col("value")], {"end": "n"} | {f"c{i}": f"n{i}" for i in range(len(classes))}, ["f"], "values").withColumn("start", F.col("end") - F.col("n")), "running-classes")
    whole = along.groupBy("f").agg(*[F.max(f"c{i}").alias(f"c{i}") for i in range(len(classes))]).collect()
    vector = lambda r: np.array([r[f"c{i}"] for i in range(len(classes))], float)

    def look_up(wanted: dict[int, list[int]]) -> dict:
        asked = spark.createDataFrame([(f, r) for f, ranks in wanted.items() for r in ranks], "f int, rank long")
        out = {f: {} for f in wanted}
        for r in along.join(F.broadcast(asked), "f").where("rank > start AND rank <= end").collect():  # at most parts - 1 rows an interval
            out[r["f"]][r["rank"]] = (r["value"], r["end"], vector(r))
        return out

    out = _all_rounds({r["f"]: cut_rounds(vector(r), k, parts, min_gain) for r in whole}, look_up)
    release(along)
    return out


def fit_together(df: DataFrame, features, label: str, classes: int, part: str, sets: dict[int, list[int]], k: int, parts: int = 20, grid: int | None = None) -> dict[int, BinnerModel]:
    """The EntropyBinner of k intervals of each set of parts (an integer column from 0; `label` is one below `classes`), with the same cuts, from passes that all sets and features share.

    Records are counted once by part and class at the values of a grid and between these. Values between two of them are looked up where a quantile falls there, in few passes for all. The grid is made of some records' values:
    more of them only mean fewer values to look up, and no cut hangs on it. Where more than LOOKED_UP are wanted, each set is fitted by itself.
    """
    features, n_parts = list(features), max(max(s) for s in sets.values()) + 1
    if k < 2 or not features:
        return {s: BinnerModel(features, {}) for s in sets}
    ship_package(df.sparkSession)
    spark, many = df.sparkSession, n_parts * classes
    grid = grid or max(200, min(4000, GRID_COUNTERS // (2 * many * len(features))))
    clean = [F.col(f"`{c}`").cast("double").alias(f"v{i}") for i, c in enumerate(features)]
    held = sorted({p for s in sets.values() for p in s})
    wide = df.where(F.col(label).isNotNull() & F.col(part).isin(held)).select((F.col(part) * classes + F.col(label).cast("int")).cast("int").alias("g"), *clean)
    rows = wide.count()
    some = wide.drop("g").sample(False, min(1.0, 10 * grid / max(rows, 1)), 7).toArrow()
    known = [np.unique(c.drop_null().to_numpy()) for c in some.columns]
    known = [v[~np.isnan(v)] for v in known]
    edges = [v if len(v) <= grid else v[np.linspace(0, len(v) - 1, grid).astype(int)] for v in known]
    # cells by place: 2i is between edge i - 1 and edge i, 2i + 1 at edge i
    ends = np.cumsum([0, *(2 * len(e) + 1 for e in edges)])
    sent = spark.sparkContext.broadcast(edges)

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(many * int(ends[-1]), np.int64)
        for batch in batches:
            g = batch.column(0).to_numpy().astype(np.int64)
            for i, e in enumerate(sent.value):
                x = batch.column(1 + i).fill_null(np.nan).to_numpy(zero_copy_only=False)
                at, there = np.searchsorted(e, x), ~np.isnan(x)
                cell = 2 * at + (np.append(e, np.nan)[at] == x)
                size = 2 * len(e) + 1
                total[many * ends[i] : many * ends[i + 1]] += np.bincount((g * size + cell)[there], minlength=many * size)
        yield pa.RecordBatch.from_pydict({"counts": pa.array([zlib.compress(total.tobytes(), 1)], pa.binary())})

    batch_rows = {ROWS_PER_BATCH: str(max(5000, 2_000_000 // (len(features) + 1)))}
    few = wide.coalesce(spark.sparkContext.defaultParallelism)
    with settings(spark, batch_rows):
        total = sum(np.frombuffer(zlib.decompress(r[0]), np.int64) for r in few.mapInArrow(count, "counts binary").collect())  # one row a core
    table = [total[many * a : many * b].reshape(n_parts, classes, b - a).transpose(2, 0, 1) for a, b in zip(ends, ends[1:])]
    running = {(s, i): np.cumsum(t[:, own].sum(axis=1), axis=0) for s, own in sets.items() for i, t in enumerate(table)}
    found: dict[tuple[int, int], tuple[np.ndarray, np.ndarray]] = {}

    def values_between(cells: set[tuple[int, int]]) -> bool:
        """Into found: the values in cells (feature, place), and their records by part and class. False if there are too many."""
        bounds = {}
        for i, c in sorted(cells):
            e = np.concatenate([[-np.inf], edges[i], [np.inf]])
            bounds.setdefault(i, []).append((e[c // 2], e[c // 2 + 1], c))
        own = {i: tuple(np.array(x) for x in zip(*b)) for i, b in bounds.items()}
        asked = spark.sparkContext.broadcast(own)

        def look(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                g = batch.column(0).to_numpy().astype(np.int64)
                for at, (i, (low, high, cell)) in enumerate(asked.value.items()):
                    x = batch.column(1 + at).fill_null(np.nan).to_numpy(zero_copy_only=False)
                    j = np.searchsorted(low, x) - 1
                    if low[0] == -np.inf:
                        j[x == -np.inf] = 0
                    met = np.flatnonzero((j >= 0) & ((x < high[j]) | ((high[j] == np.inf) & (x == np.inf))))
                    if not len(met):
                        continue
                    value, of = np.unique(x[met], return_inverse=True)
                    key, n = np.unique(of * many + g[met], return_counts=True)
                    value = value[key // many]
                    place = cell[np.maximum(np.searchsorted(low, value) - 1, 0)]
                    columns = [np.full(len(key), i, np.int32), place.astype(np.int32), value, (key % many).astype(np.int32), n.astype(np.int64)]
                    yield pa.RecordBatch.from_arrays([pa.array(c) for c in columns], ["f", "cell", "value", "g", "n"])

        with settings(spark, batch_rows):
            met = few.select("g", *[f"v{i}" for i in own]).mapInArrow(look, "f int, cell int, value double, g int, n long").groupBy("f", "cell", "value", "g").agg(F.sum("n").alias("n")).limit(LOOKED_UP + 1).toArrow()
        if met.num_rows > LOOKED_UP:
            return False
        f, cell, value, g, n = (c.to_numpy() for c in met.columns)
        order = np.lexsort([value, cell, f])
        f, cell, value, g, n = (x[order] for x in (f, cell, value, g, n))
        first = np.flatnonzero(np.append(True, (f[1:] != f[:-1]) | (cell[1:] != cell[:-1]))) if len(f) else []
        for lo, hi in zip(first, [*first[1:], len(f)]):
            own_values, of = np.unique(value[lo:hi], return_inverse=True)
            counts = np.zeros((len(own_values), many), np.int64)
            counts[of, g[lo:hi]] = n[lo:hi]
            found[int(f[lo]), int(cell[lo])] = own_values, counts.reshape(-1, n_parts, classes)
        return True

    missed: set[tuple[int, int]] = set()

    def look_up(wanted: dict[tuple[int, int], list[int]]) -> dict:
        out = {}
        for (s, i), ranks in wanted.items():
            out[s, i], along = {}, running[s, i]
            for r, c in zip(ranks, np.searchsorted(along.sum(axis=1), ranks).tolist()):
                if c % 2 == 0 and (i, c) in found:
                    values, counts = found[i, c]
                    inside = np.cumsum(counts[:, sets[s]].sum(axis=1), axis=0) + (along[c - 1] if c else 0)
                    j = int(np.searchsorted(inside.sum(axis=1), r))
                    value, upto = values[j], inside[j]
                else:
                    value, upto = edges[i][c // 2] if c // 2 < len(edges[i]) else np.inf, along[c]
                    if c % 2 == 0:
                        missed.add((i, c))
                out[s, i][r] = (float(value), int(upto.sum()), upto.astype(float))
        return out

    while True:  # a run that misses nothing is exact; one that does tells nearly all values that the next ones ask for
        missed.clear()
        cuts = _all_rounds({name: cut_rounds(along[-1].astype(float), k, parts) for name, along in running.items()}, look_up)
        if not missed:
            break
        if not values_between(missed):
            return {s: EntropyBinner(k, parts, features, label).fit(df.where(F.col(part).isin(own))) for s, own in sets.items()}
    return {s: BinnerModel(features, {i + 1: cuts[s, i] for i in range(len(features))}) for s in sets}


@dataclass
class BinnerModel:
    features: list[str]
    cuts: dict[int, list[tuple[float, float]]]  # by ordinal, in order of choice

    def truncate(self, k: int) -> BinnerModel:
        """The model of a smaller k: cuts are nested, so one fit serves all k."""
        return BinnerModel(self.features, {f: c[: max(0, k - 1)] for f, c in self.cuts.items()})

    def table(self, spark) -> DataFrame:
        rows = [(f, i, float(c), float(g)) for f, cs in self.cuts.items() for i, (c, g) in enumerate(cs, 1)]
        return spark.createDataFrame(rows, "f int, cut_no int, cut double, gain double")

    def interval(self, ordinal: int) -> Column:
        """b1 ... bk by (lo, cut]; null stays null, NaN is null."""
        column = F.col(f"`{self.features[ordinal - 1]}`").cast("double")
        out, cuts = None, sorted(c for c, _ in self.cuts.get(ordinal, []))
        for i, c in enumerate(cuts, 1):
            out = F.when(column <= c, F.lit(f"b{i}")) if out is None else out.when(column <= c, F.lit(f"b{i}"))
        last = F.lit(f"b{len(cuts) + 1}")
        return F.when(column.isNotNull() & ~F.isnan(column), last if out is None else out.otherwise(last))

    def transform(self, df: DataFrame, suffix: str = "_bin", keep_original: bool = True) -> DataFrame:
        binned = [self.interval(i).alias(f"{c}{suffix}") for i, c in enumerate(self.features, 1)]
        others = [F.col(f"`{c}`") for c in df.columns if keep_original or c not in self.features]
        return df.select(*others, *binned)


class EntropyBinner:
    """k intervals for each continuous feature by the label; `parts` quantiles are tried in every interval in each round (20 by default).

    quantiles="exact" keeps all distinct values; "approx" compresses each feature to `cells` cells first. All rounds of a feature
    run in one task on its counts, if these are no more than IN_TASK; else its rounds are jobs over ranges of its values, with the same cuts. k=0 or 1 leaves a feature whole.
    """

    def __init__(self, k: int, parts: int = 20, features: list[str] | None = None, label: str = "y", quantiles: str = "exact", cells: int = CELLS, min_gain: float = 0.0, in_task: int = IN_TASK):
        self.in_task = in_task
        self.k, self.parts, self.features, self.label, self.quantiles, self.cells, self.min_gain = k, parts, list(features or []), label, quantiles, cells, min_gain

    def fit(self, df: DataFrame) -> BinnerModel:
        if self.k < 2 or not self.features:
            return BinnerModel(self.features, {})
        ship_package(df.sparkSession)
        counts = histogram(df, self.features, self.label, self.cells if self.quantiles == "approx" else None)
        if self.quantiles != "approx":
            counts = materialise(counts, "histogram")
        k, parts, min_gain = self.k, self.parts, self.min_gain
        large = [r["f"] for r in counts.groupBy("f").agg(F.count(F.lit(1)).alias("rows")).where(F.col("rows") > self.in_task).select("f").collect()]

        def cut(rows: pd.DataFrame) -> pd.DataFrame:
            wide = rows.pivot_table(index="value", columns="y", values="n", fill_value=0, aggfunc="sum").sort_index()
            found = fit_cuts(wide.index.to_numpy(), wide.to_numpy().astype(float), k, parts, min_gain)
            f = int(rows["f"].iloc[0])
            return pd.DataFrame([(f, i, c, g) for i, (c, g) in enumerate(found, 1)], columns=["f", "cut_no", "cut", "gain"])

        small = counts.where(~F.col("f").isin(large)) if large else counts
        rows = small.groupBy("f").applyInPandas(cut, "f int, cut_no int, cut double, gain double").collect()  # (k - 1) rows a feature
        cuts: dict[int, list] = {i: [] for i in range(1, len(self.features) + 1)}
        for r in sorted(rows, key=lambda r: (r["f"], r["cut_no"])):
            cuts[r["f"]].append((r["cut"], r["gain"]))
        if large:
            cuts |= fit_cuts_by_ranges(counts.where(F.col("f").isin(large)), k, parts, min_gain)
        release(counts)
        return BinnerModel(self.features, cuts)


def quantile_candidates(df: DataFrame, features, label: str, parts: int = 20) -> DataFrame:
    """(f, j, cut): the first round's candidates by DataFrame operations, on distinct values rather than rows."""
    counts = histogram(df, features, label).groupBy("f", "value").agg(F.sum("n").alias("n"))
    along = W.partitionBy("f").orderBy("value")
    ends = counts.withColumn("end", F.sum("n").over(along)).withColumn("m", F.sum("n").over(W.partitionBy("f")))
    ends = ends.withColumn("start", F.col("end") - F.col("n"))
    j = F.explode(F.sequence(F.lit(1), F.lit(parts - 1)))
    ranked = ends.select("f", "value", "start", "end", "m", j.alias("j")).withColumn("rank", F.expr(f"(j * m + {parts - 1}) div {parts}"))
    return ranked.where("rank > start AND rank <= end").select("f", "j", F.col("value").alias("cut"))


def first_cut(df: DataFrame, features, label: str, parts: int = 20) -> DataFrame:
    """(f, cut, gain) of the best first cut, by DataFrame operations."""
    counts = histogram(df, features, label)
    candidates = quantile_candidates(df, features, label, parts).select("f", "cut").distinct()
    classes = counts.groupBy("f", "y").agg(F.sum("n").alias("total"))
    below = counts.join(candidates, "f").where("value <= cut").groupBy("f", "cut", "y").agg(F.sum("n").alias("low"))
    grid = candidates.join(classes, "f").join(below, ["f", "cut", "y"], "left").withColumn("low", F.coalesce("low", F.lit(0)))
    side = W.partitionBy("f", "cut")
    n, low = F.sum("total").over(side), F.sum("low").over(side)
    high = F.col("total") - F.col("low")
    terms = grid.select("f", "cut", n.alias("n"), low.alias("n_low"), entropy_term(F.col("total"), n).alias("whole"), entropy_term(F.col("low"), low).alias("a"), entropy_term(high, n - low).alias("b"))
    gained = terms.groupBy("f", "cut", "n", "n_low").agg(F.sum("whole").alias("whole"), F.sum("a").alias("a"), F.sum("b").alias("b")).where("n_low < n")
    gain = F.round(F.col("whole") - F.col("n_low") / F.col("n") * F.col("a") - (F.col("n") - F.col("n_low")) / F.col("n") * F.col("b"), 9)
    return gained.withColumn("gain", gain).withColumn("r", F.row_number().over(W.partitionBy("f").orderBy(F.col("gain").desc(), "cut"))).where("r = 1").select("f", "cut", "gain")


def quantile_classes(df: DataFrame, response: str, classes: int = 5, tie: str | None = None, exact: bool = True) -> DataFrame:
    """df with `y`, the response's class 1..classes by quantiles: by exact ranks, numbered range by range (nulls come first), or by approximate cut points without a sort."""
    if exact:
        rows = numbered(df, [response, *([tie] if tie else [])])
        n = rows.count()
        least, more = n // classes, n % classes  # the first `more` classes have one record more
        first = more * (least + 1)
        late = F.floor((F.col("at") - first) / max(1, least)) + more + 1
        return rows.withColumn("y", F.when(F.col("at") < first, F.floor(F.col("at") / (least + 1)) + 1).otherwise(late).cast("int")).drop("at")
    cuts = df.stat.approxQuantile(response, [i / classes for i in range(1, classes)], 1e-4)
    out = F.lit(1)
    for c in cuts:
        out = out + (F.col(response) > c).cast("int")
    return df.withColumn("y", out)
