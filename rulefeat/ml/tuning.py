"""Grid search over intervals and numbers of rules, with smoothing and refit."""

from __future__ import annotations

from collections.abc import Callable
from concurrent.futures import ThreadPoolExecutor
from dataclasses import replace
from functools import reduce

import numpy as np
from pyspark.ml.functions import array_to_vector
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..operators.binning import EntropyBinner, fit_together
from ..operators.selectors import mine, recut
from ..storage import materialise
from .attach import assemble, codes
from .baselines import scales
from .learners import scores
from .lockstep import Design, Lockstep, Model, Packed, cube, pack


def prepared(df: DataFrame, model, categorical, continuous, k: int) -> tuple[DataFrame, list[str]]:
    """df with the binned columns of the model cut to k intervals, and the list of categorical columns."""
    if k < 2 or not continuous:
        return df, list(categorical)
    return model.truncate(k).transform(df), [*categorical, *(f"{c}_bin" for c in continuous)]


#: Rows that a partition of a learner's table should have at least: each of its many passes starts a task for every partition.
ROWS = 50_000


def compact(df: DataFrame, label: str = "assembled") -> DataFrame:
    """df stored, and read again in few partitions where it is small."""
    kept = materialise(df, label)
    return kept.coalesce(max(1, kept.count() // ROWS))


def antecedents(mined, d_conf: int) -> list[dict]:
    """Distinct antecedents of the d_conf best rules in the order in which the ranking first has them, each with that place; those of fewer rules are the first of them."""
    seen: dict[tuple, dict] = {}
    for r in recut(mined, d_conf).rules.orderBy("rank").collect():  # a budget's number
        seen.setdefault((r["f1"], r["v1"], r["f2"], r["v2"]), {"size": r["size"], "f1": r["f1"], "v1": r["v1"], "f2": r["f2"], "v2": r["v2"], "first": r["rank"]})
    return list(seen.values())


def grid(train: DataFrame, valid: DataFrame, ks, d_confs, d_freq: int, label: str, categorical, continuous, fit: Callable, criterion: str = "log_loss", parts: int = 20, mode: str = "binned_plus_rules", threads: int = 2) -> DataFrame:
    """(k, d_conf, criterion, score): one binning fit for all k, one mining run and one stored table for each k, one learner for each (k, d_conf).

    train and valid have a numeric column `label` besides the string label that the miner uses; fit(train) gives a fitted classifier.
    The rule lists of one k are cuts of one ranking, so a learner's columns are the first ones of the table. Fits of one k are independent jobs.
    """
    spark = train.sparkSession
    binner = EntropyBinner(max(ks), parts, list(continuous), label).fit(train)
    out = []
    for k in ks:
        (a, columns), (b, _) = prepared(train, binner, categorical, continuous, k), prepared(valid, binner, categorical, continuous, k)
        known = codes(a, columns)
        rows = antecedents(mine(a, label, columns, d_freq, True), max(d_confs)) if columns and max(d_confs) else []
        how, shown = (mode, () if mode == "binned_plus_rules" else continuous) if k >= 2 else ("label_plus_rules", continuous)
        x, z = (compact(assemble(d, how, rows, columns, shown, known, as_array=True).select("label", "features")) for d in (a, b))
        first = z.select(F.size("features")).first() or x.select(F.size("features")).first()
        base = (first[0] if first else 0) - len(rows)
        taken = {d_conf: base + sum(r["first"] <= d_conf for r in rows) for d_conf in d_confs}

        def score(width: int, x=x, z=z) -> float:
            cut = lambda d: d.select("label", array_to_vector(F.slice("features", 1, max(1, width))).alias("features"))
            return float(scores(fit(cut(x)).transform(cut(z)))[criterion])

        with ThreadPoolExecutor(threads) as pool:
            widths = sorted(set(taken.values()))
            got = dict(zip(widths, pool.map(score, widths)))
        out += [(k, d_conf, criterion, got[taken[d_conf]]) for d_conf in d_confs]
    return spark.createDataFrame(out, "k int, d_conf int, criterion string, score double")


def smooth(scored: DataFrame, kind: str = "gaussian", sigma: float = 1.0, radius: int = 2, sigma_score: float = 0.1) -> DataFrame:
    """The grid with a smoothed score at each point, from neighbours by their places on the axes (a grid is a few hundred points).

    kinds: gaussian, box, median, bilateral (gaussian weights that also fall with the difference in score).
    """
    places = lambda c: F.dense_rank().over(W.orderBy(c))
    at = scored.withColumns({"i": places("k"), "j": places("d_conf")})
    other = at.select(F.col("i").alias("oi"), F.col("j").alias("oj"), F.col("score").alias("oscore"))
    near = at.join(F.broadcast(other), (F.abs(F.col("i") - F.col("oi")) <= radius) & (F.abs(F.col("j") - F.col("oj")) <= radius))
    square = (F.col("i") - F.col("oi")) * (F.col("i") - F.col("oi")) + (F.col("j") - F.col("oj")) * (F.col("j") - F.col("oj"))
    if kind == "median":
        value = F.median("oscore")
    else:
        w = F.exp(-square / (2.0 * sigma * sigma)) if kind in ("gaussian", "bilateral") else F.lit(1.0)
        if kind == "bilateral":
            w = w * F.exp(-F.pow(F.col("score") - F.col("oscore"), 2) / (2.0 * sigma_score * sigma_score))
        value = F.sum(w * F.col("oscore")) / F.sum(w)
    return near.groupBy(*scored.columns).agg(value.alias("smoothed"))


def best(smoothed: DataFrame, lower_is_better: bool = True):
    order = F.col("smoothed").asc() if lower_is_better else F.col("smoothed").desc()
    return smoothed.orderBy(order, "k", "d_conf").first()


def refit(train: DataFrame, valid: DataFrame, test: DataFrame, k: int, d_conf: int, d_freq: int, label: str, categorical, continuous, fit: Callable, parts: int = 20) -> tuple[dict, DataFrame]:
    """Fit the whole chain on train and validation together; scores and predictions on test."""
    both = train.unionByName(valid)
    binner = EntropyBinner(k, parts, list(continuous), label).fit(both)
    (a, columns), (b, _) = prepared(both, binner, categorical, continuous, k), prepared(test, binner, categorical, continuous, k)
    known = codes(a, columns)
    rows = sorted(recut(mine(a, label, columns, d_freq, True), d_conf).features.collect(), key=lambda r: r["feature_id"]) if columns and d_conf else []
    how, shown = ("binned_plus_rules", ()) if k >= 2 else ("label_plus_rules", continuous)
    x, z = (compact(assemble(d, how, rows, columns, shown, known).select("label", "features")) for d in (a, b))
    predicted = fit(x).transform(z)
    return scores(predicted), predicted


def mined_apart(parts: dict[int, DataFrame], label: str, columns, d_freq: int):
    """One mining run, per class, of several records' frames (number: frame) as groups `cv`; a frame's columns may mean other intervals than the next one's."""
    return mine(reduce(DataFrame.unionByName, [d.select(F.lit(i).alias("cv"), label, *columns) for i, d in parts.items()]), label, columns, d_freq, True, by=("cv",))


def mined_together(packed: Packed, counted, groups: dict[int, tuple[list[tuple[str, list[float] | None]], list[int]]], d_freq: int, frames: Callable[[], dict[int, DataFrame]], label: str, columns):
    """The same of groups (columns (name, cuts), parts) from the counts of a Cube; without one, of frames() with the label and columns."""
    if counted is None:
        return mined_apart(frames(), label, columns, d_freq)
    views = {g: ([(counted.first[c], packed.table(c, x)[:-1]) for c, x in own], list(parts)) for g, (own, parts) in groups.items()}
    return mine(replace(counted, groups=views), label, columns, d_freq, True, by=("cv",))


def code_column(packed: Packed, column: str, cuts: list[float], known: list[str]) -> tuple:
    """The design column of label codes: the place among the known values, -1 for others."""
    at = {v: i for i, v in enumerate(known)}
    return "code", packed.place(column), np.array([at.get(v, -1) for v in packed.table(column, cuts)], np.float32)


def rule_column(packed: Packed, columns: list[tuple[str, list[float]]], rule) -> tuple:
    """The 0/1 design column of an antecedent over columns (name, cuts)."""
    held = []
    for f, v in (("f1", "v1"), ("f2", "v2")):
        if rule[f] is not None:
            name, cuts = columns[rule[f] - 1]
            held.append((packed.place(name), np.array([x == rule[v] for x in packed.table(name, cuts)])))
    return "rule", held


def interval_names(cuts: list[float]) -> list[str]:
    """The intervals of a fitted feature as label codes order them: none is empty in the rows that it was fitted on."""
    return sorted(f"b{i}" for i in range(1, len(cuts) + 2))


def binned_designs(packed: Packed, binner, train: DataFrame, ks, most: int, d_freq: int, label: str, continuous, names: list[str], parts: tuple[frozenset, frozenset]) -> tuple[list[Design], list[list[int]]]:
    """For each k a design of interval codes and the antecedents of the `most` best rules (of the numbers themselves where k is below 2), and the place in the ranking that each antecedent needs."""
    bins, cut = [f"{c}_bin" for c in continuous], {k: binner.truncate(k) for k in ks}
    columns_of = {k: [(c, [x for x, _ in cut[k].cuts[i]]) for i, c in enumerate(continuous, 1)] if k >= 2 else [] for k in ks}
    ranked: dict[int, dict[tuple, int]] = {k: {} for k in ks}
    if max(ks) >= 2 and most:
        split = {k: own for k, own in columns_of.items() if own}
        mined = mined_together(packed, cube(packed, names, parts[0]), {k: (own, parts[0]) for k, own in split.items()}, d_freq, lambda: {k: cut[k].transform(train) for k in split}, label, bins)
        for r in recut(mined, most).rules.orderBy("cv", "rank").collect():  # a budget's number for each k
            ranked[r["cv"]].setdefault((r["f1"], r["v1"], r["f2"], r["v2"]), r["rank"])
    designs, firsts = [], []
    for k in ks:
        own = columns_of[k]
        columns = [code_column(packed, c, x, interval_names(x)) for c, x in own] or [("number", i) for i in range(len(continuous))]
        columns += [rule_column(packed, own, dict(zip(("f1", "v1", "f2", "v2"), a))) for a in ranked[k]]
        designs.append(Design(columns, *parts))
        firsts.append(list(ranked[k].values()))
    return designs, firsts


def packed_for(binner, df: DataFrame, label: str, part: str, draw: str, continuous, classes: int) -> Packed:
    """df packed at the finest intervals of the binner, its numbers standardised: learners want one scale."""
    return pack(df, label, part, draw, [], continuous, {}, {c: [x for x, _ in binner.cuts.get(i, [])] for i, c in enumerate(continuous, 1)}, classes, scales(df, continuous))


def _prefixes(designs: list[Design], firsts: list[list[int]], d_confs) -> dict[tuple[int, int], int]:
    """Columns of each design (by place) that the rules of each d_conf need: the first ones."""
    return {(i, d): len(design.columns) - len(first) + sum(f <= d for f in first) for i, (design, first) in enumerate(zip(designs, firsts)) for d in d_confs}


def grid_together(df: DataFrame, ks, d_confs, d_freq: int, label: str, continuous, names: list[str], learners=("logistic",), criterion: str = "log_loss", parts: int = 20) -> dict[str, DataFrame]:
    """grid() of each learner, all points in lockstep, over df(…, `y` as the miner's label, `label` as its place among the names, part: 0 train, 1 validation, draw)."""
    ks, train, classes = list(ks), df.where("part = 0"), len(names)
    binner = fit_together(df, continuous, "label", classes, "part", {0: [0]}, max(ks), parts)[0]
    packed = packed_for(binner, df, "label", "part", "draw", continuous, classes)
    designs, firsts = binned_designs(packed, binner, train, ks, max(d_confs), d_freq, label, continuous, names, (frozenset([0]), frozenset([1])))
    width = _prefixes(designs, firsts, d_confs)
    points = sorted({(i, w, learner) for (i, _), w in width.items() for learner in learners})
    models = [Model(i, np.arange(w), learner) for i, w, learner in points]
    engine = Lockstep(packed, designs)
    got = engine.tally(models, engine.fit(models))
    value = {p: measures(got[at])[criterion] for at, p in enumerate(points) if at in got}
    rows = {learner: [(k, d, criterion, value.get((i, width[i, d], learner))) for i, k in enumerate(ks) for d in d_confs] for learner in learners}
    return {learner: df.sparkSession.createDataFrame(r, "k int, d_conf int, criterion string, score double") for learner, r in rows.items()}


def refit_together(df: DataFrame, chosen: list[tuple[str, int, int]], d_freq: int, label: str, continuous, names: list[str], parts: int = 20) -> list[tuple[dict, np.ndarray]]:
    """refit() of each (learner, k, d_conf) in lockstep, learnt on parts 0 and 1 of df and scored on part 2: measures, and test rows by truth and prediction."""
    ks, most = sorted({k for _, k, _ in chosen}), max(d for _, _, d in chosen)
    both, classes = df.where("part < 2"), len(names)
    binner = fit_together(df, continuous, "label", classes, "part", {0: [0, 1]}, max(ks), parts)[0]
    packed = packed_for(binner, df, "label", "part", "draw", continuous, classes)
    designs, firsts = binned_designs(packed, binner, both, ks, most, d_freq, label, continuous, names, (frozenset([0, 1]), frozenset([2])))
    width = _prefixes(designs, firsts, {d for _, _, d in chosen})
    models = [Model(ks.index(k), np.arange(width[ks.index(k), d]), learner) for learner, k, d in chosen]
    engine = Lockstep(packed, designs)
    got = engine.tally(models, engine.fit(models))
    none = [0, 0.0, np.zeros((classes, classes), int)]
    return [(measures(got.get(i, none)), got.get(i, none)[2]) for i in range(len(models))]


def measures(tally: list) -> dict[str, float | None]:
    """log_loss and accuracy of one model's tally(), and the AUC of its hard predictions where there are two classes and rows of both."""
    rows, loss, counts = tally
    out = {"log_loss": loss / rows if rows else None, "accuracy": float(np.trace(counts)) / rows if rows else None}
    if len(counts) == 2:
        of = counts.sum(axis=1)
        out["auc_hard"] = float((counts[0, 0] / of[0] + counts[1, 1] / of[1]) / 2) if of.all() else None
    return out


__all__ = ["best", "grid", "grid_together", "prepared", "refit", "refit_together", "smooth"]
