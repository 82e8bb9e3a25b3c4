"""Selectors of categorical features and pair interactions by class rules.

Two scans of the data: one counts items by class (and, as an item of its own, the classes), one counts pairs of kept items by class. All later
steps work on at most budget-squared rows.
"""

from __future__ import annotations

import math
import warnings
from dataclasses import dataclass, field
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions.measures import EPS, with_measures
from ..storage import materialise, release
from . import counts, features as feature_ops, rules as rule_ops
from .bits import Bits
from .cube import Cube
from .ranking import join_on, support_order, top

ANTECEDENT = ["f1", "v1", "f2", "v2"]


@dataclass
class Mined:
    """Frequent sets of one mining run. Every score, budget of rules and redundancy setting is a re-cut of these rows."""

    sets: DataFrame  # by..., size, f1, v1, f2, v2, y, supp, rank, supp_x, supp_y, n
    by: tuple[str, ...] = ()
    steps: dict[str, int] = field(default_factory=dict)


def as_sets(singles: DataFrame, by=()) -> DataFrame:
    none = F.lit(None)
    return singles.select(*by, F.lit(1).alias("size"), F.col("f").alias("f1"), F.col("v").alias("v1"), none.cast("int").alias("f2"), none.cast("string").alias("v2"), "y", "supp")


def with_totals(sets: DataFrame, all_counts: DataFrame, labels: DataFrame, by=()) -> DataFrame:
    """Add supp_x (sum over classes of the antecedent's counts), supp_y and n; no new scan."""
    totals = all_counts.groupBy(*by, *ANTECEDENT).agg(F.sum("supp").alias("supp_x"))
    return join_on(join_on(sets, totals, [*by, *ANTECEDENT]), labels.select(*by, "y", "supp_y", "n"), [*by, "y"])


def class_and_item_counts(df: DataFrame | Bits | Cube, features, label: str, by=(), weight: str | None = None, null_policy: str = "skip") -> tuple[DataFrame, DataFrame]:
    """(labels, singles) of counts.labels() and counts.singles() by one scan: each record's class goes with its items, as that of feature 0."""
    both = materialise(df.singles() if isinstance(df, (Bits, Cube)) else counts.singles(df, features, label, by, weight, null_policy, with_label=True), "singles")
    per = both.where("f = 0").select(*by, "y", F.col("supp").alias("supp_y"))
    every = W.partitionBy(*by)
    labels = per.withColumns({"n": F.sum("supp_y").over(every), "n_classes": F.count(F.lit(1)).over(every)})
    items = both.where("f > 0")
    items._scratch_path = both._scratch_path
    return labels, items


def _budgets(labels: DataFrame, d_freq: int, class_budget, by) -> DataFrame:
    """Budget of each class: even shares (rounded down, 1 at least), shares by class size, or a dictionary."""
    if class_budget == "even":
        b = F.floor(F.lit(d_freq) / F.col("n_classes"))
    elif class_budget == "proportional":
        b = F.floor(F.lit(d_freq) * F.col("supp_y") / F.col("n"))
    else:
        table = F.create_map(*[x for k, v in class_budget.items() for x in (F.lit(str(k)), F.lit(int(v)))])
        b = F.coalesce(F.element_at(table, F.col("y")), F.lit(1))
    return labels.select(*by, "y", F.greatest(b.cast("int"), F.lit(1)).alias("budget"))


def mine(df: DataFrame, label: str, features, d_freq: int, per_class: bool, **settings) -> Mined:
    """The d_freq most frequent (antecedent, class) sets of one or two items, over all classes or a share for each: mine_both() for one of the two."""
    return mine_both(df, label, features, d_freq, (per_class,), **settings)[per_class]


def mine_both(df: DataFrame, label: str, features, d_freq: int, kinds=(False, True), by: tuple[str, ...] = (), weight: str | None = None, null_policy: str = "skip", class_budget="even", plan: str = "auto", min_count: int = 0) -> dict[bool, Mined]:
    """Frequent sets by kind of budget: True for a share of d_freq for each class, False for one budget over all; sets of fewer than min_count records are left out.

    Two scans of the data, whether one kind is wanted or both. A pair is a candidate if both its items are kept with the same class; it is counted for every class in the one pass, so that confidences
    need no other. An item's supersets are never more frequent, so these are the top sets among all singles and pairs.
    df may be a view of Bits, or a Cube, by the one column of `by`; its items are counted without weights.
    """
    features, packed = list(features), isinstance(df, (Bits, Cube))
    if packed and (by != (df.by,) or weight or null_policy != "skip" or len(features) != df.p):
        raise ValueError("Bits and cubes are mined by the column of their groups, all features of them, without weights or nulls as values")
    only = df if packed else df.select(*dict.fromkeys([*by, label, *features, *([weight] if weight else [])]))
    labels, single_counts = class_and_item_counts(only, features, label, by, weight, null_policy)
    every_single = as_sets(single_counts, by)
    singles = every_single.where(F.col("supp") >= min_count)

    def cut(rows: DataFrame, per_class: bool) -> DataFrame:
        if per_class:
            return top(join_on(rows, _budgets(labels, d_freq, class_budget, by), [*by, "y"]), support_order(), F.col("budget"), (*by, "y")).drop("budget")
        return top(rows, support_order(), d_freq, tuple(by))

    first = {kind: materialise(cut(singles, kind), "top-singles") for kind in kinds}
    kept = reduce(DataFrame.unionByName, [f.select(*by, "f1", "v1") for f in first.values()]).distinct()
    done, n_items, pair_counts = {}, 0, None
    if not kept.isEmpty():
        counted, n_items = only.pairs_of(kept) if packed else counts.pairs_of(only, features, label, kept, by, weight, null_policy, plan)
        pair_counts = materialise(counted, "pairs")
    for kind in kinds:
        sets, everything = singles, every_single
        if pair_counts is not None:
            named = pair_counts.select(*by, F.lit(2).alias("size"), *ANTECEDENT, "y", "supp")
            wanted = join_on(named.where(F.col("supp") >= min_count), counts.candidates(first[kind], by), [*by, *ANTECEDENT, "y"], "left_semi")
            sets, everything = singles.unionByName(wanted), every_single.unionByName(named)
        scored = with_totals(cut(sets, kind), everything, labels, by).select(*by, "size", *ANTECEDENT, "y", "supp", "rank", "supp_x", "supp_y", "n")
        done[kind] = Mined(materialise(scored, "frequent-sets"), tuple(by), {"items": n_items})
    for table in (single_counts, *first.values(), *([pair_counts] if pair_counts is not None else [])):
        release(table)
    return done


@dataclass
class Selected:
    mined: Mined
    rules: DataFrame
    features: DataFrame


def _select(mined: Mined, d_conf: int, score: str, redundancy: str | None, margin: float, eps: float, min_score: float | None = None) -> Selected:
    scored = with_measures(mined.sets, eps)
    if redundancy:
        scored = rule_ops.nonredundant(scored, score, redundancy, margin, mined.by)
    if min_score is not None:
        scored = scored.where(F.col(score) >= min_score)
    chosen = rule_ops.top_rules(scored, d_conf, score, mined.by)
    return Selected(mined, chosen, feature_ops.from_rules(chosen, mined.by))


def select_by_budget(df, label, features, d_freq: int, d_conf: int, score: str = "conf", eps: float = EPS, min_score: float | None = None, **mining) -> Selected:
    """The d_freq most frequent sets of all, then the d_conf most confident rules of them; min_count and min_score are floors beside the budgets."""
    return _select(mine(df, label, features, d_freq, False, **mining), d_conf, score, None, 1.0, eps, min_score)


def select_balanced(df, label, features, d_freq: int, d_conf: int, score: str = "rconf", eps: float = EPS, min_score: float | None = None, **mining) -> Selected:
    """An equal share of frequent sets for every class, then the d_conf rules that are highest by relative confidence (or another score)."""
    return _select(mine(df, label, features, d_freq, True, **mining), d_conf, score, None, 1.0, eps, min_score)


def select_nonredundant(df, label, features, d_freq: int, d_conf: int, score: str = "rconf", redundancy: str = "strict", margin: float = 1.0, eps: float = EPS, min_score: float | None = None, **mining) -> Selected:
    """select_balanced() without interactions that tell no more than their main effects. The default selector."""
    return _select(mine(df, label, features, d_freq, True, **mining), d_conf, score, redundancy, margin, eps, min_score)


def recut(mined: Mined, d_conf: int, score: str = "rconf", redundancy: str | None = "strict", margin: float = 1.0, eps: float = EPS, min_score: float | None = None) -> Selected:
    """Other rules of the same mining run: no scan of the data."""
    return _select(mined, d_conf, score, redundancy, margin, eps, min_score)


def select_by_threshold(df, label, features, min_support: float | None = None, min_conf: float = 0.5, min_count: int | None = None, max_rules: int = 10_000, null_policy: str = "skip", plan: str = "auto") -> Selected:
    """All class rules of one or two items with support and confidence at the thresholds or above; the output is unbounded.

    More frequent sets than max_rules warn before pairs are counted, and more rules than that after. Thresholds too high for the data give an empty result with the same columns.
    """
    features = list(features)
    only = df.select(*dict.fromkeys([label, *features]))
    labels, single_counts = class_and_item_counts(only, features, label, null_policy=null_policy)
    singles = as_sets(single_counts)
    n = labels.agg(F.coalesce(F.sum("supp_y"), F.lit(0))).first()[0]
    least = min_count if min_count is not None else max(1, math.ceil((min_support or 0.0) * n - 1e-9))
    frequent = singles.where(F.col("supp") >= least)
    if (many := frequent.count()) > max_rules:
        warnings.warn(f"{many} frequent items with their classes, and their pairs to come: raise the thresholds", stacklevel=2)
    everything, sets = singles, frequent
    if many:
        counted, _ = counts.pairs_of(only, features, label, frequent, null_policy=null_policy, plan=plan)
        named = materialise(counted, "pairs").select(F.lit(2).alias("size"), *ANTECEDENT, "y", "supp")
        everything, sets = singles.unionByName(named), frequent.unionByName(named.where(F.col("supp") >= least))
    done = materialise(with_totals(sets, everything, labels), "frequent-sets")
    rules = with_measures(done).where(F.col("conf") >= min_conf)
    if (found := rules.count()) > max_rules:
        warnings.warn(f"{found} rules: raise the thresholds", stacklevel=2)
    return Selected(Mined(done), rules, feature_ops.from_rules(rules))
