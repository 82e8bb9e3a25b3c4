"""Ways to give generated features to a learner."""

from __future__ import annotations

from pyspark.ml.functions import array_to_vector
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..operators.features import predicate
from ..operators.items import MISSING, value_of

MODES = ("rules", "label_plus_rules", "onehot_plus_interactions", "binned_plus_rules", "products")


#: Categories of one column at most that are encoded: they go to the driver and become literals.
CATEGORIES = 5000


def bounded(df: DataFrame, columns) -> None:
    """Makes sure that no column has more than CATEGORIES values."""
    many = df.agg(*[F.approx_count_distinct(value_of(c)).alias(f"c{i}") for i, c in enumerate(columns)]).first()
    if wide := [c for i, c in enumerate(columns) if many[f"c{i}"] > CATEGORIES]:
        raise ValueError(f"more than {CATEGORIES} categories in {', '.join(wide)}: bin, hash or leave them out")


def codes(df: DataFrame, columns) -> dict[str, list[str]]:
    """Sorted distinct values of each column: one aggregate, after another has made sure that there are no more than CATEGORIES."""
    if not columns:
        return {}
    bounded(df, columns)
    row = df.agg(*[F.array_sort(F.collect_set(value_of(c))).alias(f"c{i}") for i, c in enumerate(columns)]).first()
    return {c: list(row[f"c{i}"]) for i, c in enumerate(columns)}


def code(column: str, values: list[str]) -> Column:
    """The place of the value among the sorted ones; null or unknown is -1."""
    table = F.create_map(*[x for i, v in enumerate(values) for x in (F.lit(v), F.lit(i))]) if values else F.expr("map('', 0)")
    return F.coalesce(F.element_at(table, value_of(column)), F.lit(-1))


def label_encode(df: DataFrame, columns, known: dict[str, list[str]] | None = None) -> DataFrame:
    known = known or codes(df, columns)
    return df.select("*", *[code(c, known[c]).alias(f"{c}_code") for c in columns])


def _ones(features: list, columns) -> list[Column]:
    return [predicate(r, columns).cast("double") for r in features]


def label_plus_rules(df: DataFrame, features: DataFrame, columns, known=None) -> DataFrame:
    """Label codes and every generated feature, mains and interactions, as 0/1 columns."""
    rows = sorted(features.collect(), key=lambda r: r["feature_id"])
    return label_encode(df, columns, known).select("*", *[predicate(r, columns).cast("tinyint").alias(f"rule_{r['feature_id']}") for r in rows])


def onehot_slots(columns, known: dict[str, list[str]]) -> list[tuple[str, str]]:
    return [(c, v) for c in columns for v in known[c]]


def onehot_plus_interactions_long(df: DataFrame, features: DataFrame, columns, keys: list[str]) -> DataFrame:
    """Sparse long form: (keys..., slot) where 1. Main effects are in the one-hot slots already, so only interactions are added."""
    pairs = sorted((r for r in features.collect() if r["size"] == 2), key=lambda r: r["feature_id"])
    hot = [F.concat(F.lit(f"{i}="), value_of(c)) for i, c in enumerate(columns, 1)]
    rules = [F.when(predicate(r, columns), F.lit(f"rule{i}")) for i, r in enumerate(pairs, 1)]
    return df.select(*keys, F.explode(F.array_compact(F.array(*hot, *rules))).alias("slot"))


def assemble(df: DataFrame, mode: str, features: list, categorical, continuous=(), known=None, as_array: bool = False) -> DataFrame:
    """df with a vector column `features` (or an array, if asked; generated features are its last places), by mode:

    original: label codes and numbers as they are; onehot: 0/1 slots and numbers; rules: generated features only; label_plus_rules; onehot_plus_interactions;
    binned_plus_rules: interval codes with all generated features; products: numbers and the products of the antecedents' feature pairs.
    """
    known = known if known is not None else codes(df, categorical)
    numbers = [F.coalesce(F.col(f"`{c}`").cast("double"), F.lit(0.0)) for c in continuous]
    coded = [code(c, known[c]).cast("double") for c in categorical]
    hot = [F.coalesce((value_of(c) == v), F.lit(False)).cast("double") for c, v in onehot_slots(categorical, known)]
    pairs = [r for r in features if r["size"] == 2]
    chosen = {
        "original": lambda: coded + numbers,
        "onehot": lambda: hot + numbers,
        "rules": lambda: _ones(features, categorical),
        "label_plus_rules": lambda: coded + numbers + _ones(features, categorical),
        "onehot_plus_interactions": lambda: hot + numbers + _ones(pairs, categorical),
        "binned_plus_rules": lambda: coded + _ones(features, categorical),
    }[mode]()
    values = F.array(*(chosen or [F.lit(0.0)]))
    return df.withColumn("features", values if as_array else array_to_vector(values))


def products(df: DataFrame, pairs: list[tuple[int, int]], continuous) -> DataFrame:
    """df with a product column for each pair of ordinals."""
    return df.select("*", *[(F.col(continuous[a - 1]) * F.col(continuous[b - 1])).alias(f"{continuous[a - 1]}_x_{continuous[b - 1]}") for a, b in pairs])


__all__ = ["MISSING", "MODES", "assemble", "codes", "label_encode", "label_plus_rules", "onehot_plus_interactions_long", "products"]
