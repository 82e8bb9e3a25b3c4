"""Records to items: long form, item dictionaries, transactions."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

MISSING = "<null>"
CATEGORICAL = (T.StringType, T.BooleanType, T.ByteType, T.ShortType, T.IntegerType, T.LongType, T.DateType, T.DecimalType)


@dataclass(frozen=True)
class Roles:
    """Which columns are features (their place in the list is the ordinal, from 1), and which is the label."""

    label: str
    categorical: tuple[str, ...]
    continuous: tuple[str, ...] = ()
    null_policy: str = "skip"

    def __post_init__(self):
        if self.null_policy not in ("skip", "category"):
            raise ValueError(f"null_policy {self.null_policy!r}")
        if self.label in (*self.categorical, *self.continuous):
            raise ValueError(f"{self.label} is both the label and a feature")


def infer_roles(df: DataFrame, label: str, max_categories: int = 64, null_policy: str = "skip") -> Roles:
    """Strings, booleans and integers of few values are categorical, floating numbers continuous; one aggregate pass for the distinct counts."""
    fields = [f for f in df.schema.fields if f.name != label]
    candidates = [f.name for f in fields if isinstance(f.dataType, CATEGORICAL)]
    few = df.agg(*[F.approx_count_distinct(c).alias(c) for c in candidates]).first() if candidates else {}
    numeric = (T.IntegerType, T.LongType, T.ShortType, T.ByteType, T.DecimalType)
    categorical = tuple(f.name for f in fields if f.name in candidates and few[f.name] <= max_categories)
    continuous = tuple(f.name for f in fields if isinstance(f.dataType, (T.DoubleType, T.FloatType)) or (f.name in candidates and f.name not in categorical and isinstance(f.dataType, numeric)))
    return Roles(label, categorical, continuous, null_policy)


def value_of(column: str, null_policy: str = "skip") -> Column:
    """A feature's value as the string that items carry; NaN counts as missing."""
    v = F.col(f"`{column}`").cast("string")
    v = F.when(v != "NaN", v)
    return F.coalesce(v, F.lit(MISSING)) if null_policy == "category" else v


def _tagged(ordinal: int, column: str) -> Column:
    """An item for each distinct element of a list column."""
    return F.transform(F.array_distinct(F.coalesce(F.col(f"`{column}`"), F.array())), lambda v: F.struct(F.lit(ordinal).alias("f"), v.cast("string").alias("v")))


def _looked_up(table: Column, column: str) -> Column:
    """Ids of a list column's distinct elements, sorted."""
    return F.array_sort(F.array_compact(F.transform(F.array_distinct(F.coalesce(F.col(f"`{column}`"), F.array())), lambda v: F.element_at(table, v.cast("string")))))


def long_items(df: DataFrame, features: list[str] | tuple[str, ...], label: str, by: tuple[str, ...] = (), weight: str | None = None, null_policy: str = "skip", with_label: bool = False) -> DataFrame:
    """One row (f, v, y) for each record and feature with a value, with the columns of `by` and `weight`; records without a label have none.

    A feature of type array<string> gives an item for each distinct element.
    """
    kinds = dict(df.dtypes)
    parts = []
    for i, c in enumerate(features, 1):
        if kinds[c].startswith("array"):
            parts.append(_tagged(i, c))
        else:
            parts.append(F.array(F.struct(F.lit(i).alias("f"), value_of(c, null_policy).alias("v"))))
    if with_label:
        parts.append(F.array(F.struct(F.lit(0).alias("f"), F.col(label).cast("string").alias("v"))))
    keys = [F.col(b) for b in by] + ([F.col(weight).alias("weight")] if weight else [])
    long = df.where(F.col(label).isNotNull()).select(*keys, F.col(label).cast("string").alias("y"), F.explode(F.concat(*parts) if len(parts) > 1 else parts[0]).alias("item"))
    return long.select(*by, *(["weight"] if weight else []), "item.f", "item.v", "y").where(F.col("v").isNotNull())


def kept_ids(df: DataFrame, features, items: list[tuple[int, str]], null_policy: str = "skip") -> Column:
    """Array of the ids (places in `items`) that a record holds, in order; items is a driver-side list of bounded size, in order of (f, v)."""
    by_feature: dict[int, list[tuple[str, int]]] = {}
    for at, (f, v) in enumerate(items):
        by_feature.setdefault(f, []).append((v, at))
    kinds, parts = dict(df.dtypes), []
    for f, values in sorted(by_feature.items()):
        column = features[f - 1]
        table = F.create_map(*[x for v, at in values for x in (F.lit(v), F.lit(at))])
        if kinds[column].startswith("array"):
            parts.append(_looked_up(table, column))
        else:
            parts.append(F.array(F.element_at(table, value_of(column, null_policy))))
    return F.array_compact(F.concat(*parts)) if parts else F.array().cast("array<int>")


def transactions(df: DataFrame, key: str, item: str) -> DataFrame:
    """(key, items): the distinct items of each key, sorted."""
    return df.where(F.col(item).isNotNull()).groupBy(key).agg(F.array_sort(F.collect_set(F.col(item).cast("string"))).alias("items"))
