"""Rules to binary features, and their application to records."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .items import value_of

def from_rules(rules: DataFrame, by: tuple[str, ...] = ()) -> DataFrame:
    """Distinct antecedents: several rules with one antecedent make one feature. feature_id counts from 1 in order of size and items."""
    distinct = rules.select(*by, "size", "f1", "v1", "f2", "v2").distinct()
    order = W.partitionBy(*by).orderBy("size", "f1", "v1", F.coalesce("f2", F.lit(-1)), F.coalesce("v2", F.lit("")))
    return distinct.withColumn("feature_id", F.row_number().over(order)).select(*by, "feature_id", "size", "f1", "v1", "f2", "v2")


def named(features: DataFrame, columns) -> DataFrame:
    """features with a name: column=value, two of them joined by a comma."""
    names = F.array(*[F.lit(c) for c in columns])
    part = lambda i: F.concat(F.get(names, F.col(f"f{i}") - 1), F.lit("="), F.col(f"v{i}"))
    return features.withColumn("name", F.concat_ws(", ", part(1), F.when(F.col("f2").isNotNull(), part(2))))


def predicate(row, columns, null_policy: str = "skip") -> Column:
    """True where a record has all of a feature's values, false elsewhere, never null."""
    tests = [value_of(columns[row[f] - 1], null_policy) == F.lit(row[v]) for f, v in (("f1", "v1"), ("f2", "v2")) if row[f] is not None]
    return F.coalesce(reduce(lambda a, b: a & b, tests), F.lit(False))


def apply(df: DataFrame, features: list, columns, mode: str = "columns", prefix: str = "rule_", null_policy: str = "skip") -> DataFrame:
    """df with the features (collected rows, a budget's number) as 0/1 columns, or as the indexes of those that hold ("indexes").

    One projection, so it fuses with the scan and with what follows.
    """
    taken = set(df.columns)
    name = lambda r: next(n for n in (f"{prefix}{r['feature_id']}", f"{prefix}{r['feature_id']}_") if n not in taken)
    if mode == "columns":
        return df.select("*", *[predicate(r, columns, null_policy).cast("tinyint").alias(name(r)) for r in features])
    if mode == "indexes":
        held = [F.when(predicate(r, columns, null_policy), F.lit(i)) for i, r in enumerate(features)]
        return df.withColumn(f"{prefix}indexes", F.array_compact(F.array(*held)) if held else F.array().cast("array<int>"))
    raise ValueError(f"mode {mode!r}")


def matrix(df: DataFrame, features: DataFrame, columns, keys: list[str], null_policy: str = "skip") -> DataFrame:
    """Sparse long form: (keys..., feature_id) where the feature is 1. The features are broadcast: a budget's number of rows."""
    rows = features.collect()
    held = F.array_compact(F.array(*[F.when(predicate(r, columns, null_policy), F.lit(r["feature_id"])) for r in rows])) if rows else F.array().cast("array<int>")
    return df.select(*keys, F.explode(held).alias("feature_id"))


def feature_counts(df: DataFrame, features: DataFrame, columns, label: str, null_policy: str = "skip") -> DataFrame:
    """(feature_id, y, n): records per feature and class."""
    return matrix(df, features, columns, [label], null_policy).groupBy("feature_id", F.col(label).cast("string").alias("y")).agg(F.count(F.lit(1)).alias("n"))


def product_pairs(features: DataFrame) -> DataFrame:
    """Distinct feature pairs of the antecedents of size two: their numeric products become features."""
    return features.where("size = 2").select("f1", "f2").distinct()
