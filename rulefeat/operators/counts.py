"""Counting passes. Counts are additive: partial aggregation in each task, then one shuffle of at most as many rows as there are counters."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.pandas.types import to_arrow_schema

from ..plans import pair_plans
from ..storage import ship_package
from .items import long_items, value_of
from .ranking import join_on


#: Rows that are counted at once by columns; results don't hang on it.
BLOCK = 20_000


def labels(df: DataFrame, label: str, by: tuple[str, ...] = (), weight: str | None = None) -> DataFrame:
    """(by..., y, supp_y, n, n_classes)."""
    from pyspark.sql import Window as W

    many = F.sum(weight) if weight else F.count(F.lit(1))
    per = df.where(F.col(label).isNotNull()).groupBy(*by, F.col(label).cast("string").alias("y")).agg(many.cast("long").alias("supp_y"))
    every = W.partitionBy(*by)
    return per.withColumns({"n": F.sum("supp_y").over(every), "n_classes": F.count(F.lit(1)).over(every)})


def singles(df: DataFrame, features, label: str, by: tuple[str, ...] = (), weight: str | None = None, null_policy: str = "skip", with_label: bool = False) -> DataFrame:
    """(by..., f, v, y, supp): support of every item with every class; with_label adds the classes' own counts as feature 0.

    Wide records are counted column by column in blocks of rows; others, and those with weights or lists, as one row an item.
    """
    kinds = dict(df.dtypes)
    if len(features) > pair_plans.DENSE and not weight and not df.isStreaming and not any(kinds[c].startswith("array") for c in features):
        return _by_columns(df, list(features), label, by, null_policy, with_label).groupBy(*by, "f", "v", "y").agg(F.sum("supp").alias("supp"))
    long = long_items(df, features, label, by, weight, null_policy, with_label)
    return long.groupBy(*by, "f", "v", "y").agg((F.sum("weight") if weight else F.count(F.lit(1))).cast("long").alias("supp"))


def _by_columns(df: DataFrame, features: list[str], label: str, by, null_policy: str, with_label: bool) -> DataFrame:
    """(by..., y, f, v, supp) of blocks of rows; a task holds one block."""
    ship_package(df.sparkSession)
    y, keys = F.col(label).cast("string"), [*by, "y"]
    first = [y.alias("v0")] if with_label else []
    wide = df.where(F.col(label).isNotNull()).select(*by, y.alias("y"), *first, *[value_of(c, null_policy).alias(f"v{i}") for i, c in enumerate(features, 1)])
    schema = T.StructType([*(wide.schema[k] for k in keys), T.StructField("f", T.IntegerType()), T.StructField("v", T.StringType()), T.StructField("supp", T.LongType())])
    arrow, begin = to_arrow_schema(schema), 0 if with_label else 1

    def counted(held: list[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for block in pa.Table.from_batches(held).combine_chunks().to_batches():
            of, named = pair_plans.groups_of(block, len(keys))
            for f, column in enumerate(block.columns[len(keys) :], begin):
                own = column.dictionary_encode()
                place, wide_ = own.indices.fill_null(-1).to_numpy(zero_copy_only=False), len(own.dictionary)
                known = place >= 0
                key, n = np.unique(of[known] * wide_ + place[known], return_counts=True)
                if len(key):
                    group = [pa.array([g[k] for g in named], t).take(pa.array(key // wide_)) for k, t in zip(range(len(keys)), arrow.types)]
                    yield pa.RecordBatch.from_arrays([*group, pa.array(np.full(len(key), f, np.int32)), own.dictionary.take(pa.array(key % wide_)).cast(arrow.field("v").type), pa.array(n.astype(np.int64))], schema=arrow)

    def partial(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, rows = [], 0
        for batch in batches:
            if batch.num_rows:
                held.append(batch)
                rows += batch.num_rows
            if rows >= BLOCK:
                yield from counted(held)
                held, rows = [], 0
        if held:
            yield from counted(held)

    return wide.mapInArrow(partial, schema)


def candidates(top_singles: DataFrame, by: tuple[str, ...] = ()) -> DataFrame:
    """(by..., f1, v1, f2, v2, y): pairs of items of different features that are both frequent with the same class."""
    a = top_singles.select(*by, F.col("f1"), F.col("v1"), "y")
    b = top_singles.select(*by, F.col("f1").alias("f2"), F.col("v1").alias("v2"), "y")
    return join_on(a, b, [*by, "y"]).where("f1 < f2").select(*by, "f1", "v1", "f2", "v2", "y")


def pairs(df: DataFrame, features, label: str, items: list[tuple[int, str]], by: tuple[str, ...] = (), weight: str | None = None, null_policy: str = "skip", plan: str = "auto", kept: DataFrame | None = None) -> DataFrame:
    """(by..., f1, v1, f2, v2, y, supp) of all pairs of the listed items of different features, for every class; with `kept`, of each group's own items.

    All three plans give the same rows; "auto" chooses by the number of items and features.
    """
    return pair_plans.count_pairs(df, features, label, items, by, weight, null_policy, plan, kept)


def pairs_of(df: DataFrame, features, label: str, kept: DataFrame, by: tuple[str, ...] = (), weight: str | None = None, null_policy: str = "skip", plan: str = "auto") -> tuple[DataFrame, int]:
    """(pairs(), number of items) of the items of kept(by..., f1, v1).

    Up to `pair_plans.LITERAL_ITEMS` different items go to the driver and become literals of one projection; more stay a table that the records' items are joined with.
    """
    distinct = kept.select("f1", "v1").distinct()
    found = [(r[0], r[1]) for r in distinct.limit(pair_plans.LITERAL_ITEMS + 1).collect()]
    if len(found) <= pair_plans.LITERAL_ITEMS and plan != "join":
        return pairs(df, features, label, found, by, weight, null_policy, plan, kept.select(*by, "f1", "v1").distinct() if by else None), len(found)
    return pair_plans.count_pairs_by_join(df, features, label, kept.select(*by, "f1", "v1").distinct(), by, weight, null_policy), distinct.count()


def value_cube(df: DataFrame, columns: list[str]) -> DataFrame:
    """Counts over all combinations of a few columns, with a grouping id (bit set where a column is rolled up)."""
    return df.cube(*columns).agg(F.count(F.lit(1)).alias("supp"), F.grouping_id().cast("long").alias("gid"))


def value_rollup(df: DataFrame, columns: list[str]) -> DataFrame:
    return df.rollup(*columns).agg(F.count(F.lit(1)).alias("supp"), F.grouping_id().cast("long").alias("gid"))


def singles_by_grouping_sets(df: DataFrame, features, label: str) -> DataFrame:
    """singles() by one GROUPING SETS aggregate: another plan for wide tables of few values, without the long form."""
    renamed = df.where(F.col(label).isNotNull()).select(F.col(label).cast("string").alias("y"), *[F.col(f"`{c}`").cast("string").alias(f"c{i}") for i, c in enumerate(features, 1)])
    columns = [f"c{i}" for i in range(1, len(features) + 1)]
    grouped = renamed.groupingSets([["y", c] for c in columns], "y", *columns).agg(F.count(F.lit(1)).alias("supp"), F.grouping_id().alias("gid"))
    width = len(columns)
    f = F.expr("CASE " + " ".join(f"WHEN (gid & {1 << (width - i)}) = 0 THEN {i}" for i in range(1, width + 1)) + " END")
    return grouped.select(f.alias("f"), F.coalesce(*columns).alias("v"), "y", "supp").where("v IS NOT NULL")
