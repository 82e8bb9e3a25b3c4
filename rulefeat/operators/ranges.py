"""Sums and numbers along a total order, made range by range: no task sees all rows."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..storage import materialise


def summed(rows: DataFrame, order: list[Column], values: dict[str, str], group: list[str], label: str) -> DataFrame:
    """rows with, for each new name in `values`, the sum of a column over the rows of the group up to and with this one, in a total order that begins with the group.

    Rows are sorted in ranges, each range is summed on its own, and the totals of the ranges (one row each) are added up apart. Group columns are never null.
    """
    placed = materialise(rows.repartitionByRange(*order).sortWithinPartitions(*order).withColumn("__part", F.spark_partition_id()), label)
    along = W.partitionBy(*group).orderBy("__part").rowsBetween(W.unboundedPreceding, -1)
    totals = placed.groupBy(*group, "__part").agg(*[F.sum(c).alias(f"__in_{n}") for n, c in values.items()])
    starts = totals.select(*group, "__part", *[F.coalesce(F.sum(f"__in_{n}").over(along), F.lit(0)).alias(f"__start_{n}") for n in values])
    inside = W.partitionBy(*group, "__part").orderBy(*order).rowsBetween(W.unboundedPreceding, 0)
    within = placed.withColumns({f"__within_{n}": F.sum(c).over(inside) for n, c in values.items()})
    out = within.join(starts, [*group, "__part"]).withColumns({n: F.col(f"__start_{n}") + F.col(f"__within_{n}") for n in values})
    return out.drop("__part", *[f"__{s}_{n}" for n in values for s in ("start", "within")])
