"""Total orders. No result depends on the order of partitions or tasks."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F


def join_on(left: DataFrame, right: DataFrame, keys, how: str = "inner") -> DataFrame:
    """Join on columns of one name, of which nulls are equal too; the keys come once, from the left."""
    own = [c for c in right.columns if c not in keys]
    named = right.select(*[F.col(c).alias(f"__k_{c}") for c in keys], *own)
    on = [F.col(c).eqNullSafe(F.col(f"__k_{c}")) for c in keys]
    return left.join(named, on, how).select(*left.columns, *([] if how in ("left_semi", "left_anti") else own))


def antecedent_order() -> list[Column]:
    return [F.col("size").asc(), F.col("f1").asc(), F.col("v1").asc(), F.coalesce("f2", F.lit(-1)).asc(), F.coalesce("v2", F.lit("")).asc(), F.col("y").asc()]


def support_order() -> list[Column]:
    """Most frequent first; of equals the smaller antecedent, the earlier features, the lesser values, the lesser class."""
    return [F.col("supp").desc(), *antecedent_order()]


def score_order(score: str) -> list[Column]:
    return [F.col(score).desc(), *support_order()]


def top(rows: DataFrame, order: list[Column], budget, groups: tuple[str, ...] = ()) -> DataFrame:
    """The first `budget` (a number or a column) rows of each group, with their rank.

    With a number and no groups this is a heap in each task and one merge; with groups Spark limits each group before the shuffle.
    """
    if isinstance(budget, int) and not groups:
        first = rows.orderBy(*order).limit(budget)
        return first.withColumn("rank", F.row_number().over(W.orderBy(*order)))
    ranked = rows.withColumn("rank", F.row_number().over(W.partitionBy(*groups).orderBy(*order)))
    return ranked.where(F.col("rank") <= budget)
