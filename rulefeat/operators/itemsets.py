"""Level-wise mining of frequent sets of any size from transactions, and a pattern-growth miner to check it with."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..storage import materialise


def least_count(n: int, min_support: float | None, min_count: int | None) -> int:
    """Fractions become counts: the least whole number that is no smaller than the fraction of n."""
    return min_count if min_count is not None else max(1, math.ceil(min_support * n - 1e-9))


def candidates(prev: DataFrame, k: int) -> DataFrame:
    """Sets of k items whose subsets of k-1 are all frequent: joined on their first k-2 items, then pruned by a semi-join for each subset."""
    a = prev.select(F.slice("items", 1, k - 2).alias("head"), F.element_at("items", -1).alias("a"))
    b = prev.select(F.slice("items", 1, k - 2).alias("head"), F.element_at("items", -1).alias("b"))
    joined = a.join(b, "head").where("a < b").select(F.concat("head", F.array("a", "b")).alias("items"))
    known = prev.select(F.col("items").alias("subset"))
    for drop in range(k - 2):  # without either of the last two items the set is one of those joined
        joined = joined.withColumn("subset", F.expr(f"filter(items, (v, i) -> i <> {drop})")).join(known, "subset", "left_semi").drop("subset")
    return joined


def count_candidates(tx: DataFrame, cand: DataFrame, k: int) -> DataFrame:
    """Support of each candidate. A record is met with the candidates that start with one of its items, not with all."""
    anchored = cand.select(F.element_at("items", 1).alias("anchor"), F.element_at("items", 2).alias("second"), F.col("items").alias("set"))
    starts = F.flatten(F.transform("items", lambda a, i: F.transform(F.slice("items", i + 2, F.size("items")), lambda b: F.struct(a.alias("a"), b.alias("b")))))
    rows = tx.where(F.size("items") >= k).select("items", F.explode(starts).alias("p")).select("items", F.col("p.a").alias("anchor"), F.col("p.b").alias("second"))
    met = rows.join(anchored, ["anchor", "second"])
    if k > 2:
        met = met.where(F.size(F.array_intersect("items", "set")) == k)
    return met.groupBy(F.col("set").alias("items")).agg(F.count(F.lit(1)).alias("supp"))


def levelwise(tx: DataFrame, min_support: float | None = None, min_count: int | None = None, max_len: int | None = None) -> DataFrame:
    """tx(items: sorted distinct arrays) to (size, items, supp) of all frequent sets. A level that is empty ends the search."""
    n = tx.count()
    least = least_count(n, min_support, min_count)
    single = tx.select(F.explode("items").alias("i")).groupBy("i").agg(F.count(F.lit(1)).alias("supp")).where(F.col("supp") >= least)
    level = materialise(single.select(F.array("i").alias("items"), "supp"), "level")
    found, k = level.withColumn("size", F.lit(1)), 1
    frequent = level.select(F.col("items")[0].alias("i"))
    # infrequent items can't be in any larger set; they leave the transactions once
    slim = materialise(
        tx.select("items", F.monotonically_increasing_id().alias("t")).select("t", F.explode("items").alias("i")).join(frequent, "i", "left_semi").groupBy("t").agg(F.array_sort(F.collect_set("i")).alias("items")).drop("t"), "slim"
    )
    while (max_len is None or k < max_len) and not level.isEmpty():
        k += 1
        cand = materialise(candidates(level, k), "candidates")
        level = materialise(count_candidates(slim, cand, k).where(F.col("supp") >= least).select("items", "supp"), "level")
        found = found.unionByName(level.withColumn("size", F.lit(k)))
    return found.select("size", "items", "supp")


def pattern_growth(tx: DataFrame, min_support: float, max_len: int | None = None) -> DataFrame:
    """The same sets by Spark's pattern-growth miner, which makes no candidates."""
    from pyspark.ml.fpm import FPGrowth

    mined = FPGrowth(itemsCol="items", minSupport=min_support).fit(tx).freqItemsets
    out = mined.select(F.size("items").alias("size"), F.array_sort("items").alias("items"), F.col("freq").alias("supp"))
    return out.where(F.col("size") <= max_len) if max_len else out


def bruteforce_pairs(df: DataFrame, key: list[str], features, label: str) -> DataFrame:
    """Pair counts by joining the items of each record with themselves: no pruning, for tests on small tables."""
    from .items import long_items

    long = long_items(df.withColumn("__key", F.struct(*key)), features, label, ("__key",))
    a = long.select("__key", "y", F.col("f").alias("f1"), F.col("v").alias("v1"))
    b = long.select("__key", F.col("f").alias("f2"), F.col("v").alias("v2"))
    return a.join(b, "__key").where("f1 < f2").groupBy("f1", "v1", "f2", "v2", "y").agg(F.count(F.lit(1)).alias("supp"))
