"""Connected components of links between long keys, by alternating star contractions."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..storage import materialise, release


def _toward_least(pairs: DataFrame) -> DataFrame:
    """For every node u with neighbours v: the least of u and all v."""
    return pairs.groupBy("u").agg(F.least(F.min("v"), F.first("u")).alias("low"))


def _large_star(edges: DataFrame) -> DataFrame:
    both = edges.select("u", "v").unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
    return both.join(_toward_least(both), "u").where("v > u").select(F.col("v").alias("u"), F.col("low").alias("v")).where("u <> v").distinct()


def _small_star(edges: DataFrame) -> DataFrame:
    down = edges.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v"))
    least = down.groupBy("u").agg(F.min("v").alias("low"))
    to_low = down.join(least, "u").where("v <> low").select(F.col("v").alias("u"), F.col("low").alias("v"))
    return to_low.unionByName(least.select("u", F.col("low").alias("v"))).distinct()


def _print(edges: DataFrame) -> tuple:
    row = edges.agg(F.count(F.lit(1)), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
    return row[0], row[1]


def connected(links: DataFrame) -> DataFrame:
    """links(u, v) of longs to (node, root): root is the least node reachable. Nodes without links have no row.

    Links point from the greater to the lesser node after each round; the rounds end when no link changes.
    Each round is written to the shared folder, and only its count and sum of hashes go to the driver.
    """
    edges = materialise(links.where("u <> v").select("u", "v").distinct(), "links")
    mark = _print(edges)
    while mark[0]:
        contracted = materialise(_small_star(_large_star(edges)), "links")
        now = _print(contracted)
        release(edges)
        edges = contracted
        if now == mark:
            break
        mark = now
    return edges.select(F.col("u").alias("node"), F.col("v").alias("root")).unionByName(edges.select(F.col("v").alias("node"), F.col("v").alias("root")).distinct())
