"""Counting on samples drawn with replacement, and how far off their frequencies can be."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

#: Multiplier and increment of the reproducible draw.
LCG = (1_103_515_245, 12_345)


def numbered(df: DataFrame, order: list[str]) -> DataFrame:
    """df with `at`, 0-based, in a total order; ranges are sorted in parallel and the ranges' sizes are added up apart, so no task sees all rows."""
    cut = df.repartitionByRange(*order).sortWithinPartitions(*order).withColumn("__at", F.monotonically_increasing_id())
    from ..storage import materialise

    cut = materialise(cut, "numbered")
    part = F.shiftright("__at", 33)
    sizes = cut.groupBy(part.alias("__part")).agg(F.count(F.lit(1)).alias("__n"))
    starts = sizes.withColumn("__start", F.coalesce(F.sum("__n").over(W.orderBy("__part").rowsBetween(W.unboundedPreceding, -1)), F.lit(0))).select("__part", "__start")
    inside = F.col("__at").bitwiseAND((1 << 33) - 1)
    return cut.withColumn("__part", part).join(F.broadcast(starts), "__part").withColumn("at", inside + F.col("__start")).drop("__at", "__part", "__start")  # one row a partition


def draw(df: DataFrame, n_prime: int, seed: int = 1, method: str = "poisson", order: list[str] | None = None) -> DataFrame:
    """A sample of about (poisson) or exactly (exact, lcg) n_prime records with replacement; exact draws give each record once with its multiplicity in `weight`.

    poisson needs no shuffle; exact and lcg number the records by `order` and join n_prime draws of places. lcg is reproducible in SQL.
    """
    if method == "poisson":
        n = df.count()
        return df.sample(True, min(1e6, n_prime / n), seed).withColumn("weight", F.lit(1).cast("long")) if n else df.withColumn("weight", F.lit(1).cast("long"))
    rows = numbered(df, order or df.columns)
    n = rows.count()
    if not n:
        return rows.withColumn("weight", F.lit(0).cast("long")).drop("at")
    j = df.sparkSession.range(n_prime)
    place = F.pmod(F.lit(LCG[0]) * F.col("id") + LCG[1] + seed, F.lit(n)) if method == "lcg" else F.pmod(F.xxhash64("id", F.lit(seed)), F.lit(n))
    draws = j.select(place.alias("at")).groupBy("at").agg(F.count(F.lit(1)).alias("weight"))
    return rows.join(draws, "at").drop("at")


def estimate(counted: DataFrame, n_prime: int) -> DataFrame:
    """Frequencies estimated by the share of draws that hold each set."""
    return counted.withColumn("p_hat", F.col("supp").cast("double") / F.lit(n_prime))


def hoeffding(n: int, eps: float) -> float:
    """Bound of the chance that an estimated frequency is off by eps or more."""
    return 2 * math.exp(-2 * n * eps * eps)


def swap_bound(n: int, eps: float) -> float:
    """Bound of the chance that of two sets whose frequencies differ by eps the rarer one doesn't come out rarer."""
    return 4 * math.exp(-n * eps * eps / 2)


def hoeffding_column(n: Column, eps: Column) -> Column:
    """hoeffding() of samples whose sizes are a column."""
    return 2 * F.exp(-2 * n * eps * eps)


def swap_bound_column(n: Column, eps: Column) -> Column:
    """swap_bound() of samples whose sizes are a column."""
    return 4 * F.exp(-n * eps * eps / 2)


def required_size(eps: float, delta: float, kind: str = "single", n_sets: int = 1) -> int:
    """Draws that bring the bound down to delta, for n_sets sets (or pairs of sets) at once."""
    if kind == "single":
        return math.ceil(math.log(2 * n_sets / delta) / (2 * eps * eps))
    return math.ceil(2 * math.log(4 * n_sets / delta) / (eps * eps))


def freq_error(sample: DataFrame, full: DataFrame, keys: list[str]) -> DataFrame:
    """sample(keys, p_hat) and full(keys, p) to keys, p_hat, p, error; a set that one side lacks has frequency 0 there."""
    a, b = sample.select(*keys, "p_hat"), full.select(*[F.col(k).alias(f"__{k}") for k in keys], "p")
    on = [F.col(k).eqNullSafe(F.col(f"__{k}")) for k in keys]
    joined = a.join(b, on, "full_outer").select(*[F.coalesce(k, f"__{k}").alias(k) for k in keys], F.coalesce("p_hat", F.lit(0.0)).alias("p_hat"), F.coalesce("p", F.lit(0.0)).alias("p"))
    return joined.withColumn("error", F.abs(F.col("p_hat") - F.col("p")))


def recall_at(sample: DataFrame, full: DataFrame, keys: list[str], k: int) -> DataFrame:
    """How many of the k sets that lead by `rank` in full are among sample's rows."""
    lead = full.where(F.col("rank") <= k).select(*[F.coalesce(F.col(c).cast("string"), F.lit("")).alias(c) for c in keys])
    have = sample.select(*[F.coalesce(F.col(c).cast("string"), F.lit("")).alias(c) for c in keys])
    return lead.join(have, keys, "left_semi").agg(F.count(F.lit(1)).alias("found"))


def recount(df: DataFrame, sets: DataFrame, features, label: str) -> DataFrame:
    """Exact supports of given sets (at most a budget's number, broadcast as expressions) in one pass: (f1, v1, f2, v2, y, supp, supp_x)."""
    from .features import from_rules, matrix

    distinct = from_rules(sets)
    held = matrix(df, distinct, list(features), [label]).groupBy("feature_id", F.col(label).cast("string").alias("y")).agg(F.count(F.lit(1)).alias("supp"))
    total = held.withColumn("supp_x", F.sum("supp").over(W.partitionBy("feature_id")))
    return total.join(distinct, "feature_id").select("f1", "v1", "f2", "v2", "y", "supp", "supp_x")
