"""Measures of itemsets, rules and splits as columns over integer counts."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

#: Added to the denominator of the relative confidence.
EPS = 1e-6


def _d(c) -> Column:
    return (F.col(c) if isinstance(c, str) else c).cast("double")


def rule_support(supp, n) -> Column:
    """Fraction of all records that hold antecedent and consequent."""
    return F.try_divide(_d(supp), _d(n))


def confidence(supp, supp_x) -> Column:
    return F.try_divide(_d(supp), _d(supp_x))


def lift(supp, supp_x, supp_y, n) -> Column:
    """Confidence over the consequent's share."""
    return F.try_divide(_d(supp) * _d(n), _d(supp_x) * _d(supp_y))


def relative_confidence(supp, supp_x, supp_y, n, eps: float = EPS) -> Column:
    """Odds of the class among records with the antecedent, over its odds among all records."""
    return _d(supp) / (_d(supp_x) - _d(supp) + F.lit(eps)) * F.try_divide(_d(n) - _d(supp_y), _d(supp_y))


def with_measures(sets: DataFrame, eps: float = EPS) -> DataFrame:
    """sets(supp, supp_x, supp_y, n) with support, conf, lift, rconf and log_rconf."""
    scored = sets.withColumns({
        "support": rule_support("supp", "n"), "conf": confidence("supp", "supp_x"), "lift": lift("supp", "supp_x", "supp_y", "n"),
        "rconf": relative_confidence("supp", "supp_x", "supp_y", "n", eps),
    })
    return scored.withColumn("log_rconf", F.when(F.col("rconf") > 0, F.round(F.ln("rconf"), 6)))


def info_distance(counts: DataFrame, antecedent: list[str]) -> DataFrame:
    """counts(antecedent..., y, supp, supp_y, n), zero counts left out, to the total variation between posterior and prior.

    Classes that an antecedent never meets count with their prior: their share is what the others' priors leave.
    """
    total = F.sum("supp").over(W.partitionBy(*antecedent))
    gap = F.abs(_d("supp") / _d(total) - _d("supp_y") / _d("n"))
    seen = counts.withColumn("supp_x", total).withColumn("gap", gap)
    summed = seen.groupBy(*antecedent).agg(F.sum("gap").alias("gap"), F.sum("supp_y").alias("met"), F.max("n").alias("n"), F.max("supp_x").alias("supp_x"))
    return summed.select(*antecedent, "supp_x", ((F.col("gap") + (_d("n") - _d("met")) / _d("n")) / 2).alias("distance"))


def entropy_term(count: Column, total: Column) -> Column:
    """-p ln p of one class, 0 for none."""
    share = F.try_divide(_d(count), _d(total))
    return F.when(_d(count) > 0, -share * F.ln(share)).otherwise(0.0)


def entropy(counts: list[float]) -> float:
    total = sum(counts)
    return -sum(c / total * math.log(c / total) for c in counts if c) if total else 0.0


def information_gain(whole: list[float], parts: list[list[float]]) -> float:
    """Entropy of the whole less that of its parts, weighted by their shares."""
    n = sum(whole)
    return entropy(whole) - sum(sum(p) / n * entropy(p) for p in parts) if n else 0.0
