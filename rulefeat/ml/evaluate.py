"""Measures over predictions; every one is a single aggregate."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

CLIP = 1e-15


def log_loss(p_true: Column) -> Column:
    return F.avg(-F.ln(F.greatest(F.least(p_true, F.lit(1 - CLIP)), F.lit(CLIP))))


def accuracy(truth: str, prediction: str) -> Column:
    return F.avg((F.col(truth) == F.col(prediction)).cast("double"))


def error_rate(truth: str, prediction: str) -> Column:
    return 1 - accuracy(truth, prediction)


def mse(truth: str, prediction: str) -> Column:
    gap = F.col(truth) - F.col(prediction)
    return F.avg(gap * gap)


def confusion(df: DataFrame, truth: str, prediction: str) -> DataFrame:
    """(truth, prediction, n)."""
    return df.groupBy(F.col(truth).cast("string").alias("truth"), F.col(prediction).cast("string").alias("prediction")).agg(F.count(F.lit(1)).alias("n"))


def auc(df: DataFrame, truth: str, score: str) -> DataFrame:
    """Share of (positive, negative) pairs in order, ties half; truth is 0/1. Counts per distinct score are shuffled, not rows.

    The running sum over scores is made in ranges of the scores, whose totals are added up apart, as scores may be as many as rows.
    """
    from ..operators.sampling import numbered

    per = df.groupBy(F.col(score).alias("s")).agg(F.sum(F.col(truth).cast("long")).alias("pos"), F.sum(1 - F.col(truth).cast("long")).alias("neg"))
    placed = numbered(per, ["s"])
    block = F.floor(F.col("at") / 10_000)
    sums = placed.groupBy(block.alias("block")).agg(F.sum("neg").alias("neg_in"))
    before = sums.withColumn("below", F.coalesce(F.sum("neg_in").over(W.orderBy("block").rowsBetween(W.unboundedPreceding, -1)), F.lit(0))).select("block", "below")
    inner = placed.withColumn("block", block).withColumn("own", F.coalesce(F.sum("neg").over(W.partitionBy("block").orderBy("at").rowsBetween(W.unboundedPreceding, -1)), F.lit(0)))
    joined = inner.join(before, "block")
    wins = F.sum(F.col("pos") * (2 * (F.col("below") + F.col("own")) + F.col("neg")))
    return joined.agg(wins.alias("w"), F.sum("pos").alias("p"), F.sum("neg").alias("n")).select(F.try_divide(F.col("w").cast("double"), 2.0 * F.col("p") * F.col("n")).alias("auc"))


def auc_hard(df: DataFrame, truth: str, prediction: str) -> DataFrame:
    """AUC of hard 0/1 predictions: the mean of sensitivity and specificity."""
    t, p = F.col(truth).cast("long"), F.col(prediction).cast("long")
    return df.agg(((F.try_divide(F.sum(t * p), F.sum(t)) + F.try_divide(F.sum((1 - t) * (1 - p)), F.sum(1 - t))) / 2).alias("auc"))


def class_distribution(df: DataFrame, label: str, split: str) -> DataFrame:
    return df.groupBy(split, F.col(label).alias("y")).agg(F.count(F.lit(1)).alias("n"))


def summarise(scores: DataFrame, keys: list[str], score: str = "score") -> DataFrame:
    """Mean, standard deviation, standard error and number of runs."""
    return scores.groupBy(*keys).agg(F.avg(score).alias("mean"), F.stddev_samp(score).alias("deviation"), (F.stddev_samp(score) / F.sqrt(F.count(score))).alias("std_error"), F.count(score).alias("runs"))


def rule_frequency(rules_by_trial: DataFrame, keys=("f1", "v1", "f2", "v2", "y")) -> DataFrame:
    """In how many trials each rule is found."""
    return rules_by_trial.groupBy(*keys).agg(F.count(F.lit(1)).alias("occurrences"))
