"""The experiments as queries, each over its whole frame at full width. Learnt scores have no SQL; the rules that they rest on have, and the scores of fixed predictions."""

from __future__ import annotations

from pyspark.sql import functions as F

from .. import workloads
from ..operators import selectors
from . import sqltext as q
from .mining import PARTS, PARTS_F, parts
from .registry import query

for _name, _constant in (("planted_prediction_s1", False), ("planted_prediction_s2", True)):
    query(_name)(lambda spark, sf, c=_constant: workloads.planted_prediction(spark, sf, constant=c))


@query("planted_literal_rules")
def planted_literal_rules(spark, sf):
    """Rules found in 100 trials of 1000 records of the exact distribution, both sets, the five most frequent of each method."""
    out = None
    for name, constant in (("s1", False), ("s2", True)):
        one = workloads.planted_rule_frequency(spark, sf, constant=constant, literal=True).select(F.lit(name).alias("data"), "*")
        out = one if out is None else out.unionByName(one)
    return out.where("occurrences >= 5")


@query("furnace_grid")
def furnace_grid(spark, sf):
    """Log-loss on the validation part by number of intervals and rules, as scored and smoothed, of the logistic learner."""
    return workloads.furnace_grid(spark, sf)


@query("furnace_scores")
def furnace_scores(spark, sf):
    """Scores on the test part of the original features and of the refit chain at each learner's best point of a grid."""
    return workloads.furnace_tuned(spark, sf)


@query("furnace_confusion")
def furnace_confusion(spark, sf):
    """Confusion on the test part of each learner at (0, 0) and (4, 25), over the broad frame of 86 features."""
    return workloads.furnace_refit(spark, sf, {"logistic": (4, 25), "perceptron": (4, 25)}, wide=True)[1]


for _name in workloads.PUBLIC_LIKE:
    # of k from 2 to 10 every second, of the largest set all
    query(f"encodings_{_name}")(lambda spark, sf, n=_name: workloads.encodings_by_cross_validation(spark, sf, n, **({} if n == "star" else {"ks": (2, 4, 6, 8, 10)})))


def _fold_sql(fold: int) -> str:
    train = f"SELECT * FROM ({PARTS}) p WHERE p_partkey % 5 <> {fold}"
    return q.rules_sql(train, PARTS_F, 40, 10, True, "rconf", "strict").replace(f"SELECT {q.RULES_OUT}", f"SELECT {fold} AS fold, {q.RULES_OUT}")


@query("fold_rules", " UNION ALL ".join(f"SELECT * FROM ({_fold_sql(f)}) f{f}" for f in range(5)))
def fold_rules(spark, sf):
    """The rules of each training part of a cross validation."""
    from .mining import rules_out

    df, out = parts(spark, sf), None
    for fold in range(5):
        rules = selectors.select_nonredundant(df.where(F.col("p_partkey") % 5 != fold), "y", PARTS_F, 40, 10).rules
        one = rules_out(rules).select(F.lit(fold).alias("fold"), "*")
        out = one if out is None else out.unionByName(one)
    return out


@query("regression_comparison")
def regression_comparison(spark, sf):
    return workloads.regression_comparison(spark, sf)


@query("vector_comparison")
def vector_comparison(spark, sf):
    return workloads.vector_classification(spark, sf)


@query("run_times")
def run_times(spark, sf):
    """Seconds and counter operations of a selector run by size of sample and by number of features."""
    return workloads.run_times(spark, sf)


@query("sampling_errors")
def sampling_errors(spark, sf):
    """Errors of sampled frequencies by sample size, and how often the leading four sets are recovered, on the exact distribution."""
    return workloads.frequency_estimates(spark, sf, literal_rows=10_000, draws=5)
