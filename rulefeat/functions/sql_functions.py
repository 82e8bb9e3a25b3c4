"""The measures as SQL functions, a pandas aggregate, and table functions."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .measures import EPS

#: name, arguments, body
SQL_BODIES = [
    ("rule_conf", "supp BIGINT, supp_x BIGINT", "try_divide(supp * 1.0D, supp_x)"),
    ("rule_lift", "supp BIGINT, supp_x BIGINT, supp_y BIGINT, n BIGINT", "try_divide(supp * 1.0D * n, supp_x * 1.0D * supp_y)"),
    ("rule_rconf", "supp BIGINT, supp_x BIGINT, supp_y BIGINT, n BIGINT", f"supp * 1.0D / (supp_x - supp + {EPS}D) * try_divide((n - supp_y) * 1.0D, supp_y)"),
]


@F.pandas_udf(T.DoubleType())
def label_entropy(y: pd.Series) -> float:
    """Entropy of a group's labels (a convenience: the count-based form scales, this one gathers a group)."""
    import numpy as np

    share = y.value_counts(normalize=True).to_numpy()
    return float(-(share * np.log(share)).sum()) if len(share) else 0.0


@F.udtf(returnType=T.StructType([T.StructField("a", T.IntegerType()), T.StructField("b", T.IntegerType())]))
class PairsOf:
    """All pairs a < b of an array of item ids, for lateral use."""

    def eval(self, items: list[int]) -> Iterator[tuple[int, int]]:
        ordered = sorted(set(items or ()))
        for i, a in enumerate(ordered):
            for b in ordered[i + 1 :]:
                yield a, b


def register(spark: SparkSession) -> None:
    for name, arguments, body in SQL_BODIES:
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}({arguments}) RETURNS DOUBLE RETURN {body}")
    spark.udf.register("label_entropy", label_entropy)
    spark.udtf.register("pairs_of", PairsOf)
