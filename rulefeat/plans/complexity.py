"""Predicted and observed cost of a mining run, step by step, in counters touched and counters held."""

from __future__ import annotations

import math
import time

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def predict(n: int, p: int, n_classes: int, d_freq: int, d_conf: int, values: int = 2) -> list[tuple[str, float, float]]:
    """(step, operations, counters held); categories and classes are constants in the growth, and factors here."""
    lg = lambda x: math.log2(max(2, x))
    single, pair = p * values * n_classes, d_freq * (d_freq - 1) // 2 * n_classes
    return [
        ("count singles", n * p, single),
        ("top singles", single * lg(d_freq), d_freq),
        ("count pairs", n * d_freq * d_freq, pair),
        ("top sets", (single + pair) * lg(d_freq), d_freq),
        ("score", d_freq, d_freq),
        ("top rules", d_freq * lg(d_conf or 1), d_conf),
        ("features", d_conf, d_conf),
        ("redundancy", d_freq * lg(d_freq) + d_freq * d_conf, d_freq),
    ]


def observe(df: DataFrame, label: str, features, d_freq: int, d_conf: int) -> DataFrame:
    """(step, touched, held) of one run: what each counting step emits and holds, from the counts themselves."""
    from ..operators import counts, selectors
    from ..operators.ranking import support_order, top

    features = list(features)
    singles = counts.singles(df, features, label).cache()
    n_items, n_single = singles.agg(F.sum("supp"), F.count(F.lit(1))).first()
    mined = selectors.mine(df, label, features, d_freq, True)
    n_classes = singles.select("y").distinct().count()
    kept = top(selectors.as_sets(singles), support_order(), F.lit(max(1, d_freq // n_classes)), ("y",)).select("f1", "v1").distinct()
    items = [(r[0], r[1]) for r in kept.collect()]
    pairs = counts.pairs(df, features, label, items).agg(F.coalesce(F.sum("supp"), F.lit(0)), F.count(F.lit(1))).first()
    chosen = selectors.recut(mined, d_conf)
    n_sets, n_rules, n_features = mined.sets.count(), chosen.rules.count(), chosen.features.count()
    rows = [("count singles", n_items, n_single), ("top singles", n_single, len(items)), ("count pairs", pairs[0], pairs[1]), ("top sets", n_single + pairs[1], n_sets), ("score", n_sets, n_sets), ("top rules", n_sets, n_rules), ("features", n_rules, n_features)]
    singles.unpersist()
    return df.sparkSession.createDataFrame([(s, int(t), int(h)) for s, t, h in rows], "step string, touched long, held long")


def timed(run, repeats: int = 3) -> list[float]:
    """Seconds of each run of a function that returns a DataFrame, drained without keeping rows."""
    from ..sources.tables import drain

    out = []
    for _ in range(repeats):
        start = time.perf_counter()
        drain(run())
        out.append(time.perf_counter() - start)
    return out
