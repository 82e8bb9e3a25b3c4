"""Rules from frequent sets: ranking, redundancy, general rules, and rules used as a classifier."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .ranking import join_on, score_order, top


def top_rules(scored: DataFrame, d_conf: int, score: str, by: tuple[str, ...] = ()) -> DataFrame:
    return top(scored.drop("rank"), score_order(score), d_conf, tuple(by))


def _with_mains(scored: DataFrame, score: str, by) -> DataFrame:
    mains = scored.where("size = 1").select(*by, F.col("f1").alias("mf"), F.col("v1").alias("mv"), "y", F.col(score).alias("m"))
    out = scored
    for side in ("1", "2"):
        own = mains.select(*by, F.col("mf").alias(f"f{side}"), F.col("mv").alias(f"v{side}"), "y", F.col("m").alias(f"main{side}"))
        out = join_on(out, own, [*by, f"f{side}", f"v{side}", "y"], "left")
    return out.select(*scored.columns, "main1", "main2")


def nonredundant(scored: DataFrame, score: str = "rconf", redundancy: str = "strict", margin: float = 1.0, by: tuple[str, ...] = ()) -> DataFrame:
    """Main effects, and the pairs whose score beats both their main effects with the same class.

    "strict" asks for more, "printed" for at least as much, times margin. In a top list by support a pair's mains always
    precede it, so one filter does what a loop over the sorted sets would.
    """
    if redundancy not in ("strict", "printed"):
        raise ValueError(f"redundancy {redundancy!r}")
    bar = F.greatest("main1", "main2") * F.lit(float(margin))  # a main that isn't there is passed over
    beats = F.col(score) > bar if redundancy == "strict" else F.col(score) >= bar
    return _with_mains(scored, score, by).where((F.col("size") == 1) | bar.isNull() | beats).drop("main1", "main2")


def dropped_as_redundant(scored: DataFrame, score: str = "rconf", redundancy: str = "strict", margin: float = 1.0, by: tuple[str, ...] = ()) -> DataFrame:
    """The pairs that nonredundant() leaves out, with the scores of their mains."""
    bar = F.greatest("main1", "main2") * F.lit(float(margin))
    lost = F.col(score) <= bar if redundancy == "strict" else F.col(score) < bar
    return _with_mains(scored, score, by).where((F.col("size") == 2) & lost)


def nonredundant_loop(rows: list[dict], score: str = "rconf", redundancy: str = "strict", margin: float = 1.0) -> list[dict]:
    """The same by going through collected sets in order of support, for tests."""
    kept, scores = [], {}
    for r in sorted(rows, key=lambda r: (str(r["y"]), -r["supp"], r["size"], r["f1"], r["v1"], r["f2"] or -1, r["v2"] or "")):
        if r["size"] == 1:
            scores[r["f1"], r["v1"], r["y"]] = r[score]
            kept.append(r)
            continue
        mains = [scores[k] for k in ((r["f1"], r["v1"], r["y"]), (r["f2"], r["v2"], r["y"])) if k in scores]
        if all(r[score] > margin * m if redundancy == "strict" else r[score] >= margin * m for m in mains):
            kept.append(r)
    return kept


def general_rules(frequent: DataFrame, n: int, min_conf: float) -> DataFrame:
    """frequent(items sorted array, supp), all levels, to rules x -> y with any non-empty disjoint sides: (x, y, supp, supp_x, supp_y, conf, lift)."""
    masks = F.expr("sequence(1, shiftleft(1, size(items)) - 2)")
    split = frequent.where(F.size("items") > 1).select("items", "supp", F.explode(masks).alias("mask"))
    x = F.expr("filter(items, (v, i) -> (shiftright(mask, i) & 1) = 1)")
    y = F.expr("filter(items, (v, i) -> (shiftright(mask, i) & 1) = 0)")
    sided = split.select(x.alias("x"), y.alias("y"), "supp")
    of = lambda name: frequent.select(F.col("items").alias(name), F.col("supp").alias(f"supp_{name}"))
    joined = sided.join(of("x"), "x").join(of("y"), "y")
    conf = F.col("supp").cast("double") / F.col("supp_x")
    lift = (F.col("supp").cast("double") * n) / (F.col("supp_x").cast("double") * F.col("supp_y"))
    return joined.select("x", "y", "supp", "supp_x", "supp_y", conf.alias("conf"), lift.alias("lift")).where(F.col("conf") >= min_conf)


def class_rules(frequent: DataFrame, class_items: list[str]) -> DataFrame:
    """Of level-wise frequent sets those with one class item, as antecedent -> class with the antecedent's support."""
    marks = F.array(*[F.lit(c) for c in class_items])
    sided = frequent.select(F.array_except("items", marks).alias("x"), F.array_intersect("items", marks).alias("c"), "supp").where("size(c) = 1 AND size(x) > 0")
    own = frequent.select(F.col("items").alias("x"), F.col("supp").alias("supp_x"))
    return sided.join(own, "x").select("x", F.col("c")[0].alias("y"), "supp", "supp_x", (F.col("supp").cast("double") / F.col("supp_x")).alias("conf"))


#: Rules of a classifier at most: they become one expression.
VOTING = 2000


def vote(records: DataFrame, rules: DataFrame, features, default: str, key: str, null_policy: str = "skip") -> DataFrame:
    """Classify by the first matching rule in order of confidence, then support: (key, prediction, conf).

    The rules are a budget's number (more than VOTING raise) and become one expression that stops at the first that fits: no join, no shuffle.
    """
    from .features import predicate

    ordered = rules.orderBy(*score_order("conf")).limit(VOTING + 1).collect()
    if len(ordered) > VOTING:
        raise ValueError(f"more than {VOTING} rules to vote by: give the selector a budget")
    first = F.coalesce(*[F.when(predicate(r, list(features), null_policy), F.struct(F.lit(r["y"]).alias("y"), F.lit(r["conf"]).alias("conf"))) for r in ordered], F.lit(None).cast("struct<y:string,conf:double>"))
    return records.select(F.col(key).alias("key"), first.alias("b")).select("key", F.coalesce("b.y", F.lit(default)).alias("prediction"), F.col("b.conf").alias("conf"))
