"""Queries of the counting, mining and selection operators."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.measures import info_distance, with_measures
from ..ml import attach as attach_modes
from ..operators import counts, features as feature_ops, itemsets, rules as rule_ops, selectors
from ..operators.ranking import support_order, top
from ..sources import frames
from ..storage import materialise
from . import sqltext as q
from .registry import query

STAR, STAR_F = frames.STAR, frames.STAR_CATEGORICAL
STAR_NATURAL = f"SELECT {', '.join(c for c in [*STAR_F, 'l_orderkey', 'l_linenumber', 'l_partkey', 'l_suppkey'] if c != 'l_returnflag')}, l_returnflag AS y FROM ({STAR}) s"
NATURAL_F = STAR_F[1:]
PARTS, PARTS_F = frames.PARTS, frames.PARTS_FEATURES
PART_BUDGET = {"d_freq": 40, "d_conf": 10}
LEVEL_SUPPORT = 0.0035
LONG = "CAST({} AS BIGINT)"


#: Results show a missing second item as feature 0 with an empty value.
SECOND_SQL = "coalesce(f2, 0) AS f2, coalesce(v2, '') AS v2"


def second() -> list:
    return [F.coalesce("f2", F.lit(0)).alias("f2"), F.coalesce("v2", F.lit("")).alias("v2")]


def sets_out(df: DataFrame) -> DataFrame:
    return df.select("size", "f1", "v1", *second(), "y", "supp", F.col("rank").cast("long").alias("rank"))


def rules_out(df: DataFrame) -> DataFrame:
    return df.select("size", "f1", "v1", *second(), "y", "supp", "supp_x", F.round("conf", 6).alias("conf"), F.round("lift", 6).alias("lift"), "log_rconf", F.col("rank").cast("long").alias("rank"))


def features_out(df: DataFrame) -> DataFrame:
    return df.select(F.col("feature_id").cast("long").alias("feature_id"), "size", "f1", "v1", *second())


def star(spark: SparkSession, sf: str) -> DataFrame:
    return frames.frame(spark, sf, STAR_NATURAL)


def star_once(spark: SparkSession, sf: str) -> DataFrame:
    """The features and the label alone, joined once for all scans that follow."""
    return materialise(star(spark, sf).select(*NATURAL_F, "y"), "star")


def parts(spark: SparkSession, sf: str) -> DataFrame:
    return frames.frame(spark, sf, PARTS)


@query("item_counts", q.counted(STAR_NATURAL, NATURAL_F) + " SELECT f1 AS f, v1 AS v, y, supp FROM sets1")
def item_counts(spark, sf):
    return counts.singles(star(spark, sf), NATURAL_F, "y")


@query("item_counts_grouping_sets", q.counted(STAR_NATURAL, NATURAL_F) + " SELECT f1 AS f, v1 AS v, y, supp FROM sets1")
def item_counts_grouping_sets(spark, sf):
    return counts.singles_by_grouping_sets(star(spark, sf), NATURAL_F, "y")


@query("frequent_singles", q.counted(STAR_NATURAL, NATURAL_F) + f" SELECT {q.SETS_OUT} FROM (SELECT *, row_number() OVER (ORDER BY {q.ORDER}) AS rank FROM sets1) z WHERE rank <= 30")
def frequent_singles(spark, sf):
    return sets_out(top(selectors.as_sets(counts.singles(star(spark, sf), NATURAL_F, "y")), support_order(), 30))


@query("pair_candidates", q.mined(STAR_NATURAL, NATURAL_F, 30, False) + " SELECT f1, v1, f2, v2, y FROM cand")
def pair_candidates(spark, sf):
    return counts.candidates(top(selectors.as_sets(counts.singles(star(spark, sf), NATURAL_F, "y")), support_order(), 30))


def _pairs(spark, sf, plan: str) -> DataFrame:
    df = star_once(spark, sf)
    first = materialise(top(selectors.as_sets(counts.singles(df, NATURAL_F, "y")), support_order(), 30), "top-singles")
    items = [(r[0], r[1]) for r in first.select("f1", "v1").distinct().collect()]
    wanted = counts.candidates(first)
    return counts.pairs(df, NATURAL_F, "y", items, plan=plan).join(wanted, ["f1", "v1", "f2", "v2", "y"], "left_semi").select("f1", "v1", "f2", "v2", "y", "supp")


for _plan in ("explode", "gram", "bits"):
    query("pair_counts" + ("" if _plan == "explode" else f"_{_plan}"), q.mined(STAR_NATURAL, NATURAL_F, 30, False) + " SELECT f1, v1, f2, v2, y, supp FROM sets2")(lambda spark, sf, p=_plan: _pairs(spark, sf, p))


@query("frequent_pairs", q.mined(STAR_NATURAL, NATURAL_F, 30, False) + f" SELECT {q.SETS_OUT} FROM freq")
def frequent_pairs(spark, sf):
    return sets_out(selectors.mine(star_once(spark, sf), "y", NATURAL_F, 30, False).sets)


# --- baskets, any size -------------------------------------------------------------------------------------------------

_BASKETS = f"WITH b AS ({frames.plain_sql(frames.BASKETS)}), n AS (SELECT count(DISTINCT basket) AS n FROM b), m AS (SELECT ceil({LEVEL_SUPPORT} * n - 1e-9) AS least, n FROM n)"
_L1 = "l1 AS (SELECT item AS i1, count(*) AS supp FROM b GROUP BY 1 HAVING count(*) >= (SELECT least FROM m))"
_L2 = "l2 AS (SELECT a.item AS i1, b.item AS i2, count(*) AS supp FROM b a JOIN b ON a.basket = b.basket AND a.item < b.item GROUP BY 1, 2 HAVING count(*) >= (SELECT least FROM m))"
_L3 = "l3 AS (SELECT a.item AS i1, b.item AS i2, c.item AS i3, count(*) AS supp FROM b a JOIN b ON a.basket = b.basket AND a.item < b.item JOIN b c ON a.basket = c.basket AND b.item < c.item GROUP BY 1, 2, 3 HAVING count(*) >= (SELECT least FROM m))"


def baskets(spark, sf) -> DataFrame:
    from ..operators.items import transactions

    return materialise(transactions(frames.frame(spark, sf, frames.BASKETS), "basket", "item").select("items"), "baskets")


def _level(spark, sf, k: int) -> DataFrame:
    found = itemsets.levelwise(baskets(spark, sf), min_support=LEVEL_SUPPORT, max_len=k).where(F.col("size") == k)
    return found.select(*[F.col("items")[i].alias(f"i{i + 1}") for i in range(k)], "supp")


for _k, _cte in ((1, _L1), (2, _L2), (3, _L3)):
    query(f"levelwise_baskets_l{_k}", f"{_BASKETS}, {_cte} SELECT * FROM l{_k}")(lambda spark, sf, k=_k: _level(spark, sf, k))


@query("pattern_growth_baskets", f"{_BASKETS}, {_L1}, {_L2} SELECT 1 AS size, i1 AS items, supp FROM l1 UNION ALL SELECT 2, concat(i1, ',', i2), supp FROM l2")
def pattern_growth_baskets(spark, sf):
    return itemsets.pattern_growth(baskets(spark, sf), LEVEL_SUPPORT, 2).select("size", F.array_join("items", ",").alias("items"), "supp")


@query("rules_all_baskets", f"""{_BASKETS}, {_L1}, {_L2}, r AS (SELECT i1 AS x, i2 AS y, supp FROM l2 UNION ALL SELECT i2, i1, supp FROM l2)
SELECT r.x, r.y, r.supp, round(CAST(r.supp AS DOUBLE) / a.supp, 6) AS conf, round((CAST(r.supp AS DOUBLE) * n) / (CAST(a.supp AS DOUBLE) * c.supp), 6) AS lift
FROM r JOIN l1 a ON r.x = a.i1 JOIN l1 c ON r.y = c.i1, m WHERE CAST(r.supp AS DOUBLE) / a.supp >= 0.05""")
def rules_all_baskets(spark, sf):
    tx = baskets(spark, sf)
    found = materialise(itemsets.levelwise(tx, min_support=LEVEL_SUPPORT, max_len=2).select("items", "supp"), "frequent")
    out = rule_ops.general_rules(found, tx.count(), 0.05)
    return out.select(F.col("x")[0].alias("x"), F.col("y")[0].alias("y"), "supp", F.round("conf", 6).alias("conf"), F.round("lift", 6).alias("lift"))


# --- selectors on parts ------------------------------------------------------------------------------------------------

_THRESHOLD = q.mined(PARTS, PARTS_F, 1_000_000, False) + ", thr AS (SELECT * FROM scored WHERE supp >= ceil(0.02 * n - 1e-9) AND conf >= 0.5)"


@query("class_rules_threshold", f"{_THRESHOLD} SELECT size, f1, v1, {SECOND_SQL}, y, supp, CAST(supp_x AS BIGINT) AS supp_x, round(conf, 6) AS conf, round(lift, 6) AS lift FROM thr")
def class_rules_threshold(spark, sf):
    r = selectors.select_by_threshold(parts(spark, sf), "y", PARTS_F, 0.02, 0.5).rules
    return r.select("size", "f1", "v1", *second(), "y", "supp", "supp_x", F.round("conf", 6).alias("conf"), F.round("lift", 6).alias("lift"))


@query("threshold_features", f"{_THRESHOLD}, ff AS (SELECT {q.FEATURES_OUT} FROM (SELECT DISTINCT size, f1, v1, f2, v2 FROM thr) d) SELECT feature_id, size, f1, v1, {SECOND_SQL} FROM ff")
def threshold_features(spark, sf):
    return features_out(selectors.select_by_threshold(parts(spark, sf), "y", PARTS_F, 0.02, 0.5).features)


@query("class_rules_levelwise", q.counted(PARTS, PARTS_F) + """, least AS (SELECT ceil(0.02 * max(n) - 1e-9) AS m FROM lab), tot AS (SELECT f1, v1, sum(supp) AS supp_x FROM sets1 GROUP BY ALL)
SELECT concat(CAST(f1 AS VARCHAR), '=', v1) AS x, concat('class=', y) AS y, supp, CAST(supp_x AS BIGINT) AS supp_x, round(CAST(supp AS DOUBLE) / supp_x, 6) AS conf FROM sets1 JOIN tot USING (f1, v1), least WHERE supp >= m""")
def class_rules_levelwise(spark, sf):
    df = parts(spark, sf)
    tagged = [F.concat(F.lit(f"{i}="), F.col(c)) for i, c in enumerate(PARTS_F, 1)]
    tx = materialise(df.select(F.array_sort(F.array(*tagged, F.concat(F.lit("class="), "y"))).alias("items")), "tagged")
    found = materialise(itemsets.levelwise(tx, min_support=0.02, max_len=2).select("items", "supp"), "frequent")
    classes = [f"class={r[0]}" for r in df.select("y").distinct().collect()]
    return rule_ops.class_rules(found, classes).select(F.col("x")[0].alias("x"), "y", "supp", "supp_x", F.round("conf", 6).alias("conf"))


def _budget(spark, sf):
    return selectors.select_by_budget(parts(spark, sf), "y", PARTS_F, **PART_BUDGET)


@query("budget_frequent", q.mined(PARTS, PARTS_F, 40, False) + f" SELECT {q.SETS_OUT} FROM freq")
def budget_frequent(spark, sf):
    return sets_out(_budget(spark, sf).mined.sets)


@query("budget_rules", q.rules_sql(PARTS, PARTS_F, 40, 10, False, "conf"))
def budget_rules(spark, sf):
    return rules_out(_budget(spark, sf).rules)


@query("budget_features", q.features_cte(PARTS, PARTS_F, 40, 10, False, "conf") + " SELECT feature_id, size, f1, v1, " + SECOND_SQL + " FROM feats")
def budget_features(spark, sf):
    return features_out(_budget(spark, sf).features)


@query("balanced_frequent", q.mined(PARTS, PARTS_F, 40, True) + f" SELECT {q.SETS_OUT} FROM freq")
def balanced_frequent(spark, sf):
    return sets_out(selectors.select_balanced(parts(spark, sf), "y", PARTS_F, **PART_BUDGET).mined.sets)


for _score in ("rconf", "lift", "conf"):
    query("balanced_rules" + ("" if _score == "rconf" else f"_{_score}"), q.rules_sql(PARTS, PARTS_F, 40, 10, True, _score))(
        lambda spark, sf, s=_score: rules_out(selectors.select_balanced(parts(spark, sf), "y", PARTS_F, score=s, **PART_BUDGET).rules)
    )


@query("balanced_features", q.features_cte(PARTS, PARTS_F, 40, 10) + " SELECT feature_id, size, f1, v1, " + SECOND_SQL + " FROM feats")
def balanced_features(spark, sf):
    return features_out(selectors.select_balanced(parts(spark, sf), "y", PARTS_F, **PART_BUDGET).features)


for _name, _redundancy, _margin in (("nonredundant_rules", "strict", 1.0), ("nonredundant_printed", "printed", 1.0), ("nonredundant_margin2", "strict", 2.0)):
    query(_name, q.rules_sql(PARTS, PARTS_F, 40, 10, True, "rconf", _redundancy, _margin))(
        lambda spark, sf, r=_redundancy, m=_margin: rules_out(selectors.select_nonredundant(parts(spark, sf), "y", PARTS_F, redundancy=r, margin=m, **PART_BUDGET).rules)
    )


query("nonredundant_conf", q.rules_sql(PARTS, PARTS_F, 40, 10, True, "conf", "strict", 1.0))(
    lambda spark, sf: rules_out(selectors.select_nonredundant(parts(spark, sf), "y", PARTS_F, score="conf", **PART_BUDGET).rules)
)


def _nonredundant(spark, sf):
    return selectors.select_nonredundant(parts(spark, sf), "y", PARTS_F, **PART_BUDGET)


_FEATS = q.features_cte(PARTS, PARTS_F, 40, 10, True, "rconf", "strict", 1.0)


@query("nonredundant_features", f"{_FEATS} SELECT feature_id, size, f1, v1, {SECOND_SQL} FROM feats")
def nonredundant_features(spark, sf):
    return features_out(_nonredundant(spark, sf).features)


@query("redundancy_dropped", q.mined(PARTS, PARTS_F, 40, True) + q.beaten() + " SELECT f1, v1, f2, v2, y, supp, CAST(supp_x AS BIGINT) AS supp_x, round(ln(rconf), 6) AS log_rconf FROM lost")
def redundancy_dropped(spark, sf):
    mined = selectors.mine(parts(spark, sf), "y", PARTS_F, 40, True)
    return rule_ops.dropped_as_redundant(with_measures(mined.sets)).select("f1", "v1", "f2", "v2", "y", "supp", "supp_x", "log_rconf")


@query("feature_matrix", _FEATS + q.held_cte(PARTS_F) + " SELECT p_partkey, CAST(feature_id AS BIGINT) AS feature_id FROM held JOIN base USING (rid)")
def feature_matrix(spark, sf):
    return feature_ops.matrix(parts(spark, sf), _nonredundant(spark, sf).features, PARTS_F, ["p_partkey"]).select("p_partkey", F.col("feature_id").cast("long").alias("feature_id"))


@query("feature_counts", _FEATS + q.held_cte(PARTS_F) + " SELECT CAST(feature_id AS BIGINT) AS feature_id, y, count(*) AS n FROM held JOIN base USING (rid) GROUP BY 1, 2")
def feature_counts(spark, sf):
    return feature_ops.feature_counts(parts(spark, sf), _nonredundant(spark, sf).features, PARTS_F, "y").select(F.col("feature_id").cast("long").alias("feature_id"), "y", "n")


@query("feature_names", _FEATS + " SELECT CAST(feature_id AS BIGINT) AS feature_id, " + "concat(CASE f1 " + " ".join(f"WHEN {i} THEN '{c}'" for i, c in enumerate(PARTS_F, 1)) + " END, '=', v1, CASE WHEN f2 IS NULL THEN '' ELSE concat(', ', CASE f2 " + " ".join(f"WHEN {i} THEN '{c}'" for i, c in enumerate(PARTS_F, 1)) + " END, '=', v2) END) AS name FROM feats")
def feature_names(spark, sf):
    return feature_ops.named(_nonredundant(spark, sf).features, PARTS_F).select(F.col("feature_id").cast("long").alias("feature_id"), "name")


_CODES = ", ".join(f"CAST(dense_rank() OVER (ORDER BY {c}) - 1 AS BIGINT) AS {c}_code" for c in PARTS_F)


@query("attach_label", _FEATS + q.held_cte(PARTS_F) + f" SELECT p_partkey, {_CODES}, (SELECT count(*) FROM held h WHERE h.rid = base.rid) AS n_rules FROM base")
def attach_label(spark, sf):
    out = attach_modes.label_plus_rules(parts(spark, sf), _nonredundant(spark, sf).features, PARTS_F)
    ones = [F.col(c).cast("long") for c in out.columns if c.startswith("rule_")]
    return out.select("p_partkey", *[F.col(f"{c}_code").cast("long").alias(f"{c}_code") for c in PARTS_F], sum(ones[1:], ones[0]).alias("n_rules"))


@query("attach_onehot_interactions", _FEATS + q.held_cte(PARTS_F) + " SELECT p_partkey, concat(CAST(f AS VARCHAR), '=', v) AS slot FROM items JOIN base USING (rid) UNION ALL SELECT p_partkey, concat('rule', CAST(row_number AS VARCHAR)) FROM (SELECT feature_id, row_number() OVER (ORDER BY feature_id) AS row_number FROM feats WHERE size = 2) g JOIN held USING (feature_id) JOIN base USING (rid)")
def attach_onehot_interactions(spark, sf):
    return attach_modes.onehot_plus_interactions_long(parts(spark, sf), _nonredundant(spark, sf).features, PARTS_F, ["p_partkey"])


for _name, _shares, _given in (("balanced_rules_proportional", "proportional", "proportional"), ("balanced_rules_given", "CASE l.y WHEN '0' THEN 12 WHEN '3' THEN 7 ELSE 1 END", {"0": 12, "3": 7})):
    query(_name, q.mined(PARTS, PARTS_F, 40, True, shares=_shares) + f" SELECT {q.RULES_OUT} FROM ({q.ranked('scored', 'rconf', 10)}) r")(
        lambda spark, sf, g=_given: rules_out(selectors.select_balanced(parts(spark, sf), "y", PARTS_F, class_budget=g, **PART_BUDGET).rules)
    )


@query("floored_rules", q.mined(PARTS, PARTS_F, 40, True, least=20) + q.beaten() + f" SELECT {q.RULES_OUT} FROM ({q.ranked('(SELECT * FROM kept WHERE rconf >= 2)', 'rconf', 10)}) r")
def floored_rules(spark, sf):
    return rules_out(selectors.select_nonredundant(parts(spark, sf), "y", PARTS_F, min_count=20, min_score=2.0, **PART_BUDGET).rules)


for _plan in ("gram", "join"):
    query(f"nonredundant_rules_{_plan}", q.rules_sql(PARTS, PARTS_F, 40, 10, True, "rconf", "strict"))(
        lambda spark, sf, p=_plan: rules_out(selectors.select_nonredundant(parts(spark, sf), "y", PARTS_F, plan=p, **PART_BUDGET).rules)
    )


# --- planted trials ----------------------------------------------------------------------------------------------------

PLANTED_P = 99
METHODS = (("budget", False, "conf", None, 1.0), ("balanced", True, "rconf", None, 1.0), ("nonredundant", True, "rconf", "strict", 1.0), ("nonredundant_1.5", True, "rconf", "strict", 1.5), ("nonredundant_2", True, "rconf", "strict", 2.0))


def _planted_sql(constant: bool) -> str:
    select, xs, parts_ = frames.planted(PLANTED_P, constant), [f"x{i}" for i in range(1, PLANTED_P + 1)], []
    for name, per_class, score, redundancy, margin in METHODS:
        text = q.mined(select, xs, 45, per_class, "trial") + (q.beaten(score, redundancy, margin, "trial") if redundancy else "")
        parts_.append(f"SELECT '{name}' AS method, f1, v1, {SECOND_SQL}, y, occurrences FROM ({text} SELECT f1, v1, f2, v2, y, count(*) AS occurrences FROM ({q.ranked('kept' if redundancy else 'scored', score, 5, 'trial')}) r GROUP BY ALL)")
    return " UNION ALL ".join(parts_)


def _planted(spark, sf, constant: bool) -> DataFrame:
    df, xs = materialise(frames.frame(spark, sf, frames.planted(PLANTED_P, constant)), "planted"), [f"x{i}" for i in range(1, PLANTED_P + 1)]
    runs = selectors.mine_both(df, "y", xs, 45, by=("trial",))
    out = None
    for name, per_class, score, redundancy, margin in METHODS:
        rules = selectors.recut(runs[per_class], 5, score, redundancy, margin).rules
        one = rules.groupBy("f1", "v1", "f2", "v2", "y").agg(F.count(F.lit(1)).alias("occurrences")).select(F.lit(name).alias("method"), "f1", "v1", *second(), "y", "occurrences")
        out = one if out is None else out.unionByName(one)
    return out


query("planted_s1_rules", _planted_sql(False))(lambda spark, sf: _planted(spark, sf, False))
query("planted_s2_rules", _planted_sql(True))(lambda spark, sf: _planted(spark, sf, True))


# --- other frames ------------------------------------------------------------------------------------------------------

_VECTORS, _DIMS = frames.vectors()


@query("embedding_rules", q.rules_sql(_VECTORS, _DIMS, 90, 18, True, "rconf", "strict"))
def embedding_rules(spark, sf):
    return rules_out(selectors.select_nonredundant(frames.frame(spark, sf, _VECTORS), "y", _DIMS, 90, 18).rules)


@query("role_rules", q.rules_sql(frames.TURNS, frames.TURN_FEATURES, 45, 10, True, "rconf", "strict"))
def role_rules(spark, sf):
    return rules_out(selectors.select_nonredundant(frames.frame(spark, sf, frames.TURNS), "y", frames.TURN_FEATURES, 45, 10).rules)


_DIST = q.counted(PARTS, PARTS_F)


@query("info_distance", f"""{_DIST}, g AS (SELECT DISTINCT f1 AS f, v1 AS v FROM sets1), t AS (SELECT f1 AS f, v1 AS v, sum(supp) AS supp_x FROM sets1 GROUP BY ALL)
SELECT g.f, g.v, CAST(t.supp_x AS BIGINT) AS supp_x, round(sum(abs(CAST(coalesce(s.supp, 0) AS DOUBLE) / t.supp_x - CAST(l.supp_y AS DOUBLE) / l.n)) / 2, 6) AS distance
FROM g JOIN t USING (f, v) CROSS JOIN lab l LEFT JOIN sets1 s ON s.f1 = g.f AND s.v1 = g.v AND s.y = l.y GROUP BY ALL""")
def info_distance_parts(spark, sf):
    df = parts(spark, sf)
    rows = counts.singles(df, PARTS_F, "y").join(counts.labels(df, "y"), "y")
    return info_distance(rows, ["f", "v"]).select("f", "v", "supp_x", F.round("distance", 6).alias("distance"))


def _coverage_sql() -> str:
    out = []
    for name, per_class, score, redundancy in (("budget", False, "conf", None), ("balanced", True, "rconf", None), ("nonredundant", True, "rconf", "strict")):
        text = q.mined(PARTS, PARTS_F, 40, per_class) + (q.beaten(score, redundancy) if redundancy else "")
        out.append(f"SELECT '{name}' AS method, classes, features FROM ({text} SELECT count(DISTINCT y) AS classes, count(DISTINCT concat(f1, v1, '|', coalesce(f2, 0), coalesce(v2, ''))) AS features FROM ({q.ranked('kept' if redundancy else 'scored', score, 10)}) r)")
    out.append(f"SELECT 'threshold' AS method, classes, features FROM ({_THRESHOLD} SELECT count(DISTINCT y) AS classes, count(DISTINCT concat(f1, v1, '|', coalesce(f2, 0), coalesce(v2, ''))) AS features FROM thr)")
    return " UNION ALL ".join(out)


@query("class_coverage", _coverage_sql())
def class_coverage(spark, sf):
    df, out = parts(spark, sf), None
    for name, s in (("budget", selectors.select_by_budget(df, "y", PARTS_F, **PART_BUDGET)), ("balanced", selectors.select_balanced(df, "y", PARTS_F, **PART_BUDGET)), ("nonredundant", selectors.select_nonredundant(df, "y", PARTS_F, **PART_BUDGET)), ("threshold", selectors.select_by_threshold(df, "y", PARTS_F, 0.02, 0.5))):
        one = s.rules.agg(F.count_distinct("y").alias("classes"), F.count_distinct(F.struct("f1", "v1", "f2", "v2")).alias("features")).select(F.lit(name).alias("method"), "*")
        out = one if out is None else out.unionByName(one)
    return out


_CUBED = "FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY {}(l_returnflag, l_linestatus, o_orderpriority)"
for _kind, _fn in (("cube", counts.value_cube), ("rollup", counts.value_rollup)):
    query(f"count_{_kind}", f"SELECT l_returnflag, l_linestatus, o_orderpriority, count(*) AS supp, grouping_id(l_returnflag, l_linestatus, o_orderpriority) AS gid {_CUBED.format(_kind.upper())}")(
        lambda spark, sf, f=_fn: f(star(spark, sf).withColumnRenamed("y", "l_returnflag"), ["l_returnflag", "l_linestatus", "o_orderpriority"])
    )
