"""Queries of sampling, binning, mixed data, evaluation, baselines, joins over time, and streams."""

from __future__ import annotations


from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions.measures import with_measures
from ..ml import attach, baselines, evaluate, learners, tuning
from ..operators import binning, counts, params, rules as rule_ops, sampling, selectors
from ..operators.features import product_pairs
from ..plans import complexity
from ..sources import frames
from ..storage import materialise
from ..streaming import running
from . import sqltext as q
from .mining import PARTS, PARTS_F, parts, rules_out
from .registry import query

# --- sampling ----------------------------------------------------------------------------------------------------------

BITS, BITS_F = frames.frequency_bits(), [f"x{i}" for i in range(1, 11)]
KEY = ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey"]
SEED, TOP, N_SET = 1, 5, (100, 500, 1000, 5000)


def _one_class(df: DataFrame, weight: str | None = None) -> DataFrame:
    """The frequent sets of features that are 1, one label."""
    ones = df.select(*[F.when(F.col(c) == "1", F.col(c)).alias(c) for c in BITS_F], "y", *([weight] if weight else []))
    return selectors.mine(ones, "y", BITS_F, TOP, False, weight=weight).sets


def _frequency_ctes(n_prime: int) -> str:
    """hits(f1, f2, supp) of the draw and full(f1, f2, supp) of all, sets of one or two ones."""
    xs = " UNION ALL ".join(f"SELECT pos, {i} AS f FROM {{0}} WHERE x{i} = '1'" for i in range(1, 11))
    return f"""WITH b AS ({frames.plain_sql(BITS)}), r AS (SELECT row_number() OVER (ORDER BY {', '.join(KEY)}) - 1 AS pos, * FROM b), n AS (SELECT count(*) AS n FROM b),
w AS (SELECT ({sampling.LCG[0]} * CAST(i AS BIGINT) + {sampling.LCG[1] + SEED}) % n AS pos, count(*) AS weight FROM range({n_prime}) t(i), n GROUP BY 1),
it AS ({xs.format('r')}),
f1s AS (SELECT a.f AS f1, NULL AS f2, count(*) AS supp FROM it a GROUP BY 1), f2s AS (SELECT a.f AS f1, b.f AS f2, count(*) AS supp FROM it a JOIN it b ON a.pos = b.pos AND a.f < b.f GROUP BY 1, 2),
s1 AS (SELECT a.f AS f1, NULL AS f2, sum(weight) AS supp FROM it a JOIN w USING (pos) GROUP BY 1), s2 AS (SELECT a.f AS f1, b.f AS f2, sum(weight) AS supp FROM it a JOIN it b ON a.pos = b.pos AND a.f < b.f JOIN w ON w.pos = a.pos GROUP BY 1, 2),
full_sets AS (SELECT * FROM f1s UNION ALL SELECT * FROM f2s), draw_sets AS (SELECT * FROM s1 UNION ALL SELECT * FROM s2),
lead AS (SELECT *, row_number() OVER (ORDER BY supp DESC, f2 IS NOT NULL, f1, coalesce(f2, -1)) AS rank FROM full_sets), led AS (SELECT *, row_number() OVER (ORDER BY supp DESC, f2 IS NOT NULL, f1, coalesce(f2, -1)) AS rank FROM draw_sets)"""


def _drawn(spark, sf, n_prime: int):
    df = frames.frame(spark, sf, BITS)
    return df, materialise(sampling.draw(df, n_prime, SEED, "lcg", KEY), "draw")


@query("sample_lcg_frequency", _frequency_ctes(5000) + " SELECT d.f1, coalesce(d.f2, 0) AS f2, round(CAST(d.supp AS DOUBLE) / 5000, 6) AS p_hat, round(CAST(f.supp AS DOUBLE) / n, 6) AS p FROM led d JOIN full_sets f ON d.f1 = f.f1 AND d.f2 IS NOT DISTINCT FROM f.f2, n WHERE d.rank <= 5")
def sample_lcg_frequency(spark, sf):
    df, drawn = _drawn(spark, sf, 5000)
    kept = sampling.estimate(_one_class(drawn, "weight"), 5000)
    ones = df.select(*[F.when(F.col(c) == "1", F.col(c)).alias(c) for c in BITS_F], "y")
    exact = sampling.recount(ones, kept, BITS_F, "y").select(F.col("f1").alias("g1"), F.col("f2").alias("g2"), F.col("supp").alias("whole"))
    n = df.count()
    met = kept.join(exact, (F.col("f1") == F.col("g1")) & F.col("f2").eqNullSafe(F.col("g2")))
    return met.select("f1", F.coalesce("f2", F.lit(0)).alias("f2"), F.round("p_hat", 6).alias("p_hat"), F.round(F.col("whole").cast("double") / n, 6).alias("p"))


def _error_sql(n_prime: int) -> str:
    return f"""SELECT {n_prime} AS n_prime, round(max(abs(CAST(coalesce(d.supp, 0) AS DOUBLE) / {n_prime} - CAST(f.supp AS DOUBLE) / n)), 6) AS max_error, count(*) FILTER (WHERE f.rank <= 4 AND e.f1 IS NOT NULL) AS found
FROM lead f LEFT JOIN draw_sets d ON d.f1 = f.f1 AND d.f2 IS NOT DISTINCT FROM f.f2 LEFT JOIN (SELECT * FROM led WHERE rank <= 5) e ON e.f1 = f.f1 AND e.f2 IS NOT DISTINCT FROM f.f2, n WHERE f.rank <= 5"""


@query("sample_error_by_n", " UNION ALL ".join(f"SELECT * FROM ({_frequency_ctes(m)} {_error_sql(m)})" for m in N_SET))
def sample_error_by_n(spark, sf):
    df = frames.frame(spark, sf, BITS)
    full = _one_class(df)
    n = df.count()
    truth = materialise(full.select("f1", "v1", "f2", "v2", "rank", (F.col("supp").cast("double") / n).alias("p")), "truth")
    out = None
    for m in N_SET:
        _, drawn = _drawn(spark, sf, m)
        ones = drawn.select(*[F.when(F.col(c) == "1", F.col(c)).alias(c) for c in BITS_F], "y", "weight")
        single = counts.singles(ones, BITS_F, "y", weight="weight")
        pair = counts.pairs(ones, BITS_F, "y", [(i, "1") for i in range(1, 11)], weight="weight")
        every = selectors.as_sets(single).unionByName(pair.select(F.lit(2).alias("size"), "f1", "v1", "f2", "v2", "y", "supp"))
        error = sampling.freq_error(sampling.estimate(every, m), truth, ["f1", "v1", "f2", "v2"])
        worst = error.where("p > 0").agg(F.round(F.max("error"), 6).alias("max_error"))
        found = sampling.recall_at(_one_class(drawn, "weight"), truth, ["f1", "v1", "f2", "v2"], 4)
        one = worst.crossJoin(found).select(F.lit(m).alias("n_prime"), "max_error", "found")  # one row each
        out = one if out is None else out.unionByName(one)
    return out


@query("sample_full_confidence", f"""WITH b AS ({frames.plain_sql(PARTS)}), r AS (SELECT row_number() OVER (ORDER BY p_partkey) - 1 AS pos, * FROM b), n AS (SELECT count(*) AS n FROM b),
w AS (SELECT ({sampling.LCG[0]} * CAST(i AS BIGINT) + {sampling.LCG[1] + SEED}) % n AS pos, count(*) AS weight FROM range(500) t(i), n GROUP BY 1), it AS ({' UNION ALL '.join(f"SELECT pos, {i} AS f1, {c} AS v1, y FROM r" for i, c in enumerate(PARTS_F, 1))}),
s AS (SELECT f1, v1, y, sum(weight) AS drawn FROM it JOIN w USING (pos) GROUP BY ALL), t AS (SELECT *, row_number() OVER (ORDER BY drawn DESC, f1, v1, y) AS rank FROM s), a AS (SELECT f1, v1, y, count(*) AS supp, sum(count(*)) OVER (PARTITION BY f1, v1) AS supp_x FROM it GROUP BY f1, v1, y)
SELECT f1, v1, y, CAST(drawn AS BIGINT) AS drawn, supp, CAST(supp_x AS BIGINT) AS supp_x, round(CAST(supp AS DOUBLE) / supp_x, 6) AS conf FROM t JOIN a USING (f1, v1, y) WHERE rank <= 12""")
def sample_full_confidence(spark, sf):
    df = parts(spark, sf)
    drawn = sampling.draw(df, 500, SEED, "lcg", ["p_partkey"])
    single = selectors.as_sets(counts.singles(drawn, PARTS_F, "y", weight="weight"))
    from ..operators.ranking import support_order, top

    kept = materialise(top(single, support_order(), 12), "kept")
    exact = sampling.recount(df, kept, PARTS_F, "y").select("f1", "v1", "y", F.col("supp").alias("all"), "supp_x")
    joined = kept.select("f1", "v1", "y", F.col("supp").alias("drawn")).join(exact, ["f1", "v1", "y"])
    return joined.select("f1", "v1", "y", "drawn", F.col("all").alias("supp"), "supp_x", F.round(F.col("all").cast("double") / F.col("supp_x"), 6).alias("conf"))


#: The line items of each supplier as a sample, and the distances that its frequencies may be off by.
_SIZES = "SELECT CAST(l_suppkey AS BIGINT) AS l_suppkey, count(*) AS n FROM lineitem GROUP BY l_suppkey"
EPSILONS = (0.01, 0.02, 0.05, 0.1)


def _bounds(spark, sf, bound) -> DataFrame:
    items = frames.spread(spark.read.parquet(f"{sf}/lineitem.parquet").select(F.col("l_suppkey").cast("long").alias("l_suppkey")))
    sizes = items.groupBy("l_suppkey").agg(F.count(F.lit(1)).alias("n"))
    return sizes.select("l_suppkey", "n", F.explode(F.array(*map(F.lit, EPSILONS))).alias("eps")).withColumn("bound", F.round(bound(F.col("n"), F.col("eps")), 6))


for _name, _f, _sql in (("hoeffding_table", sampling.hoeffding_column, "2 * exp(-2 * n * CAST(eps AS DOUBLE) * CAST(eps AS DOUBLE))"), ("swap_bound_table", sampling.swap_bound_column, "4 * exp(-n * CAST(eps AS DOUBLE) * CAST(eps AS DOUBLE) / 2)")):
    query(_name, f"SELECT l_suppkey, n, CAST(eps AS DOUBLE) AS eps, round({_sql}, 6) AS bound FROM ({_SIZES}) s, (VALUES {', '.join(f'({e})' for e in EPSILONS)}) e(eps)")(lambda spark, sf, f=_f: _bounds(spark, sf, f))

# --- binning -----------------------------------------------------------------------------------------------------------

STAR = frames.STAR
BIN_F = ["l_quantity", "o_totalprice"]
_LONG = f"WITH b AS ({frames.plain_sql(STAR)}), v AS (SELECT 1 AS f, l_quantity AS value, y FROM b UNION ALL SELECT 2, o_totalprice, y FROM b)"
_CAND = _LONG + ", r AS (SELECT f, value, row_number() OVER (PARTITION BY f ORDER BY value) AS pos, count(*) OVER (PARTITION BY f) AS m FROM v), j AS (SELECT CAST(unnest(range(1, 20)) AS INT) AS j), cand AS (SELECT f, j, value AS cut FROM r JOIN j ON pos = CAST(ceil(j * m / 20.0) AS BIGINT))"


@query("bin_candidates", _CAND + " SELECT f, j, cut FROM cand")
def bin_candidates(spark, sf):
    return binning.quantile_candidates(frames.frame(spark, sf, STAR), BIN_F, "y", 20)


def _entropy(parts_: list[str]) -> str:
    total = "(" + " + ".join(parts_) + ")"
    return "(" + " + ".join(f"CASE WHEN {p} > 0 THEN -(CAST({p} AS DOUBLE) / {total}) * ln(CAST({p} AS DOUBLE) / {total}) ELSE 0 END" for p in parts_) + ")"


@query("bin_first_cut", _CAND + f""", d AS (SELECT DISTINCT f, cut FROM cand), c AS (SELECT d.f, d.cut, count(*) FILTER (WHERE y = '0' AND value <= cut) AS a0, count(*) FILTER (WHERE y = '1' AND value <= cut) AS a1, count(*) FILTER (WHERE y = '0' AND value > cut) AS b0, count(*) FILTER (WHERE y = '1' AND value > cut) AS b1 FROM d JOIN v USING (f) GROUP BY ALL),
g AS (SELECT f, cut, round({_entropy(['(a0 + b0)', '(a1 + b1)'])} - CAST(a0 + a1 AS DOUBLE) / (a0 + a1 + b0 + b1) * {_entropy(['a0', 'a1'])} - CAST(b0 + b1 AS DOUBLE) / (a0 + a1 + b0 + b1) * {_entropy(['b0', 'b1'])}, 9) AS gain FROM c WHERE b0 + b1 > 0)
SELECT f, cut, round(gain, 6) AS gain FROM (SELECT *, row_number() OVER (PARTITION BY f ORDER BY gain DESC, cut) AS r FROM g) z WHERE r = 1""")
def bin_first_cut(spark, sf):
    return binning.first_cut(frames.frame(spark, sf, STAR), BIN_F, "y", 20).select("f", "cut", F.round("gain", 6).alias("gain"))


def rounds_sql(select: str, column: str, classes: list[str], k: int, parts_: int = 20) -> str:
    """All rounds of the binner unrolled for one feature: after round i, CTE cut{i} has one row (cut, gain)."""
    c = [f"count(*) FILTER (WHERE y = '{x}')" for x in classes]
    text = f"WITH b AS ({frames.plain_sql(select)}), v AS (SELECT CAST({column} AS DOUBLE) AS value, y, 0 AS part FROM b WHERE {column} IS NOT NULL)"
    previous = "v"
    for i in range(1, k):
        old = ", ".join(f"{x} AS w{n}" for n, x in enumerate(c))
        sub = ", ".join(f"{x.replace('WHERE ', 'WHERE value <= cut AND ')} AS a{n}, {x.replace('WHERE ', 'WHERE value > cut AND ')} AS b{n}" for n, x in enumerate(c))
        wa, wb, ww = ([f"{s}{n}" for n in range(len(classes))] for s in "abw")
        size = lambda names: "(" + " + ".join(names) + ")"
        text += f""",
r{i} AS (SELECT part, value, row_number() OVER (PARTITION BY part ORDER BY value) AS pos, count(*) OVER (PARTITION BY part) AS m FROM {previous}),
c{i} AS (SELECT DISTINCT part, value AS cut FROM r{i} JOIN (SELECT CAST(unnest(range(1, {parts_})) AS BIGINT) AS j) ON pos = (j * m + {parts_ - 1}) // {parts_}),
p{i} AS (SELECT part, {old} FROM {previous} GROUP BY part), t{i} AS (SELECT {', '.join(f'sum(w{n}) AS n{n}' for n in range(len(classes)))}, sum({size(ww)} * {_entropy(ww)}) AS inside FROM p{i}),
e{i} AS (SELECT part, cut, {sub} FROM c{i} JOIN {previous} USING (part) GROUP BY part, cut),
g{i} AS (SELECT e.part, e.cut, round({_entropy([f'n{n}' for n in range(len(classes))])} - (inside - {size(ww)} * {_entropy(ww)} + {size(wa)} * {_entropy(wa)} + {size(wb)} * {_entropy(wb)}) / {size([f'n{n}' for n in range(len(classes))])}, 9) AS gain FROM e{i} e JOIN p{i} USING (part), t{i} WHERE {size(wb)} > 0),
cut{i} AS (SELECT {i} AS cut_no, part, cut, gain FROM g{i} ORDER BY gain DESC, cut LIMIT 1),
v{i} AS (SELECT value, y, CASE WHEN u.part = k.part AND value > k.cut THEN {i} ELSE u.part END AS part FROM {previous} u, cut{i} k)"""
        previous = f"v{i}"
    return text


_ROUNDS = rounds_sql(STAR, "l_quantity", ["0", "1"], 4)
_CUTS = " UNION ALL ".join(f"SELECT cut_no, cut, gain FROM cut{i}" for i in range(1, 4))


def _quantity_model(spark, sf, quantiles: str = "exact"):
    df = frames.frame(spark, sf, STAR)
    return df, binning.EntropyBinner(4, 20, ["l_quantity"], "y", quantiles).fit(df)


@query("bin_cuts_k4", f"{_ROUNDS} SELECT cut_no, cut, round(gain, 6) AS gain FROM ({_CUTS}) z")
def bin_cuts_k4(spark, sf):
    return _quantity_model(spark, sf)[1].table(spark).select("cut_no", "cut", F.round("gain", 6).alias("gain"))


_PRICE_ROUNDS = rounds_sql(STAR, "o_totalprice", ["0", "1"], 4)


@query("bin_cuts_sketch", f"{_PRICE_ROUNDS} SELECT cut_no, round(gain, 3) AS gain FROM ({_CUTS}) z")
def bin_cuts_sketch(spark, sf):
    """The gains of the cuts that 10,000 cells of a column of many values give; the SQL has those of the exact cuts."""
    df = frames.frame(spark, sf, f"SELECT o_totalprice, y FROM ({STAR}) s")
    model = binning.EntropyBinner(4, 20, ["o_totalprice"], "y", "approx").fit(df)
    return model.table(spark).select("cut_no", F.round("gain", 3).alias("gain"))


@query("bin_cuts_price", f"{_PRICE_ROUNDS} SELECT cut_no, cut, round(gain, 6) AS gain FROM ({_CUTS}) z")
def bin_cuts_price(spark, sf):
    """Exact cuts of the same column, by jobs over ranges of its values."""
    df = frames.frame(spark, sf, f"SELECT o_totalprice, y FROM ({STAR}) s")
    model = binning.EntropyBinner(4, 20, ["o_totalprice"], "y", in_task=1000).fit(df)
    return model.table(spark).select("cut_no", "cut", F.round("gain", 6).alias("gain"))


@query("bin_apply", f"{_ROUNDS}, k AS ({_CUTS}), e AS (SELECT row_number() OVER (ORDER BY cut) AS i, cut FROM k) SELECT concat('b', CAST(1 + (SELECT count(*) FROM e WHERE e.cut < v.value) AS VARCHAR)) AS l_quantity_bin, y, count(*) AS n FROM v GROUP BY 1, 2")
def bin_apply(spark, sf):
    df, model = _quantity_model(spark, sf)
    return model.transform(df).groupBy("l_quantity_bin", "y").agg(F.count(F.lit(1)).alias("n"))


@query("bin_gain_by_k", f"{_ROUNDS} SELECT cut_no + 1 AS k, round(gain, 6) AS gain FROM ({_CUTS}) z")
def bin_gain_by_k(spark, sf):
    _, model = _quantity_model(spark, sf)
    rows = [(k, model.truncate(k).cuts[1][-1][1]) for k in (2, 3, 4)]
    return spark.createDataFrame(rows, "k int, gain double").withColumn("gain", F.round("gain", 6))


@query("interval_band_join", f"""{_ROUNDS}, k AS ({_CUTS}), o AS (SELECT cut FROM k UNION ALL SELECT NULL), e AS (SELECT row_number() OVER (ORDER BY cut NULLS LAST) AS i, cut AS high, lag(cut) OVER (ORDER BY cut NULLS LAST) AS low FROM o)
SELECT CAST(i AS BIGINT) AS band, count(*) AS n FROM v JOIN e ON (low IS NULL OR value > low) AND (high IS NULL OR value <= high) GROUP BY 1""")
def interval_band_join(spark, sf):
    df, model = _quantity_model(spark, sf)
    cuts = sorted(c for c, _ in model.cuts[1])
    bands = spark.createDataFrame([(i + 1, low, high) for i, (low, high) in enumerate(zip([None, *cuts], [*cuts, None]))], "band long, low double, high double")
    met = df.join(F.broadcast(bands), (F.col("low").isNull() | (F.col("l_quantity") > F.col("low"))) & (F.col("high").isNull() | (F.col("l_quantity") <= F.col("high"))))  # a row an interval
    return met.groupBy("band").agg(F.count(F.lit(1)).alias("n"))


# --- mixed data --------------------------------------------------------------------------------------------------------


def _mixed(df: DataFrame, categorical, continuous, k: int, d_freq: int, d_conf: int):
    model = binning.EntropyBinner(k, 20, list(continuous), "y").fit(df)
    columns = [*categorical, *(f"{c}_bin" for c in continuous)]
    return model, columns, selectors.select_nonredundant(model.transform(df), "y", columns, d_freq, d_conf)


def first_cut_cte(select: str, continuous: list[str], classes: list[str], parts_: int = 20) -> str:
    """A SELECT of the frame with a two-interval column `<name>_bin` for each continuous feature; all features are cut at once, in the long form."""
    long = " UNION ALL ".join(f"SELECT {i} AS f, CAST({c} AS DOUBLE) AS value, y FROM src WHERE {c} IS NOT NULL" for i, c in enumerate(continuous, 1))
    low, high, all_ = ([f"{s}{n}" for n in range(len(classes))] for s in ("a", "b", "n"))
    size = lambda names: "(" + " + ".join(names) + ")"
    sides = ", ".join(f"count(*) FILTER (WHERE y = '{x}' AND value <= cut) AS a{n}, count(*) FILTER (WHERE y = '{x}' AND value > cut) AS b{n}, count(*) FILTER (WHERE y = '{x}') AS n{n}" for n, x in enumerate(classes))
    columns = ", ".join(f"CASE WHEN {c} <= c{i} OR (c{i} IS NULL AND {c} IS NOT NULL) THEN 'b1' WHEN {c} > c{i} THEN 'b2' END AS {c}_bin" for i, c in enumerate(continuous, 1))
    cuts = ", ".join(f"max(cut) FILTER (WHERE f = {i}) AS c{i}" for i in range(1, len(continuous) + 1))
    return f"""WITH src AS MATERIALIZED ({frames.plain_sql(select)}), v AS MATERIALIZED ({long}), r AS (SELECT f, value, row_number() OVER (PARTITION BY f ORDER BY value) AS pos, count(*) OVER (PARTITION BY f) AS m FROM v),
cand AS MATERIALIZED (SELECT DISTINCT f, value AS cut FROM r JOIN (SELECT CAST(unnest(range(1, {parts_})) AS BIGINT) AS j) ON pos = (j * m + {parts_ - 1}) // {parts_}),
e AS (SELECT f, cut, {sides} FROM cand JOIN v USING (f) GROUP BY f, cut),
g AS (SELECT f, cut, round({_entropy(all_)} - ({size(low)} * {_entropy(low)} + {size(high)} * {_entropy(high)}) / {size(all_)}, 9) AS gain FROM e WHERE {size(high)} > 0),
best AS (SELECT f, cut FROM (SELECT *, row_number() OVER (PARTITION BY f ORDER BY gain DESC, cut) AS r FROM g) z WHERE r = 1), cuts AS MATERIALIZED (SELECT {cuts} FROM best)
SELECT src.*, {columns} FROM src, cuts"""


TEXT_Y = f"SELECT doc_id, {', '.join(frames.TEXT_CATEGORICAL)}, {', '.join(frames.TEXT_CONTINUOUS)}, quality AS y FROM ({frames.TEXTS}) t"
TEXT_COLUMNS = [*frames.TEXT_CATEGORICAL, *(f"{c}_bin" for c in frames.TEXT_CONTINUOUS)]


@query("mixed_rules_documents", q.rules_sql(first_cut_cte(TEXT_Y, frames.TEXT_CONTINUOUS, ["0", "1"]), TEXT_COLUMNS, 30, 15, True, "rconf", "strict"))
def mixed_rules_documents(spark, sf):
    return rules_out(_mixed(frames.frame(spark, sf, TEXT_Y), frames.TEXT_CATEGORICAL, frames.TEXT_CONTINUOUS, 2, 30, 15)[2].rules)


NARROW_STAR = f"SELECT {', '.join([*frames.STAR_CATEGORICAL, *frames.STAR_CONTINUOUS])}, y FROM ({STAR}) s"
STAR_COLUMNS = [*frames.STAR_CATEGORICAL, *(f"{c}_bin" for c in frames.STAR_CONTINUOUS)]


@query("star_rules", q.rules_sql(first_cut_cte(NARROW_STAR, frames.STAR_CONTINUOUS, ["0", "1"]), STAR_COLUMNS, 30, 15, True, "rconf", "strict"))
def star_rules(spark, sf):
    df = materialise(frames.frame(spark, sf, NARROW_STAR), "star")
    return rules_out(_mixed(df, frames.STAR_CATEGORICAL, frames.STAR_CONTINUOUS, 2, 30, 15)[2].rules)


ORDER_COLUMNS = [*frames.ORDER_CATEGORICAL, *(f"{c}_bin" for c in frames.ORDER_CONTINUOUS)]


@query("order_rules", q.rules_sql(first_cut_cte(frames.ORDERS, frames.ORDER_CONTINUOUS, ["0", "1"]), ORDER_COLUMNS, 40, 20, True, "rconf", "strict"))
def order_rules(spark, sf):
    df = materialise(frames.frame(spark, sf, frames.ORDERS), "orders")
    return rules_out(_mixed(df, frames.ORDER_CATEGORICAL, frames.ORDER_CONTINUOUS, 2, 40, 20)[2].rules)


SERIES, SERIES_F = frames.series_sql(), frames.series_features()
_CLASSES = ["high", "low", "proper"]


@query("mixed_rules_events", q.rules_sql(first_cut_cte(SERIES, SERIES_F, _CLASSES), [f"{c}_bin" for c in SERIES_F], 150, 25, True, "rconf", "strict"))
def mixed_rules_events(spark, sf):
    return rules_out(_mixed(materialise(frames.series(spark, sf), "series"), [], SERIES_F, 2, 150, 25)[2].rules)


CUSTOMERS, CUSTOMER_F = frames.CUSTOMERS, frames.CUSTOMER_FEATURES
_QUINTILES = f"SELECT *, CAST(ntile(5) OVER (ORDER BY response, c_custkey) AS VARCHAR(8)) AS y FROM ({CUSTOMERS}) c"


@query("target_quintiles", f"SELECT c_custkey, CAST(y AS INT) AS y FROM ({frames.plain_sql(_QUINTILES)}) z")
def target_quintiles(spark, sf):
    return binning.quantile_classes(frames.frame(spark, sf, CUSTOMERS), "response", 5, "c_custkey").select("c_custkey", "y")


_CUSTOMER_CHAIN = q.features_cte(first_cut_cte(_QUINTILES, CUSTOMER_F, list("12345")), [f"{c}_bin" for c in CUSTOMER_F], 100, 20, True, "rconf", "strict")


def _customer_pairs(spark, sf):
    df = materialise(binning.quantile_classes(frames.frame(spark, sf, CUSTOMERS), "response", 5, "c_custkey").withColumn("y", F.col("y").cast("string")), "customers")
    return df, product_pairs(_mixed(df, [], CUSTOMER_F, 2, 100, 20)[2].features)


@query("product_pairs_customer", _CUSTOMER_CHAIN + " SELECT DISTINCT f1, f2 FROM feats WHERE size = 2")
def product_pairs_customer(spark, sf):
    return _customer_pairs(spark, sf)[1]


_CUSTOMER_LONG = " UNION ALL ".join(f"SELECT c_custkey, {i} AS f, '{c}' AS name, {c} AS x FROM base" for i, c in enumerate(CUSTOMER_F, 1))


@query("attach_products", _CUSTOMER_CHAIN + f", xs AS ({_CUSTOMER_LONG}) SELECT a.c_custkey, concat(a.name, '_x_', b.name) AS pair, round(a.x * b.x, 0) AS product FROM (SELECT DISTINCT f1, f2 FROM feats WHERE size = 2) s JOIN xs a ON a.f = f1 JOIN xs b ON b.f = f2 AND b.c_custkey = a.c_custkey")
def attach_products(spark, sf):
    df, pairs = _customer_pairs(spark, sf)
    chosen = sorted((r["f1"], r["f2"]) for r in pairs.collect())
    names = [f"{CUSTOMER_F[a - 1]}_x_{CUSTOMER_F[b - 1]}" for a, b in chosen]
    wide = attach.products(df, chosen, CUSTOMER_F).select("c_custkey", *names)
    return wide.unpivot(["c_custkey"], names, "pair", "product").select("c_custkey", "pair", F.round("product", 0).alias("product"))


# --- parameters, measures ----------------------------------------------------------------------------------------------

#: Frames by their number of features; the number of classes is the data's.
_SHAPES = ((len(frames.STAR_CATEGORICAL + frames.STAR_CONTINUOUS), STAR), (len(frames.ORDER_CONTINUOUS), frames.ORDERS), (len(frames.ORDER_CATEGORICAL + frames.ORDER_CONTINUOUS), frames.ORDERS), (len(PARTS_F), PARTS))
_CLASSES_OF = " UNION ALL ".join(f"SELECT {p} AS p, CAST(count(DISTINCT y) AS INT) AS c FROM ({frames.plain_sql(select)}) s{i}" for i, (p, select) in enumerate(_SHAPES))


@query("parameter_rules", f"SELECT p, c AS n_classes, CAST(5 * c * floor(sqrt(p)) AS INT) AS d_freq, CAST(5 * floor(sqrt(p)) AS INT) AS d_conf FROM ({_CLASSES_OF}) s")
def parameter_rules(spark, sf):
    """Budgets that the shapes of four sets of features give."""
    classes = {select: frames.frame(spark, sf, select).agg(F.count_distinct("y")).first()[0] for select in dict.fromkeys(s for _, s in _SHAPES)}
    rows = [(p, classes[select], b.d_freq, b.d_conf) for p, select in _SHAPES for b in [params.suggest(p, classes[select])]]
    return spark.createDataFrame(rows, "p int, n_classes int, d_freq int, d_conf int")


@query("class_distribution", f"SELECT split, y, count(*) AS n FROM ({frames.plain_sql(SERIES)}) s GROUP BY 1, 2")
def class_distribution(spark, sf):
    return evaluate.class_distribution(frames.series(spark, sf), "y", "split")


def _vote_sql(fold: int) -> str:
    """CTE pred(p_partkey, truth, prediction, conf) of a fold, by the rules of the others."""
    train = f"SELECT * FROM ({PARTS}) p WHERE p_partkey % 5 <> {fold}"
    return q.mined(train, PARTS_F, 40, True) + q.beaten() + f""", rr AS ({q.ranked('kept', 'rconf', 10)}), ro AS (SELECT *, row_number() OVER (ORDER BY conf DESC, {q.ORDER}) AS place FROM rr),
test AS (SELECT * FROM ({frames.plain_sql(PARTS)}) p WHERE p_partkey % 5 = {fold}), ti AS ({' UNION ALL '.join(f"SELECT p_partkey, {i} AS f, {c} AS v FROM test" for i, c in enumerate(PARTS_F, 1))}),
hit AS (SELECT a.p_partkey, r.y, r.conf, r.place FROM ro r JOIN ti a ON a.f = r.f1 AND a.v = r.v1 LEFT JOIN ti b ON b.p_partkey = a.p_partkey AND b.f = r.f2 AND b.v = r.v2 WHERE r.f2 IS NULL OR b.v IS NOT NULL),
pred AS (SELECT t.p_partkey, t.y AS truth, coalesce(arg_min(h.y, h.place), (SELECT y FROM lab ORDER BY supp_y DESC, y LIMIT 1)) AS prediction, arg_min(h.conf, h.place) AS conf FROM test t LEFT JOIN hit h USING (p_partkey) GROUP BY ALL)"""


_VOTE = _vote_sql(0)


def _votes(spark, sf, fold: int = 0) -> DataFrame:
    df = parts(spark, sf)
    train, test = df.where(F.col("p_partkey") % 5 != fold), df.where(F.col("p_partkey") % 5 == fold)
    rules = selectors.select_nonredundant(train, "y", PARTS_F, 40, 10).rules
    default = counts.labels(train, "y").orderBy(F.col("supp_y").desc(), "y").first()["y"]
    votes = rule_ops.vote(test, materialise(rules, "rules"), PARTS_F, default, "p_partkey")
    return test.select(F.col("p_partkey").alias("key"), F.col("y").alias("truth")).join(votes, "key")


_FOLDS = " UNION ALL ".join(f"SELECT {f} AS fold, error FROM ({_vote_sql(f)} SELECT avg(CASE WHEN truth = prediction THEN 0.0 ELSE 1.0 END) AS error FROM pred) f{f}" for f in range(5))


@query("vote_error_by_fold", f"SELECT count(*) AS runs, round(avg(error), 6) AS mean, round(stddev_samp(error), 6) AS deviation, round(stddev_samp(error) / sqrt(count(*)), 6) AS std_error FROM ({_FOLDS}) f")
def vote_error_by_fold(spark, sf):
    out = None
    for fold in range(5):
        one = _votes(spark, sf, fold).agg(evaluate.error_rate("truth", "prediction").alias("score")).select(F.lit("vote").alias("method"), "score")
        out = one if out is None else out.unionByName(one)
    done = evaluate.summarise(out, ["method"])
    return done.select("runs", *[F.round(c, 6).alias(c) for c in ("mean", "deviation", "std_error")])


@query("rule_support", q.mined(PARTS, PARTS_F, 40, True) + q.beaten() + f", rr AS ({q.ranked('kept', 'rconf', 10)}) SELECT CAST(rank AS BIGINT) AS rank, supp, round(CAST(supp AS DOUBLE) / n, 6) AS support FROM rr")
def rule_support(spark, sf):
    rules = selectors.select_nonredundant(parts(spark, sf), "y", PARTS_F, 40, 10).rules
    return rules.select(F.col("rank").cast("long").alias("rank"), "supp", F.round(F.col("supp").cast("double") / F.col("n"), 6).alias("support"))


@query("rule_vote_confusion", _VOTE + " SELECT truth, prediction, count(*) AS n FROM pred GROUP BY 1, 2")
def rule_vote_confusion(spark, sf):
    return evaluate.confusion(_votes(spark, sf), "truth", "prediction")


@query("rule_vote_accuracy", _VOTE + " SELECT round(avg(CASE WHEN truth = prediction THEN 1.0 ELSE 0.0 END), 6) AS accuracy, round(1 - avg(CASE WHEN truth = prediction THEN 1.0 ELSE 0.0 END), 6) AS error_rate FROM pred")
def rule_vote_accuracy(spark, sf):
    return _votes(spark, sf).agg(F.round(evaluate.accuracy("truth", "prediction"), 6).alias("accuracy"), F.round(evaluate.error_rate("truth", "prediction"), 6).alias("error_rate"))


_P_TRUE = "greatest(least(CASE WHEN truth = prediction THEN coalesce(conf, 0.5) ELSE (1 - coalesce(conf, 0.5)) / 3 END, 1 - 1e-15), 1e-15)"


@query("rule_vote_logloss", _VOTE + f" SELECT round(avg(-ln({_P_TRUE})), 6) AS log_loss FROM pred")
def rule_vote_logloss(spark, sf):
    sure = F.coalesce("conf", F.lit(0.5))
    p = F.when(F.col("truth") == F.col("prediction"), sure).otherwise((1 - sure) / 3)
    return _votes(spark, sf).agg(F.round(evaluate.log_loss(p), 6).alias("log_loss"))


@query("auc_rank", "SELECT round((sum(r) FILTER (WHERE quality = 1) - count(*) FILTER (WHERE quality = 1) * (count(*) FILTER (WHERE quality = 1) + 1) / 2.0) / (CAST(count(*) FILTER (WHERE quality = 1) AS DOUBLE) * count(*) FILTER (WHERE quality = 0)), 6) AS auc FROM (SELECT quality, rank() OVER (ORDER BY n_chars) + (count(*) OVER (PARTITION BY n_chars) - 1) / 2.0 AS r FROM documents JOIN labels USING (doc_id)) z")
def auc_rank(spark, sf):
    df = spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "n_chars").join(spark.read.parquet(f"{sf}/labels.parquet"), "doc_id")
    return evaluate.auc(df, "quality", "n_chars").select(F.round("auc", 6).alias("auc"))


@query("auc_hard", "SELECT round((avg(CASE WHEN quality = 1 THEN CASE WHEN n_chars > 500 THEN 1.0 ELSE 0.0 END END) + avg(CASE WHEN quality = 0 THEN CASE WHEN n_chars <= 500 THEN 1.0 ELSE 0.0 END END)) / 2, 6) AS auc FROM documents JOIN labels USING (doc_id)")
def auc_hard(spark, sf):
    df = spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "n_chars").join(spark.read.parquet(f"{sf}/labels.parquet"), "doc_id")
    return evaluate.auc_hard(df.withColumn("hard", (F.col("n_chars") > 500).cast("int")), "quality", "hard").select(F.round("auc", 6).alias("auc"))


@query("mse_base", f"WITH c AS ({frames.plain_sql(CUSTOMERS)}), m AS (SELECT regr_slope(response, mean_price) AS a, regr_intercept(response, mean_price) AS b FROM c WHERE c_custkey % 3 <> 0) SELECT round(avg(power(response - a * mean_price - b, 2)), 4) AS mse FROM c, m WHERE c_custkey % 3 = 0")
def mse_base(spark, sf):
    """Error on the last third of a line through one column that the others gave."""
    df = frames.frame(spark, sf, f"SELECT c_custkey, mean_price, response FROM ({CUSTOMERS}) c")
    line = df.where("c_custkey % 3 <> 0").agg(F.regr_slope("response", "mean_price").alias("a"), F.regr_intercept("response", "mean_price").alias("b")).first()
    test = df.where("c_custkey % 3 = 0").withColumn("guess", F.lit(line["a"]) * F.col("mean_price") + F.lit(line["b"]))
    return test.agg(F.round(evaluate.mse("response", "guess"), 4).alias("mse"))


_SCORED = "SELECT l_linenumber AS k, CAST(FLOOR(l_quantity / 5) * 5 AS INT) AS d_conf, CAST(SUM(CAST(ROUND(l_discount * 100) AS BIGINT)) AS DOUBLE) / COUNT(*) / 100 AS score FROM {lineitem} GROUP BY 1, 2"
_NEAR = f"""WITH g AS ({frames.plain_sql(_SCORED)}), p AS (SELECT *, dense_rank() OVER (ORDER BY k) AS i, dense_rank() OVER (ORDER BY d_conf) AS j FROM g),
n AS (SELECT a.k, a.d_conf, a.score AS own, b.score, exp(-(power(a.i - b.i, 2) + power(a.j - b.j, 2)) / 2) AS w FROM p a JOIN p b ON abs(a.i - b.i) <= 2 AND abs(a.j - b.j) <= 2)"""
for _kind, _value in (("gaussian", "sum(w * score) / sum(w)"), ("box", "avg(score)"), ("median", "median(score)"), ("bilateral", "sum(w * exp(-power(own - score, 2) / 0.02) * score) / sum(w * exp(-power(own - score, 2) / 0.02))")):
    query("grid_smooth" + ("" if _kind == "gaussian" else f"_{_kind}"), f"{_NEAR} SELECT k, d_conf, round({_value}, 6) AS smoothed FROM n GROUP BY 1, 2")(
        lambda spark, sf, kind=_kind: tuning.smooth(frames.frame(spark, sf, _SCORED), kind).select("k", "d_conf", F.round("smoothed", 6).alias("smoothed"))
    )


@query("marginal_screen", f"WITH base AS MATERIALIZED ({frames.plain_sql(CUSTOMERS)}), xs AS MATERIALIZED ({_CUSTOMER_LONG}), s AS (SELECT a.f AS f1, b.f AS f2, abs(corr(a.x * b.x, base.response)) AS strength FROM xs a JOIN xs b ON a.c_custkey = b.c_custkey AND a.f < b.f JOIN base ON base.c_custkey = a.c_custkey GROUP BY 1, 2) SELECT f1, f2, round(strength, 6) AS strength FROM s WHERE NOT isnan(strength) ORDER BY round(strength, 7) DESC, f1, f2 LIMIT 20")
def marginal_screen(spark, sf):
    found = baselines.marginal_screen(frames.frame(spark, sf, CUSTOMERS), CUSTOMER_F, "response", 20)
    return found.select("f1", "f2", F.round("strength", 6).alias("strength"))


_SCREEN = q.mined(PARTS, PARTS_F, 40, True) + f", rr AS ({q.ranked('scored', 'rconf', 10)}), mains AS (SELECT DISTINCT f1 AS f FROM rr WHERE size = 1), prs AS (SELECT f1, f2, count(*) AS n FROM scored WHERE size = 2 GROUP BY 1, 2)"


@query("hierarchy_screen", f"{_SCREEN} SELECT 'strong' AS mode, count(*) AS pairs, CAST(coalesce(sum(n), 0) AS BIGINT) AS sets FROM prs WHERE f1 IN (SELECT f FROM mains) AND f2 IN (SELECT f FROM mains) UNION ALL SELECT 'weak', count(*), CAST(coalesce(sum(n), 0) AS BIGINT) FROM prs WHERE f1 IN (SELECT f FROM mains) OR f2 IN (SELECT f FROM mains)")
def hierarchy_screen(spark, sf):
    mined = selectors.mine(parts(spark, sf), "y", PARTS_F, 40, True)
    mains = rule_ops.top_rules(with_measures(mined.sets), 10, "rconf").where("size = 1").select(F.col("f1").alias("f"))
    pairs = mined.sets.where("size = 2").groupBy("f1", "f2").agg(F.count(F.lit(1)).alias("n"))
    out = None
    for mode in ("strong", "weak"):
        one = baselines.hierarchy_screen(pairs, mains, mode).agg(F.count(F.lit(1)).alias("pairs"), F.coalesce(F.sum("n"), F.lit(0)).alias("sets")).select(F.lit(mode).alias("mode"), "*")
        out = one if out is None else out.unionByName(one)
    return out


@query("step_costs")
def step_costs(spark, sf):
    df = frames.frame(spark, sf, frames.planted(20))
    xs = [f"x{i}" for i in range(1, 21)]
    seen = complexity.observe(df, "y", xs, 45, 5)
    expected = spark.createDataFrame([(s, float(o), float(h)) for s, o, h in complexity.predict(df.count(), 20, 3, 45, 5)], "step string, predicted double, predicted_held double")
    return seen.join(expected, "step")


# --- time and streams --------------------------------------------------------------------------------------------------


@query("asof_previous_label", "SELECT event_id, coalesce(last_value(CASE WHEN event_type = 'error' THEN event_id END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), -1) AS last_error FROM events")
def asof_previous_label(spark, sf):
    w = W.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(W.unboundedPreceding, -1)
    marked = spark.read.parquet(f"{sf}/events.parquet").select("event_id", "user_id", "ts", F.when(F.col("event_type") == "error", F.col("event_id")).alias("e"))
    return marked.select("event_id", F.coalesce(F.last("e", ignorenulls=True).over(w), F.lit(-1)).alias("last_error"))


@query("stream_item_counts", "SELECT f, v, y, count(*) AS supp FROM (SELECT 1 AS f, CASE WHEN value < 50 THEN 'small' ELSE 'large' END AS v, event_type AS y FROM events UNION ALL SELECT 2, CAST(user_id % 10 AS VARCHAR), event_type FROM events) z GROUP BY 1, 2, 3")
def stream_item_counts(spark, sf):
    stream = running.read_events(spark, running.stage_events(spark, sf, late_every=100))
    shaped = stream.select(F.when(F.col("value") < 50, "small").otherwise("large").alias("size"), (F.col("user_id") % 10).alias("group"), "event_type")
    return running.run_to_end(running.item_counts(shaped, ["size", "group"], "event_type"), "stream-items")


@query("stream_window_counts", "SELECT strftime(time_bucket(INTERVAL '1 day', ts), '%Y-%m-%d') AS day, event_type AS y, count(*) AS supp FROM events GROUP BY 1, 2")
def stream_window_counts(spark, sf):
    stream = running.read_events(spark, running.stage_events(spark, sf, late_every=100))
    done = running.run_to_end(running.window_counts(stream, "event_type"), "stream-windows")
    return done.select(F.date_format("start", "yyyy-MM-dd").alias("day"), "y", "supp")


@query("stream_session_counts", """WITH g AS (SELECT user_id, ts, CASE WHEN ts < lag(ts) OVER w + INTERVAL '30 minutes' THEN 0 ELSE 1 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)),
s AS (SELECT user_id, ts, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS sess FROM g) SELECT user_id, supp, count(*) AS sessions FROM (SELECT user_id, sess, count(*) AS supp FROM s GROUP BY 1, 2) z GROUP BY 1, 2""")
def stream_session_counts(spark, sf):
    stream = running.read_events(spark, running.stage_events(spark, sf))
    done = running.run_to_end(running.session_counts(stream, watermark="60 days"), "stream-sessions", "complete")
    return done.groupBy("user_id", "supp").agg(F.count(F.lit(1)).alias("sessions"))


@query("stream_last_label", "SELECT event_id, coalesce(lag(event_type) OVER (PARTITION BY user_id ORDER BY ts, event_id), '') AS previous, event_type AS now FROM events")
def stream_last_label(spark, sf):
    stream = running.read_events(spark, running.stage_events(spark, sf))
    return running.run_to_end(running.last_label_per_user(stream), "stream-last", "append").select("event_id", F.coalesce("previous", F.lit("")).alias("previous"), "now")


# --- learners ----------------------------------------------------------------------------------------------------------


def _sets(spark, sf, fold: int = 0):
    df = parts(spark, sf).withColumn("label", F.col("y").cast("double"))
    train, test = materialise(df.where(F.col("p_partkey") % 5 != fold), "train"), materialise(df.where(F.col("p_partkey") % 5 == fold), "test")
    rows = sorted(selectors.select_nonredundant(train, "y", PARTS_F, 40, 10).features.collect(), key=lambda r: r["feature_id"])
    return train, test, rows


def _score_rows(spark, sf, learner: str, fit, modes) -> DataFrame:
    train, test, rows = _sets(spark, sf)
    known, out = attach.codes(train, PARTS_F), []
    for mode in modes:
        model = fit(attach.assemble(train, mode, rows, PARTS_F, (), known))
        for metric, value in learners.scores(model.transform(attach.assemble(test, mode, rows, PARTS_F, (), known))).items():
            out.append((mode, learner, metric, float(value)))
    return spark.createDataFrame(out, "method string, learner string, metric string, value double")


@query("lr_scores")
def lr_scores(spark, sf):
    return _score_rows(spark, sf, "logistic", lambda d: learners.logistic(d.count()).fit(d), ("original", "rules", "label_plus_rules", "onehot", "onehot_plus_interactions"))


@query("mlp_scores")
def mlp_scores(spark, sf):
    return _score_rows(spark, sf, "perceptron", lambda d: learners.EarlyStoppingPerceptron(bursts=3).fit(d), ("original", "label_plus_rules"))


@query("forest_scores")
def forest_scores(spark, sf):
    return _score_rows(spark, sf, "forest", lambda d: learners.forest(trees=20).fit(d), ("original", "rules"))


@query("cv_summary")
def cv_summary(spark, sf):
    out = []
    for fold in range(5):
        train, test, rows = _sets(spark, sf, fold)
        known = attach.codes(train, PARTS_F)
        for mode in ("original", "onehot_plus_interactions"):
            model = learners.logistic(train.count()).fit(attach.assemble(train, mode, rows, PARTS_F, (), known))
            got = learners.scores(model.transform(attach.assemble(test, mode, rows, PARTS_F, (), known)))
            out += [(mode, "logistic", metric, fold, float(v)) for metric, v in got.items()]
    rows = spark.createDataFrame(out, "method string, learner string, metric string, fold int, score double")
    return evaluate.summarise(rows, ["method", "learner", "metric"]).select("method", "learner", "metric", "mean", "std_error", "runs")
