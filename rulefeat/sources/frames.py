"""Frames over the given tables: one portable SELECT each, read by Spark with table arguments and by any other engine with views.

Planted labels are arithmetic on table columns, so every engine builds the same ones.
"""

from __future__ import annotations

import re

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..storage import ship_package

MODULI = (1009, 1013, 1019, 1021, 1031, 1033, 1039, 1049)


def terms(i: int) -> tuple[int, int, int, int, int]:
    """The i-th random bit of a line item: factors of its order, part and supplier key, what is added to their sum, and the modulus of which the remainder is odd or even."""
    return 2 * i + 7919, 4 * i + 104729, 6 * i + 1299709, i, MODULI[(i - 4) % len(MODULI)]


def bit(i: int) -> str:
    """The i-th random bit of a line item."""
    a, b, c, d, m = terms(i)
    return f"((CAST(l_orderkey AS BIGINT)*{a} + CAST(l_partkey AS BIGINT)*{b} + CAST(l_suppkey AS BIGINT)*{c} + {d}) % {m}) % 2"


def _s(expression: str, name: str) -> str:
    return f"CAST({expression} AS VARCHAR(64)) AS {name}"


_RED = "CASE WHEN l_returnflag = 'R' THEN 1 ELSE 0 END"
_OPEN = "CASE WHEN l_linestatus = 'O' THEN 1 ELSE 0 END"
_MANY = "CASE WHEN l_quantity > 25 THEN 1 ELSE 0 END"


def _label_and_trial(trials: int) -> str:
    return f"""  CAST(CASE WHEN (CAST(l_orderkey AS BIGINT)*7919 + CAST(l_linenumber AS BIGINT)*104729) % 100 < 5 THEN (CAST(l_orderkey AS BIGINT)*31 + CAST(l_linenumber AS BIGINT)*17) % 3
       WHEN l_returnflag <> 'R' THEN 0 WHEN l_linestatus = 'O' AND l_quantity > 25 THEN 2 ELSE 1 END AS VARCHAR(8)) AS y,
  CAST((CAST(l_orderkey AS BIGINT)*131 + CAST(l_linenumber AS BIGINT)*31 + CAST(l_partkey AS BIGINT)*17) % {trials} AS INT) AS trial
FROM {{lineitem}}"""


def planted(p: int = 99, constant: bool = False, trials: int = 60, used: int | None = None) -> str:
    """Binary features x1..xp of line items with a three-class label and a trial number; constant: the last two features are always 1."""
    bits = [f"CAST({bit(i)} AS INT)" for i in range(4, p + 1)]
    if constant:
        bits[-2:] = ["1", "1"]
    xs = [_RED, _OPEN, _MANY, *bits]
    columns = ", ".join(_s(x, f"x{i}") for i, x in enumerate(xs, 1))
    where = f" WHERE trial < {used}" if used is not None else ""
    return f"SELECT * FROM (SELECT {columns},\n{_label_and_trial(trials)}) t{where}"


def planted_bits(spark: SparkSession, sf_dir: str, p: int, constant: bool, draw, used: int | None = None, trials: int = 60):
    """planted() as Bits with the trial as part; draw(columns...) of a line item's key. The random bits come from the keys' remainders, by the same terms as in the SELECT."""
    from ..operators import bits

    select = f"SELECT {_RED} AS x1, {_OPEN} AS x2, {_MANY} AS x3, l_orderkey, l_partkey, l_suppkey, l_linenumber,\n{_label_and_trial(trials)}"
    rows = frame(spark, sf_dir, select).withColumn("draw", draw("l_orderkey", "l_linenumber"))
    rows = rows if used is None else rows.where(F.col("trial") < used)
    drawn = range(4, p - 1 if constant else p + 1)
    by_modulus = {m: [i for i in drawn if terms(i)[4] == m] for m in MODULI}

    def read(batch) -> np.ndarray:
        out = np.ones((p, batch.num_rows), np.int8)
        for i in range(3):
            out[i] = batch.column(3 + i).to_numpy()
        keys = [batch.column(6 + i).fill_null(0).to_numpy().astype(np.int64) for i in range(3)]
        if min(k.min() for k in keys) < 0:
            raise ValueError("a key below zero")
        for m, own in by_modulus.items():
            rest = [(k % m).astype(np.int32) for k in keys]
            for i in own:
                *factors, more, _ = terms(i)
                out[i - 1] = (sum(r * np.int32(f % m) for r, f in zip(rest, factors)) + np.int32(more)) % np.int32(m) & 1
        unknown = [batch.column(6 + i).is_null().to_numpy(zero_copy_only=False) for i in range(3) if batch.column(6 + i).null_count]
        if unknown:
            out[3 : drawn.stop - 1, np.logical_or.reduce(unknown)] = -1
        return out.T

    return bits.pack(rows, "trial", "draw", "y", p, ["0", "1", "2"], ["x1", "x2", "x3", "l_orderkey", "l_partkey", "l_suppkey"], read)


def frequency_bits() -> str:
    """Ten binary features of line items with given frequencies and one label, and the row's key."""
    h = "((CAST(l_orderkey AS BIGINT)*7919 + CAST(l_partkey AS BIGINT)*31 + CAST(l_suppkey AS BIGINT)*17) % 1009)"
    xs = [
        "CASE WHEN l_quantity > 5 THEN 1 ELSE 0 END",
        f"CASE WHEN l_quantity > 5 THEN CASE WHEN {h} % 6 < 5 THEN 1 ELSE 0 END ELSE CAST({h} % 2 AS INT) END",
        "CASE WHEN (CAST(l_orderkey AS BIGINT)*131 + CAST(l_partkey AS BIGINT)*7 + CAST(l_suppkey AS BIGINT)*3) % 1013 % 10 < 7 THEN 1 ELSE 0 END",
        *[f"CAST({bit(i)} AS INT)" for i in range(4, 11)],
    ]
    return f"SELECT {', '.join(_s(x, f'x{i}') for i, x in enumerate(xs, 1))}, 'all' AS y, l_orderkey, l_linenumber, l_partkey, l_suppkey FROM {{lineitem}}"


#: Frames by name, with their features in order, label and key.
STAR = f"""SELECT l_returnflag, l_linestatus, o_orderpriority, o_orderstatus, c_mktsegment, p_type, r_name, {_s('EXTRACT(MONTH FROM l_shipdate)', 'ship_month')},
  CAST(l_quantity AS DOUBLE) AS l_quantity, CAST(l_extendedprice AS DOUBLE) AS l_extendedprice, CAST(l_discount AS DOUBLE) AS l_discount, CAST(l_tax AS DOUBLE) AS l_tax, CAST(o_totalprice AS DOUBLE) AS o_totalprice, CAST(c_acctbal AS DOUBLE) AS c_acctbal,
  l_orderkey, l_linenumber, l_partkey, l_suppkey,
  CAST(CASE WHEN (CAST(l_orderkey AS BIGINT)*7919 + CAST(l_partkey AS BIGINT)*104729 + CAST(l_suppkey AS BIGINT)*1299709) % 100 < 8 THEN l_suppkey % 2
       WHEN (o_totalprice > 250000 AND c_mktsegment IN ('BUILDING', 'MACHINERY', 'AUTOMOBILE') AND l_linestatus = 'O') OR (l_returnflag = 'R' AND (o_orderpriority LIKE '1%' OR o_orderpriority LIKE '2%')) THEN 1 ELSE 0 END AS VARCHAR(8)) AS y
FROM {{lineitem}} JOIN {{orders}} ON l_orderkey = o_orderkey JOIN {{customer}} ON o_custkey = c_custkey JOIN {{part}} ON l_partkey = p_partkey
JOIN {{supplier}} ON l_suppkey = s_suppkey JOIN {{nation}} ON c_nationkey = n_nationkey JOIN {{region}} ON n_regionkey = r_regionkey"""
STAR_CATEGORICAL = ["l_returnflag", "l_linestatus", "o_orderpriority", "o_orderstatus", "c_mktsegment", "p_type", "r_name", "ship_month"]
STAR_CONTINUOUS = ["l_quantity", "l_extendedprice", "l_discount", "l_tax", "o_totalprice", "c_acctbal"]

PARTS = """SELECT p_partkey, p_brand, p_type, CASE WHEN p_size <= 10 THEN 's1' WHEN p_size <= 20 THEN 's2' WHEN p_size <= 30 THEN 's3' WHEN p_size <= 40 THEN 's4' ELSE 's5' END AS size_band,
  split_part(p_name, ' ', 1) AS adjective, split_part(p_name, ' ', 2) AS noun, CONCAT('r', CAST(LEAST(3, CAST(FLOOR((p_retailprice - 900) / 25) AS INT)) AS VARCHAR(8))) AS retail_band,
  CAST(CASE WHEN CAST(p_partkey AS BIGINT)*7919 % 100 < 3 THEN p_partkey % 4 WHEN p_type IN ('ECONOMY', 'SMALL', 'PROMO') OR p_size <= 10 THEN 0
       WHEN p_size > 40 AND p_type = 'LARGE' THEN 3 WHEN p_size > 40 THEN 2 ELSE 1 END AS VARCHAR(8)) AS y
FROM {part}"""
PARTS_FEATURES = ["p_brand", "p_type", "size_band", "adjective", "noun", "retail_band"]

TEXTS = """SELECT d.doc_id, d.lang, d.source, CASE WHEN d.text LIKE CONCAT('%', chr(10), '%') THEN 'yes' ELSE 'no' END AS has_newline, CASE WHEN d.text LIKE '%@%' THEN 'yes' ELSE 'no' END AS has_at,
  CASE WHEN regexp_replace(d.text, '[0-9][0-9][0-9]', '') <> d.text THEN 'yes' ELSE 'no' END AS has_digits, CASE WHEN lower(d.text) LIKE '%licen%' THEN 'yes' ELSE 'no' END AS has_license,
  CASE WHEN length(d.text) - length(replace(d.text, chr(10), '')) >= 10 THEN 'yes' ELSE 'no' END AS many_lines,
  CAST(d.n_chars AS DOUBLE) AS n_chars, CAST(length(d.text) - length(replace(d.text, ' ', '')) + 1 AS DOUBLE) AS words,
  CAST(length(d.text) - length(replace(d.text, chr(10), '')) + 1 AS DOUBLE) AS lines,
  CAST(l.quality AS VARCHAR(8)) AS quality, CAST(l.toxic AS VARCHAR(8)) AS toxic
FROM {documents} d JOIN {labels} l ON d.doc_id = l.doc_id"""
TEXT_CATEGORICAL = ["lang", "source", "has_newline", "has_at", "has_digits", "has_license", "many_lines"]
TEXT_CONTINUOUS = ["n_chars", "words", "lines"]


#: Lags, lags of the same user, and windows of the two frames over time: 27 and 86 features.
NARROW, BROAD = (10, 5, (5, 20)), (40, 22, (5, 10, 20, 40, 80))
LOW, HIGH = 15.34, 172.89


def series_features(lags: int = 10, user_lags: int = 5, windows: tuple[int, ...] = (5, 20)) -> list[str]:
    past = [f"lag{i}" for i in range(1, lags + 1)] + [f"user_lag{i}" for i in range(1, user_lags + 1)]
    return past + [f"{n}{r}" for r in windows for n in ("mean", "least", "most", "spread")] + ["hour", "user_events", "gap", "prop"]


def _earlier(x: np.ndarray, known: np.ndarray, i: int) -> pa.Array:
    """The value i rows before, null where there is none."""
    out, there = np.zeros_like(x), np.zeros(len(x), bool)
    out[i:], there[i:] = x[: len(x) - i], known[: len(x) - i]
    return pa.array(out, mask=~there)


def _rolled(x: np.ndarray, sizes, combine, fill: float) -> dict[int, np.ndarray]:
    """combine() of the r values before each row, for each r of sizes: runs of powers of two, of which two make any r."""
    most, n, run, length, out = max(sizes), len(x), np.concatenate([np.full(max(sizes), fill), x]), 1, {}
    for r in sorted(sizes):
        while 2 * length <= r:  # run[t]: of the `length` values up to t
            run = np.concatenate([run[:length], combine(run[length:], run[:-length])])
            length *= 2
        end, start = run[most - 1 : most - 1 + n], run[most - 1 - (r - length) : most - 1 - (r - length) + n]
        out[r] = combine(end, start)
    return out


def _windows(block: pa.Table, lags: int, windows: tuple[int, ...]) -> dict[str, pa.Array]:
    """The features of earlier rows of a block in order of time."""
    value = block.column("value").combine_chunks()
    known, x = np.asarray(value.is_valid()), value.fill_null(np.nan).to_numpy(zero_copy_only=False)
    cents = block.column("__c").combine_chunks().fill_null(0).to_numpy(zero_copy_only=False)
    if len(cents) and float(np.abs(cents).max()) * max(windows) >= 2**31:
        raise ArithmeticError("squares of the values' hundredths leave 64 bits")
    out = {f"lag{i}": _earlier(x, known, i) for i in range(1, lags + 1)}
    sums = [np.concatenate([[0], np.cumsum(v)]) for v in (known.astype(np.int64), cents, cents * cents)]
    least, most = _rolled(x, windows, np.fmin, np.nan), _rolled(np.where(known, x, -np.inf), windows, np.maximum, -np.inf)
    at = np.arange(len(x))
    for r in windows:
        n, s, q = (v[at] - v[np.maximum(at - r, 0)] for v in sums)
        with np.errstate(divide="ignore", invalid="ignore"):
            out[f"mean{r}"] = pa.array(s.astype(float) / n.astype(float) / 100, mask=n == 0)
            out[f"spread{r}"] = pa.array(np.sqrt((n * q - s * s).astype(float) / (n * (n - 1)).astype(float)) / 100, mask=n <= 1)
        out[f"least{r}"], out[f"most{r}"] = pa.array(least[r], mask=n == 0), pa.array(most[r], mask=n == 0)
    return out


def _of_users(rows: DataFrame, user_lags: int) -> DataFrame:
    """rows(user_id, value, at, ...) with user_lag1.. and user_events: a user's rows go by in order, the last few are held."""
    fields = [f"user_lag{i}" for i in range(1, user_lags + 1)]
    kinds = ", ".join([*(f"`{f.name}` {f.dataType.simpleString()}" for f in rows.schema), *(f"{c} double" for c in fields), "user_events double"])

    def along(batches):
        held, count = None, 0  # (user, no user, value, known) of the last rows, and the last user's rows so far
        for batch in batches:
            if not (n := batch.num_rows):
                continue
            user, value = batch.column(batch.schema.get_field_index("user_id")), batch.column(batch.schema.get_field_index("value"))
            own = [user.fill_null(0).to_numpy(zero_copy_only=False), np.asarray(user.is_null()), value.fill_null(0.0).to_numpy(zero_copy_only=False), np.asarray(value.is_valid())]
            u, none, x, known = own if held is None else [np.concatenate(p) for p in zip(held, own)]
            before = len(u) - n
            same = np.append(False, (u[1:] == u[:-1]) & (none[1:] == none[:-1]))
            start = np.maximum.accumulate(np.where(same, 0, np.arange(len(u))))  # of the user's run, as far as it is seen
            number = (np.arange(len(u)) - start + 1)[before:]
            if before and same[before]:  # the run goes on from rows that may be forgotten
                first = start[before:] == start[before]
                number = np.where(first, count + np.arange(1, n + 1), number)
            made = []
            for i in range(1, user_lags + 1):
                there = np.arange(len(u)) - i >= start
                made.append(pa.array(np.roll(x, i)[before:], mask=~(there & np.roll(known, i))[before:]))
            count, held = int(number[-1]), [p[-max(user_lags, 1) :] for p in (u, none, x, known)]
            yield pa.RecordBatch.from_arrays([*batch.columns, *made, pa.array(number.astype(float))], names=[*batch.schema.names, *fields, "user_events"])

    return rows.repartition("user_id").sortWithinPartitions("user_id", "at").mapInArrow(along, kinds)


def series(spark: SparkSession, sf_dir: str, lags: int = 10, user_lags: int = 5, windows: tuple[int, ...] = (5, 20), block: int = 20_000) -> DataFrame:
    """Events in order of time, with past values as features, the planted three-class label and the split by rank.

    The order is cut into blocks, each with as many of the rows before it as a feature looks back, so no task sees all rows. Sums over windows are of whole hundredths: no result hangs on their order.
    A user's rows go by in order in one task, which holds on to few.
    """
    from ..operators.sampling import numbered

    ship_package(spark)
    events = spread(spark.read.parquet(f"{sf_dir}/events.parquet")).select("event_id", "user_id", "ts", "value", "props", F.round(F.col("value") * 100).cast("long").alias("__c"))
    rows = numbered(events, ["ts", "event_id"])
    total, back = rows.count(), max([1, lags, *windows])
    block = max(block, back)
    made = rows.withColumns({"hour": F.hour("ts").cast("double"), "prop": F.regexp_extract("props", "([0-9]+)", 1).try_cast("double")}).drop("props")
    own = F.floor(F.col("at") / block)
    shared = F.when(F.col("at") % block >= block - back, F.array(own, own + 1)).otherwise(F.array(own))
    placed = _of_users(made, user_lags).withColumn("__block", F.explode(shared))
    columns = series_features(lags, user_lags, windows)
    names = ["event_id", "user_id", "ts", "value", "at", "__before", *(c for c in columns if c != "gap")]
    kind = {f.name: f.dataType.simpleString() for f in placed.schema}
    kind["__before"] = kind["ts"]

    def along(key, table):
        table = table.take(pc.sort_indices(table, sort_keys=[("at", "ascending")]))
        features = _windows(table, lags, windows) | {"__before": pa.chunked_array([pa.nulls(1, table.schema.field("ts").type), *table.column("ts").slice(0, len(table) - 1).chunks])}
        first = int(np.searchsorted(table.column("at").to_numpy(), key[0].as_py() * block))  # the rows before are of the block before
        return pa.table({n: features[n] if n in features else table.column(n) for n in names}).slice(first)

    with_past = placed.groupBy("__block").applyInArrow(along, ", ".join(f"`{n}` {kind.get(n, 'double')}" for n in names))
    y = F.when(F.col("value") < LOW, "low").when(F.col("value") > HIGH, "high").otherwise("proper")
    split = F.when(F.col("at") + 1 <= 0.75 * total, "train").when(F.col("at") + 1 <= 0.875 * total, "validation").otherwise("test")
    gap = (F.expr("timestampdiff(MICROSECOND, __before, ts)") / 1_000_000).cast("double")
    return with_past.withColumn("gap", gap).select("event_id", "user_id", "ts", "value", *columns, y.alias("y"), split.alias("split"))


def series_sql(lags: int = 10, user_lags: int = 5, windows: tuple[int, ...] = (5, 20)) -> str:
    """The same for an engine with views, by windows over all rows."""
    columns = [f"LAG(value, {i}) OVER w AS lag{i}" for i in range(1, lags + 1)] + [f"LAG(value, {i}) OVER u AS user_lag{i}" for i in range(1, user_lags + 1)]
    for r in windows:
        over = f"OVER (ORDER BY ts, event_id ROWS BETWEEN {r} PRECEDING AND 1 PRECEDING)"
        n, s_, q = f"COUNT(c) {over}", f"SUM(c) {over}", f"SUM(c * c) {over}"
        columns += [f"CASE WHEN {n} > 0 THEN CAST({s_} AS DOUBLE) / CAST({n} AS DOUBLE) / 100 END AS mean{r}", f"MIN(value) {over} AS least{r}", f"MAX(value) {over} AS most{r}"]
        columns += [f"CASE WHEN {n} > 1 THEN SQRT(CAST({n} * {q} - {s_} * {s_} AS DOUBLE) / CAST({n} * ({n} - 1) AS DOUBLE)) / 100 END AS spread{r}"]
    inner = f"""SELECT event_id, user_id, ts, value, CAST(EXTRACT(HOUR FROM ts) AS DOUBLE) AS hour, ROW_NUMBER() OVER w AS pos, COUNT(*) OVER () AS total, {', '.join(columns)},
  CAST(ROW_NUMBER() OVER u AS DOUBLE) AS user_events, CAST(epoch_us(ts) - LAG(epoch_us(ts)) OVER w AS DOUBLE) / 1000000 AS gap, TRY_CAST(regexp_extract(props, '[0-9]+') AS DOUBLE) AS prop
  FROM (SELECT *, CAST(ROUND(value * 100) AS BIGINT) AS c FROM events) e WINDOW w AS (ORDER BY ts, event_id), u AS (PARTITION BY user_id ORDER BY ts, event_id)"""
    label = f"CASE WHEN value < {LOW} THEN 'low' WHEN value > {HIGH} THEN 'high' ELSE 'proper' END AS y"
    split = "CASE WHEN pos <= 0.75 * total THEN 'train' WHEN pos <= 0.875 * total THEN 'validation' ELSE 'test' END AS split"
    return f"SELECT event_id, user_id, ts, value, {', '.join(series_features(lags, user_lags, windows))}, {label}, {split} FROM ({inner}) t"


def _customer_columns() -> dict[str, str]:
    """101 features of a customer's orders by name: sums of money are of whole cents, so they are the same in every engine."""
    cents = "CAST(ROUND(o_totalprice * 100) AS BIGINT)"
    out = {
        "acctbal": "MAX(c_acctbal)", "n_orders": "COUNT(*)", "mean_price": f"CAST(SUM({cents}) AS DOUBLE) / COUNT(*) / 100", "max_price": "MAX(o_totalprice)", "min_price": "MIN(o_totalprice)",
        "range_price": "MAX(o_totalprice) - MIN(o_totalprice)", "count_cheap": "SUM(CASE WHEN o_totalprice < 50000 THEN 1 ELSE 0 END)", "count_dear": "SUM(CASE WHEN o_totalprice > 250000 THEN 1 ELSE 0 END)",
        "count_early": "SUM(CASE WHEN EXTRACT(YEAR FROM o_orderdate) < 1998 THEN 1 ELSE 0 END)",
    }
    status, priority = {x.lower(): f"o_orderstatus = '{x}'" for x in "FOP"}, {f"p{i}": f"o_orderpriority LIKE '{i}%'" for i in range(1, 6)}
    groups = status | priority | {f"y{y}": f"EXTRACT(YEAR FROM o_orderdate) = {y}" for y in range(1995, 2002)} | {f"m{m}": f"EXTRACT(MONTH FROM o_orderdate) = {m}" for m in range(1, 13)}
    groups |= {f"q{i}": f"EXTRACT(MONTH FROM o_orderdate) BETWEEN {3 * i - 2} AND {3 * i}" for i in range(1, 5)} | {f"{a}_{b}": f"{x} AND {y}" for a, x in status.items() for b, y in priority.items()}
    for name, test in groups.items():
        out[f"count_{name}"] = f"SUM(CASE WHEN {test} THEN 1 ELSE 0 END)"
        out[f"sum_{name}"] = f"CAST(SUM(CASE WHEN {test} THEN {cents} ELSE 0 END) AS DOUBLE) / 100"
    return out


CUSTOMER_FEATURES = list(_customer_columns())
CUSTOMERS = f"""SELECT c_custkey, {', '.join(f'CAST({x} AS DOUBLE) AS {n}' for n, x in _customer_columns().items())},
  CAST(SUM(CAST(ROUND(o_totalprice * 100) AS BIGINT)) AS DOUBLE) / COUNT(*) / 100 / 1000 + 0.5 * SUM(CASE WHEN o_orderstatus = 'F' THEN 1 ELSE 0 END) * SUM(CASE WHEN o_orderpriority LIKE '1%' THEN 1 ELSE 0 END) + CAST((CAST(c_custkey AS BIGINT)*7919) % 100 AS DOUBLE) / 10 AS response
FROM {{customer}} JOIN {{orders}} ON c_custkey = o_custkey GROUP BY c_custkey"""

#: Orders as a set of 13 continuous and 10 discrete features with a label of about a fifth ones.
ORDERS = f"""SELECT o_orderkey, o_orderstatus, o_orderpriority, c_mktsegment, n_name, r_name, {_s('EXTRACT(MONTH FROM o_orderdate)', 'order_month')}, {_s('EXTRACT(YEAR FROM o_orderdate)', 'order_year')},
  flags, {_s('lines', 'line_count')}, CASE WHEN returned > 0 THEN 'yes' ELSE 'no' END AS any_returned,
  CAST(o_totalprice AS DOUBLE) AS o_totalprice, CAST(c_acctbal AS DOUBLE) AS c_acctbal, quantity, most_quantity, price, most_price, least_price, discount, most_discount, tax, most_tax, CAST(returned AS DOUBLE) AS returned, CAST(open_lines AS DOUBLE) AS open_lines,
  CAST(CASE WHEN CAST(o_orderkey AS BIGINT)*7919 % 100 < 8 THEN o_orderkey % 2 WHEN (c_mktsegment IN ('BUILDING', 'MACHINERY') AND most_price > 90000) OR (o_orderpriority LIKE '1%' AND returned > 1) THEN 1 ELSE 0 END AS VARCHAR(8)) AS y
FROM {{orders}} JOIN {{customer}} ON o_custkey = c_custkey JOIN {{nation}} ON c_nationkey = n_nationkey JOIN {{region}} ON n_regionkey = r_regionkey
JOIN (SELECT l_orderkey, COUNT(*) AS lines, CAST(SUM(CAST(l_quantity AS BIGINT)) AS DOUBLE) AS quantity, CAST(MAX(l_quantity) AS DOUBLE) AS most_quantity, CAST(SUM(CAST(ROUND(l_extendedprice * 100) AS BIGINT)) AS DOUBLE) / 100 AS price,
  CAST(MAX(l_extendedprice) AS DOUBLE) AS most_price, CAST(MIN(l_extendedprice) AS DOUBLE) AS least_price, CAST(SUM(CAST(ROUND(l_discount * 100) AS BIGINT)) AS DOUBLE) / 100 AS discount, CAST(MAX(l_discount) AS DOUBLE) AS most_discount,
  CAST(SUM(CAST(ROUND(l_tax * 100) AS BIGINT)) AS DOUBLE) / 100 AS tax, CAST(MAX(l_tax) AS DOUBLE) AS most_tax, SUM(CASE WHEN l_returnflag = 'R' THEN 1 ELSE 0 END) AS returned, SUM(CASE WHEN l_linestatus = 'O' THEN 1 ELSE 0 END) AS open_lines,
  CONCAT(MIN(l_returnflag), MAX(l_returnflag)) AS flags FROM {{lineitem}} GROUP BY l_orderkey) l ON l_orderkey = o_orderkey"""
ORDER_CATEGORICAL = ["o_orderstatus", "o_orderpriority", "c_mktsegment", "n_name", "r_name", "order_month", "order_year", "flags", "line_count", "any_returned"]
ORDER_CONTINUOUS = ["o_totalprice", "c_acctbal", "quantity", "most_quantity", "price", "most_price", "least_price", "discount", "most_discount", "tax", "most_tax", "returned", "open_lines"]

TURNS = """SELECT conv_id, turn, CASE WHEN turn = 0 THEN 't0' WHEN turn % 2 = 1 THEN 'odd' ELSE 'even' END AS turn_kind, CASE WHEN length(text) < 40 THEN 'short' WHEN length(text) < 200 THEN 'middle' ELSE 'long' END AS length_band,
  CASE WHEN text LIKE '%?' THEN 'yes' ELSE 'no' END AS asks, lower(split_part(text, ' ', 1)) AS first_word, role AS y FROM {conversations}"""
TURN_FEATURES = ["turn_kind", "length_band", "asks", "first_word"]

BASKETS = "SELECT DISTINCT l_orderkey AS basket, p_brand AS item FROM {lineitem} JOIN {part} ON l_partkey = p_partkey"


def vectors(dims: int = 64, below: int = 9, signs: bool = True) -> tuple[str, list[str]]:
    """Embeddings as columns: their signs, or their numbers. Array places differ among engines, so {at} stands for the first."""
    columns = [f"e{i}" for i in range(dims)]
    one = (lambda i: f"CASE WHEN embedding[{{at+{i}}}] > 0 THEN 'p' ELSE 'n' END AS e{i}") if signs else (lambda i: f"CAST(embedding[{{at+{i}}}] AS DOUBLE) AS e{i}")
    return f"SELECT vec_id, CAST(label AS VARCHAR(8)) AS y, {', '.join(one(i) for i in range(dims))} FROM {{embeddings}} WHERE label < {below}", columns


def tables_of(select: str) -> list[str]:
    return sorted(set(re.findall(r"\{([a-z]+)\}", select)))


def frame(spark: SparkSession, sf_dir: str, select: str) -> DataFrame:
    """The SELECT over the Parquet tables of sf_dir."""
    names = tables_of(select)
    text = re.sub(r"\{at\+(\d+)\}", lambda m: m[1], select)
    return spark.sql(text, **{n: spread(spark.read.parquet(f"{sf_dir}/{n}.parquet")) for n in names})


def spread(df: DataFrame, least_bytes: int = 1 << 20) -> DataFrame:
    """A scan that is one or few splits (a file of one row group can't be split) but no small table is dealt out to all cores; a scan of many splits stays as it is."""
    cores = df.sparkSession.sparkContext.defaultParallelism
    plan = df._jdf.queryExecution()
    small = int(plan.optimizedPlan().stats().sizeInBytes()) < least_bytes
    return df if small or plan.toRdd().getNumPartitions() * 2 > cores else df.repartition(cores)


def plain_sql(select: str) -> str:
    """The SELECT for an engine where the tables are views and arrays count from 1."""
    text = re.sub(r"\{at\+(\d+)\}", lambda m: str(int(m[1]) + 1), select)
    return re.sub(r"\{([a-z]+)\}", r"\1", text)
