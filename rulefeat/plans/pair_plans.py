"""Physical plans for counting pairs of kept items by class. All give the same rows.

explode: each record's kept ids become pairs, counted by hash aggregation; best for few kept items in a record.
gram: each task adds up products of 0/1 blocks for each group and class and emits its upper triangle; best for dense records with many items.
bits: one conditional sum for each pair in a wide aggregate; best for few pairs.
join: the records' items meet a table of the kept ones by a join; for more items than literals can hold.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.pandas.types import to_arrow_schema

from ..operators.items import kept_ids, long_items
from ..operators.ranking import join_on
from ..storage import ship_package

#: Costs at which one plan becomes cheaper than another; rows don't hang on them. Pairs up to which conditional sums are taken; items up to which a block of counters (items squared, eight
#: bytes each) fits a task; kept items of a record up to which their pairs are exploded; counters of all groups that a task holds before it emits them; items that may be literals of a plan.
BIT_PAIRS, GRAM_ITEMS, DENSE, HELD, LITERAL_ITEMS = 200, 3000, 8, 1 << 23, 20_000


def choose_plan(n_items: int, n_features: int) -> str:
    """Cost in counters touched per record: m(m-1)/2 exploded rows against a block product, where m is at most one item of each feature."""
    if n_items * (n_items - 1) // 2 <= BIT_PAIRS:
        return "bits"
    return "gram" if min(n_features, n_items) > DENSE and n_items <= GRAM_ITEMS else "explode"


def count_pairs(df: DataFrame, features, label: str, items: list[tuple[int, str]], by=(), weight=None, null_policy="skip", plan="auto", kept: DataFrame | None = None) -> DataFrame:
    """kept(by..., f1, v1): which of the items count in which group, where groups have different ones (a budget's number of rows for each group)."""
    items = sorted(set(items))
    if plan == "auto":
        plan = choose_plan(len(items), len(features))
        plan = "explode" if plan == "bits" and by else plan
    if plan == "bits" and by:
        raise ValueError("the bits plan counts one group")
    labelled = df.where(F.col(label).isNotNull())
    ids = labelled.select(*by, F.col(label).cast("string").alias("y"), *([F.col(weight).alias("weight")] if weight else []), kept_ids(df, features, items, null_policy).alias("ids"))
    if kept is not None and by and items:
        place = F.create_map(*[x for i, (f, v) in enumerate(items) for x in (F.lit(f"{f}={v}"), F.lit(i))])
        named_ids = kept.select(*by, F.element_at(place, F.concat_ws("=", F.col("f1").cast("string"), "v1")).alias("id"))
        own = named_ids.groupBy(*by).agg(F.collect_set("id").alias("own"))
        ids = join_on(ids, own, list(by)).withColumn("ids", F.array_sort(F.array_intersect("ids", "own"))).drop("own")
    counted = {"explode": _explode, "gram": _gram, "bits": _bits}[plan](ids, items, by, weight)
    # ids back to items: a literal lookup of bounded size
    f_of = F.array(*[F.lit(f) for f, _ in items]) if items else F.array().cast("array<int>")
    v_of = F.array(*[F.lit(v) for _, v in items]) if items else F.array().cast("array<string>")
    named = counted.select(
        *by, F.get(f_of, F.col("a")).alias("f1"), F.get(v_of, F.col("a")).alias("v1"), F.get(f_of, F.col("b")).alias("f2"), F.get(v_of, F.col("b")).alias("v2"), "y", F.col("supp").cast("long").alias("supp")
    )
    return named.where("f1 < f2")


def count_pairs_by_join(df: DataFrame, features, label: str, kept: DataFrame, by=(), weight=None, null_policy="skip") -> DataFrame:
    """The same from a table kept(by..., f1, v1) of any size: a record's items that it has are brought together again by the record's number."""
    numbered = df.withColumn("__rid", F.monotonically_increasing_id())
    long = long_items(numbered, features, label, ("__rid", *by), weight, null_policy)
    met = join_on(long, kept.select(*by, F.col("f1").alias("f"), F.col("v1").alias("v")), [*by, "f", "v"], "left_semi")
    lists = met.groupBy("__rid", *by, "y", *(["weight"] if weight else [])).agg(F.array_sort(F.collect_list(F.struct("f", "v"))).alias("ids"))
    pairs = F.flatten(F.transform("ids", lambda a, i: F.transform(F.filter(F.slice("ids", i + 2, F.size("ids")), lambda b: b["f"] > a["f"]), lambda b: F.struct(a.alias("a"), b.alias("b")))))
    rows = lists.select(*by, "y", *(["weight"] if weight else []), F.explode(pairs).alias("p"))
    supp = (F.sum("weight") if weight else F.count(F.lit(1))).cast("long").alias("supp")
    return rows.groupBy(*by, F.col("p.a.f").alias("f1"), F.col("p.a.v").alias("v1"), F.col("p.b.f").alias("f2"), F.col("p.b.v").alias("v2"), "y").agg(supp)


def _explode(ids: DataFrame, items, by, weight) -> DataFrame:
    pairs = F.flatten(F.transform("ids", lambda a, i: F.transform(F.slice("ids", i + 2, F.size("ids")), lambda b: F.struct(a.alias("a"), b.alias("b")))))
    rows = ids.select(*by, "y", *(["weight"] if weight else []), F.explode(pairs).alias("p"))
    return rows.groupBy(*by, "p.a", "p.b", "y").agg((F.sum("weight") if weight else F.count(F.lit(1))).alias("supp"))


def groups_of(batch: pa.RecordBatch, keys: int) -> tuple[np.ndarray, list[tuple]]:
    """The place of each row's group, by its first `keys` columns, among the batch's groups, and these."""
    code = np.zeros(batch.num_rows, np.int64)
    for k in range(keys):
        own = batch.column(k).dictionary_encode()
        _, code = np.unique(code * (len(own.dictionary) + 1) + own.indices.fill_null(len(own.dictionary)).to_numpy(zero_copy_only=False), return_inverse=True)
    _, first = np.unique(code, return_index=True)
    return code, [tuple(batch.column(k)[i].as_py() for k in range(keys)) for i in first.tolist()]


def _gram(ids: DataFrame, items, by, weight) -> DataFrame:
    """Each task holds a block of counters for every group and class that it has met, over the items that occur in it; full tasks emit and begin anew, as counts add up."""
    ship_package(ids.sparkSession)
    keys = [*by, "y"]
    rows = ids.select(*keys, "ids", *([F.col("weight").cast("long").alias("weight")] if weight else []))
    schema = T.StructType([*(rows.schema[k] for k in keys), T.StructField("a", T.IntegerType()), T.StructField("b", T.IntegerType()), T.StructField("supp", T.LongType())])
    arrow = to_arrow_schema(schema)

    def emit(sums: dict) -> Iterator[pa.RecordBatch]:
        for group, (seen, total) in sums.items():
            a, b = np.nonzero(np.triu(total, 1))
            named = [pa.array([v] * len(a), t) for v, t in zip(group, arrow.types)]
            yield pa.RecordBatch.from_arrays([*named, pa.array(seen[a].astype(np.int32)), pa.array(seen[b].astype(np.int32)), pa.array(total[a, b])], schema=arrow)

    def partial(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums: dict[tuple, tuple[np.ndarray, np.ndarray]] = {}
        held = 0
        for batch in batches:
            if not batch.num_rows:
                continue
            of, named = groups_of(batch, len(keys))
            lists = batch.column(len(keys))
            offsets = lists.offsets.to_numpy()
            row, flat = np.repeat(np.arange(len(of)), np.diff(offsets)), lists.flatten().to_numpy()
            times = batch.column(len(keys) + 1).to_numpy() if weight else None
            for g, group in enumerate(named):
                own = np.flatnonzero(of == g)
                place = np.full(len(of), -1)
                place[own] = np.arange(len(own))
                hit = place[row] >= 0
                seen, at = np.unique(flat[hit], return_inverse=True)
                block = np.zeros((len(own), len(seen)))
                block[place[row[hit]], at] = 1
                product = np.rint((block * times[own, None]).T @ block if weight else block.T @ block).astype(np.int64)  # exact below 2^53
                if group in sums:
                    old, total = sums[group]
                    held -= total.size
                    both = np.union1d(old, seen)
                    wide = np.zeros((len(both), len(both)), np.int64)
                    for part, counts in ((old, total), (seen, product)):
                        i = np.searchsorted(both, part)
                        wide[np.ix_(i, i)] += counts
                    seen, product = both, wide
                sums[group] = (seen, product)
                held += product.size
                if held > HELD:
                    yield from emit(sums)
                    sums.clear()
                    held = 0
        yield from emit(sums)

    return rows.mapInArrow(partial, schema).groupBy(*by, "a", "b", "y").agg(F.sum("supp").alias("supp"))


def _bits(ids: DataFrame, items, by, weight) -> DataFrame:
    places = [(a, b) for a in range(len(items)) for b in range(a + 1, len(items)) if items[a][0] < items[b][0]]
    if not places:
        return ids.select(F.lit(0).alias("a"), F.lit(0).alias("b"), "y", F.lit(0).cast("long").alias("supp")).limit(0)
    one = F.col("weight") if weight else F.lit(1)
    flags = ids.select("y", *(["weight"] if weight else []), *[F.array_contains("ids", i).alias(f"h{i}") for i in range(len(items))])
    wide = flags.groupBy("y").agg(*[F.sum(F.when(F.col(f"h{a}") & F.col(f"h{b}"), one)).alias(f"p{a}_{b}") for a, b in places])
    entries = F.array(*[F.struct(F.lit(a).alias("a"), F.lit(b).alias("b"), F.col(f"p{a}_{b}").alias("supp")) for a, b in places])
    return wide.select("y", F.explode(entries).alias("e")).select("e.a", "e.b", "y", "e.supp").where("supp > 0")
