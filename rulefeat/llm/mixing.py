"""Mixing sources to target weights by weighted fair queueing (DataFrame operations only).

Every source is a queue of its shuffled documents, gone through up to `epochs` times. A document's virtual finish time is the number of words that its
queue has sent when it ends, divided by the source's target. All documents of all sources are range-sorted by that time, words are added up along
the order, and the mix is cut where the total budget is spent. Sums along an order are made range by range, and the ranges' totals are added up
apart, so that no task sees a whole source.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..storage import materialise

WORD = r"[^\x20\x09-\x0D]+"
#: Weights of the sources in order, repeating.
WEIGHTS = (5.0, 2.0, 1.0)
EPOCHS, SEED = 3, 7
#: Words of one packet: a document that isn't over when its source's target is reached is sent in packets, so that the cut falls within it.
QUANTUM = 1


def word_count(text: Column) -> Column:
    """Number of runs of other characters than white space; null has none."""
    bare = F.btrim(F.coalesce(text.cast("string"), F.lit("")), F.lit(" \t\n\x0b\f\r"))
    return F.when(bare == "", 0).otherwise(F.length(F.regexp_replace(bare, WORD + r"[\x20\x09-\x0D]*", "x"))).cast("long")


def source_targets(sizes: DataFrame, weights: tuple[float, ...] = WEIGHTS, epochs: int = EPOCHS) -> DataFrame:
    """sizes(source, size) to source, queue (its number from 1), source_size, target.

    Sources in order of code points, null last, take the weights in turn. A target stops at `epochs` times
    its source's size and the excess is shared anew among the rest by weight. The level at which that ends is found by one pass in the order of
    size to weight, as a source is capped exactly when the level without the sources before it reaches it. The windows here go over one row a source.
    """
    per_source = sizes.groupBy("source").agg(F.sum("size").alias("source_size"))
    turn = F.row_number().over(Window.orderBy(F.col("source").asc_nulls_last())) - 1
    weight = F.element_at(F.array(*[F.lit(float(w)) for w in weights]), (turn % len(weights) + 1).cast("int"))
    weighed = per_source.select("source", (turn + 1).alias("queue"), "source_size", weight.alias("weight"), (F.col("source_size") * epochs).alias("cap"))
    every = Window.partitionBy()
    by_level = Window.orderBy(F.col("cap") / F.col("weight"), F.col("source").asc_nulls_last())
    before = by_level.rowsBetween(Window.unboundedPreceding, -1)
    left = F.sum("source_size").over(every) - F.coalesce(F.sum("cap").over(before), F.lit(0))
    heft = F.sum("weight").over(every) - F.coalesce(F.sum("weight").over(before), F.lit(0.0))
    stepped = weighed.select("*", F.row_number().over(by_level).alias("place"), (left / heft).alias("level"))
    # up to the first source that its level doesn't cap, all are capped; that level holds from there on
    free = F.min(F.when(F.col("cap") > F.col("weight") * F.col("level"), F.struct("place", "level"))).over(every)
    stepped = stepped.select("*", free.alias("free"))
    capped = F.col("free").isNull() | (F.col("place") < F.col("free.place"))
    target = F.when(capped, F.col("cap").cast("double")).otherwise(F.col("weight") * F.col("free.level"))
    return stepped.select("source", "queue", "source_size", target.alias("target"))


def _turn(doc_id: Column, text: Column, seed: int) -> Column:
    """Eight bytes that a document's id and text decide: its place in the shuffled queue. Null ids are spread by their texts."""
    named = F.concat(F.coalesce(doc_id.cast("string"), F.lit("")), F.lit(f":{seed}:"), F.coalesce(text.cast("string"), F.lit("")))
    return F.unhex(F.substring(F.md5(named.cast("binary")), 1, 16))


def _summed(rows: DataFrame, order: list[Column], value: str, group: list[str], label: str) -> DataFrame:
    """rows with `sent`, the sum of `value` over the rows of the group up to and with this one, in a total order that begins with the group.

    Rows are sorted in ranges, each range is summed on its own, and the totals of the ranges (one row each) are added up apart.
    """
    placed = materialise(rows.repartitionByRange(*order).sortWithinPartitions(*order).withColumn("__part", F.spark_partition_id()), label)
    along = Window.partitionBy(*group).orderBy("__part").rowsBetween(Window.unboundedPreceding, -1)
    starts = placed.groupBy(*group, "__part").agg(F.sum(value).alias("__in")).select(*group, "__part", F.coalesce(F.sum("__in").over(along), F.lit(0)).alias("__start"))
    inside = Window.partitionBy(*group, "__part").orderBy(*order).rowsBetween(Window.unboundedPreceding, 0)
    within = placed.withColumn("__within", F.sum(value).over(inside))
    return within.join(starts, [*group, "__part"]).withColumn("sent", F.col("__start") + F.col("__within")).drop("__part", "__start", "__within")


def _queued(docs: DataFrame, text_col: str, id_col: str, source_col: str, weights, epochs: int, seed: int) -> DataFrame:
    """row, doc_id, source, size, turn, queue, source_size, target, before (words that its queue sends before it)."""
    text, doc_id = F.col(text_col), F.col(id_col)
    read = docs.select(doc_id.alias("doc_id"), F.col(source_col).alias("source"), word_count(text).alias("size"), F.coalesce(_turn(doc_id, text, seed), F.lit(b"")).alias("turn"))
    rows = materialise(read.withColumn("row", F.monotonically_increasing_id()), "mix-sizes")
    targets = materialise(source_targets(rows.select("source", "size"), weights, epochs), "mix-targets").withColumnRenamed("source", "__source")
    named = rows.join(targets, F.col("source").eqNullSafe(F.col("__source"))).drop("__source")
    order = [F.col("queue"), F.col("turn"), F.col("doc_id").asc_nulls_last(), F.col("size"), F.col("row")]
    return materialise(_summed(named, order, "size", ["queue"], "mix-queues").withColumn("before", F.col("sent") - F.col("size")).drop("sent"), "mix-queued")


def _sent(queued: DataFrame, epochs: int, quantum: int | None) -> DataFrame:
    """(row, copy, at, words, finish, taken) of what may be sent before the budget is spent: copies of documents, or (from the target on) their packets.

    What ends by virtual time 1 is never cut, as the targets add up to the budget. After it the queues send together no more than what each had
    begun, one packet a queue; what begins later than that isn't made.
    """
    row = queued.agg(F.sum("size").alias("budget"), F.count_distinct("queue").alias("queues"), F.max("size").alias("longest")).first()
    budget, packet = row["budget"] or 0, quantum or row["longest"] or 1
    open_until = F.col("target") + F.lit(float((row["queues"] + 1) * packet))
    begins = F.col("copy") * F.col("source_size") + F.col("before")
    copies = queued.where("size > 0 AND target > 0").withColumn("copy", F.explode(F.sequence(F.lit(0), F.lit(epochs - 1)))).withColumn("begins", begins).where(F.col("begins") < open_until)
    whole = F.array(F.struct(F.lit(0).cast("long").alias("at"), F.col("size").alias("words")))
    if quantum:
        last = F.floor((F.least(F.col("size").cast("double"), F.ceil(open_until) - F.col("begins")) - 1) / quantum).cast("long")
        split = F.transform(F.sequence(F.lit(0).cast("long"), last), lambda j: F.struct((j * quantum).alias("at"), F.least(F.lit(quantum).cast("long"), F.col("size") - j * quantum).alias("words")))
        pieces = F.when(F.col("begins") + F.col("size") <= F.col("target"), whole).otherwise(split)
    else:
        pieces = whole
    items = copies.withColumn("p", F.explode(pieces)).select("row", "queue", "turn", "doc_id", "size", "copy", "p.at", "p.words", ((F.col("begins") + F.col("p.at") + F.col("p.words")).cast("double") / F.col("target")).alias("finish"))
    order = [F.col("finish"), F.col("queue"), F.col("turn"), F.col("doc_id").asc_nulls_last(), F.col("size"), F.col("copy"), F.col("at"), F.col("row")]
    sent = _summed(items, order, "words", [], "mix-order")
    taken = F.greatest(F.lit(0).cast("long"), F.least(F.col("words"), F.lit(budget) - (F.col("sent") - F.col("words"))))
    return sent.select("row", "copy", "at", "words", "finish", taken.alias("taken"))


def schedule(docs: DataFrame, text_col: str = "text", id_col: str = "doc_id", source_col: str = "source", weights: tuple[float, ...] = WEIGHTS, epochs: int = EPOCHS, seed: int = SEED, quantum: int = QUANTUM) -> DataFrame:
    """One row per input row: doc_id, source, size, source_size, target, taken, virtual_finish.

    taken is the number of words the mix takes, repeats counted, at most `epochs` times size; the words of all rows add up to the budget, those of a source come within
    a packet a source of its target. virtual_finish is the time at which the row's first copy ends (null where the target is 0).
    Null texts have no words; null sources are one source, the last. Null ids and repeated rows count like others; rows alike in id, source and text are interchangeable, so reruns agree.
    An empty table gives an empty result. A source, or rows that are all alike, may be any share of the table.
    """
    queued = _queued(docs, text_col, id_col, source_col, weights, epochs, seed)
    got = _sent(queued, epochs, quantum).groupBy("row").agg(F.sum("taken").alias("taken"))
    return queued.join(got, "row", "left").select(
        "doc_id", "source", "size", "source_size", "target", F.coalesce("taken", F.lit(0).cast("long")).alias("taken"),
        F.try_divide((F.col("before") + F.col("size")).cast("double"), F.col("target")).alias("virtual_finish"),
    )


def mix(docs: DataFrame, text_col: str = "text", id_col: str = "doc_id", source_col: str = "source", weights: tuple[float, ...] = WEIGHTS, epochs: int = EPOCHS, seed: int = SEED) -> DataFrame:
    """The mix itself: the rows of docs, each as often as it is taken, range-sorted by finish time; all columns are kept.

    Texts stay whole: the one document that the cut meets goes in if at least half of it fits. Texts without words are not in the mix.
    Rows alike in id, source and text are one document with as many copies as they have together, in the other columns of one of them.
    """
    queued = _queued(docs, text_col, id_col, source_col, weights, epochs, seed)
    got = _sent(queued, epochs, None).where("2 * taken >= words").groupBy("row").agg(F.count(F.lit(1)).alias("copies"), F.min("finish").alias("finish"))
    plan = queued.join(got, "row").groupBy("doc_id", "source", "turn").agg(
        F.sum("copies").alias("copies"), F.min("finish").alias("finish"), F.any_value(F.col("source_size") / F.col("target")).alias("turn_time"), F.count(F.lit(1)).alias("rows")
    )
    plan = materialise(plan, "mix-plan")
    keyed = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("__row"), F.col(id_col).alias("__id"), F.col(source_col).alias("__source"), F.coalesce(_turn(F.col(id_col), F.col(text_col), seed), F.lit(b"")).alias("__turn"))
    own = plan.select(F.col("doc_id").alias("__p_id"), F.col("source").alias("__p_source"), F.col("turn").alias("__turn"), "copies", "finish", "turn_time", "rows")
    met = keyed.join(own, "__turn").where(F.col("__id").eqNullSafe(F.col("__p_id")) & F.col("__source").eqNullSafe(F.col("__p_source")))
    if not plan.where("rows > 1").isEmpty():
        met = met.groupBy("__turn", "__id", "__source", "copies", "finish", "turn_time").agg(F.any_value("__row").alias("__row"))
    each = met.withColumn("__time", F.explode(F.transform(F.sequence(F.lit(0).cast("long"), F.col("copies") - 1), lambda i: F.col("finish") + i * F.col("turn_time"))))
    return each.orderBy("__time", "__turn").select("__row.*")
