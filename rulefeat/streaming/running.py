"""Running supports on streams of events, re-ranking of rules as counts grow, and scoring of streams."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..operators import counts
from ..operators.ranking import support_order, top
from ..operators.selectors import Mined, as_sets, recut, with_totals
from ..storage import materialise, release, scratch_path

EVENT_SCHEMA = "event_id long, user_id long, ts timestamp, event_type string, value double, props string"


def stage_events(spark: SparkSession, sf_dir: str, files: int = 4, late_every: int = 0) -> str:
    """Events as a folder of files by time; with late_every, each so-many-th event comes two files later."""
    events = spark.read.parquet(f"{sf_dir}/events.parquet").select("event_id", "user_id", F.col("ts").cast("timestamp").alias("ts"), "event_type", "value", "props")
    low, high = events.agg(F.min(F.unix_seconds("ts")), F.max(F.unix_seconds("ts"))).first()
    part = F.floor((F.unix_seconds("ts") - low) * files / (high - low + 1))
    if late_every:
        part = F.when(F.col("event_id") % late_every == 0, F.least(part + 2, F.lit(files - 1))).otherwise(part)
    path = scratch_path(spark, "events")
    for i in range(files):
        events.where(part == i).coalesce(1).write.mode("append").parquet(path)
    return path


def read_events(spark: SparkSession, path: str, files_per_trigger: int = 1) -> DataFrame:
    return spark.readStream.schema(EVENT_SCHEMA).option("maxFilesPerTrigger", files_per_trigger).parquet(path)


def item_counts(stream: DataFrame, features: list[str], label: str) -> DataFrame:
    """(f, v, y, supp) so far."""
    from ..operators.items import long_items

    return long_items(stream, features, label).groupBy("f", "v", "y").agg(F.count(F.lit(1)).alias("supp"))


def window_counts(stream: DataFrame, label: str, length: str = "1 day", slide: str | None = None, watermark: str | None = None) -> DataFrame:
    """(start, y, supp) of tumbling or sliding windows; rows later than the watermark are left out."""
    if watermark:
        stream = stream.withWatermark("ts", watermark)
    w = F.window("ts", length, slide) if slide else F.window("ts", length)
    return stream.groupBy(w.alias("w"), F.col(label).alias("y")).agg(F.count(F.lit(1)).alias("supp")).select(F.col("w.start").alias("start"), "y", "supp")


def session_counts(stream: DataFrame, gap: str = "30 minutes", watermark: str = "1 hour") -> DataFrame:
    """(user_id, start, supp): events of each user's sessions."""
    s = F.session_window("ts", gap)
    return stream.withWatermark("ts", watermark).groupBy(s.alias("s"), "user_id").agg(F.count(F.lit(1)).alias("supp")).select("user_id", F.col("s.start").alias("start"), "supp")


def without_repeats(stream: DataFrame, keys: list[str], watermark: str = "1 day") -> DataFrame:
    return stream.withWatermark("ts", watermark).dropDuplicatesWithinWatermark(keys)


def with_labels(events: DataFrame, labels: DataFrame, within: str = "1 hour", watermark: str = "2 hours") -> DataFrame:
    """Events with the labels (event_id, label_ts, y) that come within a bound after them."""
    a, b = events.withWatermark("ts", watermark), labels.withWatermark("label_ts", watermark)
    return a.join(b, (a["event_id"] == b["event_id"]) & (b["label_ts"] >= a["ts"]) & (b["label_ts"] <= a["ts"] + F.expr(f"INTERVAL {within}"))).drop(b["event_id"])


def last_label_per_user(stream: DataFrame, label: str = "event_type") -> DataFrame:
    """(user_id, previous, now) for each event, from state kept per user without a bound in time."""

    def follow(key: tuple, batches: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        last = state.get[0] if state.exists else None
        for rows in batches:
            rows = rows.sort_values(["ts", "event_id"])
            now = rows[label].tolist()
            yield pd.DataFrame({"user_id": key[0], "event_id": rows["event_id"].tolist(), "previous": [last, *now[:-1]], "now": now})
            last = now[-1] if now else last
        state.update((last,))

    return stream.groupBy("user_id").applyInPandasWithState(follow, "user_id long, event_id long, previous string, now string", "last string", "append", "NoTimeout")


def run_to_end(result: DataFrame, label: str, mode: str = "complete") -> DataFrame:
    """Drive a stream over what is there into a table: the last complete result, or all appended rows."""
    spark = result.sparkSession
    out = scratch_path(spark, label)

    def keep(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{out}/rows" if mode == "complete" else f"{out}/rows/batch={number}")

    query = result.writeStream.outputMode(mode).foreachBatch(keep).option("checkpointLocation", f"{out}/state").trigger(availableNow=True).start()
    query.awaitTermination()
    return spark.read.schema(result.schema).parquet(f"{out}/rows" if mode == "complete" else f"{out}/rows/*")


class RunningRules:
    """Counts of items, classes and pairs added up batch by batch; rules are re-ranked from the merged counts.

    All items and classes are counted, and the pairs of the items that are frequent so far. The columns at hand of each batch are kept in the shared folder: when an item
    becomes frequent later, its pairs are counted anew over what came before, so the rules are those of all batches mined at once.
    """

    def __init__(self, features: list[str], label: str, d_freq: int, d_conf: int):
        self.features, self.label, self.d_freq, self.d_conf = list(features), label, d_freq, d_conf
        self.counted: set[tuple[int, str]] = set()
        self.singles: DataFrame | None = None
        self.pairs: DataFrame | None = None
        self.folder: str | None = None
        self.batches = 0

    def _merged(self, old: DataFrame | None, new: DataFrame, keys: list[str]) -> DataFrame:
        both = materialise((new if old is None else old.unionByName(new)).groupBy(*keys).agg(F.sum("supp").alias("supp")), "running")
        if old is not None:
            release(old)
        return both

    def _labels(self) -> DataFrame:
        every = W.partitionBy()  # a row a class
        return self.singles.where("f = 0").select("y", F.col("supp").alias("supp_y"), F.sum("supp").over(every).alias("n"), F.count(F.lit(1)).over(every).alias("n_classes"))

    def _cut(self, sets: DataFrame) -> DataFrame:
        share = self._labels().select("y", F.greatest(F.floor(F.lit(self.d_freq) / F.col("n_classes")).cast("int"), F.lit(1)).alias("budget"))
        return top(sets.join(share, "y"), support_order(), F.col("budget"), ("y",)).drop("budget")

    def absorb(self, batch: DataFrame, number: int | None = None) -> None:
        """One batch (`number` is what foreachBatch gives; batches come in order, each once)."""
        spark = batch.sparkSession
        self.folder = self.folder or scratch_path(spark, "batches")
        own = materialise(batch.select(*self.features, self.label), "batch", path=f"{self.folder}/batch={self.batches}")
        self.batches += 1
        keys = ["f1", "v1", "f2", "v2", "y"]
        self.singles = self._merged(self.singles, counts.singles(own, self.features, self.label, with_label=True), ["f", "v", "y"])
        if self.counted:
            self.pairs = self._merged(self.pairs, counts.pairs(own, self.features, self.label, sorted(self.counted)), keys)
        frequent = {(r[0], r[1]) for r in self._cut(as_sets(self.singles.where("f > 0"))).select("f1", "v1").distinct().collect()}  # a budget's number
        if new := frequent - self.counted:
            items = sorted(self.counted | frequent)
            fresh = F.array(*[F.struct(F.lit(f).alias("f"), F.lit(v).alias("v")) for f, v in sorted(new)])
            whole = counts.pairs(spark.read.parquet(self.folder).drop("batch"), self.features, self.label, items)
            late = whole.where(F.array_contains(fresh, F.struct(F.col("f1").alias("f"), F.col("v1").alias("v"))) | F.array_contains(fresh, F.struct(F.col("f2").alias("f"), F.col("v2").alias("v"))))
            self.pairs = self._merged(self.pairs, late, keys)
            self.counted |= new

    def rules(self) -> DataFrame:
        singles = as_sets(self.singles.where("f > 0"))
        named = self.pairs.select(F.lit(2).alias("size"), "f1", "v1", "f2", "v2", "y", "supp")
        wanted = named.join(counts.candidates(self._cut(singles)), ["f1", "v1", "f2", "v2", "y"], "left_semi").select(*named.columns)
        sets = self._cut(singles.unionByName(wanted))
        return recut(Mined(with_totals(sets, singles.unionByName(named), self._labels())), self.d_conf).rules
