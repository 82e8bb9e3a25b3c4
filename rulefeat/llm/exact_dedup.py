"""Exact duplicate removal with disk-backed streaming state (DataFrame operations only).

Each text is reduced to the SHA-256 of its bytes without white space. The keyed rows
(digest, document id, number of code points, multiplicity) go through a streaming
aggregation whose state lives in RocksDB, has no expiry and keeps for each digest
the winner's identifier and the locator of its content (id and length).
Groups that were hit more than once are then compared byte for byte; digests whose texts
differ are regrouped by the full text.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..storage import materialise, scratch_path, settings
from .marks import marked

WHITE = r"[\x20\x09-\x0D]+"
ROCKS = "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider"
STATE_SETTINGS = {
    "spark.sql.streaming.stateStore.providerClass": ROCKS,
    "spark.sql.streaming.stateStore.rocksdb.changelogCheckpointing.enabled": "true",
    "spark.sql.streaming.stateStore.rocksdb.boundedMemoryUsage": "true",
    "spark.sql.streaming.stateStore.rocksdb.maxMemoryUsageMB": "256",
    # many small stores: no megabytes set aside on disk for each one's logs
    "spark.sql.streaming.stateStore.rocksdb.allowFAllocate": "false",
    "spark.sql.streaming.noDataMicroBatches.enabled": "false",
}


def squeezed(text: Column) -> Column:
    """The text without white space; null counts as empty."""
    return F.regexp_replace(F.coalesce(text.cast("string"), F.lit("")), WHITE, "")


def _better() -> Column:
    """Orders rows of one group: most code points first, then the smallest id, null ids last."""
    return F.struct((-F.col("n_chars")).alias("rank"), F.col("doc_id").isNull().alias("unnamed"), F.col("doc_id").alias("doc_id"))


class DedupState:
    """Keyed state on the shared disk. Each absorb() call is one run of the same streaming query."""

    def __init__(self, spark: SparkSession, folder: str | None = None, bytes_per_batch: int = 64 << 30):
        self.spark, self.bytes_per_batch = spark, bytes_per_batch
        self.folder = folder or scratch_path(spark, "dedup-state")
        self.inbox, self.outbox = f"{self.folder}/inbox", f"{self.folder}/outbox"

    def absorb(self, keyed: DataFrame) -> None:
        """Append keyed rows (key, doc_id, n_chars, copies) to the stream and bring the state up to date."""
        keyed.write.mode("append").parquet(self.inbox)
        stream = (
            self.spark.readStream.schema(keyed.schema).option("maxBytesPerTrigger", self.bytes_per_batch).parquet(self.inbox)
            .groupBy("key").agg(F.min(_better()).alias("best"), F.sum("copies").alias("group_size"))
        )
        outbox = self.outbox

        def keep(batch: DataFrame, number: int) -> None:
            batch.write.mode("overwrite").parquet(f"{outbox}/batch={number}")

        with settings(self.spark, STATE_SETTINGS):
            query = (
                stream.writeStream.outputMode("update").foreachBatch(keep)
                .option("checkpointLocation", f"{self.folder}/state").trigger(availableNow=True).start()
            )
            query.awaitTermination()

    def winners(self) -> DataFrame:
        """One row per key as the state has it: key, keep_id, keep_chars, group_size."""
        kept = self.spark.read.option("basePath", self.outbox).parquet(f"{self.outbox}/*")
        # within the changes of several batches the latest is also the best and the largest
        return (
            kept.groupBy("key").agg(F.min("best").alias("best"), F.max("group_size").alias("group_size"))
            .select("key", F.col("best.doc_id").alias("keep_id"), (-F.col("best.rank")).alias("keep_chars"), "group_size")
        )


def exact_dedup(docs: DataFrame, text_col: str = "text", id_col: str = "doc_id", key_bytes: int = 32, bytes_per_batch: int = 64 << 30) -> DataFrame:
    """One row per input row: doc_id, keep_id, group_size, kept, text_sha256.

    Texts are equal when they are identical without white space; a null text is an empty one. The row with the most code points,
    then the smallest id (null ids last) stays. Rows repeated under one id with equal texts
    of equal length count in group_size, and just one of them is kept. An empty table gives an empty result.
    Columns other than the two named are not read. key_bytes below 32 shortens the state's key (tests force collisions with it).
    """
    spark = docs.sparkSession
    read = docs.select(F.col(id_col).alias("doc_id"), F.length(F.coalesce(F.col(text_col).cast("string"), F.lit(""))).alias("n_chars"), squeezed(F.col(text_col)).alias("plain"))
    read = read.withColumn("digest", F.unhex(F.sha2("plain", 256))).withColumn("key", F.coalesce(F.substring("digest", 1, key_bytes), F.lit(b"")))
    # a third of all rows may share a text: rows are counted before anything is shuffled by it
    keyed = materialise(read.groupBy("key", "digest", "doc_id", "n_chars").agg(F.count(F.lit(1)).alias("copies")), "dedup-keyed")
    state = DedupState(spark, bytes_per_batch=bytes_per_batch)
    state.absorb(keyed.select("key", "doc_id", "n_chars", "copies"))
    if keyed.isEmpty():
        winners = spark.createDataFrame([], "key binary, keep_id long, keep_chars int, group_size long")
    else:
        winners = materialise(state.winners(), "dedup-winners")

    # full bytes on hits: all members of a group are equal exactly when the least and the greatest are
    hits = winners.where("group_size > 1").select("key")
    first_bits = F.conv(F.hex(F.substring("key", 1, 4)), 16, 10)
    perhaps = marked(read.select("key", "plain"), first_bits, hits, first_bits).where("__maybe")
    # each task takes the least and the greatest of its own before any text moves: a hot text moves twice a task, not once a row
    ends = perhaps.groupBy("key").agg(F.min("plain").alias("low"), F.max("plain").alias("high")).where("low <> high")
    unequal = materialise(ends.join(hits, "key", "left_semi").select("key"), "dedup-unequal")
    sure = keyed.join(winners, "key")
    if not unequal.isEmpty():
        sure = sure.join(unequal, "key", "left_anti")
    out = sure.select("doc_id", "n_chars", "digest", "copies", "keep_id", "keep_chars", "group_size")
    if not unequal.isEmpty():
        apart = read.join(unequal, "key", "left_semi").groupBy("digest", "plain", "doc_id", "n_chars").agg(F.count(F.lit(1)).alias("copies"))
        best = apart.groupBy("digest", "plain").agg(F.min(_better()).alias("best"), F.sum("copies").alias("group_size"))
        out = out.unionByName(
            apart.join(best, ["digest", "plain"]).select("doc_id", "n_chars", "digest", "copies", F.col("best.doc_id").alias("keep_id"), (-F.col("best.rank")).alias("keep_chars"), "group_size")
        )
    first = F.col("doc_id").eqNullSafe(F.col("keep_id")) & (F.col("n_chars") == F.col("keep_chars")) & (F.col("turn") == 1)
    return out.withColumn("turn", F.explode(F.sequence(F.lit(1).cast("long"), F.col("copies")))).select(
        "doc_id", "keep_id", F.col("group_size").cast("long").alias("group_size"), first.alias("kept"), F.lower(F.hex("digest")).alias("text_sha256"), "n_chars"
    )


def drop_copies(docs: DataFrame, text_col: str = "text", id_col: str = "doc_id") -> DataFrame:
    """docs without the rows that exact_dedup() drops, all columns kept.

    Rows repeated under one id (null ids included) with equal texts of equal length are reduced to one of them. Only rows whose id may be among those of
    dropped rows are met with the decisions; the others stay where they are.
    """
    found = materialise(exact_dedup(docs, text_col, id_col), "dedup-decisions")
    name = F.xxhash64(F.col(id_col))
    told = marked(docs, name, found.where("NOT kept"), F.xxhash64("doc_id"))
    sure, unsure = told.where("NOT __maybe").drop("__maybe"), told.where("__maybe").drop("__maybe")
    one = F.length(F.coalesce(F.col(text_col).cast("string"), F.lit("")))
    kept = found.where("kept").select(F.col("doc_id").alias("__id"), F.col("n_chars").alias("__n"), F.col("text_sha256").alias("__digest"))
    keyed = unsure.select("*", F.coalesce(F.sha2(squeezed(F.col(text_col)), 256), F.lit("")).alias("__sha"), one.alias("__len"))
    stay = keyed.join(kept, keyed[id_col].eqNullSafe(kept["__id"]) & (keyed["__len"] == kept["__n"]) & (keyed["__sha"] == kept["__digest"]), "left_semi")
    if not found.groupBy("doc_id", "text_sha256", "n_chars").count().where("count > 1").isEmpty():
        columns = [F.col(f"`{c}`") for c in docs.columns]
        stay = stay.groupBy("__sha", "__len", F.col(id_col).alias("__own")).agg(F.any_value(F.struct(*columns)).alias("__row")).select("__row.*")
    return sure.unionByName(stay.select(*docs.columns))
