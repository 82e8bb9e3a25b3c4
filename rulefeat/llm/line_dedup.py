"""Reversible line dedup: sharded cuckoo filters backed by exact reference counts.

A line's key (stripped, A-Z lowered) is held as a 128-bit hash. The reference table has, for each
key, the documents that hold it: inserting documents appends their references, deleting
documents appends the same with a negative sign, so any deletion undoes its insertion. Keys that enough documents hold are repeated keys;
their hashes are in cuckoo filters, one for each shard of the key space, which learn and forget keys as counts pass the threshold.
The filters are a table with a row a shard; there are as many shards as keep a filter small. Lines are sent to their shard, whose filter comes before them in the same
partition, and only what it lets through meets the exact table. A shard with many lines is dealt out to several partitions, each with a copy of its filter.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..storage import ROWS_PER_BATCH, SMALL_BATCHES, drop_path, materialise, scratch_path, settings, ship_package, trim_memory
from .marks import marked

SLOTS, KICKS = 4, 500
#: Repeated keys of a shard at most (on average), and lines that one partition looks up in a copy of its filter.
SHARD_KEYS, SHARD_LINES = 1 << 15, 1 << 18


class CuckooFilter:
    """16-bit fingerprints in buckets of four; a key has two buckets, either found from the other and the fingerprint."""

    def __init__(self, capacity: int):
        self.buckets = 1 << max(2, int(np.ceil(np.log2(max(1, capacity) / (SLOTS * 0.85)))))
        self.table = np.zeros((self.buckets, SLOTS), np.uint16)
        self.spill: dict[tuple[int, int], int] = {}  # what found no place in KICKS moves, so that no key is ever lost

    def _place(self, h1, h2):
        mask = np.uint64(self.buckets - 1)
        mark = (np.asarray(h2).astype(np.uint64) & np.uint64(0xFFFF)).astype(np.uint16)
        mark = np.where(mark == 0, np.uint16(1), mark)
        first = (np.asarray(h1).astype(np.uint64) >> np.uint64(8)) & mask
        return mark, first, self._other(first, mark)

    def _other(self, bucket, mark):
        return bucket ^ ((mark.astype(np.uint64) * np.uint64(0x5BD1E995)) & np.uint64(self.buckets - 1))

    def insert(self, h1: int, h2: int) -> None:
        mark, first, second = (x.item() for x in map(np.asarray, self._place(np.uint64(h1), np.uint64(h2))))
        for b in (first, second):
            free = np.flatnonzero(self.table[b] == 0)
            if free.size:
                self.table[b, free[0]] = mark
                return
        at = second
        for turn in range(KICKS):
            slot = (mark + turn) % SLOTS
            mark, self.table[at, slot] = int(self.table[at, slot]), mark
            at = int(self._other(np.uint64(at), np.uint16(mark)))
            free = np.flatnonzero(self.table[at] == 0)
            if free.size:
                self.table[at, free[0]] = mark
                return
        key = (mark, min(at, int(self._other(np.uint64(at), np.uint16(mark)))))
        self.spill[key] = self.spill.get(key, 0) + 1

    def insert_all(self, keys: np.ndarray) -> None:
        """Insert rows (h1, h2): all that find a free slot in one of their buckets at once, the others one by one."""
        mark, *both = self._place(keys[:, 0], keys[:, 1])
        left = np.arange(len(keys))
        for bucket in both:
            at = bucket[left]
            order = np.argsort(at, kind="stable")
            left, at = left[order], at[order].astype(np.int64)
            turn = np.arange(len(at)) - np.searchsorted(at, at)  # which of its bucket's newcomers
            free = self.table[at] == 0
            slot = np.argsort(~free, axis=1, kind="stable")
            fits = turn < free.sum(axis=1)
            self.table[at[fits], slot[fits, turn[fits]]] = mark[left[fits]]
            left = left[~fits]
        for h1, h2 in keys[left]:
            self.insert(h1, h2)

    def delete(self, h1: int, h2: int) -> bool:
        """Forget one insertion of the key; false if it wasn't there."""
        mark, first, second = (x.item() for x in map(np.asarray, self._place(np.uint64(h1), np.uint64(h2))))
        for b in (first, second):
            full = np.flatnonzero(self.table[b] == mark)
            if full.size:
                self.table[b, full[0]] = 0
                return True
        key = (mark, min(first, second))
        if self.spill.get(key, 0):
            self.spill[key] -= 1
            return True
        return False

    def contains(self, h1: np.ndarray, h2: np.ndarray) -> np.ndarray:
        mark, first, second = self._place(h1, h2)
        hit = (self.table[first] == mark[:, None]).any(axis=1) | (self.table[second] == mark[:, None]).any(axis=1)
        if self.spill:
            low = np.minimum(first, second)
            hit |= np.fromiter((self.spill.get((int(m), int(b)), 0) > 0 for m, b in zip(mark, low)), bool, len(mark))
        return hit

    def dump(self) -> bytes:
        rest = np.array([(m, b, n) for (m, b), n in self.spill.items() if n], np.uint64).reshape(-1, 3)
        return np.array([self.buckets, len(rest)], np.uint64).tobytes() + rest.tobytes() + self.table.tobytes()

    @classmethod
    def load(cls, raw: bytes) -> CuckooFilter:
        out = cls.__new__(cls)
        head = np.frombuffer(raw, np.uint64, 2)
        out.buckets, n = int(head[0]), int(head[1])
        rest = np.frombuffer(raw, np.uint64, 3 * n, 16).reshape(-1, 3)
        out.spill = {(int(m), int(b)): int(c) for m, b, c in rest}
        out.table = np.frombuffer(raw, np.uint16, offset=16 + 24 * n).reshape(-1, SLOTS).copy()
        return out


def line_keys(text: str | None, least: int) -> list[bytes | None]:
    """For each line of the text its 128-bit key, None for lines of fewer than `least` code points."""
    out = []
    for raw in (text or "").encode("utf-8", "surrogatepass").split(b"\n"):
        key = raw.strip().lower()  # bytes: ASCII white space and A-Z only
        if len(key) >= least and (len(key) >= 4 * least or len(key.decode("utf-8", "surrogatepass")) >= least):
            out.append(hashlib.blake2b(key, digest_size=16).digest())
        else:
            out.append(None)
    return out


def _references(docs: DataFrame, text_col: str, id_col: str, least: int) -> DataFrame:
    """(h1, h2, doc_id), each key once for each row of docs."""

    def keys(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for start in range(0, batch.num_rows, 256):
                part = batch.slice(start, 256)
                found, rows = [], []
                for i, text in enumerate(part.column(1)):
                    new = {k for k in line_keys(text.as_py(), least) if k}
                    found.extend(new)
                    rows.extend([i] * len(new))
                both = np.frombuffer(b"".join(found), np.int64).reshape(-1, 2)
                yield pa.RecordBatch.from_arrays([pa.array(both[:, 0]), pa.array(both[:, 1]), part.column(0).take(pa.array(rows, pa.int64()))], ["h1", "h2", "doc_id"])
        trim_memory()

    id_type = dict(docs.select(id_col).dtypes)[id_col]
    return docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).cast("string").alias("text")).mapInArrow(keys, f"h1 long, h2 long, doc_id {id_type}")


def _probed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows (shard, salt, filter, h1, h2, doc_id), each shard's filter before its lines: the lines that it lets through. One filter is held at a time."""
    shard, have = None, None
    for batch in batches:
        of, keep = batch.column(0).to_numpy(), np.zeros(batch.num_rows, bool)
        heads = np.flatnonzero(np.asarray(batch.column(2).is_valid()))
        both = np.stack([batch.column(i).fill_null(0).to_numpy() for i in (3, 4)], axis=1).view(np.uint64)
        for low, high in zip([0, *heads.tolist()], [*heads.tolist(), batch.num_rows]):
            if low < high and batch.column(2)[low].is_valid:
                shard, have, low = of[low], CuckooFilter.load(batch.column(2)[low].as_py()), low + 1
            own = np.flatnonzero(of[low:high] == shard) + low if have is not None else np.zeros(0, np.int64)
            if len(own):
                keep[own] = have.contains(both[own, 0], both[own, 1])
        yield batch.select([3, 4, 5]).filter(pa.array(keep))
    trim_memory()


class LineIndex:
    """The state of incremental line dedup in a shared folder: log of references, counts, filters."""

    def __init__(self, spark: SparkSession, folder: str | None = None, least: int = 20, threshold: int = 3, shard_keys: int = SHARD_KEYS, shard_lines: int = SHARD_LINES):
        self.spark, self.folder = spark, folder or scratch_path(spark, "lines")
        self.least, self.threshold, self.shard_keys, self.shard_lines = least, threshold, shard_keys, shard_lines
        self.rounds, self.deletions, self.shards, self.lines = 0, False, 0, 0
        self.repeated: DataFrame | None = None  # (h1, h2, n, top_id) of the keys at the threshold or beyond
        self.filters: DataFrame | None = None  # (shard, filter)
        ship_package(spark)

    def insert(self, docs: DataFrame, text_col: str = "text", id_col: str = "doc_id") -> LineIndex:
        return self._log(docs, text_col, id_col, 1)

    def delete(self, docs: DataFrame, text_col: str = "text", id_col: str = "doc_id") -> LineIndex:
        """Take out documents that were inserted before, with the same texts."""
        self.deletions = True
        return self._log(docs, text_col, id_col, -1)

    def _log(self, docs: DataFrame, text_col: str, id_col: str, sign: int) -> LineIndex:
        moved = _references(docs, text_col, id_col, self.least).withColumn("sign", F.lit(sign))
        with settings(self.spark, SMALL_BATCHES):
            moved.write.option("compression", "zstd").parquet(f"{self.folder}/log/round={self.rounds}")
        self.rounds += 1
        self.lines = self.spark.read.parquet(*(f"{self.folder}/log/round={i}" for i in range(self.rounds))).count()  # from the files' footers
        self._refresh()
        return self

    def counts(self) -> DataFrame:
        """(h1, h2, n, top_id): how many documents hold each key now, and the largest id among them (null ids are the smallest)."""
        log = self.spark.read.parquet(*(f"{self.folder}/log/round={i}" for i in range(self.rounds)))
        if self.deletions:
            log = log.groupBy("h1", "h2", "doc_id").agg(F.sum("sign").alias("sign")).where("sign > 0")
        return log.groupBy("h1", "h2").agg(F.sum("sign").alias("n"), F.max("doc_id").alias("top_id"))

    def _shard(self) -> Column:
        return F.col("h1").bitwiseAND(F.lit(self.shards - 1).cast("long")).cast("int")

    def _refresh(self) -> None:
        """Recount, and bring the filters up to date with the keys that passed the threshold either way."""
        before, self.repeated = self.repeated, materialise(self.counts().where(F.col("n") >= self.threshold), "repeated-keys")
        wanted = 1 << max(0, (self.repeated.count() - 1) // self.shard_keys).bit_length()
        up, down = F.lit(1).alias("move"), F.lit(-1).alias("move")
        now, grown = self.repeated.select("h1", "h2"), wanted > self.shards
        self.shards = max(wanted, self.shards)
        if before is not None and not grown:
            then = before.select("h1", "h2")
            moves = now.join(then, ["h1", "h2"], "left_anti").select("*", up).unionByName(then.join(now, ["h1", "h2"], "left_anti").select("*", down))
            changed = self._built(moves, self.filters)
            if changed.where("filter IS NULL").isEmpty():  # all had room
                self.filters = changed
                return
        self.filters = self._built(now.select("*", up), None)

    def _built(self, moves: DataFrame, old: DataFrame | None) -> DataFrame:
        """The filters after moves(h1, h2, move); a null one has no room left. A shard's keys go to one task: there are as many shards as keep them few."""

        def build(moved: pd.DataFrame, held: pd.DataFrame) -> pd.DataFrame:
            shard = int((moved if len(moved) else held)["shard"].iloc[0])
            into, out = (moved.loc[moved["move"] == m, ["h1", "h2"]].to_numpy(np.int64).view(np.uint64) for m in (1, -1))
            have = CuckooFilter.load(bytes(held["filter"].iloc[0])) if len(held) else CuckooFilter(len(into))
            for a, b in out:
                have.delete(a, b)
            if np.count_nonzero(have.table) + sum(have.spill.values()) + len(into) > 0.95 * have.table.size:
                return pd.DataFrame({"shard": [shard], "filter": [None]})
            have.insert_all(into)
            return pd.DataFrame({"shard": [shard], "filter": [have.dump()]})

        held = old if old is not None else self.spark.createDataFrame([], "shard int, filter binary")
        sharded = moves.withColumn("shard", self._shard())
        with settings(self.spark, SMALL_BATCHES):
            return materialise(sharded.groupBy("shard").cogroup(held.groupBy("shard")).applyInPandas(build, "shard int, filter binary"), "filters")

    def maybe(self, references: DataFrame) -> DataFrame:
        """Of references(h1, h2, doc_id) those that the filters let through."""
        id_type = dict(references.dtypes)["doc_id"]
        # lines of a shard: those of its repeated keys, which may be many, and its even share of all
        share = self.lines / self.shards
        loads = self.repeated.groupBy(self._shard().alias("shard")).agg(F.ceil((F.sum("n") + share) / self.shard_lines).cast("int").alias("salts"))
        heads = self.filters.join(loads, "shard").withColumn("salt", F.explode(F.sequence(F.lit(0), F.col("salts") - 1)))
        none = F.lit(None)
        rows = references.withColumn("shard", self._shard()).join(loads.where("salts > 1"), "shard", "left")
        rows = rows.withColumn("salt", F.coalesce(F.pmod(F.xxhash64("doc_id", "h2"), "salts"), F.lit(0)).cast("int"))
        both = heads.select("shard", "salt", "filter", none.cast("long").alias("h1"), none.cast("long").alias("h2"), none.cast(id_type).alias("doc_id")).unionByName(
            rows.select("shard", "salt", none.cast("binary").alias("filter"), "h1", "h2", "doc_id")
        )
        routed = both.repartition("shard", "salt").sortWithinPartitions("shard", "salt", F.col("filter").isNull())
        return routed.mapInArrow(_probed, f"h1 long, h2 long, doc_id {id_type}")

    def dropped(self, docs: DataFrame, text_col: str = "text", id_col: str = "doc_id") -> DataFrame:
        """(doc_id, drops): for the documents that lose lines, the keys of those."""
        maybe = self.maybe(_references(docs, text_col, id_col, self.least))
        sure = maybe.join(self.repeated.select("h1", "h2", "top_id"), ["h1", "h2"]).where(~F.col("doc_id").eqNullSafe(F.col("top_id")))
        drops = sure.groupBy("doc_id").agg(F.collect_set(F.struct("h1", "h2")).alias("drops"))
        with settings(self.spark, {ROWS_PER_BATCH: "2000"}):
            return materialise(drops, "dropped-lines")

    def apply(self, docs: DataFrame, text_col: str = "text", id_col: str = "doc_id") -> DataFrame:
        """docs with columns __kept (the text without its dropped lines), __n_lines and __n_dropped. Only documents that may lose lines move."""
        least = self.least
        drops = self.dropped(docs, text_col, id_col).withColumnRenamed("doc_id", "__id")

        @F.pandas_udf("kept string, n_lines long, n_dropped long")
        def cut(texts: pd.Series, drops: pd.Series) -> pd.DataFrame:
            out = []
            for text, gone in zip(texts, drops):
                text = text or ""
                lines = text.split("\n")
                if gone is None or not len(gone):
                    out.append((text, len(lines), 0))
                    continue
                keys = {np.array([g["h1"], g["h2"]], np.int64).tobytes() for g in gone}
                stay = [ln for ln, k in zip(lines, line_keys(text, least)) if k not in keys]
                out.append(("\n".join(stay), len(lines), len(lines) - len(stay)))
            return pd.DataFrame(out, columns=["kept", "n_lines", "n_dropped"])

        columns = [F.col(f"`{c}`") for c in docs.columns]
        told = marked(docs, F.xxhash64(F.col(id_col)), drops, F.xxhash64("__id"))
        text = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
        whole = told.where("NOT __maybe").select(*columns, text.alias("__kept"), (F.length(text) - F.length(F.replace(text, F.lit("\n"), F.lit(""))) + 1).cast("long").alias("__n_lines"), F.lit(0).cast("long").alias("__n_dropped"))
        some = told.where("__maybe")
        joined = some.join(drops, some[id_col].eqNullSafe(drops["__id"]), "left").withColumn("__cut", cut(F.col(text_col).cast("string"), F.col("drops")))
        return whole.unionByName(joined.select(*columns, F.col("__cut.kept").alias("__kept"), F.col("__cut.n_lines").alias("__n_lines"), F.col("__cut.n_dropped").alias("__n_dropped")))

    def forget(self) -> None:
        drop_path(self.spark, self.folder)


def dedup_lines(docs: DataFrame, text_col: str = "text", id_col: str = "doc_id", least: int = 20, threshold: int = 3) -> DataFrame:
    """docs with repeated lines left only in the document with the largest id; other columns stay as they are.

    A null or empty text is one empty line (a null stays null only if nothing can be dropped: it becomes empty). Null ids count as documents, smaller than all others.
    Rows repeated under one id are that many documents for the threshold and keep or lose a line together. An empty table stays empty.
    """
    out = LineIndex(docs.sparkSession, least=least, threshold=threshold).insert(docs, text_col, id_col).apply(docs, text_col, id_col)
    return out.select(*[F.col("__kept").alias(c) if c == text_col else F.col(c) for c in docs.columns])


def line_report(docs: DataFrame, text_col: str = "text", id_col: str = "doc_id", least: int = 20, threshold: int = 3) -> DataFrame:
    """One row per input row: doc_id, n_lines (before), n_dropped, kept_sha256 of the lines that stay. Cases as in dedup_lines()."""
    own = docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("text"))
    out = LineIndex(docs.sparkSession, least=least, threshold=threshold).insert(own).apply(own)
    return out.select("doc_id", F.col("__n_lines").alias("n_lines"), F.col("__n_dropped").alias("n_dropped"), F.sha2("__kept", 256).alias("kept_sha256"))
