"""Shared scratch tables, and shipping of this package to the executors."""

from __future__ import annotations

import os
import tempfile
import threading
import uuid
import zipfile

from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession

_LOCAL_FALLBACK: list[str] = []
_SHIPPED: set[str] = set()
_SHIPPING = threading.Lock()


def scratch_root(spark: SparkSession) -> str:
    """The shared folder the cluster names; a local one only where none is named and all runs on one machine (tests)."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named.rstrip("/")
    if not spark.sparkContext.master.startswith("local"):
        raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
    if not _LOCAL_FALLBACK:
        _LOCAL_FALLBACK.append("file://" + os.path.realpath(tempfile.mkdtemp(prefix="rulefeat-")))
    return _LOCAL_FALLBACK[0]


def _hadoop_path(spark: SparkSession, path: str):
    target = spark._jvm.org.apache.hadoop.fs.Path(path)
    return target.getFileSystem(spark._jsc.hadoopConfiguration()), target


def scratch_path(spark: SparkSession, label: str) -> str:
    """A new folder name below the shared folder; it goes when the driver ends."""
    path = f"{scratch_root(spark)}/rulefeat-{label}-{uuid.uuid4().hex}"
    fs, target = _hadoop_path(spark, path)
    fs.deleteOnExit(target)
    return path


def drop_path(spark: SparkSession, path: str) -> None:
    fs, target = _hadoop_path(spark, path)
    fs.delete(target, True)


@contextmanager
def settings(spark: SparkSession, wanted: dict[str, str]):
    """Session settings for the actions inside the block; those of before come back after it."""
    before = {k: spark.conf.get(k, None) for k in wanted}
    for k, v in wanted.items():
        spark.conf.set(k, v)
    try:
        yield
    finally:
        for k, v in before.items():
            if v is None:
                spark.conf.unset(k)
            else:
                spark.conf.set(k, v)


ROWS_PER_BATCH = "spark.sql.execution.arrow.maxRecordsPerBatch"
#: Batches of few rows to and from Python, for columns of whole texts or payloads.
SMALL_BATCHES = {ROWS_PER_BATCH: "500"}
#: For tables of rows of up to megabytes each: how many go to Python, or out of a file, at once (else 4096 out of a file), and how writers keep pages and row groups small (else they look at their sizes every 100 rows).
BLOCK_READS = {ROWS_PER_BATCH: "4", "spark.sql.parquet.columnarReaderBatchSize": "4"}
BLOCK_WRITES = {"parquet.page.size.row.check.min": "1", "parquet.block.size.row.check.min": "1", "parquet.block.size": str(1 << 24)}
#: Bytes up to which a side of a join may go through the driver in operators over whole corpora.
BROADCAST = 1 << 18


def small_broadcasts(spark: SparkSession) -> dict[str, str]:
    """Settings that keep all but small sides of joins off the driver: the engine's estimates don't see how many rows explode() makes, or how much a compressed file holds."""
    least = min(BROADCAST, spark._jsparkSession.sessionState().conf().autoBroadcastJoinThreshold())
    return {"spark.sql.autoBroadcastJoinThreshold": str(least), "spark.sql.adaptive.autoBroadcastJoinThreshold": str(least)}


def materialise(df: DataFrame, label: str, compression: str = "zstd", path: str | None = None, options: dict[str, str] | None = None) -> DataFrame:
    """Write df to the shared folder (or to `path`, where it stays) and read it back: lineage ends there, any executor can be lost."""
    spark = df.sparkSession
    path = path or scratch_path(spark, label)
    df.write.options(compression=compression, **(options or {})).parquet(path)
    back = spark.read.schema(df.schema).parquet(path)
    back._scratch_path = path
    return back


def release(df: DataFrame) -> None:
    """Delete the table behind a materialise() result that no later plan reads."""
    path = getattr(df, "_scratch_path", None)
    if path:
        drop_path(df.sparkSession, path)


def trim_memory() -> None:
    """In a Python worker at a task's end: give freed memory back to the system, as idle workers stay alive."""
    import ctypes
    import gc

    import pyarrow

    gc.collect()
    pyarrow.default_memory_pool().release_unused()
    try:
        ctypes.CDLL("libc.so.6").malloc_trim(0)
    except (OSError, AttributeError):  # another C library
        pass


def ship_package(spark: SparkSession) -> None:
    """Make the session ready for Python operators over whole texts.

    The executors get this package as a zip file, once per application; and where batches to Python are left at Spark's
    default of ten thousand rows, they become a thousand, so that a worker's memory doesn't hang on the length of texts.
    """
    if spark.conf.get(ROWS_PER_BATCH, "10000") == "10000":
        spark.conf.set(ROWS_PER_BATCH, "1000")
    with _SHIPPING:  # drivers of independent jobs come here from several threads, and a second file of the name is an error
        _ship(spark)


def _ship(spark: SparkSession) -> None:
    app = spark.sparkContext.applicationId
    if app in _SHIPPED:
        return
    here = os.path.dirname(os.path.abspath(__file__))
    folder = os.path.realpath(tempfile.mkdtemp(prefix="rulefeat-zip-"))
    target = os.path.join(folder, "rulefeat_package.zip")
    with zipfile.ZipFile(target, "w", zipfile.ZIP_DEFLATED) as packed:
        for top, _, names in os.walk(here):
            for name in names:
                if name.endswith(".py"):
                    full = os.path.join(top, name)
                    packed.write(full, os.path.relpath(full, os.path.dirname(here)))
    spark.sparkContext.addPyFile(target)
    _SHIPPED.add(app)
