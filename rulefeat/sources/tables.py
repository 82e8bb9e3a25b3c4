"""Reading tables in several formats, and writing results."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

FORMATS = ("parquet", "orc", "csv", "json", "text")


def read_table(spark: SparkSession, path: str, format: str = "parquet", schema=None, **options) -> DataFrame:
    """Text formats take a schema where one is known, so that no pass is spent on guessing it."""
    if format not in FORMATS:
        raise ValueError(f"format {format!r}")
    reader = spark.read.format(format).options(**({"header": "true"} | options if format == "csv" else options))
    return (reader.schema(schema) if schema is not None else reader).load(path)


def register_views(spark: SparkSession, sf_dir: str, names: list[str]) -> None:
    for n in names:
        spark.read.parquet(f"{sf_dir}/{n}.parquet").createOrReplaceTempView(n)


def save(df: DataFrame, path: str, partition_by: tuple[str, ...] = (), mode: str = "overwrite") -> None:
    writer = df.write.mode(mode).option("compression", "zstd")
    (writer.partitionBy(*partition_by) if partition_by else writer).parquet(path)


def drain(df: DataFrame) -> None:
    """Run a plan to its end without keeping the rows, for timing."""
    df.write.format("noop").mode("overwrite").save()
