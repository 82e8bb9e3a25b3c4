"""Synthetic binary tables with planted rules: as DataFrame expressions, and as a batch data source for spark.read."""

from __future__ import annotations

import random
from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

RATE = 0.3  # of x1 in the planted table
NOISE = 0.05


def planted_rules(spark: SparkSession, rows: int = 1000, p: int = 99, trials: int = 1, constant: bool = False, seed: int = 1) -> DataFrame:
    """(trial, x1..xp, y): x1 is 1 with chance 0.3, the others with 1/2; label 0 where x1 is 0, 2 where x1, x2 and x3 are all 1, else 1.

    A twentieth of the labels is drawn anew among the three. constant: the last two columns are always 1.
    """
    base = spark.range(rows * trials).withColumn("trial", (F.col("id") / rows).cast("int"))
    chance = [RATE, *[0.5] * (p - 1)]
    if constant:
        chance[-2:] = [1.1, 1.1]
    xs = base.select("id", "trial", *[(F.rand(seed * 1000 + i) < c).cast("int").cast("string").alias(f"x{i}") for i, c in enumerate(chance, 1)], F.rand(seed * 1000).alias("u"), F.floor(F.rand(seed * 1000 - 1) * 3).cast("string").alias("other"))
    clean = F.when(F.col("x1") == "0", "0").when((F.col("x2") == "1") & (F.col("x3") == "1"), "2").otherwise("1")
    return xs.withColumn("y", F.when(F.col("u") < NOISE, F.col("other")).otherwise(clean)).drop("u", "other", "id")


def frequent_sets(spark: SparkSession, rows: int = 10_000, p: int = 10, seed: int = 1) -> DataFrame:
    """Binary features for frequency estimates: x1 at 0.9, x2 at 75/90 where x1 is 1 and 1/2 elsewhere, x3 at 0.7, the rest at 1/2; one label."""
    u = [F.rand(seed * 1000 + i) for i in range(p + 1)]
    base = spark.range(rows).select(*[u[i].alias(f"u{i}") for i in range(1, p + 1)]).withColumn("x1", (F.col("u1") < 0.9).cast("int"))
    base = base.withColumn("x2", F.when(F.col("x1") == 1, F.col("u2") < 75 / 90).otherwise(F.col("u2") < 0.5).cast("int")).withColumn("x3", (F.col("u3") < 0.7).cast("int"))
    base = base.withColumns({f"x{i}": (F.col(f"u{i}") < 0.5).cast("int") for i in range(4, p + 1)})
    return base.select(*[F.col(f"x{i}").cast("string").alias(f"x{i}") for i in range(1, p + 1)], F.lit("all").alias("y"))


class _Part(InputPartition):
    def __init__(self, number: int, rows: int):
        self.number, self.rows = number, rows


class _Reader(DataSourceReader):
    def __init__(self, options):
        self.rows, self.p = int(options.get("rows", "1000")), int(options.get("p", "10"))
        self.parts, self.seed = int(options.get("partitions", "4")), int(options.get("seed", "1"))

    def partitions(self):
        each = [self.rows // self.parts + (i < self.rows % self.parts) for i in range(self.parts)]
        return [_Part(i, n) for i, n in enumerate(each)]

    def read(self, partition: _Part) -> Iterator[tuple]:
        draw = random.Random(self.seed * 100_003 + partition.number)
        for _ in range(partition.rows):
            x = [int(draw.random() < RATE), *(int(draw.random() < 0.5) for _ in range(self.p - 1))]
            y = draw.randrange(3) if draw.random() < NOISE else 0 if not x[0] else 2 if x[1] and x[2] else 1
            yield (*map(str, x), str(y))


class PlantedRulesSource(DataSource):
    """spark.read.format("planted_rules").option("rows", ...).option("p", ...).load() after register_sources()."""

    @classmethod
    def name(cls) -> str:
        return "planted_rules"

    def schema(self) -> str:
        return ", ".join([*(f"x{i} string" for i in range(1, int(self.options.get("p", "10")) + 1)), "y string"])

    def reader(self, schema):
        return _Reader(self.options)


def register_sources(spark: SparkSession) -> None:
    spark.dataSource.register(PlantedRulesSource)
