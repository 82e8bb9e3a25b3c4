"""A table of bits of fixed size that tells which rows a set of keys may concern, so that only those rows move."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

BITS = 24  # at most 512 words of 4 KiB, whatever the number of keys


def _place(key: Column) -> Column:
    # never null, so that no filter for nulls works the key out a second time below a join
    return F.coalesce(key.cast("long"), F.lit(0)).bitwiseAND((1 << BITS) - 1)


def marked(rows: DataFrame, key: Column, wanted: DataFrame, wanted_key: Column, name: str = "__maybe") -> DataFrame:
    """rows with a boolean column: false only where the row's key (a long, spread like a hash) isn't among wanted's. The table of bits is broadcast.

    With more keys than bits all rows are true: the table then saves nothing, and changes nothing.
    """
    one_on = _place(wanted_key) + 1  # Spark's bitmaps number bits from 1, and hold 2^15 of them in a word
    words = wanted.select(one_on.alias("p")).groupBy(F.bitmap_bucket_number("p").alias("__word")).agg(F.bitmap_construct_agg(F.bitmap_bit_position("p")).alias("__bits"))
    met = rows.select("*", _place(key).alias("__place")).join(F.broadcast(words), F.shiftright("__place", 15) + 1 == F.col("__word"), "left")
    byte = F.conv(F.hex(F.expr("substring(__bits, cast(shiftright(__place & 32767, 3) as int) + 1, 1)")), 16, 10).cast("int")
    bit = F.expr("shiftleft(1, cast(__place & 7 as int))").bitwiseAND(byte) != 0
    return met.select(*[F.col(f"`{c}`") for c in rows.columns], F.coalesce(bit, F.lit(False)).alias(name))
