"""Sets of small numbers as bitmaps: built and united by aggregates inside the JVM."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def bitset_parts(df: DataFrame, keys: list[str], number: str) -> DataFrame:
    """(keys, bucket, bits): a bitmap of the numbers of each group and range of numbers."""
    at = F.col(number).cast("long")
    return df.where(at.isNotNull()).groupBy(*keys, F.bitmap_bucket_number(at).alias("bucket")).agg(F.bitmap_construct_agg(F.bitmap_bit_position(at)).alias("bits"))


def bitset_or(bits: Column | str) -> Column:
    """Aggregate: the union of bitmaps of one bucket."""
    return F.bitmap_or_agg(bits)


def bitset_size(parts: DataFrame, keys: list[str], name: str = "n") -> DataFrame:
    """How many numbers the united bitmaps of each group have."""
    united = parts.groupBy(*keys, "bucket").agg(bitset_or("bits").alias("bits"))
    return united.groupBy(*keys).agg(F.sum(F.bitmap_count("bits")).alias(name))
