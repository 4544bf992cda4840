"""Bit functions for sets over small dense domains."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def bitmap_sizes(df: DataFrame, key: str, value: str) -> DataFrame:
    """(key, n): distinct values per key by fixed-size bitmaps; values count from 0 and are shifted, as bit 0 of bucket 0 is value 0's."""
    v = F.col(value) + 1
    part = df.groupBy(key, F.bitmap_bucket_number(v).alias("bucket")).agg(F.bitmap_construct_agg(F.bitmap_bit_position(v)).alias("bits"))
    return part.groupBy(key).agg(F.sum(F.bitmap_count("bits")).cast("long").alias("n"))


def bit_positions(bits: Column) -> Column:
    return F.filter(F.sequence(F.lit(0), F.lit(63)), lambda i: F.getbit(bits, i) == 1)
