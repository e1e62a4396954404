"""A key filter of fixed size: hashed keys set bits of a map that is small enough to broadcast whatever the input.

Rows whose bit is clear have no partner and need no join. Rows whose bit is set go on to the exact join, so a full map
costs time, never rows.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

MARK_BITS = 24


def marks(keys: DataFrame, key: str) -> DataFrame:
    """The bit map of the 64-bit hashes in ``key``: 2**MARK_BITS bits (2 MB) at most, in rows of 4 KB."""
    bit = F.expr(f"shiftrightunsigned(`{key}`, {64 - MARK_BITS})")
    return keys.where(F.col(key).isNotNull()).select(bit.alias("b")).groupBy(F.bitmap_bucket_number("b").alias("bucket")).agg(F.bitmap_construct_agg(F.bitmap_bit_position("b")).alias("map"))


def marked(rows: DataFrame, bits: DataFrame, key: str) -> DataFrame:
    """``rows`` with a boolean ``hit``: false only if the row's key is not among the marked ones."""
    numbered = rows.withColumn("_b", F.expr(f"shiftrightunsigned(`{key}`, {64 - MARK_BITS})")).withColumn("_bucket", F.bitmap_bucket_number("_b"))
    joined = numbered.join(F.broadcast(bits.select(F.col("bucket").alias("_bucket"), F.col("map").alias("_map"))), "_bucket", "left")
    byte = F.conv(F.hex(F.substring("_map", F.expr("cast(bitmap_bit_position(_b) div 8 as int) + 1"), F.lit(1))), 16, 10).cast("int")
    hit = byte.bitwiseAND(F.expr("shiftleft(1, cast(bitmap_bit_position(_b) % 8 as int))")) != 0
    return joined.withColumn("hit", F.coalesce(hit, F.lit(False))).select(*(f"`{c}`" for c in rows.columns), "hit")
