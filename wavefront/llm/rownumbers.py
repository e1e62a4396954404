"""Gapless numbers for the rows of a table, in DataFrame functions only.

Rows are dealt into buckets by a hash of their key; a bucket's rows are numbered by a window of its own and the
buckets' totals, at most ``MOST_BUCKETS`` rows whatever the input, are summed up to give each its first number. Equal
rows are counted first, so one repeated row is one row of the window.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from wavefront.session import cut

ROWS_A_BUCKET = 20_000
MOST_BUCKETS = 4096
PIECE = 4096


def bucket_count(rows: int) -> int:
    return max(1, min(MOST_BUCKETS, -(-rows // ROWS_A_BUCKET)))


def bucket_of(buckets: int, *keys: str) -> Column:
    return F.pmod(F.xxhash64(F.lit(17), *keys), F.lit(buckets)).cast("int")


def copied(rows: DataFrame, times: str) -> DataFrame:
    """Each row as often as column ``times`` says, with ``_copy`` 0, 1, ...; in pieces, so no array grows with the copies."""
    pieces = rows.withColumn("_piece", F.explode(F.expr(f"sequence(0L, ({times} - 1) div {PIECE})")))
    within = F.expr(f"sequence(_piece * {PIECE}, least(_piece * {PIECE} + {PIECE}, {times}) - 1)")
    return pieces.withColumn("_copy", F.explode(within)).drop("_piece")


def numbered(df: DataFrame, name: str = "row_number") -> tuple[DataFrame, int]:
    """``df`` (any columns that can be grouped by) with numbers 0..n-1 in ``name``, and n. Equal rows are
    interchangeable; the numbering depends on nothing but the rows."""
    keys = df.columns
    counted = cut(df.groupBy(*keys).agg(F.count(F.lit(1)).alias("_n")))
    n = int(counted.agg(F.coalesce(F.sum("_n"), F.lit(0))).first()[0])
    b = bucket_count(n)
    rows = counted.withColumn("_b", bucket_of(b, *keys))
    totals = rows.groupBy("_b").agg(F.sum("_n").alias("_t"))
    before = Window.orderBy("_b").rowsBetween(Window.unboundedPreceding, -1)
    first = totals.select("_b", F.coalesce(F.sum("_t").over(before), F.lit(0)).alias("_first"))
    within = Window.partitionBy("_b").orderBy(*keys).rowsBetween(Window.unboundedPreceding, -1)
    start = rows.withColumn("_s", F.coalesce(F.sum("_n").over(within), F.lit(0))).join(F.broadcast(first), "_b")
    return copied(start, "_n").select(*keys, (F.col("_first") + F.col("_s") + F.col("_copy")).alias(name)), n
