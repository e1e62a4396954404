"""Shards by a keyed permutation of global row numbers: a reproducible shuffle whose shard and slot are computed.

A number x below n is split as x = left + a * right with a * b >= n just covering it; rounds add a keyed hash of one
half to the other, modulo a or b, which permutes 0..a*b-1. Where the result is n or more it is permuted again (cycle
walking), so 0..n-1 is permuted. a*b - n is below a, so a second walk has a chance of about 1/sqrt(n); the walks of one
number are bounded by ``MOST_WALKS``, and a number still outside then is an error, never a wrong place.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from wavefront.llm.rownumbers import numbered

ROUNDS = 6
MOST_WALKS = 64


def _round(state: Column, k: Column, a: int, b: int, seed: int) -> Column:
    left, right = state["l"], state["r"]
    to_left = F.pmod(left + F.pmod(F.xxhash64(F.lit(seed), k, right), F.lit(a)), F.lit(a))
    to_right = F.pmod(right + F.pmod(F.xxhash64(F.lit(seed), k, left), F.lit(b)), F.lit(b))
    even = k % 2 == 0
    return F.struct(F.when(even, to_left).otherwise(left).alias("l"), F.when(even, right).otherwise(to_right).alias("r"))


def permuted(x: Column, n: int, seed: int) -> Column:
    """A permutation of 0..n-1, keyed by ``seed``."""
    a = max(1, math.isqrt(max(n - 1, 0)) + 1)
    b = max(1, -(-n // a))
    once = lambda y: F.aggregate(
        F.sequence(F.lit(0), F.lit(ROUNDS - 1)),
        F.struct((y % a).cast("long").alias("l"), F.floor(y / a).cast("long").alias("r")),
        lambda s, k: _round(s, k, a, b, seed),
        lambda s: s["l"] + F.lit(a).cast("long") * s["r"],
    )
    walks = min(a * b - n + 1, MOST_WALKS)
    if a * b <= n:
        return once(x)
    inside = lambda z: F.when(z < n, z).otherwise(F.raise_error(F.lit(f"a row number is still outside after {walks} walks")).cast("long"))
    return F.aggregate(F.sequence(F.lit(1), F.lit(walks)), once(x), lambda z, _: F.when(z >= n, once(z)).otherwise(z), inside)


def shard(docs: DataFrame, shards: int = 40, seed: int = 20240607) -> DataFrame:
    """Deal the rows of ``docs(doc_id, text, ...)`` into ``shards`` shards whose row counts differ by one at most.

    Returns ``doc_id, size, text_crc32, law, shard, slot, grown_shard, row_number, position``: position is the row's
    place in the shuffle, shard = position mod shards, slot = position div shards. Null texts count as empty; null or
    repeated doc_ids are rows like any other and equal rows are interchangeable; other columns are ignored; an empty
    table gives an empty result.
    """
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    slim = docs.select(F.col("doc_id").cast("long").alias("doc_id"), (F.octet_length(text) + F.lit(16)).cast("long").alias("size"), F.crc32(F.encode(text, "UTF-8")).alias("text_crc32"))
    rows, n = numbered(slim)
    placed = rows.withColumn("position", permuted(F.col("row_number"), n, seed))
    return placed.select("doc_id", "size", "text_crc32", F.lit("rows").alias("law"), (F.col("position") % shards).cast("int").alias("shard"), F.expr(f"position div {shards}").alias("slot"), F.lit(None).cast("int").alias("grown_shard"), "row_number", "position")
