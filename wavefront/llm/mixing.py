"""Mixing sources to target shares along a curriculum, in DataFrame functions only.

Targets: sources share the corpus's total size by weight; no target passes ``MOST_PASSES`` times its source's size, and
what is cut off is shared again by weight. That fixed point is found directly: sorted by cap over weight, the first
sources are full and one level of filling serves all others.

Positions: a source's weight over training time t in [0, 1] is piecewise linear. Its integral, scaled to the target,
is the source's cumulative demand; the document whose words stand at offset c of the source's stream is due at the
time when the demand reaches c. The inverse is a quadratic on one piece. Rows are range-sorted by that time.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from wavefront.llm.rownumbers import bucket_count, bucket_of, copied
from wavefront.session import cut

WEIGHTS = (5, 2, 1)
MOST_PASSES = 3
#: Weight over training time, one schedule for each place in WEIGHTS: (time, relative weight) knots.
SCHEDULES = (((0.0, 1.0), (1.0, 1.0)), ((0.0, 0.5), (0.5, 0.75), (1.0, 2.0)), ((0.0, 2.0), (0.25, 1.0), (1.0, 0.5)))
BROADCAST_ROWS = 200_000


def pieces(knots: tuple[tuple[float, float], ...]) -> list[dict]:
    """The schedule's pieces with the share of its integral before (c0) and after (c1) each."""
    parts = [(t0, t1, w0, w1, (t1 - t0) * (w0 + w1) / 2) for (t0, w0), (t1, w1) in zip(knots, knots[1:], strict=False)]
    total, done, out = math.fsum(p[4] for p in parts), 0.0, []
    for k, (t0, t1, w0, w1, area) in enumerate(parts):
        end = 1.0 if k == len(parts) - 1 else done + area / total
        out.append({"t0": t0, "t1": t1, "w0": w0, "w1": w1, "c0": done, "c1": end, "total": total})
        done = end
    return out


def due(share: Column, place: Column) -> Column:
    """When a source of schedule number ``place`` has used up ``share`` (0..1) of its demand."""
    out = F.lit(None).cast("double")
    for k, knots in enumerate(SCHEDULES):
        for p in pieces(knots):
            rest = F.greatest(share - F.lit(p["c0"]), F.lit(0.0)) * F.lit(p["total"])
            slope = (p["w1"] - p["w0"]) / (p["t1"] - p["t0"])
            step = rest / F.lit(p["w0"]) if slope == 0 else (F.sqrt(F.greatest(F.lit(p["w0"] ** 2) + 2 * slope * rest, F.lit(0.0))) - F.lit(p["w0"])) / F.lit(slope)
            out = F.when((place == k) & (share >= p["c0"]) & ((share < p["c1"]) | F.lit(p["c1"] == 1.0)), F.least(F.lit(p["t0"]) + step, F.lit(p["t1"]))).otherwise(out)
    return out


def source_targets(sizes: DataFrame) -> DataFrame:
    """``(source, source_size)`` -> place in the order of sources, weight and target. One row a source."""
    w = len(WEIGHTS)
    order = Window.orderBy(F.col("source").asc_nulls_last())
    t = sizes.withColumn("place", ((F.row_number().over(order) - 1) % w).cast("int"))
    t = t.withColumn("weight", F.element_at(F.array(*map(F.lit, WEIGHTS)), F.col("place") + 1)).withColumn("cap", F.col("source_size") * MOST_PASSES)
    by_level = Window.orderBy(F.col("cap") / F.col("weight"), "place", F.col("source").asc_nulls_last())
    every = Window.partitionBy()
    before = by_level.rowsBetween(Window.unboundedPreceding, -1)
    onward = by_level.rowsBetween(Window.currentRow, Window.unboundedFollowing)
    t = t.withColumn("rest", F.sum("source_size").over(every) - F.coalesce(F.sum("cap").over(before), F.lit(0))).withColumn("open", F.sum("weight").over(onward))
    # the first source whose cap is above its share of what the fuller ones leave is where the level of filling is set
    t = t.withColumn("free", F.col("rest") * F.col("weight") <= F.col("cap") * F.col("open"))
    level = F.first(F.when(F.col("free"), F.struct("rest", "open")), ignorenulls=True).over(by_level.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing))
    t = t.withColumn("level", level)
    shared = F.col("level.rest").cast("double") * F.col("weight") / F.col("level.open")
    full = F.col("level").isNull() | (F.col("cap") * F.col("level.open") < F.col("level.rest") * F.col("weight"))
    return t.select("source", "source_size", "place", "weight", F.when(full, F.col("cap").cast("double")).otherwise(shared).alias("target"))


def words_in(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text.cast("string"), F.lit(r"[^\x20\x09-\x0D]+")), F.lit(0)).cast("long")


def mixed(docs: DataFrame) -> DataFrame:
    """Take documents of ``docs(doc_id, text, source, ...)`` until each source meets its target.

    Returns ``doc_id, size, source_size, target, taken, position, source, passes, place, start``, a row
    for each input row. ``size`` counts words (null text: none). A source is read in an order fixed by a hash of its
    rows, whole passes first; the last pass stops at the target, within a document if need be, so ``taken`` (words,
    repeats counted) sums to the rounded target and never passes MOST_PASSES times the size. ``position`` is when
    the document is first due (null if it is never taken). The null source is a source, last in order; null or
    repeated doc_ids are rows like any other; an empty table gives an empty result.
    """
    slim = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("source").cast("string").alias("source"), words_in(F.col("text")).alias("size"))
    rows = cut(slim.groupBy("doc_id", "source", "size").agg(F.count(F.lit(1)).alias("_n")))
    n = int(rows.agg(F.coalesce(F.sum("_n"), F.lit(0))).first()[0])
    b = bucket_count(n)
    rows = rows.withColumn("_b", bucket_of(b, "doc_id", "source", "size"))
    sums = cut(rows.groupBy("source", "_b").agg(F.sum(F.col("size") * F.col("_n")).alias("_t")))
    targets = source_targets(sums.groupBy("source").agg(F.sum("_t").alias("source_size")))
    before = Window.partitionBy("source").orderBy("_b").rowsBetween(Window.unboundedPreceding, -1)
    firsts = sums.withColumn("_first", F.coalesce(F.sum("_t").over(before), F.lit(0))).drop("_t")
    names = ["source_size", "place", "weight", "target"]
    table = cut(firsts.join(targets.select(F.col("source").alias("_s2"), *names), F.col("source").eqNullSafe(F.col("_s2"))).select(F.col("source").alias("_s"), F.col("_b").alias("_b2"), "_first", *names))
    small = table.count() <= BROADCAST_ROWS
    within = Window.partitionBy("source", "_b").orderBy(F.xxhash64(F.lit(29), "doc_id", "size"), "doc_id", "size").rowsBetween(Window.unboundedPreceding, -1)
    rows = rows.withColumn("_w", F.coalesce(F.sum(F.col("size") * F.col("_n")).over(within), F.lit(0)))
    rows = rows.join(F.broadcast(table) if small else table.hint("merge"), F.col("source").eqNullSafe(F.col("_s")) & (F.col("_b") == F.col("_b2")))
    rows = copied(rows, "_n").withColumn("start", F.col("_first") + F.col("_w") + F.col("_copy") * F.col("size"))
    goal = F.round("target").cast("long")
    passes = F.when(F.col("source_size") > 0, F.expr("cast(round(target) as bigint) div source_size")).otherwise(F.lit(0).cast("long"))
    last = F.greatest(F.lit(0), F.least(F.col("size"), goal - passes * F.col("source_size") - F.col("start")))
    rows = rows.withColumn("taken", passes * F.col("size") + last)
    share = F.col("start") / F.col("target")
    return rows.select("doc_id", "size", "source_size", "target", F.col("taken").cast("long").alias("taken"), F.when(F.col("taken") > 0, due(share, F.col("place"))).alias("position"), "source", passes.alias("passes"), "place", "start")


def mix(docs: DataFrame) -> DataFrame:
    """``mixed`` without its helper columns, range-sorted by position."""
    return mixed(docs).orderBy("position", "doc_id", "start").drop("place", "start")


def training_order(docs: DataFrame) -> DataFrame:
    """The rows of ``docs``, with their own columns, as often as the mix takes them and in training order.

    A document taken in part counts as taken once more if half its words or more are; wordless documents carry no
    demand and are not taken. Equal rows share what their numbers take.
    """
    m = mixed(docs)
    copies = F.floor(F.col("taken") / F.col("size") + 0.5).cast("int")
    m = m.where("size > 0").withColumn("_copies", copies).where("_copies > 0")
    m = m.withColumn("_rank", F.row_number().over(Window.partitionBy("doc_id", "source", "size").orderBy("start")))
    m = m.select(F.col("doc_id").alias("_d"), F.col("source").alias("_s"), F.col("size").alias("_z"), "_rank", "source_size", "target", "place", "start", F.explode(F.sequence(F.lit(0), F.col("_copies") - 1)).alias("_pass"))
    m = m.withColumn("_position", due(F.least((F.col("start") + F.col("_pass") * F.col("source_size")) / F.col("target"), F.lit(1.0)), F.col("place")))
    row = docs.select(F.struct("*").alias("row"))  # own columns may bear any name
    keyed = row.select("row", F.col("row.doc_id").cast("long").alias("_did"), F.col("row.source").cast("string").alias("_src"), words_in(F.col("row.text")).alias("_size"))
    twins = Window.partitionBy("_did", "_src", "_size").orderBy(F.xxhash64("row.text"))
    keyed = keyed.withColumn("_own", F.row_number().over(twins))
    same = F.col("_did").eqNullSafe(F.col("_d")) & F.col("_src").eqNullSafe(F.col("_s")) & (F.col("_size") == F.col("_z")) & (F.col("_own") == F.col("_rank"))
    return keyed.join(m.hint("merge"), same).select("row", "_position", "_d", "_pass").orderBy("_position", "_d", "_pass").select("row.*")
