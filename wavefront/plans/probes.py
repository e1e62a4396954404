"""Instruments: what a run costs in jobs and bytes, and the loop with its three operators materialised one by one."""

from __future__ import annotations

import contextlib
import time
import uuid
from collections.abc import Iterator
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from wavefront.operators import steps
from wavefront.plans.search import rounds_conf
from wavefront.session import cut


@dataclass
class Cost:
    """Of the Spark jobs that a block has started on this thread."""

    jobs: int = 0
    seconds: float = 0.0
    shuffle_bytes: int = 0
    spilled_bytes: int = 0


@contextlib.contextmanager
def watched(spark: SparkSession) -> Iterator[Cost]:
    """Count jobs and add up the bytes that their stages have shuffled and spilled, from Spark's own status store."""
    sc, group, cost = spark.sparkContext, f"wavefront-{uuid.uuid4().hex}", Cost()
    sc.setJobGroup(group, "watched")
    began = time.time()
    try:
        yield cost
    finally:
        cost.seconds = time.time() - began
        sc.setLocalProperty("spark.jobGroup.id", None)  # type: ignore[arg-type]
        sc._jsc.sc().listenerBus().waitUntilEmpty()
        tracker, store = sc.statusTracker(), sc._jsc.sc().statusStore()
        jobs = [tracker.getJobInfo(j) for j in tracker.getJobIdsForGroup(group)]
        cost.jobs = len(jobs)
        for stage in {k for j in jobs if j for k in j.stageIds}:
            info = tracker.getStageInfo(stage)
            if info and info.numCompletedTasks:  # a skipped stage has no attempt
                data = store.lastStageAttempt(stage)
                cost.shuffle_bytes += data.shuffleWriteBytes()
                cost.spilled_bytes += data.diskBytesSpilled()


def stepwise(edges: DataFrame, sources: DataFrame, kind: str = "level", expand: str = "argmin", merge: str = "single", limit: float | None = None, most: int = 100_000) -> tuple[DataFrame, DataFrame]:
    """Single-direction search from ``sources(qid, s)`` with select, expand and merge each materialised and timed.

    Returns the visited table ``(qid, nid, d, p, f)`` and ``(round, operator, rows, seconds)``; the rows of select are
    the frontier, of expand its candidates, of merge the visited rows that it has added or lowered.
    """
    spark = edges.sparkSession
    id_kind, cost_kind = edges.schema["fid"].dataType, edges.schema["cost"].dataType
    log: list[tuple[int, str, int, float]] = []

    def step(number: int, name: str, df: DataFrame) -> tuple[DataFrame, int]:
        began = time.time()
        df = cut(df)
        n = df.count()
        log.append((number, name, n, time.time() - began))
        return df, n

    with rounds_conf(spark, edges.count()):
        visited = cut(sources.select(F.col("qid").cast("long").alias("qid"), F.col("s").cast(id_kind).alias("nid"), F.lit(0).cast(cost_kind).alias("d"), F.lit(None).cast(id_kind).alias("p"), F.lit(steps.OPEN).cast("byte").alias("f")))
        for number in range(1, most + 1):
            front, n = step(number, "select", steps.select_frontier(visited, kind))
            if not n:
                log.pop()
                break
            cand, _ = step(number, "expand", steps.expand(front, edges, expand, limit))
            closed = visited.join(front.select("qid", "nid", F.lit(steps.CLOSED).cast("byte").alias("now")), ["qid", "nid"], "left").withColumn("f", F.coalesce("now", "f")).drop("now")
            began = time.time()
            merged = cut(steps.merge(closed, cand, merge))
            seconds = time.time() - began
            old = visited.select("qid", "nid", F.col("d").alias("was"))
            affected = merged.join(old, ["qid", "nid"], "left").where("was is null or d < was").count()
            log.append((number, "merge", affected, seconds))
            visited = merged
        else:
            raise RuntimeError(f"nodes are still open after {most} rounds")
    return visited, spark.createDataFrame(log, "round int, operator string, rows long, seconds double")
