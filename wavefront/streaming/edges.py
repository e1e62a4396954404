"""Edges from the event stream: de-duplicated arrivals, windowed counts, late rows, and state that links a user's successive events."""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from wavefront.session import cut, shared_folder

SCHEMA = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def read_events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The events table as a stream; watermarks want a timestamp with a zone."""
    raw = spark.readStream.schema(SCHEMA).option("pathGlobFilter", "events*").parquet(sf_dir)
    return raw.withColumn("ts", F.col("ts").cast("timestamp"))


def run(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Run over all that is there and return the table it made. Files of both kinds lie in the shared folder."""
    spark = stream.sparkSession
    base = f"{shared_folder(spark)}/stream-{uuid.uuid4().hex}"

    def keep(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{base}/out/batch={number}")

    query = stream.writeStream.outputMode(mode).foreachBatch(keep).option("checkpointLocation", f"{base}/state").trigger(availableNow=True).start()
    query.awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{base}/out")


def distinct_events(stream: DataFrame) -> DataFrame:
    return stream.withWatermark("ts", "1 day").dropDuplicatesWithinWatermark(["event_id"])


def windows(stream: DataFrame, width: str, slide: str | None = None) -> DataFrame:
    w = F.window("ts", width, slide) if slide else F.window("ts", width)
    counted = stream.withWatermark("ts", "365 days").groupBy(w.alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n"))
    return counted.select(F.col("w.start").alias("start"), "event_type", "n")


def sessions(stream: DataFrame, gap: str) -> DataFrame:
    counted = stream.withWatermark("ts", "365 days").groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count(F.lit(1)).alias("n"))
    return counted.select("user_id", F.col("w.start").alias("start"), "n")


def previous_events(stream: DataFrame) -> DataFrame:
    """``event_id, user_id, previous``: a user's event before each event. The state holds one event id a user, so it grows
    with the users and not with the events; a batch's events of one user are put in order, batches come as they come."""

    def step(key: tuple, parts: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        rows = pd.concat(list(parts)).sort_values(["ts", "event_id"])
        ids = rows["event_id"].tolist()
        before = [state.get[0] if state.exists else None, *ids[:-1]]
        state.update((ids[-1],))
        yield pd.DataFrame({"event_id": ids, "user_id": key[0], "previous": pd.array(before, dtype="Int64")})

    slim = stream.select("event_id", "ts", "user_id")
    return slim.groupBy("user_id").applyInPandasWithState(step, "event_id long, user_id long, previous long", "last long", "append", GroupStateTimeout.NoTimeout)


def count_late(spark: SparkSession, sf_dir: str, delay: str) -> int:
    """Events that a watermark ``delay`` behind the latest event would drop, counted beside the stream by an observation."""
    from pyspark.sql import Observation

    latest = spark.read.schema(SCHEMA).option("pathGlobFilter", "events*").parquet(sf_dir).agg(F.max(F.col("ts").cast("timestamp"))).first()[0]
    late = F.col("ts") < F.lit(latest) - F.expr(f"interval {delay}")
    seen: list[int] = []

    def count(batch: DataFrame, number: int) -> None:
        watch = Observation()
        batch.observe(watch, F.count(F.when(late, 1)).alias("late")).write.format("noop").mode("overwrite").save()
        seen.append(watch.get["late"])

    state = f"{shared_folder(spark)}/late-{uuid.uuid4().hex}"
    read_events(spark, sf_dir).writeStream.foreachBatch(count).option("checkpointLocation", state).trigger(availableNow=True).start().awaitTermination()
    return sum(seen)


def maintain(spark: SparkSession, stream: DataFrame, merge: Callable[[DataFrame], None], state: str) -> None:
    """Hand each micro-batch of edges ``(fid, tid, cost)`` to ``merge``, such as ``segments.apply_inserts`` and a save."""
    query = stream.writeStream.foreachBatch(lambda batch, _: merge(batch)).option("checkpointLocation", state).trigger(availableNow=True).start()
    query.awaitTermination()
