"""Given tables and edge lists as DataFrames; sinks for edges."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def edges(df: DataFrame, fid: str | Column = "fid", tid: str | Column = "tid", cost: str | Column = "cost", undirected: bool = False) -> DataFrame:
    """An edge table ``fid, tid, cost``: self-loops go, the least of parallel edges stays, undirected ones are doubled.

    Null or negative weights and null ends are refused when rows are read: a search over them would be wrong.
    """
    e = df.select(*(F.col(c).alias(n) if isinstance(c, str) else c.alias(n) for c, n in ((fid, "fid"), (tid, "tid"), (cost, "cost"))))
    good = F.col("fid").isNotNull() & F.col("tid").isNotNull() & F.col("cost").isNotNull() & (F.col("cost") >= 0)
    e = e.where(F.when(good, True).otherwise(F.raise_error(F.lit("an edge has a null end or a null or negative weight")).cast("boolean")))
    if undirected:
        e = e.unionByName(e.select(F.col("tid").alias("fid"), F.col("fid").alias("tid"), "cost"))
    return e.where("fid <> tid").groupBy("fid", "tid").agg(F.min("cost").alias("cost"))


def from_rows(spark: SparkSession, rows: list[tuple], kind: str = "fid string, tid string, cost long") -> DataFrame:
    return spark.createDataFrame(rows, kind)


def read_edges(spark: SparkSession, form: str, path: str, schema: str = "fid long, tid long, cost long", **options: str) -> DataFrame:
    """``form``: parquet, orc, csv, json (schema declared, never inferred)."""
    return spark.read.format(form).schema(schema).options(**options).load(path)


def read_edges_jdbc(spark: SparkSession, url: str, name: str, column: str, low: int, high: int, parts: int) -> DataFrame:
    return spark.read.jdbc(url, name, column=column, lowerBound=low, upperBound=high, numPartitions=parts)


def write_edges(df: DataFrame, path: str, form: str = "parquet", parts: int | None = None) -> None:
    """Edges in files; with ``parts`` laid out by a hash of ``fid`` and sorted, so a frontier reads few of them."""
    if parts:
        laid = df.withColumn("part", F.pmod(F.xxhash64("fid"), F.lit(parts)).cast("int"))
        laid.repartition("part").sortWithinPartitions("part", "fid").write.partitionBy("part").format(form).mode("overwrite").save(path)
    else:
        df.write.format(form).mode("overwrite").save(path)


def merge_into(df: DataFrame, target: str) -> None:
    """Lower weights into a catalog table that supports row-level merges."""
    df.alias("new").mergeInto(target, F.expr(f"new.fid = {target}.fid and new.tid = {target}.tid")).whenMatched(F.expr(f"new.cost < {target}.cost")).updateAll().whenNotMatched().insertAll().merge()
