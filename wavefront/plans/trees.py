"""Minimal spanning trees of undirected edge tables (both directions present). Edges are ordered by (cost, ends), so the tree is unique."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from wavefront.operators.components import connected_components
from wavefront.plans.search import rounds_conf
from wavefront.session import cut

def _key() -> Column:
    return F.struct("cost", F.least("fid", "tid").alias("lo"), F.greatest("fid", "tid").alias("hi"))



def prim(edges: DataFrame, root: object) -> DataFrame:
    """``fid, tid, cost`` (fid < tid) of the tree that holds ``root``, a node a round: for small graphs.

    Select takes the open node with the least connecting edge, expand offers its edges, and merge keeps the least
    connecting edge of each node outside the tree; nodes inside are never touched again.
    """
    spark = edges.sparkSession
    order = edges.select("fid", "tid", _key().alias("key"))
    with rounds_conf(spark, 1):
        order = cut(order)
        kind = order.schema["key"].dataType.simpleString()
        id_kind = order.schema["fid"].dataType.simpleString()
        state = cut(spark.createDataFrame([(root,)], f"nid {id_kind}").select("nid", F.lit(None).cast(kind).alias("key"), F.lit(0).alias("f")))
        while True:
            pick = state.where("f = 0").orderBy(F.col("key").asc_nulls_first(), "nid").select("nid").head()
            if pick is None:
                break
            offers = order.where(F.col("fid") == F.lit(pick[0])).select(F.col("tid").alias("nid"), F.col("key").alias("offer"))
            inside = F.when(F.col("nid") == F.lit(pick[0]), 1).otherwise(F.coalesce("f", F.lit(0)))
            lower = F.when((F.coalesce("f", F.lit(0)) == 0) & (F.col("nid") != F.lit(pick[0])), F.least("key", "offer")).otherwise(F.col("key"))
            state = cut(state.join(offers, "nid", "full_outer").select("nid", lower.alias("key"), inside.alias("f")))
    return state.where("key is not null").select(F.col("key.lo").alias("fid"), F.col("key.hi").alias("tid"), F.col("key.cost").alias("cost"))


def boruvka(edges: DataFrame) -> DataFrame:
    """The spanning forest, set-at-a-time: every component takes its least outgoing edge, components that meet merge."""
    spark = edges.sparkSession
    with rounds_conf(spark, edges.count()):
        order = cut(edges.where("fid < tid").select("fid", "tid", "cost"))
        labels = cut(order.select(F.col("fid").alias("node")).union(order.select("tid")).distinct().withColumn("component", F.col("node")))
        tree = None
        while True:
            a, b = labels.select(F.col("node").alias("fid"), F.col("component").alias("ca")), labels.select(F.col("node").alias("tid"), F.col("component").alias("cb"))
            across = order.join(a, "fid").join(b, "tid").where("ca <> cb")
            least = across.select(F.explode(F.array("ca", "cb")).alias("c"), _key().alias("key")).groupBy("c").agg(F.min("key").alias("key"))
            chosen = cut(least.select("key.*").distinct().select(F.col("lo").alias("fid"), F.col("hi").alias("tid"), "cost"))
            if chosen.isEmpty():
                return tree if tree is not None else chosen
            tree = chosen if tree is None else tree.unionByName(chosen)
            links = chosen.join(a, "fid").join(b, "tid").select(F.col("ca").alias("u"), F.col("cb").alias("v"))
            merged = connected_components(links)
            labels = cut(labels.join(merged.select(F.col("node").alias("component"), F.col("component").alias("to")), "component", "left").select("node", F.coalesce("to", "component").alias("component")))
