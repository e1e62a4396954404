"""Graphs derived from the given tables, in whole-number arithmetic so that another engine rebuilds them exactly."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from wavefront.sources.tables import edges, table


def _chain(spark: SparkSession, sf_dir: str, key: str, k: int) -> DataFrame:
    """Each order's lines in a total order, a line's key linked to the next one's."""
    line = table(spark, sf_dir, "lineitem").where(F.col("l_orderkey") % k == 0)
    order = Window.partitionBy("l_orderkey").orderBy("l_linenumber", "l_partkey", "l_suppkey", "l_quantity", "l_extendedprice")
    linked = line.select(F.col(key).alias("fid"), F.lead(key).over(order).alias("tid"), F.col("l_quantity").cast("long").alias("cost"))
    return linked.where("tid is not null")


def random_graph(spark: SparkSession, sf_dir: str, k: int = 8) -> DataFrame:
    return edges(_chain(spark, sf_dir, "l_partkey", k))


def power_graph(spark: SparkSession, sf_dir: str, k: int = 8) -> DataFrame:
    """Ends skewed towards small ids: in-degree falls with the square root of the rank."""
    n = table(spark, sf_dir, "part").agg(F.count(F.lit(1)).alias("n"))
    e = _chain(spark, sf_dir, "l_partkey", k).crossJoin(F.broadcast(n))
    return edges(e.select("fid", F.expr("tid * tid div n").alias("tid"), "cost"))


def co_order_graph(spark: SparkSession, sf_dir: str, k: int = 8) -> DataFrame:
    line = table(spark, sf_dir, "lineitem").where(F.col("l_orderkey") % k == 0).select("l_orderkey", "l_partkey").distinct()
    pair = line.alias("a").join(line.alias("b"), "l_orderkey").where("a.l_partkey < b.l_partkey")
    pair = pair.select(F.col("a.l_partkey").alias("fid"), F.col("b.l_partkey").alias("tid"))
    return edges(pair.withColumn("cost", (1 + (F.col("fid") + F.col("tid")) % 50).cast("long")), undirected=True)


def web_graph(spark: SparkSession, sf_dir: str) -> DataFrame:
    page = table(spark, sf_dir, "pages").select("page_id", F.explode(F.array_distinct(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1)))).alias("href"))
    cost = (1 + (F.col("page_id") * 31 + F.length("href")) % 30).cast("long")
    return edges(page.select(F.concat(F.lit("p:"), F.col("page_id").cast("string")).alias("fid"), F.concat(F.lit("h:"), "href").alias("tid"), cost.alias("cost")), undirected=True)


def nation_graph(spark: SparkSession, sf_dir: str) -> DataFrame:
    t = lambda n: table(spark, sf_dir, n)
    line = t("lineitem").select("l_orderkey", "l_suppkey", F.col("l_quantity").cast("long").alias("q"))
    line = line.join(t("orders").select(F.col("o_orderkey").alias("l_orderkey"), "o_custkey"), "l_orderkey")
    line = line.join(t("customer").select(F.col("c_custkey").alias("o_custkey"), F.col("c_nationkey").cast("long").alias("fid")), "o_custkey")
    line = line.join(t("supplier").select(F.col("s_suppkey").alias("l_suppkey"), F.col("s_nationkey").cast("long").alias("tid")), "l_suppkey")
    weight = line.groupBy("fid", "tid").agg((F.sum("q") % 97 + 1).alias("cost"))
    return edges(weight.where("cost <= 25"))


def nation_undirected(spark: SparkSession, sf_dir: str) -> DataFrame:
    return edges(nation_graph(spark, sf_dir), undirected=True)


def supplier_graph(spark: SparkSession, sf_dir: str, k: int = 64) -> DataFrame:
    return edges(_chain(spark, sf_dir, "l_suppkey", k))


def trade_graph(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Customers (even ids) and the parts they bought (odd ids); weight: the least quantity."""
    line = table(spark, sf_dir, "lineitem").select(F.col("l_orderkey").alias("o_orderkey"), "l_partkey", F.col("l_quantity").cast("long").alias("cost"))
    pair = line.join(table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey"), "o_orderkey")
    return edges(pair.select((F.col("o_custkey") * 2).alias("fid"), (F.col("l_partkey") * 2 + 1).alias("tid"), "cost"), undirected=True)


def event_graph(spark: SparkSession, sf_dir: str) -> DataFrame:
    order = Window.partitionBy("user_id").orderBy("ts", "event_id")
    e = table(spark, sf_dir, "events").select(F.col("event_id").alias("fid"), F.lead("event_id").over(order).alias("tid"), "ts", F.lead("ts").over(order).alias("next"))
    seconds = F.unix_timestamp(F.col("next").cast("timestamp")) - F.unix_timestamp(F.col("ts").cast("timestamp"))
    return edges(e.where("tid is not null").select("fid", "tid", (F.floor(seconds / 3600) + 1).cast("long").alias("cost")))


def scrambled(x: Column, seed: int) -> Column:
    """A 31-bit hash in whole-number arithmetic that any SQL engine repeats: two rounds of shift, exclusive or and product."""
    x = (x * 2654435 + seed) % (1 << 31)
    for _ in range(2):
        x = (x.bitwiseXOR(F.shiftright(x, 16)) * 73244475) % (1 << 31)
    return x.bitwiseXOR(F.shiftright(x, 15))


def generated(spark: SparkSession, nodes: int, degree: int = 3, seed: int = 1, skewed: bool = False, heaviest: int = 20) -> DataFrame:
    """``nodes * degree`` random edges before self-loops and parallels go, weights 1..``heaviest``; ``skewed``: ends drawn with
    a density that falls with the square root of the id. Every edge is a function of its number, so the generator is one
    narrow map over a range, of any size."""
    i = F.col("id") * 3
    end = F.expr("r * r div n") if skewed else F.col("r")
    drawn = spark.range(nodes * degree).select((scrambled(i, seed) % nodes).alias("fid"), (scrambled(i + 1, seed) % nodes).alias("r"), (1 + scrambled(i + 2, seed) % heaviest).alias("cost"), F.lit(nodes).cast("long").alias("n"))
    return edges(drawn.select("fid", end.alias("tid"), "cost"))


def _parts(spark: SparkSession, sf_dir: str) -> int:
    return table(spark, sf_dir, "part").count()


def _suppliers(spark: SparkSession, sf_dir: str) -> int:
    return table(spark, sf_dir, "supplier").count()


TOY = [("s", "c", 1), ("s", "d", 3), ("s", "b", 4), ("c", "d", 1), ("c", "e", 3), ("d", "f", 5), ("b", "f", 6), ("e", "h", 7), ("f", "t", 6), ("h", "t", 2)]

GRAPHS: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "random": random_graph,
    "random_dense": lambda s, d: random_graph(s, d, 1),
    "power": power_graph,
    "power_dense": lambda s, d: power_graph(s, d, 1),
    "coorder": co_order_graph,
    "coorder_dense": lambda s, d: co_order_graph(s, d, 1),
    "web": web_graph,
    "nation": nation_graph,
    "nation_undirected": nation_undirected,
    "supplier": supplier_graph,
    "supplier_dense": lambda s, d: supplier_graph(s, d, 1),
    "trade": trade_graph,
    "eventline": event_graph,
    # as many nodes as there are parts (20,000 at scale 0.1), half and a quarter of them; as many as suppliers
    "gen_random": lambda s, d: generated(s, _parts(s, d)),
    "gen_random_half": lambda s, d: generated(s, _parts(s, d) // 2),
    "gen_power": lambda s, d: generated(s, _parts(s, d), seed=2, skewed=True),
    "gen_power_half": lambda s, d: generated(s, _parts(s, d) // 2, seed=2, skewed=True),
    "gen_power_small": lambda s, d: generated(s, _suppliers(s, d), seed=2, skewed=True),
}

_kept: dict[tuple, DataFrame] = {}


def kept(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """The graph, materialised once a session, so that many queries share it."""
    key = (spark.sparkContext.applicationId, sf_dir, name)
    if key not in _kept:
        _kept[key] = GRAPHS[name](spark, sf_dir).persist()
    return _kept[key]


def query_pairs(spark: SparkSession, sf_dir: str, q: int = 100) -> DataFrame:
    """``qid, s, t``: arithmetic pairs of part keys, so that another engine draws the same."""
    n = table(spark, sf_dir, "part").count()
    i = F.col("id")
    pair = spark.range(q).select(i.alias("qid"), ((i * 7919 + 17) % n).alias("s"), ((i * 104729 + 1031) % n).alias("t"))
    return pair.where("s <> t")
