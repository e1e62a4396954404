"""Paths from visited tables: predecessor and successor chains, followed for all queries at once."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from wavefront.plans.search import Result, meeting_nodes, rounds_conf
from wavefront.session import cut


def _chase(links: DataFrame, start: DataFrame, most: int = 100_000) -> DataFrame:
    """``links(qid, nid, next)``, ``start(qid, nid)`` -> ``(qid, step, nid)`` with step 0 at the start. Raises beyond ``most`` steps."""
    here = start.select("qid", F.lit(0).alias("step"), "nid")
    done = [cut(here)]
    for k in range(1, most):
        on = done[-1].join(links, ["qid", "nid"]).where("next is not null").select("qid", F.lit(k).alias("step"), F.col("next").alias("nid"))
        on = cut(on)
        if on.isEmpty():
            break
        done.append(on)
    else:
        raise RuntimeError(f"a path has more than {most} nodes")
    out = done[0]
    for part in done[1:]:
        out = out.unionByName(part)
    return out


def paths(found: Result) -> DataFrame:
    """``qid, pos, nid``: each answered query's path, source first. Two-sided searches are joined at the least meeting node."""
    spark = found.answers.sparkSession
    two = found.visited.where("d2t is not null").limit(1).count() > 0
    with rounds_conf(spark, 1):
        same = found.answers.where("s = t").select("qid", F.lit(0).alias("pos"), F.col("s").alias("nid"))
        answers = found.answers.where("s <> t")
        if not two:
            back = _chase(found.visited.select("qid", "nid", F.col("p2s").alias("next")), answers.select("qid", F.col("t").alias("nid")))
            last = back.groupBy("qid").agg(F.max("step").alias("last"))
            return cut(back.join(last, "qid").select("qid", (F.col("last") - F.col("step")).alias("pos"), "nid").unionByName(same))
        meet = cut(meeting_nodes(found.visited, answers))
        head = _chase(found.visited.select("qid", "nid", F.col("p2s").alias("next")), meet)
        tail = _chase(found.visited.select("qid", "nid", F.col("p2t").alias("next")), meet).where("step > 0")
        last = head.groupBy("qid").agg(F.max("step").alias("last"))
        before = head.join(last, "qid").select("qid", (F.col("last") - F.col("step")).alias("pos"), "nid")
        after = tail.join(last, "qid").select("qid", (F.col("last") + F.col("step")).alias("pos"), "nid")
        return cut(before.unionByName(after).unionByName(same))


def paths_by_recursion(found: Result) -> DataFrame:
    """The same for one-sided searches as one recursive statement."""
    spark = found.answers.sparkSession
    return spark.sql(
        "with recursive walk(qid, nid, step) max recursion level 10000 as (select qid, t, 0 from {a} union all select w.qid, v.p2s, w.step + 1 from walk w join {v} v on w.qid = v.qid and w.nid = v.nid where v.p2s is not null) "
        "select qid, cast(max(step) over (partition by qid) - step as int) as pos, nid from walk",
        a=found.answers,
        v=found.visited,
    )


def priced(path: DataFrame, edges: DataFrame) -> DataFrame:
    """``qid, cost``: the sum of edge weights along each path (0 for a path of one node)."""
    from pyspark.sql import Window

    hop = path.withColumn("next", F.lead("nid").over(Window.partitionBy("qid").orderBy("pos")))
    cost = hop.join(edges, (F.col("nid") == F.col("fid")) & (F.col("next") == F.col("tid")), "left")
    return cost.groupBy("qid").agg(F.coalesce(F.sum("cost"), F.lit(0)).cast("long").alias("cost"), F.count(F.when(F.col("next").isNotNull() & F.col("cost").isNull(), 1)).alias("missing"))
