"""The segment index: every pair closer than a threshold with the neighbour of its far end, plus the edges it does not cover.

Built set-at-a-time: all nodes are sources at once, a round settles a band of distances over the whole table. The
tables have the shape of an edge table with ``pid``, so the frontier loop searches them as it searches edges.
"""

from __future__ import annotations

import heapq
import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.pandas.types import to_arrow_schema

from wavefront.operators.steps import ACTIVE, CLOSED, OPEN, RULES, cheapest_sql, merge_sql, neighbours_sql
from wavefront.plans import columns, inside
from wavefront.plans.replicated import Adjacency, copies, share
from wavefront.plans.search import Graph, Options, Result, rounds_conf, search
from wavefront.session import cut, let_go


def local_pairs(edges: DataFrame, threshold: float, opts: Options | None = None) -> tuple[DataFrame, int]:
    """``(qid, nid, d, p)`` for all nodes within ``threshold`` of each source, and the rounds it took."""
    opts = opts or Options()
    spark = edges.sparkSession
    tag = f"wavefront_{uuid.uuid4().hex[:12]}"
    edges.createOrReplaceTempView(f"{tag}_edges")
    cost = edges.schema["cost"].dataType.simpleString()
    rows, w_min = edges.agg(F.count(F.lit(1)), F.min("cost")).first()
    step = max(w_min or 0, 0) or 1
    parent = edges.schema["fid"].dataType.simpleString()
    state = spark.sql(f"select distinct fid as qid, fid as nid, cast(0 as {cost}) as d, cast(null as {parent}) as p, cast({OPEN} as tinyint) as f from {tag}_edges")
    number = 0
    with rounds_conf(spark, 8 * (rows or 1), opts.width):
        state = cut(state, laid_out=True)
        while True:
            held = state
            state.createOrReplaceTempView(f"{tag}_state")
            level, open_ = spark.sql(f"select min(d), count(1) from {tag}_state where f = {OPEN}").first()
            if not open_:
                break
            number += 1
            test = RULES["build"].replace("bound", repr(number * step)).replace("level", repr(level))
            state = cut(
                spark.sql(
                    f"with flagged as (select qid, nid, d, p, case when f = {OPEN} and {test} then cast({ACTIVE} as tinyint) else f end as f from {tag}_state), front as (select qid, nid, d from flagged where f = {ACTIVE}), "
                    f"cand as ({neighbours_sql('front', f'{tag}_edges', limit=threshold)}), new as ({cheapest_sql('cand', opts.expand)}), old as (select qid, nid, d, p, case when f = {ACTIVE} then cast({CLOSED} as tinyint) else f end as f from flagged) "
                    f"{merge_sql('old', 'new', opts.merge)}"
                ),
                laid_out=True,
            )
            let_go(held)
    spark.catalog.dropTempView(f"{tag}_edges")
    spark.catalog.dropTempView(f"{tag}_state")
    return state.select("qid", "nid", "d", "p"), number


def _pairs_inside(edges: DataFrame, threshold: float, opts: Options) -> tuple[DataFrame, int] | None:
    """``local_pairs`` but for the sources' own rows, from tasks that hold the edges no longer than the threshold (no other one
    can lie inside it) and take a share of the sources each. None where these do not fit, or weights are not whole and positive."""
    short = edges.where(F.col("cost") <= threshold).select("fid", "tid", "cost").persist()
    rows, w_min = short.agg(F.count(F.lit(1)), F.min("cost")).first()
    nid, cost = (edges.schema[c].dataType for c in ("fid", "cost"))
    if not rows or w_min <= 0 or not inside.fits(rows, cost) or isinstance(cost, T.DoubleType):
        short.unpersist()
        return None
    parts = copies(rows)
    schema = T.StructType([T.StructField(n, k) for n, k in (("qid", nid), ("nid", nid), ("d", cost), ("p", nid))])
    arrow = to_arrow_schema(schema)

    def by_columns(g: Adjacency, task: int) -> Iterator[pa.RecordBatch]:
        own = np.arange(task, len(g.ids), parts)
        for at in range(0, len(own), columns.BLOCK):
            block = own[at : at + columns.BLOCK]
            state = columns.near(g, block, threshold, w_min, opts)
            state = state.filter(state["p"].is_valid())
            k, d, p = (state[c].to_numpy() for c in ("k", "d", "p"))
            found = (g.ids[block[k // len(g.ids)]], g.ids[k % len(g.ids)], d, g.ids[p])
            yield pa.RecordBatch.from_arrays([pa.array(x, type=f.type) for x, f in zip(found, arrow, strict=True)], schema=arrow)

    def work(g: Adjacency, task: int) -> Iterator[pa.RecordBatch]:
        if columns.takes(opts, cost):
            yield from by_columns(g, task)
            return
        start, to, _, weight = g.sides[0]
        found: list[tuple] = []
        for s in range(task, len(g.ids), parts):
            best, par, heap = {s: 0}, {}, [(0, s)]
            while heap:
                d, u = heapq.heappop(heap)
                if d > best[u]:
                    continue
                for k in range(start[u], start[u + 1]):
                    v, c = to[k], d + weight[k]
                    if c > threshold:
                        continue
                    old = best.get(v)
                    if old is None or c < old:
                        best[v], par[v] = c, u
                        heapq.heappush(heap, (c, v))
                    elif c == old and u < par[v]:
                        par[v] = u
            found += [(s, v, best[v], p) for v, p in par.items()]
            if len(found) > 50_000:
                yield _batch(g, found, arrow)
                found = []
        yield _batch(g, found, arrow)

    pairs = share(short, None, None, parts, work, ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in schema))
    short.unpersist()
    # the rounds that statements take: each settles a band of the least weight's width, or the next level where it is empty
    levels, rounds = sorted({0, *(r[0] for r in pairs.select("d").distinct().collect())}), 0
    while levels:
        rounds += 1
        levels = [d for d in levels if d >= rounds * w_min and d != levels[0]]
    return pairs, rounds


def _batch(g: Adjacency, found: list[tuple], schema: pa.Schema) -> pa.RecordBatch:
    s, v, d, p = zip(*found, strict=True) if found else ((),) * 4
    named = lambda x: g.ids[np.array(x, dtype="int64")]
    return pa.RecordBatch.from_arrays([pa.array(x, type=f.type) for x, f in zip((named(s), named(v), list(d), named(p)), schema, strict=True)], schema=schema)


def build(edges: DataFrame, threshold: float, opts: Options | None = None) -> tuple[DataFrame, int]:
    """One direction of the index ``(fid, tid, pid, cost)`` and the rounds of its first step. Pass reversed edges for
    the other direction. An edge stays unless a segment joins its ends at no more than its weight."""
    pairs, rounds = (_pairs_inside(edges, threshold, opts) if opts and opts.inside else None) or local_pairs(edges, threshold, opts)
    segments = pairs.where("qid <> nid").select(F.col("qid").alias("fid"), F.col("nid").alias("tid"), F.col("p").alias("pid"), F.col("d").alias("cost"))
    left = edges.join(segments.select("fid", "tid"), ["fid", "tid"], "left_anti").select("fid", "tid", F.col("fid").alias("pid"), "cost")
    return segments.unionByName(left), rounds


def index(edges: DataFrame, threshold: float, opts: Options | None = None) -> Graph:
    back = edges.select(F.col("tid").alias("fid"), F.col("fid").alias("tid"), "cost")
    return Graph(build(edges, threshold, opts)[0], build(back, threshold, opts)[0])


def estimate(edges: DataFrame, threshold: float, share: float = 0.02) -> float:
    """Segments the whole index would hold, from the sources in a hashed share of the nodes."""
    near = edges.where(F.pmod(F.xxhash64("fid"), F.lit(10_000)) < share * 10_000).select("fid").distinct()
    n = near.count()
    if not n:
        return float(edges.count())
    seen, _ = sssp_rows(edges, near, threshold)
    return seen / n * edges.select("fid").distinct().count()


def sssp_rows(edges: DataFrame, sources: DataFrame, threshold: float) -> tuple[int, int]:
    from wavefront.plans.search import sssp

    numbered = sources.select(F.monotonically_increasing_id().alias("qid"), F.col("fid").alias("s"))
    return sssp(Graph.of(edges), cut(numbered), threshold).visited.where("p2s is not null").count(), 0


def save(g: Graph, path: str, threshold: float, parts: int = 64) -> None:
    """Both tables laid out by a hash of the join key and sorted by it, with one row of what they were built for."""
    spark = g.out.sparkSession
    for name, df in (("out", g.out), ("back", g.back)):
        laid = df.withColumn("part", F.pmod(F.xxhash64("fid"), F.lit(parts)).cast("int"))
        laid.repartition("part").sortWithinPartitions("part", "fid").write.partitionBy("part").mode("overwrite").parquet(f"{path}/{name}")
    spark.createDataFrame([(float(threshold), float(g.w_min), parts)], "threshold double, w_min double, parts int").write.mode("overwrite").parquet(f"{path}/meta")


def load(spark, path: str) -> tuple[Graph, float]:
    meta = spark.read.parquet(f"{path}/meta").first()
    read = lambda n: spark.read.parquet(f"{path}/{n}").drop("part")
    return Graph(read("out"), read("back"), meta["w_min"]), meta["threshold"]


def segmented(idx: Graph, pairs: DataFrame, threshold: float, opts: Options | None = None) -> Result:
    """Selective search: a round takes the open nodes up to round * threshold on the side it turns to."""
    return search(idx, pairs, "band", 2, threshold, opts)


def apply_inserts(edges: DataFrame, segments: DataFrame, new: DataFrame, threshold: float, opts: Options | None = None) -> tuple[DataFrame, DataFrame]:
    """Edges and one direction of the index after edge inserts: only sources that reach a new edge's tail within the
    threshold are searched again, found in the old index itself and among the tails."""
    after = edges.unionByName(new.select("fid", "tid", "cost")).where("fid <> tid").groupBy("fid", "tid").agg(F.min("cost").alias("cost"))
    after = cut(after)
    tails = new.select(F.col("fid").alias("tail")).distinct()
    # a source may reach a tail through another new edge, so tails within reach of the enlarged graph are followed back
    back = after.select(F.col("tid").alias("fid"), F.col("fid").alias("tid"), "cost")
    from wavefront.plans.search import sssp

    numbered = cut(tails.select(F.monotonically_increasing_id().alias("qid"), F.col("tail").alias("s")))
    touched = cut(sssp(Graph.of(back), numbered, threshold, opts).visited.where("d2s is not null").select(F.col("nid").alias("fid")).distinct())
    again, _ = _from_sources(after, touched, threshold, opts)
    fresh = again.where("qid <> nid").select(F.col("qid").alias("fid"), F.col("nid").alias("tid"), F.col("p").alias("pid"), F.col("d").alias("cost"))
    own = after.join(touched, "fid", "left_semi")
    left = own.join(fresh.select("fid", "tid"), ["fid", "tid"], "left_anti").select("fid", "tid", F.col("fid").alias("pid"), "cost")
    return after, segments.join(touched, "fid", "left_anti").select("fid", "tid", "pid", "cost").unionByName(fresh).unionByName(left)


def _from_sources(edges: DataFrame, sources: DataFrame, threshold: float, opts: Options | None) -> tuple[DataFrame, int]:
    from wavefront.plans.search import sssp

    numbered = cut(sources.select(F.monotonically_increasing_id().alias("qid"), F.col("fid").alias("s")))
    seen = sssp(Graph.of(edges), numbered, threshold, opts).visited.where("d2s is not null")
    return seen.join(numbered, "qid").select(F.col("s").alias("qid"), "nid", F.col("d2s").alias("d"), F.col("p2s").alias("p")), 0
