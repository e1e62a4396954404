"""The experiment workloads, re-expressed on the derived graphs: tables of times, rounds, visited nodes and sizes."""

from __future__ import annotations

import time
import uuid

from pyspark import StorageLevel
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from wavefront.plans import local, search, segments
from wavefront.plans.graph_queries import Query, graph, node_pairs, trade_pairs
from wavefront.plans.search import Graph, Options
from wavefront.session import shared_folder
from wavefront.sources.graphs import kept, query_pairs, random_graph

QUERIES: dict[str, Query] = {}
ORACLE: dict[str, str] = {}


def _means(r: search.Result) -> tuple[float, float]:
    row = r.answers.agg(F.avg(F.col("forward_rounds") + F.col("backward_rounds")), F.avg("visited")).first()
    return float(row[0] or 0), float(row[1] or 0)


def _timed(run) -> tuple[search.Result, float]:
    began = time.time()
    r = run()
    return r, time.time() - began


_variant_rows: dict[tuple, list[tuple]] = {}


def variants(s: SparkSession, d: str) -> DataFrame:
    """Single-direction, bidirectional and bidirectional set search on the same pairs."""
    key = (s.sparkContext.applicationId, d)
    if key not in _variant_rows:
        pairs, g = node_pairs(s, d, "supplier", 3), graph(s, d, "supplier")
        rows = []
        for name, f in (("one_way", search.dijkstra), ("two_way", search.bidirectional), ("two_way_set", search.bidirectional_set)):
            r, seconds = _timed(lambda f=f: f(g, pairs, Options(inside=True)))
            rows.append((name, *_means(r), seconds))
        _variant_rows[key] = rows
    return s.createDataFrame(_variant_rows[key], "method string, expansions double, visited double, seconds double")


QUERIES["exp_dijkstra_variants"] = variants
QUERIES["exp_variants_trend"] = lambda s, d: variants(s, d).groupBy().pivot("method", ["one_way", "two_way", "two_way_set"]).agg(F.first("expansions")).select((F.col("two_way") < F.col("one_way")).alias("two_ways_save_rounds"), (F.col("two_way_set") <= F.col("two_way")).alias("sets_save_rounds"))
ORACLE["exp_variants_trend"] = "select true as two_ways_save_rounds, true as sets_save_rounds"


def threshold_sweep(name: str, thresholds: tuple[int, ...]) -> Query:
    def run(s: SparkSession, d: str) -> DataFrame:
        """Query and build cost by the index threshold."""
        rows = []
        for x in thresholds:
            began = time.time()
            g = graph(s, d, name, x, Options(inside=True))
            size, build = g.out.count(), time.time() - began
            r, seconds = _timed(lambda g=g, x=x: segments.segmented(g, query_pairs(s, d, 4), x, Options(inside=True)))
            rows.append((x, size, build, *_means(r), seconds))
        return s.createDataFrame(rows, "threshold int, segments long, build_seconds double, expansions double, visited double, seconds double")

    return run


QUERIES["exp_threshold_power"] = threshold_sweep("power", (10, 20, 30))
QUERIES["exp_threshold_coorder"] = threshold_sweep("coorder", (2, 6))


def storage(s: SparkSession, d: str) -> DataFrame:
    """The same searches with edges read from files, kept on disk and kept in memory."""
    path = f"{shared_folder(s)}/edges-{uuid.uuid4().hex}"
    kept(s, d, "trade").write.parquet(path)
    rows = []
    for name, level in (("files", None), ("disk", StorageLevel.DISK_ONLY), ("memory", StorageLevel.MEMORY_AND_DISK)):
        e = s.read.parquet(path)
        e = e.persist(level) if level else e
        rows.append((name, _timed(lambda e=e: search.bidirectional_bfs(Graph.of(e), trade_pairs(s, d)))[1]))
        e.unpersist()
    return s.createDataFrame(rows, "edges string, seconds double")


QUERIES["exp_storage"] = storage


def layout(s: SparkSession, d: str, parts: int = 16) -> DataFrame:
    """Files of the index that one frontier of ten nodes touches: laid out by the join key, and as a heap."""
    path = f"{shared_folder(s)}/index-{uuid.uuid4().hex}"
    segments.save(graph(s, d, "random", 10), path, 10, parts)
    graph(s, d, "random", 10).out.repartition(parts).write.parquet(f"{path}/heap")
    front = s.range(10).select((F.col("id") * 31 % 97).alias("nid"))
    wanted = [r[0] for r in front.select(F.pmod(F.xxhash64("nid"), F.lit(parts)).cast("int").alias("part")).distinct().collect()]
    rows = []
    for name, e in (("laid_out", s.read.parquet(f"{path}/out").where(F.col("part").isin(wanted))), ("heap", s.read.parquet(f"{path}/heap"))):
        touched = e.select(F.input_file_name().alias("f")).distinct().count()
        rows.append((name, touched, e.count(), e.join(F.broadcast(front), F.col("fid") == F.col("nid")).count()))
    return s.createDataFrame(rows, "layout string, files long, rows_read long, rows_joined long")


QUERIES["exp_layout"] = layout


def build_growth(s: SparkSession, d: str) -> DataFrame:
    """Index build time by graph size."""
    rows = []
    for k in (32, 16, 8):
        e = random_graph(s, d, k).persist()
        n = e.count()
        began = time.time()
        size = segments.build(e, 10)[0].count()
        rows.append((n, size, time.time() - began))
        e.unpersist()
    return s.createDataFrame(rows, "edges long, segments long, seconds double")


QUERIES["exp_build_growth"] = build_growth
