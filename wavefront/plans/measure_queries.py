"""Cost measures of the methods: rounds, visited nodes, phases, operators, bounds, index size."""

from __future__ import annotations

import time

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from wavefront.plans import search, segments
from wavefront.plans.graph_queries import Query, graph, node_pairs
from wavefront.plans.search import Options
from wavefront.sources.graphs import kept, query_pairs
from wavefront.streaming import edges as stream

QUERIES: dict[str, Query] = {}
ORACLE: dict[str, str] = {}


_found: dict[tuple, dict[str, search.Result]] = {}


def methods(s: SparkSession, d: str, on: str, q: int, threshold: int = 5) -> dict[str, search.Result]:
    """The three methods on the same pairs, run once a session."""
    key = (s.sparkContext.applicationId, d, on, q, threshold)
    if key not in _found:
        _found[key] = _methods(s, d, on, query_pairs(s, d, q), threshold)
    return _found[key]


def _methods(s: SparkSession, d: str, on: str, pairs: DataFrame, threshold: int) -> dict[str, search.Result]:
    g = graph(s, d, on)
    return {"set": search.bidirectional_set(g, pairs), "bfs": search.bidirectional_bfs(g, pairs), f"segmented_{threshold}": segments.segmented(graph(s, d, on, threshold), pairs, threshold)}


def cost_table(found: dict[str, search.Result]) -> DataFrame:
    out = None
    for name, r in found.items():
        row = r.answers.select(F.lit(name).alias("method"), "qid", "distance", (F.col("forward_rounds") + F.col("backward_rounds")).alias("expansions"), "visited")
        out = row if out is None else out.unionByName(row)
    return out


QUERIES["measure_expansions"] = lambda s, d: cost_table(methods(s, d, "random", 20)).groupBy("method").agg(F.avg("expansions").alias("expansions"), F.avg("visited").alias("visited"))


def trend(s: SparkSession, d: str) -> DataFrame:
    """Does the published order hold? Rounds: bfs < segmented < set; visited: set <= segmented < bfs (means over pairs)."""
    m = cost_table(methods(s, d, "random", 20)).groupBy().pivot("method", ["set", "bfs", "segmented_5"]).agg(F.avg("expansions").alias("e"), F.avg("visited").alias("v"))
    return m.select((F.col("bfs_e") < F.col("segmented_5_e")).alias("bfs_fewest_rounds"), (F.col("segmented_5_e") < F.col("set_e")).alias("segments_save_rounds"), (F.col("segmented_5_v") < F.col("bfs_v")).alias("segments_visit_less_than_bfs"))


QUERIES["measure_trend"] = trend
ORACLE["measure_trend"] = "select true as bfs_fewest_rounds, true as segments_save_rounds, true as segments_visit_less_than_bfs"


def bounds(s: SparkSession, d: str) -> DataFrame:
    """On whole weights with w_min 1: rounds of set search within distance / w_min + 2, of segmented search within 2 (distance + l) / (l + w_min) + 2."""
    rows = cost_table(methods(s, d, "random", 20))
    limit = F.when(F.col("method") == "set", F.col("distance") + 2).when(F.col("method") == "segmented_5", 2 * (F.col("distance") + 5) / 6 + 2)
    return rows.where("method <> 'bfs'").groupBy("method").agg(F.min(F.col("expansions") <= limit).alias("holds"))


QUERIES["measure_bounds"] = bounds
ORACLE["measure_bounds"] = "select * from (values ('set', true), ('segmented_5', true)) v(method, holds)"


def phases(s: SparkSession, d: str) -> DataFrame:
    """Seconds spent in expansion, statistics and recovery of one single-direction search."""
    from wavefront.plans import recover

    r = search.dijkstra(graph(s, d, "nation"), node_pairs(s, d, "nation", 4), Options(inside=False))
    began = time.time()
    recover.paths(r).count()
    rows = [("expansion", r.seconds["expansion"]), ("statistics", r.seconds["statistics"]), ("recovery", time.time() - began)]
    return s.createDataFrame(rows, "phase string, seconds double")


QUERIES["measure_phases"] = phases


def dialects(s: SparkSession, d: str) -> DataFrame:
    """Seconds of one breadth-first batch in each pair of dialects."""
    rows = []
    for e, m in (("aggjoin", "two_step"), ("window", "single"), ("window", "two_step"), ("argmin", "single")):
        began = time.time()
        search.bidirectional_bfs(graph(s, d, "power"), query_pairs(s, d, 6), Options(expand=e, merge=m)).answers.count()
        rows.append((e, m, time.time() - began))
    return s.createDataFrame(rows, "expand string, merge string, seconds double")


QUERIES["measure_dialects"] = dialects


def builds(s: SparkSession, d: str) -> DataFrame:
    """Size, rounds and seconds of the index by threshold; rounds stay within threshold / w_min + 1."""
    rows = []
    for x in (5, 10, 20):
        began = time.time()
        table, rounds = segments.build(kept(s, d, "power"), x)
        rows.append((x, table.count(), rounds, rounds <= x + 1, time.time() - began))
    return s.createDataFrame(rows, "threshold int, segments long, rounds int, within_bound boolean, seconds double")


QUERIES["measure_index_build"] = builds
QUERIES["measure_index_estimate"] = lambda s, d: s.createDataFrame([(10, segments.estimate(kept(s, d, "random"), 10, 0.1))], "threshold int, segments double")

QUERIES["stream_edges_dedup"] = lambda s, d: stream.run(stream.distinct_events(stream.read_events(s, d))).select("event_id", "user_id")
ORACLE["stream_edges_dedup"] = "select event_id, user_id from events"
QUERIES["stream_windows"] = lambda s, d: stream.run(stream.windows(stream.read_events(s, d), "1 day"), "complete").select(F.col("start").cast("date").cast("string").alias("day"), "event_type", "n")
ORACLE["stream_windows"] = "select strftime(date_trunc('day', ts), '%Y-%m-%d') as day, event_type, count(*) as n from events group by 1, 2"
QUERIES["stream_sliding"] = lambda s, d: stream.run(stream.windows(stream.read_events(s, d), "2 days", "1 day"), "complete").select(F.col("start").cast("date").cast("string").alias("day"), "event_type", "n")
ORACLE["stream_sliding"] = "select strftime(day, '%Y-%m-%d') as day, event_type, count(*) as n from (select date_trunc('day', ts) as day, event_type from events union all select date_trunc('day', ts) - interval 1 day, event_type from events) group by 1, 2"
QUERIES["stream_session"] = lambda s, d: stream.run(stream.sessions(stream.read_events(s, d), "12 hours"), "complete").select("user_id", "n")
ORACLE["stream_session"] = "select user_id, count(*) as n from (select user_id, sum(new) over (partition by user_id order by ts, event_id) as k from (select user_id, ts, event_id, case when lag(ts) over w is null or ts >= lag(ts) over w + interval 12 hours then 1 else 0 end as new from events window w as (partition by user_id order by ts, event_id))) group by user_id, k"
