"""Headline searches at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line."""

from __future__ import annotations

import json
import os
import time

from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from wavefront.plans import local, search, segments
from wavefront.plans.graph_queries import graph, node_pairs
from wavefront.plans.search import Options
from wavefront.sources.graphs import kept, query_pairs


def main() -> None:
    d = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    cpus = os.environ.get("BENCH_CPUS", "8")
    spark = (
        SparkSession.builder.master(f"local[{cpus}]")
        .config("spark.driver.memory", "8g")
        .config("spark.sql.shuffle.partitions", cpus)
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .config("spark.sql.session.timeZone", "UTC")
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    took: dict[str, float] = {}
    shape: dict[str, dict] = {}

    def timed(name: str, run, pairs: int | None = None) -> None:
        began = time.time()
        r = run()
        n = r.answers.count() if isinstance(r, search.Result) else r if isinstance(r, int) else r.count()
        took[name] = round(time.time() - began, 3)
        if isinstance(r, search.Result):
            m = r.answers.agg(F.avg(F.col("forward_rounds") + F.col("backward_rounds")), F.avg("visited")).first()
            shape[name] = {"pairs": pairs, "answered": n, "sec_per_query": round(took[name] / max(1, pairs), 4), "expansions": round(m[0] or 0, 1), "visited": round(m[1] or 0, 1)}

    timed("build_random_graph", lambda: kept(spark, d, "random").count())
    timed("build_power_graph", lambda: kept(spark, d, "power").count())
    plain, power = graph(spark, d, "random"), graph(spark, d, "power")
    timed("warm_up", lambda: search.bidirectional_set(plain, query_pairs(spark, d, 5), Options(max_rounds=10, allow_unfinished=True)), 5)
    hundred = query_pairs(spark, d, 100)
    timed("bidirectional_set_random_100", lambda: search.bidirectional_set(plain, hundred), 100)
    timed("bidirectional_bfs_random_100", lambda: search.bidirectional_bfs(plain, hundred), 100)
    timed("index_random_20", lambda: graph(spark, d, "random", 20).out.count() + graph(spark, d, "random", 20).back.count())
    timed("segmented_20_random_100", lambda: segments.segmented(graph(spark, d, "random", 20), hundred, 20), 100)
    timed("bidirectional_set_power_100", lambda: search.bidirectional_set(power, hundred), 100)
    timed("index_power_30", lambda: graph(spark, d, "power", 30).out.count() + graph(spark, d, "power", 30).back.count())
    timed("segmented_30_power_100", lambda: segments.segmented(graph(spark, d, "power", 30), hundred, 30), 100)
    # generated graphs of the published size (20,000 nodes of degree 3 at scale 0.1), one query alone and batches
    made, drawn = graph(spark, d, "gen_power"), graph(spark, d, "gen_random")
    timed("bidirectional_set_gen_power_1", lambda: search.bidirectional_set(made, node_pairs(spark, d, "gen_power", 1)), 1)
    timed("bidirectional_set_gen_power_100", lambda: search.bidirectional_set(made, node_pairs(spark, d, "gen_power", 100)), 100)
    timed("bidirectional_gen_power_20", lambda: search.bidirectional(made, node_pairs(spark, d, "gen_power", 20)), 20)
    timed("index_gen_random_5", lambda: graph(spark, d, "gen_random", 5).out.count() + graph(spark, d, "gen_random", 5).back.count())
    timed("segmented_5_gen_random_100", lambda: segments.segmented(graph(spark, d, "gen_random", 5), node_pairs(spark, d, "gen_random", 100), 5), 100)
    timed("bidirectional_bfs_gen_random_100", lambda: search.bidirectional_bfs(drawn, node_pairs(spark, d, "gen_random", 100)), 100)
    held = local.load(kept(spark, d, "random"))  # loading is not part of the in-memory baselines
    timed("local_bidirectional_random_100", lambda: held.bidirectional(hundred))
    timed("local_one_way_random_100", lambda: held.dijkstra(hundred))
    took.pop("warm_up")
    print(json.dumps({"metric": "headline searches, total", "value": round(sum(took.values()), 3), "unit": "sec", "queries": took, "sf": d, "shape": shape}))


if __name__ == "__main__":
    main()
