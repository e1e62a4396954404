"""Shares of a graph's work are tasks of their own, and loops leave little behind."""

from __future__ import annotations

import os
import time

import pyarrow as pa
import pytest

from wavefront.operators.components import connected_components
from wavefront.plans import workload_queries
from wavefront.plans.replicated import share
from wavefront.session import cut
from wavefront.sources.tables import from_rows


def test_each_share_is_a_task_of_its_own(spark):
    e = from_rows(spark, [(1, 2, 3), (2, 3, 1), (3, 1, 2)], "fid long, tid long, cost long").coalesce(1)
    pairs = spark.createDataFrame([(q, 1, 3) for q in range(20)], "qid long, s long, t long")

    def work(g, task):
        rows = [(task, q, len(g.ids)) for q, _, _ in g.asked]
        yield pa.RecordBatch.from_pydict({n: pa.array([r[k] for r in rows], pa.int64()) for k, n in enumerate(("task", "qid", "nodes"))})

    found = share(e, None, pairs, 4, work, "task long, qid long, nodes long")
    rows = found.collect()
    assert found.rdd.getNumPartitions() == 4
    assert sorted(r["qid"] for r in rows) == list(range(20)) and {r["nodes"] for r in rows} == {3}


def test_a_cut_leaves_no_shuffle_files(spark):
    blocks = lambda: sum(b.toString().startswith("shuffle_") for b in list(spark._jvm.scala.jdk.javaapi.CollectionConverters.asJava(spark._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager().getAllBlocks())))
    before, end = blocks(), time.time() + 10
    kept = cut(spark.range(1000).repartition(8, "id"))
    while blocks() > before and time.time() < end:
        time.sleep(0.1)
    assert blocks() <= before and kept.count() == 1000 and kept.count() == 1000


def test_components_leave_their_last_state_only(spark):
    folder = spark.sparkContext._jsc.sc().getCheckpointDir().get().removeprefix("file:")
    before = set(os.listdir(folder)) if os.path.isdir(folder) else set()
    found = connected_components(spark.createDataFrame([(k, k + 1) for k in range(1, 40)], "u long, v long"))
    assert len(set(os.listdir(folder)) - before) == 1
    assert {tuple(r) for r in found.collect()} == {(k, 1) for k in range(1, 41)}


def test_memory_comparison_builds_its_index_inside_tasks(monkeypatch):
    asked = []

    def graph(s, d, on, threshold, opts=None):
        asked.append(opts)
        raise InterruptedError

    monkeypatch.setattr(workload_queries, "node_pairs", lambda *a: None)
    monkeypatch.setattr(workload_queries, "graph", graph)
    with pytest.raises(InterruptedError):
        workload_queries._memory(None, "")
    assert asked[0] and asked[0].inside
