"""The dialects inside tasks, on column tables: the rows of the statements, and few Spark jobs whatever the rounds."""

from __future__ import annotations

import pytest

from wavefront.operators.steps import EXPANDS, MERGES
from wavefront.plans import search, segments, workload_queries
from wavefront.plans.search import Graph, Options
from wavefront.sources.graphs import generated

DIALECTS = [(e, m) for e in EXPANDS for m in MERGES]


@pytest.fixture(scope="module")
def small(spark):
    return Graph.of(generated(spark, 120, heaviest=5, seed=3).persist())


@pytest.fixture(scope="module")
def pairs(spark):
    # ends outside the graph, equal ends and a missing source are among them
    return spark.createDataFrame([*((q, q * 7 % 120, q * 31 % 120) for q in range(1, 7)), (7, 3, 9999), (8, 9998, 4), (9, 5, 5), (10, None, 4)], "qid long, s long, t long")


def seen(r: search.Result) -> tuple:
    rounds = r.rounds.select("qid", "round", "dir", "open", "level", "best", "visited")
    return tuple(sorted((tuple(x) for x in df.collect()), key=repr) for df in (r.answers, r.visited.select("qid", "nid", "d2s", "p2s", "f", "d2t", "p2t", "b"), rounds))


@pytest.mark.parametrize("kind, sides, threshold, radius", [("level", 2, None, None), ("all", 2, None, None), ("band", 2, 3, None), ("one", 2, None, None), ("level", 1, None, 6), ("one", 1, None, None)])
def test_columns_give_the_rows_of_rounds_inside_tasks(small, pairs, kind, sides, threshold, radius):
    want = seen(search.search(small, pairs, kind, sides, threshold, Options(inside=True), radius))
    assert want[0]
    for e, m in DIALECTS if kind == "level" else [("window", "two_step"), ("aggjoin", "algebra")]:
        assert seen(search.search(small, pairs, kind, sides, threshold, Options(expand=e, merge=m, inside=True, columns=True), radius)) == want, (e, m)


def test_columns_give_the_rows_of_statements(small, pairs):
    two = pairs.where("qid in (1, 2, 7)")
    want = seen(search.bidirectional_bfs(small, two, Options(expand="aggjoin", merge="two_step")))
    assert seen(search.bidirectional_bfs(small, two, Options(expand="aggjoin", merge="two_step", inside=True, columns=True))) == want


def test_a_round_limit_is_not_silent_by_columns(small, pairs):
    opts = Options(expand="window", merge="algebra", inside=True, columns=True, max_rounds=2)
    with pytest.raises(RuntimeError):
        search.bidirectional_set(small, pairs, opts)
    opts.allow_unfinished = True
    plain = Options(inside=True, max_rounds=2, allow_unfinished=True)
    assert seen(search.bidirectional_set(small, pairs, opts)) == seen(search.bidirectional_set(small, pairs, plain))


def test_large_costs_do_not_wrap(spark):
    far = 1 << 61
    e = spark.createDataFrame([(1, 2, far), (2, 3, far), (1, 3, far + far // 2), (1, 4, 1)], "fid long, tid long, cost long")
    ask = spark.createDataFrame([(1, 1, 3)], "qid long, s long, t long")
    for ex, m in DIALECTS:
        r = search.set_dijkstra(Graph.of(e), ask, Options(expand=ex, merge=m, inside=True, columns=True))
        assert [x["distance"] for x in r.answers.collect()] == [far + far // 2], (ex, m)


def test_index_by_columns_has_the_rows_of_statements(small):
    rows = lambda found: (sorted(map(tuple, found[0].collect())), found[1])
    want = rows(segments.build(small.out, 4))
    for e, m in DIALECTS:
        assert rows(segments.build(small.out, 4, Options(expand=e, merge=m, inside=True, columns=True))) == want, (e, m)


def test_dialect_workloads_take_no_jobs_a_round(spark, small, pairs, monkeypatch):
    made, measure = [], workload_queries._measure
    monkeypatch.setattr(workload_queries, "graph", lambda *a: small)
    monkeypatch.setattr(workload_queries, "node_pairs", lambda *a: pairs)
    monkeypatch.setattr(workload_queries, "_DIALECTS", (("aggjoin", "algebra"),))
    monkeypatch.setattr(workload_queries, "_measure", lambda *a, **b: made.append(measure(*a, **b)) or made[-1])
    workload_queries._dialects(spark, "")
    assert made[0][3] and made[0][9] < 1.5  # jobs a round; statements take two and those of their broadcasts


def test_builds_take_no_rounds_of_statements(spark, small, monkeypatch):
    def refuse(*a):
        raise AssertionError("a build ran as statements")

    want = segments.build(small.out, 3)[0].count()
    monkeypatch.setattr(segments, "local_pairs", refuse)
    monkeypatch.setattr(workload_queries, "kept", lambda *a: small.out)
    found = workload_queries._builds(spark, "", "gen_power", 3)
    assert [r[0] for r in found] == workload_queries._HOW and {r[1] for r in found} == {want}
