"""All methods give the same exact distances; worked example, special cases, traps and bounds."""

import collections
import heapq
import random
from pathlib import Path

import pytest

from wavefront.plans import local, patterns, probes, recover, search, segments, trees
from wavefront.plans.search import Graph, Options
from wavefront.session import cut
from wavefront.sources.graphs import TOY
from wavefront.sources.tables import edges, from_rows

INTS = "fid long, tid long, cost long"


def exact(rows, s):
    adj = collections.defaultdict(list)
    for f, t, c in rows:
        adj[f].append((t, c))
    best, heap = {s: 0}, [(0, s)]
    while heap:
        d, u = heapq.heappop(heap)
        if d > best[u]:
            continue
        for v, c in adj[u]:
            if d + c < best.get(v, 1 << 60):
                best[v] = d + c
                heapq.heappush(heap, (d + c, v))
    return best


def asked(found):
    return {r["qid"]: r["distance"] for r in found.answers.collect()}


@pytest.fixture(scope="module")
def toy(spark):
    return from_rows(spark, TOY).persist()


def one(spark, s, t, kind="string"):
    return spark.createDataFrame([(0, s, t)], f"qid long, s {kind}, t {kind}")


def test_toy_distance_and_path(spark, toy):
    r = search.bidirectional_set(Graph.of(toy), one(spark, "s", "t"))
    assert asked(r) == {0: 13}
    p = [x["nid"] for x in recover.paths(r).orderBy("pos").collect()]
    assert p[0] == "s" and p[-1] == "t"
    assert recover.priced(recover.paths(r), toy).first()["cost"] == 13


def test_toy_index_at_six(spark, toy):
    out, _ = segments.build(toy, 6)
    got = {(r["fid"], r["tid"]): (r["pid"], r["cost"]) for r in out.collect()}
    assert len(got) == 12
    assert got["s", "e"] == ("c", 4) and got["s", "d"] == ("c", 2) and got["e", "h"] == ("e", 7)


@pytest.fixture(scope="module")
def noise(spark):
    r = random.Random(3)
    rows = [(r.randrange(60), r.randrange(60), r.randint(1, 9)) for _ in range(150)]
    rows = [(f, t, min(c for a, b, c in rows if (a, b) == (f, t))) for f, t in {(f, t) for f, t, _ in rows if f != t}]
    return rows, edges(spark.createDataFrame(rows, INTS)).persist()


def pairs_of(spark):
    return spark.createDataFrame([(i, (i * 7) % 60, (i * 13 + 5) % 60) for i in range(8)], "qid long, s long, t long")


METHODS = {
    "set_dijkstra": search.set_dijkstra,
    "set": search.bidirectional_set,
    "bfs": search.bidirectional_bfs,
    "unpruned": lambda g, p: search.bidirectional_bfs(g, p, Options(prune=False)),
    "algebra": lambda g, p: search.bidirectional_bfs(g, p, Options(expand="aggjoin", merge="algebra")),
    "modern": lambda g, p: search.bidirectional_bfs(g, p, Options(expand="window")),
}


@pytest.mark.parametrize("name", METHODS)
def test_methods_are_exact(spark, noise, name):
    rows, e = noise
    want = {p["qid"]: exact(rows, p["s"]).get(p["t"]) for p in pairs_of(spark).collect()}
    assert asked(METHODS[name](Graph.of(e), pairs_of(spark))) == {q: d for q, d in want.items() if d is not None}


@pytest.mark.parametrize("threshold", [0, 4, 100])
def test_segmented_is_exact_and_paths_reprice(spark, noise, threshold):
    rows, e = noise
    want = {p["qid"]: exact(rows, p["s"]).get(p["t"]) for p in pairs_of(spark).collect()}
    found = segments.segmented(segments.index(e, threshold), pairs_of(spark), max(threshold, 1))
    assert asked(found) == {q: d for q, d in want.items() if d is not None}
    costs = {r["qid"]: (r["cost"], r["missing"]) for r in recover.priced(recover.paths(found), e).collect()}
    assert costs == {q: (d, 0) for q, d in asked(found).items()}


def test_local_baselines(spark, noise):
    rows, e = noise
    want = {p["qid"]: exact(rows, p["s"]).get(p["t"]) for p in pairs_of(spark).collect()}
    want = {q: d for q, d in want.items() if d is not None}
    for f in (local.dijkstra, local.bidirectional):
        assert {r["qid"]: r["distance"] for r in f(e, pairs_of(spark)).collect()} == want


def test_local_baselines_keep_the_edges_off_the_driver(spark, noise, monkeypatch):
    """The driver collects no edge: a graph of millions of edges would not fit it."""
    rows, e = noise
    refuse = lambda *_: pytest.fail("edges are collected on the driver")
    for name in ("toPandas", "toArrow", "collect", "toLocalIterator"):
        monkeypatch.setattr(type(e), name, refuse)
    found = [f(e, pairs_of(spark)) for f in (local.dijkstra, local.bidirectional)]
    monkeypatch.undo()
    want = {i: exact(rows, (i * 7) % 60).get((i * 13 + 5) % 60) for i in range(8)}
    for df in found:
        assert {r["qid"]: r["distance"] for r in df.collect()} == {q: d for q, d in want.items() if d is not None}


def test_index_definition_and_mirror(spark, noise):
    rows, e = noise
    out, _ = segments.build(e, 5)
    dist = {f: exact(rows, f) for f in {r[0] for r in rows}}
    got = {(r["fid"], r["tid"]): r["cost"] for r in out.collect()}
    near = {(f, t): d for f in dist for t, d in dist[f].items() if f != t and d <= 5}
    left = {(f, t): c for f, t, c in rows if (f, t) not in near}
    assert got == near | left
    back = segments.build(e.selectExpr("tid as fid", "fid as tid", "cost"), 5)[0]
    assert {(r["tid"], r["fid"]): r["cost"] for r in back.collect()} == got


def test_an_index_built_inside_tasks_is_that_of_the_statements(spark, noise):
    _, e = noise
    key = lambda df: sorted((r["fid"], r["tid"], r["pid"], r["cost"]) for r in df.collect())
    for threshold in (0, 1, 4, 12):
        (a, m), (b, n) = (segments.build(e, threshold, Options(inside=x)) for x in (False, True))
        assert key(a) == key(b) and m == n


def test_a_rounds_state_is_let_go(spark, noise, tmp_path):
    """The shared folder holds the last state, not one for each round."""
    _, e = noise
    folder = spark.sparkContext._jsc.sc().getCheckpointDir().get().removeprefix("file:")
    size = lambda: sum(f.stat().st_size for f in Path(folder).rglob("part-*"))
    before = size()
    state, rounds = segments.local_pairs(e, 40)
    one = size() - before
    last = Path(cut(state).checkpoint_file.removeprefix("file:"))
    assert rounds > 20 and one < 4 * sum(f.stat().st_size for f in last.rglob("part-*"))


def test_many_queries_keep_their_control_rows_in_a_table(spark, noise, monkeypatch):
    rows, e = noise
    monkeypatch.setattr(search, "INLINE_QUERIES", 2)
    want = {p["qid"]: exact(rows, p["s"]).get(p["t"]) for p in pairs_of(spark).collect()}
    assert asked(search.bidirectional_bfs(Graph.of(e), pairs_of(spark))) == {q: d for q, d in want.items() if d is not None}


RULES = [("one", 2, None), ("level", 2, None), ("all", 2, None), ("band", 2, 5), ("one", 1, None), ("level", 1, None)]


@pytest.mark.parametrize("kind,sides,threshold", RULES)
def test_rounds_inside_tasks_are_those_of_the_statements(spark, noise, kind, sides, threshold):
    """Answers, visited rows and the log of rounds, row by row; no Spark job for each round."""
    _, e = noise
    pairs = pairs_of(spark).unionByName(spark.createDataFrame([(90, 3, 3), (91, 3, 999), (92, 999, 3)], "qid long, s long, t long"))
    g = segments.index(e, threshold) if threshold else Graph.of(e)
    a, b = (search.search(g, pairs, kind, sides, threshold, Options(inside=x)) for x in (False, True))
    rows = lambda df, *drop: collections.Counter(tuple(r) for r in df.drop(*drop).collect())
    assert rows(a.answers) == rows(b.answers)
    assert rows(a.visited) == rows(b.visited)
    assert rows(a.rounds, "seconds") == rows(b.rounds, "seconds")
    if kind == "one":
        with probes.watched(spark) as cost:
            most = search.search(g, pairs, kind, sides, threshold).rounds.agg({"round": "max"}).first()[0]
        assert cost.jobs < most


def test_special_cases(spark, toy):
    p = spark.createDataFrame([(0, "s", "s"), (1, "s", "nowhere"), (2, "t", "s"), (3, "s", "c")], "qid long, s string, t string")
    assert asked(search.bidirectional_set(Graph.of(toy), p)) == {0: 0, 3: 1}


def test_a_leaf_first_does_not_end_the_search(spark):
    """A round that improves nothing says nothing about the other open nodes."""
    e = from_rows(spark, [("s", "leaf", 1), ("s", "a", 2), ("a", "t", 2)])
    for f in (search.set_dijkstra, search.bidirectional_set, search.bidirectional_bfs):
        assert asked(f(Graph.of(e), one(spark, "s", "t"))) == {0: 4}


def test_zero_weights(spark):
    e = from_rows(spark, [("s", "a", 0), ("a", "s", 0), ("a", "b", 0), ("b", "t", 1), ("s", "t", 2)])
    assert asked(search.bidirectional_set(Graph.of(e), one(spark, "s", "t"))) == {0: 1}


def test_bfs_needs_fewest_rounds_and_retired_queries_keep_their_rows(spark, noise):
    _, e = noise
    a = search.bidirectional_set(Graph.of(e), pairs_of(spark))
    b = search.bidirectional_bfs(Graph.of(e), pairs_of(spark))
    total = lambda r: sum(x["forward_rounds"] + x["backward_rounds"] for x in r.answers.collect())
    assert total(b) < total(a)
    assert a.visited.groupBy("qid", "nid").count().where("count > 1").isEmpty()
    assert {r["qid"] for r in a.visited.select("qid").distinct().collect()} == set(range(8))


def test_plans_do_not_grow_with_rounds(spark, noise):
    _, e = noise
    size = lambda n: len(search.search(Graph.of(e), pairs_of(spark), "all", opts=Options(max_rounds=n)).visited._jdf.queryExecution().optimizedPlan().toString())
    assert size(4) < 3 * size(1)


def test_inserts_give_the_index_of_the_new_graph(spark, noise):
    rows, e = noise
    new = spark.createDataFrame([(1, 2, 1), (5, 40, 1)], INTS)
    after, got = segments.apply_inserts(e, segments.build(e, 5)[0], new, 5)
    want = segments.build(after, 5)[0]
    key = lambda df: sorted((r["fid"], r["tid"], r["pid"], r["cost"]) for r in df.collect())
    assert key(got) == key(want)


def test_trees_agree(spark):
    r = random.Random(4)
    rows = [(a, b, r.randint(1, 20)) for a in range(12) for b in range(a + 1, 12) if r.random() < 0.5 or b == a + 1]
    e = edges(spark.createDataFrame(rows, INTS), undirected=True).persist()
    key = lambda df: sorted((x["fid"], x["tid"], x["cost"]) for x in df.collect())
    assert key(trees.prim(e, 0)) == key(trees.boruvka(e))
    assert len(key(trees.prim(e, 0))) == 11


def test_pattern_injectivity(spark):
    nodes = spark.createDataFrame([(1, "a"), (2, "b")], "nid long, label string")
    e = spark.createDataFrame([(1, 2, 1), (2, 1, 1)], INTS)
    assert patterns.match(nodes, e, ["a", "b", "a"], [(0, 1), (1, 2)]).count() == 0
    assert patterns.match(nodes, e, ["a", "b", "a"], [(0, 1), (1, 2)], injective=False).count() == 1


def test_reach_and_levels(spark, toy):
    r = search.reachable(Graph.of(toy), spark.createDataFrame([(0, "s", "t"), (1, "t", "s")], "qid long, s string, t string"))
    assert {x["qid"]: x["reached"] for x in r.collect()} == {0: True, 1: False}
    hops = search.bfs_levels(Graph.of(toy), spark.createDataFrame([(0, "s")], "qid long, s string"), 2)
    assert {x["nid"]: x["hops"] for x in hops.collect()} == {"s": 0, "b": 1, "c": 1, "d": 1, "e": 2, "f": 2}
