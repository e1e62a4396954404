"""The loop's operators on the toy graph and on hand cases; dialects agree row by row."""

import pytest

from wavefront.operators import steps
from wavefront.sources.graphs import TOY
from wavefront.sources.tables import edges, from_rows

VISITED = "qid long, nid string, d long, p string, f tinyint"


def rows(df, *columns):
    return sorted(tuple(r[c] for c in columns) for r in df.collect())


def test_edges_keep_least_parallel_and_drop_loops(spark):
    e = edges(from_rows(spark, [("a", "b", 3), ("a", "b", 1), ("a", "a", 1)]))
    assert rows(e, "fid", "tid", "cost") == [("a", "b", 1)]


def test_negative_weight_is_refused(spark):
    with pytest.raises(Exception, match="negative"):
        edges(from_rows(spark, [("a", "b", -1)])).collect()


def second_round(spark):
    """After s: b, c, d are seen; c is the least."""
    return spark.createDataFrame([(0, "s", 0, None, 1), (0, "b", 4, "s", 0), (0, "c", 1, "s", 0), (0, "d", 3, "s", 0)], VISITED)


def test_select_rules(spark):
    v = second_round(spark)
    names = lambda kind, bound=None: [r[0] for r in rows(steps.select_frontier(v, kind, bound), "nid")]
    assert names("one") == ["c"]
    assert names("level") == ["c"]
    assert names("band", 3) == ["c", "d"]
    assert names("build", 3) == ["c"]
    assert names("all") == ["b", "c", "d"]


@pytest.mark.parametrize("dialect", steps.EXPANDS)
def test_expand_finds_cheapest_with_parent(spark, dialect):
    got = steps.expand(steps.select_frontier(second_round(spark), "all"), from_rows(spark, TOY), dialect)
    assert rows(got, "nid", "cost", "parent") == [("d", 2, "c"), ("e", 4, "c"), ("f", 8, "d")]


@pytest.mark.parametrize("dialect", steps.EXPANDS)
def test_expand_tie_takes_least_parent(spark, dialect):
    v = spark.createDataFrame([(0, "x", 1, None, 0), (0, "a", 1, None, 0)], VISITED)
    got = steps.expand(v, from_rows(spark, [("x", "t", 2), ("a", "t", 2)]), dialect)
    assert rows(got, "nid", "cost", "parent") == [("t", 3, "a")]


@pytest.mark.parametrize("dialect", steps.MERGES)
def test_merge_cases(spark, dialect):
    v = spark.createDataFrame([(0, "a", 5, "s", 1), (0, "b", 5, "s", 1), (0, "c", 5, "s", 1), (0, "d", 5, "s", 0)], VISITED)
    n = spark.createDataFrame([(0, "a", 4, "z"), (0, "b", 5, "z"), (0, "c", 5, "a"), (0, "e", 9, "z")], "qid long, nid string, cost long, parent string")
    got = rows(steps.merge(v, n, dialect), "nid", "d", "p", "f")
    # a improves and re-opens; b keeps its row at an equal label; c only takes the smaller parent; e comes in open
    assert got == [("a", 4, "z", 0), ("b", 5, "s", 1), ("c", 5, "a", 1), ("d", 5, "s", 0), ("e", 9, "z", 0)]


def test_window_expand_plans_a_group_limit(spark):
    plan = steps.expand(second_round(spark), from_rows(spark, TOY), "window")._jdf.queryExecution().executedPlan().toString()
    assert "WindowGroupLimit" in plan
