"""What a search refuses or reports, generated graphs, the scripted loop, instruments, streams."""

import pyarrow.parquet as pq
import pytest

from wavefront.plans import probes, recover, scripted, search
from wavefront.plans.search import Graph, Options
from wavefront.sources.graphs import generated
from wavefront.sources.tables import from_rows
from wavefront.streaming import edges as stream

CHAIN = [(k, k + 1, 1) for k in range(1, 6)]


@pytest.fixture(scope="module")
def chain(spark):
    return from_rows(spark, CHAIN, "fid long, tid long, cost long").persist()


def pairs(spark, *rows):
    return spark.createDataFrame(list(rows), "qid long, s long, t long")


@pytest.mark.parametrize("rows", [[(0, 1, 3), (0, 1, 5), (1, 2, 5)], [(None, 1, 3)]])
def test_a_qid_names_one_query(spark, chain, rows):
    with pytest.raises(ValueError, match="qid"):
        search.bidirectional_set(Graph.of(chain), pairs(spark, *rows))


def test_a_round_limit_is_not_silent(spark, chain):
    asked = pairs(spark, (0, 1, 3), (1, 1, 6))
    with pytest.raises(RuntimeError, match="1 queries are still open"):
        search.set_dijkstra(Graph.of(chain), asked, Options(max_rounds=3))
    r = search.set_dijkstra(Graph.of(chain), asked, Options(max_rounds=3, allow_unfinished=True))
    assert [x["qid"] for x in r.answers.collect()] == [0] and [x["qid"] for x in r.unfinished.collect()] == [1]


def test_a_long_path_is_not_cut(spark, chain):
    r = search.set_dijkstra(Graph.of(chain), pairs(spark, (0, 1, 6)))
    links = r.visited.selectExpr("qid", "nid", "p2s as next")
    with pytest.raises(RuntimeError, match="more than 3 nodes"):
        recover._chase(links, pairs(spark, (0, 1, 6)).selectExpr("qid", "t as nid"), 3)
    assert [x["nid"] for x in recover.paths(r).orderBy("pos").collect()] == [1, 2, 3, 4, 5, 6]


def test_generated_graphs_do_not_depend_on_the_layout(spark):
    a = generated(spark, 300, skewed=True)
    assert sorted(a.collect()) == sorted(generated(spark, 300, skewed=True).repartition(7).collect())
    assert 800 < a.count() <= 900 and a.where("fid = tid or cost < 1 or cost > 20 or fid >= 300 or tid >= 300").count() == 0
    low = generated(spark, 300, skewed=True).where("tid < 75").count()
    assert low > 1.5 * generated(spark, 300).where("tid < 75").count()


def test_the_scripted_loop(spark, chain):
    assert scripted.register(spark, "line", Graph.of(chain)) == ["line_edges", "line_edges_back"]
    assert sorted(map(tuple, scripted.single_source(spark, "line_edges", 2).collect())) == [(k, k - 2) for k in range(2, 7)]


def test_steps_are_counted(spark, chain):
    with probes.watched(spark) as cost:
        visited, log = probes.stepwise(chain, spark.createDataFrame([(0, 1)], "qid long, s long"))
    assert sorted((r["nid"], r["d"]) for r in visited.collect()) == [(k, k - 1) for k in range(1, 7)]
    rows = {(r["round"], r["operator"]): r["rows"] for r in log.collect()}
    assert rows[1, "select"] == 1 and rows[1, "merge"] == 1 and rows[6, "expand"] == 0 and rows[6, "merge"] == 0
    assert cost.jobs >= 18 and cost.seconds > 0


def test_previous_events_and_late_rows(spark, tmp_path):
    rows = [(1, "2024-01-01 10:00:00", 7), (2, "2024-01-05 10:00:00", 7), (3, "2024-01-05 09:00:00", 8), (4, "2024-01-02 00:00:00", 7)]
    made = spark.createDataFrame(rows, "event_id long, ts string, user_id long").selectExpr("event_id", "cast(ts as timestamp_ntz) as ts", "user_id", "'x' as event_type", "1.0D as value", "'{}' as props")
    pq.write_table(made.toArrow(), tmp_path / "events.parquet")  # a stream reads files, not folders of them
    got = stream.run(stream.previous_events(stream.read_events(spark, str(tmp_path)))).collect()
    assert {r["event_id"]: r["previous"] for r in got} == {1: None, 4: 1, 2: 4, 3: None}
    assert stream.count_late(spark, str(tmp_path), "2 days") == 2
