"""The frontier loop as one SQL script, and searches as views: what can be had without a driver program."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from wavefront.plans.search import Graph, Result


def register(spark: SparkSession, name: str, graph: Graph, result: Result | None = None) -> list[str]:
    """Temporary views ``<name>_edges`` and ``<name>_edges_back`` and, for a search, ``<name>_answers``, ``_visited`` and ``_rounds``."""
    views = {"edges": graph.out, "edges_back": graph.back}
    if result is not None:
        views |= {"answers": result.answers, "visited": result.visited, "rounds": result.rounds}
    for suffix, df in views.items():
        df.createOrReplaceTempView(f"{name}_{suffix}")
    return [f"{name}_{suffix}" for suffix in views]


def single_source(spark: SparkSession, edges: str, source: int, most_nodes: int = 100_000) -> DataFrame:
    """``nid, d``: distances from ``source`` over the view ``edges`` (whole-number ids), a level a round, as a SQL script.

    The visited table is a variable of the script, so this is for graphs of at most ``most_nodes`` nodes; more raise.
    """
    if spark.table(edges).selectExpr("fid as n").union(spark.table(edges).selectExpr("tid")).distinct().count() > most_nodes:
        raise ValueError(f"the scripted search takes {most_nodes} nodes at most")
    return spark.sql(f"""
        BEGIN
          DECLARE seen ARRAY<STRUCT<nid: BIGINT, d: BIGINT, closed: BOOLEAN>> = array(named_struct('nid', {int(source)}L, 'd', 0L, 'closed', false));
          DECLARE near BIGINT = 0;
          WHILE near IS NOT NULL DO
            SET seen = (
              WITH v AS (SELECT inline(seen)),
                   offers AS (SELECT e.tid AS nid, min(v.d + e.cost) AS d FROM v JOIN {edges} e ON v.nid = e.fid WHERE NOT v.closed AND v.d = near GROUP BY e.tid),
                   met AS (SELECT nid, d, closed OR d = near AS closed FROM v UNION ALL SELECT nid, d, false FROM offers)
              SELECT collect_list(named_struct('nid', nid, 'd', d, 'closed', closed)) FROM (SELECT nid, min(d) AS d, bool_or(closed) AS closed FROM met GROUP BY nid));
            SET near = (SELECT min(d) FROM (SELECT inline(seen)) WHERE NOT closed);
          END WHILE;
          SELECT nid, d FROM (SELECT inline(seen));
        END
    """)
