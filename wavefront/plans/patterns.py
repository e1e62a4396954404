"""Graph patterns over labelled data: one query node a step, tuples of data nodes that widen by one."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def match(nodes: DataFrame, edges: DataFrame, labels: Sequence[str | None], links: Sequence[tuple[int, int]], injective: bool = True) -> DataFrame:
    """Tuples ``m0..mk`` of data nodes: ``labels[i]`` is the label of query node i (None: any), ``links`` its directed
    edges between query nodes. Each later node must be linked to an earlier one. ``injective`` asks for distinct
    data nodes. ``nodes(nid, label)``, ``edges(fid, tid, ...)``.
    """
    ends = edges.select("fid", "tid").distinct()

    def labelled(i: int, df: DataFrame, column: str) -> DataFrame:
        if labels[i] is None:
            return df
        return df.join(nodes.where(F.col("label") == labels[i]).select(F.col("nid").alias(column)), column, "left_semi")

    found = labelled(0, nodes.select(F.col("nid").alias("m0")), "m0")
    for k in range(1, len(labels)):
        own = [(a, b) for a, b in links if max(a, b) == k and a != b]
        if not own:
            raise ValueError(f"query node {k} is not linked to an earlier one")
        a, b = own[0]
        step = ends.select(F.col("fid").alias(f"m{a}"), F.col("tid").alias(f"m{b}"))
        found = labelled(k, found.join(step, f"m{min(a, b)}"), f"m{k}")
        for a, b in own[1:]:
            found = found.join(ends.select(F.col("fid").alias(f"m{a}"), F.col("tid").alias(f"m{b}")), [f"m{a}", f"m{b}"], "left_semi")
        if injective:
            for j in range(k):
                found = found.where(F.col(f"m{j}") != F.col(f"m{k}"))
    return found.select(*(f"m{i}" for i in range(len(labels))))
