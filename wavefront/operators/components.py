"""Connected components of an edge table by alternating large-star and small-star rounds.

Only edge tables move; nothing is gathered on the driver but one count and one checksum a round. Each round's least
neighbours are materialised, so the join that hands them back has a plain exchange on either side and adaptive
execution may split a hot centre's partition. Few edges take no rounds: one task joins them.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_type

from wavefront.session import cut, let_go

ONE_TASK = 250_000  # edges that a task may hold; more take rounds


def _at_once(kind: pa.DataType) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """All edges -> every node and the least node of its component: larger roots hook on to smaller ones until no edge joins two."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        read = [(b.column(0).to_numpy(zero_copy_only=False), b.column(1).to_numpy(zero_copy_only=False)) for b in batches if b.num_rows]
        if not read:
            return
        ends = np.concatenate([u for u, _ in read] + [v for _, v in read])
        ids, at = np.unique(ends, return_inverse=True)
        a, b, root = at[: len(at) // 2], at[len(at) // 2 :], np.arange(len(ids))
        while len(a):
            np.minimum.at(root, np.maximum(a, b), np.minimum(a, b))
            while (root[root] != root).any():
                root = root[root]
            a, b = root[a], root[b]
            apart = a != b
            a, b = a[apart], b[apart]
        for k in range(0, len(ids), 50_000):
            yield pa.RecordBatch.from_arrays([pa.array(x[k : k + 50_000], kind) for x in (ids, ids[root])], names=["node", "component"])

    return run


def _state(edges: DataFrame) -> tuple[int, int]:
    row = edges.agg(F.count(F.lit(1)), F.bit_xor(F.xxhash64("u", "v"))).first()
    return int(row[0]), int(row[1] or 0)


def connected_components(edges: DataFrame, max_rounds: int = 60) -> DataFrame:
    """``edges(u, v)`` of whole numbers -> ``(node, component)``: the least node reachable, for every node of an edge.

    Self-loops and nulls are dropped, repeated edges count once, an empty table gives an empty one. Nodes without
    an edge do not appear. Raises if ``max_rounds`` do not suffice (the rounds needed grow with the logarithm of
    the size).
    """
    e = edges.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).where("u > v").distinct()
    e = cut(e)
    state = _state(e)
    if 0 < state[0] <= ONE_TASK:
        kind = e.schema["u"].dataType
        found = cut(e.coalesce(1).mapInArrow(_at_once(to_arrow_type(kind)), f"node {kind.simpleString()}, component {kind.simpleString()}"))
        let_go(e)
        return found
    for _ in range(max_rounds):
        if not state[0]:
            break
        both = e.select("u", "v").unionByName(e.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = cut(both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m")))
        star = both.join(least.hint("merge"), "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v"))
        star = cut(star.where("u > v").distinct())
        lesser = cut(star.groupBy("u").agg(F.min("v").alias("m")))
        small = star.join(lesser.hint("merge"), "u").select(F.explode(F.array(F.struct(F.col("v").alias("u"), F.col("m").alias("v")), F.struct("u", F.col("m").alias("v")))).alias("p"))
        before, e = e, cut(small.select("p.u", "p.v").where("u > v").distinct())
        for read in (before, least, star, lesser):
            let_go(read)
        was, state = state, _state(e)
        if was == state:
            break
    else:
        raise RuntimeError(f"components still change after {max_rounds} rounds")
    roots = e.select(F.col("v").alias("node"), F.col("v").alias("component")).distinct()
    return e.select(F.col("u").alias("node"), F.col("v").alias("component")).unionByName(roots)
