"""Tasks that hold a whole edge table as adjacency arrays and take a share of the work.

The edges reach every task from their own partitions, never through the driver. How many tasks hold a copy at a time
is bounded by bytes, so a large graph has fewer and longer tasks.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from wavefront.session import conf, cut

COPY_BYTES = 1_200_000_000  # of all copies together
EDGE_BYTES = 100  # of an edge while its arrays are made
MOST_COPIES = 8
OUT, BACK, ASKED = 0, 1, 2  # kinds of rows that a task reads: edges by their tail, by their head; queries


@dataclass
class Adjacency:
    """``ids`` ascend, so numbers compare as ids do. A side is (start, to, parent, cost); a null parent is the edge's own tail."""

    ids: np.ndarray
    sides: list[tuple]
    asked: list[tuple]

    def numbers(self, found: list) -> dict:
        """Ids to numbers; those outside the graph come after all others."""
        at = np.searchsorted(self.ids, np.array(found, dtype=self.ids.dtype)) if len(self.ids) and found else []
        out, n = {}, len(self.ids)
        for x, k in zip(found, [int(k) for k in at] if len(self.ids) else [n] * len(found), strict=True):
            if x not in out:
                out[x] = k if k < len(self.ids) and self.ids[k] == x else n
                n += out[x] == n
        return out


def _view(a: np.ndarray):
    return a.tolist() if a.dtype == object else memoryview(np.ascontiguousarray(a))


def _column(c: pa.ChunkedArray | pa.Array) -> np.ndarray:
    return c.to_numpy(zero_copy_only=False)


def adjacency(batches: Iterator[pa.RecordBatch], mirrored: bool, segments: bool) -> Adjacency:
    parts: dict[int, list] = {OUT: [], BACK: []}
    asked: list[tuple] = []
    for batch in batches:
        what = _column(batch.column("what"))
        if (what == ASKED).any():
            rows = batch.filter(pa.array(what == ASKED))
            asked += zip(*(rows.column(n).to_pylist() for n in ("qid", "fid", "tid")), strict=True)
        for side in (OUT, BACK):
            if (what == side).any():
                e = batch if (what == side).all() else batch.filter(pa.array(what == side))
                parts[side].append([_column(e.column(n)) for n in (("fid", "tid", "cost", "pid") if segments else ("fid", "tid", "cost"))])
    empty = np.array([], dtype="int64")
    tables = {}
    for side in (OUT, BACK):
        columns = list(zip(*parts[side], strict=True))
        parts[side] = []
        tables[side] = [np.concatenate(c) for c in columns] or [empty] * (4 if segments else 3)
    ends = [np.unique(c) for side in tables for c in (tables[side][0], tables[side][1], *tables[side][3:]) if len(c)]
    ids = np.unique(np.concatenate(ends)) if ends else empty
    number = lambda c: np.searchsorted(ids, c).astype("int32") if len(c) else np.array([], dtype="int32")
    # columns become numbers one at a time, and each one's ids go, so that a task holds few of them at once
    for side in tables:
        for k in (0, 1, 3)[: len(tables[side])]:
            if k < len(tables[side]):
                tables[side][k] = number(tables[side][k])
    if mirrored:
        f, t, c = tables[OUT][:3]
        tables[BACK] = [t, f, c]
    sides = []
    for side in (OUT, BACK):
        f, t, c, *p = tables[side]
        order = np.argsort(f, kind="stable")
        start = np.zeros(len(ids) + 1, dtype="int64")
        np.cumsum(np.bincount(f, minlength=len(ids)), out=start[1:])
        sides.append((_view(start), _view(t[order]), _view(p[0][order]) if p else None, _view(c[order])))
    return Adjacency(ids, sides, asked)


def copies(edge_rows: int) -> int:
    return int(max(1, min(MOST_COPIES, COPY_BYTES // (EDGE_BYTES * max(1, edge_rows)))))


def share(out: DataFrame, back: DataFrame | None, pairs: DataFrame | None, parts: int, work: Callable[[Adjacency, int], Iterator[pa.RecordBatch]], schema: str) -> DataFrame:
    """``work(adjacency, task)`` in ``parts`` tasks. Each has all edges (``back`` is ``out`` turned round where None) and those
    of ``pairs(qid, s, t)`` that are dealt to it by a hash of qid. Edges should be kept: every task reads them. The result is
    made at once: a union of single partitions would otherwise be planned as one partition, and its shares run one after another."""
    segments = "pid" in out.columns
    id_kind, cost_kind = (out.schema[c].dataType for c in ("fid", "cost"))
    none = lambda kind: F.lit(None).cast(kind)
    kind = lambda k: F.lit(k).cast("int").alias("what")
    edge = lambda e, k: e.select(kind(k), none("long").alias("qid"), "fid", "tid", (F.col("pid") if segments else none(id_kind)).alias("pid"), "cost")
    rows = [edge(out, OUT)] + ([edge(back, BACK)] if back is not None else [])
    found = None
    for task in range(parts):
        own = list(rows)
        if pairs is not None:
            mine = pairs.where(F.pmod(F.xxhash64("qid"), F.lit(parts)) == task)
            own.append(mine.select(kind(ASKED), F.col("qid").cast("long").alias("qid"), F.col("s").cast(id_kind).alias("fid"), F.col("t").cast(id_kind).alias("tid"), none(id_kind).alias("pid"), none(cost_kind).alias("cost")))
        read = own[0]
        for more in own[1:]:
            read = read.unionByName(more)

        def run(batches: Iterator[pa.RecordBatch], task: int = task, mirrored: bool = back is None) -> Iterator[pa.RecordBatch]:
            yield from work(adjacency(batches, mirrored, segments), task)

        part = read.coalesce(1).mapInArrow(run, schema)
        found = part if found is None else found.unionByName(part)
    with conf(out.sparkSession, spark__sql__unionOutputPartitioning="false"):
        return cut(found.select("*"))
