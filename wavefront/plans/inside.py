"""The frontier loop inside tasks: the same rounds as the statements of ``search``, with no Spark job for each.

Queries do not touch each other's rows, so a task that holds the edge table can take some of them through all their
rounds. Select, expand and merge are those of ``wavefront.operators.steps``, rule by rule: answers, visited rows and the log of
rounds are equal to those of the loop over tables.
"""

from __future__ import annotations

import heapq
import time
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.pandas.types import to_arrow_schema

from wavefront.operators.steps import CLOSED, OPEN
from wavefront.plans import columns as by_columns
from wavefront.plans.replicated import Adjacency, copies, share

MOST_EDGES = 8_000_000
VISITED, ANSWER, ROUND, CUT_OFF = 0, 1, 2, 3
_WAYS = {"f": 0, "b": 1, "none": -1}


def fits(rows: int, cost: T.DataType) -> bool:
    return rows <= MOST_EDGES and isinstance(cost, (T.LongType, T.IntegerType, T.DoubleType))


class Side:
    """Labels of one direction. ``heap`` has every open node under its label, and stale entries."""

    def __init__(self, start: int):
        self.d, self.p, self.f = {start: 0}, {start: None}, {start: OPEN}
        self.open = 1
        self.heap = [(0, start)]

    def level(self):
        while self.heap and not (self.f[self.heap[0][1]] == OPEN and self.d[self.heap[0][1]] == self.heap[0][0]):
            heapq.heappop(self.heap)
        return self.heap[0][0] if self.heap else None

    def select(self, kind: str, level, bound) -> list:
        if kind == "all":
            taken = [u for u, f in self.f.items() if f == OPEN]
            self.heap = []
        else:
            taken, top = [], level if bound is None or kind != "band" else max(level, bound)
            while self.level() is not None and self.heap[0][0] <= top:
                taken.append(heapq.heappop(self.heap)[1])
                self.f[taken[-1]] = CLOSED
                if kind == "one":
                    break
        for u in taken:
            self.f[u] = CLOSED
        self.open -= len(taken)
        return taken


def run(g: Adjacency, s: int, t: int | None, kind: str, sides: int, threshold, opts, radius, direction: Callable) -> tuple:
    """One query: ``(state, distance or None, rounds by side, visited, log, finished)``."""
    at = [Side(s), Side(t)] if sides == 2 else [Side(s)]
    visited, best, log = sides, None, []
    c: dict = {"kf": 0, "kb": 0, "af": 0, "ab": 0}
    for number in range(1, opts.max_rounds + 2):
        began = time.perf_counter()
        level = [x.level() for x in at]
        now = {"nf": at[0].open, "nb": at[1].open if sides == 2 else 0, "visited": visited}
        if sides == 2:
            over = not at[0].open or not at[1].open or best is not None and (level[0] + level[1] > best or level[0] + level[1] == best and not opts.strict_stop)
            distance = best
        else:
            distance = at[0].d.get(t) if t is not None else None
            over = not at[0].open or distance is not None and level[0] >= distance
        if over:
            return at, distance, c, visited, log, True
        if number > opts.max_rounds:
            break
        way = "f" if sides == 1 else direction(opts.direction, now, c)
        w = _WAYS[way]
        c["k" + way] += 1
        me, you = at[w], at[1 - w] if sides == 2 else None
        other = level[1 - w] if sides == 2 else None
        log.append((number, w, me.open, level[w], best, visited))
        c["was"] = visited
        start, to, par, cost = g.sides[w]
        prune = opts.prune and best is not None and other is not None
        new: dict = {}
        for u in me.select(kind, level[w], None if threshold is None else c["k" + way] * threshold):
            if u >= len(g.ids):
                continue
            d = me.d[u]
            for k in range(start[u], start[u + 1]):
                x = d + cost[k]
                if radius is not None and x > radius or prune and x + other >= best:
                    continue
                v, p = to[k], u if par is None else par[k]
                if v not in new or (x, p) < new[v]:
                    new[v] = (x, p)
        for v, (x, p) in new.items():
            old = me.d.get(v)
            if old is None or x < old:
                me.open += me.f.get(v) != OPEN
                visited += old is None and (you is None or v not in you.d)
                me.d[v], me.p[v], me.f[v] = x, p, OPEN
                heapq.heappush(me.heap, (x, v))
                if you is not None and v in you.d and (best is None or x + you.d[v] < best):
                    best = x + you.d[v]
            elif x == old and old > 0 and me.p[v] is not None and p < me.p[v]:
                me.p[v] = p
        log[-1] = (*log[-1], time.perf_counter() - began)
    return at, None, c, visited, log, False


def search(out: DataFrame, back: DataFrame | None, rows: int, pairs: DataFrame, asked: int, kind: str, sides: int, threshold, opts, radius, direction: Callable) -> DataFrame:
    """Rows ``what, qid, nid, d2s, p2s, f, d2t, p2t, b, n1, n2, n3``: visited rows as they stand in the state; answers (s, t, distance,
    rounds by side, visited); rounds (level, best, side; number, open, visited); queries that the round limit cut off."""
    nid, cost = (out.schema[c].dataType for c in ("fid", "cost"))
    schema = T.StructType([T.StructField("what", T.IntegerType()), T.StructField("qid", T.LongType()), *(T.StructField(n, k) for n, k in (("nid", nid), ("d2s", cost), ("p2s", nid), ("f", T.ByteType()), ("d2t", cost), ("p2t", nid), ("b", T.ByteType()))), *(T.StructField(n, T.LongType()) for n in ("n1", "n2", "n3")), T.StructField("seconds", T.DoubleType())])
    arrow = to_arrow_schema(schema)

    def work(g: Adjacency, _: int) -> Iterator[pa.RecordBatch]:
        ids = g.ids
        at = g.numbers([x for _, s, t in g.asked for x in (s, t) if x is not None])
        names = {v: k for k, v in at.items() if v >= len(ids)}
        name = lambda u: None if u is None else names[u] if u >= len(ids) else ids[u].item() if hasattr(ids[u], "item") else ids[u]
        ends = [(at[s], None if t is None else at[t]) for _, s, t in g.asked]
        if by_columns.takes(opts, cost):
            results = by_columns.run(g, ends, kind, sides, threshold, opts, radius, direction)
        else:
            results = ((i, run(g, *e, kind, sides, threshold, opts, radius, direction)) for i, e in enumerate(ends))
        for i, (state, distance, c, visited, log, finished) in results:
            q, s, t = g.asked[i]
            a, b = state[0], state[1] if sides == 2 else None
            seen = list(a.d) + ([u for u in b.d if u not in a.d] if b else [])
            side = lambda x: ([x.d.get(u) for u in seen], [name(x.p.get(u)) for u in seen], [x.f.get(u) for u in seen]) if x else ([None] * len(seen),) * 3
            none = [None] * len(seen)
            columns = [[VISITED] * len(seen), [q] * len(seen), [name(u) for u in seen], *side(a), *side(b), none, none, none, none]
            extra = [(ROUND, q, None, r[3], None, r[1], r[4], None, None, r[0], r[2], r[5], r[6]) for r in log]
            if not finished:
                extra.append((CUT_OFF, q, s, None, t, None, None, None, None, None, None, None, None))
            elif t is not None and distance is not None:
                extra.append((ANSWER, q, s, distance, t, None, None, None, None, c["kf"], c["kb"], visited, None))
            elif t is not None:
                extra.append((ROUND, q, None, None, None, _WAYS["none"], None, None, None, -1, 0, visited, 0.0))
            columns = [[*x, *(r[k] for r in extra)] for k, x in enumerate(columns)]
            yield pa.RecordBatch.from_arrays([pa.array(x, type=f.type) for x, f in zip(columns, arrow, strict=True)], schema=arrow)

    kinds = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in schema)
    return share(out, back, pairs, min(copies(rows), asked), work, kinds)


def ways(column: str) -> F.Column:
    return F.when(F.col(column) == 0, "f").when(F.col(column) == 1, "b").otherwise("none")
