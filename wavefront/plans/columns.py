"""Rounds inside tasks in every dialect: the operators of ``steps`` as relational operators on column tables.

A side's state is a table ``(k, d, p, f)``, where ``k`` is the number of a query and of a node in one, so it holds the rows that its
side has seen and a null label does not occur. Each dialect takes the joins, aggregates, sorts and differences that its SQL text
names; rows are equal in all of them and equal to those of the statements. All queries of a task go through a round together.
"""

from __future__ import annotations

import time
from collections.abc import Callable, Iterator
from types import SimpleNamespace

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import types as T

from wavefront.operators.steps import CLOSED, EXPANDS, MERGES, OPEN
from wavefront.plans.replicated import Adjacency

BLOCK = 50_000  # sources of an index build that go through the rounds together
_MOST = 1 << 62


def takes(opts, cost: T.DataType) -> bool:
    return opts.columns and opts.expand in EXPANDS and opts.merge in MERGES and isinstance(cost, (T.LongType, T.IntegerType))


def _array(t: pa.Table, name: str) -> np.ndarray:
    return t.column(name).to_numpy()


def _table(k: np.ndarray, d: np.ndarray, p: pa.Array | pa.ChunkedArray, f: np.ndarray) -> pa.Table:
    return pa.table({"k": pa.array(k, pa.int64()), "d": pa.array(d, pa.int64()), "p": p, "f": pa.array(f, pa.int8())})


def start_rows(k: np.ndarray) -> pa.Table:
    return _table(k, np.zeros(len(k), "int64"), pa.nulls(len(k), pa.int64()), np.full(len(k), OPEN, "int8"))


def neighbours(side: tuple, nodes: int, n: int, k: np.ndarray, d: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Candidates ``(k, cost, parent)`` of the frontier's rows; ``n`` numbers a query, nodes from ``nodes`` on have no edges."""
    start, to, par, cost = side
    inner = k % n < nodes
    k, d = k[inner], d[inner]
    start, u = np.asarray(start), k % n
    many = start[u + 1] - start[u]
    at = np.repeat(start[u] - np.cumsum(many) + many, many) + np.arange(many.sum())
    own = np.repeat(u, many)
    return np.repeat(k - u, many) + np.asarray(to)[at], np.repeat(d, many) + np.asarray(cost)[at].astype("int64"), own if par is None else np.asarray(par)[at].astype("int64")


def cheapest(cand: pa.Table, dialect: str) -> pa.Table:
    """One candidate for each k: the least cost, then the least parent."""
    if dialect == "argmin":  # one aggregate; the pair is one whole number where it fits in one
        cost, parent = _array(cand, "cost"), _array(cand, "parent")
        width = int(parent.max(initial=0)) + 1
        if int(cost.max(initial=0)) >= _MOST // width:
            least: dict[int, tuple] = {}
            for k, *pair in zip(_array(cand, "k").tolist(), cost.tolist(), parent.tolist(), strict=True):
                if k not in least or tuple(pair) < least[k]:
                    least[k] = tuple(pair)
            return pa.table({"k": pa.array(least, pa.int64()), "cost": pa.array([c for c, _ in least.values()], pa.int64()), "parent": pa.array([p for _, p in least.values()], pa.int64())})
        m = pa.table({"k": cand["k"], "m": cost * width + parent}).group_by("k", use_threads=False).aggregate([("m", "min")])
        both = _array(m, "m_min")
        return pa.table({"k": m["k"], "cost": both // width, "parent": both % width})
    if dialect == "window":
        rows = cand.sort_by([("k", "ascending"), ("cost", "ascending"), ("parent", "ascending")])
        k = _array(rows, "k")
        first = np.flatnonzero(np.diff(k, prepend=k[:1] - 1))
        place = np.arange(len(k)) - np.repeat(first, np.diff(first, append=len(k))) + 1
        return rows.filter(pa.array(place == 1))
    if dialect == "aggjoin":
        least = cand.group_by("k", use_threads=False).aggregate([("cost", "min")])
        met = cand.join(least, ["k", "cost"], ["k", "cost_min"], "inner", use_threads=False)
        return met.group_by(["k", "cost"], use_threads=False).aggregate([("parent", "min")]).rename_columns(["k", "cost", "parent"])
    raise ValueError(dialect)


def _tests(j: pa.Table) -> tuple[pa.Array, pa.Array]:
    """Whether a candidate beats the label of its row, and whether it only has a smaller parent."""
    there = pc.is_valid(j["cost"])
    better = pc.and_(there, pc.or_(pc.is_null(j["d"]), pc.fill_null(pc.less(j["cost"], j["d"]), False)))
    equal = pc.and_(pc.fill_null(pc.equal(j["cost"], j["d"]), False), pc.fill_null(pc.greater(j["d"], 0), False))
    return better, pc.and_(equal, pc.fill_null(pc.less(j["parent"], j["p"]), False))


def _labels(j: pa.Table) -> pa.Table:
    better, nearer = _tests(j)
    p = pc.if_else(pc.or_(better, nearer), j["parent"], j["p"])
    return pa.table({"k": j["k"], "d": pc.if_else(better, j["cost"], j["d"]), "p": p, "f": pc.if_else(better, pa.scalar(OPEN, pa.int8()), j["f"])})


def _fresh(n: pa.Table) -> pa.Table:
    return _table(_array(n, "k"), _array(n, "cost"), n["parent"], np.full(len(n), OPEN, "int8"))


def merged(old: pa.Table, new: pa.Table, dialect: str) -> pa.Table:
    """``old`` with the candidates merged in, as ``steps.merge_sql`` does it. Both are keyed by k, so differences go by k."""
    if not len(new):
        return old
    join = lambda a, b, kind: a.join(b, "k", join_type=kind, use_threads=False)
    if dialect == "single":
        return _labels(join(old, new, "full outer"))
    if dialect == "two_step":
        return pa.concat_tables([_labels(join(old, new, "left outer")), _fresh(join(new, old.select(["k"]), "left anti"))])
    if dialect == "algebra":
        met = join(old, new, "inner")
        wins = pc.or_(*_tests(met))
        gone = join(old, met.filter(wins).select(["k"]), "left semi")
        kept = join(new, met.filter(pc.invert(wins)).select(["k"]), "left anti")
        none = lambda t, kind: pa.nulls(len(t), kind)
        both = pa.concat_tables(
            [
                pa.table({"k": kept["k"], "nd": kept["cost"], "np": kept["parent"], "d": none(kept, pa.int64()), "f": none(kept, pa.int8())}),
                pa.table({"k": gone["k"], "nd": none(gone, pa.int64()), "np": none(gone, pa.int64()), "d": gone["d"], "f": gone["f"]}),
            ]
        )
        g = both.group_by("k", use_threads=False).aggregate([(c, "max") for c in ("nd", "np", "d", "f")])
        opened = pc.or_(pc.is_null(g["d_max"]), pc.fill_null(pc.less(g["nd_max"], g["d_max"]), False))
        taken = pa.table({"k": g["k"], "d": g["nd_max"], "p": g["np_max"], "f": pc.if_else(opened, pa.scalar(OPEN, pa.int8()), g["f_max"])})
        return pa.concat_tables([join(old, gone.select(["k"]), "left anti"), taken])
    raise ValueError(dialect)


def turned(state: pa.Table, active: np.ndarray, cand: tuple, opts) -> pa.Table:
    """State after a round: its active rows closed, the candidates merged in."""
    f = np.where(active, CLOSED, _array(state, "f")).astype("int8")
    old = _table(_array(state, "k"), _array(state, "d"), state["p"], f)
    return merged(old, cheapest(pa.table(dict(zip(("k", "cost", "parent"), cand, strict=True))), opts.expand), opts.merge)


def near(g: Adjacency, sources: np.ndarray, threshold: float, step: int, opts) -> pa.Table:
    """State of all nodes within ``threshold`` of each source, by the rounds of an index build; k has the source's place in it."""
    n = max(1, len(g.ids))
    state, number = start_rows(np.arange(len(sources)) * n + sources), 0
    while True:
        k, d, f = (_array(state, c) for c in ("k", "d", "f"))
        if not (f == OPEN).any():
            return state
        number += 1
        active = (f == OPEN) & ((d < number * step) | (d == d[f == OPEN].min()))
        cand = neighbours(g.sides[0], n, n, k[active], d[active])
        inside = cand[1] <= threshold
        state = turned(state, active, tuple(c[inside] for c in cand), opts)


def run(g: Adjacency, ends: list[tuple[int, int | None]], kind: str, sides: int, threshold, opts, radius, direction: Callable) -> Iterator[tuple]:
    """For each query ``(its place, what inside.run returns for it)``, as they end."""
    if not ends:
        return
    n = max(len(g.ids), 1 + max(x for e in ends for x in e if x is not None))
    at = [start_rows(np.array([i * n + e[w] for i, e in enumerate(ends)], "int64")) for w in range(sides)]
    live, control, log = set(range(len(ends))), [{"kf": 0, "kb": 0, "af": 0, "ab": 0} for _ in ends], [[] for _ in ends]

    def rows_of(i: int) -> list:
        out = []
        for x in at:
            own = x.filter(pa.array(_array(x, "k") // n == i))
            node = (_array(own, "k") - i * n).tolist()
            out.append(SimpleNamespace(**{c: dict(zip(node, own[c].to_pylist(), strict=True)) for c in ("d", "p", "f")}))
        return out

    for number in range(1, opts.max_rounds + 2):
        began = time.perf_counter()
        seen = [_survey(x, n, len(ends)) for x in at]
        met = at[0].join(at[1].select(["k", "d"]), "k", join_type="inner", right_suffix="_b", use_threads=False) if sides == 2 else None
        best: dict[int, int] = {}
        twice = np.zeros(len(ends), "int64")
        if met is not None and len(met):
            q, total = _array(met, "k") // n, _array(met, "d") + _array(met, "d_b")
            np.add.at(twice, q, 1)
            least = np.full(len(ends), np.iinfo("int64").max)
            np.minimum.at(least, q, total)
            best = {i: int(least[i]) for i in np.flatnonzero(twice).tolist()}
        turn: list[dict[int, tuple]] = [{}, {}]
        ended = []
        for i in sorted(live):
            level = [s[0].get(i) for s in seen]
            opened = [int(s[1][i]) for s in seen]
            visited = sum(int(s[2][i]) for s in seen) - int(twice[i])
            if sides == 2:
                distance = best.get(i)
                over = not opened[0] or not opened[1] or distance is not None and (sum(level) > distance or sum(level) == distance and not opts.strict_stop)
            else:
                distance = seen_at(at[0], i * n + ends[i][1]) if ends[i][1] is not None else None
                over = not opened[0] or distance is not None and level[0] >= distance
            if over or number > opts.max_rounds:
                yield i, (rows_of(i), distance if over else None, control[i], visited, log[i], over)
                ended.append(i)
                continue
            c = control[i]
            now = {"nf": opened[0], "nb": opened[1] if sides == 2 else 0, "visited": visited}
            way = "f" if sides == 1 else direction(opts.direction, now, c)
            w = 0 if way == "f" else 1
            c["k" + way] += 1
            c["was"] = visited
            log[i].append((number, w, opened[w], level[w], best.get(i), visited))
            turn[w][i] = (level[w], level[1 - w] if sides == 2 else None, best.get(i) if sides == 2 else None, None if threshold is None else c["k" + way] * threshold)
        live.difference_update(ended)
        if not live:
            return
        if ended:
            at = [x.filter(pa.array(~np.isin(_array(x, "k") // n, ended))) for x in at]
        for w in range(sides):
            if turn[w]:
                at[w] = _turn(g, w, at[w], n, len(ends), turn[w], kind, opts, radius)
        spent = time.perf_counter() - began
        for i in live:
            log[i][-1] = (*log[i][-1], spent)


def seen_at(state: pa.Table, k: int) -> int | None:
    found = _array(state, "d")[_array(state, "k") == k]
    return int(found[0]) if len(found) else None


def _survey(state: pa.Table, n: int, asked: int) -> tuple[dict[int, int], np.ndarray, np.ndarray]:
    """Levels, open rows and rows by query."""
    q, open_ = _array(state, "k") // n, _array(state, "f") == OPEN
    level = np.full(asked, np.iinfo("int64").max)
    np.minimum.at(level, q[open_], _array(state, "d")[open_])
    count = np.bincount(q[open_], minlength=asked)
    return {i: int(level[i]) for i in np.flatnonzero(count).tolist()}, count, np.bincount(q, minlength=asked)


def _turn(g: Adjacency, w: int, state: pa.Table, n: int, asked: int, turn: dict[int, tuple], kind: str, opts, radius) -> pa.Table:
    k, d, f = (_array(state, c) for c in ("k", "d", "f"))
    q = k // n
    column = lambda at, none: np.array([none if i not in turn or turn[i][at] is None else turn[i][at] for i in range(asked)])
    level, other, best, bound = column(0, -1), column(1, 0), column(2, -1), column(3, -1)
    active = (f == OPEN) & np.isin(q, list(turn))
    if kind == "one":
        mine = np.flatnonzero(active & (d == level[q]))
        mine = mine[np.argsort(k[mine])]
        active[:] = False
        active[mine[np.unique(q[mine], return_index=True)[1]]] = True
    elif kind != "all":
        active &= (d == level[q]) | (d <= bound[q] if kind == "band" else False)
    cand = neighbours(g.sides[w], len(g.ids), n, k[active], d[active])
    at, keep = cand[0] // n, np.ones(len(cand[0]), bool)
    if radius is not None:
        keep &= cand[1] <= radius
    if opts.prune:
        known = np.array([i in turn and turn[i][1] is not None and turn[i][2] is not None for i in range(asked)])
        keep &= ~known[at] | (cand[1] + other[at] < best[at])
    return turned(state, active, tuple(c[keep] for c in cand), opts)
