"""The three operators of the frontier loop, each in several dialects, as SQL text over named tables.

Text, because a round is then one statement: the loop sends one string where a chain of column calls would send
hundreds. Tables: visited ``(qid, nid, d, p, f, *rest)`` keyed by (qid, nid) with sign f 0 open, 1 closed, 2 active; edges
``(fid, tid, cost)`` with an optional ``pid``, the neighbour of the far end inside a segment; candidates
``(qid, nid, cost, parent)``. Ties go to the least parent, so all dialects agree row by row.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame

OPEN, CLOSED, ACTIVE = 0, 1, 2
EXPANDS = ("argmin", "window", "aggjoin")
MERGES = ("single", "two_step", "algebra")
RULES = {
    "one": "nid = mid",
    "level": "d = level",
    "band": "(d <= bound or d = level)",
    "build": "(d < bound or d = level)",
    "all": "true",
}


def neighbours_sql(frontier: str, edges: str, parent: str = "fid", limit: float | None = None, prune: bool = False) -> str:
    """Every candidate of the frontier. ``prune`` wants columns ``other`` and ``best`` in it: a candidate that cannot
    beat the best path known, given the other side's level, goes before any shuffle."""
    tests = ([f"v.d + e.cost <= {limit}"] if limit is not None else []) + (["(v.best is null or v.other is null or v.d + e.cost + v.other < v.best)"] if prune else [])
    where = f" where {' and '.join(tests)}" if tests else ""
    return f"select v.qid, e.tid as nid, v.d + e.cost as cost, e.{parent} as parent from {frontier} v join {edges} e on v.nid = e.fid{where}"


def cheapest_sql(cand: str, dialect: str = "argmin") -> str:
    """One candidate for each (qid, nid): the least cost, then the least parent."""
    if dialect == "argmin":
        return f"select qid, nid, m.cost as cost, m.parent as parent from (select qid, nid, min(struct(cost, parent)) as m from {cand} group by qid, nid)"
    if dialect == "window":
        return f"select qid, nid, cost, parent from (select *, row_number() over (partition by qid, nid order by cost, parent) as place from {cand}) where place = 1"
    if dialect == "aggjoin":
        least = f"select qid, nid, min(cost) as cost from {cand} group by qid, nid"
        return f"select x.qid, x.nid, x.cost, min(x.parent) as parent from {cand} x join ({least}) y on x.qid = y.qid and x.nid = y.nid and x.cost = y.cost group by x.qid, x.nid, x.cost"
    raise ValueError(dialect)


_BETTER = "(n.cost is not null and (v.d is null or n.cost < v.d))"
_NEARER = "(n.cost is not null and n.cost = v.d and n.parent < v.p and v.d > 0)"


def merge_sql(visited: str, cand: str, dialect: str = "single", rest: Sequence[str] = ()) -> str:
    """Visited with candidates merged in: a lower label wins and re-opens its node, an equal one leaves the row as it
    is but for a smaller parent, unseen nodes come in open. Columns in ``rest`` stay as they are."""
    labels = f"case when {_BETTER} then n.cost else v.d end as d, case when {_BETTER} or {_NEARER} then n.parent else v.p end as p, case when {_BETTER} then cast({OPEN} as tinyint) else v.f end as f"
    own = "".join(f", v.{c}" for c in rest)
    nulls = "".join(f", null as {c}" for c in rest)
    match = "v.qid = n.qid and v.nid = n.nid"
    fresh = f"n.qid, n.nid, n.cost as d, n.parent as p, cast({OPEN} as tinyint) as f{nulls}"
    if dialect == "single":
        return f"select coalesce(v.qid, n.qid) as qid, coalesce(v.nid, n.nid) as nid, {labels}{own} from {visited} v full join {cand} n on {match}"
    if dialect == "two_step":
        updated = f"select v.qid, v.nid, {labels}{own} from {visited} v left join {cand} n on {match}"
        return f"{updated} union all select {fresh} from {cand} n left anti join {visited} v on {match}"
    if dialect == "algebra":
        columns = "".join(f", {c}" for c in ("p", "f", *rest))
        old = f"select v.qid, v.nid, v.d, v.p, v.f{own} from {visited} v left semi join {cand} n on {match} and ({_BETTER} or {_NEARER})"
        new = f"select n.qid, n.nid, n.cost, n.parent from {cand} n left semi join {visited} v on {match} and not ({_BETTER} or {_NEARER})"
        # a kept candidate takes the sign, and the columns beyond the label, of the row it replaces; both come together by
        # union and grouping, so the planner's size estimate of the state does not square from round to round
        both = (
            f"select qid, nid, cost as nd, parent as np, null as d, null as f{nulls} from (select qid, nid, cost, parent from {cand} except all {new}) union all "
            f"select qid, nid, null, null, d, f{''.join(f', {c}' for c in rest)} from ({old})"
        )
        kept = "".join(f", max({c}) as {c}" for c in rest)
        taken = f"select qid, nid, max(nd) as d, max(np) as p, case when max(d) is null or max(nd) < max(d) then cast({OPEN} as tinyint) else max(f) end as f{kept} from ({both}) group by qid, nid"
        return f"(select qid, nid, d{columns} from {visited} except all {old}) union all {taken}"
    raise ValueError(dialect)


def select_frontier(visited: DataFrame, kind: str, bound: float | None = None) -> DataFrame:
    """Frontier of a stand-alone visited table: a level, or one node, is found for each qid."""
    levels = "select qid as q, min(d) as level, min(struct(d, nid)).nid as mid from {v} where f = 0 group by qid"
    test = RULES[kind].replace("bound", "null" if bound is None else str(bound))
    return visited.sparkSession.sql(f"select /*+ broadcast(l) */ {{v}}.* from {{v}} join ({levels}) l on qid = l.q where f = 0 and {test}", v=visited)


def expand(frontier: DataFrame, edges: DataFrame, dialect: str = "argmin", limit: float | None = None, prune: bool = False) -> DataFrame:
    near = neighbours_sql("{v}", "{e}", "pid" if "pid" in edges.columns else "fid", limit, prune)
    return frontier.sparkSession.sql(f"with cand as ({near}) {cheapest_sql('cand', dialect)}", v=frontier, e=edges)


def merge(visited: DataFrame, cand: DataFrame, dialect: str = "single") -> DataFrame:
    rest = [c for c in visited.columns if c not in ("qid", "nid", "d", "p", "f")]
    return visited.sparkSession.sql(merge_sql("{v}", "{n}", dialect, rest), v=visited, n=cand)
