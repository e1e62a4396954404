"""Point-to-point searches for a set of pairs at once, on one frontier loop.

State is one row for each (qid, nid) with labels from the source (d2s, p2s, f) and to the target (d2t, p2t, b); a null
label means unseen from that side. A round turns each live query to one side, joins its frontier with the edges of
that side and merges the result: one materialisation and one aggregate, whatever the number of queries. The state
enters each round as a leaf, so plans do not grow. What the driver holds is one control row for each query. Where a round has
little to do (one node a query) and the edge table fits in a task, the rounds run inside tasks instead: see ``inside``.
"""

from __future__ import annotations

import contextlib
import time
import uuid
from collections.abc import Iterator
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from wavefront.operators.steps import ACTIVE, CLOSED, OPEN, RULES, cheapest_sql, merge_sql, neighbours_sql
from wavefront.plans import columns, inside
from wavefront.session import conf, cut, let_go, shuffle_width

ROWS_A_PARTITION = 500_000
BROADCAST_FRONTIER = 200_000


@dataclass
class Graph:
    """``out`` is joined on fid going forward, ``back`` (fid = the edge's head) going backward; both may carry pid."""

    out: DataFrame
    back: DataFrame
    w_min: float = 1
    mirrored: bool = False  # back is out turned round

    @classmethod
    def of(cls, edges: DataFrame) -> Graph:
        return cls(edges, edges.select(F.col("tid").alias("fid"), F.col("fid").alias("tid"), "cost"), mirrored=True)


@dataclass
class Options:
    expand: str = "argmin"
    merge: str = "single"
    prune: bool = True
    direction: str = "fewer_open"  # or fewer_affected, alternate
    strict_stop: bool = False  # True: go on while lf + lb = best
    max_rounds: int = 100_000  # a search that needs more raises, unless unfinished queries may be told apart
    allow_unfinished: bool = False
    retire_share: float = 0.5
    width: int | None = None
    inside: bool | None = None  # rounds inside tasks; None: for a node at a time. Larger graphs and other dialects take statements
    columns: bool = False  # rounds inside tasks in any dialect, by its operators on column tables, where inside allows tasks


@dataclass
class Result:
    answers: DataFrame
    visited: DataFrame
    rounds: DataFrame
    seconds: dict[str, float] = field(default_factory=dict)
    unfinished: DataFrame | None = None  # qid, s, t of the queries that max_rounds cut off, where that is allowed


@contextlib.contextmanager
def rounds_conf(spark: SparkSession, rows: int, width: int | None = None) -> Iterator[None]:
    """Fixed, co-partitioned rounds: as many partitions as the edges ask for and the session allows, no re-planning."""
    n = width or max(1, min(shuffle_width(spark), -(-rows // ROWS_A_PARTITION)))
    with conf(spark, spark__sql__shuffle__partitions=str(n), spark__sql__adaptive__enabled="false", spark__sql__requireAllClusterKeysForCoPartition="false"):
        yield


INLINE_QUERIES = 400
_CONTROL = ("qid", "dir", "level", "other", "best", "bound", "mid")


def _literal(x: object) -> str:
    if x is None:
        return "null"
    if isinstance(x, str):
        escaped = x.replace("\\", "\\\\").replace("'", "\\'")
        return f"'{escaped}'"
    return repr(x)


def _control_sql(spark: SparkSession, control: list[dict], nid: T.DataType, cost: T.DataType, view: str) -> str:
    """The control rows as a table of literals, or as a view where there are many."""
    kinds = ("bigint", "string", *[cost.simpleString()] * 4, nid.simpleString())
    if len(control) > INLINE_QUERIES:
        types = (T.LongType(), T.StringType(), cost, cost, cost, cost, nid)
        rows = [tuple(c[n] for n in _CONTROL) for c in control]
        spark.createDataFrame(rows, T.StructType([T.StructField(n, k) for n, k in zip(_CONTROL, types, strict=True)])).createOrReplaceTempView(view)
        return f"select * from {view}"
    rows = ", ".join("(" + ", ".join(_literal(c[n]) for n in _CONTROL) + ")" for c in control)
    return f"select {', '.join(f'cast({n} as {k}) as {n}' for n, k in zip(_CONTROL, kinds, strict=True))} from values {rows} as t({', '.join(_CONTROL)})"


def _survey(spark: SparkSession, state: str, ends: str | None, one: bool) -> dict[int, dict]:
    """One aggregate over the state: levels, open counts, best sum and, where ``ends`` is given, the target's label."""
    target = ", min(case when nid = e.t then d2s end) as dt, max(case when nid = e.t then f end) as ft" if ends else ""
    source = f"{state} s join {ends} e on s.qid = e.qid" if ends else f"{state} s"
    mids = ", min(case when f = 0 then struct(d2s, nid) end) as mf, min(case when b = 0 then struct(d2t, nid) end) as mb" if one else ""
    rows = spark.sql(
        f"select {'/*+ broadcast(e) */ ' if ends else ''}s.qid, min(case when f = 0 then d2s end) as lf, min(case when b = 0 then d2t end) as lb, count(case when f = 0 then 1 end) as nf, count(case when b = 0 then 1 end) as nb, "
        f"min(d2s + d2t) as best, count(1) as visited{target}{mids} from {source} group by s.qid"
    )
    return {r["qid"]: r.asDict(recursive=True) for r in rows.collect()}


def search(graph: Graph, pairs: DataFrame, kind: str, sides: int = 2, threshold: float | None = None, opts: Options | None = None, radius: float | None = None, timed: bool = False) -> Result:
    """Run the loop with frontier rule ``kind``.

    ``pairs(qid, s, t)``: a null t (with sides=1) asks for all nodes within ``radius``. Answers ``(qid, s, t, distance)``
    have a row for each pair with a path; s = t is 0 after no round; ends outside the graph simply have no path. A
    qid names one query: null or repeated ones are refused. Queries still open after ``max_rounds`` are never dropped
    in silence: the search raises, or lists them in ``unfinished`` if the options allow that.
    """
    opts = opts or Options()
    spark = graph.out.sparkSession  # pairs may come from a stream's batch, which has a session of its own
    seconds = {"statistics": 0.0, "expansion": 0.0}
    edge_rows = graph.out.count()
    nid_type, cost_type = graph.out.schema["fid"].dataType, graph.out.schema["cost"].dataType
    todo = pairs.select(F.col("qid").cast("long").alias("qid"), F.col("s").cast(nid_type).alias("s"), F.col("t").cast(nid_type).alias("t"))
    listed = [r.asDict() for r in todo.collect()]
    by_qid = {r["qid"]: r for r in listed}
    if len(by_qid) < len(listed) or None in by_qid:
        raise ValueError("a qid is null or stands for several pairs")
    live = [r["qid"] for r in listed if r["s"] is not None and r["s"] != r["t"] and (sides == 1 or r["t"] is not None)]
    found: list[tuple] = [(r["qid"], r["s"], r["t"], 0, 0, 0, 0) for r in listed if r["s"] is not None and r["s"] == r["t"]]
    log: list[tuple] = []
    pair_type = T.StructType([T.StructField("qid", T.LongType()), T.StructField("s", nid_type), T.StructField("t", nid_type)])
    read = edge_rows + (graph.back.count() if sides == 2 and not graph.mirrored else 0)
    plain = (opts.expand, opts.merge) == ("argmin", "single") or columns.takes(opts, cost_type)
    if live and plain and (kind == "one" if opts.inside is None else opts.inside) and inside.fits(read, cost_type):
        return _inside(graph, spark.createDataFrame([(q, by_qid[q]["s"], by_qid[q]["t"]) for q in live], pair_type), found, read, len(live), kind, sides, threshold, opts, radius)
    ends = spark.createDataFrame([(q, by_qid[q]["s"], by_qid[q]["t"]) for q in live], pair_type)
    none = lambda kind_: F.lit(None).cast(kind_)
    label = lambda end, d, p, f, od, op, of: ends.where(F.col(end).isNotNull()).select("qid", F.col(end).alias("nid"), F.lit(0).cast(cost_type).alias(d), none(nid_type).alias(p), F.lit(OPEN).cast("byte").alias(f), none(cost_type).alias(od), none(nid_type).alias(op), none("byte").alias(of))
    names = ["qid", "nid", "d2s", "p2s", "f", "d2t", "p2t", "b"]
    state = label("s", "d2s", "p2s", "f", "d2t", "p2t", "b").select(*names)
    if sides == 2:
        state = state.unionByName(label("t", "d2t", "p2t", "b", "d2s", "p2s", "f").select(*names))
    retired: list[DataFrame] = []
    control: dict[int, dict] = {q: {"kf": 0, "kb": 0, "af": 0, "ab": 0} for q in live}
    tag = f"wavefront_{uuid.uuid4().hex[:12]}"
    views = {"f": (f"{tag}_out", "pid" if "pid" in graph.out.columns else "fid"), "b": (f"{tag}_back", "pid" if "pid" in graph.back.columns else "fid")}
    graph.out.createOrReplaceTempView(views["f"][0])
    graph.back.createOrReplaceTempView(views["b"][0])
    ends.createOrReplaceTempView(f"{tag}_ends")
    with rounds_conf(spark, edge_rows, opts.width):
        held = state = cut(state, laid_out=True)
        done_since: list[int] = []
        for number in range(1, opts.max_rounds + 2):
            began = time.time()
            state.createOrReplaceTempView(f"{tag}_state")
            stats = _survey(spark, f"{tag}_state", f"{tag}_ends" if sides == 1 else None, kind == "one") if live else {}
            seconds["statistics"] += time.time() - began
            turn: list[dict] = []
            for q in list(live):
                s, c = stats[q], control[q]
                distance, over = None, False
                if sides == 2:
                    lf, lb, best = s["lf"], s["lb"], s["best"]
                    if not s["nf"] or not s["nb"]:
                        distance, over = best, True
                    elif best is not None and (lf + lb > best or lf + lb == best and not opts.strict_stop):
                        distance, over = best, True
                else:
                    over = not s["nf"] or s["dt"] is not None and (s["ft"] == CLOSED and s["lf"] >= s["dt"] or s["lf"] >= s["dt"])
                    distance = s["dt"]
                if over:
                    live.remove(q)
                    done_since.append(q)
                    if distance is not None and by_qid[q]["t"] is not None:
                        found.append((q, by_qid[q]["s"], by_qid[q]["t"], distance, c["kf"], c["kb"], s["visited"]))
                    elif by_qid[q]["t"] is not None:
                        log.append((q, -1, "none", 0, None, None, s["visited"], 0.0))
                    continue
                way = "f" if sides == 1 else _direction(opts.direction, s, c)
                if number > opts.max_rounds:
                    continue
                c["k" + way] += 1
                k = c["k" + way]
                level = s["l" + way]
                bound = None if threshold is None else k * threshold
                mid = s["m" + way]["nid"] if kind == "one" else None
                other = s["lb" if way == "f" else "lf"] if sides == 2 else None
                turn.append({"qid": q, "dir": way, "level": level, "other": other, "best": s["best"] if sides == 2 else None, "bound": bound, "mid": mid})
                log.append((q, number, way, s["n" + way], level, s["best"], s["visited"], 0.0))
                c["was"] = s["visited"]
            if not live or number > opts.max_rounds:
                if live and not opts.allow_unfinished:
                    raise RuntimeError(f"{len(live)} queries are still open after {opts.max_rounds} rounds")
                break
            if len(done_since) >= max(1, opts.retire_share * (len(live) + len(done_since))):
                gone = spark.createDataFrame([(q,) for q in done_since], "qid long")
                retired.append(cut(state.join(F.broadcast(gone), "qid", "left_semi")))
                state = state.join(F.broadcast(gone), "qid", "left_anti")
                done_since = []
                state.createOrReplaceTempView(f"{tag}_state")
            began = time.time()
            used = {w: views[w] for w in ("f", "b") if any(c["dir"] == w for c in turn)}
            backward = [c["qid"] for c in turn if c["dir"] == "b"] if len(turn) <= INLINE_QUERIES else None
            few = sum(stats[c["qid"]]["n" + c["dir"]] for c in turn) <= BROADCAST_FRONTIER
            state = cut(spark.sql(_round_sql(f"{tag}_state", _control_sql(spark, turn, nid_type, cost_type, f"{tag}_control"), backward, used, kind, opts, radius, few)), laid_out=True)
            let_go(held)
            held = state
            spent = time.time() - began
            seconds["expansion"] += spent
            log = [(*r[:7], spent) if r[1] == number else r for r in log]
    for end in ("out", "back", "ends", "state", "control"):
        spark.catalog.dropTempView(f"{tag}_{end}")
    visited = state
    for part in retired:
        visited = visited.unionByName(part)
    cut_off = spark.createDataFrame([(q, by_qid[q]["s"], by_qid[q]["t"]) for q in live], pair_type)
    return Result(_answers(spark, found, nid_type, cost_type), visited, spark.createDataFrame(log, _log_type(cost_type)), seconds, cut_off)


def _answers(spark: SparkSession, found: list[tuple], nid: T.DataType, cost: T.DataType) -> DataFrame:
    kinds = (("qid", T.LongType()), ("s", nid), ("t", nid), ("distance", cost), ("forward_rounds", T.LongType()), ("backward_rounds", T.LongType()), ("visited", T.LongType()))
    return spark.createDataFrame(found, T.StructType([T.StructField(n, k) for n, k in kinds]))


def _log_type(cost: T.DataType) -> T.StructType:
    kinds = (("qid", T.LongType()), ("round", T.LongType()), ("dir", T.StringType()), ("open", T.LongType()), ("level", cost), ("best", cost), ("visited", T.LongType()), ("seconds", T.DoubleType()))
    return T.StructType([T.StructField(n, k) for n, k in kinds])


def _inside(graph: Graph, ends: DataFrame, found: list[tuple], rows: int, asked: int, kind: str, sides: int, threshold: float | None, opts: Options, radius: float | None) -> Result:
    """The same result from rounds inside tasks; ``found`` has the answers that need no round."""
    began = time.time()
    back = None if graph.mirrored or sides == 1 else graph.back
    r = inside.search(graph.out, back, rows, ends, asked, kind, sides, threshold, opts, radius, _direction)
    part = lambda k: r.where(F.col("what") == k)
    if (n := part(inside.CUT_OFF).count()) and not opts.allow_unfinished:
        raise RuntimeError(f"{n} queries are still open after {opts.max_rounds} rounds")
    nid, cost = (graph.out.schema[c].dataType for c in ("fid", "cost"))
    answers = part(inside.ANSWER).select("qid", F.col("nid").alias("s"), F.col("p2s").alias("t"), F.col("d2s").alias("distance"), F.col("n1").alias("forward_rounds"), F.col("n2").alias("backward_rounds"), F.col("n3").alias("visited"))
    log = part(inside.ROUND).select("qid", F.col("n1").alias("round"), inside.ways("f").alias("dir"), F.col("n2").alias("open"), F.col("d2s").alias("level"), F.col("d2t").alias("best"), F.col("n3").alias("visited"), "seconds")
    cut_off = part(inside.CUT_OFF).select("qid", F.col("nid").alias("s"), F.col("p2s").alias("t"))
    visited = part(inside.VISITED).select("qid", "nid", "d2s", "p2s", "f", "d2t", "p2t", "b")
    return Result(answers.unionByName(_answers(r.sparkSession, found, nid, cost)), visited, log, {"statistics": 0.0, "expansion": time.time() - began}, cut_off)


def _direction(how: str, s: dict, c: dict) -> str:
    if how == "alternate":
        return "f" if c["kf"] <= c["kb"] else "b"
    if how == "fewer_affected":
        grown = s["visited"] - c.get("was", 0)
        c["a" + c.get("last", "f")] = grown
        way = "f" if c["af"] <= c["ab"] else "b"
        c["last"] = way
        return way
    return "f" if s["nf"] <= s["nb"] else "b"


def _round_sql(state: str, control: str, backward: list[int] | None, tables: dict[str, tuple[str, str]], kind: str, opts: Options, radius: float | None, few: bool) -> str:
    """The statement of one round: each query's rows are seen from its side, merged, and turned back."""
    pick = lambda a, b: f"case when c.dir = 'b' then {b} else {a} end"
    seen = (
        f"select /*+ broadcast(c) */ s.qid, s.nid, {pick('d2s', 'd2t')} as d, {pick('p2s', 'p2t')} as p, {pick('f', 'b')} as f0, {pick('d2t', 'd2s')} as od, {pick('p2t', 'p2s')} as op, "
        f"{pick('b', 'f')} as of, c.dir, c.level, c.other, c.best, c.bound, c.mid from {state} s left join c on s.qid = c.qid"
    )
    flagged = f"select *, case when dir is not null and f0 = {OPEN} and {RULES[kind]} then cast({ACTIVE} as tinyint) else f0 end as f from seen"
    near = [f"(select {'/*+ broadcast(v) */ ' if few else ''}{neighbours_sql(f'front_{way}', table, parent, radius, opts.prune)[7:]})" for way, (table, parent) in tables.items()]
    fronts = ", ".join(f"front_{way} as (select qid, nid, d, other, best from flagged where f = {ACTIVE} and dir = '{way}')" for way in tables)
    # rows are turned back by a list of the queries that went backward, or by the control table where there are many
    went_back = "c.dir = 'b'" if backward is None else f"m.qid in ({', '.join(map(str, backward))})" if backward else "false"
    turn = lambda a, b: f"case when {went_back} then {b} else {a} end"
    again = " left join c on m.qid = c.qid" if backward is None else ""
    return (
        f"with c as ({control}), seen as ({seen}), flagged as ({flagged}), {fronts}, cand as ({' union all '.join(near)}), new as ({cheapest_sql('cand', opts.expand)}), "
        f"old as (select qid, nid, d, p, case when f = {ACTIVE} then cast({CLOSED} as tinyint) else f end as f, od, op, of from flagged), merged as ({merge_sql('old', 'new', opts.merge, ('od', 'op', 'of'))}) "
        f"select {'/*+ broadcast(c) */ ' if again else ''}m.qid, m.nid, {turn('d', 'od')} as d2s, {turn('p', 'op')} as p2s, {turn('f', 'of')} as f, {turn('od', 'd')} as d2t, {turn('op', 'p')} as p2t, {turn('of', 'f')} as b from merged m{again}"
    )


def dijkstra(g: Graph, pairs: DataFrame, opts: Options | None = None) -> Result:
    return search(g, pairs, "one", 1, opts=opts)


def set_dijkstra(g: Graph, pairs: DataFrame, opts: Options | None = None) -> Result:
    return search(g, pairs, "level", 1, opts=opts)


def bidirectional(g: Graph, pairs: DataFrame, opts: Options | None = None) -> Result:
    return search(g, pairs, "one", 2, opts=opts)


def bidirectional_set(g: Graph, pairs: DataFrame, opts: Options | None = None) -> Result:
    return search(g, pairs, "level", 2, opts=opts)


def bidirectional_bfs(g: Graph, pairs: DataFrame, opts: Options | None = None) -> Result:
    return search(g, pairs, "all", 2, opts=opts)


def sssp(g: Graph, sources: DataFrame, radius: float | None = None, opts: Options | None = None) -> Result:
    """Distances from each source ``(qid, s)`` to every node within ``radius``: see ``visited``."""
    target = F.lit(None).cast(g.out.schema["fid"].dataType)
    return search(g, sources.select("qid", "s", target.alias("t")), "level", 1, opts=opts, radius=radius)


def bfs_levels(g: Graph, sources: DataFrame, max_hops: int | None = None) -> DataFrame:
    """``qid, nid, hops``."""
    one = F.lit(1).cast("long").alias("cost")
    unit = Graph(g.out.select("fid", "tid", one), g.back.select("fid", "tid", one))
    return sssp(unit, sources, max_hops).visited.select("qid", "nid", F.col("d2s").alias("hops"))


def reachable(g: Graph, pairs: DataFrame) -> DataFrame:
    """``qid, s, t, reached``: does any path lead from s to t? Breadth first from both ends on unit weights."""
    one = F.lit(1).cast("long").alias("cost")
    unit = Graph(g.out.select("fid", "tid", one).persist(), g.back.select("fid", "tid", one).persist())
    hit = bidirectional_bfs(unit, pairs).answers.select("qid", F.lit(True).alias("hit"))
    return pairs.join(F.broadcast(hit), "qid", "left").select("qid", "s", "t", F.coalesce("hit", F.lit(False)).alias("reached"))


def meeting_nodes(visited: DataFrame, answers: DataFrame) -> DataFrame:
    """``qid, nid``: the least node whose two labels sum to the distance."""
    met = visited.join(F.broadcast(answers.select("qid", "distance")), "qid").where(F.col("d2s") + F.col("d2t") == F.col("distance"))
    return met.groupBy("qid").agg(F.min("nid").alias("nid"))


