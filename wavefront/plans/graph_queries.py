"""Queries on the derived graphs, each with the statement by which DuckDB gets the same rows."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from wavefront.operators import steps
from wavefront.plans import local, patterns, recover, search, segments, trees
from wavefront.plans.search import Graph, Options
from wavefront.sources.graphs import GRAPHS, kept, query_pairs
from wavefront.sources.tables import table

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLE: dict[str, str] = {}


def add(name: str, oracle: str | None = None) -> Callable[[Query], Query]:
    def put(f: Query) -> Query:
        QUERIES[name] = f
        if oracle:
            ORACLE[name] = oracle
        return f

    return put


# ---- the same graphs in DuckDB


def _chain_sql(key: str, k: int, tid: str = "tid") -> str:
    lead = f"select {key} as fid, lead({key}) over (partition by l_orderkey order by l_linenumber, l_partkey, l_suppkey, l_quantity, l_extendedprice) as tid, cast(l_quantity as bigint) as cost from lineitem where l_orderkey % {k} = 0"
    return f"select fid, tid, min(cost) as cost from (select fid, {tid} as tid, cost from ({lead}) where tid is not null) where fid <> tid group by fid, tid"


def _both(sql: str) -> str:
    return f"select fid, tid, min(cost) as cost from (select fid, tid, cost from ({sql}) union all select tid, fid, cost from ({sql})) where fid <> tid group by fid, tid"


def _generated_sql(nodes: str, seed: int, skewed: bool = False, degree: int = 3, heaviest: int = 20) -> str:
    drawn = f"select unnest(range(n * {degree})) as i, n from (select {nodes} as n)"
    step = lambda at: f"select i, n, {', '.join(f'(xor(x{k}, x{k} >> 16) * 73244475) % 2147483648 as x{k}' for k in range(3))} from ({at})"
    start = f"select cast(i as bigint) as i, cast(n as bigint) as n, {', '.join(f'((i * 3 + {k}) * 2654435 + {seed}) % 2147483648 as x{k}' for k in range(3))} from ({drawn})"
    last = f"select n, {', '.join(f'xor(x{k}, x{k} >> 15) as x{k}' for k in range(3))} from ({step(step(start))})"
    end = "(x1 % n) * (x1 % n) // n" if skewed else "x1 % n"
    return f"select fid, tid, min(cost) as cost from (select x0 % n as fid, {end} as tid, 1 + x2 % {heaviest} as cost from ({last})) where fid <> tid group by fid, tid"


_TRADE = "select o_custkey * 2 as fid, l_partkey * 2 + 1 as tid, cast(l_quantity as bigint) as cost from lineitem join orders on l_orderkey = o_orderkey"
_WEB = "select 'p:' || cast(page_id as varchar) as fid, 'h:' || href as tid, cast(1 + (page_id * 31 + length(href)) % 30 as bigint) as cost from (select distinct page_id, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) as href from pages)"
_CO = "select a.p as fid, b.p as tid, cast(1 + (a.p + b.p) % 50 as bigint) as cost from (select distinct l_orderkey o, l_partkey p from lineitem where l_orderkey % 8 = 0) a join (select distinct l_orderkey o, l_partkey p from lineitem where l_orderkey % 8 = 0) b on a.o = b.o and a.p < b.p"
_NATION = "select fid, tid, cost from (select cast(c_nationkey as bigint) as fid, cast(s_nationkey as bigint) as tid, cast(sum(cast(l_quantity as bigint)) % 97 + 1 as bigint) as cost from lineitem join orders on l_orderkey = o_orderkey join customer on o_custkey = c_custkey join supplier on l_suppkey = s_suppkey group by 1, 2) where cost <= 25 and fid <> tid"
_POWER = "(tid * tid) // (select count(*) from part)"
GRAPH_SQL: dict[str, str] = {
    "random": _chain_sql("l_partkey", 8),
    "random_dense": _chain_sql("l_partkey", 1),
    "power": _chain_sql("l_partkey", 8, _POWER),
    "power_dense": _chain_sql("l_partkey", 1, _POWER),
    "coorder": _both(_CO),
    "coorder_dense": _both(_CO.replace(" where l_orderkey % 8 = 0", "")),
    "web": _both(_WEB),
    "nation": _NATION,
    "nation_undirected": _both(_NATION),
    "supplier": _chain_sql("l_suppkey", 64),
    "supplier_dense": _chain_sql("l_suppkey", 1),
    "trade": _both(_TRADE),
    "eventline": "select fid, tid, min(cost) as cost from (select event_id as fid, lead(event_id) over w as tid, cast((floor(epoch(lead(ts) over w))::bigint - floor(epoch(ts))::bigint) // 3600 + 1 as bigint) as cost from events window w as (partition by user_id order by ts, event_id)) where tid is not null group by fid, tid",
    "gen_random": _generated_sql("(select count(*) from part)", 1),
    "gen_random_half": _generated_sql("(select count(*) // 2 from part)", 1),
    "gen_power": _generated_sql("(select count(*) from part)", 2, True),
    "gen_power_half": _generated_sql("(select count(*) // 2 from part)", 2, True),
    "gen_power_small": _generated_sql("(select count(*) from supplier)", 2, True),
}


def pairs_sql(q: int) -> str:
    return f"select qid, s, t from (select i as qid, (i * 7919 + 17) % n as s, (i * 104729 + 1031) % n as t from range({q}) r(i), (select count(*) as n from part)) where s <> t"


def distances_sql(edges: str, pairs: str) -> str:
    """CTEs e, pairs and sp(qid, node, dist): exact distances from each pair's source."""
    return (
        f"with recursive e as ({edges}), pairs as ({pairs}), sp(qid, node, dist) using key (qid, node) as (select qid, s, cast(0 as bigint) from pairs union "
        "select x.qid, e.tid, cast(min(x.dist + e.cost) as bigint) from sp x join e on x.node = e.fid left join recurring.sp r on r.qid = x.qid and r.node = e.tid where r.dist is null or x.dist + e.cost < r.dist group by x.qid, e.tid) "
    )


def answers_sql(edges: str, pairs: str) -> str:
    return distances_sql(edges, pairs) + "select p.qid, sp.dist as distance from pairs p join sp on p.qid = sp.qid and p.t = sp.node"


# ---- graphs and their figures

for _name in GRAPHS:
    add(f"g_{_name}_edges", GRAPH_SQL[_name])(lambda s, d, n=_name: kept(s, d, n).select("fid", "tid", "cost"))

_STATS = ("random", "power", "coorder", "nation", "supplier", "trade", "eventline")


@add("g_stats_nodes_edges", " union all ".join(f"select '{n}' as graph, count(*) as edges, (select count(*) from (select fid from ({GRAPH_SQL[n]}) union select tid from ({GRAPH_SQL[n]}))) as nodes, min(cost) as w_min from ({GRAPH_SQL[n]})" for n in _STATS))
def g_stats(s: SparkSession, d: str) -> DataFrame:
    out = None
    for n in _STATS:
        e = kept(s, d, n)
        nodes = e.select("fid").union(e.select("tid")).distinct().agg(F.count(F.lit(1)).alias("nodes"))
        row = e.agg(F.count(F.lit(1)).alias("edges"), F.min("cost").alias("w_min")).crossJoin(nodes).select(F.lit(n).alias("graph"), "edges", "nodes", "w_min")
        out = row if out is None else out.unionByName(row)
    return out


@add("g_degree_dist", f"select degree, count(*) as nodes from (select tid, count(*) as degree from ({GRAPH_SQL['power']}) group by tid) group by degree")
def g_degrees(s: SparkSession, d: str) -> DataFrame:
    return kept(s, d, "power").groupBy("tid").agg(F.count(F.lit(1)).alias("degree")).groupBy("degree").agg(F.count(F.lit(1)).alias("nodes"))


# ---- operators on a fixed snapshot: node 1, its neighbours expanded, theirs open


def snapshot(s: SparkSession, d: str) -> DataFrame:
    """Visited after two hops from node 1 on the dense random graph: hop 1 closed, hop 2 open."""
    e = kept(s, d, "random_dense")
    return s.sql(
        "with one as (select tid as nid, cost as d, cast(1 as bigint) as p from {e} where fid = 1), two as (select e.tid as nid, min(struct(o.d + e.cost as d, o.nid as p)) as m from one o join {e} e on o.nid = e.fid where e.tid <> 1 group by e.tid) "
        "select cast(0 as bigint) as qid, nid, d, p, cast(1 as tinyint) as f from one union all select cast(0 as bigint), t.nid, m.d, m.p, cast(0 as tinyint) from two t left anti join one o on t.nid = o.nid",
        e=e,
    )


_SNAP = (
    f"with e as ({GRAPH_SQL['random_dense']}), one as (select tid as nid, cost as d, 1 as p from e where fid = 1), cand2 as (select e.tid as nid, o.d + e.cost as d, o.nid as p from one o join e on o.nid = e.fid where e.tid <> 1), "
    "two as (select nid, d, p from (select *, row_number() over (partition by nid order by d, p) as k from cand2) where k = 1 and nid not in (select nid from one)), "
    "v as (select nid, d, p, 1 as f from one union all select nid, d, p, 0 from two), lev as (select min(d) as m from v where f = 0)"
)
_FRONT = {"one": "d = m and nid = (select min(nid) from v, lev where f = 0 and d = m)", "level": "d = m", "band": "(d <= 10 or d = m)", "build": "(d < 10 or d = m)", "all": "true"}
for _kind, _test in _FRONT.items():
    add(f"op_select_{_kind}", f"{_SNAP} select nid, d from v, lev where f = 0 and {_test}")(lambda s, d, k=_kind: steps.select_frontier(snapshot(s, d), k, 10).select("nid", "d"))

_CAND = "near as (select e.tid as nid, v.d + e.cost as cost, e.fid as parent from v join e on v.nid = e.fid where f = 0 {extra}), cand as (select nid, cost, parent from (select *, row_number() over (partition by nid order by cost, parent) as k from near) where k = 1)"


def _expanded(s: SparkSession, d: str, **how) -> DataFrame:
    front = steps.select_frontier(snapshot(s, d), "all")
    if how.get("prune"):
        front = front.select("*", F.lit(3).cast("long").alias("other"), F.lit(25).cast("long").alias("best"))
    return steps.expand(front, kept(s, d, "random_dense"), **how)


for _how in steps.EXPANDS:
    add(f"op_expand_{_how}", f"{_SNAP}, {_CAND.format(extra='')} select nid, cost, parent from cand")(lambda s, d, h=_how: _expanded(s, d, dialect=h).select("nid", "cost", "parent"))
add("op_expand_bounded", f"{_SNAP}, {_CAND.format(extra='and v.d + e.cost <= 20')} select nid, cost, parent from cand")(lambda s, d: _expanded(s, d, limit=20).select("nid", "cost", "parent"))
add("op_expand_pruned", f"{_SNAP}, {_CAND.format(extra='and v.d + e.cost + 3 < 25')} select nid, cost, parent from cand")(lambda s, d: _expanded(s, d, prune=True).select("nid", "cost", "parent"))
for _how in steps.MERGES:
    add(
        f"op_merge_{_how}",
        f"{_SNAP}, {_CAND.format(extra='')} select coalesce(v.nid, c.nid) as nid, case when v.d is null or c.cost < v.d then c.cost else v.d end as d, case when v.d is null or c.cost < v.d or (c.cost = v.d and c.parent < v.p) then c.parent else v.p end as p, "
        "cast(case when v.d is null or c.cost < v.d then 0 else v.f end as bigint) as f from v full join cand c on v.nid = c.nid",
    )(lambda s, d, h=_how: steps.merge(snapshot(s, d), _expanded(s, d), h).select("nid", "d", "p", F.col("f").cast("long").alias("f")))


# ---- shortest paths

_graph_kept: dict[tuple, Graph] = {}


def graph(s: SparkSession, d: str, name: str, threshold: int | None = None, opts: Options | None = None) -> Graph:
    key = (s.sparkContext.applicationId, d, name, threshold)
    if key not in _graph_kept:
        e = kept(s, d, name)
        g = Graph.of(e) if threshold is None else segments.index(e, threshold, opts)
        _graph_kept[key] = replace(g, out=g.out.persist(), back=g.back.persist())
    return _graph_kept[key]


def node_pairs(s: SparkSession, d: str, name: str, q: int) -> DataFrame:
    """Arithmetic pairs over the ids of graphs whose nodes are not parts."""
    if name.startswith("supplier") or name.endswith("_small"):
        n = table(s, d, "supplier").count()
    elif name.endswith("_half"):
        n = table(s, d, "part").count() // 2
    elif name in ("nation", "nation_undirected"):
        n = 25
    else:
        return query_pairs(s, d, q)
    i = F.col("id")
    return s.range(q).select(i.alias("qid"), ((i * 7919 + 17) % n).alias("s"), ((i * 104729 + 1031) % n).alias("t")).where("s <> t")


def node_pairs_sql(name: str, q: int) -> str:
    n = "(select count(*) as n from supplier)" if name.startswith("supplier") or name.endswith("_small") else "(select count(*) // 2 as n from part)" if name.endswith("_half") else "(select 25 as n)" if name.startswith("nation") else None
    return pairs_sql(q) if n is None else f"select qid, s, t from (select i as qid, (i * 7919 + 17) % n as s, (i * 104729 + 1031) % n as t from range({q}) r(i), {n}) where s <> t"


def _sp(name: str, on: str, run: Callable, q: int = 10, threshold: int | None = None) -> None:
    @add(name, answers_sql(GRAPH_SQL[on], node_pairs_sql(on, q)))
    def ask(s: SparkSession, d: str) -> DataFrame:
        return run(graph(s, d, on, threshold), node_pairs(s, d, on, q)).answers.select("qid", "distance")


_sp("sp_dijkstra", "nation", search.dijkstra, 4)
_sp("sp_dijkstra_supplier", "supplier", search.dijkstra, 4)
_sp("sp_set_dijkstra", "random_dense", search.set_dijkstra)
_sp("sp_bidirectional", "supplier", search.bidirectional, 6)
_sp("sp_bidirectional_nation", "nation", search.bidirectional, 6)
_sp("sp_bidirectional_set", "random", search.bidirectional_set, 20)
_sp("sp_bidirectional_set_power", "power", search.bidirectional_set, 20)
_sp("sp_bidirectional_set_noprune", "random_dense", lambda g, p: search.bidirectional_set(g, p, Options(prune=False)))
_sp("sp_bidirectional_set_strict_stop", "random_dense", lambda g, p: search.bidirectional_set(g, p, Options(strict_stop=True)))
_sp("sp_direction_fewer_affected", "random_dense", lambda g, p: search.bidirectional_set(g, p, Options(direction="fewer_affected")))
_sp("sp_direction_alternate", "random_dense", lambda g, p: search.bidirectional_set(g, p, Options(direction="alternate")))
_sp("sp_bidirectional_bfs", "random", search.bidirectional_bfs, 20)
_sp("sp_bidirectional_bfs_coorder", "coorder", search.bidirectional_bfs, 20)
_sp("sp_undirected", "coorder", search.bidirectional_set, 10)
_sp("sp_undirected_dense", "coorder_dense", search.bidirectional_set, 10)
_sp("sp_bidirectional_dense", "supplier_dense", search.bidirectional, 6)
for _l in (5, 10, 20):
    _sp(f"sp_segmented_{_l}", "random", lambda g, p, x=_l: segments.segmented(g, p, x), 20, _l)
_sp("sp_segmented_power_10", "power", lambda g, p: segments.segmented(g, p, 10), 20, 10)
_sp("sp_hundred_pairs", "random", lambda g, p: segments.segmented(g, p, 20), 100, 20)
_sp("sp_traditional", "power", lambda g, p: search.bidirectional_bfs(g, p, Options(expand="aggjoin", merge="two_step")))
_sp("sp_algebra", "power", lambda g, p: search.bidirectional_bfs(g, p, Options(expand="aggjoin", merge="algebra")))
_sp("sp_modern", "power", lambda g, p: search.bidirectional_bfs(g, p, Options(expand="window", merge="single")))
_sp("sp_nomerge", "power", lambda g, p: search.bidirectional_bfs(g, p, Options(expand="window", merge="two_step")))

_WEB_PAIRS = "select i as qid, 'p:' || cast((i * 5 + 7) % n as varchar) as s, 'p:' || cast((i * 5 + 67) % n as varchar) as t from range(8) r(i), (select count(*) as n from pages)"


@add("sp_segmented_web", answers_sql(GRAPH_SQL["web"], _WEB_PAIRS))
def sp_web(s: SparkSession, d: str) -> DataFrame:
    n, i = table(s, d, "pages").count(), F.col("id")
    name = lambda x: F.concat(F.lit("p:"), x.cast("string"))
    pairs = s.range(8).select(i.alias("qid"), name((i * 5 + 7) % n).alias("s"), name((i * 5 + 67) % n).alias("t"))
    return segments.segmented(graph(s, d, "web", 4), pairs, 4).answers.select("qid", "distance")


_TRADE_PAIRS = "select i as qid, ((i * 37 + 5) % n) * 2 as s, ((i * 101 + 9) % n) * 2 as t from range(8) r(i), (select count(*) as n from customer)"


@add("sp_trade_bfs", answers_sql(GRAPH_SQL["trade"], _TRADE_PAIRS))
def sp_trade(s: SparkSession, d: str) -> DataFrame:
    return search.bidirectional_bfs(graph(s, d, "trade"), trade_pairs(s, d)).answers.select("qid", "distance")


def trade_pairs(s: SparkSession, d: str) -> DataFrame:
    n, i = table(s, d, "customer").count(), F.col("id")
    return s.range(8).select(i.alias("qid"), (((i * 37 + 5) % n) * 2).alias("s"), (((i * 101 + 9) % n) * 2).alias("t"))


@add("sp_segmented_trade", answers_sql(GRAPH_SQL["trade"], _TRADE_PAIRS))
def sp_segmented_trade(s: SparkSession, d: str) -> DataFrame:
    return segments.segmented(graph(s, d, "trade", 2), trade_pairs(s, d), 2).answers.select("qid", "distance")


for _n, _f in (("dijkstra", local.dijkstra), ("bidirectional", local.bidirectional)):
    add(f"sp_local_{_n}", answers_sql(GRAPH_SQL["random"], pairs_sql(100)))(lambda s, d, f=_f: f(kept(s, d, "random"), query_pairs(s, d, 100)).select("qid", "distance"))

_ODD = "select * from (values (0, 5, 5), (1, 999999999, 5), (2, 5, 999999999)) v(qid, s, t)"


@add("sp_special_cases", f"select cast(0 as bigint) as qid, cast(0 as bigint) as distance where exists ({_ODD})")
def sp_special(s: SparkSession, d: str) -> DataFrame:
    odd = s.createDataFrame([(0, 5, 5), (1, 999999999, 5), (2, 5, 999999999)], "qid long, s long, t long")
    return search.bidirectional_set(graph(s, d, "power"), odd).answers.select("qid", "distance")


@add("sp_unreachable", f"{distances_sql(GRAPH_SQL['power'], pairs_sql(30))} select p.qid from pairs p anti join sp on p.qid = sp.qid and p.t = sp.node")
def sp_unreachable(s: SparkSession, d: str) -> DataFrame:
    pairs = query_pairs(s, d, 30)
    found = search.bidirectional_bfs(graph(s, d, "power"), pairs).answers
    return pairs.join(found.select("qid"), "qid", "left_anti").select("qid")


# ---- paths

_CANON = (
    distances_sql(GRAPH_SQL["supplier"], node_pairs_sql("supplier", 4))
    + ", tight as (select a.qid, e.tid as node, min(e.fid) as prev from e join sp a on a.node = e.fid join sp b on b.qid = a.qid and b.node = e.tid where a.dist + e.cost = b.dist group by 1, 2), "
    "walk(qid, node, k) as (select p.qid, p.t, 0 from pairs p join sp on p.qid = sp.qid and p.t = sp.node union all select w.qid, t.prev, w.k + 1 from walk w join tight t on w.qid = t.qid and w.node = t.node join pairs p on p.qid = w.qid where w.node <> p.s) "
    "select qid, cast(max(k) over (partition by qid) - k as bigint) as pos, node as nid from walk"
)


@add("path_canonical", _CANON)
def path_canonical(s: SparkSession, d: str) -> DataFrame:
    found = search.set_dijkstra(graph(s, d, "supplier"), node_pairs(s, d, "supplier", 4))
    return recover.paths(found).select("qid", F.col("pos").cast("long").alias("pos"), "nid")


@add("path_recursive_cte", _CANON)
def path_recursive(s: SparkSession, d: str) -> DataFrame:
    found = search.set_dijkstra(graph(s, d, "supplier"), node_pairs(s, d, "supplier", 4))
    return recover.paths_by_recursion(found).select("qid", F.col("pos").cast("long").alias("pos"), "nid")


_REPRICE = distances_sql(GRAPH_SQL["random"], pairs_sql(10)) + "select p.qid, sp.dist as path_cost, sp.dist as distance from pairs p join sp on p.qid = sp.qid and p.t = sp.node"


@add("path_reprice", _REPRICE)
def path_reprice(s: SparkSession, d: str) -> DataFrame:
    found = search.bidirectional_bfs(graph(s, d, "random"), query_pairs(s, d, 10))
    cost = recover.priced(recover.paths(found), kept(s, d, "random"))
    return cost.join(found.answers, "qid").select("qid", F.col("cost").alias("path_cost"), "distance")


@add("path_reprice_segmented", _REPRICE)
def path_reprice_segmented(s: SparkSession, d: str) -> DataFrame:
    found = segments.segmented(graph(s, d, "random", 20), query_pairs(s, d, 10), 20)
    # a segment's parent is the node inside it next to its end, so every hop of the chain is an edge
    cost = recover.priced(recover.paths(found), kept(s, d, "random"))
    return cost.join(found.answers, "qid").select("qid", F.col("cost").alias("path_cost"), "distance")


# ---- index


def _index_sql(edges: str, l: int, back: bool) -> str:
    e = f"select tid as fid, fid as tid, cost from ({edges})" if back else edges
    return (
        f"with recursive e as ({e}), b(src, nid, d) as (select fid, tid, cost from e where cost <= {l} union select b.src, e.tid, b.d + e.cost from b join e on b.nid = e.fid where b.d + e.cost <= {l}), "
        "sp as (select src, nid, min(d) as d from b where src <> nid group by src, nid), zero as (select src, nid, d from sp union all select distinct fid, fid, 0 from e), "
        "tight as (select z.src, e.tid as nid, min(e.fid) as pid from zero z join e on z.nid = e.fid join sp on sp.src = z.src and sp.nid = e.tid where z.d + e.cost = sp.d group by 1, 2) "
        "select sp.src as fid, sp.nid as tid, t.pid, sp.d as cost from sp join tight t on sp.src = t.src and sp.nid = t.nid union all select fid, tid, fid, cost from e where not exists (select 1 from sp where sp.src = e.fid and sp.nid = e.tid)"
    )


for _l, _back in ((5, False), (10, False), (10, True)):
    add(f"idx_{'in' if _back else 'out'}_{_l}", _index_sql(GRAPH_SQL["random"], _l, _back))(lambda s, d, x=_l, b=_back: (graph(s, d, "random", x).back if b else graph(s, d, "random", x).out).select("fid", "tid", "pid", "cost"))


@add("idx_size_sweep", " union all ".join(f"select cast({x} as bigint) as threshold, count(*) as segments from ({_index_sql(GRAPH_SQL['power'], x, False)})" for x in (5, 10, 20)))
def idx_sweep(s: SparkSession, d: str) -> DataFrame:
    out = None
    for x in (5, 10, 20):
        row = segments.build(kept(s, d, "power"), x)[0].agg(F.count(F.lit(1)).alias("segments")).select(F.lit(x).cast("long").alias("threshold"), "segments")
        out = row if out is None else out.unionByName(row)
    return out


@add("idx_after_inserts", _index_sql(f"select fid, tid, min(cost) as cost from (select * from ({GRAPH_SQL['random']}) union all select * from (values (1::bigint, 2::bigint, 1::bigint), (2, 40, 2), (77, 3, 1)) v(fid, tid, cost)) group by fid, tid", 10, False))
def idx_inserts(s: SparkSession, d: str) -> DataFrame:
    new = s.createDataFrame([(1, 2, 1), (2, 40, 2), (77, 3, 1)], "fid long, tid long, cost long")
    return segments.apply_inserts(kept(s, d, "random"), graph(s, d, "random", 10).out, new, 10)[1]


# ---- other searches


@add("reach_pairs", f"{distances_sql(GRAPH_SQL['random'], pairs_sql(20))} select p.qid, sp.node is not null as reached from pairs p left join sp on p.qid = sp.qid and p.t = sp.node")
def reach_pairs(s: SparkSession, d: str) -> DataFrame:
    return search.reachable(graph(s, d, "random"), query_pairs(s, d, 20)).select("qid", "reached")


@add("bfs_levels", f"{distances_sql('select fid, tid, cast(1 as bigint) as cost from (' + GRAPH_SQL['random'] + ')', 'select 0 as qid, 1 as s, -1 as t')} select node as nid, dist as hops from sp where dist <= 4")
def bfs_levels(s: SparkSession, d: str) -> DataFrame:
    one = s.createDataFrame([(0, 1)], "qid long, s long")
    return search.bfs_levels(graph(s, d, "random"), one, 4).select("nid", "hops")


@add("sssp_radius", f"{distances_sql(GRAPH_SQL['random_dense'], 'select 0 as qid, 1 as s, -1 as t')} select node as nid, dist as distance from sp where dist <= 15")
def sssp_radius(s: SparkSession, d: str) -> DataFrame:
    one = s.createDataFrame([(0, 1)], "qid long, s long")
    return search.sssp(graph(s, d, "random_dense"), one, 15).visited.where("d2s is not null").select("nid", F.col("d2s").alias("distance"))


_MST = (
    f"with recursive e as ({GRAPH_SQL['nation_undirected']}), k as (select fid, tid, cost, cost * 10000 + least(fid, tid) * 100 + greatest(fid, tid) as w from e), "
    "r(a, w, node) as (select fid, w, fid from k where fid < tid union select r.a, r.w, k.tid from r join k on r.node = k.fid where k.w < r.w) "
    "select k.fid, k.tid, k.cost from k where k.fid < k.tid and not exists (select 1 from r where r.a = k.fid and r.w = k.w and r.node = k.tid)"
)
add("mst_prim", _MST)(lambda s, d: trees.prim(kept(s, d, "nation_undirected"), 0))
add("mst_boruvka", _MST)(lambda s, d: trees.boruvka(kept(s, d, "nation_undirected")))


# ---- patterns


def star(s: SparkSession, d: str) -> tuple[DataFrame, DataFrame]:
    """Entities of the given tables as labelled nodes, foreign keys as edges."""
    t = lambda n: table(s, d, n)
    node = lambda df, mark, key, label: df.select(F.concat(F.lit(mark), F.col(key).cast("string")).alias("nid"), label.alias("label"))
    link = lambda df, m1, k1, m2, k2: df.select(F.concat(F.lit(m1), F.col(k1).cast("string")).alias("fid"), F.concat(F.lit(m2), F.col(k2).cast("string")).alias("tid")).distinct()
    nodes = node(t("customer"), "c", "c_custkey", F.col("c_mktsegment"))
    for df, m, k, label in ((t("part"), "p", "p_partkey", F.col("p_brand")), (t("orders"), "o", "o_orderkey", F.lit("order")), (t("nation"), "n", "n_nationkey", F.lit("nation")), (t("supplier"), "s", "s_suppkey", F.lit("supplier"))):
        nodes = nodes.unionByName(node(df, m, k, label))
    edges = link(t("orders"), "c", "o_custkey", "o", "o_orderkey").unionByName(link(t("lineitem"), "o", "l_orderkey", "p", "l_partkey"))
    return nodes, edges.unionByName(link(t("customer"), "c", "c_custkey", "n", "c_nationkey")).unionByName(link(t("supplier"), "s", "s_suppkey", "n", "s_nationkey"))


def brands(s: SparkSession, d: str) -> DataFrame:
    return table(s, d, "part").select(F.col("p_partkey").alias("nid"), F.col("p_brand").alias("label"))


@add("pattern_path", "select distinct 'c' || o_custkey as m0, 'o' || o_orderkey as m1, 'p' || l_partkey as m2 from orders join customer on o_custkey = c_custkey join lineitem on l_orderkey = o_orderkey join part on p_partkey = l_partkey where c_mktsegment = (select min(c_mktsegment) from customer) and p_brand = (select min(p_brand) from part)")
def pattern_path(s: SparkSession, d: str) -> DataFrame:
    nodes, edges = star(s, d)
    segment = table(s, d, "customer").agg(F.min("c_mktsegment")).first()[0]
    brand = table(s, d, "part").agg(F.min("p_brand")).first()[0]
    return patterns.match(nodes, edges, [segment, "order", brand], [(0, 1), (1, 2)])


_TRI = f"with e as ({GRAPH_SQL['coorder']}), b as (select distinct p_brand from part order by p_brand limit 3) select a.fid as m0, a.tid as m1, c.tid as m2 from e a join e c on a.tid = c.fid join e x on x.fid = a.fid and x.tid = c.tid join part p on p.p_partkey = a.fid join part q on q.p_partkey = a.tid join part r on r.p_partkey = c.tid where a.fid <> c.tid and p.p_brand = (select min(p_brand) from b) and q.p_brand = (select p_brand from b order by p_brand limit 1 offset 1) and r.p_brand = (select max(p_brand) from b)"


@add("pattern_triangle", _TRI)
def pattern_triangle(s: SparkSession, d: str) -> DataFrame:
    three = [r[0] for r in table(s, d, "part").select("p_brand").distinct().orderBy("p_brand").limit(3).collect()]
    return patterns.match(brands(s, d), kept(s, d, "coorder"), three, [(0, 1), (1, 2), (0, 2)])


@add("pattern_star_labels", "select 'n' || n_nationkey as m0, 'c' || c_custkey as m1, 's' || s_suppkey as m2 from nation join customer on c_nationkey = n_nationkey join supplier on s_nationkey = n_nationkey where c_mktsegment = (select min(c_mktsegment) from customer)")
def pattern_star(s: SparkSession, d: str) -> DataFrame:
    nodes, edges = star(s, d)
    segment = table(s, d, "customer").agg(F.min("c_mktsegment")).first()[0]
    return patterns.match(nodes, edges, ["nation", segment, "supplier"], [(1, 0), (2, 0)])


@add("pattern_noninjective", f"with e as ({GRAPH_SQL['coorder']}) select a.fid as m0, a.tid as m1, c.tid as m2 from e a join e c on a.tid = c.fid join part p on p.p_partkey = a.fid join part r on r.p_partkey = c.tid where p.p_brand = (select min(p_brand) from part) and r.p_brand = (select min(p_brand) from part)")
def pattern_noninjective(s: SparkSession, d: str) -> DataFrame:
    brand = table(s, d, "part").agg(F.min("p_brand")).first()[0]
    return patterns.match(brands(s, d), kept(s, d, "coorder"), [brand, None, brand], [(0, 1), (1, 2)], injective=False)


@add("tour_nearest_neighbour")
def tour(s: SparkSession, d: str) -> DataFrame:
    return local.nearest_neighbour_tour(kept(s, d, "nation_undirected"), 0)
