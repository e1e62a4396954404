"""The relational operators around the methods, one query each on the given tables, with DuckDB's statement."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from wavefront.functions import paths
from wavefront.plans.graph_queries import GRAPH_SQL, Query
from wavefront.session import shared_folder
from wavefront.sources.graphs import kept
from wavefront.sources.tables import read_edges, table, write_edges

QUERIES: dict[str, Query] = {}
ORACLE: dict[str, str] = {}


def _sql(name: str, spark_sql: str, oracle: str | None = None) -> None:
    """A query whose statement both engines read alike (or with an own one for DuckDB)."""

    def run(s: SparkSession, d: str) -> DataFrame:
        used = [t for t in ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "labels", "conversations") if "{" + t + "}" in spark_sql]
        frames = {t: table(s, d, t) for t in used}
        if "{supplier_edges}" in spark_sql:
            frames["supplier_edges"] = kept(s, d, "supplier")
        if "{random_edges}" in spark_sql:
            frames["random_edges"] = kept(s, d, "random")
        return s.sql(spark_sql, **frames)

    QUERIES[name] = run
    plain = oracle or spark_sql
    for t in ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "labels", "conversations"):
        plain = plain.replace("{" + t + "}", t)
    ORACLE[name] = plain.replace("{supplier_edges}", f"({GRAPH_SQL['supplier']})").replace("{random_edges}", f"({GRAPH_SQL['random']})")


_MONEY = "cast(sum(cast(l_extendedprice * 100 as bigint)) as bigint)"
_sql("rel_scan_filter_project", "select l_orderkey, l_linenumber, cast(l_quantity as bigint) as quantity from {lineitem} where l_quantity < 10 and l_discount between 0.03 and 0.05")
for _hint, _how in (("hash", "shuffle_hash(o)"), ("merge", "merge(o)"), ("broadcast", "broadcast(c)")):
    _body = "n_name, cast(count(*) as bigint) as orders, cast(sum(cast(round(o_totalprice * 100) as bigint)) as bigint) as cents from {orders} o join {customer} c on o.o_custkey = c.c_custkey join {nation} n on c.c_nationkey = n.n_nationkey group by n_name"
    _sql(f"rel_join_inner_{_hint}", f"select /*+ {_how} */ {_body}", f"select {_body}")
_sql("rel_join_left", "select d.doc_id, l.quality, l.toxic from {documents} d left join {labels} l on d.doc_id = l.doc_id")
_sql("rel_join_full", "select coalesce(a.p, b.p) as part, coalesce(a.n, 0) as early, coalesce(b.n, 0) as late from (select l_partkey as p, count(*) as n from {lineitem} where l_linenumber = 1 group by l_partkey) a full join (select l_partkey as p, count(*) as n from {lineitem} where l_linenumber > 4 group by l_partkey) b on a.p = b.p")
_sql("rel_join_semi", "select o_orderkey from {orders} left semi join {lineitem} on o_orderkey = l_orderkey and l_returnflag = 'R'", "select o_orderkey from orders where exists (select 1 from lineitem where o_orderkey = l_orderkey and l_returnflag = 'R')")
_sql("rel_join_anti", "select o_orderkey from {orders} left anti join {lineitem} on o_orderkey = l_orderkey and l_returnflag = 'R'", "select o_orderkey from orders where not exists (select 1 from lineitem where o_orderkey = l_orderkey and l_returnflag = 'R')")
_sql("rel_join_theta", "select a.n_nationkey as a, b.n_nationkey as b from {nation} a join {nation} b on a.n_regionkey = b.n_regionkey and a.n_nationkey < b.n_nationkey")
_sql("rel_join_range", "select o_orderkey, band from {orders} join (values (1, 0.0, 50000.0), (2, 50000.0, 150000.0), (3, 150000.0, 1e12)) v(band, lo, hi) on o_totalprice >= lo and o_totalprice < hi")
_sql(
    "rel_join_interval",
    "select p.event_id as purchase, c.event_id as click from {events} p join {events} c on p.user_id = c.user_id where p.event_type = 'purchase' and c.event_type = 'click' and c.ts <= p.ts and p.ts <= c.ts + interval 1 hour",
)


def _asof(s: SparkSession, d: str) -> DataFrame:
    """Each purchase with the user's latest view at or before it: one window over both, no range join."""
    e = table(s, d, "events").where("event_type in ('purchase', 'view')")
    view = F.when(F.col("event_type") == "view", F.struct("ts", "event_id"))
    # at equal times views come first, then by id
    order = Window.partitionBy("user_id").orderBy("ts", F.when(F.col("event_type") == "view", 0).otherwise(1), "event_id").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return e.withColumn("v", F.last(view, ignorenulls=True).over(order)).where("event_type = 'purchase'").select(F.col("event_id").alias("purchase"), F.col("v.event_id").alias("view"))


QUERIES["rel_join_asof"] = _asof
ORACLE["rel_join_asof"] = 'select p.event_id as purchase, (select v.event_id from events v where v.user_id = p.user_id and v.event_type = \'view\' and v.ts <= p.ts order by v.ts desc, v.event_id desc limit 1) as "view" from events p where p.event_type = \'purchase\''
_sql("rel_agg_hash", "select l_returnflag, l_linestatus, cast(count(*) as bigint) as n, cast(sum(cast(l_quantity as bigint)) as bigint) as quantity from {lineitem} group by l_returnflag, l_linestatus")
_sql("rel_agg_distinct", "select l_suppkey, cast(count(distinct l_partkey) as bigint) as parts from {lineitem} group by l_suppkey")
QUERIES["rel_agg_approx"] = lambda s, d: table(s, d, "lineitem").agg(F.approx_count_distinct("l_partkey", 0.01).alias("parts"))
_sql("rel_agg_rollup", "select o_orderstatus, o_orderpriority, cast(count(*) as bigint) as n from {orders} group by rollup (o_orderstatus, o_orderpriority)")
_sql("rel_agg_cube", "select o_orderstatus, o_orderpriority, cast(count(*) as bigint) as n from {orders} group by cube (o_orderstatus, o_orderpriority)")
_sql("rel_agg_grouping_sets", "select o_orderstatus, o_orderpriority, cast(count(*) as bigint) as n from {orders} group by grouping sets ((o_orderstatus), (o_orderpriority), ())")
_sql("rel_argmin", "select l_partkey, m.k as orderkey, m.p as cents from (select l_partkey, min(struct(p, k)) as m from (select l_partkey, cast(round(l_extendedprice * 100) as bigint) as p, l_orderkey as k from {lineitem}) group by l_partkey)", "select l_partkey, k as orderkey, p as cents from (select *, row_number() over (partition by l_partkey order by p, k) as r from (select l_partkey, cast(round(l_extendedprice * 100) as bigint) as p, l_orderkey as k from lineitem)) where r = 1")
for _f in ("rank", "row_number", "dense_rank"):
    _sql(f"rel_window_{_f}", f"select l_orderkey, l_partkey, l_linenumber, cast({_f}() over (partition by l_orderkey order by l_quantity desc, l_partkey, l_linenumber) as bigint) as place from {{lineitem}}" if _f == "row_number" else f"select l_orderkey, l_partkey, l_linenumber, cast({_f}() over (partition by l_orderkey order by l_quantity desc) as bigint) as place from {{lineitem}}")
_sql("rel_window_lead_lag", "select event_id, lead(event_id) over (partition by user_id order by ts, event_id) as next, lag(event_id) over (partition by user_id order by ts, event_id) as previous from {events}")
_sql("rel_window_running", "select event_id, cast(sum(cast(floor(value * 100) as bigint)) over (partition by user_id order by ts, event_id rows between unbounded preceding and current row) as bigint) as running from {events}")
_sql(
    "rel_window_range_frame",
    "select event_id, cast(count(*) over (partition by event_type order by unix_timestamp(cast(ts as timestamp)) range between 3600 preceding and current row) as bigint) as n from {events}",
    "select event_id, count(*) over (partition by event_type order by cast(floor(epoch(ts)) as bigint) range between 3600 preceding and current row) as n from events",
)
_sql("rel_topk", "select fid, cast(sum(cost) as bigint) as total from {random_edges} group by fid order by total desc, fid limit 20")
_sql("rel_set_union", "select p_partkey from {part} where p_size < 10 union select p_partkey from {part} where p_size > 40")
_sql("rel_set_intersect", "select l_partkey from {lineitem} where l_linenumber = 1 intersect select l_partkey from {lineitem} where l_linenumber = 5")
_sql("rel_set_except", "select p_partkey as p from {part} except select l_partkey from {lineitem} where l_linenumber = 1")
_sql("rel_scalar_subquery", "select fid, tid from {random_edges} where cost = (select min(cost) from {random_edges})")
_HOPS = "with recursive w(nid, hops) as (select cast(0 as bigint), 0 union all select e.tid, w.hops + 1 from w join {supplier_edges} e on w.nid = e.fid where w.hops < 3) select nid, cast(min(hops) as bigint) as hops from w group by nid"
_sql("rel_recursive_hops", _HOPS)
_PATHS = "select l_orderkey, transform(array_sort(collect_list(struct(l_linenumber, l_partkey))), x -> x.l_partkey) as path from {lineitem} group by l_orderkey"
_PATHS_DUCK = "select l_orderkey, l_partkey, row_number() over (partition by l_orderkey order by l_linenumber, l_partkey) - 1 as pos from lineitem"
_sql("rel_explode_paths", f"select l_orderkey, cast(pos as bigint) as pos, nid from (select l_orderkey, posexplode(path) as (pos, nid) from ({_PATHS}))", f"select l_orderkey, cast(pos as bigint) as pos, l_partkey as nid from ({_PATHS_DUCK})")
_PATH_EDGES = f"select l_orderkey, cast(pos as bigint) as pos, fid, tid from (select l_orderkey, pos, l_partkey as fid, lead(l_partkey) over (partition by l_orderkey order by pos) as tid from ({_PATHS_DUCK})) where tid is not null"


def _path_rows(s: SparkSession, d: str) -> DataFrame:
    return s.sql(_PATHS, lineitem=table(s, d, "lineitem"))


QUERIES["rel_path_edges"] = lambda s, d: paths.path_edges(_path_rows(s, d)).withColumn("pos", F.col("pos").cast("long"))
ORACLE["rel_path_edges"] = _PATH_EDGES


def _udtf(s: SparkSession, d: str) -> DataFrame:
    paths.register(s)
    return s.sql("select l_orderkey, cast(t.pos as bigint) as pos, t.fid, t.tid from {p}, lateral path_edges(path) t", p=_path_rows(s, d))


QUERIES["rel_udtf_path_edges"] = _udtf
ORACLE["rel_udtf_path_edges"] = _PATH_EDGES
_sql("rel_fn_string", "select page_id, lower(regexp_extract(url, '://([^/?#]*)', 1)) as host, cast(length(url) as bigint) as n, split(url, '/')[2] as third from {pages}", "select page_id, lower(regexp_extract(url, '://([^/?#]*)', 1)) as host, cast(length(url) as bigint) as n, split(url, '/')[3] as third from pages")
_sql("rel_fn_date", "select cast(year(o_orderdate) as bigint) as y, cast(month(o_orderdate) as bigint) as m, cast(count(*) as bigint) as n from {orders} group by 1, 2")
_sql("rel_fn_math", "select l_orderkey, l_linenumber, cast(least(l_quantity, 10) as bigint) as a, cast(greatest(l_quantity, 40) as bigint) as b, cast(floor(l_quantity / 7) as bigint) as c, cast(abs(l_quantity - 25) as bigint) as d, cast(coalesce(nullif(l_linenumber, 1), 0) as bigint) as e from {lineitem}")
_sql("rel_fn_array", f"select l_orderkey, cast(size(path) as bigint) as n, element_at(path, 1) as first, element_at(path, -1) as last, cast(aggregate(path, cast(0 as bigint), (a, x) -> a + x) as bigint) as total from ({_PATHS})", f"select l_orderkey, count(*) as n, arg_min(l_partkey, pos) as first, arg_max(l_partkey, pos) as last, cast(sum(l_partkey) as bigint) as total from ({_PATHS_DUCK}) group by l_orderkey")
_sql("rel_fn_map", "select conv_id, coalesce(m['user'], 0) as user_turns, coalesce(m['assistant'], 0) as assistant_turns from (select conv_id, map_from_entries(collect_list(struct(role, n))) as m from (select conv_id, role, count(*) as n from {conversations} where role is not null group by conv_id, role) group by conv_id)", "select conv_id, count(*) filter (role = 'user') as user_turns, count(*) filter (role = 'assistant') as assistant_turns from conversations where role is not null group by conv_id")
_sql("rel_fn_json", "select event_id, get_json_object(props, '$.k') as k from {events}", "select event_id, json_extract_string(props, '$.k') as k from events")
_sql("rel_turns_as_path", "select conv_id, turn as fid, lead(turn) over (partition by conv_id order by turn) as tid from {conversations}")


def _knn(s: SparkSession, d: str) -> DataFrame:
    """Exact nearest five by Euclidean distance for every fiftieth vector against all, in whole millionths."""
    e = table(s, d, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("x"))
    ask = e.where("vec_id % 50 = 0").select(F.col("vec_id").alias("q"), F.col("x").alias("y"))
    far = F.aggregate(F.zip_with("x", "y", lambda a, b: (a - b) * (a - b)), F.lit(0.0), lambda t, x: t + x)
    near = e.join(F.broadcast(ask), F.col("q") != F.col("vec_id")).select("q", "vec_id", F.round(far, 6).alias("far"))
    order = Window.partitionBy("q").orderBy("far", "vec_id")
    return near.withColumn("place", F.row_number().over(order)).where("place <= 5").select("q", "vec_id", F.col("place").cast("long").alias("place"))


QUERIES["rel_embedding_knn"] = _knn
ORACLE["rel_embedding_knn"] = "select q, vec_id, place from (select *, row_number() over (partition by q order by far, vec_id) as place from (select a.vec_id as q, b.vec_id, round(list_sum(list_transform(list_zip(a.embedding, b.embedding), lambda z: (z[1]::double - z[2]::double) * (z[1]::double - z[2]::double))), 6) as far from embeddings a join embeddings b on a.vec_id <> b.vec_id where a.vec_id % 50 = 0)) where place <= 5"


def _round_trip(form: str) -> Query:
    def run(s: SparkSession, d: str) -> DataFrame:
        path = f"{shared_folder(s)}/wavefront_edges_{form}_{abs(hash(d)) % 10**8}"
        write_edges(kept(s, d, "nation"), path, form, parts=4 if form == "parquet" else None)
        return read_edges(s, form, path).select("fid", "tid", "cost")

    return run


for _form in ("parquet", "orc", "csv", "json"):
    QUERIES[f"io_roundtrip_{_form}"] = _round_trip(_form)
    ORACLE[f"io_roundtrip_{_form}"] = GRAPH_SQL["nation"]
