"""The relational surface around the methods: joins, aggregation, windows, sets, functions, streams, logs."""

from __future__ import annotations

from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .. import functions as fn
from .. import sources as io
from .. import streaming as st
from ..model import ops as o
from ..model.types import ANY, Field, Num
from ..operators import oplog
from ..operators.relation import DEAD, EID, LAST, ORD, Database, Relation
from .docs import L_EVENTS, events_log, table

DEC = "decimal(18,2)"


def _dec(c: str, name: str):
    return F.sum(F.col(c).cast(DEC)).cast("double").alias(name)


def scan_project(s, d):
    return table(s, d, "lineitem").select("l_orderkey", "l_quantity")


def filter_predicates(s, d):
    p = table(s, d, "part")
    return p.where(F.col("p_size").between(10, 30) & F.col("p_brand").isin("Brand#11", "Brand#23", "Brand#34") | F.col("p_name").like("%a%") & F.col("p_name").rlike("^[a-m]") & ~F.col("p_type").eqNullSafe(F.lit(None))).select("p_partkey")


def join(how: str, hint: str | None = None):
    def run(s, d):
        left, lab = table(s, d, "documents").select("doc_id", "lang").where("lang = 'en'"), table(s, d, "labels").where("quality = 1")
        return left.join(lab.hint(hint) if hint else lab, "doc_id", how)

    return run


def hinted(hint: str):
    def run(s, d):
        n, r = table(s, d, "nation"), table(s, d, "region")
        return n.join(r.hint(hint), n.n_regionkey == r.r_regionkey).select("n_name", "r_name")

    return run


def semi_returned(s, d):
    o_, li = table(s, d, "orders"), table(s, d, "lineitem").where("l_returnflag = 'R'")
    return o_.join(li, o_.o_orderkey == li.l_orderkey, "left_semi").select("o_orderkey")


def anti_unlabelled(s, d):
    return table(s, d, "documents").select("doc_id").join(table(s, d, "labels"), "doc_id", "left_anti")


BANDS = [(0, 950.0, "low"), (950.0, 1400.0, "mid"), (1400.0, 1e9, "high")]


def theta_band(s, d):
    bands = s.createDataFrame([(float(a), b, n) for a, b, n in BANDS], "lo double, hi double, band string")
    p = table(s, d, "part")
    return p.join(F.broadcast(bands), (p.p_retailprice >= bands.lo) & (p.p_retailprice < bands.hi)).select("p_partkey", "band")


def cross_regions(s, d):
    return table(s, d, "region").select("r_name").crossJoin(table(s, d, "nation").select("n_name"))


def range_epoch(s, d):
    """Operations to the epoch that holds their sequence number: the epoch bucket makes it an equi-join."""
    epochs = s.range(0, 64).select(F.col("id").alias("epoch"), (F.col("id") * 250).alias("lo"), (F.col("id") * 250 + 250).alias("hi"))
    ops = events_log(s, d)["all"].withColumn("bucket", F.floor(F.col("seq") / 250))
    return ops.join(F.broadcast(epochs), (ops.bucket == epochs.epoch) & (ops.seq >= epochs.lo) & (ops.seq < epochs.hi)).select("seq", "epoch")


def asof_cell(s, d):
    """Each purchase with the user's last view before it."""
    e = table(s, d, "events")
    w = W.partitionBy("user_id").orderBy("event_id").rowsBetween(W.unboundedPreceding, -1)
    both = e.where("event_type in ('view', 'purchase')").withColumn("last_view", F.last(F.when(F.col("event_type") == "view", F.col("event_id")), True).over(w))
    return both.where("event_type = 'purchase'").select("event_id", "last_view")


def lateral_topn(s, d):
    c, o_ = table(s, d, "customer"), table(s, d, "orders")
    c.createOrReplaceTempView("surface_customer")
    o_.createOrReplaceTempView("surface_orders")
    # the lateral form of a top-k per row; Spark turns it into a window, so nothing is nested
    return s.sql("""select c_custkey, o_orderkey from surface_customer c join lateral
      (select o_orderkey, row_number() over (order by o_totalprice desc, o_orderkey) as r from surface_orders o where o.o_custkey = c.c_custkey) where r <= 3""")


def agg_basic(s, d):
    li = table(s, d, "lineitem")
    return li.groupBy("l_returnflag", "l_linestatus").agg(_dec("l_quantity", "qty"), _dec("l_extendedprice", "price"), F.count(F.lit(1)).alias("n"), F.min("l_shipdate").alias("first"), F.max("l_shipdate").alias("last"))


def agg_distinct(s, d):
    return table(s, d, "documents").agg(F.count_distinct("text").alias("texts"), F.count_distinct("source").alias("sources"))


def agg_approx(s, d):
    """Whether the sketch's estimate is within its error."""
    return table(s, d, "orders").agg((F.abs(F.approx_count_distinct("o_orderkey", 0.02) - F.count_distinct("o_orderkey")) <= 0.1 * F.count_distinct("o_orderkey")).alias("close"))


def _branches(s, d):
    e = events_log(s, d)["all"]
    return e.select(F.col("fid").alias("f"), F.when(F.col("seq") < 2000, "O").when(F.col("seq") % 2 == 0, "L").otherwise("R").alias("br"))


def cube_ops(s, d):
    return _branches(s, d).cube("f", "br").agg(F.count(F.lit(1)).alias("n"))


def rollup_ops(s, d):
    return _branches(s, d).rollup("f", "br").agg(F.count(F.lit(1)).alias("n"))


def grouping_sets(s, d):
    return _branches(s, d).groupingSets([["f"], ["br"]], "f", "br").agg(F.count(F.lit(1)).alias("n"))


def pivot_types(s, d):
    return table(s, d, "events").groupBy("user_id").pivot("event_type", ["view", "purchase"]).agg(F.count(F.lit(1)))


def collect_sorted(s, d):
    c = table(s, d, "conversations")
    return c.groupBy("conv_id").agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("turn", "role"))), lambda x: x["role"]), ",").alias("roles"))


def window_rank(s, d):
    w = W.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey")
    by = W.partitionBy("o_custkey").orderBy("o_orderpriority")
    return table(s, d, "orders").select("o_orderkey", F.row_number().over(w).alias("rn"), F.rank().over(by).alias("rk"), F.dense_rank().over(by).alias("dr"), F.ntile(3).over(w).alias("nt"))


def lag_lead(s, d):
    w = W.partitionBy("u", "f").orderBy("seq")
    e = events_log(s, d)["all"].select("seq", F.col("eid").alias("u"), F.col("fid").alias("f"), F.col("val_n").cast("bigint").alias("v"))
    return e.select("seq", F.lag("v").over(w).alias("before"), F.lead("v").over(w).alias("after"))


def rows_frame(s, d):
    w = W.partitionBy("user_id").orderBy("event_id").rowsBetween(-2, 0)
    return table(s, d, "events").select("event_id", F.count(F.lit(1)).over(w).alias("n"), F.min("event_id").over(w).alias("first"))


def range_frame(s, d):
    at = F.unix_seconds(F.col("ts").cast("timestamp"))
    w = W.partitionBy("user_id").orderBy("sec").rangeBetween(-86400, 0)
    return table(s, d, "events").withColumn("sec", at).select("event_id", F.count(F.lit(1)).over(w).alias("n"))


def topk(s, d):
    """A limit that is the feature."""
    return table(s, d, "orders").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(10).select("o_orderkey")


def topk_group(s, d):
    w = W.partitionBy("o_orderpriority").orderBy(F.desc("o_totalprice"), "o_orderkey")
    return table(s, d, "orders").withColumn("r", F.row_number().over(w)).where("r <= 5").select("o_orderpriority", "o_orderkey", "r")


def set_op(kind: str):
    def run(s, d):
        e = events_log(s, d)
        a, b = (e[k].select(F.col("eid").alias("u"), F.col("fid").alias("f")) for k in ("left", "right"))
        return getattr(a, kind)(b) if kind != "union_distinct" else a.union(b).distinct()

    return run


def strings(s, d):
    c = table(s, d, "customer")
    n = F.col("c_name")
    return c.select("c_custkey", F.upper(n).alias("up"), F.substring(n, 1, 4).alias("sub"), F.length(n).alias("len"), F.lpad(F.col("c_custkey").cast("string"), 8, "0").alias("pad"), F.regexp_replace(n, "#0*", "-").alias("rep"), F.split(n, "#")[0].alias("part"), F.levenshtein(n, F.lit("Customer")).alias("dist"))


def dates(s, d):
    t = F.col("o_orderdate")
    return table(s, d, "orders").select("o_orderkey", F.date_trunc("month", t).cast("timestamp_ntz").alias("month"), F.year(t).alias("y"), F.dayofmonth(t).alias("dom"), F.datediff(F.lit("2030-01-01").cast("date"), t).alias("days"), (t + F.expr("interval 3 days")).alias("later"))


def maths(s, d):
    p = F.col("p_retailprice")
    return table(s, d, "part").select("p_partkey", F.floor(p).cast("bigint").alias("fl"), F.ceil(p).cast("bigint").alias("ce"), (F.col("p_size") % 7).alias("m"), F.try_divide(F.col("p_size"), F.col("p_size") - F.col("p_size")).alias("none"), F.greatest("p_size", F.lit(25)).alias("g"), F.round(p.cast(DEC), 1).cast("double").alias("r"))


def arrays(s, d):
    e = table(s, d, "embeddings")
    v = F.col("embedding")
    return e.select("vec_id", F.size(v).alias("n"), F.size(F.filter(v, lambda x: x > 0)).alias("pos"), F.slice(v, 1, 1)[0].cast("double").alias("first"), F.round(F.aggregate(v, F.lit(0).cast("decimal(38,6)"), lambda a, x: (a + x.cast("decimal(38,6)")).cast("decimal(38,6)")), 3).cast("double").alias("total"))


def maps_json(s, d):
    p = F.col("props")
    return table(s, d, "events").select("event_id", F.get_json_object(p, "$.k").cast("bigint").alias("a"), F.from_json(p, "k bigint")["k"].alias("b"), F.variant_get(F.parse_json(p), "$.k", "bigint").alias("c"), F.map_from_arrays(F.array(F.lit("x")), F.array(F.col("event_id")))["x"].alias("m"))


def struct_edit(s, d):
    p = table(s, d, "part").select("p_partkey", F.struct("p_brand", "p_type", "p_size").alias("r"))
    return p.select("p_partkey", F.col("r").withField("p_size", F.col("r.p_size") + 1).dropFields("p_type").alias("r")).select("p_partkey", "r.*")


def conditional(s, d):
    return table(s, d, "orders").select("o_orderkey", F.when(F.col("o_orderstatus") == "F", 1).when(F.col("o_orderstatus") == "O", 2).otherwise(3).alias("c"), F.coalesce(F.nullif("o_orderstatus", F.lit("F")), F.lit("-")).alias("s"))


def _sides(s, d):
    e = events_log(s, d)
    rows = e["left"].withColumn("side", F.lit(1)).unionByName(e["right"].withColumn("side", F.lit(0))).unionByName(e["shared"].withColumn("side", F.lit(0)))
    return rows.select(F.col("eid").cast("bigint").alias("u"), F.col("fid").alias("f"), "seq", "side", "val_n")


def udf_rules(s, d):
    ranked = _sides(s, d).withColumn("rank", fn.winner("side", "seq"))
    return ranked.groupBy("u", "f").agg(F.max_by("val_n", "rank").cast("bigint").alias("v"))


def udaf_merge(s, d):
    ranked = _sides(s, d).withColumn("rank", F.col("side").cast("bigint") * (1 << 40) + F.col("seq"))
    # a group is the writes of one cell; the built-in max_by of the other queries needs no group in Python
    return ranked.groupBy("u", "f").agg(fn.merge_cells("rank", "val_n").cast("bigint").alias("v"))


def udtf_history(s, d):
    fn.register(s, "events", Database({}), events_log(s, d)["all"])
    return s.sql("""select cast(eid as bigint) as u, fid as f, seq, step, cast(value as bigint) as v from
      (select eid, fid, collect_list(named_struct('seq', seq, 'value', val_n)) as w from events__oplog group by eid, fid), lateral cell_history(w)""")


def log_roundtrip(s, d):
    """A log written to Parquet and to JSON lines and read back from both."""
    ops = events_log(s, d)["all"]
    path = st.shared_folder(s, "oplog")
    io.write_oplog(ops, f"{path}/parquet", "doc")
    io.write_jsonl(ops, f"{path}/json")
    a, (b, _) = io.read_oplog(s, f"{path}/parquet", "doc", "cells"), io.read_jsonl(s, f"{path}/json")
    key = ["seq", "eid", "fid", "val_n"]
    return a.join(b.select(*key), key).select("seq", F.col("eid").cast("bigint").alias("u"), F.col("fid").alias("f"), F.col("val_n").cast("bigint").alias("v"))


def snapshot_tail(s, d):
    """State from a snapshot and the log's tail."""
    e = events_log(s, d)
    cells = lambda ops: oplog.last_writers(ops).select(F.concat_ws("/", "eid", "fid").alias(EID), F.array(F.lit(0).cast("bigint"), F.lit(LAST)).alias(ORD), F.lit(False).alias(DEAD), F.col("val_n").alias("v"))
    base = Database({"cells": Relation(cells(e["shared"]), (Field("v", "v", Num()),))})
    path = st.shared_folder(s, "snapshot")
    io.write_snapshot(base, path, 2000)
    base = io.read_snapshot(s, path, 2000, base)
    tail = e["left"].unionByName(e["right"]).withColumns({"eid": F.concat_ws("/", "eid", "fid"), "fid": F.lit("v")})
    new = tail.select("eid").distinct().join(base["cells"].df.select(F.col(EID).alias("eid")), "eid", "left_anti")
    adds = oplog.log(new, "append_elem", "cells", seq=F.lit(0), arg_eid=F.col("eid"))
    return oplog.replay(base, adds.unionByName(tail)).export("cells", F.split(EID, "/")[0].cast("bigint").alias("u"), F.split(EID, "/")[1].alias("f"), F.col("v").cast("bigint").alias("v"))


def _stream(s, d, twice: bool = False):
    e = table(s, d, "events")
    e = e.unionByName(e.where("event_id % 10 = 0")) if twice else e
    return st.read_events(s, st.slices(e, F.col("event_id") * 7 + 3, 4))


def stream_tumbling(s, d):
    return st.drain(st.windows(_stream(s, d), "1 day"), "complete")


def stream_sliding(s, d):
    return st.drain(st.windows(_stream(s, d), "2 days", "1 day"), "complete")


def stream_session(s, d):
    return st.drain(st.sessions(_stream(s, d), "6 hours"), "complete")


def stream_dedup(s, d):
    return st.drain(st.without_redelivery(_stream(s, d, True)).select("event_id", "user_id"))


def stream_state_cells(s, d):
    ops = _stream(s, d).select(F.col("user_id").alias("u"), F.col("event_type").alias("f"), F.col("event_id").alias("seq"), F.floor(F.col("value") / 50).cast("bigint").alias("v"))
    up = st.drain(st.latest_cells(ops), "update")
    return up.groupBy("u", "f").agg(F.max_by("v", "seq").alias("v"))


def stream_autosync(s, d):
    """Writes arrive in shuffled slices and are carried across a wrap as they come; the replica's state follows from its log."""
    path = st.shared_folder(s, "replica")
    src = _stream(s, d)
    given = {"seq": F.col("event_id"), "eid": F.col("user_id").cast("string"), "fid": F.lit("who"), "val_s": F.col("event_type")}
    ops = oplog.log(src, "set_cell", "tasks", **given)
    empty = Database({"tasks": Relation(s.createDataFrame([], f"{EID} string, {ORD} array<bigint>, {DEAD} boolean, who string"), (Field("who", "who", Num()),))})
    q = st.auto_sync(ops, [o.wrap_list(("tasks", ANY, "who"))], empty, lambda b, i: b.write.mode("overwrite").parquet(f"{path}/batch={i}"))
    q.awaitTermination()
    return oplog.last_writers(s.read.parquet(path)).select(F.col("eid").cast("bigint").alias("u"), "sub", F.col("val_s").alias("f"))


def stream_static_join(s, d):
    return st.drain(st.follow_links(_stream(s, d), table(s, d, "customer").select("c_custkey", "c_nationkey"), "user_id", "c_custkey").select("event_id", "c_nationkey"))


def stream_stream_join(s, d):
    """Every third operation is transferred ten minutes later and meets its origin."""
    e = table(s, d, "events").where("event_id % 3 = 0")
    moved = st.read_events(s, st.slices(e, F.col("event_id"), 2)).select(F.col("event_id").alias("origin"), (F.col("at") + F.expr("interval 10 minutes")).alias("at2"))
    return st.drain(st.match_origins(_stream(s, d), moved, "1 hour").select("event_id", F.col("at2").cast("timestamp_ntz").alias("arrived")))


QUERIES = {
    "rel_scan_project": scan_project,
    "rel_filter_predicates": filter_predicates,
    "rel_join_inner": join("inner"),
    "rel_join_left": join("left"),
    "rel_join_full": join("full"),
    "rel_join_broadcast": hinted("broadcast"),
    "rel_join_merge": hinted("merge"),
    "rel_join_hash": hinted("shuffle_hash"),
    "rel_semi_returned": semi_returned,
    "rel_anti_unlabelled": anti_unlabelled,
    "rel_theta_band": theta_band,
    "rel_cross_regions": cross_regions,
    "rel_range_epoch": range_epoch,
    "rel_asof_cell": asof_cell,
    "rel_lateral_topn": lateral_topn,
    "rel_agg_basic": agg_basic,
    "rel_agg_distinct": agg_distinct,
    "rel_agg_approx": agg_approx,
    "rel_cube_ops": cube_ops,
    "rel_rollup": rollup_ops,
    "rel_grouping_sets": grouping_sets,
    "rel_pivot_types": pivot_types,
    "rel_collect_sorted": collect_sorted,
    "rel_window_rank": window_rank,
    "rel_window_lag_lead": lag_lead,
    "rel_window_rows_frame": rows_frame,
    "rel_window_range_frame": range_frame,
    "rel_topk": topk,
    "rel_topk_per_group": topk_group,
    "rel_union_all": set_op("unionAll"),
    "rel_union_distinct": set_op("union_distinct"),
    "rel_intersect": set_op("intersect"),
    "rel_intersect_all": set_op("intersectAll"),
    "rel_except": set_op("subtract"),
    "rel_except_all": set_op("exceptAll"),
    "rel_strings": strings,
    "rel_dates": dates,
    "rel_math": maths,
    "rel_arrays": arrays,
    "rel_maps_json": maps_json,
    "rel_struct_edit": struct_edit,
    "rel_conditional": conditional,
    "rel_udf_rules": udf_rules,
    "rel_udaf_merge": udaf_merge,
    "rel_udtf_history": udtf_history,
    "oplog_io_roundtrip": log_roundtrip,
    "oplog_snapshot_tail": snapshot_tail,
    "stream_tumbling": stream_tumbling,
    "stream_sliding": stream_sliding,
    "stream_session": stream_session,
    "stream_dedup": stream_dedup,
    "stream_state_cells": stream_state_cells,
    "stream_autosync": stream_autosync,
    "stream_static_join": stream_static_join,
    "stream_stream_join": stream_stream_join,
}

_W = f"with {L_EVENTS}"
_JOIN = "select doc_id, lang, quality, toxic from (select doc_id, lang from documents where lang = 'en') {how} join (select * from labels where quality = 1) using (doc_id)"
_NR = "select n_name, r_name from nation join region on r_regionkey = n_regionkey"
_MERGED = f"{_W} select u, f, coalesce(arg_max(v, seq) filter (where br = 'L'), arg_max(v, seq)) as v from e group by u, f"
_SETS = f"{_W}, a as (select u, f from e where br = 'L'), b as (select u, f from e where br = 'R') select cast(u as varchar) as u, f from (select * from a {{op}} select * from b)"
ORACLES = {
    "rel_scan_project": "select l_orderkey, l_quantity from lineitem",
    "rel_filter_predicates": "select p_partkey from part where p_size between 10 and 30 and p_brand in ('Brand#11', 'Brand#23', 'Brand#34') or p_name like '%a%' and regexp_matches(p_name, '^[a-m]') and p_type is not null",
    "rel_join_inner": _JOIN.format(how="inner"),
    "rel_join_left": _JOIN.format(how="left"),
    "rel_join_full": _JOIN.format(how="full"),
    "rel_join_broadcast": _NR,
    "rel_join_merge": _NR,
    "rel_join_hash": _NR,
    "rel_semi_returned": "select o_orderkey from orders where exists (select 1 from lineitem where l_orderkey = o_orderkey and l_returnflag = 'R')",
    "rel_anti_unlabelled": "select doc_id from documents where doc_id not in (select doc_id from labels)",
    "rel_theta_band": "select p_partkey, band from part join (values (0.0, 950.0, 'low'), (950.0, 1400.0, 'mid'), (1400.0, 1000000000.0, 'high')) b(lo, hi, band) on p_retailprice >= lo and p_retailprice < hi",
    "rel_cross_regions": "select r_name, n_name from region, nation",
    "rel_range_epoch": f"{_W} select seq, cast(i as bigint) as epoch from e join range(64) r(i) on seq >= i * 250 and seq < i * 250 + 250",
    "rel_asof_cell": "select p.event_id, v.event_id as last_view from (select * from events where event_type = 'purchase') p asof left join (select * from events where event_type = 'view') v on p.user_id = v.user_id and p.event_id > v.event_id",
    "rel_lateral_topn": "select o_custkey as c_custkey, o_orderkey from (select *, row_number() over (partition by o_custkey order by o_totalprice desc, o_orderkey) as r from orders) where r <= 3",
    "rel_agg_basic": "select l_returnflag, l_linestatus, cast(sum(cast(l_quantity as decimal(18,2))) as double) as qty, cast(sum(cast(l_extendedprice as decimal(18,2))) as double) as price, count(*) as n, min(l_shipdate) as first, max(l_shipdate) as last from lineitem group by 1, 2",
    "rel_agg_distinct": "select count(distinct text) as texts, count(distinct source) as sources from documents",
    "rel_agg_approx": "select true as close",
    "rel_cube_ops": f"{_W} select f, br, count(*) as n from e group by cube (f, br)",
    "rel_rollup": f"{_W} select f, br, count(*) as n from e group by rollup (f, br)",
    "rel_grouping_sets": f"{_W} select f, br, count(*) as n from e group by grouping sets ((f), (br))",
    "rel_pivot_types": "select user_id, nullif(count(*) filter (where event_type = 'view'), 0) as view, nullif(count(*) filter (where event_type = 'purchase'), 0) as purchase from events group by 1",
    "rel_collect_sorted": "select conv_id, string_agg(role, ',' order by turn) as roles from conversations group by 1",
    "rel_window_rank": "select o_orderkey, row_number() over w as rn, rank() over b as rk, dense_rank() over b as dr, ntile(3) over w as nt from orders window w as (partition by o_custkey order by o_totalprice desc, o_orderkey), b as (partition by o_custkey order by o_orderpriority)",
    "rel_window_lag_lead": f"{_W} select seq, lag(v) over w as before, lead(v) over w as after from e window w as (partition by u, f order by seq)",
    "rel_window_rows_frame": "select event_id, count(*) over w as n, min(event_id) over w as first from events window w as (partition by user_id order by event_id rows between 2 preceding and current row)",
    "rel_window_range_frame": "select event_id, count(*) over (partition by user_id order by cast(floor(epoch(ts)) as bigint) range between 86400 preceding and current row) as n from events",
    "rel_topk": "select o_orderkey from orders order by o_totalprice desc, o_orderkey limit 10",
    "rel_topk_per_group": "select * from (select o_orderpriority, o_orderkey, row_number() over (partition by o_orderpriority order by o_totalprice desc, o_orderkey) as r from orders) where r <= 5",
    "rel_union_all": _SETS.format(op="union all"),
    "rel_union_distinct": _SETS.format(op="union"),
    "rel_intersect": _SETS.format(op="intersect"),
    "rel_intersect_all": _SETS.format(op="intersect all"),
    "rel_except": _SETS.format(op="except"),
    "rel_except_all": _SETS.format(op="except all"),
    "rel_strings": "select c_custkey, upper(c_name) as up, substr(c_name, 1, 4) as sub, cast(length(c_name) as integer) as len, lpad(cast(c_custkey as varchar), 8, '0') as pad, regexp_replace(c_name, '#0*', '-') as rep, split_part(c_name, '#', 1) as part, cast(levenshtein(c_name, 'Customer') as integer) as dist from customer",
    "rel_dates": "select o_orderkey, cast(date_trunc('month', o_orderdate) as timestamp) as month, cast(year(o_orderdate) as integer) as y, cast(day(o_orderdate) as integer) as dom, cast(date_diff('day', cast(o_orderdate as date), date '2030-01-01') as integer) as days, o_orderdate + interval 3 day as later from orders",
    "rel_math": "select p_partkey, cast(floor(p_retailprice) as bigint) as fl, cast(ceil(p_retailprice) as bigint) as ce, p_size % 7 as m, cast(null as double) as none, greatest(p_size, 25) as g, cast(round(cast(p_retailprice as decimal(18,2)), 1) as double) as r from part",
    "rel_arrays": "select vec_id, cast(len(embedding) as integer) as n, cast(len(list_filter(embedding, lambda x: x > 0)) as integer) as pos, cast(embedding[1] as double) as first, cast(round(list_sum(list_transform(embedding, lambda x: cast(x as decimal(38,6)))), 3) as double) as total from embeddings",
    "rel_maps_json": "select event_id, cast(json_extract_string(props, '$.k') as bigint) as a, cast(json_extract_string(props, '$.k') as bigint) as b, cast(json_extract_string(props, '$.k') as bigint) as c, event_id as m from events",
    "rel_struct_edit": "select p_partkey, p_brand, p_size + 1 as p_size from part",
    "rel_conditional": "select o_orderkey, case o_orderstatus when 'F' then 1 when 'O' then 2 else 3 end as c, coalesce(nullif(o_orderstatus, 'F'), '-') as s from orders",
    "rel_udf_rules": _MERGED,
    "rel_udaf_merge": _MERGED,
    "rel_udtf_history": f"{_W} select u, f, seq, cast(row_number() over (partition by u, f order by seq) as integer) as step, v from e",
    "oplog_io_roundtrip": f"{_W} select seq, u, f, v from e",
    "oplog_snapshot_tail": f"{_W} select u, f, arg_max(v, seq) as v from e group by u, f",
    "stream_tumbling": "select date_trunc('day', ts) as start, event_type, count(*) as n from events group by 1, 2",
    "stream_sliding": "select date_trunc('day', ts) - to_days(i) as start, event_type, count(*) as n from events, (values (0), (1)) t(i) group by 1, 2",
    "stream_session": """with g as (select user_id, ts, case when ts - lag(ts) over (partition by user_id order by ts) < interval 6 hour then 0 else 1 end as new from events),
      s as (select user_id, ts, sum(new) over (partition by user_id order by ts rows unbounded preceding) as k from g) select min(ts) as start, user_id, count(*) as n from s group by user_id, k""",
    "stream_dedup": "select event_id, user_id from events",
    "stream_state_cells": f"{_W} select u, f, arg_max(v, seq) as v from e group by u, f",
    "stream_static_join": "select event_id, c_nationkey from events join customer on c_custkey = user_id",
    "stream_stream_join": "select event_id, ts + interval 10 minute as arrived from events where event_id % 3 = 0",
    "stream_autosync": "select user_id as u, 'ONE' as sub, arg_max(event_type, event_id) as f from events group by 1",
}
