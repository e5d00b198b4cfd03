"""A natural operation log: replay, conflicts, transfer, optimal diffs, undo and baselines on it."""

from __future__ import annotations

from pyspark.sql import functions as F

from .. import baselines as bl
from .. import measures as ms
from ..operators import oplog
from .docs import L_EVENTS, events_log

def cell() -> list:
    """The user and the event type that a log row writes."""
    return [F.col("eid").cast("bigint").alias("u"), F.col("fid").alias("f")]


def v(c: str, name: str = "v"):
    return F.col(c).cast("bigint").alias(name)


def replay(spark, sf):
    return oplog.last_writers(events_log(spark, sf)["all"]).select(*cell(), v("val_n"))


def conflicts(spark, sf):
    e = events_log(spark, sf)
    return oplog.conflicts(e["left"], e["right"]).select(*cell(), v("ln", "l"), v("rn", "r"))


def transfer_left(spark, sf):
    e = events_log(spark, sf)
    right = e["shared"].unionByName(e["right"])
    return oplog.transfer_values(e["left"], right).select(*cell(), v("val_n"))


def optimised(spark, sf):
    e = events_log(spark, sf)
    c = oplog.optimised_cells(e["shared"], e["left"], e["right"])
    return c.where("keep_left or keep_right").select(*cell(), "keep_left", "keep_right", v("la.val_n", "l"), v("ra.val_n", "r"))


def diff_sizes(spark, sf):
    return ms.diff_sizes(*(events_log(spark, sf)[k] for k in ("shared", "left", "right")))


def synthesise(spark, sf):
    """Two whole histories; where they part is found from their operation IDs."""
    e = events_log(spark, sf)
    a, b = e["shared"].unionByName(e["left"]), e["shared"].unionByName(e["right"])
    shared = a.join(b.select("op_id"), "op_id", "left_semi").select(*a.columns)
    left, right = (x.join(b if x is a else a, "op_id", "left_anti").select(*a.columns) for x in (a, b))
    c = oplog.optimised_cells(shared, left, right)
    return c.where("keep_left or keep_right").select(*cell(), "keep_left", "keep_right", v("la.val_n", "l"), v("ra.val_n", "r"))


UNDONE = "seq % 7 = 0"


def undo(spark, sf):
    return oplog.undo(events_log(spark, sf)["all"], F.expr(UNDONE)).select(*cell(), v("val_n"))


def undo_overridden(spark, sf):
    return oplog.undo_overridden(events_log(spark, sf)["all"], F.expr(UNDONE)).select("seq")


def undo_scrubbed(spark, sf):
    """State after the undo delta; it equals the state of a history without the undone operations."""
    ops = events_log(spark, sf)["all"]
    state = oplog.last_writers(ops).select("eid", "fid", "val_n")
    delta = oplog.undo(ops, F.expr(UNDONE)).select("eid", "fid", F.col("val_n").alias("n"), F.lit(True).alias("hit"))
    return state.join(delta, ["eid", "fid"], "left").select(*cell(), F.when(F.col("hit"), F.col("n")).otherwise(F.col("val_n")).cast("bigint").alias("v")).where("v is not null")


def history_page(spark, sf):
    """The last hundred operations: a limit that is the feature."""
    return events_log(spark, sf)["all"].orderBy(F.desc("seq")).limit(100).select("seq", *cell(), v("val_n"))


def simplify(spark, sf):
    return oplog.simplify(events_log(spark, sf)["all"]).select("seq")


def naive_undo(spark, sf):
    return bl.truncate_undo(events_log(spark, sf)["all"], 5000).select(*cell(), v("val_n"))


def fingerprint(spark, sf):
    """Whether both ways of merging end in one state: equal fingerprints, one aggregate each."""
    e = events_log(spark, sf)
    a = oplog.transfer_values(e["left"], e["shared"].unionByName(e["right"])).select("eid", "fid", "val_n")
    order = e["shared"].unionByName(e["right"]).unionByName(e["left"].withColumn("seq", F.col("seq") + 1_000_000_000))
    b = oplog.last_writers(order).select("eid", "fid", "val_n")
    return oplog.fingerprint(a).join(oplog.fingerprint(b), ["cells", "hash"]).select("cells")


def three_way(spark, sf):
    e = events_log(spark, sf)
    return bl.three_way_merge(*(oplog.last_writers(x).select(*cell(), v("val_n")) for x in (e["shared"], e["shared"].unionByName(e["left"]), e["shared"].unionByName(e["right"]))), ["u", "f"], "v")


def keyed_diff(spark, sf):
    e = events_log(spark, sf)
    a, b = (oplog.last_writers(e["shared"].unionByName(e[s])).select(*cell(), v("val_n")) for s in ("left", "right"))
    return bl.keyed_state_diff(a, b, ["u", "f"])


def row_diff(spark, sf):
    e = events_log(spark, sf)
    a, b = (oplog.last_writers(e["shared"].unionByName(e[s])).select(*cell(), v("val_n")) for s in ("left", "right"))
    return bl.row_set_diff(a, b)


def merge_fidelity(spark, sf):
    e = events_log(spark, sf)
    intended = ms.intended_cells(e["shared"], e["left"], e["right"]).select(*cell(), v("val_n"))
    return ms.merge_fidelity(intended, transfer_left(spark, sf), three_way(spark, sf), ["u", "f"])


QUERIES = {
    "events_replay": replay,
    "events_conflicts": conflicts,
    "events_transfer_left": transfer_left,
    "events_optimized_diff": optimised,
    "events_diff_sizes": diff_sizes,
    "events_synthesize": synthesise,
    "events_undo": undo,
    "events_undo_overridden": undo_overridden,
    "events_undo_scrubbed": undo_scrubbed,
    "events_history_page": history_page,
    "events_simplify": simplify,
    "events_fingerprint": fingerprint,
    "baseline_truncate_undo": naive_undo,
    "baseline_three_way": three_way,
    "baseline_keyed_diff": keyed_diff,
    "baseline_row_diff": row_diff,
    "measure_merge_fidelity": merge_fidelity,
}

_W = f"with {L_EVENTS}"
_LAST = "last as (select u, f, arg_max(v, seq) filter (where br = 'L') as l, arg_max(v, seq) filter (where br = 'R') as r, arg_max(v, seq) filter (where br = 'O') as s from e group by u, f)"
_SETS = "sets as (select u, f, list(v) filter (where br = 'L') as lv, list(v) filter (where br = 'R') as rv from e group by u, f)"
_OPT = f"""{_LAST}, {_SETS}, cur as (select u, f, coalesce(l, s) as la, coalesce(r, s) as ra, l is not null as wl, r is not null as wr,
  coalesce(list_contains(lv, coalesce(r, s)), false) as inl, coalesce(list_contains(rv, coalesce(l, s)), false) as inr from last join sets using (u, f)),
  opt as (select u, f, la is distinct from ra and wl and (inl or not inr) as keep_left, la is distinct from ra and wr and not inl as keep_right, la as l, ra as r from cur)"""
_STATES = f"{_LAST}, a as (select u, f, coalesce(l, s) as v from last where coalesce(l, s) is not null), b as (select u, f, coalesce(r, s) as v from last where coalesce(r, s) is not null)"
_THREE = f"{_LAST} select u, f, s as base, coalesce(l, s) as a, coalesce(r, s) as b, case when l is distinct from s and coalesce(r, s) is distinct from s and coalesce(l, s) is distinct from coalesce(r, s) and l is not null then 'conflict' when coalesce(l, s) is distinct from s then 'a' else 'b' end as outcome from last"
ORACLES = {
    "events_replay": f"{_W} select u, f, arg_max(v, seq) as v from e group by u, f",
    "events_conflicts": f"{_W}, {_LAST} select u, f, l, r from last where l is not null and r is not null and l <> r",
    "events_transfer_left": f"{_W}, {_LAST} select u, f, coalesce(l, r, s) as v from last",
    "events_optimized_diff": f"{_W}, {_OPT} select * from opt where keep_left or keep_right",
    "events_synthesize": f"{_W}, {_OPT} select * from opt where keep_left or keep_right",
    "events_diff_sizes": f"""{_W}, {_OPT}, m(method, l, r) as (
        select 'raw', count(*) filter (where br = 'L'), count(*) filter (where br = 'R') from e
        union all select 'simplify_first', count(*) filter (where l is not null and l is distinct from coalesce(r, s)), count(*) filter (where r is not null and r is distinct from coalesce(l, s)) from last
        union all select 'loop', count(*) filter (where keep_left), count(*) filter (where keep_right) from opt)
      select method, cast(l as bigint) as left_ops, cast(r as bigint) as right_ops from m""",
    "events_undo": f"{_W}, c as (select u, f, arg_max(seq, seq) as top, arg_max(v, seq) filter (where seq % 7 <> 0) as v from e group by u, f) select u, f, v from c where top % 7 = 0",
    "events_undo_overridden": f"{_W} select seq from (select seq, max(case when seq % 7 <> 0 then seq end) over (partition by u, f) as k from e) where seq % 7 = 0 and k > seq",
    "events_undo_scrubbed": f"{_W} select u, f, arg_max(v, seq) as v from e where seq % 7 <> 0 group by u, f",
    "events_history_page": f"{_W} select seq, u, f, v from e order by seq desc limit 100",
    "events_simplify": f"{_W} select max(seq) as seq from e group by u, f",
    "events_fingerprint": f"{_W} select count(distinct (u, f)) as cells from e",
    "baseline_truncate_undo": f"{_W} select u, f, arg_max(v, seq) as v from e where seq < 5000 group by u, f",
    "baseline_three_way": f"""{_W}, {_STATES}, x as (select coalesce(s0.u, a.u, b.u) as u, coalesce(s0.f, a.f, b.f) as f, s0.s as base, a.v as a, b.v as b
        from (select u, f, s from last where s is not null) s0 full join a on a.u = s0.u and a.f = s0.f full join b on b.u = coalesce(s0.u, a.u) and b.f = coalesce(s0.f, a.f))
      select u, f, case when a is not distinct from b then a when a is not distinct from base then b when b is not distinct from base then a end as v,
        a is distinct from b and a is distinct from base and b is distinct from base as conflict from x""",
    "baseline_keyed_diff": f"{_W}, {_STATES} select coalesce(a.u, b.u) as u, coalesce(a.f, b.f) as f, case when a.u is null then 'insert' when b.u is null then 'delete' else 'update' end as change from a full join b on a.u = b.u and a.f = b.f where a.v is distinct from b.v",
    "baseline_row_diff": f"{_W}, {_STATES} select u, f, v, 'delete' as change from (select * from a except select * from b) union all select u, f, v, 'insert' from (select * from b except select * from a)",
    "measure_merge_fidelity": f"""{_W}, {_LAST}, c as (select coalesce(l, r, s) as want, l is not null and r is not null and l is distinct from s and r is distinct from s and l is distinct from r as conflict,
        case when coalesce(l, s) is not distinct from coalesce(r, s) then coalesce(l, s) when coalesce(l, s) is not distinct from s then coalesce(r, s) when coalesce(r, s) is not distinct from s then coalesce(l, s) end as tw from last)
      select 'transfer' as method, count(*) as rows, count(*) as faithful from c union all select 'three_way', count(*), count(*) filter (where tw is not distinct from want) from c""",
}
