"""Branches of one document, and measures over transfers."""

from __future__ import annotations

from pyspark.sql import functions as F

from .. import measures as ms
from .. import streaming as st
from .. import vcs
from ..model.ops import wrap_list
from ..model.types import ANY, Atom, Num, Str
from ..operators import oplog
from ..operators.relation import Database, from_table
from .docs import table, todo_db
from .todo import new_inserts, new_writes


def _customers(spark, sf) -> vcs.Document:
    c = table(spark, sf, "customer").select("c_custkey", "c_name", "c_acctbal")
    r = from_table(c, F.col("c_custkey"), "c", {"c_custkey": Atom("bigint"), "c_name": Str(), "c_acctbal": Num()})
    return vcs.Document("main", Database({"customers": r}), oplog.log(c.limit(0), "set_cell", "customers"))


def _writes(spark, sf, every: int, value: str, seq: int):
    c = table(spark, sf, "customer").where(F.col("c_custkey") % every == 0)
    e = F.concat(F.lit("c"), F.col("c_custkey").cast("string"))
    return oplog.log(c, "set_cell", "customers", seq=F.col("c_custkey") + seq, eid=e, fid=F.lit("c_name"), val_s=F.lit(value))


def _branches(spark, sf) -> tuple[vcs.Document, vcs.Document]:
    main = _customers(spark, sf).append(_writes(spark, sf, 2, "shared", 0))
    return vcs.branch(main, "left").append(_writes(spark, sf, 3, "left", 1_000_000)), vcs.branch(main, "right").append(_writes(spark, sf, 5, "right", 2_000_000))


def _names(doc: vcs.Document, out: str):
    return doc.state().export("customers", "c_custkey", F.col("c_name").alias(out))


def sync(spark, sf):
    left, right = vcs.sync(*_branches(spark, sf))
    return _names(left, "l").join(_names(right, "r"), "c_custkey")


def cherry_pick(spark, sf):
    left, right = _branches(spark, sf)
    d = vcs.diff(left, right)
    return _names(right.append(vcs.rebase(d, vcs.cherry_pick(d, F.col("seq") % 2 == 0))), "name")


def graph(spark, sf):
    left, right = _branches(spark, sf)
    d = vcs.diff(left, right)
    merged = right.append(vcs.rebase(d, vcs.cherry_pick(d, F.lit(True))))
    return vcs.version_graph([left, merged]).where("target = 'right'")


def report(spark, sf):
    out = vcs.report(vcs.diff(*_branches(spark, sf)))
    return out.select(F.substring("eid", 2, 20).cast("bigint").alias("c_custkey"), "left_s", "right_s", "conflict")


def compact(spark, sf):
    left, _ = _branches(spark, sf)
    return _names(vcs.compact(left, 1_000_000, st.shared_folder(spark, "compact")), "name")


def bundle(spark, sf):
    left, _ = _branches(spark, sf)
    path = st.shared_folder(spark, "bundle")
    vcs.export_bundle(left, path)
    return _names(vcs.import_bundle(spark, path, "left", left.start), "name")


def transfer_rate(spark, sf):
    """Transferred and blocked operations by kind when lists of assignees go back to single ones."""
    db = todo_db(spark, sf)
    wrap = wrap_list(("tasks", ANY, "who"))
    return ms.transfer_rate(*oplog.backward(new_writes(db).unionByName(new_inserts(db)), wrap, db.apply(wrap)))


def closure_size(spark, sf):
    """How many operations each write of a second assignee needs."""
    db = todo_db(spark, sf)
    sizes = ms.closure_size(new_writes(db).unionByName(new_inserts(db)))
    return sizes.groupBy("needs").agg(F.count(F.lit(1)).alias("ops"))


QUERIES = {
    "vcs_sync": sync,
    "vcs_cherry_pick": cherry_pick,
    "vcs_version_graph": graph,
    "vcs_diff_report": report,
    "vcs_compact": compact,
    "vcs_bundle": bundle,
    "measure_transfer_rate": transfer_rate,
    "measure_closure_size": closure_size,
}

_SIDES = "with s as (select c_custkey, c_name, c_custkey % 2 = 0 as o, c_custkey % 3 = 0 as l, c_custkey % 5 = 0 as r from customer)"
_LEFT = "case when l then 'left' when o then 'shared' else c_name end"
_MERGED = "case when l then 'left' when r then 'right' when o then 'shared' else c_name end"
ORACLES = {
    "vcs_sync": f"{_SIDES} select c_custkey, {_MERGED} as l, {_MERGED} as r from s",
    "vcs_cherry_pick": f"{_SIDES} select c_custkey, case when l and c_custkey % 2 = 0 then 'left' when r then 'right' when o then 'shared' else c_name end as name from s",
    "vcs_version_graph": f"{_SIDES} select 'left' as source, 'right' as target, count(*) as operations from s where l",
    "vcs_diff_report": f"{_SIDES}, c as (select c_custkey, l, r, case when l then 'left' when o then 'shared' end as a, case when r then 'right' when o then 'shared' end as b from s) select c_custkey, a as left_s, b as right_s, l and r as conflict from c where (l or r)",
    "vcs_compact": f"{_SIDES} select c_custkey, {_LEFT} as name from s",
    "vcs_bundle": f"{_SIDES} select c_custkey, {_LEFT} as name from s",
    "measure_transfer_rate": "select 'set_cell' as kind, count(*) filter (where o_orderkey % 5 = 0) as moved, count(*) filter (where o_orderkey % 3 = 0) as blocked from orders union all select 'insert_elem', 0, count(*) from orders where o_orderkey % 3 = 0",
    "measure_closure_size": "select cast(1 as bigint) as needs, count(*) as ops from orders where o_orderkey % 3 = 0",
}
