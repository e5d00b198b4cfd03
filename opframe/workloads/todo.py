"""One assignee becomes a list of assignees: transfer, sync and blocking between diverged copies."""

from __future__ import annotations

from pyspark.sql import functions as F

from .. import vcs
from ..model import ops as o
from ..model.types import ANY, ONE
from ..operators import oplog
from ..operators.relation import EID, Database
from .docs import D_TODO, todo_db

WRAP = o.wrap_list(("tasks", ANY, "who"))


def _rows(db: Database, every: int):
    return db["tasks"].live().select("k", F.col(EID).alias("e")).where(F.col("k") % every == 0)


def old_writes(db: Database):
    """Writes on the copy with single assignees."""
    src = _rows(db, 7)
    return oplog.log(src, "set_cell", "tasks", seq=F.col("k"), eid=F.col("e"), fid=F.lit("who"), val_s=F.concat(F.lit("Jill-"), F.col("k").cast("string")))


def new_writes(db: Database):
    """Writes on the copy with lists of assignees."""
    src = _rows(db, 5)
    return oplog.log(src, "set_cell", "tasks", seq=F.col("k"), eid=F.col("e"), fid=F.lit("who"), sub=F.lit(ONE), val_s=F.lit("Jacque"))


def new_inserts(db: Database):
    """Second assignees in front of the first, and their names."""
    src = _rows(db, 3)
    add = oplog.log(src, "insert_elem", "tasks", seq=F.col("k"), eid=F.col("e"), fid=F.lit("who"), arg_eid=F.lit("g"), anchor=F.lit(ONE))
    name = oplog.log(src, "set_cell", "tasks", seq=F.col("k") + 1, eid=F.col("e"), fid=F.lit("who"), sub=F.lit("g"), val_s=F.lit("Tom"))
    return add.unionByName(name)


def assignees(db: Database):
    """k, pos, eid, who: one row for each assignee."""
    return db["tasks"].live().select("k", F.posexplode("who").alias("pos", "x")).select("k", F.col("pos").cast("bigint").alias("pos"), F.col("x.eid").alias("eid"), F.col("x.val").alias("who"))


def wrap(spark, sf):
    return assignees(todo_db(spark, sf).apply(WRAP))


def transfer_forward(spark, sf):
    db = todo_db(spark, sf)
    moved = oplog.forward(old_writes(db), WRAP, db)
    return assignees(oplog.replay(oplog.replay(db.apply(WRAP), new_writes(db).unionByName(new_inserts(db))), moved))


def transfer_backward(spark, sf):
    db = todo_db(spark, sf)
    back, _ = oplog.backward(new_writes(db), WRAP, db.apply(WRAP))
    return oplog.replay(oplog.replay(db, old_writes(db)), back).export("tasks", "k", "who")


def blocked_ops(spark, sf):
    db = todo_db(spark, sf)
    _, bad = oplog.backward(new_inserts(db), WRAP, db.apply(WRAP))
    return bad.where("kind = 'insert_elem'").select(F.substring("eid", 2, 20).cast("bigint").alias("k"), "kind", "blocker_kind")


def branches(spark, sf) -> tuple[vcs.Document, vcs.Document]:
    """The copy with single assignees, and the one that made them lists."""
    db = todo_db(spark, sf)
    mine = old_writes(db)
    theirs = new_writes(db).unionByName(new_inserts(db))
    return vcs.Document("old", db, mine), vcs.Document("new", db, theirs.limit(0)).alter(0, WRAP).append(theirs)


def sync(spark, sf):
    """Both planes both ways: the wrap goes left, the left's writes win, and both copies are one."""
    left, right = vcs.sync(*branches(spark, sf))
    return assignees(left.state()).withColumn("side", F.lit("left")).unionByName(assignees(right.state()).withColumn("side", F.lit("right")))


def delete_one(spark, sf):
    db = todo_db(spark, sf)
    src = _rows(db, 11)
    drops = oplog.log(src, "drop_elem", "tasks", seq=F.col("k"), eid=F.col("e"), fid=F.lit("who"), arg_eid=F.lit(ONE))
    back, bad = oplog.backward(drops, WRAP, db.apply(WRAP))
    refused = oplog.replay(db, back).export("tasks", "k", F.col("who").alias("refused"))
    blanks = bad.withColumns({"kind": F.lit("set_cell"), "val_s": F.lit("")}).drop("blocker_kind")
    blanked = oplog.replay(db, blanks).export("tasks", "k", F.nullif("who", F.lit("")).alias("blanked"))
    return refused.join(blanked, "k")


def data_only(spark, sf):
    db = todo_db(spark, sf)
    back, _ = oplog.backward(new_writes(db).unionByName(new_inserts(db)), WRAP, db.apply(WRAP))
    return oplog.replay(db, back).export("tasks", "k", "who")


def type_only(spark, sf):
    """Only the wrap goes to the old copy, whose data stay."""
    old, new = branches(spark, sf)
    return assignees(vcs.merge(vcs.diff(new, old), old, ("type",)).state())


def dependency_transfer(spark, sf):
    """The write of a second assignee brings the insertion and the wrap along, and nothing else."""
    old, new = branches(spark, sf)
    bare = vcs.Document("bare", old.start, old.ops.limit(0))
    t = vcs.transfer_all(vcs.diff(new, bare), ("value",), F.coalesce(F.col("sub") == "g", F.lit(False)), True)
    return assignees(vcs.apply_transfer(bare, t).state())


def unwrap_back(spark, sf):
    return todo_db(spark, sf).apply(WRAP).apply(o.unwrap_first(("tasks", ANY, "who"))).export("tasks", "k", "who")


QUERIES = {
    "todo_wrap_list": wrap,
    "todo_transfer_forward": transfer_forward,
    "todo_transfer_backward": transfer_backward,
    "todo_blocked_ops": blocked_ops,
    "todo_sync": sync,
    "todo_delete_one": delete_one,
    "todo_data_only": data_only,
    "todo_type_only": type_only,
    "todo_dependency_transfer": dependency_transfer,
    "todo_unwrap_first": unwrap_back,
}

_W = f"with {D_TODO}"
_JILL = "when k % 7 = 0 then 'Jill-' || k"
_BOTH = f"""select k, 0 as pos, 'g' as eid, 'Tom' as who from t where k % 3 = 0
  union all select k, case when k % 3 = 0 then 1 else 0 end as pos, 'ONE' as eid, case {_JILL} when k % 5 = 0 then 'Jacque' else who end as who from t"""
ORACLES = {
    "todo_wrap_list": f"{_W} select k, cast(0 as bigint) as pos, 'ONE' as eid, who from t",
    "todo_transfer_forward": f"{_W} {_BOTH}",
    "todo_transfer_backward": f"{_W} select k, case when k % 5 = 0 then 'Jacque' {_JILL} else who end as who from t",
    "todo_blocked_ops": f"{_W} select k, 'insert_elem' as kind, 'wrap_list' as blocker_kind from t where k % 3 = 0",
    "todo_sync": f"{_W}, b as ({_BOTH}) select b.*, s.side from b, (values ('left'), ('right')) s(side)",
    "todo_delete_one": f"{_W} select k, who as refused, case when k % 11 <> 0 then who end as blanked from t",
    "todo_data_only": f"{_W} select k, case when k % 5 = 0 then 'Jacque' else who end as who from t",
    "todo_type_only": f"{_W} select k, cast(0 as bigint) as pos, 'ONE' as eid, case {_JILL} else who end as who from t",
    "todo_dependency_transfer": f"""{_W} select k, 0 as pos, 'g' as eid, 'Tom' as who from t where k % 3 = 0
      union all select k, case when k % 3 = 0 then 1 else 0 end, 'ONE', who from t""",
    "todo_unwrap_first": f"{_W} select k, who from t",
}
