"""Transfers across type operations on both branches, undo on both planes, formulas that follow the schema, and measures of them."""

from __future__ import annotations

from pyspark.sql import functions as F

from .. import baselines as bl
from .. import measures as ms
from .. import vcs
from ..kernel.rules import Blocked
from ..model import ops as o
from ..model.types import ANY, ONE, Num, Str
from ..operators import oplog
from ..operators.forward import reconcile, undo_merge
from ..operators.relation import EID, ORD, Database, from_table
from ..plans.formula import Formula, evaluate, evaluate_named, from_diff, update_through
from .acme import JOIN, PENDING, SPLIT, _view_edits, deduped, flat, moves, split_db
from .docs import D_ORDERS, D_TODO, L_EVENTS, orders_db, table, todo_db
from .structure import parts_db
from .todo import WRAP, new_inserts, new_writes, old_writes

P = ("part", ANY)
WHO = ("tasks", ANY, "who")


def _key() -> list:
    return [F.concat(F.lit("p"), F.col("p_partkey").cast("string"))]


def _part_writes(spark, sf, every: int, rest: int, fid: str, seq: int = 100, sub: str | None = None, target: str = "part", **value):
    src = table(spark, sf, "part").where(F.col("p_partkey") % every == rest)
    return oplog.log(src, "set_cell", target, seq=F.col("p_partkey") + seq, eid=_key()[0], fid=F.lit(fid), sub=F.lit(sub), **value)


def _branches(db: Database, left, right, types: tuple[o.Op, ...]) -> tuple[vcs.Document, vcs.Document]:
    """Two copies of one document: the right has type operations, then its writes."""
    none = left.limit(0)
    return vcs.Document("left", db, left), vcs.Document("right", db, none).alter(1, *types).append(right)


def _both_ways(db, left, right, types):
    """(the right after the left's data came, the left after the right's data came, what was blocked)."""
    a, b = _branches(db, left, right, types)
    d = vcs.diff(a, b)
    back = vcs.transfer_all(d.flip(), ("value",))
    return vcs.apply_transfer(b, vcs.transfer_all(d, ("value",))).state(), vcs.apply_transfer(a, back).state(), back.blocked


def convert(spark, sf):
    """Prices as numbers on the left, as text on the right; text that is no number stays on the right."""
    k = F.col("p_partkey").cast("string")
    left = _part_writes(spark, sf, 10, 0, "p_retailprice", val_n=F.col("p_partkey").cast("double"))
    right = _part_writes(spark, sf, 10, 5, "p_retailprice", val_s=F.concat(k, F.lit(".5"))).unionByName(_part_writes(spark, sf, 20, 3, "p_retailprice", val_s=F.concat(F.lit("x"), k)))
    there, back, blocked = _both_ways(parts_db(spark, sf), left, right, (o.convert_type((*P, "p_retailprice"), Str(), Num()),))
    bad = blocked.select(F.col("eid").alias("__b"), F.lit(True).alias("blocked"))
    out = there.export("part", "p_partkey", F.col("p_retailprice").alias("there")).join(back.export("part", EID, "p_partkey", F.col("p_retailprice").alias("back")), "p_partkey")
    return out.join(bad, F.col(EID) == F.col("__b"), "left").select("p_partkey", "there", "back", F.coalesce("blocked", F.lit(False)).alias("blocked"))


def define_blocked(spark, sf):
    """Writes of a column that the right made depend on its making; others go back."""
    right = _part_writes(spark, sf, 4, 0, "note", val_s=F.lit("n")).unionByName(_part_writes(spark, sf, 6, 0, "p_brand", val_s=F.lit("B")))
    left = _part_writes(spark, sf, 7, 0, "p_type", val_s=F.lit("T"))
    types = (o.append_field(P, "note"), o.define_type((*P, "note"), Str()))
    _, back, blocked = _both_ways(parts_db(spark, sf), left, right, types)
    moved = back.export("part", "p_brand").where("p_brand = 'B'").agg(F.count(F.lit(1)).alias("n")).select(F.lit("set_cell").alias("kind"), F.lit("moved").alias("outcome"), "n")
    return blocked.groupBy("kind", F.col("blocker_kind").alias("outcome")).agg(F.count(F.lit(1)).alias("n")).unionByName(moved)


def unwrap(spark, sf):
    """Lists of assignees on the left, the first one alone on the right."""
    db = todo_db(spark, sf)
    wrapped = db.apply(WRAP)
    left = oplog.forward(old_writes(db), WRAP, db)
    src = db["tasks"].live().where("k % 5 = 0")
    right = oplog.log(src, "set_cell", "tasks", seq=F.col("k") + 100, eid=F.col(EID), fid=F.lit("who"), val_s=F.lit("Jacque"))
    there, back, _ = _both_ways(wrapped, left, right, (o.unwrap_first(WHO, ONE, Str()),))
    return there.export("tasks", "k", F.col("who").alias("there")).join(back.export("tasks", "k", F.get("who", 0)["val"].alias("back")), "k")


def record_move(spark, sf):
    """A column beside a record on the left, within it on the right."""
    db = parts_db(spark, sf).apply(o.wrap_record((*P, "p_brand"), "name"))
    left = _part_writes(spark, sf, 10, 0, "p_type", val_s=F.lit("T"))
    right = _part_writes(spark, sf, 15, 0, "p_brand", sub="kind", val_s=F.lit("K"))
    there, back, _ = _both_ways(db, left, right, (o.move_field((*P, "p_type"), (*P, "p_brand", "kind")),))
    return there.export("part", "p_partkey", F.col("p_brand.kind").alias("there")).join(back.export("part", "p_partkey", F.col("p_type").alias("back")), "p_partkey")


def split_numbers(spark, sf):
    """Number columns through a split, and a relinked row, which takes the numbers of what it links to."""
    types = (o.split_table((*P, "p_size"), ("sizes",), ("p_size", "p_retailprice")),)
    left = _part_writes(spark, sf, 10, 0, "p_retailprice", val_n=F.col("p_partkey") + 0.25)
    right = _part_writes(spark, sf, 15, 0, "p_size", target="sizes", val_n=F.lit(99.0))
    src = table(spark, sf, "part").where("p_partkey % 20 = 2")
    to = F.concat(F.lit("p"), (F.col("p_partkey") - 1).cast("string"))
    right = right.unionByName(oplog.log(src, "set_link", "part", seq=F.col("p_partkey") + 100, eid=_key()[0], fid=F.lit("p_size_link"), val_s=to))
    there, back, _ = _both_ways(parts_db(spark, sf), left, right, types)
    joined = there.apply(o.join_link((*P, "p_size_link"))).export("part", "p_partkey", F.col("p_retailprice").alias("there"))
    return joined.join(back.export("part", "p_partkey", F.col("p_size").cast("bigint").alias("size"), F.col("p_retailprice").alias("price")), "p_partkey")


def split_drop(spark, sf):
    """An order that is dropped on the left takes the customer row along that only it links to."""
    db = orders_db(spark, sf)
    src = db["orders"].live().where("k % 50 = 0")
    left = oplog.log(src, "drop_elem", "orders", seq=F.col("k") + 100, arg_eid=F.col(EID))
    right = oplog.log(src.where("false"), "drop_elem", "orders")
    there, _, _ = _both_ways(db, left, right, (SPLIT,))
    return there.export("customers", F.col(EID).alias("eid"), "name").unionByName(there.export("orders", F.concat(F.lit("order "), F.col(EID)).alias("eid"), F.col("item").alias("name")))


def both_planes(spark, sf):
    """Type operations on both branches and data on both: after syncing, both sides are one."""
    a, b = _branches(parts_db(spark, sf), _part_writes(spark, sf, 10, 0, "p_brand", val_s=F.lit("L")), _part_writes(spark, sf, 15, 0, "p_brand", sub="b", val_s=F.lit("R")), (o.wrap_record((*P, "p_brand"), "b"),))
    a = a.alter(5_000_000, o.rename_field((*P, "p_type"), "sort"), o.convert_type((*P, "p_size"), Str(), parts_db(spark, sf)["part"].field("p_size").type))
    a = a.append(_part_writes(spark, sf, 25, 0, "p_size", seq=6_000_000, val_s=F.lit("99")))
    left, right = vcs.sync(a, b)
    states = [x.state() for x in (left, right)]
    assert states[0]["part"].fields == states[1]["part"].fields or {f.fid: f.type for f in states[0]["part"].fields} == {f.fid: f.type for f in states[1]["part"].fields}
    cols = lambda n: ["p_partkey", F.col("p_brand.b").alias(f"{n}_brand"), F.col("p_size").alias(f"{n}_size")]
    return states[0].export("part", *cols("left")).join(states[1].export("part", *cols("right")), "p_partkey")


# ---- undo ---------------------------------------------------------------------------------


def _todo_doc(spark, sf) -> vcs.Document:
    db = todo_db(spark, sf)
    src = db["tasks"].live()
    new = F.concat(F.lit("n"), F.col("k").cast("string"))
    ops = old_writes(db).unionByName(oplog.log(src.where("k % 100 = 0"), "append_elem", "tasks", seq=F.col("k") + 10_000_000, arg_eid=new))
    ops = ops.unionByName(oplog.log(src.where("k % 100 = 0"), "set_cell", "tasks", seq=F.col("k") + 20_000_000, eid=new, fid=F.lit("who"), val_s=F.lit("New")))
    return vcs.Document("main", db, ops.unionByName(oplog.log(src.where("k % 50 = 0"), "drop_elem", "tasks", seq=F.col("k") + 30_000_000, arg_eid=F.col(EID))))


UNDONE = "kind = 'append_elem' and seq % 200 = 0 or kind = 'set_cell' and eid like 'o%' and seq % 2 = 0 or kind = 'drop_elem' and seq % 100 = 0"


def _who(doc: vcs.Document):
    return doc.state().export("tasks", F.col(EID).alias("eid"), "who")


def undo_insert(spark, sf):
    """Insertions, drops and writes are taken back; what was written in a row that is gone grounds out."""
    return _who(vcs.undo(_todo_doc(spark, sf), F.expr(UNDONE)))


def undo_of_undo(spark, sf):
    """The delta is part of the log, and taking it back restores the state before."""
    once = vcs.undo(_todo_doc(spark, sf), F.expr(UNDONE))
    return _who(vcs.undo(once, F.col("undo_of").isNotNull()))


def undo_simplified(spark, sf):
    """Undone operations and their undos cancel."""
    once = vcs.undo(_todo_doc(spark, sf), F.expr("kind = 'set_cell' and eid like 'o%' and seq % 2 = 0"))
    return oplog.cancel_undone(once.ops).groupBy("kind").agg(F.count(F.lit(1)).alias("n"))


def undo_fidelity(spark, sf):
    """Cells after the delta that equal those of the history without the undone operations."""
    doc = _todo_doc(spark, sf)
    return ms.undo_fidelity(_who(vcs.undo(doc, F.expr(UNDONE))), _who(vcs.scrub(doc, F.expr(UNDONE))), ["eid"])


def undo_type(spark, sf):
    """A wrap is taken back after writes behind it: the delta is a type operation, and the writes stay."""
    db = todo_db(spark, sf)
    doc = vcs.Document("main", db, new_writes(db).limit(0)).alter(0, WRAP, o.rename_field(("tasks", ANY, "what"), "task")).append(new_writes(db).withColumn("seq", F.col("seq") + 10))
    return vcs.undo_type(doc, 0).state().export("tasks", "k", "who")


def undo_of_merge(spark, sf):
    """A deduplication is taken back: rows live again, links return, and a link that was set anew is kept."""
    split = split_db(spark, sf)
    m = moves(split)
    after = deduped(spark, sf)
    src = split["orders"].live().where("k % 100 = 0")
    relink = oplog.log(src, "set_link", "orders", seq=F.lit(1), eid=F.col(EID), fid=F.lit("name_link"), val_s=F.lit("*"))
    now = oplog.replay(after, relink, ["orders"])
    back = oplog.replay(now, undo_merge(split, now, "customers", m, 2))
    return back.export("orders", F.col(EID).alias("eid"), F.col("name_link").alias("customer"))


# ---- deduplication, correspondence, updates, formulas ---------------------------------------


def reconciled(spark, sf):
    """Classes after one member in thirteen was written: who left its class, and which class that was."""
    split = split_db(spark, sf)
    m = moves(split)
    classes = m.select(F.col("src").alias("eid"), F.col("dst").alias("root"))
    src = orders_db(spark, sf)["orders"].live().where("k % 13 = 0")
    ops = oplog.log(src, "set_cell", "customers", seq=F.col("k"), eid=F.col(EID), fid=F.lit("address"), val_s=F.lit("MOVED"))
    now = oplog.replay(split, ops, ["customers"])
    return reconcile(now["customers"], classes, ("name", "address")).select("src", "dst", "was")


def correspondence(spark, sf):
    """Probes of every customer cell that land on the cell that they came from."""
    db = deduped(spark, sf)
    cells = db["customers"].live().select(EID, F.explode(F.array(F.lit("name"), F.lit("address"))).alias("f"))
    probe = oplog.log(cells, "set_cell", "customers", seq=F.lit(0), eid=F.col(EID), fid=F.col("f"), origin_op=F.concat_ws(".", EID, "f"))
    back, _ = oplog.backward(probe, SPLIT, db)
    rows = back.select(F.col("origin_op").alias("cell"), F.concat_ws(".", "eid", "fid").alias("counterpart"))
    links = db["orders"].live().select(EID, "name_link")
    truth = links.select(F.explode(F.array(*[F.struct(F.concat_ws(".", "name_link", F.lit(f)).alias("cell"), F.concat_ws(".", EID, F.lit(f)).alias("counterpart")) for f in ("name", "address")])).alias("x")).select("x.*")
    return ms.correspondence_accuracy(rows, truth)


def updatability(spark, sf):
    """Edits of a view that reach the base: a row without a customer has no place for a name."""
    db = deduped(spark, sf)
    db = db.put(orders=oplog.replay(db, oplog.log(db["orders"].live().where("k % 10 = 0"), "set_link", "orders", seq=F.lit(1), eid=F.col(EID), fid=F.lit("name_link"), val_s=F.lit("*")), ["orders"])["orders"])
    edits = _view_edits(db, "name", {"val_s": F.lit("V")}, "k % 5 = 0").unionByName(_view_edits(db, "item", {"val_s": F.lit("I")}, "k % 7 = 0"))
    ok, bad = update_through(db, Formula((JOIN,), "orders"), edits)
    return ms.updatability(ok, bad)


def shared_size(spark, sf):
    from .docs import events_log

    e = events_log(spark, sf)
    return ms.shared_size(e["shared"], e["left"], e["right"])


def formula_from_diff(spark, sf):
    """The developer's split and pending view, as a formula over production's data, which moved on."""
    db = orders_db(spark, sf)
    writes = oplog.log(db["orders"].live().where("k % 19 = 0"), "set_cell", "orders", seq=F.col("k"), eid=F.col(EID), fid=F.lit("name"), val_s=F.lit("Prod"))
    dev = vcs.Document("dev", db, writes.limit(0)).alter(1, SPLIT, o.rename_field(("orders", ANY, "name_link"), "customer"))
    prod = vcs.Document("prod", db, writes)
    f = from_diff(vcs.diff(dev, prod), "customers")
    return evaluate(prod.state(), f).select(F.col(EID).alias("eid"), "name", "address")


def formula_auto_rewrite(spark, sf):
    """A formula of the database is rewritten by each type operation that the database undergoes."""
    db = orders_db(spark, sf).apply(o.define_formula(("pending",), Formula((o.drop_present(("orders", ANY, "ship_date")),), "orders")))
    db = db.run([SPLIT, o.rename_field(("orders", ANY, "name_link"), "customer"), o.wrap_record(("orders", ANY, "item"), "label")])
    out = evaluate_named(db, "pending")
    return out.select("k", F.col("item"), F.col("name"))


def formula_broken(spark, sf):
    """A formula of the database that reads a dropped column says what broke it; one that does not still gives its rows."""
    db = orders_db(spark, sf).apply(o.define_formula(("pending",), Formula((o.drop_present(("orders", ANY, "ship_date")),), "orders")))
    count = lambda d, name: d.agg(F.count(F.lit(1)).alias(name))
    before, out = count(evaluate_named(db, "pending"), "before"), []
    for formula, column in (("reads it", "ship_date"), ("does not", "item")):
        now, cause = db.apply(o.drop_field(("orders", ANY), column)), None
        try:
            rows = before.crossJoin(count(evaluate_named(now, "pending"), "after"))
        except Blocked as e:
            cause, rows = e.blocker.ids[0], before.withColumn("after", F.lit(None).cast("bigint"))
        out.append(rows.select(F.lit(formula).alias("formula"), F.lit(cause is not None).alias("broken"), F.lit(cause).cast("string").alias("cause"), "before", "after"))
    return out[0].unionByName(out[1])


def manual_pending(spark, sf):
    """Baseline: the pending view written by hand for the split schema, to be rewritten at every change of it."""
    db = deduped(spark, sf)
    db["orders"].live().createOrReplaceTempView("manual_orders")
    db["customers"].live().createOrReplaceTempView("manual_customers")
    return bl.manual_query(spark, "select k, item, quantity, ship_date, name, address from manual_orders left join manual_customers c on name_link = c.__eid where ship_date is null")


def rewrite_fidelity(spark, sf):
    """Rows of the rewritten formula that the query by hand gives, too."""
    from .acme import COLUMNS, TYPE_OPS, rewrite_back, rewrite_forward

    f = rewrite_forward(rewrite_back(PENDING, TYPE_OPS), TYPE_OPS)
    mine = evaluate(deduped(spark, sf), f).select(*COLUMNS)
    return ms.rewrite_fidelity(mine, manual_pending(spark, sf).select(*COLUMNS), ["k"])


def engine_cost(spark, sf):
    """Jobs and stages of moving a log across a split; how many they are does not depend on its length."""
    db = orders_db(spark, sf)
    ops = oplog.log(db["orders"].live(), "set_cell", "orders", seq=F.col("k"), eid=F.col(EID), fid=F.lit("name"), val_s=F.lit("X"))
    cost = ms.engine_cost(spark, "split", lambda: oplog.forward(ops, SPLIT, db).write.format("noop").mode("overwrite").save(), ops.count())
    return cost.select("name", "ops", (F.col("jobs") <= 12).alias("few_jobs"), (F.col("seconds") > 0).alias("timed"))


def delete_from_history(spark, sf):
    """Baseline: rows struck out of the log leave others dangling that mention what they made."""
    doc = _todo_doc(spark, sf)
    return bl.delete_from_history(doc.ops, F.expr("kind = 'append_elem'")).groupBy("kind", "dangling").agg(F.count(F.lit(1)).alias("n"))


def last_common_ancestor(spark, sf):
    """Baseline: histories of one document are alike up to the first operation that differs; what was transferred later is not seen."""
    db = todo_db(spark, sf)
    both = old_writes(db)
    a, b = both.unionByName(new_inserts(db).withColumn("seq", F.col("seq") + 10_000_000)), both.where("seq < 1000").unionByName(both.where("seq >= 1000").withColumn("op_id", F.concat("op_id", F.lit("'"))))
    return spark.createDataFrame([(bl.last_common_ancestor(a, b),)], "shared bigint")


def single_source_views(spark, sf):
    """Baseline: both schemas as views of one table; they agree because neither can diverge."""
    f = orders_db(spark, sf)["orders"].live().select("k", "name", "address")
    bl.single_source_views(f, ["name", "address"], "single")
    return spark.sql("select f.k, s.customer from single_flat f join single_split s on f.k = s.k")


def relocate(spark, sf):
    """A row's content goes to another row, links follow, and the list gets another name."""
    c = table(spark, sf, "customer").select("c_custkey", "c_name", "c_nationkey")
    n = table(spark, sf, "nation")
    from ..model.types import Atom, LinkT

    db = Database(
        {
            "customer": from_table(c.withColumn("nation", F.concat(F.lit("n"), F.col("c_nationkey").cast("string"))), F.col("c_custkey"), "c", {"c_custkey": Atom("bigint"), "nation": LinkT(("nation",))}),
            "nation": from_table(n, F.col("n_nationkey"), "n", {"n_nationkey": Atom("int"), "n_name": Str()}),
        }
    )
    db = db.run([o.move_elem(("nation", "n3"), "n7"), o.move_table(("nation",), ("country",)), o.join_link(("customer", ANY, "nation"))])
    return db.export("customer", "c_custkey", "n_nationkey")


QUERIES = {
    "xfer_convert": convert,
    "xfer_define_blocked": define_blocked,
    "xfer_unwrap": unwrap,
    "xfer_record_move": record_move,
    "xfer_split_numbers": split_numbers,
    "xfer_split_drop": split_drop,
    "xfer_both_planes": both_planes,
    "undo_insert": undo_insert,
    "undo_of_undo": undo_of_undo,
    "undo_simplified": undo_simplified,
    "undo_type": undo_type,
    "undo_merge": undo_of_merge,
    "acme_reconcile_classes": reconciled,
    "formula_from_diff": formula_from_diff,
    "formula_auto_rewrite": formula_auto_rewrite,
    "formula_broken": formula_broken,
    "measure_undo_fidelity": undo_fidelity,
    "measure_correspondence": correspondence,
    "measure_updatability": updatability,
    "measure_shared_size": shared_size,
    "measure_rewrite_fidelity": rewrite_fidelity,
    "measure_engine_cost": engine_cost,
    "baseline_delete_from_history": delete_from_history,
    "baseline_last_common_ancestor": last_common_ancestor,
    "baseline_single_source_views": single_source_views,
    "baseline_manual_query": manual_pending,
    "geo_relocate": relocate,
}

_W, _T = f"with {D_ORDERS}", f"with {D_TODO}"
_TEXT = "case when {0} = floor({0}) then cast(cast({0} as bigint) as varchar) else cast({0} as varchar) end"
_PRICE = _TEXT.format("p_retailprice")
_DOC = f"""{_T}, r as (
  select 'o' || k as eid, case when k % 7 = 0 then 'Jill-' || k else who end as who, k, who as old from t where k % 50 <> 0 union all select 'n' || k, 'New', k, null from t where k % 100 = 0)"""
_UNDONE = f"""{_T} select 'o' || k as eid, case when k % 7 = 0 and k % 2 <> 0 then 'Jill-' || k else who end as who from t where k % 50 <> 0 or k % 100 = 0
  union all select 'n' || k, 'New' from t where k % 100 = 0 and k % 200 <> 0"""
_SETS_SQL = """last as (select u, f, arg_max(v, seq) filter (where br = 'L') as l, arg_max(v, seq) filter (where br = 'R') as r, arg_max(v, seq) filter (where br = 'O') as s, count(*) filter (where br = 'L') as nl, count(*) filter (where br = 'R') as nr,
    list(v) filter (where br = 'L') as lv, list(v) filter (where br = 'R') as rv from e group by u, f),
  c as (select nl, nr, coalesce(l, s) is distinct from coalesce(r, s) as differ, nl > 0 as wl, nr > 0 as wr, coalesce(list_contains(lv, coalesce(r, s)), false) as inl, coalesce(list_contains(rv, coalesce(l, s)), false) as inr from last)
  select cast(sum(nl) - count(*) filter (where differ and wl and (inl or not inr)) as bigint) as left_shared, cast(sum(nr) - count(*) filter (where differ and wr and not inl) as bigint) as right_shared from c"""
ORACLES = {
    "xfer_convert": f"""select p_partkey, case when p_partkey % 10 = 0 then cast(p_partkey as varchar) when p_partkey % 10 = 5 then p_partkey || '.5' when p_partkey % 20 = 3 then 'x' || p_partkey else {_PRICE} end as there,
      case when p_partkey % 10 = 0 then cast(p_partkey as double) when p_partkey % 10 = 5 then p_partkey + 0.5 else p_retailprice end as back, p_partkey % 20 = 3 as blocked from part""",
    "xfer_define_blocked": "select 'set_cell' as kind, 'define_type' as outcome, count(*) as n from part where p_partkey % 4 = 0 union all select 'set_cell', 'moved', count(*) from part where p_partkey % 6 = 0",
    "xfer_unwrap": f"{_T} select k, case when k % 7 = 0 then 'Jill-' || k when k % 5 = 0 then 'Jacque' else who end as there, case when k % 5 = 0 then 'Jacque' when k % 7 = 0 then 'Jill-' || k else who end as back from t",
    "xfer_record_move": "select p_partkey, case when p_partkey % 10 = 0 then 'T' when p_partkey % 15 = 0 then 'K' else p_type end as there, case when p_partkey % 15 = 0 then 'K' when p_partkey % 10 = 0 then 'T' else p_type end as back from part",
    "xfer_split_numbers": """with s as (select p_partkey, case when p_partkey % 10 = 0 then p_partkey + 0.25 else p_retailprice end as price, case when p_partkey % 15 = 0 then 99 else p_size end as size,
        p_retailprice as old_price, case when p_partkey % 20 = 2 then p_partkey - 1 else p_partkey end as at from part)
      select a.p_partkey, cast(b.price as double) as there, cast(b.size as bigint) as size, cast(case when a.p_partkey % 20 = 2 then b.old_price else a.price end as double) as price from s a join s b on b.p_partkey = a.at""",
    "xfer_split_drop": f"{_W} select 'o' || k as eid, name from d where k % 50 <> 0 union all select 'order o' || k, item from d where k % 50 <> 0",
    "xfer_both_planes": """with s as (select p_partkey, case when p_partkey % 10 = 0 then 'L' when p_partkey % 15 = 0 then 'R' else p_brand end as brand, case when p_partkey % 25 = 0 then '99' else cast(p_size as varchar) end as size from part)
      select p_partkey, brand as left_brand, size as left_size, brand as right_brand, size as right_size from s""",
    "undo_insert": _UNDONE,
    "undo_of_undo": f"{_DOC} select eid, who from r",
    "undo_simplified": f"""{_T} select 'set_cell' as kind, count(*) filter (where k % 7 = 0 and k % 2 <> 0) + count(*) filter (where k % 100 = 0) as n from t
      union all select 'append_elem', count(*) from t where k % 100 = 0 union all select 'drop_elem', count(*) from t where k % 50 = 0""",
    "undo_type": f"{_T} select k, case when k % 5 = 0 then 'Jacque' else who end as who from t",
    "undo_merge": f"{_W} select 'o' || k as eid, case when k % 100 = 0 then '*' else 'o' || k end as customer from d",
    "acme_reconcile_classes": f"""{_W}, c as (select k, min(k) over (partition by name, address) as rep from d), u as (select k, rep, k % 13 = 0 as w, rep % 13 = 0 as rw from c),
      x as (select k, rep, w, rw, min(k) over (partition by rep, w) as first, min(case when k <> rep then k end) over (partition by rep, w) as other from u)
      select 'o' || k as src, 'o' || case when w = rw then rep else other end as dst, 'o' || rep as was from x where k <> rep""",
    "formula_from_diff": f"{_W} select 'o' || k as eid, case when k % 19 = 0 then 'Prod' else name end as name, address from d",
    "formula_auto_rewrite": f"{_W} select k, item, name from d where ship_date is null",
    "formula_broken": f"""{_W}, n as (select count(*) as before from d where ship_date is null)
      select formula, cause is not null as broken, cause, before, case when cause is null then before end as after from n, (values ('reads it', 'ship_date'), ('does not', null)) t(formula, cause)""",
    "measure_undo_fidelity": f"select count(*) as rows, count(*) as faithful from ({_UNDONE})",
    "measure_correspondence": f"{_W} select 2 * count(*) as cells, 2 * count(*) as found from d",
    "measure_updatability": f"""{_W}, e as (select count(*) filter (where k % 5 = 0) as names, count(*) filter (where k % 7 = 0) as items, count(*) filter (where k % 10 = 0) as lost from d)
      select 'set_cell' as kind, names + items as offered, names + items - lost as accepted from e""",
    "measure_shared_size": f"""with {L_EVENTS}, {_SETS_SQL}""",
    "measure_rewrite_fidelity": f"{_W} select count(*) as rows, count(*) as faithful from d where ship_date is null",
    "measure_engine_cost": "select 'split' as name, count(*) as ops, true as few_jobs, true as timed from orders",
    "baseline_delete_from_history": f"""{_T} select 'set_cell' as kind, true as dangling, count(*) as n from t where k % 100 = 0 union all select 'set_cell', false, count(*) from t where k % 7 = 0 union all select 'drop_elem', false, count(*) from t where k % 50 = 0""",
    "baseline_last_common_ancestor": f"{_T} select count(*) as shared from t where k % 7 = 0 and k < 1000",
    "baseline_single_source_views": f"{_W} select k, min(k) over (partition by name, address) as customer from d",
    "baseline_manual_query": f"{_W} select * from d where ship_date is null",
    "geo_relocate": "select c_custkey, case when c_nationkey = 7 then 3 when c_nationkey = 3 then 3 else c_nationkey end as n_nationkey from customer",
}
