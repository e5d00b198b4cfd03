"""Splitting, deduplicating and joining an orders table, its divergence, and queries over it."""

from __future__ import annotations

from pyspark.sql import functions as F

from .. import vcs
from ..model import ops as o
from ..model.types import ANY
from ..operators import oplog
from ..operators.forward import dedupe_moves, merge, resolve, settled
from ..operators.relation import EID, ORD, Database
from ..plans.formula import Formula, evaluate, rewrite_back, rewrite_forward, update_through
from .docs import D_ORDERS, SPLIT, orders_db, table

COLUMNS = ["k", "item", "quantity", "ship_date", "name", "address"]
JOIN = o.join_link(("orders", ANY, "name_link"))
PENDING = Formula((JOIN, o.drop_present(("orders", ANY, "ship_date"))), "orders")


def flat(db: Database):
    """The orders' columns with blank strings as null, as oracles have them."""
    return db.export("orders", *[F.nullif(F.col(c), F.lit("")).alias(c) if c in ("item", "name", "address") else F.col(c) for c in COLUMNS])


def split_db(spark, sf):
    return orders_db(spark, sf).apply(SPLIT).apply(o.rename_field(("orders", ANY, "name_link"), "customer"))


def moves(db: Database):
    """The deduplication's moves, computed once for all that follows them."""
    return settled(dedupe_moves(db["customers"], ("name", "address")), "moves")


def deduped(spark, sf):
    db = split_db(spark, sf)
    return merge(db, "customers", moves(db))


def split_orders(spark, sf):
    return split_db(spark, sf).export("orders", F.col(EID).alias("eid"), "item", "quantity", "ship_date", F.col("name_link").alias("customer"))


def split_customers(spark, sf):
    return split_db(spark, sf).export("customers", F.col(EID).alias("eid"), "name", "address")


def dedupe_customers(spark, sf):
    return deduped(spark, sf).export("customers", F.col(EID).alias("eid"), "name", "address")


def forwarded_links(spark, sf):
    return deduped(spark, sf).export("orders", F.col(EID).alias("eid"), F.col("name_link").alias("customer"))


def join_roundtrip(spark, sf):
    return flat(deduped(spark, sf).apply(JOIN))


def chain_moves(spark, sf):
    from pyspark.sql import Window as W

    c = table(spark, sf, "customer")
    w = W.partitionBy("c_nationkey").orderBy("c_custkey")
    chain = c.select(F.col("c_custkey").cast("string").alias("src"), F.lag("c_custkey").over(w).cast("string").alias("dst")).where("dst is not null")
    return resolve(chain).select(F.col("eid").cast("long").alias("c_custkey"), F.col("root").cast("long").alias("root"))


def _new_orders(db: Database, known: bool):
    """A log of orders added on the new side for every thousandth order: linked to that order's customer or to a new one."""
    src = db["orders"].live().where("k % 1000 = 0").select("k", F.concat(F.lit("n"), F.col("k").cast("string")).alias("e"), "name_link")
    rows = oplog.log(src, "append_elem", "orders", seq=F.col("k"), arg_eid=F.col("e"))
    rows = rows.unionByName(oplog.log(src, "set_cell", "orders", seq=F.col("k"), eid=F.col("e"), fid=F.lit("k"), val_n=-F.col("k").cast("double")))
    rows = rows.unionByName(oplog.log(src, "set_cell", "orders", seq=F.col("k"), eid=F.col("e"), fid=F.lit("item"), val_s=F.lit("NEW")))
    if known:
        return rows.unionByName(oplog.log(src, "set_link", "orders", seq=F.col("k"), eid=F.col("e"), fid=F.lit("name_link"), val_s=F.col("name_link")))
    rows = rows.unionByName(oplog.log(src, "append_elem", "customers", seq=F.col("k"), arg_eid=F.concat(F.lit("c"), "e")))
    rows = rows.unionByName(oplog.log(src, "set_cell", "customers", seq=F.col("k"), eid=F.concat(F.lit("c"), "e"), fid=F.lit("name"), val_s=F.lit("New")))
    return rows.unionByName(oplog.log(src, "set_link", "orders", seq=F.col("k"), eid=F.col("e"), fid=F.lit("name_link"), val_s=F.concat(F.lit("c"), "e")))


def _insert_back(known: bool):
    def run(spark, sf):
        db = deduped(spark, sf)
        ops, _ = oplog.backward(_new_orders(db, known), SPLIT, db)
        return flat(oplog.replay(orders_db(spark, sf), ops))

    return run


def new_customer_blockers(spark, sf):
    db = deduped(spark, sf)
    _, blocked = oplog.backward(_new_orders(db, False), SPLIT, db)
    return blocked.groupBy("kind", "blocker_kind").agg(F.count(F.lit(1)).alias("n"))


def _address_writes(db: Database):
    src = db["orders"].live().where("k % 13 = 0")
    return oplog.log(src, "set_cell", "orders", seq=F.col("k"), eid=F.col(EID), fid=F.lit("address"), val_s=F.concat(F.lit("MOVED/"), F.col("k").cast("string")))


def old_update_overwrite(spark, sf):
    old = orders_db(spark, sf)
    db = split_db(spark, sf)
    m = moves(db)
    ordered = m.join(db["customers"].df.select(F.col(EID).alias("src"), F.col(ORD).alias("ord")), "src")
    ops = oplog.forward_merge(oplog.forward(_address_writes(old), SPLIT, old), "customers", ordered, "overwrite")
    return flat(oplog.replay(merge(db, "customers", m), ops, ["customers"]).apply(JOIN))


def old_update_equivalence(spark, sf):
    old = orders_db(spark, sf)
    split = split_db(spark, sf)
    # writes land on the members of a class, and members that differ now are classes of their own
    db = oplog.replay(split, oplog.forward(_address_writes(old), SPLIT, old), ["customers"])
    return merge(db, "customers", moves(db)).export("customers", F.col(EID).alias("eid"), "name", "address")


def customer_update_back(spark, sf):
    db = deduped(spark, sf)
    src = db["customers"].live().select(EID, F.substring(EID, 2, 20).cast("long").alias("k")).where("k % 17 = 0")
    ops = oplog.log(src, "set_cell", "customers", seq=F.col("k"), eid=F.col(EID), fid=F.lit("name"), val_s=F.concat(F.lit("Renamed "), F.col("k").cast("string")))
    back, _ = oplog.backward(ops, SPLIT, db)
    return flat(oplog.replay(orders_db(spark, sf), back))


def type_deploy(spark, sf):
    """The developer's split, transferred onto a production copy whose data moved on."""
    db = orders_db(spark, sf)
    ops = oplog.log(db["orders"].live().where("k % 19 = 0"), "set_cell", "orders", seq=F.col("k"), eid=F.col(EID), fid=F.lit("name"), val_s=F.lit("Prod"))
    dev, prod = vcs.Document("dev", db, ops.limit(0)).alter(1, SPLIT), vcs.Document("prod", db, ops)
    return vcs.merge(vcs.diff(dev, prod), prod, ("type",)).state().export("customers", F.col(EID).alias("eid"), "name", "address")


def decompose(spark, sf):
    db = orders_db(spark, sf).apply(o.decompose(("orders", ANY, "name"), ("customers",), ("name", "address")))
    return db.export("orders", F.col(EID).alias("eid"), F.col("name_link").alias("customer"))


def _formula(formula: Formula, base=deduped):
    def run(spark, sf):
        out = evaluate(base(spark, sf), formula)
        return out.select(*[F.nullif(F.col(c), F.lit("")).alias(c) if c in ("item", "name", "address") else F.col(c) for c in COLUMNS])

    return run


SHIPPED = Formula((JOIN, o.drop_absent(("orders", ANY, "ship_date"))), "orders")
TYPE_OPS = [SPLIT, o.rename_field(("orders", ANY, "name_link"), "customer")]


def rewritten_back(spark, sf):
    return _formula(rewrite_back(PENDING, TYPE_OPS), orders_db)(spark, sf)


def rewritten_forward(spark, sf):
    return _formula(rewrite_forward(rewrite_back(PENDING, TYPE_OPS), TYPE_OPS))(spark, sf)


def rewrite_ops(spark, sf):
    """A formula's operations before and after rewriting, and the rows that the returned table has after each, on the schema that the formula is for."""
    back = rewrite_back(PENDING, TYPE_OPS)
    again = rewrite_forward(back, TYPE_OPS)
    old = orders_db(spark, sf)
    new = old.run(TYPE_OPS)
    new = merge(new, "customers", moves(new))
    out = None
    for step, f, db in (("given", PENDING, new), ("back", back, old), ("forward", again, new)):
        for i, x in enumerate(f.ops):
            db = db.apply(x)
            row = db[f.ret].live().agg(F.count(F.lit(1)).alias("rows")).select(F.lit(step).alias("step"), F.lit(i).alias("i"), F.lit(x.kind).alias("kind"), "rows")
            out = row if out is None else out.unionByName(row)
    return out


def survives_rename(spark, sf):
    changes = [o.rename_field(("orders", ANY, "ship_date"), "shipped"), o.wrap_record(("orders", ANY, "item"), "label")]
    f = rewrite_forward(PENDING, changes)
    return _formula(f, lambda s, d: deduped(s, d).run(changes))(spark, sf)


def _view_edits(db: Database, column: str, value, where: str):
    src = db["orders"].live().where(where)
    return oplog.log(src, "set_cell", "orders", seq=F.col("k"), eid=F.col(EID), fid=F.lit(column), **value)


def _shipped_back(spark, sf):
    db = deduped(spark, sf)
    edits = _view_edits(db, "ship_date", {"val_t": F.lit("2030-01-01 00:00:00").cast("timestamp_ntz")}, "ship_date is null and k % 4 = 0")
    ops, _ = update_through(db, PENDING, edits)
    return oplog.replay(db, ops, ["orders"])


def view_update_ship_date(spark, sf):
    return _formula(PENDING, _shipped_back)(spark, sf)


def view_update_base(spark, sf):
    return flat(_shipped_back(spark, sf).apply(JOIN))


def view_update_customer(spark, sf):
    db = deduped(spark, sf)
    edits = _view_edits(db, "name", {"val_s": F.concat(F.lit("V"), F.col("k").cast("string"))}, "ship_date is null and k % 23 = 0")
    ops, _ = update_through(db, PENDING, edits)
    return flat(oplog.replay(db, ops, ["customers"]).apply(JOIN))


def pinned_dead_link(spark, sf):
    f = Formula((JOIN, o.drop_field(("orders", ANY), "name"), o.drop_field(("orders", ANY), "address")), "orders")
    return evaluate(deduped(spark, sf), f).select("k", "item", "quantity", "ship_date")


def insert_through_split(spark, sf):
    """A new order of the old copy, transferred forward: it appears with a linked customer row of its own."""
    old = orders_db(spark, sf)
    src = old["orders"].live().where("k % 1000 = 0")
    e = F.concat(F.lit("n"), F.col("k").cast("string"))
    ops = oplog.log(src, "append_elem", "orders", seq=F.col("k"), arg_eid=e)
    ops = ops.unionByName(oplog.log(src, "set_cell", "orders", seq=F.col("k") + 1, eid=e, fid=F.lit("name"), val_s=F.lit("N")))
    db = oplog.replay(split_db(spark, sf), oplog.forward(ops, SPLIT, old))
    return db.export("orders", F.col(EID).alias("eid"), F.col("name_link").alias("customer")).where("eid like 'n%'").join(
        db.export("customers", F.col(EID).alias("customer"), "name"), "customer"
    )


QUERIES = {
    "acme_split_orders": split_orders,
    "acme_split_customers": split_customers,
    "acme_dedupe_customers": dedupe_customers,
    "acme_forwarded_links": forwarded_links,
    "acme_join_roundtrip": join_roundtrip,
    "acme_chain_moves": chain_moves,
    "acme_insert_into_new": _insert_back(True),
    "acme_new_customer_blocked": _insert_back(False),
    "acme_new_customer_blockers": new_customer_blockers,
    "acme_insert_through_split": insert_through_split,
    "acme_old_update_forward": old_update_overwrite,
    "acme_old_update_equivalence": old_update_equivalence,
    "acme_customer_update_back": customer_update_back,
    "acme_type_deploy": type_deploy,
    "acme_decompose": decompose,
    "view_join": _formula(Formula((JOIN,), "orders")),
    "view_pending": _formula(PENDING),
    "view_shipped": _formula(SHIPPED),
    "view_update_ship_date": view_update_ship_date,
    "view_update_base": view_update_base,
    "view_update_customer": view_update_customer,
    "view_dead_link": pinned_dead_link,
    "formula_rewrite_back": rewritten_back,
    "formula_rewrite_forward": rewritten_forward,
    "formula_rewrite_ops": rewrite_ops,
    "formula_survives_rename": survives_rename,
}

_W = f"with {D_ORDERS}"
_CLASS = "min(k) over (partition by name, address)"
_NEW = "k % 1000 = 0"
ORACLES = {
    "acme_split_orders": f"{_W} select 'o' || k as eid, item, quantity, ship_date, 'o' || k as customer from d",
    "acme_split_customers": f"{_W} select 'o' || k as eid, name, address from d",
    "acme_dedupe_customers": f"{_W} select 'o' || min(k) as eid, name, address from d group by name, address",
    "acme_forwarded_links": f"{_W} select 'o' || k as eid, 'o' || {_CLASS} as customer from d",
    "acme_join_roundtrip": f"{_W} select * from d",
    "acme_chain_moves": "select * from (select c_custkey, min(c_custkey) over (partition by c_nationkey) as root from customer) where c_custkey <> root",
    "acme_insert_into_new": f"{_W} select * from d union all select -k, 'NEW', null, null, name, address from d where {_NEW}",
    "acme_new_customer_blocked": f"{_W} select * from d union all select -k, 'NEW', null, null, null, null from d where {_NEW}",
    "acme_new_customer_blockers": f"{_W} select kind, 'split_table' as blocker_kind, count(*) as n from d, (values ('append_elem'), ('set_cell')) t(kind) where {_NEW} group by 1",
    "acme_insert_through_split": f"{_W} select 'n' || k as customer, 'n' || k as eid, 'N' as name from d where {_NEW}",
    "acme_old_update_forward": f"""{_W}, c as (select *, max(k) over (partition by name, address) as last, count(*) over (partition by name, address) as n from d)
      select k, item, quantity, ship_date, name, case when last % 13 = 0 then 'MOVED/' || last else address end as address from c""",
    "acme_old_update_equivalence": f"""{_W}, u as (select k, name, case when k % 13 = 0 then 'MOVED/' || k else address end as address from d)
      select 'o' || min(k) as eid, name, address from u group by name, address""",
    "acme_customer_update_back": f"""{_W}, c as (select *, {_CLASS} as rep from d)
      select k, item, quantity, ship_date, case when rep % 17 = 0 then 'Renamed ' || rep else name end as name, address from c""",
    "acme_type_deploy": f"{_W} select 'o' || k as eid, case when k % 19 = 0 then 'Prod' else name end as name, address from d",
    "acme_decompose": f"{_W} select 'o' || k as eid, 'o' || {_CLASS} as customer from d",
    "view_join": f"{_W} select * from d",
    "view_pending": f"{_W} select * from d where ship_date is null",
    "view_shipped": f"{_W} select * from d where ship_date is not null",
    "view_update_ship_date": f"{_W} select * from d where ship_date is null and k % 4 <> 0",
    "view_update_base": f"""{_W} select k, item, quantity, case when ship_date is null and k % 4 = 0 then timestamp '2030-01-01 00:00:00' else ship_date end as ship_date, name, address from d""",
    "view_update_customer": f"""{_W}, c as (select *, max(case when ship_date is null and k % 23 = 0 then k end) over (partition by name, address) as w from d)
      select k, item, quantity, ship_date, case when w is not null then 'V' || w else name end as name, address from c""",
    "view_dead_link": f"{_W} select k, item, quantity, ship_date from d",
    "formula_rewrite_back": f"{_W} select * from d where ship_date is null",
    "formula_rewrite_forward": f"{_W} select * from d where ship_date is null",
    "formula_rewrite_ops": f"""{_W}, n as (select count(*) as every, count(*) filter (where ship_date is null) as pending from d)
      select step, i, kind, case kind when 'join_link' then every else pending end as rows
      from n, (values ('given', 0, 'join_link'), ('given', 1, 'drop_present'), ('back', 0, 'drop_present'), ('forward', 0, 'join_link'), ('forward', 1, 'drop_present')) t(step, i, kind)""",
    "formula_survives_rename": f"{_W} select * from d where ship_date is null",
}
