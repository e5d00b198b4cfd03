"""Operation logs as DataFrames: replay, transfer across schema changes, diffs, undo, dependencies.

A row is one operation. Moving any number of operations across a type operation is a fixed
number of column expressions or joins, never a loop over operations. Values travel in three
typed columns so that numbers are never printed and parsed.
"""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..model.ops import Op, from_json, to_json
from ..model.types import NULL_LINK, ONE, Atom, LinkT, ListT, Num, RecordT, Str, Type, initial_column, spark_type
from .forward import settled
from .relation import DEAD, EID, LAST, ORD, Database, Rejected, Relation, converted, moved_columns

#: Columns of a log and their Spark types: fixed values.
SCHEMA = {
    "seq": "bigint", "op_id": "string", "kind": "string", "list_key": "string", "eid": "string", "fid": "string", "sub": "string",
    "val_s": "string", "val_n": "double", "val_t": "timestamp_ntz", "arg_eid": "string", "anchor": "string", "origin_op": "string",
    "plane": "string", "type_json": "string", "branch": "string", "undo_of": "string", "author": "string", "at": "timestamp_ntz",
}
CELL = ["list_key", "eid", "fid", "sub"]


def log(df: DataFrame, kind: str, list_key: str, **columns: Column) -> DataFrame:
    """Rows of one kind of operation on one list; columns not given are null. op_id defaults to kind, list, element, field and seq."""
    given = {"kind": F.lit(kind), "list_key": F.lit(list_key), **columns}
    parts = [F.lit(kind), F.lit(list_key), *(given.get(c, F.lit("")) for c in ("eid", "fid", "sub", "seq"))]
    given.setdefault("op_id", F.concat_ws(":", *[F.coalesce(p.cast("string"), F.lit("")) for p in parts]))
    given.setdefault("plane", F.lit("value"))
    return df.select(*[given.get(c, F.lit(None)).cast(t).alias(c) for c, t in SCHEMA.items()])


def log_types(spark: SparkSession, ops: list[tuple[int, Op]], branch: str = "main") -> DataFrame:
    """Rows of type operations, numbered (seq, operation)."""
    rows = [(seq, f"{branch}:type:{seq}", op.kind, op.path[0] if op.path else "", "type", to_json(op), branch) for seq, op in ops]
    df = spark.createDataFrame(rows, "seq bigint, op_id string, kind string, list_key string, plane string, type_json string, branch string")
    return df.select(*[F.col(c) if c in df.columns else F.lit(None).cast(t).alias(c) for c, t in SCHEMA.items()])


def types_of(ops: DataFrame) -> list[tuple[int, Op]]:
    """(seq, operation) of a log's type operations, in order; a schema's history is short, so the driver reads it."""
    rows = ops.where("plane = 'type'").select("seq", "type_json").orderBy("seq").collect()
    return [(r["seq"], from_json(r["type_json"])) for r in rows]


def value_of(t: Type) -> Column:
    """A log row's value under a field type."""
    if isinstance(t, (Str, LinkT)):
        return F.col("val_s")
    if isinstance(t, Num):
        return F.col("val_n")
    if isinstance(t, Atom) and t.name.startswith("timestamp"):
        return F.col("val_t")
    if isinstance(t, Atom) and t.name == "string":
        return F.col("val_s")
    return F.col("val_n").cast(t.name) if isinstance(t, Atom) else F.col("val_s")


def last_writers(ops: DataFrame) -> DataFrame:
    """The last write of each cell: one aggregation with map-side combine."""
    value = F.struct("seq", "op_id", "val_s", "val_n", "val_t")
    best = ops.where("kind in ('set_cell', 'set_link')").groupBy(*CELL).agg(F.max_by(value, "seq").alias("w"))
    return best.select(*CELL, "w.*")


def replay(db: Database, ops: DataFrame, tables: list[str] | None = None) -> Database:
    """The database after a log of value operations over one schema.

    Per table one shuffle of its log rows by element and one left join to the snapshot: new
    rows are header rows, cells take their last write, drops set tombstones unless a later
    restore takes them back. Rows inserted in front of an element sort before it.
    """
    for name in tables or list(db.tables):
        r = db[name]
        mine = ops.where(F.col("list_key") == name)
        new = mine.where("kind in ('insert_elem', 'append_elem') and fid is null")
        keys = order_keys(new, r)
        header = keys.select(EID, ORD, F.lit(False).alias(DEAD), *r.header_row())
        rows = r.select().unionByName(header.select(*r.select().columns))
        plain = {f.fid: f.type for f in r.fields if not isinstance(f.type, (ListT, RecordT))}
        nested = [f for f in r.fields if isinstance(f.type, ListT)]
        writes = last_writers(mine.where(F.col("sub").isNull()))
        cells = [F.max(F.when(F.col("fid") == fid, F.struct(F.col("op_id").alias("o"), value_of(t).alias("v")))).alias(f"__{fid}") for fid, t in plain.items() if fid in r.stored()]
        dead = mine.where("kind in ('drop_elem', 'restore_elem') and fid is null").groupBy(F.col("arg_eid").alias("eid")).agg((F.max_by("kind", "seq") == "drop_elem").alias("__drop"))
        patched = rows
        if cells:
            patch = writes.groupBy(F.col("eid").alias("__p")).agg(*cells)
            patched = rows.join(patch, rows[EID] == F.col("__p"), "left")
            for fid in plain:
                if fid in r.stored():
                    patched = patched.withColumn(fid, F.when(F.col(f"__{fid}").isNotNull(), F.col(f"__{fid}.v")).otherwise(F.col(fid)))
        patched = patched.join(dead.withColumnRenamed("eid", "__d"), F.col(EID) == F.col("__d"), "left").withColumn(DEAD, F.coalesce("__drop", DEAD))
        for f in r.fields:
            if isinstance(f.type, RecordT):
                patched = _replay_record(patched, mine.where(F.col("fid") == f.fid), f.fid, f.type)
        for f in nested:
            patched = _replay_nested(patched, mine.where(F.col("fid") == f.fid), f.fid, f.type)
        db = db.put(**{name: replace(r, df=patched.select(*r.select().columns))})
    return db


def _replay_record(df: DataFrame, ops: DataFrame, fid: str, t: RecordT) -> DataFrame:
    """A record column after writes of its fields (sub)."""
    inner = [g for g in t.fields if isinstance(g.type, (Str, Num, LinkT, Atom))]
    last = last_writers(ops.where(F.col("sub").isNotNull()))
    cells = [F.max(F.when(F.col("sub") == g.fid, F.struct(F.col("op_id").alias("o"), value_of(g.type).alias("v")))).alias(f"__r{i}") for i, g in enumerate(inner)]
    if not cells:
        return df
    out = df.join(last.groupBy(F.col("eid").alias("__a")).agg(*cells), F.col(EID) == F.col("__a"), "left")
    value = F.col(fid)
    for i, g in enumerate(inner):
        value = value.withField(g.fid, F.when(F.col(f"__r{i}").isNotNull(), F.col(f"__r{i}.v")).otherwise(F.col(fid)[g.fid]))
    return out.withColumn(fid, value).drop("__a", *[f"__r{i}" for i in range(len(inner))])


def _replay_nested(df: DataFrame, ops: DataFrame, fid: str, t: ListT) -> DataFrame:
    """A list column after writes, insertions and drops of its elements (sub)."""
    at = last_writers(ops.where(F.col("sub").isNotNull())).groupBy("eid").agg(F.map_from_entries(F.collect_list(F.struct(F.col("sub"), value_of(t.elem).alias("v")))).alias("__w"))
    moved = ops.where("kind in ('insert_elem', 'append_elem', 'drop_elem')").groupBy("eid").agg(
        F.array_sort(F.collect_list(F.when(F.col("kind") != "drop_elem", F.struct("seq", F.col("arg_eid").alias("e"), "anchor")))).alias("__i"),
        F.collect_set(F.when(F.col("kind") == "drop_elem", F.col("arg_eid"))).alias("__g"),
    )
    out = df.join(at.withColumnRenamed("eid", "__a"), F.col(EID) == F.col("__a"), "left").join(moved.withColumnRenamed("eid", "__b"), F.col(EID) == F.col("__b"), "left")
    blank = F.lit("").cast("string") if isinstance(t.elem, Str) else F.lit(None).cast(out.schema[fid].dataType.elementType["val"].dataType)

    def put(items: Column, x: Column) -> Column:
        pos = F.array_position(F.transform(items, lambda y: y["eid"]), x["anchor"])
        new = F.struct(x["e"].alias("eid"), blank.alias("val"))
        size = F.size(items)
        return F.when(F.coalesce(pos, F.lit(0)) > 0, F.concat(F.slice(items, F.lit(1), (pos - 1).cast("int")), F.array(new), F.slice(items, pos.cast("int"), size))).otherwise(F.concat(items, F.array(new)))

    items = F.aggregate(F.coalesce("__i", F.array().cast(out.schema["__i"].dataType)), F.col(fid), put)
    items = F.transform(items, lambda x: F.struct(x["eid"].alias("eid"), F.when(F.map_contains_key(F.coalesce("__w", F.map_from_arrays(F.array().cast("array<string>"), F.array().cast(f"array<{out.schema[fid].dataType.elementType['val'].dataType.simpleString()}>"))), x["eid"]), F.col("__w")[x["eid"]]).otherwise(x["val"]).alias("val")))
    return out.withColumn(fid, F.filter(items, lambda x: ~F.coalesce(F.array_contains("__g", x["eid"]), F.lit(False)))).drop("__a", "__b", "__w", "__i", "__g")


def order_keys(inserts: DataFrame, r: Relation) -> DataFrame:
    """(__eid, __ord) of inserted elements.

    "In front of x" makes a forest whose roots are old elements and the list's end. An
    element's key is the keys of what it stands in front of, then its own seq: compared element
    by element, insertions sort before their anchor and among themselves by seq. Chains are
    resolved by pointer doubling. Dropped anchors stay as tombstones, so nothing shifts.
    """
    node = inserts.select(F.col("arg_eid").alias(EID), "anchor", F.array("seq").alias("path"))
    base = r.df.select(F.col(EID).alias("anchor"), F.slice(ORD, 1, F.size(ORD) - 1).alias("root"))
    if inserts.where("anchor is not null").limit(1).count():
        # a chain of n anchors is resolved in log2(n) rounds
        for _ in range(inserts.count().bit_length() + 2):
            up = node.select(F.col(EID).alias("anchor"), F.col("anchor").alias("next"), F.col("path").alias("above"))
            step = settled(node.join(up, "anchor", "left").select(
                EID, F.when(F.col("above").isNotNull(), F.col("next")).otherwise(F.col("anchor")).alias("anchor"), F.concat(F.coalesce("above", F.array().cast("array<bigint>")), "path").alias("path"), F.col("above").isNotNull().alias("moved")
            ), "order")
            moved = step.where("moved").limit(1).count()
            node = step.drop("moved")
            if not moved:
                break
    rooted = node.join(base, "anchor", "left")
    return rooted.select(EID, F.concat(F.coalesce("root", F.array(F.lit(LAST - 1))), "path", F.array(F.lit(LAST))).alias(ORD))


def next_kept(marked: DataFrame) -> DataFrame:
    """(__eid, __next): the next element without ``__gone``, in list order, of each element with it; null at the list's end.

    The list is dealt in ranges of its order, and a range is walked once, from its end. What follows
    a range comes from one row for each range.
    """
    # written once: ranges drawn a second time could have other bounds
    rows = settled(marked.select(EID, ORD, "__gone").repartitionByRange(ORD, EID).withColumn("__range", F.spark_partition_id()), "ranges")
    kept = F.when(F.col("__gone").isNull(), F.col(EID))
    w = W.partitionBy("__range").orderBy(F.desc(ORD), F.desc(EID)).rowsBetween(W.unboundedPreceding, -1)
    near = rows.withColumn("__near", F.last(kept, True).over(w)).where("__gone")
    first = rows.groupBy("__range").agg(F.min(F.when(F.col("__gone").isNull(), F.struct(ORD, EID)))[EID].alias("__first"))
    later = W.orderBy(F.desc("__range")).rowsBetween(W.unboundedPreceding, -1)  # as many rows as ranges
    far = first.select("__range", F.last("__first", True).over(later).alias("__far"))
    return near.join(F.broadcast(far), "__range", "left").select(EID, F.coalesce("__near", "__far").alias("__next"))


def order_without_tombstones(inserts: DataFrame, drops: DataFrame, r: Relation) -> DataFrame:
    """Baseline: a dropped anchor is forgotten, so what was in front of it moves in front of the next live element."""
    gone = drops.select(F.col("arg_eid").alias(EID)).distinct().withColumn("__gone", F.lit(True))
    follow = settled(next_kept(r.df.join(gone, EID, "left")).withColumnRenamed(EID, "anchor"), "next")
    moved = inserts.join(follow, "anchor", "left").withColumn("anchor", F.coalesce("__next", "anchor"))
    return order_keys(moved, r)


# ---- transfer across type operations ------------------------------------------------------

WRITES, NEW, GONE = ("set_cell", "set_link"), ("insert_elem", "append_elem"), ("drop_elem", "restore_elem")
#: Type operations that leave every row's place as it is.
STILL = ("noop", "rename_field", "insert_field", "append_field", "define_formula")


def slot_of(t: Type) -> str:
    """The log's value column for a type."""
    if isinstance(t, Num):
        return "val_n"
    if isinstance(t, Atom) and t.name != "string":
        return "val_t" if t.name.startswith(("timestamp", "date")) else "val_n"
    return "val_s"


def stored_as(t: Type, value: Column) -> dict[str, Column]:
    """The three value columns of a row that writes ``value``."""
    kinds = {"val_s": "string", "val_n": "double", "val_t": "timestamp_ntz"}
    return {c: value.cast(k) if c == slot_of(t) else F.lit(None).cast(k) for c, k in kinds.items()}


def _same(column: str, value: str | None) -> Column:
    """Null-safe: whether a column holds the value (or is null, for None)."""
    return F.col(column).isNull() if value is None else F.coalesce(F.col(column) == value, F.lit(False))


def _at(over: Op) -> tuple[str, str | None, str | None]:
    """(table, field, field within a record) that a type operation is about."""
    return over.path[0], over.path[2] if len(over.path) > 2 else None, over.path[3] if len(over.path) > 3 else None


def _replaced(ops: DataFrame, hit: Column, **columns) -> DataFrame:
    """The log with some columns of some rows changed."""
    return ops.withColumns({c: F.when(hit, v if isinstance(v, Column) else F.lit(v)).otherwise(F.col(c)) for c, v in columns.items()})


def _derived(rows: DataFrame, suffix: str, **columns) -> DataFrame:
    """Rows that other rows bring along."""
    return rows.withColumns({**{c: v if isinstance(v, Column) else F.lit(v) for c, v in columns.items()}, "op_id": F.concat("op_id", F.lit(suffix))})


def _field_type(db: Database, over: Op) -> Type:
    """Type of the slot that a type operation changes, before it."""
    table, fid, inner = _at(over)
    t = db[table].field(fid).type
    return t.field(inner).type if inner is not None and isinstance(t, RecordT) else t


def _atomic(db: Database, over: Op) -> None:
    """Log rows name a field and one place within it; what lies deeper has no row."""
    if isinstance(_field_type(db, over), (ListT, RecordT)):
        raise Rejected(f"{over.kind} of a list or record within {over.path[0]} has no set-oriented rule")


def _followed(ops: DataFrame, table: str, link: str, target: str, columns: list[tuple[str, Type]], links: DataFrame, rows: DataFrame) -> DataFrame:
    """What writes to linked rows and to links mean for the linking rows, where the link is replaced by its target's columns.

    links: (__row, __to) as they were before the log, rows: the target's. A write to a linked row
    becomes one to each row that links to it after the log's own relinking. A relinked row takes
    its new target's columns: the log's last writes of them, else the stored values; no link
    gives initial values. What was linked to a row that the log drops becomes initial, too.
    """
    # the log is read once for each column of the target
    ops = settled(ops, "log")
    own = _same("list_key", table) & _same("fid", link) & _same("kind", "set_link")
    there = _same("list_key", target)
    relinked = ops.where(own).groupBy(F.col("eid").alias("__row")).agg(F.max("seq").alias("__seq"), F.max_by("val_s", "seq").alias("__new"))
    final = links.join(relinked, "__row", "full").select("__row", F.coalesce("__new", "__to").alias("__to"))
    fan = ops.where(there & F.col("kind").isin(*WRITES)).join(final, F.col("eid") == F.col("__to"))
    fan = fan.withColumns({"eid": F.col("__row"), "list_key": F.lit(table), "origin_op": F.coalesce("origin_op", "op_id")}).drop("__row", "__to")
    out = ops.where(~there & ~own).unionByName(fan)
    last = last_writers(ops.where(there)).where("sub is null").select(F.col("eid").alias("__e"), F.col("fid").alias("__f"), *[F.col(v).alias(f"__{v}") for v in ("val_s", "val_n", "val_t")])
    moved = ops.where(own).withColumnRenamed("val_s", "__to")
    stored = rows.select(F.col(EID).alias("__r"), F.lit(True).alias("__there"), *[F.col(f).alias(f"__o_{f}") for f, _ in columns])
    moved = moved.join(stored, F.col("__to") == F.col("__r"), "left").where(F.col("__there") | (F.col("__to") == NULL_LINK))
    for f, t in columns:
        value = F.when(F.col("__there"), F.col(f"__o_{f}")).otherwise(initial_column(t))
        copy = _derived(moved, f"/{f}", kind="set_link" if isinstance(t, LinkT) else "set_cell", fid=f, **stored_as(t, value))
        newer = copy.join(last.where(F.col("__f") == f).drop("__f"), F.col("__to") == F.col("__e"), "left")
        newer = newer.withColumns({v: F.when(F.col("__e").isNotNull(), F.col(f"__{v}")).otherwise(F.col(v)) for v in ("val_s", "val_n", "val_t")})
        out = out.unionByName(newer.select(*ops.columns))
    lost = ops.where(there & _same("kind", "drop_elem")).join(final, F.col("arg_eid") == F.col("__to"))
    for f, t in columns:
        blank = _derived(lost, f"/{f}", kind="set_link" if isinstance(t, LinkT) else "set_cell", fid=f, eid=F.col("__row"), arg_eid=F.lit(None).cast("string"), list_key=table, **stored_as(t, initial_column(t)))
        out = out.unionByName(blank.select(*ops.columns))
    return out


def forward(ops: DataFrame, over: Op, before: Database) -> DataFrame:
    """Log rows after a type operation; rows without a counterpart are gone.

    ``before`` is the database that the type operation ran on: a join fans writes to a linked
    row out to every row that links to it, by joins on the link column.
    """
    kind = over.kind
    if kind in STILL or over.plane == "value":
        return ops
    table, fid, inner = _at(over)
    here = _same("list_key", table)
    slot = here & _same("fid", fid) & _same("sub", inner) if fid is not None else here
    field = here & _same("fid", fid) if fid is not None else here
    write = F.col("kind").isin(*WRITES)
    if kind == "wrap_list":
        _atomic(before, over)
        # a new row's list has the element that wrapping its blank would have made
        made = _derived(ops.where(here & F.col("kind").isin(*NEW) & F.col("fid").isNull()), "/one", kind="append_elem", eid=F.col("arg_eid"), fid=fid, arg_eid=ONE, anchor=F.lit(None).cast("string"))
        return _replaced(ops, slot & write, sub=ONE).unionByName(made)
    if kind == "wrap_record":
        _atomic(before, over)
        return _replaced(ops, slot & write, sub=over.ids[0])
    if kind == "unwrap_field":
        return _replaced(ops.where(~field | _same("sub", over.ids[0])), field, sub=F.lit(None).cast("string"))
    if kind == "unwrap_first":
        elem = before[table].field(fid).type.elem
        first = F.lit(over.arg or ONE)
        if over.arg is None:
            # the element that is first in its row now, as the operation itself takes it
            heads = before[table].df.select(F.col(EID).alias("__row"), F.get(fid, 0)["eid"].alias("__first"))
            ops, first = ops.join(heads, F.col("eid") == F.col("__row"), "left").drop("__row"), F.coalesce("__first", F.lit(ONE))
        raised = field & write & (F.col("sub") == first)
        blank = field & _same("kind", "drop_elem") & (F.col("arg_eid") == first)
        kept = ops.where(~field | F.coalesce(raised | blank, F.lit(False)))
        kept = kept.withColumn("__blank", F.coalesce(blank, F.lit(False))).withColumn("sub", F.when(field, F.lit(None)).otherwise(F.col("sub")))
        kept = _replaced(kept, F.col("__blank"), kind="set_cell", arg_eid=F.lit(None).cast("string"), **stored_as(elem, initial_column(elem)))
        return kept.drop("__blank", "__first")
    if kind == "drop_field":
        return ops.where(~(here & _same("fid", over.ids[0])))
    if kind in ("define_type", "define_link"):
        return ops.where(~slot) if inner is not None else ops.where(~field)
    if kind == "move_field":
        src, dst = over.path[2:], over.ref[2:]
        if len(src) != len(dst):
            _atomic(before, over)
        hit = slot if len(src) == 2 or len(dst) == 2 else field
        to = {"fid": dst[0]} if len(src) == len(dst) == 1 else {"fid": dst[0], "sub": dst[1] if len(dst) > 1 else F.lit(None).cast("string")}
        return _replaced(ops, hit, **to)
    if kind == "convert_type":
        old = _field_type(before, over)
        return _replaced(ops, slot & write, **stored_as(over.arg, converted(value_of(old), old, over.arg)))
    if kind == "split_table":
        new, link = over.ref[0], f"{fid}_link"
        to = _replaced(ops, here & F.col("fid").isin(moved_columns(before[table], over)), list_key=new)
        rows = ops.where(here & F.col("fid").isNull())
        added = rows.where(F.col("kind").isin(*NEW))
        gone = rows.where(F.col("kind").isin(*GONE))
        links = _derived(added, "/link", kind="set_link", fid=link, eid=F.col("arg_eid"), val_s=F.col("arg_eid"), anchor=F.lit(None).cast("string"))
        # as long as links are those that the split made, a row's linked row has no other
        return to.unionByName(_derived(added, "/linked", list_key=new)).unionByName(_derived(gone, "/linked", list_key=new)).unionByName(links)
    if kind == "join_link":
        r = before[table]
        target = r.field(fid).type.target[0]
        links = r.live().select(F.col(EID).alias("__row"), F.col(fid).alias("__to"))
        columns = [(f.fid, f.type) for f in before[target].fields if f.fid in before[target].stored()]
        out = _followed(ops, table, fid, target, columns, links, before[target].live())
        # rows that are linked by nothing are not seen
        return out.where(~(_same("list_key", target) & F.col("kind").isin(*NEW, *GONE)))
    if kind == "copy_table":
        return ops.unionByName(_derived(ops.where(here), "/copy", list_key=over.ref[0]))
    if kind == "union_table":
        return _replaced(ops, _same("list_key", over.ref[0]), list_key=table)
    if kind == "move_table":
        return _replaced(ops, here, list_key=over.ref[0])
    if kind == "match_column":
        found = F.regexp_extract("val_s", over.arg, 1)
        return ops.where(~(here & _same("fid", over.ref[2]))).unionByName(_derived(ops.where(slot & write), "/match", fid=over.ref[2], val_s=found))
    raise Rejected(f"{kind} has no set-oriented rule of projection")


def forward_merge(ops: DataFrame, table: str, moves: DataFrame, policy: str = "overwrite") -> DataFrame:
    """Log rows after a deduplication by moves (src, dst).

    A row about a merged element concerns what it was merged into. Under "overwrite" the last
    moved element's content overwrites its destination, so only writes to it survive; the
    destination's own writes are absorbed. "equivalence" keeps all and leaves classes to
    ``reconcile``. Links to merged elements follow.
    """
    fwd = moves.select(F.col("src").alias("__src"), F.col("dst").alias("__dst"))
    if policy == "equivalence":
        return ops
    last = moves.groupBy(F.col("dst").alias("__dst")).agg(F.max(F.struct("ord", "src")).alias("__m")).select("__dst", F.col("__m.src").alias("__src"))
    at = F.col("list_key") == table
    # dropping one member of a class drops nothing: the others still need its row
    part = fwd.select(F.col("__src").alias("__any")).unionByName(fwd.select(F.col("__dst").alias("__any"))).distinct()
    drops = ops.where(at & F.col("kind").isin(*GONE)).join(part, F.col("arg_eid") == F.col("__any"), "left_anti")
    merged = ops.where(at & ~F.col("kind").isin(*GONE)).join(last, F.col("eid") == F.col("__src"), "left")
    dst = last.select(F.col("__dst").alias("__own"))
    merged = merged.join(fwd.select(F.col("__src").alias("__any")), F.col("eid") == F.col("__any"), "left").join(dst, F.col("eid") == F.col("__own"), "left")
    merged = merged.where(F.col("__src").isNotNull() | (F.col("__any").isNull() & F.col("__own").isNull()))
    merged = merged.withColumn("eid", F.coalesce("__dst", "eid")).drop("__src", "__dst", "__any", "__own")
    links = ops.where(~at).join(fwd, (F.col("kind") == "set_link") & (F.col("val_s") == F.col("__src")), "left")
    return merged.unionByName(links.withColumn("val_s", F.coalesce("__dst", "val_s")).drop("__src", "__dst")).unionByName(drops)


def backward(ops: DataFrame, over: Op, after: Database) -> tuple[DataFrame, DataFrame]:
    """(rows before a type operation, blocked rows with blocker_kind).

    Blocked is what needs a slot or an element that the type operation made. ``after`` is the
    database after it; for a join, whose result has no link column, the one before it.
    """
    kind = over.kind
    table, fid, inner = _at(over) if over.path else (None, None, None)
    here = _same("list_key", table)
    slot = here & _same("fid", fid) & _same("sub", inner) if fid is not None else here
    field = here & _same("fid", fid) if fid is not None else here
    write = F.col("kind").isin(*WRITES)
    none = F.lit(None).cast("string")

    def without(rows: DataFrame, bad: Column) -> tuple[DataFrame, DataFrame]:
        bad = F.coalesce(bad, F.lit(False))
        return rows.where(~bad), rows.where(bad).withColumn("blocker_kind", F.lit(kind))

    if kind in ("insert_field", "append_field"):
        return without(ops, here & _same("fid", over.ids[0]))
    if kind in STILL or kind == "drop_field" or over.plane == "value":
        return without(ops, F.lit(False))
    if kind in ("define_type", "define_link"):
        return without(ops, slot if inner is not None else field)
    if kind == "wrap_list":
        one = F.col("kind").isin(*NEW) & _same("arg_eid", ONE)
        ok, blocked = without(ops.where(~(field & one)), field & ~(write & _same("sub", ONE)))
        return _replaced(ok, field, sub=none), blocked
    if kind == "wrap_record":
        ok, blocked = without(ops, field & ~(write & _same("sub", over.ids[0])))
        return _replaced(ok, field, sub=none), blocked
    if kind == "unwrap_field":
        return without(_replaced(ops, field, sub=over.ids[0]), F.lit(False))
    if kind == "unwrap_first":
        return without(_replaced(ops, field & write, sub=over.arg or ONE), F.lit(False))
    if kind == "move_field":
        src, dst = over.path[2:], over.ref[2:]
        hit = here & _same("fid", dst[0])
        if len(src) == 2 or len(dst) == 2:
            hit = hit & _same("sub", dst[1] if len(dst) > 1 else None)
        to = {"fid": src[0]} if len(src) == len(dst) == 1 else {"fid": src[0], "sub": src[1] if len(src) > 1 else none}
        return without(_replaced(ops, hit, **to), F.lit(False))
    if kind == "convert_type":
        old = over.was if over.was is not None else (Str() if isinstance(over.arg, Num) else Num())
        back = converted(value_of(over.arg), over.arg, old)
        empty = {"val_s": F.coalesce(F.col("val_s") == "", F.lit(True)), "val_n": F.coalesce(F.isnan("val_n"), F.lit(True)), "val_t": F.col("val_t").isNull()}[slot_of(over.arg)]
        lost = F.isnan(back) if isinstance(old, Num) else back == "" if slot_of(old) == "val_s" else back.isNull()
        ok, blocked = without(ops, slot & write & ~empty & lost)
        return _replaced(ok, slot & write, **stored_as(old, back)), blocked
    if kind == "split_table":
        new, link = over.ref[0], f"{fid}_link"
        there = _same("list_key", new)
        rows = F.col("fid").isNull()
        # rows of the new table that come and go with the row they were split from say nothing by themselves
        twins = ops.where(here & rows & F.col("kind").isin(*NEW, *GONE)).select(F.col("arg_eid").alias("__e"), F.col("kind").alias("__k")).distinct()
        inside = ops.where(there & rows & F.col("kind").isin(*NEW, *GONE)).join(twins, (F.col("arg_eid") == F.col("__e")) & (F.col("kind") == F.col("__k")), "left_anti").select(*ops.columns)
        made = inside.where(F.col("kind").isin(*NEW)).select(F.col("arg_eid").alias("__made")).distinct()
        rest = ops.where(~(there & rows & F.col("kind").isin(*NEW, *GONE)))
        about = rest.where(there).join(made, F.col("eid") == F.col("__made"), "left_semi")
        blocked = inside.unionByName(about).withColumn("blocker_kind", F.lit(kind))
        rest = rest.where(~there).unionByName(rest.where(there).join(made, F.col("eid") == F.col("__made"), "left_anti"))
        # a new row's link to its own twin is the split's own
        self_link = here & _same("fid", link) & _same("kind", "set_link") & F.coalesce(F.col("val_s") == F.col("eid"), F.lit(False))
        fresh = twins.where(F.col("__k").isin(*NEW)).select("__e")
        rest = rest.where(~self_link).unionByName(rest.where(self_link).join(fresh, F.col("eid") == F.col("__e"), "left_anti"))
        own = twins.where(F.col("__k").isin(*NEW)).select(F.col("__e").alias("__row"), F.col("__e").alias("__to"))
        links = after[table].live().select(F.col(EID).alias("__row"), F.col(link).alias("__to")).unionByName(own).groupBy("__row").agg(F.max("__to").alias("__to"))
        target = after[new]
        columns = [(f.fid, f.type) for f in target.fields if f.fid in target.stored()]
        return _followed(rest, table, link, new, columns, links, target.live()), blocked
    if kind == "join_link":
        # writes to joined columns go back to the row that the link names: an updatable view
        r = after[table]
        link = r.field(fid).type.target[0]
        theirs = here & F.col("fid").isin([f.fid for f in after[link].fields])
        at = r.live().select(F.col(EID).alias("__row"), F.col(fid).alias("__to"))
        known = after[link].live().select(F.col(EID).alias("__there"))
        joined = ops.where(theirs).join(at, F.col("eid") == F.col("__row"), "left").join(known, F.col("__to") == F.col("__there"), "left")
        # a row without a linked row has no place for them
        bad = joined.where("__there is null").drop("__row", "__to", "__there").withColumn("blocker_kind", F.lit(kind))
        moved = joined.where("__there is not null").withColumns({"eid": F.col("__to"), "list_key": F.lit(link)}).drop("__row", "__to", "__there")
        return ops.where(~F.coalesce(theirs, F.lit(False))).unionByName(moved), bad
    if kind == "move_table":
        return without(_replaced(ops, _same("list_key", over.ref[0]), list_key=table), F.lit(False))
    if kind == "copy_table":
        return without(ops, _same("list_key", over.ref[0]))
    if kind == "match_column":
        return without(ops, here & _same("fid", over.ref[2]))
    raise Rejected(f"{kind} has no set-oriented rule of retraction")


def transfer_values(left: DataFrame, right: DataFrame) -> DataFrame:
    """Final writes of each cell on the right after the left's were transferred: the transferred side wins.

    One aggregation over both logs; no operation is moved one by one.
    """
    both = left.withColumn("seq", F.struct(F.lit(1).alias("side"), "seq")).unionByName(right.withColumn("seq", F.struct(F.lit(0).alias("side"), "seq")))
    best = both.where("kind in ('set_cell', 'set_link')").groupBy(*CELL).agg(F.max_by(F.struct("op_id", "val_s", "val_n", "val_t"), "seq").alias("w"))
    return best.select(*CELL, "w.*")


def conflicts(left: DataFrame, right: DataFrame) -> DataFrame:
    """Cells written on both sides whose last values differ."""
    a = last_writers(left).select(*CELL, F.col("val_s").alias("ls"), F.col("val_n").alias("ln"))
    b = last_writers(right).select(*CELL, F.col("val_s").alias("rs"), F.col("val_n").alias("rn"))
    on = [a[c].eqNullSafe(b[c]) for c in CELL]
    both = a.join(b, on).where(~(F.col("ls").eqNullSafe(F.col("rs")) & F.col("ln").eqNullSafe(F.col("rn"))))
    return both.select(*[a[c] for c in CELL], "ls", "ln", "rs", "rn")


def optimised_cells(shared: DataFrame, left: DataFrame, right: DataFrame) -> DataFrame:
    """Per cell, what each branch still holds in the minimal diff: keep_left, keep_right and the current values.

    Closed form of the loop that moves every operation whose transfer changes nothing: equal
    current values share all; if the right's value is among the left's writes the right's
    operations go, and the other way round; else both keep their last write. Values written are
    met by a semi-join on (cell, value), so no set is collected.
    """
    key = [F.coalesce(F.col(c), F.lit("")).alias(c) for c in CELL]

    def last(ops: DataFrame, name: str) -> DataFrame:
        return ops.groupBy(*key).agg(F.max_by(F.struct("val_s", "val_n"), "seq").alias(name))

    def wrote(ops: DataFrame, name: str) -> DataFrame:
        return ops.select(*key, F.struct("val_s", "val_n").alias("w")).distinct().withColumn(name, F.lit(True))

    cells = last(left, "l").join(last(right, "r"), CELL, "full").join(last(shared, "s"), CELL, "left")
    cells = cells.select(*CELL, F.coalesce("l", "s").alias("la"), F.coalesce("r", "s").alias("ra"), F.col("l").isNotNull().alias("wl"), F.col("r").isNotNull().alias("wr"))
    cells = cells.join(wrote(left, "in_left").withColumnRenamed("w", "ra"), [*CELL, "ra"], "left").join(wrote(right, "in_right").withColumnRenamed("w", "la"), [*CELL, "la"], "left")
    same = F.col("la").eqNullSafe(F.col("ra"))
    a, b = F.coalesce("in_left", F.lit(False)), F.coalesce("in_right", F.lit(False))
    return cells.select(
        *CELL,
        "la",
        "ra",
        (~same & F.col("wl") & (a | ~b)).alias("keep_left"),
        (~same & F.col("wr") & ~a).alias("keep_right"),
    )


def undo(ops: DataFrame, chosen: Column) -> DataFrame:
    """The delta that takes back the chosen writes: one row for each cell whose last write is among them.

    A cell goes back to the last write that is kept, or to blank (null) if there is none.
    """
    picked = ops.withColumn("__undo", chosen)
    cell = picked.groupBy(*CELL).agg(
        F.max_by(F.struct("op_id", "__undo"), "seq").alias("top"), F.max_by(F.struct("val_s", "val_n", "val_t"), F.when(~F.col("__undo"), F.col("seq"))).alias("w")
    )
    return cell.where("top.__undo").select(*CELL, F.col("top.op_id").alias("undo_of"), "w.val_s", "w.val_n", "w.val_t")


def _melted(db: Database) -> DataFrame | None:
    """(list_key, eid, fid, val_s, val_n, val_t) of every plain cell of a database: one projection a table."""
    out = None
    for name, r in db.tables.items():
        plain = [f for f in r.fields if f.fid in r.stored() and not isinstance(f.type, (ListT, RecordT))]
        if plain:
            cells = F.explode(F.array(*[F.struct(F.lit(f.fid).alias("fid"), *[v.alias(c) for c, v in stored_as(f.type, F.col(f.fid)).items()]) for f in plain])).alias("x")
            rows = r.df.select(F.lit(name).alias("list_key"), F.col(EID).alias("eid"), cells).select("list_key", "eid", "x.*")
            out = rows if out is None else out.unionByName(rows)
    return out


def _blank(db: Database) -> dict[str, Column]:
    """Initial values, by list and field, as a log row's value columns."""
    out = {c: F.lit(None).cast(k) for c, k in (("val_s", "string"), ("val_n", "double"), ("val_t", "timestamp_ntz"))}
    for name, r in db.tables.items():
        for f in r.fields:
            if isinstance(f.type, (Str, LinkT, Num)):
                c = slot_of(f.type)
                out[c] = F.when(_same("list_key", name) & _same("fid", f.fid), stored_as(f.type, initial_column(f.type))[c]).otherwise(out[c])
    return out


def undo_delta(ops: DataFrame, chosen: Column, start: Database) -> DataFrame:
    """Rows to append that take the chosen value operations back: writes, insertions, drops and restores, and earlier undos.

    A cell whose last write is chosen goes back to its last kept write, else to the value that
    ``start`` (the state before the log) has. An inserted element is dropped: what was written
    in it grounds out. A drop or restore that decides an element's life is reversed to the last kept one.
    Every row names what it takes back in ``undo_of`` and is itself an operation that can be taken back.
    """
    top = ops.agg(F.max("seq")).first()[0] or 0
    picked = ops.where(F.coalesce(F.col("plane") == "value", F.lit(True))).withColumn("__undo", F.coalesce(chosen, F.lit(False)))
    value = F.struct("val_s", "val_n", "val_t")
    cells = picked.where(F.col("kind").isin(*WRITES)).groupBy(*CELL).agg(
        F.max_by(F.struct("op_id", "kind", "__undo"), "seq").alias("top"), F.max_by(value, F.when(~F.col("__undo"), F.col("seq"))).alias("w"), F.max(F.when(~F.col("__undo"), F.col("seq"))).alias("kept")
    )
    cells = cells.where("top.__undo").select(*CELL, F.col("top.op_id").alias("undo_of"), F.col("top.kind").alias("kind"), "kept", "w.val_s", "w.val_n", "w.val_t")
    old = _melted(start)
    none = cells.where("kept is null")
    if old is not None:
        first = old.select(*[F.col(c).alias(f"__{c}") for c in old.columns])
        none = none.join(first, (F.col("list_key") == F.col("__list_key")) & (F.col("eid") == F.col("__eid")) & (F.col("fid") == F.col("__fid")) & F.col("sub").isNull(), "left")
        found, blank = F.col("__eid").isNotNull(), _blank(start)
        none = none.withColumns({c: F.when(found, F.col(f"__{c}")).otherwise(blank[c]) for c in ("val_s", "val_n", "val_t")})
    columns = ["kind", *CELL, "undo_of", "val_s", "val_n", "val_t"]
    out = cells.where("kept is not null").select(*columns).unionByName(none.select(*columns)).withColumns({"arg_eid": F.lit(None).cast("string")})
    life = ["list_key", "eid", "fid", "arg_eid"]
    elements = picked.where(F.col("kind").isin(*NEW, *GONE)).groupBy(*life).agg(
        F.max_by(F.struct("op_id", "kind", "__undo"), "seq").alias("top"),
        F.max_by("kind", F.when(~F.col("__undo"), F.col("seq"))).alias("kept"),
        F.max(F.when(F.col("kind").isin(*NEW), F.col("__undo"))).alias("made_undone"),
        F.max_by("op_id", F.when(F.col("kind").isin(*NEW), F.col("seq"))).alias("maker"),
    )
    # an element without a kept operation is as it was before the log: not there if the log made it, else alive
    should = F.when(F.col("made_undone"), "drop_elem").when(F.col("kept") == "drop_elem", "drop_elem").otherwise("restore_elem")
    is_ = F.when(F.col("top.kind") == "drop_elem", "drop_elem").otherwise("restore_elem")
    turned = elements.withColumn("kind", should).where((F.col("kind") != is_) & (F.col("top.__undo") | F.col("made_undone")))
    turned = turned.select("kind", "list_key", "eid", "fid", F.when(F.col("made_undone"), F.col("maker")).otherwise(F.col("top.op_id")).alias("undo_of"), "arg_eid")
    out = out.unionByName(turned, allowMissingColumns=True)
    out = out.withColumns({"seq": F.lit(top + 1).cast("bigint"), "op_id": F.concat(F.lit(f"undo:{top + 1}:"), "undo_of"), "plane": F.lit("value")})
    return out.select(*[F.col(c).cast(t).alias(c) if c in out.columns else F.lit(None).cast(t).alias(c) for c, t in SCHEMA.items()])


def cancel_undone(ops: DataFrame) -> DataFrame:
    """Without operations and the undos that took them back; an undo that was itself undone leaves its target in place.

    Rounds are as many as undos of undos are deep.
    """
    while True:
        undos = ops.where("undo_of is not null").select("op_id", "undo_of")
        last = undos.join(undos.select(F.col("undo_of").alias("op_id")), "op_id", "left_anti")
        last = settled(last, "undos")
        if not last.limit(1).count():
            return ops
        gone = last.select("op_id").unionByName(last.select(F.col("undo_of").alias("op_id"))).distinct()
        ops = settled(ops.join(gone, "op_id", "left_anti").select(*ops.columns), "log")


def undo_overridden(ops: DataFrame, chosen: Column) -> DataFrame:
    """Chosen writes whose undoing has no effect because a kept later write overrides them."""
    picked = ops.withColumn("__undo", chosen)
    last = picked.where(~F.col("__undo")).groupBy(*CELL).agg(F.max("seq").alias("kept"))
    mine = picked.where("__undo")
    on = [mine[c].eqNullSafe(last[c]) for c in CELL]
    return mine.join(last, [*on, F.col("kept") > F.col("seq")], "left_semi").select(*ops.columns)


def common_prefix(a: DataFrame, b: DataFrame) -> int:
    """Operations that two histories share from the start, found by a join on operation IDs."""
    both = a.select("op_id", "seq").join(b.select("op_id", F.col("seq").alias("other")), "op_id", "full")
    first = both.where(~F.col("seq").eqNullSafe(F.col("other"))).agg(F.min(F.least(F.coalesce("seq", "other"), F.coalesce("other", "seq")))).first()[0]
    return a.count() if first is None else a.where(F.col("seq") < first).count()


def simplify(ops: DataFrame) -> DataFrame:
    """Without operations that were undone, overwritten writes, and elements that are inserted and dropped again."""
    ops = cancel_undone(ops)
    brief = ops.where("kind in ('insert_elem', 'append_elem')").select("list_key", F.col("arg_eid").alias("__e"))
    brief = brief.join(ops.where("kind = 'drop_elem'").select("list_key", F.col("arg_eid").alias("__e")), ["list_key", "__e"], "left_semi")
    anchors = ops.select("list_key", F.col("anchor").alias("__e")).where("__e is not null")
    brief = brief.join(anchors, ["list_key", "__e"], "left_anti").distinct()
    about = F.coalesce("arg_eid", "eid")
    rest = ops.withColumn("__e", about).join(brief, ["list_key", "__e"], "left_anti").drop("__e")
    writes = F.col("kind").isin("set_cell", "set_link")
    last = rest.where(writes).groupBy(*CELL).agg(F.max("seq").alias("seq")).select("seq")
    return rest.where(~writes).unionByName(rest.where(writes).join(last, "seq", "left_semi").select(*rest.columns))


def dependencies(ops: DataFrame) -> DataFrame:
    """(op_id, dep_id): an operation needs the earlier one that made an element it mentions.

    IDs of elements of nested lists hold within their row, so they are met together with it.
    """

    def scoped(e: Column) -> Column:
        return F.concat_ws("/", "list_key", F.when(F.col("fid").isNotNull(), F.col("eid")), e)

    def top(e: Column) -> Column:
        return F.concat_ws("/", "list_key", e)

    made = F.col("kind").isin("insert_elem", "append_elem")
    makers = ops.where(made).select(scoped(F.col("arg_eid")).alias("id"), F.col("op_id").alias("dep_id"), F.col("seq").alias("made"))
    mentioned = F.array_compact(
        F.array(
            F.when(F.col("eid").isNotNull(), top(F.col("eid"))),
            F.when(F.col("sub").isNotNull(), scoped(F.col("sub"))),
            F.when(F.col("anchor").isNotNull(), scoped(F.col("anchor"))),
            F.when(F.col("kind") == "drop_elem", scoped(F.col("arg_eid"))),
        )
    )
    uses = ops.select("op_id", "seq", F.explode(mentioned).alias("id"))
    return uses.join(makers, "id").where("made < seq").select("op_id", "dep_id").distinct()


def closure(ops: DataFrame, chosen: DataFrame) -> DataFrame:
    """Operation IDs of the chosen operations and of all that they need, by frontier joins."""
    edges = settled(dependencies(ops), "edges")
    seen = settled(chosen.select("op_id").distinct(), "seen")
    frontier = seen
    while True:
        frontier = settled(frontier.join(edges, "op_id").select(F.col("dep_id").alias("op_id")).distinct().join(seen, "op_id", "left_anti"), "frontier")
        if not frontier.limit(1).count():
            return seen
        seen = seen.unionByName(frontier)


def fingerprint(df: DataFrame) -> DataFrame:
    """One row (cells, hash) that is equal for equal rows in any order."""
    cols = [F.coalesce(F.col(c).cast("string"), F.lit("\0")) for c in sorted(df.columns)]
    return df.agg(F.count(F.lit(1)).alias("cells"), F.sum(F.xxhash64(*cols).cast("decimal(38,0)")).alias("hash"))
