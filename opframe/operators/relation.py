"""Databases of relations and the operations that change them, as lazy DataFrame plans.

A relation is a DataFrame with system columns ``__eid`` (element ID), ``__ord`` (order key: an
array compared element by element) and ``__dead`` (tombstone), and one column per field, named
by field ID. Labels live beside the plan, so renaming costs nothing. A ``Database`` is an
immutable handle: applying an operation gives a new one and runs no job.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field, replace

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..model.ops import Op
from ..model.types import ANY, NULL_LINK, ONE, Field, LinkT, ListT, Num, RecordT, Str, Type, Unit, from_spark, initial_column, is_initial, spark_type

EID, ORD, DEAD = "__eid", "__ord", "__dead"
SYSTEM = (EID, ORD, DEAD)
#: Ends every order key, so that what was inserted in front of an element sorts before it.
LAST = (1 << 63) - 1


class Rejected(ValueError):
    """A precondition of an operation does not hold."""


@dataclass(frozen=True)
class Relation:
    """Rows of one list and the fields of its element type."""

    df: DataFrame
    fields: tuple[Field, ...]

    def field(self, fid: str) -> Field:
        for f in self.fields:
            if f.fid == fid:
                return f
        raise Rejected(f"no field {fid}")

    def stored(self) -> list[str]:
        return [f.fid for f in self.fields if not isinstance(f.type, Unit)]

    def select(self) -> DataFrame:
        return self.df.select(*SYSTEM, *self.stored())

    def live(self) -> DataFrame:
        """Rows without tombstones."""
        return self.df.where(~F.col(DEAD))

    def header_row(self) -> list[Column]:
        """Initial values of the fields, as a new element has them."""
        return [initial_column(f.type).alias(f.fid) for f in self.fields if not isinstance(f.type, Unit)]


def from_table(df: DataFrame, key: Column, prefix: str, fields: dict[str, Type] | None = None, order: Column | None = None) -> Relation:
    """Import a DataFrame: element IDs are the prefix and the business key, order is the key's (or ``order``'s)."""
    kinds = fields or {f.name: from_spark(f.dataType) for f in df.schema.fields}
    out = df.select(
        F.concat(F.lit(prefix), key.cast("string")).alias(EID),
        F.array((key if order is None else order).cast("long"), F.lit(LAST)).alias(ORD),
        F.lit(False).alias(DEAD),
        *[F.coalesce(F.col(f), initial_column(t)).alias(f) if isinstance(t, (Str, LinkT)) else F.col(f) for f, t in kinds.items()],
    )
    return Relation(out, tuple(Field(f, f, t) for f, t in kinds.items()))


@dataclass(frozen=True)
class Database:
    """Named relations and formulas."""

    tables: dict[str, Relation] = field(default_factory=dict)
    formulas: dict[str, object] = field(default_factory=dict)

    def __getitem__(self, name: str) -> Relation:
        if name not in self.tables:
            raise Rejected(f"no table {name}")
        return self.tables[name]

    def put(self, **tables: Relation) -> Database:
        return replace(self, tables={**self.tables, **tables})

    def without(self, name: str) -> Database:
        return replace(self, tables={k: v for k, v in self.tables.items() if k != name})

    def apply(self, op: Op, mode: str = "developer") -> Database:
        """The database after an operation; in user mode only value operations are allowed."""
        if mode == "user" and op.plane == "type":
            raise Rejected(f"{op.kind} changes the type; that needs developer mode")
        if op.kind == "noop":
            return self
        if op.kind not in _APPLY:
            raise Rejected(f"unknown operation {op.kind}")
        out = _APPLY[op.kind](self, op)
        if self.formulas and op.plane == "type" and op.kind != "define_formula":
            from ..plans.formula import carried

            out = replace(out, formulas={k: carried(f, op) for k, f in self.formulas.items()})
        return out

    def run(self, ops: list[Op]) -> Database:
        """The database after a timeline."""
        out = self
        for op in ops:
            out = out.apply(op)
        return out

    def export(self, name: str, *columns: Column | str) -> DataFrame:
        """Live rows of a table; all fields unless columns are named."""
        r = self[name]
        return r.live().select(*(columns or [EID, *r.stored()]))


_APPLY: dict[str, Callable[[Database, Op], Database]] = {}


def _on(*kinds: str):
    def add(f):
        for k in kinds:
            _APPLY[k] = f
        return f

    return add


def _column(op: Op) -> tuple[str, str, tuple[str, ...]]:
    """(table, field, rest) of a column path (table, mark, field, ...)."""
    if len(op.path) < 3:
        raise Rejected(f"{op.kind} needs the path of a column")
    return op.path[0], op.path[2], op.path[3:]


def _retyped(r: Relation, fid: str, t: Type) -> tuple[Field, ...]:
    r.field(fid)
    return tuple(replace(f, type=t) if f.fid == fid else f for f in r.fields)


def _set(db: Database, table: str, r: Relation, fid: str, value: Column, t: Type) -> Database:
    return db.put(**{table: Relation(r.df.withColumn(fid, value), _retyped(r, fid, t))})


@_on("define_type", "define_link")
def _define(db: Database, op: Op) -> Database:
    if len(op.path) == 1:
        raise Rejected("tables are added by import")
    table, fid, _ = _column(op)
    t = LinkT(op.ref) if op.kind == "define_link" else op.arg
    return _set(db, table, db[table], fid, initial_column(t), t)


def converted(c: Column, old: Type, new: Type) -> Column:
    """An atomic under another atomic type; what does not convert becomes the initial value. Whole numbers are written without a point."""
    if isinstance(old, Num) and spark_type(new).simpleString() == "string":
        whole = (c == F.floor(c)) & (F.abs(c) < 1e15)
        c = F.when(whole, c.cast("bigint").cast("string")).when(~F.isnan(c), c.cast("string"))
    return F.coalesce(c.try_cast(spark_type(new)), initial_column(new))


@_on("convert_type")
def _convert(db: Database, op: Op) -> Database:
    table, fid, _ = _column(op)
    r, t = db[table], op.arg
    return _set(db, table, r, fid, converted(F.col(fid), r.field(fid).type, t), t)


@_on("rename_field")
def _rename(db: Database, op: Op) -> Database:
    table, fid, _ = _column(op)
    r = db[table]
    r.field(fid)
    return db.put(**{table: replace(r, fields=tuple(replace(f, name=op.arg) if f.fid == fid else f for f in r.fields))})


@_on("insert_field", "append_field")
def _add_field(db: Database, op: Op) -> Database:
    table, r = op.path[0], db[op.path[0]]
    if any(f.fid == op.ids[0] for f in r.fields):
        raise Rejected(f"field {op.ids[0]} exists")
    at = len(r.fields) if op.kind == "append_field" else [f.fid for f in r.fields].index(op.ids[1])
    new = Field(op.ids[0], op.ids[0], Unit())
    return db.put(**{table: replace(r, fields=(*r.fields[:at], new, *r.fields[at:]))})


@_on("drop_field")
def _drop_field(db: Database, op: Op) -> Database:
    table, r = op.path[0], db[op.path[0]]
    r.field(op.ids[0])
    return db.put(**{table: Relation(r.df.drop(op.ids[0]), tuple(f for f in r.fields if f.fid != op.ids[0]))})


@_on("move_field")
def _move_field(db: Database, op: Op) -> Database:
    table, r = op.path[0], db[op.path[0]]
    src, dst = op.path[2:], op.ref[2:]
    if len(src) == 1 and len(dst) == 2:
        inner, outer = r.field(src[0]), r.field(dst[0])
        df = r.df.withColumn(dst[0], F.col(dst[0]).withField(dst[1], F.col(src[0]))).drop(src[0])
        kind = RecordT((*outer.type.fields, Field(dst[1], inner.name, inner.type)))
        kept = tuple(f for f in _retyped(r, dst[0], kind) if f.fid != src[0])
        return db.put(**{table: Relation(df, kept)})
    if len(src) == 2 and len(dst) == 1:
        outer = r.field(src[0])
        inner = outer.type.field(src[1])
        left = tuple(f for f in outer.type.fields if f.fid != src[1])
        df = r.df.withColumn(dst[0], F.col(src[0])[src[1]])
        df = df.withColumn(src[0], F.col(src[0]).dropFields(src[1])) if left else df.withColumn(src[0], F.lit(None).cast("string"))
        kind = RecordT(left) if left else Unit()
        return db.put(**{table: Relation(df, (*_retyped(r, src[0], kind), Field(dst[0], inner.name, inner.type)))})
    if len(src) == len(dst) == 1:
        f = r.field(src[0])
        return db.put(**{table: Relation(r.df.withColumnRenamed(src[0], dst[0]), (*(x for x in r.fields if x.fid != src[0]), Field(dst[0], f.name, f.type)))})
    raise Rejected("a field moves within its record, into a record beside it or out of one")


@_on("wrap_list")
def _wrap_list(db: Database, op: Op) -> Database:
    table, fid, _ = _column(op)
    r = db[table]
    return _set(db, table, r, fid, F.array(F.struct(F.lit(ONE).alias("eid"), F.col(fid).alias("val"))), ListT(r.field(fid).type))


@_on("unwrap_first")
def _unwrap_first(db: Database, op: Op) -> Database:
    table, fid, _ = _column(op)
    r = db[table]
    t = r.field(fid).type
    if not isinstance(t, ListT):
        raise Rejected(f"{fid} is not a list")
    items = F.col(fid) if op.arg is None else F.filter(fid, lambda x: x["eid"] == op.arg)
    return _set(db, table, r, fid, F.coalesce(F.get(items, 0)["val"], initial_column(t.elem)), t.elem)


@_on("wrap_record")
def _wrap_record(db: Database, op: Op) -> Database:
    table, fid, _ = _column(op)
    r, inner = db[table], op.ids[0]
    return _set(db, table, r, fid, F.struct(F.col(fid).alias(inner)), RecordT((Field(inner, inner, r.field(fid).type),)))


@_on("unwrap_field")
def _unwrap_field(db: Database, op: Op) -> Database:
    table, fid, _ = _column(op)
    r = db[table]
    return _set(db, table, r, fid, F.col(fid)[op.ids[0]], r.field(fid).type.field(op.ids[0]).type)


def moved_columns(r: Relation, op: Op) -> list[str]:
    """Fields that a split moves: the pinned ones, else from the target column to the record's end."""
    names = [f.fid for f in r.fields]
    return list(op.ids) or names[names.index(op.path[2]) :]


@_on("split_table")
def _split(db: Database, op: Op) -> Database:
    table, col, _ = _column(op)
    r, new = db[table], op.ref[0]
    moved = moved_columns(r, op)
    if len(moved) == len(r.fields):
        raise Rejected("split would leave no column")
    if new in db.tables:
        raise Rejected(f"table {new} exists")
    link = f"{col}_link"
    kept = [f for f in r.fields if f.fid not in moved]
    at = min(i for i, f in enumerate(r.fields) if f.fid in moved)
    kept.insert(at, Field(link, r.field(col).name, LinkT(op.ref)))
    # the same element IDs on both sides, so that the two are projections of one source
    base = Relation(r.df.drop(*moved).withColumn(link, F.col(EID)), tuple(kept))
    return db.put(**{table: base, new: Relation(r.df.select(*SYSTEM, *moved), tuple(f for f in r.fields if f.fid in moved))})


@_on("join_link")
def _join(db: Database, op: Op) -> Database:
    table, link, _ = _column(op)
    r = db[table]
    t = r.field(link).type
    if not isinstance(t, LinkT):
        raise Rejected(f"{link} is not a link")
    linked = db[t.target[0]]
    clash = {f.fid for f in linked.fields} & {f.fid for f in r.fields}
    if clash:
        raise Rejected(f"fields {sorted(clash)} are on both sides")
    side = linked.live().select(F.col(EID).alias("__l"), *linked.stored())
    df = r.df.join(side, r.df[link] == F.col("__l"), "left").drop("__l")
    out: list[Field] = []
    for f in r.fields:
        out += list(linked.fields) if f.fid == link else [f]
    for f in linked.fields:
        # an unlinked row gets initial values; atomics whose blank is NULL have them already
        if isinstance(f.type, (Str, LinkT)):
            df = df.withColumn(f.fid, F.coalesce(f.fid, initial_column(f.type)))
    return db.without(t.target[0]).put(**{table: Relation(df.drop(link), tuple(out))})


@_on("drop_present", "drop_absent")
def _drop_blank(db: Database, op: Op) -> Database:
    table, fid, _ = _column(op)
    r = db[table]
    blank = is_initial(F.col(fid), r.field(fid).type)
    return db.put(**{table: replace(r, df=r.df.where(blank if op.kind == "drop_present" else ~blank))})


@_on("drop_where")
def _drop_where(db: Database, op: Op) -> Database:
    r = db[op.path[0]]
    return db.put(**{op.path[0]: replace(r, df=r.df.where(~F.coalesce(F.expr(op.arg), F.lit(False))))})


@_on("set_cell", "set_link")
def _set_cell(db: Database, op: Op) -> Database:
    table, eid, fid = op.path[:3]
    r = db[table]
    t = r.field(fid).type
    if len(op.path) == 4 and isinstance(t, ListT):
        cell = F.transform(fid, lambda x: F.when(x["eid"] == op.path[3], x.withField("val", F.lit(op.arg))).otherwise(x))
    else:
        if isinstance(t, (Str, LinkT)) and not isinstance(op.arg, str):
            raise Rejected(f"{op.arg!r} is no value of {fid}")
        cell = F.lit(op.arg).cast(spark_type(t))
    hit = F.lit(True) if eid == ANY else F.col(EID) == eid
    return db.put(**{table: replace(r, df=r.df.withColumn(fid, F.when(hit, cell).otherwise(F.col(fid))))})


@_on("drop_elem", "restore_elem")
def _drop_elem(db: Database, op: Op) -> Database:
    r = db[op.path[0]]
    dead = F.when(F.col(EID) == op.ids[0], F.lit(op.kind == "drop_elem")).otherwise(F.col(DEAD))
    return db.put(**{op.path[0]: replace(r, df=r.df.withColumn(DEAD, dead))})


@_on("extract_list")
def _extract(db: Database, op: Op) -> Database:
    table, fid, _ = _column(op)
    r, new = db[table], op.ref[0]
    elem = r.field(fid).type.elem
    each = r.df.select(EID, DEAD, ORD, F.posexplode(fid).alias("__pos", "__x"))
    own = F.concat_ws("/", EID, "__x.eid")
    order = F.concat(F.slice(ORD, 1, F.size(ORD) - 1), F.array(F.col("__pos").cast("long"), F.lit(LAST)))
    names = [(f.fid, f.type) for f in elem.fields] if isinstance(elem, RecordT) else [("val", elem)]
    values = [F.col(f"__x.val.{n}").alias(n) if isinstance(elem, RecordT) else F.col("__x.val").alias(n) for n, _ in names]
    part = each.select(own.alias(EID), order.alias(ORD), DEAD, F.col(EID).alias("parent"), *values)
    links = F.transform(fid, lambda x: F.concat_ws("/", F.col(EID), x["eid"]))
    child = Relation(part, (Field("parent", "parent", LinkT((table,))), *(Field(n, n, t) for n, t in names)))
    return _set(db, table, r, fid, links, from_spark(links_type())).put(**{new: child})


def links_type():
    """Spark type of a set of links."""
    from pyspark.sql import types as T

    return T.ArrayType(T.StringType())


@_on("push_column")
def _push(db: Database, op: Op) -> Database:
    table, fid, _ = _column(op)
    child, link = op.ref[0], op.ref[2]
    r, c = db[table], db[child]
    side = r.live().select(F.col(EID).alias("__p"), F.col(fid))
    df = c.df.join(side, c.df[link] == F.col("__p"), "left").drop("__p")
    return db.put(**{child: Relation(df, (*c.fields, r.field(fid)))})


@_on("match_column")
def _match(db: Database, op: Op) -> Database:
    table, fid, _ = _column(op)
    r, dst = db[table], op.ref[2]
    df = r.df.withColumn(dst, F.regexp_extract(fid, op.arg, 1))
    known = any(f.fid == dst for f in r.fields)
    return db.put(**{table: Relation(df, _retyped(r, dst, Str()) if known else (*r.fields, Field(dst, dst, Str())))})


@_on("define_computed")
def _computed(db: Database, op: Op) -> Database:
    table, fid, _ = _column(op)
    r = db[table]
    df = r.df.withColumn(fid, F.expr(op.arg))
    t = from_spark(df.schema[fid].dataType)
    known = any(f.fid == fid for f in r.fields)
    return db.put(**{table: Relation(df, _retyped(r, fid, t) if known else (*r.fields, Field(fid, fid, t)))})


@_on("copy_table")
def _copy(db: Database, op: Op) -> Database:
    return db.put(**{op.ref[0]: db[op.path[0]]})


@_on("union_table")
def _union(db: Database, op: Op) -> Database:
    a, b = db[op.path[0]], db[op.ref[0]]
    fields = (*a.fields, *(f for f in b.fields if f.fid not in {x.fid for x in a.fields}))
    return db.without(op.ref[0]).put(**{op.path[0]: Relation(a.select().unionByName(b.select(), allowMissingColumns=True), fields)})


@_on("partition_table")
def _partition(db: Database, op: Op) -> Database:
    r, test = db[op.path[0]], F.coalesce(F.expr(op.arg), F.lit(False))
    parts = {op.ref[0]: replace(r, df=r.df.where(test)), op.ids[0]: replace(r, df=r.df.where(~test))}
    return db.without(op.path[0]).put(**parts)


@_on("collapse_set")
def _collapse(db: Database, op: Op) -> Database:
    r = db[op.path[0]]
    # every member keeps its ID and learns its class, so the collapse can be taken back; an aggregate and a join, as a class may hold a third of all rows
    classes = r.df.groupBy(*op.ids).agg(F.min(F.struct(ORD, EID))[EID].alias("__class"), F.count(F.lit(1)).alias("__size"))
    classes = classes.select(*[F.col(k).alias(f"__k_{k}") for k in op.ids], "__class", "__size")
    same = [F.col(k).eqNullSafe(F.col(f"__k_{k}")) for k in op.ids]
    df = r.df.join(classes, same).drop(*[f"__k_{k}" for k in op.ids])
    return db.put(**{op.path[0]: Relation(df, r.fields)})


@_on("insert_elem", "append_elem")
def _insert_elem(db: Database, op: Op) -> Database:
    """One new row at the end, or in front of another row (whose order key it takes with a lower last part)."""
    table, e = op.path[0], op.ids[0]
    r = db[table]
    if op.kind == "append_elem":
        row = r.df.sparkSession.range(1).select(F.lit(e).alias(EID), F.array(F.lit(LAST - 1), F.lit(LAST)).alias(ORD), F.lit(False).alias(DEAD), *r.header_row())
    else:
        at = F.concat(F.slice(ORD, 1, F.size(ORD) - 1), F.array(F.lit(0).cast("long"), F.lit(LAST)))
        row = r.df.where(F.col(EID) == op.ids[1]).select(F.lit(e).alias(EID), at.alias(ORD), F.lit(False).alias(DEAD), *r.header_row())
    return db.put(**{table: replace(r, df=r.select().unionByName(row))})


@_on("move_elem")
def _move_elem(db: Database, op: Op) -> Database:
    """One row's content goes to another row, the source becomes a tombstone and links to it follow (one join on a one-row table)."""
    from .forward import forward_links

    table, e, d = op.path[0], op.path[1], op.ref[1]
    r = db[table]
    content = r.df.where(F.col(EID) == e).select(F.lit(d).alias("__to"), *[F.col(c).alias(f"__m_{c}") for c in r.stored()])
    df = r.select().join(content, F.col(EID) == F.col("__to"), "left")
    hit = F.col("__to").isNotNull()
    df = df.select(EID, ORD, F.when(F.col(EID) == e, F.lit(True)).when(hit, F.lit(False)).otherwise(F.col(DEAD)).alias(DEAD), *[F.when(hit, F.col(f"__m_{c}")).otherwise(F.col(c)).alias(c) for c in r.stored()])
    out = db.put(**{table: replace(r, df=df)})
    one = r.df.sparkSession.range(1).select(F.lit(e).alias("eid"), F.lit(d).alias("root"))
    for name, other in out.tables.items():
        for f in other.fields:
            if isinstance(f.type, LinkT) and f.type.target == (table,):
                other = replace(other, df=forward_links(other.df, f.fid, one))
        out = out.put(**{name: other})
    return out


def retarget_links(db: Database, old: str, new: str) -> Database:
    """Links into a list follow it when it gets another name: a change of types, no job."""
    out = db
    for name, r in db.tables.items():
        fields = tuple(replace(f, type=LinkT((new,))) if isinstance(f.type, LinkT) and f.type.target == (old,) else f for f in r.fields)
        out = out.put(**{name: replace(r, fields=fields)})
    return out


@_on("move_table")
def _move_table(db: Database, op: Op) -> Database:
    old, new = op.path[0], op.ref[0]
    if new in db.tables:
        raise Rejected(f"table {new} exists")
    return retarget_links(db.without(old).put(**{new: db[old]}), old, new)


@_on("decompose")
def _decompose(db: Database, op: Op) -> Database:
    from .forward import dedupe_moves, merge

    out = db.apply(Op("split_table", op.path, ref=op.ref, ids=op.ids))
    new = op.ref[0]
    return merge(out, new, dedupe_moves(out[new], op.ids))


@_on("define_formula")
def _formula(db: Database, op: Op) -> Database:
    return replace(db, formulas={**db.formulas, op.path[-1]: op.arg})


NULL = NULL_LINK
