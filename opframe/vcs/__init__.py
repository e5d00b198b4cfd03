"""Version control without a repository: documents are logs, branches are copies of them.

A document is a name, a start state and a log of value and type operations. Copying shares the
log: nothing is moved until a branch writes. Copies and transfers leave comments
(``origin_op``) from which a version graph can be drawn.

Transfer works on two planes. A schema's history is short: its type operations are moved
across the other branch's by the kernel's rules on the driver. The value operations, however
many, are moved set by set across type operations only: back over their own branch's to the
fork, or on to its head, and forward over the other's. Where both wrote a cell the
transferred write comes later.
"""

from __future__ import annotations

from dataclasses import dataclass, replace

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .. import sources
from ..kernel import rules
from ..kernel import transfer as kernel
from ..kernel.interp import State
from ..model.ops import Op
from ..model.types import Field, ListT, RecordT
from ..operators import oplog
from ..operators.forward import settled
from ..operators.relation import Database


def values(ops: DataFrame) -> DataFrame:
    """A log's value operations."""
    return ops.where(F.coalesce(F.col("plane") == "value", F.lit(True)))


#: Type operations that bring rows along when a log crosses them: what follows starts from a written log, so that plans do not multiply.
BRINGS = ("wrap_list", "split_table", "join_link", "copy_table", "match_column")


def head(start: Database, ops: DataFrame) -> tuple[DataFrame, Database]:
    """(value operations of a log as if all were made under its last schema, ``start`` under that schema).

    Of equal numbers the type operation comes first.
    """
    rows, carried, last, db = values(ops), None, None, start
    for seq, op in oplog.types_of(ops):
        part = rows.where(F.col("seq") < seq) if last is None else rows.where((F.col("seq") >= last) & (F.col("seq") < seq))
        carried = part if carried is None else carried.unionByName(part)
        # a join follows links to rows that the log may have made
        before = oplog.replay(db, carried) if op.kind == "join_link" else db
        carried, db, last = oplog.forward(carried, op, before), db.apply(op), seq
        carried = settled(carried, "head") if op.kind in BRINGS else carried
    if last is None:
        return rows, db
    return carried.unionByName(rows.where(F.col("seq") >= last)), db


def schema_of(db: Database) -> State:
    """A database's type with no rows: enough for moving type operations across each other."""
    fields = tuple(Field(n, n, ListT(RecordT(tuple(r.fields)))) for n, r in db.tables.items())
    return State(RecordT(fields), {n: {} for n in db.tables})


@dataclass(frozen=True)
class Document:
    """A start state, the log of value and type operations on it, and type operations that came before the log."""

    name: str
    start: Database
    ops: DataFrame
    types: tuple[Op, ...] = ()

    def base(self) -> Database:
        """The state that the log starts from."""
        return self.start.run(list(self.types))

    def state(self) -> Database:
        """The current state: the start under the last schema, then one replay."""
        rows, db = head(self.base(), self.ops)
        return oplog.replay(db, rows)

    def append(self, ops: DataFrame) -> Document:
        """The document with more operations."""
        return replace(self, ops=self.ops.unionByName(ops))

    def alter(self, seq: int, *ops: Op) -> Document:
        """The document with type operations, numbered from ``seq`` on."""
        return self.append(oplog.log_types(self.ops.sparkSession, [(seq + i, op) for i, op in enumerate(ops)], self.name))


def branch(doc: Document, name: str) -> Document:
    """A copy with the same history; it costs nothing, as logs are never changed."""
    return replace(doc, name=name)


@dataclass(frozen=True)
class Diff:
    """Two documents' common log and what each has besides; ``start`` is the state that both logs start from."""

    shared: DataFrame
    left: DataFrame
    right: DataFrame
    start: Database | None = None

    def flip(self) -> Diff:
        return Diff(self.shared, self.right, self.left, self.start)

    def shared_state(self) -> Database:
        """The hypothetical ancestor: it need never have existed."""
        if not self.shared.limit(1).count():
            return self.start
        rows, db = head(self.start, self.shared)
        return oplog.replay(db, rows)


def diff(a: Document, b: Document) -> Diff:
    """By operation IDs, which survive copying; operations transferred from the other side count as shared."""
    cols = a.ops.columns
    left, right = settled(a.ops, "left"), settled(b.ops, "right")
    ids = lambda ops: ops.select(F.explode(F.array_distinct(F.array("op_id", F.coalesce("origin_op", "op_id")))).alias("op_id")).distinct()
    mine, theirs = ids(right), ids(left)
    # each part is used many times by what follows
    parts = left.join(mine, "op_id", "left_semi"), left.join(mine, "op_id", "left_anti"), right.join(theirs, "op_id", "left_anti")
    return Diff(*[settled(x.select(*cols), "diff") for x in parts], a.base())


@dataclass(frozen=True)
class Transfer:
    """What a transfer brings to the right: type operations, value operations after them, what was blocked, and
    the right's own type operations as they would follow the left's."""

    types: list[Op]
    rows: DataFrame
    blocked: DataFrame
    adjusted: list[Op]


def _back(rows: DataFrame, ops: list[Op], fork: Database) -> tuple[DataFrame, DataFrame, list[int]]:
    """(rows before a line of type operations, blocked rows, places of the operations that blocked)."""
    states = [fork]
    for op in ops:
        states.append(states[-1].apply(op))
    blocked, by = rows.where("false").withColumn("blocker_kind", F.lit("")), []
    for i in range(len(ops) - 1, -1, -1):
        op = ops[i]
        rows, bad = oplog.backward(rows, op, states[i] if op.kind == "join_link" else states[i + 1])
        if op.kind in oplog.STILL and not op.ids:
            continue  # nothing depends on a label
        rows, bad = settled(rows, "back"), settled(bad, "blocked")
        blocked = blocked.unionByName(bad)
        if bad.limit(1).count():
            by.append(i)
    return rows, blocked, by


def _on(rows: DataFrame, ops: list[Op], db: Database) -> tuple[DataFrame, Database]:
    """(rows after a line of type operations, the database after it)."""
    for op in ops:
        before = oplog.replay(db, rows) if op.kind == "join_link" else db
        rows, db = oplog.forward(rows, op, before), db.apply(op)
        rows = settled(rows, "across") if op.kind in BRINGS else rows
    return rows, db


def _needed(ops: list[Op], places: list[int]) -> tuple[list[Op], list[Op]]:
    """(the type operations at ``places`` and all that they need, as they run first; the others, as they follow)."""
    want = set(places)
    for i in sorted(want, reverse=True):
        for j in range(i - 1, -1, -1):
            if any(rules.depends(ops[j], ops[k]) for k in want if k > j):
                want.add(j)
    first: list[Op] = []
    later: list[Op] = []
    for i, op in enumerate(ops):
        if i not in want:
            later.append(op)
            continue
        early, later = kernel.retract_over(later, op)
        first += early
    return first, later


def transfer_all(d: Diff, planes: tuple[str, ...] = ("value", "type"), where: Column | None = None, dependencies: bool = False) -> Transfer:
    """The left's operations for the right head.

    ``planes``: data and types, data only, or types only. ``where`` chooses value operations;
    ``dependencies`` adds the value operations that made what the chosen ones mention and the
    type operations without which they would be blocked. Data only, without dependencies,
    reports what depends on the left's type operations as blocked.
    """
    lt, rt = ([op for _, op in oplog.types_of(x)] for x in (d.left, d.right))
    fork = d.shared_state() if lt or rt else d.start
    chosen = values(d.left)
    if where is not None:
        chosen = chosen.where(where)
        if dependencies:
            chosen = settled(values(d.left).join(oplog.closure(values(d.left), chosen), "op_id", "left_semi").select(*d.left.columns), "chosen")
    # as if made under the left's last schema, whenever they were made
    at_head, _ = head(fork, d.left.where("plane = 'type'").unionByName(chosen))
    none = at_head.where("false").withColumn("blocker_kind", F.lit(""))
    if "type" in planes and where is None:
        moved, adjusted = rules.project_all(rt, lt, state=schema_of(fork)) if lt else ([], rt)
        if "value" not in planes:
            return Transfer(moved, at_head.where("false"), none, adjusted)
        rows, _ = _on(at_head, adjusted, _run(fork, lt))
        return Transfer(moved, rows, none, adjusted)
    rows, blocked, places = _back(at_head, lt, fork)
    if dependencies and places:
        first, later = _needed(lt, places)
        rows, blocked, _ = _back(at_head, later, _run(fork, first))
        moved, adjusted = rules.project_all(rt, first, state=schema_of(fork))
        rows, _ = _on(rows, adjusted, _run(fork, first))
        return Transfer(moved, rows, blocked, adjusted)
    rows, _ = _on(rows, rt, fork)
    return Transfer([], rows, blocked, rt)


def _run(db: Database, ops: list[Op]) -> Database:
    return db.run(ops)


def _transferred(rows: DataFrame) -> DataFrame:
    return rows.withColumn("origin_op", F.coalesce("origin_op", "op_id")).withColumn("op_id", F.concat("op_id", F.lit("/t")))


def apply_transfer(to: Document, t: Transfer) -> Document:
    """The document with what a transfer brings: its type operations, then its value operations."""
    top = (to.ops.agg(F.max("seq")).first()[0] or 0) + 1
    out = to.append(_type_rows(to, t.types, top)) if t.types else to
    rows = _transferred(t.rows).withColumn("seq", F.col("seq") + top + len(t.types))
    return out.append(settled(rows.select(*to.ops.columns), "transfer"))


def _type_rows(doc: Document, ops: list[Op], first: int) -> DataFrame:
    rows = oplog.log_types(doc.ops.sparkSession, [(first + i, op) for i, op in enumerate(ops)], f"{doc.name}/t")
    return rows.select(*doc.ops.columns)


def transfer(d: Diff, to: Document, op_id: str, dependencies: bool = True) -> tuple[Document, Transfer]:
    """One value operation of the left, with what it needs: a cherry-pick."""
    t = transfer_all(d, ("value",), F.col("op_id") == op_id, dependencies)
    return apply_transfer(to, t), t


def merge(d: Diff, to: Document, planes: tuple[str, ...] = ("value", "type")) -> Document:
    """All of the left on the right head."""
    return apply_transfer(to, transfer_all(d, planes))


def cherry_pick(d: Diff, chosen: Column, dependencies: bool = True) -> DataFrame:
    """Chosen operations of the left branch for the right head, with all that they need, marked as transferred."""
    return _transferred(transfer_all(d, ("value",), chosen, dependencies).rows)


def rebase(d: Diff, ops: DataFrame) -> DataFrame:
    """Transferred operations numbered after all of the right's, so that they win where both wrote."""
    top = d.right.agg(F.max("seq").alias("__top")).select(F.coalesce("__top", F.lit(0)).alias("__top"))
    return ops.crossJoin(F.broadcast(top)).withColumn("seq", F.col("seq") + F.col("__top") + 1).select(*ops.columns)


def sync(a: Document, b: Document) -> tuple[Document, Document]:
    """Everything of the left, data and types, goes right and wins, then the rest of the right goes left."""
    d = diff(a, b)
    t = transfer_all(d)
    right = apply_transfer(b, t)
    rt = [op for _, op in oplog.types_of(d.right)]
    fork = d.shared_state() if rt or t.types else d.start
    at_head, db = head(fork, d.right)
    theirs, _ = _on(at_head, t.types, db)
    won = t.rows.where(F.col("kind").isin(*oplog.WRITES)).select(*[F.col(c).alias(f"__{c}") for c in oplog.CELL]).distinct()
    on = [F.col(c).eqNullSafe(F.col(f"__{c}")) for c in oplog.CELL]
    rest = theirs.join(won, on, "left_anti")
    return apply_transfer(a, Transfer(t.adjusted if rt else [], rest, t.blocked, [])), right


def undo(doc: Document, chosen: Column) -> Document:
    """The document with a delta that takes the chosen value operations back; the delta is part of the log and can itself be shared or undone."""
    rows, db = head(doc.base(), doc.ops)
    return doc.append(oplog.undo_delta(rows, chosen, db).select(*doc.ops.columns))


def scrub(doc: Document, chosen: Column) -> Document:
    """The history as if the chosen value operations, and all that was made in elements that they made, had never been."""
    made = doc.ops.where(chosen & F.col("kind").isin(*oplog.NEW)).select("list_key", F.col("arg_eid").alias("__e"), F.col("fid").alias("__f"))
    kept = doc.ops.where(~chosen)
    inside = made.where("__f is null").select(F.col("list_key").alias("__l"), "__e").distinct()
    about = F.when(F.col("kind").isin(*oplog.NEW, *oplog.GONE) & F.col("fid").isNull(), F.col("arg_eid")).otherwise(F.col("eid"))
    kept = kept.join(inside, (F.col("list_key") == F.col("__l")) & (about == F.col("__e")), "left_anti")
    return replace(doc, ops=kept.select(*doc.ops.columns))


def undo_type(doc: Document, seq: int) -> Document:
    """The document with the type operation numbered ``seq`` taken back: a type operation, moved across the later ones.

    Raises ``Invalid`` for type operations that keep no record of what they replaced.
    """
    line = oplog.types_of(doc.ops)
    at = next(i for i, (s, _) in enumerate(line) if s == seq)
    back = kernel.undo(schema_of(doc.base()), [op for _, op in line], at)
    top = (doc.ops.agg(F.max("seq")).first()[0] or 0) + 1
    rows = _type_rows(doc, back, top).withColumn("undo_of", F.lit(str(seq)))
    return doc.append(rows.select(*doc.ops.columns))


def history(doc: Document, limit: int | None = None) -> DataFrame:
    """Operations in order with a readable line each; a limit is a page."""
    value = F.coalesce("type_json", "val_s", F.format_number("val_n", 2), F.col("val_t").cast("string"), F.lit(""))
    text = F.concat_ws(" ", "kind", F.concat_ws(".", "list_key", "eid", "fid", "sub"), value)
    rows = doc.ops.select("seq", "op_id", text.alias("line")).orderBy(F.desc("seq"))
    return rows.limit(limit) if limit else rows


def version_graph(docs: list[Document]) -> DataFrame:
    """(source, target, operations): how many operations of a document came from another by transfer."""
    rows = None
    for d in docs:
        one = d.ops.select("op_id", "origin_op", F.lit(d.name).alias("doc"))
        rows = one if rows is None else rows.unionByName(one)
    own = rows.where("origin_op is null").select(F.col("op_id").alias("__o"), F.col("doc").alias("source"))
    moved = rows.where("origin_op is not null").join(own, F.col("origin_op") == F.col("__o")).where("source <> doc")
    return moved.groupBy("source", F.col("doc").alias("target")).agg(F.count(F.lit(1)).alias("operations"))


def report(d: Diff) -> DataFrame:
    """Cells that differ: what each side holds, and whether a transfer would overwrite the other."""
    cells = oplog.optimised_cells(d.shared, d.left, d.right)
    return cells.where("keep_left or keep_right").select(*oplog.CELL, F.col("la.val_s").alias("left_s"), F.col("la.val_n").alias("left_n"), F.col("ra.val_s").alias("right_s"), F.col("ra.val_n").alias("right_n"), (F.col("keep_left") & F.col("keep_right")).alias("conflict"))


def compact(doc: Document, upto: int, path: str) -> Document:
    """A snapshot of the state up to a sequence number and the log's tail: the same state, a shorter replay."""
    spark = doc.ops.sparkSession
    old = Document(doc.name, doc.start, doc.ops.where(F.col("seq") <= upto), doc.types).state()
    sources.write_snapshot(old, path, upto)
    return Document(doc.name, sources.read_snapshot(spark, path, upto, old), doc.ops.where(F.col("seq") > upto))


def export_bundle(doc: Document, path: str) -> None:
    """One document with its whole history, data and types, as a unit: the state that the log starts from, and the log."""
    sources.write_snapshot(doc.base(), f"{path}/start", 0)
    sources.write_oplog(doc.ops, f"{path}/log", doc.name)


def import_bundle(spark: SparkSession, path: str, name: str, like: Database) -> Document:
    """A document from a bundle."""
    return Document(name, sources.read_snapshot(spark, f"{path}/start", 0, like), sources.read_oplog(spark, f"{path}/log", name))


def fast_forward(doc: Document, script: DataFrame, upto: int) -> tuple[Document, int]:
    """The document after a recorded script up to a number, and how many steps did not match it (0: valid)."""
    part = script.where(F.col("seq") <= upto)
    odd = part.join(doc.ops.select("seq", F.col("op_id").alias("__o")), "seq", "left").where("__o is not null and __o <> op_id").limit(1).count()
    return replace(doc, ops=doc.ops.unionByName(part.join(doc.ops.select("op_id"), "op_id", "left_anti").select(*doc.ops.columns))), odd
