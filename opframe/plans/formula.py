"""Formulas: queries as operations on a copy of the current state, and their rewriting across schema changes.

A formula is a list of operations and the table it returns. Evaluation folds the operations
over lazy relations, so the copy costs nothing and Catalyst plans the whole. Rewriting works on
the operation list alone, before any plan exists.
"""

from __future__ import annotations

from dataclasses import dataclass, replace

from pyspark.sql import DataFrame

from ..kernel.rules import Blocked, backward, project_all, structural_inverse
from ..model.ops import Op
from ..model.types import LinkT
from ..operators import oplog
from ..operators.relation import EID, Database


@dataclass(frozen=True)
class Formula:
    """Operations run on a copy, and the table whose live rows are the result."""

    ops: tuple[Op, ...]
    ret: str


@dataclass(frozen=True)
class Broken:
    """A formula that a type operation has left without a meaning: it says which when it is evaluated."""

    formula: Formula
    by: Op


def carried(formula: Formula | Broken, op: Op) -> Formula | Broken:
    """A database's formula after a type operation of the database: rewritten, or broken by what cannot be taken back in it."""
    if isinstance(formula, Broken):
        return formula
    try:
        return rewrite_forward(formula, [op])
    except Blocked:
        return Broken(formula, op)


def evaluate_named(db: Database, name: str) -> DataFrame:
    """Rows of a formula that is part of the database."""
    formula = db.formulas[name]
    if isinstance(formula, Broken):
        raise Blocked(formula.by, formula.by)
    return evaluate(db, formula)


def from_diff(d, ret: str) -> Formula:
    """The left branch's type operations as a formula on the right: what the left would look like on the right's present data.

    They are moved back to the fork and across the right's type operations as in a transfer; nothing runs.
    """
    from ..vcs import schema_of

    left, right = ([op for _, op in oplog.types_of(x)] for x in (d.left, d.right))
    moved, _ = project_all(right, left, state=schema_of(d.shared_state()))
    return Formula(tuple(moved), ret)


def evaluate(db: Database, formula: Formula) -> DataFrame:
    """Live rows of the returned table after the formula's operations."""
    return db.run(list(drop_dead_links(db, formula).ops)).export(formula.ret)


def drop_dead_links(db: Database, formula: Formula) -> Formula:
    """Without a join whose columns are all dropped again: such a join changes nothing but the link column."""
    ops = list(formula.ops)
    for i, op in enumerate(ops):
        if op.kind != "join_link" or op.path[0] not in db.tables:
            continue
        fields = {f.fid: f.type for f in db[op.path[0]].fields}
        t = fields.get(op.path[2])
        if not isinstance(t, LinkT) or t.target[0] not in db.tables:
            continue
        joined = {f.fid for f in db[t.target[0]].fields}
        drops = [x for x in ops[i + 1 :] if x.kind == "drop_field" and x.path[0] == op.path[0] and x.ids[0] in joined]
        if {x.ids[0] for x in drops} == joined and all(x.kind == "drop_field" for x in ops[i + 1 : i + 1 + len(drops)]):
            rest = [x for x in ops[i + 1 :] if x not in drops]
            return drop_dead_links(db, replace(formula, ops=(*ops[:i], Op("drop_field", op.path[:2], ids=(op.path[2],)), *rest)))
    return formula


def rewrite_back(formula: Formula, type_ops: list[Op]) -> Formula:
    """The formula for the schema before ``type_ops``; raises ``Blocked`` where it needs what they made."""
    ops = list(formula.ops)
    for base in reversed(type_ops):
        if base.plane == "value":
            continue  # the schema is the same on both sides
        out: list[Op] = []
        met = False
        for op in ops:
            if not met and base.kind == "split_table" and op == structural_inverse(base):
                met = True  # from here on the operations see the schema before the split
                continue
            if met:
                out.append(op)
                continue
            path = backward(base, op.path, True)
            if path is None:
                raise Blocked(op, base)
            out.append(op.at(path))
        ops = out
    return replace(formula, ops=tuple(ops))


def rewrite_forward(formula: Formula, type_ops: list[Op]) -> Formula:
    """The formula for the schema after ``type_ops``: their inverses come first, then inverse pairs cancel."""
    undo: list[Op] = []
    ops = list(formula.ops)
    for op in type_ops:
        if op.plane == "value" or op.kind in ("rename_field", "define_formula"):
            continue
        inv = structural_inverse(op)
        if inv is None and op.kind == "convert_type" and op.was is not None:
            inv = replace(op, arg=op.was, was=op.arg)
        if inv is None and _untouched(op, ops):
            continue  # what it changes is not read by the formula
        if inv is None:
            raise Blocked(op, op)
        undo = [inv, *undo]
    return replace(formula, ops=tuple(cancel_pairs([*undo, *ops])))


def _untouched(op: Op, ops: list[Op]) -> bool:
    """Whether a type operation concerns one column that no operation of a formula names (a join of its table would carry it along)."""
    if op.kind not in ("define_type", "define_link", "drop_field", "convert_type", "match_column", "define_computed", "copy_table"):
        return False
    column = op.ids[0] if op.kind == "drop_field" else op.ref[-1] if op.kind == "match_column" else op.path[-1]
    return all(column not in (*x.path, *x.ids, *x.ref) for x in ops)


def cancel_pairs(ops: list[Op]) -> list[Op]:
    """Without neighbours of which the second takes the first back."""
    out: list[Op] = []
    for op in ops:
        if out and structural_inverse(out[-1]) == op and out[-1].kind != "split_table":
            out.pop()
        else:
            out.append(op)
    return out


def update_through(db: Database, formula: Formula, edits: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(log for the base tables, blocked edits) of a log of edits on a formula's result.

    Edits go back over the formula's joins; deletions by predicate leave them alone.
    """
    states = [db]
    for op in formula.ops:
        states.append(states[-1].apply(op))
    blocked = edits.where("false").withColumn("blocker_kind", oplog.F.lit(""))
    for i in range(len(formula.ops) - 1, -1, -1):
        op = formula.ops[i]
        if op.kind == "join_link":
            # the joined view has no link column any more; the rows' links are read before the join
            edits, bad = oplog.backward(edits, op, states[i])
            blocked = blocked.unionByName(bad)
    return edits, blocked


__all__ = ["EID", "Broken", "Formula", "cancel_pairs", "carried", "evaluate_named", "from_diff", "drop_dead_links", "evaluate", "rewrite_back", "rewrite_forward", "update_through"]
