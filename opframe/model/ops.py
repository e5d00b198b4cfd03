"""Operations: what they are, where they point, and what they create."""

from __future__ import annotations

import json
from dataclasses import dataclass, replace

from . import types

Path = tuple[str, ...]

#: Operations that change data only, and those that change the type and migrate the data.
VALUE_KINDS = (
    "noop", "set_cell", "insert_elem", "append_elem", "drop_elem", "restore_elem", "move_elem", "set_link", "drop_present", "drop_absent", "drop_where",
)
TYPE_KINDS = (
    "define_type", "convert_type", "rename_field", "insert_field", "append_field", "drop_field", "restore_field", "move_field",
    "wrap_list", "unwrap_first", "wrap_record", "unwrap_field", "define_link", "split_table", "join_link",
    "move_table", "extract_list", "push_column", "match_column", "decompose", "copy_table", "union_table", "partition_table", "collapse_set",
    "define_formula", "define_computed",
)
#: Operations that concern a place and not what is in it.
SLOT_KINDS = ("rename_field", "drop_field", "move_field", "split_table", "drop_elem", "move_elem", "restore_elem", "restore_field")


@dataclass(frozen=True)
class Op:
    """One operation. ``arg`` is the value, type, name or expression; ``ref`` a second path; ``ids`` the IDs it creates or is anchored on.

    ``was``: the type that the operation found, where a retraction needs it (conversions, unwrapped lists).
    """

    kind: str
    path: Path = ()
    arg: object = None
    ref: Path = ()
    ids: tuple[str, ...] = ()
    was: object = None

    @property
    def plane(self) -> str:
        return "value" if self.kind in VALUE_KINDS else "type"

    @property
    def slot(self) -> bool:
        return self.kind in SLOT_KINDS

    def at(self, path: Path) -> Op:
        return replace(self, path=path)

    def creates(self) -> set[str]:
        """IDs that exist only after the operation."""
        if self.kind in ("insert_elem", "append_elem", "insert_field", "append_field"):
            return {self.ids[0]}
        return set()

    def mentions(self) -> set[str]:
        """IDs that must exist before the operation."""
        own = set(self.path) | set(self.ref)
        if self.kind in ("insert_elem", "insert_field"):
            own |= set(self.ids[1:])
        if self.kind in ("drop_elem", "drop_field", "restore_elem", "restore_field"):
            own |= set(self.ids)
        if self.kind == "set_link" and self.arg != "*":
            own.add(str(self.arg))
        return own


def noop(path: Path = ()) -> Op:
    return Op("noop", path)


def set_cell(path: Path, value) -> Op:
    return Op("set_cell", path, value)


def insert_elem(path: Path, eid: str, before: str) -> Op:
    return Op("insert_elem", path, ids=(eid, before))


def append_elem(path: Path, eid: str) -> Op:
    return Op("append_elem", path, ids=(eid,))


def drop_elem(path: Path, eid: str) -> Op:
    return Op("drop_elem", path, ids=(eid,))


def restore_elem(path: Path, eid: str) -> Op:
    return Op("restore_elem", path, ids=(eid,))


def move_elem(path: Path, dst: str) -> Op:
    return Op("move_elem", path, ref=(*path[:-1], dst))


def set_link(path: Path, eid: str) -> Op:
    return Op("set_link", path, eid)


def drop_present(path: Path) -> Op:
    return Op("drop_present", path)


def drop_absent(path: Path) -> Op:
    return Op("drop_absent", path)


def drop_where(path: Path, sql: str) -> Op:
    return Op("drop_where", path, sql)


def define_type(path: Path, t) -> Op:
    return Op("define_type", path, t)


def convert_type(path: Path, t, was=None) -> Op:
    return Op("convert_type", path, t, was=was)


def rename_field(path: Path, name: str) -> Op:
    return Op("rename_field", path, name)


def insert_field(path: Path, fid: str, before: str) -> Op:
    return Op("insert_field", path, ids=(fid, before))


def append_field(path: Path, fid: str) -> Op:
    return Op("append_field", path, ids=(fid,))


def drop_field(path: Path, fid: str) -> Op:
    return Op("drop_field", path, ids=(fid,))


def move_field(path: Path, to: Path) -> Op:
    return Op("move_field", path, ref=to)


def wrap_list(path: Path) -> Op:
    return Op("wrap_list", path)


def unwrap_first(path: Path, pinned: str | None = None, was=None) -> Op:
    return Op("unwrap_first", path, pinned, was=was)


def wrap_record(path: Path, fid: str) -> Op:
    return Op("wrap_record", path, ids=(fid,))


def unwrap_field(path: Path, fid: str) -> Op:
    return Op("unwrap_field", path, ids=(fid,))


def define_link(path: Path, to: Path) -> Op:
    return Op("define_link", path, ref=to)


def split_table(column: Path, new_list: Path, moved: tuple[str, ...] = ()) -> Op:
    """Columns from ``column`` to the record's end go to ``new_list``; ``moved`` pins them once projected."""
    return Op("split_table", column, ref=new_list, ids=moved)


def join_link(path: Path) -> Op:
    return Op("join_link", path)


def move_table(path: Path, to: Path) -> Op:
    """A list under another name; links into it follow."""
    return Op("move_table", path, ref=to)


def extract_list(path: Path, new_list: Path) -> Op:
    return Op("extract_list", path, ref=new_list)


def push_column(column: Path, link: Path) -> Op:
    return Op("push_column", column, ref=link)


def match_column(src: Path, dst: Path, regex: str) -> Op:
    return Op("match_column", src, regex, ref=dst)


def decompose(column: Path, new_list: Path, keys: tuple[str, ...]) -> Op:
    return Op("decompose", column, ref=new_list, ids=keys)


def copy_table(path: Path, to: Path) -> Op:
    return Op("copy_table", path, ref=to)


def union_table(path: Path, other: Path) -> Op:
    return Op("union_table", path, ref=other)


def partition_table(path: Path, sql: str, yes: Path, no: Path) -> Op:
    return Op("partition_table", path, sql, ref=yes, ids=no)


def collapse_set(path: Path, keys: tuple[str, ...]) -> Op:
    return Op("collapse_set", path, ids=keys)


def define_computed(path: Path, sql: str) -> Op:
    return Op("define_computed", path, sql)


def define_formula(path: Path, formula) -> Op:
    return Op("define_formula", path, formula)


def to_json(op: Op) -> str:
    """A type operation as it is kept in a log."""
    typed = {k: types.to_json(v) for k, v in (("arg", op.arg), ("was", op.was)) if isinstance(v, types.Type)}
    plain = {"arg": op.arg} if op.arg is not None and "arg" not in typed else {}
    return json.dumps({"kind": op.kind, "path": op.path, "ref": op.ref, "ids": op.ids, "typed": typed, **plain}, separators=(",", ":"))


def from_json(text: str) -> Op:
    """Inverse of ``to_json``."""
    x = json.loads(text)
    typed = {k: types.from_json(v) for k, v in x["typed"].items()}
    return Op(x["kind"], tuple(x["path"]), typed.get("arg", x.get("arg")), tuple(x["ref"]), tuple(x["ids"]), typed.get("was"))
