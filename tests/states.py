"""A small state with every kind of slot, operations on it, and its way into the engine."""

import random

import pyarrow as pa
from pyspark.sql import types as T
from pyspark.sql.pandas.types import to_arrow_schema

from opframe.kernel.interp import State, live
from opframe.model import ops as o
from opframe.model.types import ANY, NULL_LINK, ONE, Field, LinkT, ListT, Num, RecordT, Str, Unit, spark_type
from opframe.operators import oplog
from opframe.operators.relation import DEAD, EID, LAST, ORD, Database, Relation

ROW = ("t", ANY)


def start():
    t = RecordT(
        (
            Field("what", "what", Str()),
            Field("who", "who", Str()),
            Field("n", "n", Num()),
            Field("link", "link", LinkT(("c",))),
            Field("l", "l", ListT(Str())),
            Field("r", "r", RecordT((Field("a", "a", Str()), Field("b", "b", Str())))),
        )
    )
    c = RecordT((Field("name", "name", Str()), Field("size", "size", Num())))

    def row(i):
        return {"what": f"w{i}", "who": f"p{i}" if i else "", "n": float(i), "link": f"k{i % 2}", "l": {ONE: [f"x{i}", False]}, "r": {"a": f"a{i}", "b": f"b{i}"}}

    return State(
        RecordT((Field("t", "t", ListT(t)), Field("c", "c", ListT(c)))),
        {"t": {f"e{i}": [row(i), i == 3] for i in range(4)}, "c": {f"k{i}": [{"name": f"N{i}", "size": float(i)}, i == 2] for i in range(3)}},
    )


def type_pool():
    return [
        o.define_type((*ROW, "who"), Num()),
        o.convert_type((*ROW, "what"), Num(), Str()),
        o.convert_type((*ROW, "n"), Str(), Num()),
        o.rename_field((*ROW, "who"), "by"),
        o.rename_field((*ROW, "n"), "num"),
        o.append_field(ROW, "new"),
        o.insert_field(ROW, "new2", "n"),
        o.drop_field(ROW, "what"),
        o.drop_field(ROW, "n"),
        o.move_field((*ROW, "what"), (*ROW, "what2")),
        o.move_field((*ROW, "what"), (*ROW, "r", "w")),
        o.move_field((*ROW, "r", "a"), (*ROW, "up")),
        o.wrap_list((*ROW, "who")),
        o.wrap_list((*ROW, "n")),
        o.wrap_record((*ROW, "who"), "R"),
        o.wrap_record((*ROW, "who"), "Q"),
        o.wrap_record((*ROW, "n"), "R"),
        o.unwrap_first((*ROW, "l"), None, Str()),
        o.unwrap_field((*ROW, "r"), "a"),
        o.define_link((*ROW, "who"), ("c",)),
        o.split_table((*ROW, "n"), ("s",)),
        o.split_table((*ROW, "n"), ("s",), ("n",)),
        o.join_link((*ROW, "link")),
        o.rename_field(("c", ANY, "name"), "nm"),
        o.wrap_list(("c", ANY, "name")),
        o.convert_type(("c", ANY, "size"), Str(), Num()),
    ]


def value_pool():
    out = []
    for e in ("e0", "e1"):
        out += [
            o.set_cell(("t", e, "who"), "v" + e),
            o.set_cell(("t", e, "who"), ""),
            o.set_cell(("t", e, "what"), "17" if e == "e0" else "none"),
            o.set_cell(("t", e, "n"), 5.0),
            o.set_cell(("t", e, "l", ONE), "z" + e),
            o.set_cell(("t", e, "r", "a"), "q" + e),
            o.set_link(("t", e, "link"), "k1"),
            o.drop_elem(("t",), e),
            o.insert_elem(("t",), "n" + e, e),
            o.append_elem(("t", e, "l"), "g" + e),
            o.insert_elem(("t", e, "l"), "h" + e, ONE),
            o.drop_elem(("t", e, "l"), ONE),
        ]
    return [
        *out,
        o.restore_elem(("t",), "e3"),
        o.append_elem(("t",), "z"),
        o.append_elem(("c",), "y"),
        o.drop_elem(("c",), "k0"),
        o.restore_elem(("c",), "k2"),
        o.set_cell(("c", "k0", "name"), "M"),
        o.set_cell(("c", "k1", "size"), 9.0),
        o.set_link(("t", "e0", "link"), NULL_LINK),
    ]


def other_pool():
    return [o.noop(("t", "e0", "who")), o.move_elem(("t", "e0"), "e1"), o.move_elem(("c", "k0"), "k1"), o.drop_present((*ROW, "who")), o.drop_absent((*ROW, "who")), o.drop_present((*ROW, "n"))]


def random_writes(state, rng, n):
    """Writes of random slots of any state's live rows."""
    out = []

    def slots(t, v, path):
        if isinstance(t, ListT):
            for e, (x, dead) in v.items():
                if not dead:
                    yield from slots(t.elem, x, (*path, e))
        elif isinstance(t, RecordT):
            for f in t.fields:
                yield from slots(f.type, v[f.fid], (*path, f.fid))
        elif not isinstance(t, Unit):
            yield t, path

    found = list(slots(state.type, state.value, ()))
    for i in range(n):
        t, path = rng.choice(found)
        if isinstance(t, LinkT):
            target = state.value[t.target[0]]
            out.append(o.set_link(path, rng.choice([e for e, (_, dead) in target.items() if not dead] + [NULL_LINK])))
        else:
            out.append(o.set_cell(path, float(rng.randrange(20)) if isinstance(t, Num) else rng.choice([f"s{i}", str(rng.randrange(9))])))
    return out


def plain(v, t):
    """A kernel value as Spark rows have it."""
    if isinstance(t, ListT):
        return [(e, plain(x, t.elem)) for e, (x, dead) in v.items() if not dead]
    if isinstance(t, RecordT):
        return tuple(plain(v[f.fid], f.type) for f in t.fields)
    return v


def frame(spark, rows, schema):
    """A small table by way of Arrow: no Python workers read it."""
    kind = to_arrow_schema(T._parse_datatype_string(schema))

    def shaped(v, t):
        if pa.types.is_struct(t) and isinstance(v, tuple):
            return {t.field(i).name: shaped(x, t.field(i).type) for i, x in enumerate(v)}
        if pa.types.is_list(t) and v is not None:
            return [shaped(x, t.value_type) for x in v]
        return v

    columns = [pa.array([shaped(r[i], f.type) for r in rows], f.type) for i, f in enumerate(kind)]
    return spark.createDataFrame(pa.Table.from_arrays(columns, schema=kind))


def database(spark, state):
    tables = {}
    for table in state.type.fields:
        fields = [f for f in table.type.elem.fields if not isinstance(f.type, Unit)]
        rows = [(e, [i, LAST], dead, *[plain(v[f.fid], f.type) for f in fields]) for i, (e, (v, dead)) in enumerate(state.value[table.fid].items())]
        kinds = [f"{EID} string", f"{ORD} array<bigint>", f"{DEAD} boolean", *[f"{f.fid} {spark_type(f.type).simpleString()}" for f in fields]]
        tables[table.fid] = Relation(frame(spark, rows, ", ".join(kinds)), tuple(table.type.elem.fields))
    return Database(tables)


def log(spark, ops, first=1):
    """Log rows of value operations."""
    rows = []
    for i, x in enumerate(ops):
        p = x.path
        row = dict.fromkeys(oplog.SCHEMA) | {"seq": first + i, "op_id": f"op{first + i}", "kind": x.kind, "list_key": p[0], "plane": "value"}
        if x.kind in ("set_cell", "set_link"):
            row |= {"eid": p[1], "fid": p[2], "sub": p[3] if len(p) > 3 else None}
            row |= {"val_n": float(x.arg)} if isinstance(x.arg, float) else {"val_s": x.arg}
        else:
            row |= {"arg_eid": x.ids[0], "anchor": x.ids[1] if x.kind == "insert_elem" else None}
            if len(p) > 1:
                row |= {"eid": p[1], "fid": p[2]}
        rows.append(tuple(row[c] for c in oplog.SCHEMA))
    return frame(spark, rows, ", ".join(f"{c} {t}" for c, t in oplog.SCHEMA.items()))


def rows_of(db):
    """Live rows of the engine by table, as the kernel's ``live`` gives them."""

    def norm(v, t):
        if isinstance(t, ListT):
            return [(x["eid"], norm(x["val"], t.elem)) for x in v or []]
        if isinstance(t, RecordT):
            return {f.fid: norm(v[f.fid], f.type) for f in t.fields if not isinstance(f.type, Unit)}
        if isinstance(v, float) and v != v:
            return None
        return v

    return {name: {x[EID]: {f.fid: norm(x[f.fid], f.type) for f in r.fields if not isinstance(f.type, Unit)} for x in r.live().collect()} for name, r in db.tables.items()}


def live_of(state):
    got = live(state.value, state.type)

    def bare(v, t):
        if isinstance(t, ListT):
            return [(e, bare(x, t.elem)) for e, x in v]
        if isinstance(t, RecordT):
            return {f.fid: bare(v[f.fid], f.type) for f in t.fields if not isinstance(f.type, Unit)}
        return v

    return {f.fid: dict(bare(got[f.fid], f.type)) for f in state.type.fields}


def chosen(seed, n=10):
    """Operations that can run one after another on the start."""
    from opframe.kernel.interp import Invalid, apply

    rng, state, out = random.Random(seed), start(), []
    pool = value_pool()
    while len(out) < n:
        x = rng.choice(pool + random_writes(state, rng, 6))
        try:
            state = apply(state, x)
        except (Invalid, KeyError):
            continue
        out.append(x)
    return out
