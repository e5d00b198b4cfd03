"""Static types of documents and their initial values.

A type says how a slot is stored in Spark and which value is blank: the empty string, NaN,
typed NULL for the atomics that tables bring along, the null mark for links.
"""

from __future__ import annotations

import json
from dataclasses import dataclass

from pyspark.sql import Column
from pyspark.sql import functions as F
from pyspark.sql import types as T

#: Element ID of the only element that wrapping makes; the null link; the element type of a list in a path.
ONE, NULL_LINK, ANY = "ONE", "*", "*"


class Type:
    """Base of all types."""


@dataclass(frozen=True)
class Unit(Type):
    """The empty record, from which every history starts."""


@dataclass(frozen=True)
class Str(Type):
    """Strings; blank is the empty string."""


@dataclass(frozen=True)
class Num(Type):
    """Doubles; blank is NaN."""


@dataclass(frozen=True)
class Atom(Type):
    """Any other atomic that a table brings along, by its Spark name; blank is NULL."""

    name: str


@dataclass(frozen=True)
class ListT(Type):
    """Elements of one type, each with an ID."""

    elem: Type


@dataclass(frozen=True)
class Field:
    """A record field: a permanent ID, a label for people, a type."""

    fid: str
    name: str
    type: Type


@dataclass(frozen=True)
class RecordT(Type):
    """A fixed sequence of fields."""

    fields: tuple[Field, ...]

    def field(self, fid: str) -> Field:
        for f in self.fields:
            if f.fid == fid:
                return f
        raise KeyError(fid)


@dataclass(frozen=True)
class LinkT(Type):
    """Element IDs of the list at a path, or the null mark."""

    target: tuple[str, ...]


@dataclass(frozen=True)
class FormulaT(Type):
    """A timeline run on a copy of the current state, and the path whose value it returns."""

    ops: tuple
    ret: tuple[str, ...]


def initial(t: Type):
    """Initial value as a Python object."""
    if isinstance(t, Str):
        return ""
    if isinstance(t, Num):
        return float("nan")
    if isinstance(t, ListT):
        return []
    if isinstance(t, RecordT):
        return {f.fid: initial(f.type) for f in t.fields}
    if isinstance(t, LinkT):
        return NULL_LINK
    if isinstance(t, Unit):
        return {}
    return None


def spark_type(t: Type) -> T.DataType:
    """How a slot of this type is stored."""
    if isinstance(t, (Str, LinkT)):
        return T.StringType()
    if isinstance(t, Num):
        return T.DoubleType()
    if isinstance(t, Atom):
        return T._parse_datatype_string(t.name)
    if isinstance(t, ListT):
        return T.ArrayType(T.StructType([T.StructField("eid", T.StringType()), T.StructField("val", spark_type(t.elem))]))
    if isinstance(t, RecordT):
        return T.StructType([T.StructField(f.fid, spark_type(f.type)) for f in t.fields])
    if isinstance(t, Unit):
        return T.StructType([])
    raise TypeError(f"{t} is not stored")


def from_spark(t: T.DataType) -> Type:
    """The type of an imported column."""
    if isinstance(t, T.StringType):
        return Str()
    if isinstance(t, T.StructType):
        return RecordT(tuple(Field(f.name, f.name, from_spark(f.dataType)) for f in t.fields))
    return Atom(t.simpleString())


def initial_column(t: Type) -> Column:
    """Initial value as a column."""
    if isinstance(t, Str):
        return F.lit("")
    if isinstance(t, Num):
        return F.lit(float("nan"))
    if isinstance(t, LinkT):
        return F.lit(NULL_LINK)
    if isinstance(t, RecordT) and t.fields:
        return F.struct(*[initial_column(f.type).alias(f.fid) for f in t.fields])
    if isinstance(t, ListT):
        return F.array().cast(spark_type(t))
    return F.lit(None).cast(spark_type(t))


def is_initial(c: Column, t: Type) -> Column:
    """Whether a slot is blank; NULL counts as blank under every type."""
    if isinstance(t, Str):
        return F.coalesce(c == "", F.lit(True))
    if isinstance(t, Num):
        return F.coalesce(F.isnan(c), F.lit(True))
    if isinstance(t, LinkT):
        return F.coalesce(c == NULL_LINK, F.lit(True))
    if isinstance(t, ListT):
        return F.coalesce(F.size(c) == 0, F.lit(True))
    if isinstance(t, RecordT) and t.fields:
        out = F.lit(True)
        for f in t.fields:
            out = out & is_initial(c[f.fid], f.type)
        return out
    return c.isNull()


def to_json(t: Type) -> str:
    """Types are kept in logs as JSON."""

    def enc(x):
        if isinstance(x, ListT):
            return {"list": enc(x.elem)}
        if isinstance(x, RecordT):
            return {"record": [[f.fid, f.name, enc(f.type)] for f in x.fields]}
        if isinstance(x, LinkT):
            return {"link": list(x.target)}
        if isinstance(x, Atom):
            return {"atom": x.name}
        return type(x).__name__.lower()

    return json.dumps(enc(t), separators=(",", ":"))


def from_json(s: str) -> Type:
    """Inverse of ``to_json``."""

    def dec(x):
        if isinstance(x, str):
            return {"str": Str, "num": Num, "unit": Unit}[x]()
        (k, v), = x.items()
        if k == "list":
            return ListT(dec(v))
        if k == "record":
            return RecordT(tuple(Field(a, b, dec(c)) for a, b, c in v))
        return LinkT(tuple(v)) if k == "link" else Atom(v)

    return dec(json.loads(s))
