"""Base documents of the case studies, built from the given tables, and the same as SQL for oracles."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..model.ops import split_table
from ..model.types import ANY, Atom, Str
from ..operators.forward import settled
from ..operators.relation import Database, from_table

ORDER_TYPES = {"k": Atom("bigint"), "item": Str(), "quantity": Atom("bigint"), "ship_date": Atom("timestamp_ntz"), "name": Str(), "address": Str()}
SPLIT = split_table(("orders", ANY, "name"), ("customers",))

D_ORDERS = """d as (
  select o.o_orderkey as k, o.o_orderpriority as item, cast(coalesce(l.n, 0) as bigint) as quantity,
    case when o.o_orderstatus = 'F' then l.ship end as ship_date, c.c_name as name, c.c_mktsegment || '/' || n.n_name as address
  from orders o join customer c on c.c_custkey = o.o_custkey join nation n on n.n_nationkey = c.c_nationkey
  left join (select l_orderkey, count(*) as n, max(l_shipdate) as ship from lineitem group by 1) l on l.l_orderkey = o.o_orderkey)"""


def table(spark: SparkSession, sf: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf}/{name}.parquet")


def orders_flat(spark: SparkSession, sf: str) -> DataFrame:
    """k, item, quantity, ship_date, name, address: one row for each order."""
    lines = table(spark, sf, "lineitem").groupBy("l_orderkey").agg(F.count(F.lit(1)).alias("n"), F.max("l_shipdate").alias("ship"))
    o, c, n = (table(spark, sf, t) for t in ("orders", "customer", "nation"))
    people = c.join(F.broadcast(n), c.c_nationkey == n.n_nationkey)  # 25 nations
    return (
        o.join(people, o.o_custkey == people.c_custkey)
        .join(lines, o.o_orderkey == lines.l_orderkey, "left")
        .select(
            F.col("o_orderkey").alias("k"),
            F.col("o_orderpriority").alias("item"),
            F.coalesce("n", F.lit(0)).cast("bigint").alias("quantity"),
            F.when(F.col("o_orderstatus") == "F", F.col("ship")).alias("ship_date"),
            F.col("c_name").alias("name"),
            F.concat("c_mktsegment", F.lit("/"), "n_name").alias("address"),
        )
    )


def orders_db(spark: SparkSession, sf: str) -> Database:
    """The flat orders as a database of one table: the import is written once, and every later plan reads it."""
    return Database({"orders": from_table(settled(orders_flat(spark, sf), "orders"), F.col("k"), "o", ORDER_TYPES)})


def todo_db(spark: SparkSession, sf: str) -> Database:
    """Orders as tasks: what is to be done, and who does it."""
    o, c = table(spark, sf, "orders"), table(spark, sf, "customer")
    df = o.join(c, o.o_custkey == c.c_custkey).select(F.col("o_orderkey").alias("k"), F.col("o_orderpriority").alias("what"), F.col("c_name").alias("who"))
    return Database({"tasks": from_table(settled(df, "tasks"), F.col("k"), "o", {"k": Atom("bigint"), "what": Str(), "who": Str()})})


D_TODO = "t as (select o_orderkey as k, o_orderpriority as what, c_name as who from orders join customer on c_custkey = o_custkey)"


def events_log(spark: SparkSession, sf: str) -> dict[str, DataFrame]:
    """Writes of cells (user, event type): the shared part, the left and the right branch, and all."""
    from ..operators.oplog import log

    e = table(spark, sf, "events")
    ops = log(e, "set_cell", "cells", seq=F.col("event_id"), eid=F.col("user_id").cast("string"), fid=F.col("event_type"), val_n=F.floor(F.col("value") / 50).cast("double"))
    shared, even = F.col("seq") < 2000, F.col("seq") % 2 == 0
    return {"all": ops, "shared": ops.where(shared), "left": ops.where(~shared & even), "right": ops.where(~shared & ~even)}


L_EVENTS = """e as (select event_id as seq, user_id as u, event_type as f, cast(floor(value / 50) as bigint) as v,
  case when event_id < 2000 then 'O' when event_id % 2 = 0 then 'L' else 'R' end as br from events)"""
