"""Methods to compare with: they see states, not operations, or undo by truncation."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators import oplog


def keyed_state_diff(a: DataFrame, b: DataFrame, key: list[str]) -> DataFrame:
    """Key columns and change (insert, delete, update) between two snapshots of one schema."""
    rest = [c for c in a.columns if c not in key]
    x = a.select(*key, F.struct(*rest).alias("__a"), F.lit(True).alias("__in_a"))
    y = b.select(*key, F.struct(*rest).alias("__b"), F.lit(True).alias("__in_b"))
    both = x.join(y, key, "full").where(~F.col("__a").eqNullSafe(F.col("__b")))
    change = F.when(F.col("__in_a").isNull(), "insert").when(F.col("__in_b").isNull(), "delete").otherwise("update")
    return both.select(*key, change.alias("change"))


def row_set_diff(a: DataFrame, b: DataFrame) -> DataFrame:
    """Rows as text lines: every change is a deletion and an insertion."""
    return a.exceptAll(b).withColumn("change", F.lit("delete")).unionByName(b.exceptAll(a).withColumn("change", F.lit("insert")))


def three_way_merge(base: DataFrame, a: DataFrame, b: DataFrame, key: list[str], value: str) -> DataFrame:
    """Key, merged value and conflict flag of cells: the side that differs from the last common ancestor wins; both differ: conflict, no value."""
    x = base.select(*key, F.col(value).alias("o")).join(a.select(*key, F.col(value).alias("a")), key, "full").join(b.select(*key, F.col(value).alias("b")), key, "full")
    same, left, right = (F.col(p).eqNullSafe(F.col(q)) for p, q in (("a", "b"), ("a", "o"), ("b", "o")))
    merged = F.when(same, F.col("a")).when(left, F.col("b")).when(right, F.col("a"))
    return x.select(*key, merged.alias(value), (~same & ~left & ~right).alias("conflict"))


def last_common_ancestor(a: DataFrame, b: DataFrame) -> int:
    """Length of the histories' common beginning."""
    return oplog.common_prefix(a, b)


def truncate_undo(ops: DataFrame, seq: int) -> DataFrame:
    """Undo of the last operations only: the state without everything from ``seq`` on."""
    return oplog.last_writers(ops.where(F.col("seq") < seq))


def delete_from_history(ops: DataFrame, chosen) -> DataFrame:
    """Naive undo: replay without the chosen rows; rows that mention what they made are left dangling."""
    gone = ops.where(chosen & F.col("kind").isin("insert_elem", "append_elem")).select(F.col("arg_eid").alias("__e"))
    return ops.where(~chosen).join(gone, F.coalesce("arg_eid", "eid") == F.col("__e"), "left").withColumn("dangling", F.col("__e").isNotNull()).drop("__e")


def sql_migration(flat: DataFrame, keys: list[str]) -> tuple[DataFrame, DataFrame]:
    """The split by hand: distinct key columns with a generated key, and a foreign key beside the rest. No divergence survives it."""
    new = flat.groupBy(*keys).agg(F.min("k").alias("customer"))
    on = [flat[c].eqNullSafe(new[c]) for c in keys]
    return flat.join(new, on).select(*[flat[c] for c in flat.columns if c not in keys], "customer"), new


def single_source_views(flat: DataFrame, keys: list[str], name: str) -> None:
    """Both schemas as views over one stored table: there is nothing to transfer, and nothing can diverge."""
    flat.createOrReplaceTempView(f"{name}_flat")
    sql_migration(flat, keys)[0].createOrReplaceTempView(f"{name}_split")


def manual_query(spark, sql: str) -> DataFrame:
    """A query written by hand for one schema; it names tables and columns, and breaks when they change."""
    return spark.sql(sql)


ot_without_tombstones = oplog.order_without_tombstones
