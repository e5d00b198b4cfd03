"""Readers and writers of tables, operation logs and snapshots."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..operators.oplog import SCHEMA
from ..operators.relation import Database, Relation

LOG_SCHEMA = ", ".join(f"{c} {t}" for c, t in SCHEMA.items())


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A Parquet table."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def write_oplog(ops: DataFrame, path: str, doc_id: str) -> None:
    """Append operations, partitioned by document, plane-less list and kind, sorted by element within files."""
    out = ops.withColumn("doc_id", F.lit(doc_id)).withColumn("part_list", F.col("list_key"))
    out.repartition("part_list").sortWithinPartitions("eid", "seq").write.mode("append").partitionBy("doc_id", "part_list").parquet(path)


def read_oplog(spark: SparkSession, path: str, doc_id: str, list_key: str | None = None) -> DataFrame:
    """Operations of a document; only the partitions asked for are listed and read."""
    df = spark.read.parquet(path).where(F.col("doc_id") == doc_id)
    if list_key is not None:
        df = df.where(F.col("part_list") == list_key)
    return df.select(*SCHEMA)


def write_jsonl(ops: DataFrame, path: str) -> None:
    """Operations as JSON lines."""
    ops.write.mode("overwrite").json(path)


def read_jsonl(spark: SparkSession, path: str) -> tuple[DataFrame, DataFrame]:
    """(operations, lines that are none)."""
    schema = T._parse_datatype_string(LOG_SCHEMA + ", _corrupt string")
    df = spark.read.schema(schema).option("columnNameOfCorruptRecord", "_corrupt").json(path)
    bad = F.col("_corrupt").isNotNull() | F.col("op_id").isNull()
    return df.where(~bad).select(*SCHEMA), df.where(bad).select("_corrupt")


def write_snapshot(db: Database, path: str, seq: int) -> None:
    """Tables of a state as of a sequence number, sorted by element so that files have narrow ID ranges."""
    for name, r in db.tables.items():
        r.select().repartitionByRange("__eid").sortWithinPartitions("__eid").write.mode("overwrite").parquet(f"{path}/seq={seq}/{name}")


def read_snapshot(spark: SparkSession, path: str, seq: int, like: Database) -> Database:
    """The state as of a sequence number, with the types of ``like``."""
    return Database({n: Relation(spark.read.parquet(f"{path}/seq={seq}/{n}"), r.fields) for n, r in like.tables.items()})


def vacuum(db: Database, oldest_fork: int, dropped_at: DataFrame) -> Database:
    """Without tombstones that no branch can refer to: dropped (__eid, seq) before the oldest living fork."""
    out = db
    old = dropped_at.where(F.col("seq") < oldest_fork).select("__eid")
    for n, r in db.tables.items():
        out = out.put(**{n: Relation(r.df.join(old, "__eid", "left_anti"), r.fields)})
    return out


def export_table(df: DataFrame, path: str, kind: str = "parquet") -> None:
    """A result as parquet, json, csv or orc."""
    df.write.mode("overwrite").format(kind).option("header", True).save(path)
