"""Structured Streaming of operation logs: windows, redelivery, conflict state and continuous sync."""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..model.ops import Op
from ..operators import oplog
from ..operators.forward import shared_base
from ..operators.relation import Database


def shared_folder(spark: SparkSession, name: str) -> str:
    """A fresh folder that driver and executors share."""
    return f"{shared_base(spark)}/opframe-{name}-{uuid.uuid4().hex[:12]}"


def read_events(spark: SparkSession, path: str, files: int = 1) -> DataFrame:
    """A stream of the ``events`` table's files; the watermark needs a timestamp with a zone."""
    schema = "event_id bigint, ts timestamp_ntz, user_id bigint, event_type string, value double, props string"
    stream = spark.readStream.schema(schema).option("maxFilesPerTrigger", files).parquet(path)
    return stream.withColumn("at", F.col("ts").cast("timestamp"))


def drain(stream: DataFrame, mode: str = "append") -> DataFrame:
    """All that a stream gives for what is there now, as a table in the shared folder (complete mode keeps the last batch)."""
    spark = stream.sparkSession
    out, state = shared_folder(spark, "stream"), shared_folder(spark, "stream-state")

    def put(batch: DataFrame, batch_id: int) -> None:
        # one folder for each batch, overwritten on a retry: each batch counts once
        where = out if mode == "complete" else f"{out}/batch={batch_id}"
        batch.write.mode("overwrite").parquet(where)

    query = stream.writeStream.outputMode(mode).option("checkpointLocation", state).trigger(availableNow=True).foreachBatch(put).start()
    query.awaitTermination()
    return spark.read.schema(stream.schema).parquet(out).select(*stream.columns) if mode == "complete" else spark.read.parquet(out).select(*stream.columns)


def windows(events: DataFrame, size: str, slide: str | None = None, late: str = "3650 days") -> DataFrame:
    """Operations of each window and kind."""
    w = F.window("at", size, slide) if slide else F.window("at", size)
    return events.withWatermark("at", late).groupBy(w, "event_type").agg(F.count(F.lit(1)).alias("n")).select(F.col("window.start").cast("timestamp_ntz").alias("start"), "event_type", "n")


def sessions(events: DataFrame, gap: str, late: str = "3650 days") -> DataFrame:
    """Runs of a user's events without a longer pause."""
    grouped = events.withWatermark("at", late).groupBy(F.session_window("at", gap), "user_id").agg(F.count(F.lit(1)).alias("n"))
    return grouped.select(F.col("session_window.start").cast("timestamp_ntz").alias("start"), "user_id", "n")


def without_redelivery(events: DataFrame, key: str = "event_id", late: str = "3650 days") -> DataFrame:
    """Each operation once, however often it is delivered within the watermark."""
    return events.withWatermark("at", late).dropDuplicatesWithinWatermark([key])


def follow_links(events: DataFrame, table: DataFrame, link: str, key: str) -> DataFrame:
    """Stream-static join: each operation with the row that its link names now (a forward map, a dimension)."""
    return events.join(table, events[link] == table[key])


def match_origins(sent: DataFrame, arrived: DataFrame, within: str, late: str = "3650 days") -> DataFrame:
    """Stream-stream join of transferred operations (origin, at2) with their origins (event_id, at) up to ``within`` before them."""
    a, b = sent.withWatermark("at", late), arrived.withWatermark("at2", late)
    return a.join(b, F.expr(f"event_id = origin and at2 >= at and at2 <= at + interval {within}"))


def latest_cells(ops: DataFrame) -> DataFrame:
    """Updates (u, f, seq, v) of the last write of each cell; late and shuffled writes do no harm, as the sequence decides."""

    def step(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        seq, v = state.get if state.exists else (-1, 0)
        for b in batches:
            top = b.loc[b["seq"].idxmax()]
            if top["seq"] > seq:
                seq, v = int(top["seq"]), int(top["v"])
        state.update((seq, v))
        yield pd.DataFrame({"u": [key[0]], "f": [key[1]], "seq": [seq], "v": [v]})

    kind = "u bigint, f string, seq bigint, v bigint"
    return ops.groupBy("u", "f").applyInPandasWithState(step, kind, "seq bigint, v bigint", "update", GroupStateTimeout.NoTimeout)


def auto_sync(stream: DataFrame, over: list[Op], before: Database, apply: Callable[[DataFrame, int], None]):
    """Carry each incoming batch of operations across a fixed line of type operations and hand it on.

    A type operation starts a new epoch: stop, append it to ``over``, start again from the
    checkpoint.
    """

    def step(batch: DataFrame, batch_id: int) -> None:
        ops, db = batch, before
        for op in over:
            ops = oplog.forward(ops, op, db)
            db = db.apply(op)
        apply(ops, batch_id)

    state = shared_folder(stream.sparkSession, "autosync")
    return stream.writeStream.option("checkpointLocation", state).trigger(availableNow=True).foreachBatch(step).start()


def slices(df: DataFrame, by: Column, parts: int) -> str:
    """A folder with a table cut into files, as a source of streams."""
    path = shared_folder(df.sparkSession, "slices")
    df.withColumn("__p", F.pmod(by, F.lit(parts))).repartition(parts, "__p").drop("__p").write.parquet(path)
    return path
