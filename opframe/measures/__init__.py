"""Counts that make the method's qualitative claims measurable."""

from __future__ import annotations

import time
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import oplog
from ..operators.forward import settled

#: Case studies: what they are about, the verdict of the method as published, and ours. Fixed values.
COVERAGE = [
    (1, "multiplicity change in a schema", "solved", "solved"),
    (2, "blank on delete", "refused", "both behaviours"),
    (3, "extract an entity", "solved", "solved"),
    (4, "restructure nested records", "solved", "solved"),
    (5, "divergence control for an extracted entity", "partial", "both policies"),
    (6, "decompose with IDs", "solved", "solved"),
    (7, "code co-evolution", "partial", "select and join"),
    (8, "schema evolution with copies and predicates", "unsupported", "extension"),
    (9, "structured edits of text", "solved by matching", "solved by matching"),
    (10, "language-level problems", "unsupported", "out of scope"),
]


def coverage(spark: SparkSession, runs: dict[int, tuple[DataFrame, DataFrame, list[str]]]) -> DataFrame:
    """case_no, topic, published, ours, rows, faithful: our verdict is given up where a case's run (result, intended, key) has a row that is not as intended.

    Cases without a run have no rows.
    """
    said, out = spark.createDataFrame(COVERAGE, "case_no int, topic string, published string, ours string"), None
    for n, (result, intended, key) in runs.items():
        # a case at a time: the plan of all together takes more of the driver than any of them
        row = settled(_agreement(result, intended, key).select(F.lit(n).alias("case_no"), "rows", "faithful"), "case")
        out = row if out is None else out.unionByName(row)
    ours = F.when(F.col("rows") != F.col("faithful"), "not as intended").otherwise(F.col("ours"))
    return said.join(out, "case_no", "left").select("case_no", "topic", "published", ours.alias("ours"), "rows", "faithful")


def diff_sizes(shared: DataFrame, left: DataFrame, right: DataFrame) -> DataFrame:
    """Operations in each branch: as recorded, simplified first, and after the loop to the fixpoint."""
    raw = left.agg(F.count(F.lit(1)).alias("left_ops")).crossJoin(right.agg(F.count(F.lit(1)).alias("right_ops"))).withColumn("method", F.lit("raw"))
    c = oplog.optimised_cells(shared, left, right)
    wrote = lambda ops, n: ops.select(*[F.coalesce(F.col(x), F.lit("")).alias(x) for x in oplog.CELL]).distinct().withColumn(n, F.lit(1))
    flags = c.join(wrote(left, "wl"), oplog.CELL, "left").join(wrote(right, "wr"), oplog.CELL, "left")
    differ = ~F.col("la").eqNullSafe(F.col("ra"))
    one = flags.agg(
        F.count(F.when(differ & F.col("wl").isNotNull(), 1)).alias("sl"), F.count(F.when(differ & F.col("wr").isNotNull(), 1)).alias("sr"), F.count(F.when(F.col("keep_left"), 1)).alias("ll"), F.count(F.when(F.col("keep_right"), 1)).alias("lr")
    )
    rest = one.select(F.explode(F.array(F.struct(F.lit("simplify_first").alias("method"), F.col("sl").alias("left_ops"), F.col("sr").alias("right_ops")), F.struct(F.lit("loop").alias("method"), F.col("ll").alias("left_ops"), F.col("lr").alias("right_ops")))).alias("x")).select("x.*")
    return raw.select("method", "left_ops", "right_ops").unionByName(rest)


def transfer_rate(moved: DataFrame, blocked: DataFrame) -> DataFrame:
    """kind, moved, blocked operations."""
    a = moved.groupBy("kind").agg(F.count(F.lit(1)).alias("moved"))
    b = blocked.groupBy("kind").agg(F.count(F.lit(1)).alias("blocked"))
    return a.join(b, "kind", "full").select("kind", F.coalesce("moved", F.lit(0)).alias("moved"), F.coalesce("blocked", F.lit(0)).alias("blocked"))


def intended_cells(shared: DataFrame, left: DataFrame, right: DataFrame) -> DataFrame:
    """(eid, fid, val_n) that a merge intends, straight from the log: the last left write, else the last right one, else the last shared one."""
    cols = ["eid", "fid", "seq", "val_n"]
    rows = [x.select(F.lit(i).alias("side"), *cols) for i, x in enumerate((shared, right, left))]
    every = rows[0].unionByName(rows[1]).unionByName(rows[2])
    return every.groupBy("eid", "fid").agg(F.max_by("val_n", F.struct("side", "seq")).alias("val_n"))


def merge_fidelity(intended: DataFrame, transferred: DataFrame, merged: DataFrame, key: list[str]) -> DataFrame:
    """method, rows, faithful: cells (``key``, v) of each method that equal the intended ones; a cell that only one of them has is not faithful."""
    out = []
    for method, result in (("transfer", transferred), ("three_way", merged)):
        want = intended.select(*key, F.col("v").alias("want"), F.lit(True).alias("due"))
        both = want.join(result.select(*key, F.col("v").alias("got"), F.lit(True).alias("found")), key, "full")
        same = F.col("due") & F.col("found") & F.col("want").eqNullSafe(F.col("got"))
        out.append(both.agg(F.count(F.lit(1)).alias("rows"), F.count(F.when(same, 1)).alias("faithful")).withColumn("method", F.lit(method)))
    return out[0].unionByName(out[1]).select("method", "rows", "faithful")


def order_errors(order: DataFrame, intended: DataFrame, by: list[str]) -> DataFrame:
    """One row: neighbours (a, b) that the intended order has and ``order`` has not."""
    return intended.join(order, by, "left_anti").agg(F.count(F.lit(1)).alias("errors"))


def roundtrip(sent: DataFrame, returned: DataFrame) -> DataFrame:
    """ops, same: operations that come back from the other side as they were."""
    back = returned.select("op_id", *[F.col(c).alias(f"r_{c}") for c in ("list_key", "eid", "fid", "sub", "val_s", "val_n")])
    both = sent.join(back, "op_id", "left")
    equal = F.lit(True)
    for c in ("list_key", "eid", "fid", "sub", "val_s", "val_n"):
        equal = equal & F.col(c).eqNullSafe(F.col(f"r_{c}"))
    return both.agg(F.count(F.lit(1)).alias("ops"), F.count(F.when(equal, 1)).alias("same"))


def commutes(one_way: DataFrame, other_way: DataFrame) -> DataFrame:
    """One row: whether both ways around a square end in the same rows."""
    a, b = oplog.fingerprint(one_way), oplog.fingerprint(other_way)
    return a.select(F.struct("*").alias("a")).crossJoin(b.select(F.struct("*").alias("b"))).select(F.col("a").eqNullSafe(F.col("b")).alias("commutes"))


def closure_size(ops: DataFrame) -> DataFrame:
    """op_id, needs: how many operations each needs, directly or through others; operations that need none are left out.

    Rounds are as many as dependencies are deep; a round is one join.
    """
    edges = settled(oplog.dependencies(ops), "edges")
    step, seen = edges, edges
    while True:
        step = step.join(edges.select(F.col("op_id").alias("dep_id"), F.col("dep_id").alias("__next")), "dep_id").select("op_id", F.col("__next").alias("dep_id"))
        step = settled(step.distinct().join(seen, ["op_id", "dep_id"], "left_anti"), "closure")
        if not step.limit(1).count():
            return seen.groupBy("op_id").agg(F.count(F.lit(1)).alias("needs"))
        seen = seen.unionByName(step)


def _agreement(a: DataFrame, b: DataFrame, key: list[str]) -> DataFrame:
    """One row (rows, faithful): rows by key of either side, and those that both have alike."""
    rest = sorted(c for c in a.columns if c not in key)
    x = a.select(*key, F.struct(*rest).alias("__a"))
    both = x.join(b.select(*key, F.struct(*rest).alias("__b")), key, "full")
    return both.agg(F.count(F.lit(1)).alias("rows"), F.count(F.when(F.col("__a").eqNullSafe(F.col("__b")), 1)).alias("faithful"))


def undo_fidelity(after_delta: DataFrame, scrubbed: DataFrame, key: list[str]) -> DataFrame:
    """Rows after an undo delta that equal those of the history without the undone operations."""
    return _agreement(after_delta, scrubbed, key)


def rewrite_fidelity(rewritten: DataFrame, by_hand: DataFrame, key: list[str]) -> DataFrame:
    """Rows of a rewritten formula that equal those of the query written by hand."""
    return _agreement(rewritten, by_hand, key)


def correspondence_accuracy(found: DataFrame, truth: DataFrame) -> DataFrame:
    """cells, found: true counterparts (cell, counterpart), and those that probes landed on and nowhere else."""
    both = truth.select("cell", "counterpart", F.lit(1).alias("t")).join(found.distinct().select("cell", "counterpart", F.lit(1).alias("f")), ["cell", "counterpart"], "full")
    return both.agg(F.count(F.lit(1)).alias("cells"), F.count(F.when(F.col("t").isNotNull() & F.col("f").isNotNull(), 1)).alias("found"))


def updatability(accepted: DataFrame, blocked: DataFrame) -> DataFrame:
    """kind, offered, accepted: edits of a view, and those that reach its base."""
    rows = accepted.select("kind", F.lit(1).alias("ok")).unionByName(blocked.select("kind", F.lit(0).alias("ok")))
    return rows.groupBy("kind").agg(F.count(F.lit(1)).alias("offered"), F.sum("ok").alias("accepted"))


def shared_size(shared: DataFrame, left: DataFrame, right: DataFrame) -> DataFrame:
    """left_shared, right_shared: operations of each branch that optimising the diff moves into the shared history."""
    sizes = diff_sizes(shared, left, right)
    one = sizes.agg(*[F.max(F.when(F.col("method") == m, F.col(f"{s}_ops"))).alias(f"{m}_{s}") for m in ("raw", "loop") for s in ("left", "right")])
    return one.select((F.col("raw_left") - F.col("loop_left")).alias("left_shared"), (F.col("raw_right") - F.col("loop_right")).alias("right_shared"))


def engine_cost(spark: SparkSession, name: str, run, ops: int) -> DataFrame:
    """One row (name, ops, seconds, ops_per_second, jobs, stages) of an action, from Spark's status tracker."""
    group = f"cost-{uuid.uuid4().hex[:8]}"
    spark.sparkContext.setJobGroup(group, name)
    began = time.time()
    run()
    took = time.time() - began
    tracker = spark.sparkContext.statusTracker()
    spark.sparkContext.setLocalProperty("spark.jobGroup.id", None)
    jobs = tracker.getJobIdsForGroup(group)
    stages = sum(len(tracker.getJobInfo(j).stageIds) for j in jobs if tracker.getJobInfo(j))
    return spark.createDataFrame([(name, ops, took, ops / max(took, 1e-9), len(jobs), stages)], "name string, ops bigint, seconds double, ops_per_second double, jobs int, stages int")
