"""Connected components over link tables, without collecting links or vertices."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import materialise

#: Rows of (long, long) below which a counted table is broadcast (about 16 MB); larger ones are joined by shuffle.
BROADCAST_ROWS = 500_000


def maybe_broadcast(df: DataFrame, rows: int) -> DataFrame:
    """Broadcast hint only for a table whose counted rows are within the bound."""
    return F.broadcast(df) if rows <= BROADCAST_ROWS else df


def components(links: DataFrame) -> DataFrame:
    """(id, root) of every vertex of ``links`` (u long, v long); root is the least id reachable.

    Each round hooks every vertex to its least neighbour, follows hooks once (pointer
    doubling), and contracts: links between the hooked vertices, each kept once, are the next
    round's input, so they shrink from round to round. Rounds are written to the shared
    scratch folder. An empty table gives an empty result.
    """
    edges = materialise(links.where("u <> v").select(F.least("u", "v").alias("u"), F.greatest("u", "v").alias("v")).distinct(), "links")
    found = None
    while True:
        least = edges.groupBy(F.col("v").alias("id")).agg(F.min("u").alias("to"))
        ends = edges.select(F.col("u").alias("id"), F.col("u").alias("to")).distinct()
        hooks = materialise(least.unionByName(ends).groupBy("id").agg(F.min("to").alias("to")), "hooks")
        n = hooks.count()
        if not n:
            return found if found is not None else hooks.select("id", F.col("to").alias("root"))
        far = hooks.select(F.col("id").alias("to"), F.col("to").alias("root"))
        labels = materialise(hooks.join(maybe_broadcast(far, n), "to").select("id", "root"), "labels")
        found = labels if found is None else materialise(
            found.join(maybe_broadcast(labels.select(F.col("id").alias("root"), F.col("root").alias("next")), n), "root", "left").select("id", F.coalesce("next", "root").alias("root")), "roots"
        )
        step = edges
        for c in ("u", "v"):
            step = step.join(maybe_broadcast(labels.select(F.col("id").alias(c), F.col("root").alias("r")), n), c).drop(c).withColumnRenamed("r", c)
        edges = materialise(step.where("u <> v").select(F.least("u", "v").alias("u"), F.greatest("u", "v").alias("v")).distinct(), "links")
