"""Column functions and SQL registration."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import pandas_udf, udtf

from ..operators.relation import EID, Database


def format_path(*parts: Column) -> Column:
    """A path as one string; the empty path is a single dot."""
    text = F.concat_ws(".", *parts)
    return F.when(text == "", F.lit(".")).otherwise(text)


def parse_path(path: Column) -> Column:
    """IDs of a path string."""
    return F.when(path == ".", F.array().cast("array<string>")).otherwise(F.split(path, r"\."))


def _winner(side: pd.Series, seq: pd.Series) -> pd.Series:
    return side.astype("int64") * (1 << 40) + seq.astype("int64")


def _merge_cells(rank: pd.Series, value: pd.Series) -> float:
    return float(value.iloc[int(rank.to_numpy().argmax())])


def winner(side: Column | str, seq: Column | str) -> Column:
    """Rank of a write in a merge: the transferred side (1) wins, then the later. The escape hatch; columns do the same."""
    return pandas_udf(_winner, "bigint")(side, seq)


def merge_cells(rank: Column | str, value: Column | str) -> Column:
    """Grouped aggregate: the value of the greatest rank."""
    return pandas_udf(_merge_cells, "double")(rank, value)


class CellHistory:
    """Table function: the writes of one cell (a list of (seq, value)) with their number."""

    def eval(self, writes):
        for i, (seq, value) in enumerate(sorted((w["seq"], w["value"]) for w in writes)):
            yield seq, i + 1, value


def register(spark: SparkSession, name: str, db: Database, log: DataFrame | None = None) -> None:
    """Views ``<name>__<table>`` of live rows and ``<name>__oplog``, and the SQL functions ``winner``, ``merge_cells``, ``cell_history``."""
    for t in db.tables:
        db.export(t).createOrReplaceTempView(f"{name}__{t}")
    if log is not None:
        log.createOrReplaceTempView(f"{name}__oplog")
    spark.udf.register("winner", pandas_udf(_winner, "bigint"))
    spark.udf.register("merge_cells", pandas_udf(_merge_cells, "double"))
    spark.udtf.register("cell_history", udtf(CellHistory, returnType="seq bigint, step int, value double"))


__all__ = ["CellHistory", "EID", "format_path", "merge_cells", "parse_path", "register", "winner"]
