"""Deduplication by moves, and forwarding of links along them."""

from __future__ import annotations

import atexit
import uuid
from dataclasses import replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model.types import LinkT
from .relation import DEAD, EID, ORD, Database, Relation

#: Rows under which a counted forward map is broadcast.
BROADCAST_ROWS = 500_000


def dedupe_moves(r: Relation, keys: tuple[str, ...]) -> DataFrame:
    """(src, dst): a move of every row onto the least row, in list order, that equals it on the keys.

    An aggregate and a join rather than a window: a class may hold a third of all rows.
    """
    live = r.live().select(EID, ORD, *keys)
    first = live.groupBy(*keys).agg(F.min(F.struct(ORD, EID)).alias("__m"))
    cond = [live[k].eqNullSafe(first[k]) for k in keys]
    return live.join(first, cond).where(F.col(EID) != F.col(f"__m.{EID}")).select(F.col(EID).alias("src"), F.col(f"__m.{EID}").alias("dst"))


def resolve(moves: DataFrame) -> DataFrame:
    """(eid, root): where chains of moves end, by pointer doubling; rounds grow with the logarithm of the longest chain.

    A source moved more than once follows its least destination; a cycle raises an error.
    """
    now = settled(moves.groupBy(F.col("src").alias("eid")).agg(F.min("dst").alias("root")), "moves")
    # a chain of n moves is resolved in log2(n) rounds; a cycle never is
    for _ in range(now.count().bit_length() + 2):
        step = now.select(F.col("eid").alias("root"), F.col("root").alias("next"))
        new = settled(now.join(step, "root", "left").select("eid", F.coalesce("next", "root").alias("root"), F.col("next").isNotNull().alias("moved")), "moves")
        if new.where("eid = root").limit(1).count():
            raise ValueError("moves form a cycle")
        if not new.where("moved").limit(1).count():
            return new.select("eid", "root")
        now = new.select("eid", "root")
    raise ValueError("moves form a cycle")


def shared_base(spark) -> str:
    """The folder that driver and executors share; a local one only on a local master that names none."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("spark.checkpoint.dir must name a folder that all executors share")
        import tempfile

        base = tempfile.mkdtemp(prefix="opframe-")
    return base.rstrip("/")


_settled: list[tuple] = []


def settled(df: DataFrame, name: str = "table") -> DataFrame:
    """``df`` written once to the shared folder and read back: later plans start there, with its size known, and survive lost executors.

    What is used many times (a log under transfer, an imported base document, a forward map) is
    computed once. ``release`` deletes what was written.
    """
    path = f"{shared_base(df.sparkSession)}/opframe-{name}-{uuid.uuid4().hex[:12]}"
    df.write.parquet(path)
    _settled.append((df.sparkSession, path))
    return df.sparkSession.read.schema(df.schema).parquet(path)


@atexit.register
def release() -> None:
    """Delete all that ``settled`` wrote; no DataFrame made from it may be used afterwards."""
    while _settled:
        spark, path = _settled.pop()
        try:
            p = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
            p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(p, True)
        except Exception:  # the session is gone: its own clean-up has the folder
            return


def merge(db: Database, table: str, moves: DataFrame, flat: bool = True) -> Database:
    """Drop the moved rows of a table and forward every link to them.

    ``flat``: destinations are never moved themselves (as a dedupe plan's are), so the moves
    are the forward map; otherwise chains are resolved first.
    """
    fwd = moves.select(F.col("src").alias("eid"), F.col("dst").alias("root")) if flat else resolve(moves)
    r = db[table]
    gone = r.df.join(fwd.select(F.col("eid").alias(EID), F.lit(True).alias("__gone")), EID, "left")
    df = gone.withColumn(DEAD, F.col(DEAD) | F.coalesce("__gone", F.lit(False))).drop("__gone")
    out = db.put(**{table: replace(r, df=df)})
    for name, other in out.tables.items():
        for f in other.fields:
            if isinstance(f.type, LinkT) and f.type.target == (table,):
                other = replace(other, df=forward_links(other.df, f.fid, fwd))
        out = out.put(**{name: other})
    return out


def forward_links(df: DataFrame, link: str, fwd: DataFrame) -> DataFrame:
    """A link column that follows the forward map."""
    side = fwd.select(F.col("eid").alias("__f"), F.col("root").alias("__r"))
    return df.join(side, df[link] == F.col("__f"), "left").withColumn(link, F.coalesce("__r", link)).drop("__f", "__r")


def undo_merge(before: Database, after: Database, table: str, moves: DataFrame, seq: int = 0) -> DataFrame:
    """Log rows that take a merge by moves back: moved rows live again, and links that still are where the merge put them go to where they were.

    ``before``: the database that the merge ran on; ``after``: the present one. Links that were
    set anew since are kept.
    """
    from . import oplog

    spark = moves.sparkSession
    rows = oplog.log(moves, "restore_elem", table, seq=F.lit(seq), arg_eid=F.col("src"), undo_of=F.concat(F.lit("merge:"), "src"))
    for name, r in before.tables.items():
        for f in r.fields:
            if isinstance(f.type, LinkT) and f.type.target == (table,):
                old = r.df.select(F.col(EID).alias("__row"), F.col(f.fid).alias("src")).join(moves.select("src", "dst"), "src")
                now = after[name].df.select(F.col(EID).alias("__row"), F.col(f.fid).alias("__now"))
                back = old.join(now, "__row").where(F.col("__now") == F.col("dst"))
                rows = rows.unionByName(oplog.log(back, "set_link", name, seq=F.lit(seq), eid=F.col("__row"), fid=F.lit(f.fid), val_s=F.col("src"), undo_of=F.concat(F.lit("merge:"), "src")))
    return rows if rows is not None else spark.createDataFrame([], "seq bigint")


def reconcile(r: Relation, classes: DataFrame, keys: tuple[str, ...]) -> DataFrame:
    """(src, dst, was): classes (eid, root) regrouped after writes to their members, with the class that each member was in before.

    Members that still agree with their old representative stay with it; the others form a class for each distinct content. Two aggregates and two joins.
    """
    rows = r.df.select(EID, ORD, *keys).join(classes.select(F.col("eid").alias(EID), F.col("root").alias("was")), EID)
    own = r.df.select(F.col(EID).alias("was"), *[F.col(k).alias(f"__{k}") for k in keys])
    same = F.lit(True)
    for k in keys:
        same = same & F.col(k).eqNullSafe(F.col(f"__{k}"))
    marked = rows.join(own, "was").withColumn("__stays", same)
    first = marked.where("not __stays").groupBy("was", *keys).agg(F.min(F.struct(ORD, EID))[EID].alias("__dst")).select(F.col("was").alias("__w"), "__dst", *[F.col(k).alias(f"__k_{k}") for k in keys])
    meet = (F.col("was") == F.col("__w")) & ~F.col("__stays")
    for k in keys:
        meet = meet & F.col(k).eqNullSafe(F.col(f"__k_{k}"))
    return marked.join(first, meet, "left").select(F.col(EID).alias("src"), F.coalesce("__dst", "was").alias("dst"), "was")
