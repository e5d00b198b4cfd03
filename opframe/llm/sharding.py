"""Sharding by best-fit-decreasing bin packing (operator 7).

Groups of rows with equal texts are indivisible. They are sorted by size and counted by size;
the driver packs the counted sizes only: a run of equal groups fills the shard with the least
remaining room that holds one of them as far as it goes, then the next, just as group after
group would. That shard is found in a balanced tree. The list of sizes has a row for each
distinct size, however many groups there are. With a number of shards the capacity is the
least at which they are enough; with a capacity as few shards as it takes are opened.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import materialise
from .graph import BROADCAST_ROWS, maybe_broadcast

#: Share of all rows (1 / HEAVY) from which a group is joined by broadcast where groups are too many for that.
HEAVY = 1024


class RoomTree:
    """AVL tree of (remaining room, shard): insertion, and removal of the least room that is enough."""

    __slots__ = ("root",)

    def __init__(self) -> None:
        self.root = None

    @staticmethod
    def _h(n):
        return n[3] if n else 0

    def _fix(self, n):
        n[3] = 1 + max(self._h(n[1]), self._h(n[2]))
        lean = self._h(n[1]) - self._h(n[2])
        if lean > 1:
            if self._h(n[1][1]) < self._h(n[1][2]):
                n[1] = self._turn(n[1], 2)
            return self._turn(n, 1)
        if lean < -1:
            if self._h(n[2][2]) < self._h(n[2][1]):
                n[2] = self._turn(n[2], 1)
            return self._turn(n, 2)
        return n

    def _turn(self, n, side):
        up = n[side]
        n[side], up[3 - side] = up[3 - side], n
        n[3] = 1 + max(self._h(n[1]), self._h(n[2]))
        up[3] = 1 + max(self._h(up[1]), self._h(up[2]))
        return up

    def add(self, key: tuple[int, int]) -> None:
        """Insert a key."""

        def put(n):
            if n is None:
                return [key, None, None, 1]
            side = 1 if key < n[0] else 2
            n[side] = put(n[side])
            return self._fix(n)

        self.root = put(self.root)

    def take(self, size: int) -> tuple[int, int] | None:
        """Remove and return the least key whose room is at least ``size``; None if there is none."""
        n, best = self.root, None
        while n:
            if n[0] >= (size, -1):
                best, n = n[0], n[1]
            else:
                n = n[2]
        if best is None:
            return None

        def pop_least(n):
            if n[1] is None:
                return n[0], n[2]
            least, n[1] = pop_least(n[1])
            return least, self._fix(n)

        def drop(n):
            if best < n[0]:
                n[1] = drop(n[1])
            elif best > n[0]:
                n[2] = drop(n[2])
            elif n[1] is None or n[2] is None:
                return n[1] or n[2]
            else:
                n[0], n[2] = pop_least(n[2])
            return self._fix(n)

        self.root = drop(self.root)
        return best


def best_fit_decreasing(runs: list[tuple[int, int]], capacity: int) -> tuple[list[tuple[int, int, int]], int]:
    """((run, shard, items) in the order of items, shards opened) of runs (size, items) at a fixed capacity; sizes must fall."""
    room, out, opened = RoomTree(), [], 0
    for i, (size, items) in enumerate(runs):
        if size > capacity:
            raise ValueError("an item is larger than the capacity")
        while items:
            got = room.take(size)
            if got is None:
                got, opened = (capacity, opened), opened + 1
            # the shard with the least room that is enough stays that as it fills
            n = min(items, got[0] // size)
            out.append((i, got[1], n))
            room.add((got[0] - n * size, got[1]))
            items -= n
    return out, opened


def pack(runs: list[tuple[int, int]], shards: int) -> list[tuple[int, int, int]]:
    """(run, shard, items) so that at most ``shards`` shards hold about equal sizes; runs (size, items) of falling sizes.

    An item of more than the fair share of what is left gets a shard of its own; the others
    are packed at the least capacity found (upwards in doubling steps, then by bisection) at which the shards left are enough.
    """
    rest, left, total, out = [list(r) for r in runs], shards, sum(s * n for s, n in runs), []
    first = 0
    while left > 1 and first < len(rest) and rest[first][0] * left > total:
        out.append((first, shards - left, 1))
        total -= rest[first][0]
        left -= 1
        rest[first][1] -= 1
        if not rest[first][1]:
            first += 1
    alone, rest = shards - left, [(s, n) for s, n in rest[first:]]
    if not rest:
        return out

    def enough(capacity: int) -> bool:
        return best_fit_decreasing(rest, capacity)[1] <= left

    low = max(rest[0][0], -(-total // left))
    step, high = 1, low
    while not enough(high):
        low, high, step = high + 1, high + step, 2 * step
    while low < high:
        mid = (low + high) // 2
        if enough(mid):
            high = mid
        else:
            low = mid + 1
    return out + [(first + i, alone + k, n) for i, k, n in best_fit_decreasing(rest, high)[0]]


def _numbered(rows: DataFrame, at: str) -> tuple[DataFrame, DataFrame]:
    """(rows with ``part``, (part, before)) of a sorted, written table whose ``at`` is a monotonically increasing id; a row for each partition."""
    part = F.shiftright(at, 33).alias("part")
    sizes = rows.groupBy(part).agg(F.count(F.lit(1)).alias("n"))
    before = sizes.select("part", (F.sum("n").over(W.orderBy("part")) - F.col("n")).alias("before"))
    return rows.withColumn("part", part), before


def shard(docs: DataFrame, shards: int | None = 8, capacity: int | None = None) -> DataFrame:
    """(doc_id, size, text_crc32, shard, slot) of every row of ``docs`` (doc_id, text).

    ``shards``: that many shards of about equal sizes (unless one group alone is larger than a fair
    share). ``capacity``, with ``shards=None``: as few shards as best fit needs, none larger; a larger
    group is an error. size: UTF-8 bytes plus 1 (a null text counts as empty and shares the empty
    texts' group); rows with equal texts get one shard. slot numbers the rows of a shard from 0
    without gaps in order of doc_id, nulls first; repeated rows get a slot each. Extra columns are
    ignored. An empty table gives no rows.
    """
    spark = docs.sparkSession
    text = F.coalesce("text", F.lit("")).cast("binary")
    rows = docs.select(
        "doc_id",
        (F.length(text) + 1).cast("long").alias("size"),
        F.crc32(text).alias("text_crc32"),
        F.xxhash64(text).alias("group"),
    )
    rows = materialise(rows, "sizes")
    keys = ["group", "text_crc32", "size"]
    groups = rows.groupBy(*keys).agg(F.count(F.lit(1)).alias("rows")).withColumn("bytes", F.col("size") * F.col("rows"))
    order = [F.desc("bytes"), "group", "text_crc32", "size"]
    groups = materialise(groups.repartitionByRange(*order).sortWithinPartitions(*order).withColumn("at", F.monotonically_increasing_id()), "groups")
    runs = [(r["bytes"], r["items"]) for r in groups.groupBy("bytes").agg(F.count(F.lit(1)).alias("items")).orderBy(F.desc("bytes")).collect()]
    if capacity is not None:
        packed, _ = best_fit_decreasing(runs, capacity)
    else:
        packed = pack(runs, shards)
    # items of a run are numbered in the order of the sorted groups
    first, done, spans = [0], [0] * len(runs), []
    for _, n in runs:
        first.append(first[-1] + n)
    for i, k, n in packed:
        spans.append((runs[i][0], first[i] + done[i], first[i] + done[i] + n, k))
        done[i] += n
    schema = T.StructType([T.StructField(n, t) for n, t in (("bytes", T.LongType()), ("from", T.LongType()), ("to", T.LongType()), ("shard", T.IntegerType()))])
    table = spark.createDataFrame(spans, schema)
    numbered, before = _numbered(groups, "at")
    numbered = numbered.join(F.broadcast(before), "part").withColumn("pos", F.col("before") + F.col("at") - F.shiftleft(F.col("part"), 33))
    where = numbered.join(maybe_broadcast(table, len(spans)), "bytes").where((F.col("pos") >= F.col("from")) & (F.col("pos") < F.col("to")))
    where = materialise(where.select(*keys, "rows", "shard"), "where")
    n, total = where.count(), sum(r[0] for r in where.agg(F.coalesce(F.sum("rows"), F.lit(0))).collect())
    if n <= BROADCAST_ROWS:
        dealt = rows.join(F.broadcast(where.drop("rows")), keys)
    else:
        # at most HEAVY groups; the others are small enough to meet by shuffle
        heavy = F.broadcast(where.where(F.col("rows") * HEAVY >= total).drop("rows"))
        light = rows.join(heavy, keys, "left_anti").join(where.where(F.col("rows") * HEAVY < total).drop("rows"), keys)
        dealt = rows.join(heavy, keys).unionByName(light)
    sorted_ = dealt.select("doc_id", "size", "text_crc32", "shard").repartitionByRange("shard", "doc_id").sortWithinPartitions("shard", "doc_id", "text_crc32", "size")
    placed = materialise(sorted_.withColumn("at", F.monotonically_increasing_id()), "placed")
    part = F.shiftright("at", 33).alias("part")
    edge = placed.groupBy(part, "shard").agg(F.min("at").alias("first"), F.count(F.lit(1)).alias("n"))
    edge = edge.withColumn("before", F.sum("n").over(W.partitionBy("shard").orderBy("part")) - F.col("n"))
    edge = materialise(edge.select("part", "shard", "first", "before"), "edges")
    # rows of edge: partitions plus shards at most
    return placed.withColumn("part", part).join(maybe_broadcast(edge, edge.count()), ["part", "shard"]).select(
        "doc_id", "size", "text_crc32", "shard", (F.col("at") - F.col("first") + F.col("before")).alias("slot")
    )


def query(spark, sf_dir: str) -> DataFrame:
    """The contract's columns: ``documents`` in 8 shards under the law ``bytes``."""
    out = shard(spark.read.parquet(f"{sf_dir}/documents.parquet"), 8)
    return out.select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))
