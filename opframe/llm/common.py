"""Shared pieces of the training-data operators: scratch tables, Arrow slices and hashed words.

Scratch tables are written below ``spark.checkpoint.dir`` as the session names it, because
that folder is the one that driver and executors share; they cut lineage the way a
checkpoint does and survive a lost executor.
"""

from __future__ import annotations

import atexit
import ctypes
import gc
import tempfile
import time
import uuid
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Text bytes that a Python worker looks at in one numpy pass.
PIECE_BYTES = 3 << 20

_made: list[tuple[SparkSession, str]] = []


def scratch_dir(spark: SparkSession, name: str) -> str:
    """A fresh folder below the session's shared checkpoint folder (a local one only where none is named)."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("spark.checkpoint.dir must name a folder that all executors share")
        base = tempfile.mkdtemp(prefix="opframe-")
    path = f"{base.rstrip('/')}/opframe-{name}-{uuid.uuid4().hex[:12]}"
    _made.append((spark, path))
    return path


def drop_scratch(spark: SparkSession, path: str) -> None:
    """Delete one scratch folder through Spark's own file system layer."""
    jvm = spark.sparkContext._jvm
    p = jvm.org.apache.hadoop.fs.Path(path)
    p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(p, True)


@atexit.register
def _drop_all() -> None:
    for spark, path in _made:
        try:
            drop_scratch(spark, path)
        except Exception:  # the session is gone: its own clean-up has the folder
            return


def materialise(df: DataFrame, name: str) -> DataFrame:
    """Write ``df`` to a scratch table and read it back."""
    spark = df.sparkSession
    path = scratch_dir(spark, name)
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def release_shuffles(spark: SparkSession) -> None:
    """Let Spark delete the shuffle files of plans that are done: it does so once their handles are collected, here first, then in the JVM."""
    for _ in range(2):
        gc.collect()
        time.sleep(0.5)  # handles are given up, and files deleted, by threads of their own
        spark.sparkContext._jvm.System.gc()
        time.sleep(0.5)


def doc_bucket(col: str, mod: int):
    """crc32 of the id written as text, modulo ``mod``; null ids count as the empty text."""
    return F.crc32(F.coalesce(F.col(col).cast("string"), F.lit("")).cast("binary")) % mod


def buffers(column) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(bytes, offsets, valid) of an Arrow string column, without copying the bytes."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if pa.types.is_large_string(column.type):
        width = np.int64
    else:
        width = np.int32
    n = len(column)
    valid = np.asarray(column.is_valid())
    if n == 0:
        return np.zeros(0, np.uint8), np.zeros(1, np.int64), valid
    _, offs, data = column.buffers()
    off = np.frombuffer(offs, dtype=width)[column.offset : column.offset + n + 1].astype(np.int64)
    raw = np.frombuffer(data, dtype=np.uint8)[off[0] : off[-1]] if data is not None and off[-1] > off[0] else np.zeros(0, np.uint8)
    return raw, off - off[0], valid


#: What a Python worker keeps from task to task, with the stage that used it last.
_kept: dict[str, tuple[int, object]] = {}


def _stage() -> int:
    context = TaskContext.get()
    return context.stageId() if context else -1


def kept(key: str, make: Callable[[], object]):
    """An object of the worker process, made once and kept while tasks of one stage follow each other."""
    if key not in _kept:
        _kept[key] = (-1, make())
    _kept[key] = (_stage(), _kept[key][1])
    return _kept[key][1]


def _release() -> None:
    """Let go of what tasks of other stages kept, so that a later stage has the memory."""
    now = _stage()
    for key in [k for k, (stage, _) in _kept.items() if stage != now]:
        del _kept[key]
    trim()


def trim() -> None:
    """Give freed memory back to the system: a worker process outlives its tasks, and its memory counts all along."""
    gc.collect()
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except (AttributeError, OSError):  # another C library
        return


def pieces(batches: Iterator[pa.RecordBatch], column: str, limit: int = PIECE_BYTES) -> Iterator[pa.RecordBatch]:
    """Cut batches at row bounds into slices of about ``limit`` text bytes; a longer text is a slice of its own."""
    _release()
    for batch in batches:
        _, off, _ = buffers(batch.column(batch.schema.get_field_index(column)))
        at, n = 0, batch.num_rows
        while at < n:
            to = max(at + 1, int(np.searchsorted(off, off[at] + limit, "right")) - 1)
            yield batch.slice(at, to - at)
            at = to


_rng = np.random.default_rng(20240607)
#: Random 64-bit value of each byte, for polynomial word hashes.
BYTE_HASH = _rng.integers(1, 2**63, size=256, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_POWER = np.uint64(0x9E3779B97F4A7C15 | 1)
_powers = np.ones(1, np.uint64)


def _power_table(n: int) -> np.ndarray:
    global _powers
    if len(_powers) < n:
        size = max(n, 2 * len(_powers), 1024)
        steps = np.full(size, _POWER, np.uint64)
        steps[0] = 1
        _powers = np.multiply.accumulate(steps)
    return _powers


def mix(h: np.ndarray) -> np.ndarray:
    """A bijective 64-bit finaliser."""
    h = h ^ (h >> np.uint64(30))
    h = h * np.uint64(0xBF58476D1CE4E5B9)
    h = h ^ (h >> np.uint64(27))
    h = h * np.uint64(0x94D049BB133111EB)
    return h ^ (h >> np.uint64(31))


def byte_table(separators: bytes | list[int], lower: bool = True) -> tuple[np.ndarray, np.ndarray]:
    """(map of bytes with A-Z lowered, flags of the bytes that belong to words)."""
    to = np.arange(256, dtype=np.uint8)
    if lower:
        to[65:91] += 32
    word = np.ones(256, bool)
    word[list(separators)] = False
    return to, word


SPACES = [0x20, *range(0x09, 0x0E)]
SPACE_TABLE = byte_table(SPACES)


def words(raw: np.ndarray, off: np.ndarray, table: tuple[np.ndarray, np.ndarray]):
    """Words of concatenated texts: (mapped bytes, starts, ends, first word of each text and the end)."""
    to, is_word = table
    low = to[raw]
    flag = is_word[low]
    if not len(raw):
        none = np.zeros(0, np.int64)
        return low, none, none, np.zeros(len(off), np.int64)
    first = np.zeros(len(raw), bool)
    first[off[:-1][off[:-1] < len(raw)]] = True
    before = np.empty_like(flag)
    before[0] = False
    before[1:] = flag[:-1]
    starts = np.flatnonzero(flag & (~before | first))
    last = np.zeros(len(raw), bool)
    ends_at = off[1:][off[1:] > 0] - 1
    last[ends_at] = True
    after = np.empty_like(flag)
    after[-1] = False
    after[:-1] = flag[1:]
    ends = np.flatnonzero(flag & (~after | last)) + 1
    return low, starts, ends, np.searchsorted(starts, off)


def hash_words(low: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """64-bit hash of each word."""
    if not len(starts):
        return np.zeros(0, np.uint64)
    lens = ends - starts
    total = int(lens.sum())
    seg = np.zeros(len(lens), np.int64)
    np.cumsum(lens[:-1], out=seg[1:])
    pos = np.arange(total, dtype=np.int64) - np.repeat(seg, lens)
    at = pos + np.repeat(starts, lens)
    part = BYTE_HASH[low[at]] * _power_table(int(lens.max()))[pos]
    return mix(np.add.reduceat(part, seg))


def ragged(starts: np.ndarray, lens: np.ndarray) -> np.ndarray:
    """Indices of consecutive runs: starts[0].., starts[1].., each of its length."""
    total = int(lens.sum())
    if not total:
        return np.zeros(0, np.int64)
    seg = np.zeros(len(lens), np.int64)
    np.cumsum(lens[:-1], out=seg[1:])
    return np.arange(total, dtype=np.int64) + np.repeat(starts - seg, lens)
