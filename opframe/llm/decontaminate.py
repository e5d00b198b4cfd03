"""Benchmark decontamination: broadcast hash set of normalised test n-grams (operator 2).

Texts are normalised to words (A-Z lowered; digits, a-z and every non-ASCII character
belong to words). A window is ``width`` consecutive words of a benchmark item; an item with
fewer words, but not none, is one window of its own length. Workers hash every window of a
training text in one numpy pass, look it up in the broadcast set of hashes and verify hits
word by word. The set is bounded: a benchmark with more words than ``PASS_WORDS`` is scanned
in several passes of that bound each, and what the passes find is united per document.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import buffers, byte_table, hash_words, materialise, mix, pieces, words

#: Benchmark words whose windows are broadcast at once.
PASS_WORDS = 2_000_000
#: Words are runs of digits, lowered letters and bytes over 0x7F.
TABLE = byte_table([*range(0x00, 0x30), *range(0x3A, 0x61), *range(0x7B, 0x80)])
_STEP = [np.uint64((0xD6E8FEB86659FD93 * (2 * j + 1)) & (2**64 - 1) | 1) for j in range(64)]
_TABLE_BITS = 20
_SPANS = pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64())]))
_FOUND = "n_words bigint, n_hit bigint, items array<string>, spans array<struct<start: bigint, end: bigint>>"


def _windows_hash(h: np.ndarray, width: int) -> np.ndarray:
    n = len(h) - width + 1
    if n <= 0:
        return np.zeros(0, np.uint64)
    out = np.zeros(n, np.uint64)
    for j in range(width):
        out += h[j : j + n] * _STEP[j % 64] + np.uint64(j >> 6)
    return mix(out)


class Windows:
    """Windows of benchmark items: for each length, a hash filter and {words: item ids}."""

    def __init__(self, items: list[tuple[str, str | None]], width: int) -> None:
        self.exact: dict[int, dict[bytes, list[str]]] = {}
        self.hashes: dict[int, np.ndarray] = {}
        self.flags: dict[int, np.ndarray] = {}
        found: dict[int, list[np.ndarray]] = {}
        for item, text in items:
            raw = np.frombuffer((text or "").encode(), np.uint8)
            low, starts, ends, _ = words(raw, np.array([0, len(raw)]), TABLE)
            n = min(width, len(starts))
            if not n:
                continue
            tokens = [low[a:b].tobytes() for a, b in zip(starts, ends, strict=True)]
            for i in range(len(tokens) - n + 1):
                owners = self.exact.setdefault(n, {}).setdefault(b" ".join(tokens[i : i + n]), [])
                if item not in owners:
                    owners.append(item)
            found.setdefault(n, []).append(_windows_hash(hash_words(low, starts, ends), n))
        for n, hs in found.items():
            self.hashes[n] = np.unique(np.concatenate(hs))
            self.flags[n] = np.zeros(1 << _TABLE_BITS, bool)
            self.flags[n][self.hashes[n] >> np.uint64(64 - _TABLE_BITS)] = True

    def scan(self, raw: np.ndarray, off: np.ndarray):
        """(starts, ends, first word of each text, hit words, {text: item ids})."""
        low, starts, ends, bound = words(raw, off, TABLE)
        h, count = hash_words(low, starts, ends), np.diff(bound)
        text_of = np.repeat(np.arange(len(count)), count)
        delta, owners = np.zeros(len(starts) + 1, np.int32), {}
        for n, exact in self.exact.items():
            wh = _windows_hash(h, n)
            at = np.flatnonzero(self.flags[n][wh >> np.uint64(64 - _TABLE_BITS)])
            known = self.hashes[n]
            near = np.minimum(np.searchsorted(known, wh[at]), len(known) - 1)
            at = at[(known[near] == wh[at]) & (text_of[at] == text_of[at + n - 1])]
            for i in at.tolist():
                got = exact.get(b" ".join(low[a:b].tobytes() for a, b in zip(starts[i : i + n], ends[i : i + n], strict=True)))
                if got:
                    delta[i] += 1
                    delta[i + n] -= 1
                    owners.setdefault(int(text_of[i]), set()).update(got)
        return starts, ends, bound, np.cumsum(delta[:-1]) > 0, owners


def _passes(bench: DataFrame, width: int) -> list[DataFrame]:
    """Parts (item, text) of the benchmark whose windows are of bounded size; one for any usual benchmark."""
    rows = bench.where("text is not null").select(F.coalesce(F.col("item_id").cast("string"), F.lit("")).alias("item"), "text")
    # words are joined by anything else than their own characters
    total = rows.agg(F.sum(F.size(F.split("text", r"[\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+")))).first()[0] or 0
    n = -(-int(total) // PASS_WORDS) or 1
    return [rows if n == 1 else rows.where(F.pmod(F.xxhash64("item", "text"), F.lit(n)) == k) for k in range(n)]


def _windows(part: DataFrame, width: int) -> Windows:
    return Windows([(r["item"], r["text"]) for r in part.toLocalIterator()], width)


def _runs(starts: np.ndarray, ends: np.ndarray, hit: np.ndarray) -> list[tuple[int, int]]:
    """Byte ranges of maximal runs of hit words within one text."""
    edge = np.diff(np.concatenate([[0], hit.astype(np.int8), [0]]))
    return [(int(starts[a]), int(ends[b - 1])) for a, b in zip(np.flatnonzero(edge == 1), np.flatnonzero(edge == -1), strict=True)]


def scan(docs: DataFrame, bench: DataFrame, width: int = 10) -> DataFrame:
    """(doc_id, n_words, n_hit, items, spans) of every row of ``docs`` (doc_id, text).

    items: sorted ids, as strings, of the items with a window in the text; spans: byte ranges
    [start, end) of runs of hit words in the UTF-8 text. A null text has no words and no hits.
    A null item_id counts as the empty id; null item texts and items without words have no
    windows. Repeated rows are scanned each; an empty benchmark hits nothing.
    """
    parts = _passes(bench, width)
    if len(parts) > 1:
        return _united(docs, _hits(docs, parts, width))
    return _scan(docs, docs.sparkSession.sparkContext.broadcast([_windows(parts[0], width)]))


def _meet(docs: DataFrame, hits: DataFrame):
    return docs["doc_id"].eqNullSafe(hits["__id"]) & (F.xxhash64(docs["text"]) == hits["__text"])


def _hits(docs: DataFrame, parts: list[DataFrame], width: int) -> DataFrame:
    """(__id, __text, items, spans) of the kinds of rows (doc_id, text hash) with a hit, each part's windows broadcast alone."""
    found = None
    for part in parts:
        sets = docs.sparkSession.sparkContext.broadcast([_windows(part, width)])
        one = _scan(docs, sets, "__text").where("n_hit > 0").select(F.col("doc_id").alias("__id"), "__text", "items", "spans")
        one = materialise(one, "hits")
        sets.destroy()
        found = one if found is None else found.unionByName(one)
    lists = [F.array_sort(F.array_distinct(F.flatten(F.collect_set(c)))).alias(c) for c in ("items", "spans")]
    return materialise(found.groupBy("__id", "__text").agg(*lists), "united")


def _marked(b: pa.RecordBatch, text: int, spans: int):
    """(bytes, offsets, starts, ends, first word of each text, words within the text's spans) of a batch."""
    raw, off, _ = buffers(b.column(text))
    _, starts, ends, bound = words(raw, off, TABLE)
    delta = np.zeros(len(starts) + 1, np.int64)
    for k, l in enumerate(b.column(spans).to_pylist()):
        for x in l or ():
            delta[np.searchsorted(starts, off[k] + x["start"])] += 1
            delta[np.searchsorted(starts, off[k] + x["end"])] -= 1
    return raw, off, starts, ends, bound, np.cumsum(delta[:-1]) > 0


def _united(docs: DataFrame, hits: DataFrame) -> DataFrame:
    """``scan``'s rows from what the passes found."""
    kind = docs.schema["doc_id"].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in pieces(batches, "text"):
            _, off, starts, ends, bound, hit = _marked(b, 1, 3)
            total = np.concatenate([[0], np.cumsum(hit)])
            spans = [
                [{"start": s - int(off[k]), "end": e - int(off[k])} for s, e in _runs(starts[x:y], ends[x:y], hit[x:y])]
                for k, (x, y) in enumerate(zip(bound[:-1], bound[1:], strict=True))
            ]
            items = [x or [] for x in b.column(2).to_pylist()]
            yield pa.RecordBatch.from_arrays(
                [b.column(0), pa.array(np.diff(bound), pa.int64()), pa.array(total[bound[1:]] - total[bound[:-1]], pa.int64()), pa.array(items, pa.list_(pa.string())), pa.array(spans, _SPANS)],
                ["doc_id", "n_words", "n_hit", "items", "spans"],
            )

    joined = docs.select("doc_id", "text").join(hits, _meet(docs, hits), "left").select("doc_id", "text", "items", "spans")
    return joined.mapInArrow(run, f"doc_id {kind}, {_FOUND}")


def _cut_in_passes(docs: DataFrame, parts: list[DataFrame], width: int) -> DataFrame:
    """``decontaminate`` in mode "spans": texts with hits are cut and scanned again by all passes until none has any."""
    at, chars = docs.columns.index("text"), docs.columns.index("n_chars") if "n_chars" in docs.columns else None

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in pieces(batches, "text"):
            raw, off, starts, ends, bound, hit = _marked(b, at, b.num_columns - 1)
            texts, left = [], np.add.reduceat(np.append(~hit, False).astype(np.int64), bound[:-1])
            for k, (x, y) in enumerate(zip(bound[:-1], bound[1:], strict=True)):
                keep = np.ones(int(off[k + 1] - off[k]), bool)
                for s, e in _runs(starts[x:y], ends[x:y], hit[x:y]):
                    keep[s - off[k] : e - off[k]] = False
                texts.append(raw[off[k] : off[k + 1]][keep].tobytes().decode(errors="replace"))
            cols = list(b.columns[:-1])
            cols[at] = pa.array(texts, b.schema.field(at).type)
            if chars is not None:
                cols[chars] = pa.array([len(t) for t in texts], b.schema.field(chars).type)
            yield pa.RecordBatch.from_arrays(cols, b.schema.names[:-1]).filter(pa.array(left > 0))

    out, work = None, docs
    while True:
        hits = _hits(work, parts, width)
        clean = work.join(hits, _meet(work, hits), "left_anti")
        out = clean if out is None else out.unionByName(clean)
        if not hits.limit(1).count():
            return out
        work = materialise(work.join(hits, _meet(work, hits)).select(*[work[c] for c in docs.columns], "spans").mapInArrow(run, docs.schema), "cut")


def _scan(docs: DataFrame, sets, *also: str) -> DataFrame:
    """``scan`` against broadcast windows; with "__text", the hash of the text as well."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in pieces(batches, "text"):
            raw, off, _ = buffers(b.column(1))
            hit, owners = None, {}
            for w in sets.value:
                starts, ends, bound, one, found = w.scan(raw, off)
                hit = one if hit is None else hit | one
                for k, v in found.items():
                    owners.setdefault(k, set()).update(v)
            total = np.concatenate([[0], np.cumsum(hit)])
            n_hit = total[bound[1:]] - total[bound[:-1]]
            spans = [[] for _ in range(b.num_rows)]
            for k in owners:
                x, y = bound[k], bound[k + 1]
                spans[k] = [{"start": s - int(off[k]), "end": e - int(off[k])} for s, e in _runs(starts[x:y], ends[x:y], hit[x:y])]
            yield pa.RecordBatch.from_arrays(
                [
                    b.column(0),
                    pa.array(np.diff(bound), pa.int64()),
                    pa.array(n_hit, pa.int64()),
                    pa.array([sorted(owners.get(k, ())) for k in range(b.num_rows)], pa.list_(pa.string())),
                    pa.array(spans, _SPANS),
                    *b.columns[2:],
                ],
                ["doc_id", "n_words", "n_hit", "items", "spans", *also],
            )

    kind = docs.schema["doc_id"].dataType.simpleString()
    return docs.select("doc_id", "text", *[F.xxhash64("text").alias(c) for c in also]).mapInArrow(run, f"doc_id {kind}, {_FOUND}{''.join(f', {c} bigint' for c in also)}")


def _cut(text: str, sets: list[Windows]) -> tuple[str, int]:
    """The text without hit words, scanned again until none is left, and how many words stay."""
    raw = np.frombuffer(text.encode(), np.uint8)
    while True:
        hit = None
        for w in sets:
            starts, ends, bound, one, _ = w.scan(raw, np.array([0, len(raw)]))
            hit = one if hit is None else hit | one
        if not hit.any():
            return raw.tobytes().decode(errors="replace"), len(starts)
        keep = np.ones(len(raw), bool)
        for a, b in _runs(starts, ends, hit):
            keep[a:b] = False
        raw = raw[keep]


def decontaminate(docs: DataFrame, bench: DataFrame, width: int = 10, mode: str = "spans") -> DataFrame:
    """``docs`` with benchmark passages removed; same columns.

    mode "spans": runs of hit words are cut out (repeatedly, until a text has no hit), n_chars
    is set anew where it exists, and a text left without words goes. mode "documents": every
    document with a hit goes. Documents without hits come back unchanged, null texts too.
    """
    if mode not in ("spans", "documents"):
        raise ValueError(f"mode must be spans or documents, not {mode}")
    parts = _passes(bench, width)
    if len(parts) > 1 and mode == "spans":
        return _cut_in_passes(docs, parts, width)
    if len(parts) > 1:
        hits = _hits(docs, parts, width)
        return docs.join(hits, _meet(docs, hits), "left_anti")
    sets = docs.sparkSession.sparkContext.broadcast([_windows(parts[0], width)])
    at = docs.columns.index("text")
    chars = docs.columns.index("n_chars") if "n_chars" in docs.columns else None

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in pieces(batches, "text"):
            raw, off, _ = buffers(b.column(at))
            dirty: set[int] = set()
            for w in sets.value:
                dirty |= w.scan(raw, off)[4].keys()
            if not dirty:
                yield b
                continue
            if mode == "documents":
                yield b.filter(pa.array([k not in dirty for k in range(b.num_rows)]))
                continue
            texts, cols, keep = b.column(at).to_pylist(), list(b.columns), [True] * b.num_rows
            sizes = cols[chars].to_pylist() if chars is not None else None
            for k in dirty:
                texts[k], left = _cut(texts[k], sets.value)
                keep[k] = left > 0
                if sizes is not None:
                    sizes[k] = len(texts[k])
            cols[at] = pa.array(texts, b.schema.field(at).type)
            if sizes is not None:
                cols[chars] = pa.array(sizes, b.schema.field(chars).type)
            yield pa.RecordBatch.from_arrays(cols, schema=b.schema).filter(pa.array(keep))

    return docs.mapInArrow(run, docs.schema)


def query(spark, sf_dir: str) -> DataFrame:
    """The contract's columns for ``documents`` against ``benchmark``, 10-word windows."""
    found = scan(spark.read.parquet(f"{sf_dir}/documents.parquet"), spark.read.parquet(f"{sf_dir}/benchmark.parquet"), 10)
    return found.select(
        "doc_id",
        "n_words",
        "n_hit",
        F.size("items").cast("long").alias("n_items"),
        F.sha2(F.array_join("items", ","), 256).alias("items_sha256"),
        (F.col("n_hit") > 0).alias("contaminated"),
    )


_WORD = r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+"
_LOWER = "translate(text, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"
ORACLE = rf"""
with d as (select doc_id, coalesce(regexp_extract_all({_LOWER}, '{_WORD}'), []) as w from documents),
b as (select cast(item_id as varchar) as item, regexp_extract_all({_LOWER}, '{_WORD}') as w from benchmark where text is not null),
wins as (
  select distinct item, k, list_slice(w, i, i + k - 1) as win
  from (select item, w, least(10, len(w)) as k, unnest(range(1, len(w) - least(10, len(w)) + 2)) as i from b where len(w) > 0)
),
pos as (select doc_id, k, i, list_slice(w, i, i + k - 1) as win
  from (select doc_id, w, k, unnest(range(1, len(w) - k + 2)) as i from d, (select distinct k from wins))),
hits as (select pos.doc_id, pos.k, pos.i, wins.item from pos join wins on pos.k = wins.k and pos.win = wins.win),
covered as (select doc_id, count(*) as n from (select distinct doc_id, unnest(range(i, i + k)) as p from hits) group by doc_id),
owners as (select doc_id, count(*) as n, string_agg(item, ',' order by item) as items from (select distinct doc_id, item from hits) group by doc_id)
select d.doc_id, cast(len(d.w) as bigint) as n_words, cast(coalesce(covered.n, 0) as bigint) as n_hit,
  cast(coalesce(owners.n, 0) as bigint) as n_items, sha256(coalesce(owners.items, '')) as items_sha256, coalesce(covered.n, 0) > 0 as contaminated
from d left join covered on covered.doc_id = d.doc_id left join owners on owners.doc_id = d.doc_id
"""
