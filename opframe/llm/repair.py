"""Token-id output in Re-Pair compressed shards with random access (operator 8).

Documents are dealt to shards in ascending doc_id order and encoded there with a public
tokenizer. A shard replaces frequent pairs of neighbouring ids by nonterminals, round after
round until none is left, and stores the rules, each rule's expansion length, the compressed sequence and where
documents begin. A document is decoded alone: expansion lengths, summed along the sequence,
lead to the symbol that covers its first id.

A shard is one row of a Parquet dataset (so writes are committed whole or not at all, on any
file system that Spark reaches); ``payload`` is a binary record of the layout in
``pack_shard``.
"""

from __future__ import annotations

import struct
import zlib
from collections.abc import Iterator
from itertools import chain

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import buffers, kept, materialise, mix, pieces, ragged, scratch_dir

#: Ids after which a shard is closed; a longer document is a shard of its own.
SHARD_IDS = 1 << 20
#: Least count of a replaced pair: a rule takes 12 bytes of the record and saves 4 for each occurrence, so a rarer pair would make it longer.
LEAST_COUNT = 4
#: Hash slots that tell which pairs are too rare to be counted one by one.
SLOTS = 1 << 20
MAGIC = b"RPID1\0\0\0"
#: Text bytes that are encoded in one pass.
PASS_BYTES = 12 << 20
#: Distinct words kept encoded by a worker; past it the table starts anew (results do not depend on it).
CACHE_WORDS = 2_000_000


def _byte_alphabet() -> str:
    """The byte-level alphabet: printable bytes stand for themselves, the others for characters from 256 on."""
    own = {*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)}
    others = iter(range(256, 512))
    return "".join(chr(b) if b in own else chr(next(others)) for b in range(256))


#: Words of these characters only are in normal form C, and each character is lowered by itself to one other.
_LATIN = r"^[\x00-\x{12F}\x{131}-\x{24F}\x{1E00}-\x{1EFF}]+$"
_MARKS = ".,;:!?"


class WordEncoder:
    """Encodes texts with a ``tokenizers`` file of byte-level BPE on lowered words, each distinct word once.

    The pre-tokenizer never joins characters across a blank, tab or line end, so the ids of a
    text are those of its words one after another; nor does it join a letter with the mark that
    follows it. A word of Latin letters, marks after it or not, is therefore lowered, mapped to
    the byte alphabet and given to the library's BPE model; every other word goes through the
    library's whole pipeline. Words are split, told apart and lowered by Arrow kernels. Tests
    hold the result against the whole pipeline.
    """

    def __init__(self, path: str) -> None:
        from tokenizers import Tokenizer

        self.tok = Tokenizer.from_file(path)
        self.alphabet = _byte_alphabet()
        self._clear()

    def _clear(self) -> None:
        # words met so far and the run of each, letters first, others second
        self.known = [pa.array([], pa.string()), pa.array([], pa.string())]
        self.run_of = [np.zeros(0, np.int64), np.zeros(0, np.int64)]
        self.ids = np.zeros(1 << 20, np.uint32)
        self.used = 0
        self.start = np.zeros(1 << 18, np.int64)
        self.len = np.zeros(1 << 18, np.int64)
        self.runs = 1  # run 0 is empty

    def _store(self, ids: np.ndarray, lens: np.ndarray) -> int:
        """Append runs of ids; the number of the first."""
        while self.used + len(ids) > len(self.ids):
            self.ids = np.concatenate([self.ids, np.zeros_like(self.ids)])
        while self.runs + len(lens) > len(self.start):
            self.start = np.concatenate([self.start, np.zeros_like(self.start)])
            self.len = np.concatenate([self.len, np.zeros_like(self.len)])
        first = self.runs
        self.ids[self.used : self.used + len(ids)] = ids
        self.len[first : first + len(lens)] = lens
        self.start[first : first + len(lens)] = self.used + np.cumsum(lens) - lens
        self.used += len(ids)
        self.runs += len(lens)
        return first

    def _numbers(self, names: pa.Array, kind: int) -> np.ndarray:
        """Run number of each of the distinct names (kind 0: letters only, 1: others); unknown ones are encoded."""
        at = np.asarray(pc.fill_null(pc.index_in(names, value_set=self.known[kind]), -1), np.int64)
        got = np.append(self.run_of[kind], 0)[at]
        missing = np.flatnonzero(at < 0)
        if len(missing):
            fresh = names.take(pa.array(missing))
            if kind == 0:
                tokenize, alphabet = self.tok.model.tokenize, self.alphabet
                runs = [[x.id for x in tokenize(w if w.isascii() else "".join([alphabet[c] for c in w.encode()]))] for w in fresh.to_pylist()]
                lens = np.fromiter(map(len, runs), np.int64, len(runs))
                ids = np.fromiter(chain.from_iterable(runs), np.uint32, int(lens.sum()))
            else:
                whole = self.tok.encode(fresh.to_pylist(), is_pretokenized=True, add_special_tokens=False)
                ids = np.array(whole.ids, np.uint32)
                lens = np.bincount(np.array(whole.word_ids, np.int64), minlength=len(fresh))
            own = np.arange(len(lens)) + self._store(ids, lens)
            got[missing] = own
            self.known[kind] = pa.concat_arrays([self.known[kind], fresh])
            self.run_of[kind] = np.append(self.run_of[kind], own)
        return got

    def encode(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """(ids of all texts, how many each has)."""
        if sum(map(len, self.known)) > CACHE_WORDS:
            self._clear()
        plain = pc.replace_substring(pc.replace_substring(pc.fill_null(texts, ""), "\n", " "), "\t", " ")
        lists = pc.split_pattern(plain, " ")
        coded = lists.flatten().dictionary_encode()
        uniq = coded.dictionary.cast(pa.string())
        core = pc.utf8_rtrim(uniq, characters=_MARKS)
        good = np.array(pc.utf8_is_alpha(core))
        wide = np.flatnonzero(good & ~np.asarray(pc.string_is_ascii(core)))
        good[wide] = np.asarray(pc.match_substring_regex(core.take(pa.array(wide)), _LATIN))
        first, second = np.zeros(len(uniq), np.int64), np.zeros(len(uniq), np.int64)
        at = np.flatnonzero(good)
        if len(at):
            low = pc.utf8_lower(core.take(pa.array(at))).dictionary_encode()
            first[at] = self._numbers(low.dictionary, 0)[np.asarray(low.indices)]
            raw, off, _ = buffers(uniq)
            extra = np.diff(off) - np.asarray(pc.binary_length(core), np.int64)
            tailed = np.flatnonzero(good & (extra > 0))
            if len(tailed):
                size = extra[tailed]
                tails = pa.StringArray.from_buffers(
                    len(tailed), pa.py_buffer(np.concatenate([[0], np.cumsum(size)]).astype(np.int32)), pa.py_buffer(raw[ragged(off[tailed + 1] - size, size)])
                ).dictionary_encode()
                second[tailed] = self._numbers(tails.dictionary, 1)[np.asarray(tails.indices)]
        rest = np.flatnonzero(~good)
        if len(rest):
            first[rest] = self._numbers(uniq.take(pa.array(rest)), 1)
        pair = np.stack([first, second], axis=1).ravel()
        flat = self.ids[ragged(self.start[pair], self.len[pair])]
        size = self.len[first] + self.len[second]
        token = np.asarray(coded.indices)
        lens = size[token]
        total = np.concatenate([[0], np.cumsum(lens)])
        seg = np.concatenate([[0], np.cumsum(np.asarray(lists.value_lengths()))])
        return flat[ragged((np.cumsum(size) - size)[token], lens)], np.diff(total[seg])


def encoder(path: str) -> WordEncoder:
    """The worker process's encoder for a tokenizer file; its words stay known from task to task of a stage."""
    return kept(f"words:{path}", lambda: WordEncoder(path))


def _frequent(pair: np.ndarray, able: np.ndarray, least: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(positions, rank of the pair at each, distinct pairs by rank) of the pairs that ``able`` positions hold ``least`` times or more; a higher rank is a higher count."""
    at = np.flatnonzero(able)
    if len(at) > SLOTS // 4:
        # a slot's count bounds that of each of its pairs, so only pairs of full slots are told apart
        slot = (pair[at] * np.int64(0x5851F42D4C957F2D)) >> np.int64(44) & (SLOTS - 1)
        at = at[(np.bincount(slot, minlength=SLOTS) >= least)[slot]]
    coded = pa.array(pair[at]).dictionary_encode()
    which, kinds = np.asarray(coded.indices), np.asarray(coded.dictionary)
    counts = np.bincount(which, minlength=len(kinds))
    many = np.flatnonzero(counts >= least)
    # equal counts in an order that neighbours do not share, so that a repeated passage is paired up all along in one round
    by = many[np.lexsort((mix(kinds[many].view(np.uint64)), counts[many]))]
    rank = np.full(len(kinds), -1, np.int32)
    rank[by] = np.arange(len(by), dtype=np.int32)
    which = rank[which]
    return at[which >= 0], which[which >= 0], kinds[by]


def compress(ids: np.ndarray, terminals: int, least: int = LEAST_COUNT) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Re-Pair: (sequence, rules (n, 2), expansion length of each rule).

    A round counts neighbouring pairs exactly (occurrences that overlap count once) and
    replaces a pair wherever it is more frequent than the pairs it overlaps; so the most frequent
    pair goes first everywhere, and pairs that do not touch go in the same round. A pair that was
    too rare and lost no neighbour stays too rare and is not counted again. It ends when no pair
    occurs ``least`` times; 2 is the classic end. Symbol ``terminals + r`` stands for rule r.
    """
    seq = ids.astype(np.int64)
    rules = [np.zeros((0, 2), np.int64)]
    made, open_ = 0, np.ones(max(len(seq) - 1, 0), bool)
    while len(seq) >= 2 * least:
        bits = np.int64(int(terminals + made).bit_length())
        pair = (seq[:-1] << bits) | seq[1:]
        # in a run of one symbol every other pair overlaps the one before it
        alike = np.flatnonzero(pair[1:] == pair[:-1]) + 1
        able = open_
        if len(alike):
            run = np.flatnonzero(np.diff(alike, prepend=-9) != 1)
            place = np.arange(len(alike)) - np.repeat(run, np.diff(np.append(run, len(alike))))
            able = open_.copy()
            able[alike[place % 2 == 0]] = False
        at, rank, kinds = _frequent(pair, able, least)
        if not len(kinds):
            break
        left = open_ & ~able
        left[at] = True
        level = np.full(len(pair) + 2, -1, np.int32)
        level[at + 1] = rank
        top = (rank > level[at]) & (rank > level[at + 2])
        at, rank = at[top], rank[top]
        used = np.bincount(rank, minlength=len(kinds))
        keep = used[rank] >= least
        at, rank = at[keep], rank[keep]
        new = np.flatnonzero(used >= least)
        name = np.zeros(len(kinds), np.int64)
        name[new] = terminals + made + np.arange(len(new))
        rules.append(np.stack([kinds[new] >> bits, kinds[new] & ((1 << bits) - 1)], axis=1))
        made += len(new)
        seq[at] = name[rank]
        stay = np.ones(len(seq), bool)
        stay[at + 1] = False
        # pairs with a new symbol are new
        left = np.append(left, False)
        left[at] = True
        left[np.maximum(at - 1, 0)] = True
        seq, open_ = seq[stay], left[stay][:-1]
    every = np.concatenate(rules)
    size = np.ones(terminals + made, np.int64)
    done = 0
    for r in rules:
        size[terminals + done : terminals + done + len(r)] = size[r].sum(axis=1)
        done += len(r)
    return seq, every, size[terminals:]


def expand(seq: np.ndarray, rules: np.ndarray, terminals: int) -> np.ndarray:
    """Undo ``compress``: the text of every rule is written out once, in the order the rules were made, then gathered."""
    size = np.ones(terminals + len(rules), np.int64)
    start = np.arange(terminals + len(rules), dtype=np.int64)
    text = [np.arange(terminals, dtype=np.uint32)]
    done, used = 0, terminals
    while done < len(rules):
        # rules up to the first that uses a rule of this same run
        late = np.flatnonzero(rules[done:].max(axis=1) >= terminals + done)
        to = done + (int(late[0]) if len(late) else len(rules) - done)
        pair = rules[done:to]
        size[terminals + done : terminals + to] = size[pair].sum(axis=1)
        flat = np.concatenate(text) if len(text) > 1 else text[0]
        text = [flat, flat[ragged(start[pair.ravel()], size[pair.ravel()])]]
        own = size[terminals + done : terminals + to]
        start[terminals + done : terminals + to] = used + np.cumsum(own) - own
        used += int(own.sum())
        done = to
    flat = np.concatenate(text) if len(text) > 1 else text[0]
    return flat[ragged(start[seq], size[seq])]


def pack_shard(seq: np.ndarray, rules: np.ndarray, size: np.ndarray, counts: np.ndarray, terminals: int) -> bytes:
    """Magic, then little-endian: 4 longs (terminals, rules, symbols, documents), rules as pairs of
    unsigned ints, expansion lengths, sequence (all unsigned ints), ids of each document (longs)."""
    head = MAGIC + struct.pack("<4q", terminals, len(rules), len(seq), len(counts))
    return b"".join([head, rules.astype("<u4").tobytes(), size.astype("<u4").tobytes(), seq.astype("<u4").tobytes(), counts.astype("<i8").tobytes()])


class Shard:
    """Reader of one packed shard."""

    def __init__(self, payload: bytes) -> None:
        if payload[:8] != MAGIC:
            raise ValueError("not a shard of token ids")
        self.terminals, n_rules, n, docs = struct.unpack("<4q", payload[8:40])
        at = 40
        self.rules = np.frombuffer(payload, "<u4", 2 * n_rules, at).reshape(-1, 2).astype(np.int64)
        at += 8 * n_rules
        self.size = np.frombuffer(payload, "<u4", n_rules, at)
        at += 4 * n_rules
        self.seq = np.frombuffer(payload, "<u4", n, at).astype(np.int64)
        self.counts = np.frombuffer(payload, "<i8", docs, at + 4 * n)

    def ids(self) -> np.ndarray:
        """All ids of the shard."""
        return expand(self.seq, self.rules, self.terminals)

    def range(self, start: int, end: int) -> np.ndarray:
        """Ids [start, end) of the shard, opening only the symbols that cover them."""
        each = np.where(self.seq < self.terminals, 1, np.append(self.size, 1)[np.minimum(np.maximum(self.seq - self.terminals, 0), len(self.size))])
        edge = np.concatenate([[0], np.cumsum(each)])
        a = int(np.searchsorted(edge, start, "right")) - 1
        b = int(np.searchsorted(edge, end, "left"))
        got = expand(self.seq[a:b], self.rules, self.terminals)
        return got[start - edge[a] : end - edge[a]]

    def document(self, k: int) -> np.ndarray:
        """Ids of the shard's k-th document, its end id included."""
        edge = np.concatenate([[0], np.cumsum(self.counts)])
        return self.range(int(edge[k]), int(edge[k + 1]))


def write_ids(docs: DataFrame, path: str, tokenizer: str, end_id: int = 2) -> None:
    """Encode ``docs`` (doc_id, text) into a dataset of shards at ``path``.

    Shard rows: part, seq (their order is the order of ids), doc_ids, n_ids, payload. Documents
    are range-partitioned and sorted by doc_id, nulls first; rows that repeat a doc_id are all
    written, in an order fixed by their text. Null texts are empty: just the end id. Extra
    columns are ignored; an empty table makes an empty dataset.
    """
    kind = docs.schema["doc_id"].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        part, seq = TaskContext.get().partitionId(), 0
        words = encoder(tokenizer)
        terminals = max(words.tok.get_vocab_size(True), end_id + 1)
        held: list[np.ndarray] = []
        counts: list[np.ndarray] = []
        doc_ids: list = []
        total = 0

        def close() -> pa.RecordBatch:
            packed = pack_shard(*compress(np.concatenate(held), terminals), np.concatenate(counts), terminals)
            return pa.RecordBatch.from_arrays(
                [pa.array([part], pa.int32()), pa.array([seq], pa.int32()), pa.array([doc_ids], pa.list_(id_type)), pa.array([total], pa.int64()), pa.array([packed], pa.binary())],
                ["part", "seq", "doc_ids", "n_ids", "payload"],
            )

        for b in pieces(batches, "text", PASS_BYTES):
            id_type = b.column(0).type
            ids, n = words.encode(b.column(1))
            out = np.full(len(ids) + len(n), end_id, np.uint32)
            out[ragged(np.concatenate([[0], np.cumsum(n + 1)[:-1]]), n)] = ids
            held.append(out)
            counts.append(n + 1)
            doc_ids += b.column(0).to_pylist()
            total += len(out)
            if total >= SHARD_IDS:
                yield close()
                seq, held, counts, doc_ids, total = seq + 1, [], [], [], 0
        if doc_ids:
            yield close()

    parted = docs.select("doc_id", "text").repartitionByRange("doc_id").sortWithinPartitions("doc_id", F.xxhash64("text"))
    parted.mapInArrow(run, f"part int, seq int, doc_ids array<{kind}>, n_ids bigint, payload binary").write.parquet(path)


def shard_starts(shards: DataFrame) -> DataFrame:
    """(part, seq, shard_start): ids before each shard; two steps, so that no task sorts all shards."""
    sizes = shards.select("part", "seq", "n_ids")
    parts = sizes.groupBy("part").agg(F.sum("n_ids").alias("n"))
    before = parts.select("part", (F.sum("n").over(W.orderBy("part")) - F.col("n")).alias("part_start"))
    inside = sizes.withColumn("inside", F.sum("n_ids").over(W.partitionBy("part").orderBy("seq")) - F.col("n_ids"))
    return inside.join(before, "part").select("part", "seq", (F.col("part_start") + F.col("inside")).alias("shard_start"))


def read_documents(spark: SparkSession, path: str) -> DataFrame:
    """(doc_id, start, n_tokens, ids_crc32) of every document, decoded from the shards at ``path``."""
    shards = spark.read.parquet(path)
    starts = materialise(shard_starts(shards), "starts")
    id_type = shards.schema["doc_ids"].dataType.elementType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for k in range(b.num_rows):
                shard = Shard(b.column(1)[k].as_py())
                data, edge = memoryview(shard.ids().astype("<u4").tobytes()), np.concatenate([[0], np.cumsum(shard.counts)])
                crc = [zlib.crc32(data[4 * x : 4 * y]) for x, y in zip(edge[:-1].tolist(), edge[1:].tolist(), strict=True)]
                yield pa.RecordBatch.from_arrays(
                    [b.column(0)[k].values, pa.array(edge[:-1] + b.column(2)[k].as_py(), pa.int64()), pa.array(shard.counts, pa.int64()), pa.array(crc, pa.int64())],
                    ["doc_id", "start", "n_tokens", "ids_crc32"],
                )

    joined = shards.join(starts, ["part", "seq"]).select("doc_ids", "payload", "shard_start")
    return joined.mapInArrow(run, f"doc_id {id_type}, start bigint, n_tokens bigint, ids_crc32 bigint")


def fetch(spark: SparkSession, path: str, doc_id) -> list[np.ndarray]:
    """Ids of the document (or repeated documents) with ``doc_id``: only its shards are read, only its symbols opened."""
    at = spark.read.parquet(path).where(F.array_contains("doc_ids", F.lit(doc_id))).select("doc_ids", "payload")
    return [Shard(bytes(r["payload"])).document(k) for r in at.toLocalIterator() for k, x in enumerate(r["doc_ids"]) if x == doc_id]


def query(spark, sf_dir: str) -> DataFrame:
    """The contract's columns: ``documents`` written with word_bpe_49k and end id 2, then read back."""
    import public_tokenizers

    path = scratch_dir(spark, "token-ids")
    write_ids(spark.read.parquet(f"{sf_dir}/documents.parquet"), path, public_tokenizers.path("word_bpe_49k.json"), 2)
    return read_documents(spark, path)
