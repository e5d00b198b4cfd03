"""SentencePiece encoding and decoding by suffix-array matching (operator 1).

A batch's distinct chunks (text cut where no piece reaches across: before word marks, around
line ends, between a letter and a mark after it) are concatenated and
indexed by a suffix array as deep as the longest piece. Every piece of the vocabulary is
binary-searched for its range of suffixes, which yields all occurrences of all pieces as edges
(start, end, piece). Edges are sorted by position and relaxed from left to right, for all
chunks at once.

Two kinds of model files are relaxed differently. For a unigram model an edge improves the best
sum of scores at its end. For a merge (BPE) model the last piece of a prefix's encoding is the
one whose neighbour before it would not have been merged differently; an edge is taken if the
pair of pieces is such a pair, which reproduces the order of merges without replaying them.
"""

from __future__ import annotations

import unicodedata
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame

from .common import kept, mix
from .common import pieces as slices
from .common import ragged

MARK = "▁"
#: Distinct chunks kept encoded by a worker, and remembered pairs (log2); results depend on neither.
CACHE_CHUNKS, PAIR_BITS = 600_000, 21
_BIG = 1 << 40


class Vocabulary:
    """Pieces, scores and byte pieces of a model file, and what matching and relaxing need of them."""

    def __init__(self, path: str) -> None:
        import sentencepiece

        sp = sentencepiece.SentencePieceProcessor(model_file=path)
        n = sp.get_piece_size()
        self.text = [sp.id_to_piece(i) for i in range(n)]
        self.score = np.array([sp.get_score(i) for i in range(n)])
        self.byte_ids = {int(self.text[i][3:5], 16): i for i in range(n) if sp.is_byte(i)}
        self.unk = sp.unk_id()
        self.merges = self._is_merge_model(path)
        usable = [i for i in range(n) if not (sp.is_byte(i) or sp.is_control(i) or sp.is_unknown(i) or sp.is_unused(i))]
        self.id_of = {self.text[i]: i for i in usable}
        if self.merges:
            self._merge_tables(usable)
            usable = [i for i in usable if len(self.text[i]) == 1 or self.left[i] != i]  # the others are never reached
        chars = sorted({ord(c) for i in usable for c in self.text[i]})
        self.code = np.zeros(max(chars) + 2, np.uint16)
        self.code[chars] = np.arange(1, len(chars) + 1)
        self.depth = max(len(self.text[i]) for i in usable)
        self.order = np.array(sorted(usable, key=lambda i: [self.code[ord(c)] for c in self.text[i]]), np.int64)
        self.size = np.array([len(self.text[i]) for i in self.order], np.int64)
        low = np.zeros((len(usable), self.depth), ">u2")
        high = np.full((len(usable), self.depth), 0xFFFF, ">u2")
        for k, i in enumerate(self.order):
            codes = [self.code[ord(c)] for c in self.text[i]]
            low[k, : len(codes)] = high[k, : len(codes)] = codes
        self.low, self.high = (np.ascontiguousarray(x).view(f"S{2 * self.depth}").ravel() for x in (low, high))
        joins = [self.text[i] for i in usable if len(self.text[i]) > 1]
        self.splits_marks = not any(MARK in x.lstrip(MARK) for x in joins)
        self.splits_lines = not any("\n" in x for x in joins)
        after_letter = {b for x in joins for a, b in zip(x, x[1:], strict=False) if unicodedata.category(a)[0] == "L"}
        self.splits_marks_after_letters = "".join(c for c in ".,;:!?" if c not in after_letter)
        data = [bytes([int(t[3:5], 16)]) if i in self.byte_ids.values() else ("" if sp.is_control(i) else t).encode() for i, t in enumerate(self.text)]
        self.piece_bytes = np.frombuffer(b"".join(data), np.uint8)
        self.piece_len = np.array([len(x) for x in data], np.int64)
        self.piece_start = np.cumsum(self.piece_len) - self.piece_len

    @staticmethod
    def _is_merge_model(path: str) -> bool:
        """Whether trainer_spec.model_type (field 2, then field 3) of the file says BPE (2)."""

        def varint(b: bytes, at: int) -> tuple[int, int]:
            x = shift = 0
            while True:
                x |= (b[at] & 127) << shift
                at, shift = at + 1, shift + 7
                if b[at - 1] < 128:
                    return x, at

        def fields(b: bytes) -> Iterator[tuple[int, object]]:
            at = 0
            while at < len(b):
                tag, at = varint(b, at)
                if tag & 7 == 0:
                    value, at = varint(b, at)
                elif tag & 7 == 2:
                    size, at = varint(b, at)
                    value, at = b[at : at + size], at + size
                else:
                    size = 8 if tag & 7 == 1 else 4
                    value, at = b[at : at + size], at + size
                yield tag >> 3, value

        with open(path, "rb") as f:
            for field, value in fields(f.read()):
                if field == 2:
                    return any(k == 3 and v == 2 for k, v in fields(value))
        return False

    def _merge_tables(self, usable: list[int]) -> None:
        """Ranks of pieces, halves of their last merges, and the rank of every pair that merges."""
        n = len(self.text)
        self.rank = np.full(n + 1, -1, np.int64)
        for i in usable:
            if len(self.text[i]) > 1:
                self.rank[i] = int(-self.score[i]) + 1
        self.left, self.right = np.arange(n + 1), np.arange(n + 1)
        pairs: dict[int, int] = {}
        for i in usable:
            t = self.text[i]
            for k in range(1, len(t)):
                a, b = self.id_of.get(t[:k]), self.id_of.get(t[k:])
                if a is not None and b is not None:
                    pairs[a * (n + 1) + b] = int(self.rank[i])
        self.pair_keys = np.array(sorted(pairs), np.int64)
        self.pair_rank = np.array([pairs[k] for k in self.pair_keys.tolist()], np.int64)
        for i in usable:
            symbols = [self.id_of.get(c) for c in self.text[i]]
            if len(symbols) < 2 or None in symbols:
                continue
            while len(symbols) > 1:
                ranks = [pairs.get(a * (n + 1) + b, _BIG) for a, b in zip(symbols, symbols[1:], strict=False)]
                k = int(np.argmin(ranks))
                if ranks[k] == _BIG:
                    break
                if len(symbols) == 2:
                    self.left[i], self.right[i] = symbols
                symbols[k : k + 2] = [self.id_of[self.text[symbols[k]] + self.text[symbols[k + 1]]]]

    def compatible(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        """Whether merging in order leaves piece a beside piece b; id n stands for a character without a piece."""
        n = len(self.text)
        out = np.ones(len(a), bool)
        at, limit = np.arange(len(a)), np.full(len(a), _BIG)
        while len(at):
            key = a * (n + 1) + b
            near = np.minimum(np.searchsorted(self.pair_keys, key), len(self.pair_keys) - 1)
            rank = np.where(self.pair_keys[near] == key, self.pair_rank[near], _BIG)
            bad = rank < limit
            out[at[bad]] = False
            r1, r2 = self.rank[a], self.rank[b]
            go = ~bad & ((r1 >= 0) | (r2 >= 0))
            at, a, b, r1, r2 = at[go], a[go], b[go], r1[go], r2[go]
            one = r1 > r2
            limit = np.where(one, r1, r2 + 1)
            a, b = np.where(one, self.right[a], a), np.where(one, b, self.left[b])
        return out


class Encoder:
    """Encodes texts chunk by chunk; the chunks of a batch that are not yet known are matched together."""

    def __init__(self, path: str) -> None:
        self.v = Vocabulary(path)
        self.seen_key = np.full(1 << PAIR_BITS, -1, np.int64)
        self.seen = np.zeros(1 << PAIR_BITS, bool)
        self._clear()

    def _clear(self) -> None:
        self.known, self.run_of = pa.array([], pa.string()), np.zeros(0, np.int64)
        self.ids = np.zeros(1 << 20, np.int32)
        self.used = self.runs = 0
        self.start = np.zeros(1 << 18, np.int64)
        self.len = np.zeros(1 << 18, np.int64)

    def edges(self, code: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(start, end, piece) of every occurrence of every piece in ``code`` (zeros part the chunks)."""
        v = self.v
        n = len(code)
        padded = np.concatenate([code, np.zeros(v.depth, np.uint16)]).astype(">u2")
        suffix = np.lib.stride_tricks.sliding_window_view(padded, v.depth)[:n].copy()
        # what follows a chunk's end does not belong to its suffixes
        suffix[np.cumsum(suffix == 0, axis=1) > 0] = 0
        suffix = suffix.view(f"S{2 * v.depth}").ravel()
        order = np.argsort(suffix, kind="stable")
        ranked = suffix[order]
        lo, hi = np.searchsorted(ranked, v.low), np.searchsorted(ranked, v.high, "right")
        count = np.maximum(hi - lo, 0)
        start = order[ragged(lo, count)]
        return start, start + np.repeat(v.size, count), np.repeat(v.order, count)

    def _pairs(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        """``compatible`` with remembered answers."""
        key = a * (len(self.v.text) + 1) + b
        slot = (mix(key.astype(np.uint64)) >> np.uint64(64 - PAIR_BITS)).astype(np.int64)
        out, new = self.seen[slot], self.seen_key[slot] != key
        if new.any():
            got = self.v.compatible(a[new], b[new])
            out[new] = got
            # one writer for each slot, so that key and answer belong together
            _, first = np.unique(slot[new], return_index=True)
            at = slot[new][first]
            self.seen_key[at], self.seen[at] = key[new][first], got[first]
        return out

    def _match(self, chunks: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """(piece ids of all chunks, how many each has); characters without a piece become byte pieces."""
        v = self.v
        points = np.frombuffer("\0".join(chunks).encode("utf-32-le", "surrogatepass") + b"\0\0\0\0", np.uint32)
        size = np.fromiter(map(len, chunks), np.int64, len(chunks))
        begin = np.cumsum(size + 1) - size - 1
        inside = np.ones(len(points), bool)
        inside[begin + size] = False
        code = np.where(points < len(v.code), v.code[np.minimum(points, len(v.code) - 1)], 0).astype(np.uint16) * inside
        start, end, piece = self.edges(code)
        lone = np.flatnonzero((code == 0) & inside)
        none = len(v.text)
        start, end, piece = np.concatenate([start, lone]), np.concatenate([end, lone + 1]), np.concatenate([piece, np.full(len(lone), none)])
        owner = np.searchsorted(begin, start, "right") - 1
        depth = end - begin[owner]
        sort = np.lexsort((end, depth))
        start, end, piece, depth = start[sort], end[sort], piece[sort], depth[sort]
        back = np.full(len(points) + 1, -1, np.int64)
        last = np.full(len(points) + 1, -1, np.int64)
        first_at = np.zeros(len(points) + 1, bool)
        first_at[begin] = True
        cut = np.searchsorted(depth, np.arange(1, int(depth.max()) + 2)) if len(depth) else np.zeros(1, np.int64)
        best = np.full(len(points) + 1, -np.inf)
        best[begin] = 0.0
        score = np.append(v.score, v.score.min() - 10)
        for x, y in zip(cut[:-1].tolist(), cut[1:].tolist(), strict=True):
            s, e, p = start[x:y], end[x:y], piece[x:y]
            if v.merges:
                ok = first_at[s]
                held = np.flatnonzero(~ok & (last[s] >= 0))
                if len(held):
                    ok[held] = self._pairs(last[s[held]], p[held])
                last[e[ok]], back[e[ok]] = p[ok], s[ok]
            else:
                value = best[s] + score[p]
                np.maximum.at(best, e, value)
                win = value == best[e]
                last[e[win]], back[e[win]] = p[win], s[win]
        at = begin + size
        out_key: list[np.ndarray] = []
        out_id: list[np.ndarray] = []
        row = np.arange(len(chunks))
        step = 0
        while True:
            live = at > begin[row]
            at, row = at[live], row[live]
            if not len(at):
                break
            out_key.append(row << 32 | step)
            out_id.append(np.stack([last[at], back[at]]))
            at = back[at]
            step += 1
        if not out_key:
            return np.zeros(0, np.int32), np.zeros(len(chunks), np.int64)
        key, (ids, where) = np.concatenate(out_key), np.concatenate(out_id, axis=1)
        order = np.lexsort((-(key & 0xFFFFFFFF), key >> 32))
        ids, where, owner = ids[order], where[order], key[order] >> 32
        lens = np.bincount(owner, minlength=len(chunks))
        odd = np.flatnonzero(ids == none)
        if len(odd):
            runs = [[v.byte_ids.get(x, v.unk) for x in chr(points[where[i]]).encode("utf-8", "replace")] if v.byte_ids else [v.unk] for i in odd.tolist()]
            wide = np.ones(len(ids), np.int64)
            wide[odd] = [len(r) for r in runs]
            lens = np.bincount(owner, weights=wide, minlength=len(chunks)).astype(np.int64)
            ids = np.repeat(ids, wide)
            ids[ragged((np.cumsum(wide) - wide)[odd], wide[odd])] = np.concatenate(runs)
        return ids.astype(np.int32), lens

    def _numbers(self, names: pa.Array) -> np.ndarray:
        """Run number of each of the distinct chunks; unknown ones are matched."""
        at = np.asarray(pc.fill_null(pc.index_in(names, value_set=self.known), -1), np.int64)
        got = np.append(self.run_of, 0)[at]
        missing = np.flatnonzero(at < 0)
        if len(missing):
            fresh = names.take(pa.array(missing))
            ids, lens = self._match(fresh.to_pylist())
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
            own = np.arange(first, first + len(fresh))
            got[missing] = own
            self.known = pa.concat_arrays([self.known, fresh])
            self.run_of = np.append(self.run_of, own)
        return got

    def encode(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """(ids of all texts, how many each has). Empty and null texts have none."""
        if len(self.known) > CACHE_CHUNKS:
            self._clear()
        plain = pc.fill_null(texts, "")
        marked = pc.replace_substring(plain, " ", MARK)
        marked = pc.if_else(pc.equal(pc.binary_length(plain), 0), "", pc.binary_join_element_wise(pa.scalar(MARK), marked, ""))
        if self.v.splits_marks:
            marked = pc.replace_substring_regex(marked, f"({MARK}+)", r" \1")
        if self.v.splits_marks_after_letters:
            marked = pc.replace_substring_regex(marked, rf"(\pL)([{self.v.splits_marks_after_letters}])", r"\1 \2")
        if self.v.splits_lines:
            marked = pc.replace_substring(marked, "\n", " \n ")
        lists = pc.split_pattern(marked, " ")
        coded = lists.flatten().dictionary_encode()
        run = self._numbers(coded.dictionary.cast(pa.string()))[np.asarray(coded.indices)]
        lens = self.len[run]
        total = np.concatenate([[0], np.cumsum(lens)])
        seg = np.concatenate([[0], np.cumsum(np.asarray(lists.value_lengths()))])
        return self.ids[ragged(self.start[run], lens)], np.diff(total[seg])

    def decode(self, ids: np.ndarray, count: np.ndarray) -> list[str]:
        """Texts of runs of ids: pieces and bytes joined, word marks as blanks, the first blank dropped."""
        lens = self.v.piece_len[ids]
        data = self.v.piece_bytes[ragged(self.v.piece_start[ids], lens)].tobytes()
        total = np.concatenate([[0], np.cumsum(lens)])[np.concatenate([[0], np.cumsum(count)])].tolist()
        out = [data[a:b].decode("utf-8", "replace").replace(MARK, " ") for a, b in zip(total, total[1:], strict=False)]
        return [t[1:] if t[:1] == " " else t for t in out]


def encoder(path: str) -> Encoder:
    """The worker process's encoder of a model file."""
    return kept(f"pieces:{path}", lambda: Encoder(path))


def encode(docs: DataFrame, model: str) -> DataFrame:
    """(doc_id, ids, n_tokens, ids_crc32, round_trip) of every row of ``docs`` (doc_id, text).

    ids_crc32 is over the ids as little-endian unsigned 32-bit integers; round_trip says whether
    decoding gives the text back (a text with a literal word mark reads as a blank there).
    Null and empty texts have no ids. Repeated rows are encoded each, extra columns ignored.
    """
    kind = docs.schema["doc_id"].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        e = encoder(model)
        for b in slices(batches, "text"):
            ids, n = e.encode(b.column(1))
            edge = np.concatenate([[0], np.cumsum(n)])
            data = memoryview(ids.astype("<u4").tobytes())
            crc = [zlib.crc32(data[4 * x : 4 * y]) for x, y in zip(edge[:-1].tolist(), edge[1:].tolist(), strict=True)]
            same = [(t or "").replace(MARK, " ") == d for t, d in zip(b.column(1).to_pylist(), e.decode(ids, n), strict=True)]
            yield pa.RecordBatch.from_arrays(
                [b.column(0), pa.ListArray.from_arrays(pa.array(edge.astype(np.int32)), pa.array(ids)), pa.array(n, pa.int64()), pa.array(crc, pa.int64()), pa.array(same)],
                ["doc_id", "ids", "n_tokens", "ids_crc32", "round_trip"],
            )

    return docs.select("doc_id", "text").mapInArrow(run, f"doc_id {kind}, ids array<int>, n_tokens bigint, ids_crc32 bigint, round_trip boolean")


def decode(encoded: DataFrame, model: str) -> DataFrame:
    """(doc_id, text) of rows (doc_id, ids); null ids give an empty text."""
    kind = encoded.schema["doc_id"].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        e = encoder(model)
        for b in batches:
            lists = b.column(1)
            n = np.asarray(lists.value_lengths().fill_null(0), np.int64)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(e.decode(np.asarray(lists.flatten(), np.int64), n), pa.string())], ["doc_id", "text"])

    return encoded.select("doc_id", "ids").mapInArrow(run, f"doc_id {kind}, text string")


def query(spark, sf_dir: str) -> DataFrame:
    """All ``documents`` encoded with the public 32k model, with ids and the round trip's outcome."""
    import public_tokenizers

    return encode(spark.read.parquet(f"{sf_dir}/documents.parquet"), public_tokenizers.path("piece_bpe_32k.model"))
