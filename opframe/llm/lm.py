"""Language-model scoring by deleted interpolation (operator 5).

The corpus is cut into chunks of bounded size. A chunk keeps its texts as numbers of its own
distinct words. Every distinct unigram, bigram and trigram of the corpus is counted, without a
cap: a chunk sends the sorted 64-bit keys of its distinct n-grams, cut into as many slices of the
key space as the corpus needs, one row for each slice; a slice adds up all chunks' counts and
sends them back in the order of the keys, so that no key travels twice and what is shuffled
grows with the input. A row never holds more than a chunk's n-grams of one slice, a slice never
more than ``SLICE_KEYS`` keys on average, and each n-gram comes at most once from a chunk, so
frequent ones make no slice heavy.

* The model is f(w | u v) mixed with f(w | v), f(w) and a uniform term over the known words and
  one unknown word, each order by a weight for the frequency bucket of its context:
  p_n = weight * f_n + (1 - weight) * p_(n-1). A context that was never seen has weight zero, so
  no mass is lost and the probabilities of all words add up to one.
* The weights are learnt by expectation-maximisation on training texts that the estimates leave
  out (deleted texts), over a table of their tokens; the final estimates use all training texts.

Words are told apart by 62 bits of hash: of n distinct ones, about n^2 / 2^63 pairs are taken for
one. Longer n-grams keep as many bits (62 at most) as let one in 2^``SHARED`` of them share its key
with another, whatever the size of the corpus.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import SPACE_TABLE, buffers, doc_bucket, hash_words, materialise, mix, pieces, ragged, release_shuffles, trim, words

#: Text bytes of a chunk and of a numpy pass; keys of a slice; one training text in DELETED is left out for the weights.
CHUNK_BYTES, PASS_BYTES, SLICE_KEYS, DELETED = 3 << 20, 1 << 20, 2_000_000, 12
#: Two to the power of this is how many longer n-grams there are for one that shares its key.
SHARED = 20
#: Hashes of the end token and of what stands before a text; buckets of context frequency; most steps of expectation-maximisation and the gain in log likelihood, as a share, under which it ends.
END, START, BUCKETS, EM_STEPS, EM_GAIN = -1, -2, 32, 40, 1e-5
ESTIMATE, HELD, TEST = 0, 1, 2
#: Odd multipliers of a word's place in an n-gram.
_PLACE = [np.uint64(0x9E3779B97F4A7C15), np.uint64(0xC2B2AE3D27D4EB4F), np.uint64(0x165667B19E3779F9)]


def _pack(values: np.ndarray) -> bytes:
    """Integers, byte plane by byte plane, compressed: high bytes of sorted or small numbers cost nearly nothing."""
    if not len(values):
        return b""
    planes = np.ascontiguousarray(values.view(np.uint8).reshape(len(values), -1).T)
    return pa.compress(planes.tobytes(), "zstd", asbytes=True)


def _unpack(data: bytes, n: int, kind: str) -> np.ndarray:
    if not n:
        return np.zeros(0, kind)
    width = np.dtype(kind).itemsize
    planes = np.frombuffer(pa.decompress(data, width * n, "zstd", asbytes=True), np.uint8).reshape(width, n)
    return np.ascontiguousarray(planes.T).view(kind).ravel()


def chunks(docs: DataFrame) -> DataFrame:
    """Chunk rows of ``docs`` (doc_id, text, role): role 0 estimates, 1 is left out for the weights, 2 is not learnt from."""
    kind = docs.schema["doc_id"].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        part, seq = TaskContext.get().partitionId(), 0
        open_: dict[bool, list] = {False: [], True: []}
        size_of = {False: 0, True: 0}

        def close(held: bool) -> pa.RecordBatch:
            ids, sizes, roles, tokens = zip(*open_[held], strict=True)
            open_[held], size_of[held] = [], 0
            sizes, roles = np.concatenate(sizes), np.concatenate(roles)
            coded = pa.array(np.concatenate(tokens)).dictionary_encode()
            local, names = np.asarray(coded.indices), np.asarray(coded.dictionary)
            # numbers by falling frequency, so that the high bytes are nearly all zero
            order = np.argsort(-np.bincount(local, minlength=len(names)), kind="stable")
            number = np.empty(len(names), "<u4")
            number[order] = np.arange(len(names))
            learnt = roles != TEST
            return pa.RecordBatch.from_arrays(
                [
                    pa.array([part << 32 | seq], pa.int64()),
                    pa.array([held]),
                    pa.array([pa.concat_arrays(ids)], pa.list_(ids[0].type)),
                    pa.array([sizes.astype(np.int32)], pa.list_(pa.int32())),
                    pa.array([roles.astype(np.int32)], pa.list_(pa.int32())),
                    pa.array([_pack(number[local])], pa.binary()),
                    pa.array([names[order]], pa.list_(pa.int64())),
                    pa.array([len(local)], pa.int64()),
                    pa.array([int(sizes[learnt].sum())], pa.int64()),
                    pa.array([int(learnt.sum())], pa.int64()),
                ],
                ["chunk", "held", "doc_ids", "sizes", "roles", "tokens", "words", "n_tokens", "learnt_tokens", "learnt_texts"],
            )

        for b in pieces(batches, "text", PASS_BYTES):
            raw, off, _ = buffers(b.column(1))
            low, starts, ends, bound = words(raw, off, SPACE_TABLE)
            h = hash_words(low, starts, ends).view(np.int64)
            n = np.diff(bound)
            role = np.asarray(b.column(2))
            del raw, low, starts, ends
            for held in (False, True):
                rows = np.flatnonzero((role == HELD) == held)
                if not len(rows):
                    continue
                size = n[rows] + 1
                every = np.full(int(size.sum()), END, np.int64)
                every[ragged(np.cumsum(size) - size, n[rows])] = h[ragged(bound[rows], n[rows])]
                open_[held].append((b.column(0).take(pa.array(rows)), size, role[rows], every))
                size_of[held] += int((off[rows + 1] - off[rows]).sum())
                if size_of[held] >= CHUNK_BYTES:
                    yield close(held)
                    trim()
                    seq += 1
        for held in (False, True):
            if open_[held]:
                yield close(held)
                seq += 1

    return docs.select("doc_id", "text", "role").mapInArrow(
        run, f"chunk bigint, held boolean, doc_ids array<{kind}>, sizes array<int>, roles array<int>, tokens binary, words array<bigint>, n_tokens bigint, learnt_tokens bigint, learnt_texts bigint"
    )


def _words_first(word: np.ndarray) -> np.ndarray:
    """Order in which a slice's keys travel: words, then longer n-grams, each sorted."""
    return np.concatenate([np.flatnonzero(word), np.flatnonzero(~word)])


class Chunk:
    """Texts of one chunk row and the n-grams of their tokens.

    The low two bits of a key tell words (1) from longer n-grams (2), which keep ``bits`` high bits.
    """

    def __init__(self, b: pa.RecordBatch, k: int, order: int, bits: int) -> None:
        def row(name: str) -> np.ndarray:
            return np.asarray(b.column(b.schema.get_field_index(name))[k].values)

        self.sizes, self.roles = row("sizes").astype(np.int64), row("roles")
        names = row("words").view(np.uint64)
        n = int(self.sizes.sum())
        local = _unpack(b.column(b.schema.get_field_index("tokens"))[k].as_py(), n, "<u4")
        #: place of each token in its text
        self.place = np.arange(n) - np.repeat(np.cumsum(self.sizes) - self.sizes, self.sizes)
        start = np.array([START], np.int64).view(np.uint64)[0]
        total, keys = np.zeros(n, np.uint64), []
        mask = ~np.uint64((1 << (64 - bits)) - 1)
        for back in range(order):
            word = names[local] if back == 0 else np.concatenate([np.full(min(back, n), start), names[local[: max(n - back, 0)]]])
            if back:
                word[self.place < back] = start
            total = total + word * _PLACE[back]
            keys.append((mix(total + np.uint64(back)) & (mask if back else ~np.uint64(3))) | np.uint64(2 if back else 1))
        coded = pa.array(np.concatenate(keys)).dictionary_encode()
        distinct = np.asarray(coded.dictionary)
        by = np.argsort(distinct)
        rank = np.empty(len(by), np.int32)
        rank[by] = np.arange(len(by), dtype=np.int32)
        #: sorted distinct keys, and for each order the key of each token
        self.keys, self.at = distinct[by], rank[np.asarray(coded.indices)].reshape(order, n)

    def learnt(self) -> np.ndarray:
        """How often each key occurs in texts to learn from."""
        mask = np.repeat(self.roles != TEST, self.sizes)
        return np.bincount(self.at[:, mask].ravel(), minlength=len(self.keys)).astype("<u4")

    def edges(self, slices: int) -> np.ndarray:
        """Where each slice of the key space begins among the keys, and their end."""
        bound = [-(-(s << 64) // slices) for s in range(1, slices)]
        return np.concatenate([[0], np.searchsorted(self.keys, np.array(bound, np.uint64)), [len(self.keys)]])


def key_bits(grams: int) -> int:
    """Bits of the keys of longer n-grams, for so many of them."""
    return min(62, max(8, grams).bit_length() + SHARED)


def gram_counts(made: DataFrame, order: int, slices: int, bits: int) -> DataFrame:
    """(chunk, slice, n, e, types, e_types): for each chunk and slice the packed counts, over all training texts and over
    estimating ones, of the chunk's keys in their order; and rows of chunk -1 with the number of distinct words of a slice."""

    def send(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for k in range(b.num_rows):
                c = Chunk(b, k, order, bits)
                count, edge, word = c.learnt(), c.edges(slices), (c.keys & np.uint64(3)) == 1
                some = np.flatnonzero(np.diff(edge))
                part = [(int(edge[s]), int(edge[s + 1])) for s in some.tolist()]
                chunk, held = b.column(b.schema.get_field_index("chunk"))[k].as_py(), b.column(b.schema.get_field_index("held"))[k].as_py()
                yield pa.RecordBatch.from_arrays(
                    [
                        pa.array(some, pa.int32()),
                        pa.array(np.full(len(some), chunk)),
                        pa.array(np.full(len(some), held)),
                        pa.array([y - x for x, y in part], pa.int32()),
                        pa.array([int(word[x:y].sum()) for x, y in part], pa.int32()),
                        pa.array([_pack(c.keys[x:y][word[x:y]]) for x, y in part], pa.binary()),
                        pa.array([_pack(c.keys[x:y][~word[x:y]] >> np.uint64(64 - bits)) for x, y in part], pa.binary()),
                        pa.array([_pack(count[x:y][_words_first(word[x:y])]) for x, y in part], pa.binary()),
                    ],
                    ["slice", "chunk", "held", "size", "n_words", "words", "grams", "counts"],
                )
                del c, count
                trim()

    def add(table: pa.Table) -> pa.Table:
        size = np.asarray(table.column("size").combine_chunks(), np.int64)
        held = np.asarray(table.column("held").combine_chunks())
        own_words = np.asarray(table.column("n_words").combine_chunks(), np.int64).tolist()
        parts = []
        for w, g, n, m in zip(table.column("words"), table.column("grams"), size.tolist(), own_words, strict=True):
            parts += [_unpack(w.as_py(), m, "<u8"), (_unpack(g.as_py(), n - m, "<u8") << np.uint64(64 - bits)) | np.uint64(2)]
        keys = np.concatenate(parts)
        counts = np.concatenate([_unpack(x.as_py(), n, "<u4") for x, n in zip(table.column("counts"), size.tolist(), strict=True)])
        coded = pa.array(keys).dictionary_encode()
        which, kinds = np.asarray(coded.indices), np.asarray(coded.dictionary)
        e = np.bincount(which, weights=np.where(np.repeat(held, size), 0, counts), minlength=len(kinds)).astype("<u8")
        n = np.bincount(which, weights=counts, minlength=len(kinds)).astype("<u8")
        word = (kinds & np.uint64(3)) == 1
        end = np.cumsum(size)
        part = [which[y - k : y] for k, y in zip(size.tolist(), end.tolist(), strict=True)]
        own = table.column("slice")[0].as_py()
        none = pa.nulls(len(size), pa.int64())
        rows = pa.table(
            [
                table.column("chunk").combine_chunks(),
                pa.array(np.full(len(size), own), pa.int32()),
                pa.array([_pack(n[w]) for w in part], pa.binary()),
                pa.array([_pack(e[w]) if h else None for w, h in zip(part, held.tolist(), strict=True)], pa.binary()),
                none,
                none,
            ],
            names,
        )
        trim()
        types = pa.table([pa.array([-1], pa.int64()), pa.array([own], pa.int32()), pa.nulls(1, pa.binary()), pa.nulls(1, pa.binary()), pa.array([int((n[word] > 0).sum())], pa.int64()), pa.array([int((e[word] > 0).sum())], pa.int64())], names)
        return pa.concat_tables([rows, types])

    names = ["chunk", "slice", "n", "e", "types", "e_types"]
    sent = made.select("chunk", "held", "sizes", "roles", "tokens", "words").mapInArrow(send, "slice int, chunk bigint, held boolean, size int, n_words int, words binary, grams binary, counts binary")
    return sent.groupBy("slice").applyInArrow(add, "chunk bigint, slice int, n binary, e binary, types bigint, e_types bigint")


class Estimates:
    """What a model needs beside the counts of n-grams: tokens, distinct words and texts."""

    def __init__(self, total: int, types: int, texts: int, order: int) -> None:
        self.total, self.types, self.texts, self.order = total, types, texts, order

    def parts(self, c: Chunk, count: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(maximum-likelihood estimates (order, tokens), context bucket of each); a context never seen has bucket 0 and estimate 0."""
        f = np.zeros((self.order, len(c.place)))
        bucket = np.zeros((self.order, len(c.place)), np.int32)
        got = count[c.at]
        f[0] = got[0] / max(self.total, 1)
        bucket[0] = 1 if self.total else 0
        for n in range(1, self.order):
            # the context of a token is the n-gram, one shorter, that ends before it
            context = np.concatenate([[0], got[n - 1][:-1]])
            context[c.place == 0] = self.texts
            f[n] = got[n] / np.maximum(context, 1)
            bucket[n] = np.minimum(BUCKETS - 1, np.ceil(np.log2(context + 1.0)))
        return f, bucket

    def probability(self, f: np.ndarray, bucket: np.ndarray, weights: np.ndarray) -> np.ndarray:
        """The mixture, from the uniform term upwards."""
        p = np.full(f.shape[1], 1 / (self.types + 1))
        for n in range(self.order):
            w = weights[n][bucket[n]]
            p = w * f[n] + (1 - w) * p
        return p


def _answered(made: DataFrame, counts: DataFrame, field: str) -> DataFrame:
    """Chunk rows with the answers of all slices about one kind of counts; a chunk's answers are bounded by its bytes."""
    lists = counts.where("chunk >= 0").where(F.col(field).isNotNull()).groupBy("chunk").agg(F.collect_list(F.struct("slice", field)).alias("answers"))
    return made.join(lists, "chunk")


def _local(b: pa.RecordBatch, k: int, order: int, slices: int, bits: int, field: str) -> tuple[Chunk, np.ndarray]:
    """A chunk and the counts of its keys."""
    c = Chunk(b, k, order, bits)
    edge = c.edges(slices)
    out = np.zeros(len(c.keys), np.int64)
    for x in b.column(b.schema.get_field_index("answers"))[k].as_py():
        i, j = int(edge[x["slice"]]), int(edge[x["slice"] + 1])
        out[i:j][_words_first((c.keys[i:j] & np.uint64(3)) == 1)] = _unpack(x[field], j - i, "<u8")
    return c, out


def held_tokens(answered: DataFrame, model: Estimates, slices: int, bits: int) -> DataFrame:
    """(f1, b1, f2, b2 ...) of every token of the left-out texts: estimates and context buckets by order."""
    order = model.order

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for k in range(b.num_rows):
                c, count = _local(b, k, order, slices, bits, "e")
                f, bucket = model.parts(c, count)
                columns = [x for n in range(order) for x in (pa.array(f[n]), pa.array(bucket[n]))]
                yield pa.RecordBatch.from_arrays(columns, [x for n in range(order) for x in (f"f{n + 1}", f"b{n + 1}")])
                trim()

    return answered.mapInArrow(run, ", ".join(f"f{n + 1} double, b{n + 1} int" for n in range(order)))


def _settled(used: np.ndarray, offered: np.ndarray) -> np.ndarray:
    """Weight of each bucket; one without left-out tokens has that of the next lower one with some. Bucket 0, contexts never seen, has none."""
    out, last = np.zeros(len(used)), 0.5
    for b in range(1, len(used)):
        if offered[b] > 0:
            last = min(1 - 1e-6, max(1e-6, used[b] / offered[b]))
        out[b] = last
    return out


def expectation_maximisation(tokens: DataFrame, order: int, types: int, steps: int = EM_STEPS) -> np.ndarray:
    """Weights (order, BUCKETS) that raise the likelihood of the left-out ``tokens`` step by step.

    A step is one aggregation by context buckets; the driver gets its few sums.
    """
    weights = np.array([_settled(np.ones(BUCKETS), np.full(BUCKETS, 2.0)) for _ in range(order)])
    before = None
    for _ in range(steps):
        left, share = F.lit(1.0), []
        for n in range(order, 0, -1):
            w = F.element_at(F.lit(weights[n - 1].tolist()), F.col(f"b{n}") + 1)
            share.append((left * w * F.col(f"f{n}")).alias(f"s{n}"))
            left = left * (1 - w)
        row = tokens.select(*[f"b{n + 1}" for n in range(order)], *share, (left / (types + 1)).alias("s0"))
        total = sum((F.col(f"s{n}") for n in range(1, order + 1)), F.col("s0"))
        sums = row.withColumn("p", total).groupBy(*[f"b{n + 1}" for n in range(order)]).agg(
            F.sum(F.log("p")).alias("like"), F.count(F.lit(1)).alias("n"), *[F.sum(F.col(f"s{n}") / F.col("p")).alias(f"s{n}") for n in range(order + 1)]
        )
        got = sums.collect()
        if not got:
            return weights
        new = []
        for n in range(order, 0, -1):
            used, offered = np.zeros(BUCKETS), np.zeros(BUCKETS)
            for r in got:
                used[r[f"b{n}"]] += r[f"s{n}"]
                offered[r[f"b{n}"]] += sum(r[f"s{m}"] for m in range(n + 1))
            new.append(_settled(used, offered))
        weights = np.array(new[::-1])
        like = sum(r["like"] for r in got)
        if before is not None and like - before <= EM_GAIN * abs(like):
            break
        before = like
    return weights


def score(docs: DataFrame, learn, order: int = 3) -> DataFrame:
    """(doc_id, learnt, n_tokens, n_known, train_tokens, base_score, score) of every row of ``docs`` (doc_id, text).

    ``learn`` is a boolean column over ``docs``: the texts to learn from. A-Z are lowered;
    tokens are runs other than space and 0x09-0x0D, then one end. base_score is the add-half
    unigram log10 probability; score the mixture's. Null and empty texts are one end token.
    Repeated rows count and are scored each; extra columns are ignored. ``order``: 1 to 3. Without
    any training text every token has probability one (there is only the unknown word); without
    left-out texts the weights are a half. An empty table gives no rows.
    """
    left_out = F.pmod(F.xxhash64(F.coalesce(F.col("doc_id").cast("string"), F.lit("")), F.lit(5)), F.lit(DELETED)) == 0
    role = F.when(~learn, TEST).when(left_out, HELD).otherwise(ESTIMATE).cast("int")
    made = materialise(chunks(docs.select("doc_id", "text", role.alias("role"))), "chunks")
    estimating = F.when(~F.col("held"), F.col("learnt_tokens"))
    every, total, texts, e_total, e_texts = (
        x or 0 for x in made.agg(F.sum("n_tokens"), F.sum("learnt_tokens"), F.sum("learnt_texts"), F.sum(estimating), F.sum(F.when(~F.col("held"), F.col("learnt_texts")))).first()
    )
    slices = max(1, -(-2 * every // SLICE_KEYS))
    bits = key_bits(order * every)
    counts = materialise(gram_counts(made, order, slices, bits), "counts")
    release_shuffles(docs.sparkSession)
    types, e_types = (x or 0 for x in counts.where("chunk < 0").agg(F.sum("types"), F.sum("e_types")).first())
    held = _answered(made.where("held"), counts, "e")
    tokens = materialise(held_tokens(held, Estimates(e_total, e_types, e_texts, order), slices, bits), "held-tokens")
    weights = expectation_maximisation(tokens, order, e_types)
    model = Estimates(total, types, texts, order)
    kind = docs.schema["doc_id"].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for k in range(b.num_rows):
                c, count = _local(b, k, order, slices, bits, "n")
                mixed = np.log10(model.probability(*model.parts(c, count), weights))
                own = count[c.at[0]]
                base = np.log10((own + 0.5) / (model.total + 0.5 * (model.types + 1)))
                seg = np.cumsum(c.sizes) - c.sizes
                yield pa.RecordBatch.from_arrays(
                    [
                        b.column(b.schema.get_field_index("doc_ids"))[k].values,
                        pa.array(c.roles != TEST),
                        pa.array(c.sizes),
                        pa.array(np.add.reduceat((own > 0).astype(np.int64), seg)),
                        pa.array(np.full(len(seg), model.total, np.int64)),
                        pa.array(np.add.reduceat(base, seg)),
                        pa.array(np.add.reduceat(mixed, seg)),
                    ],
                    ["doc_id", "learnt", "n_tokens", "n_known", "train_tokens", "base_score", "score"],
                )
                del c, count, mixed, own, base
                trim()

    joined = _answered(made.select("chunk", "doc_ids", "sizes", "roles", "tokens", "words"), counts, "n")
    return joined.mapInArrow(run, f"doc_id {kind}, learnt boolean, n_tokens bigint, n_known bigint, train_tokens bigint, base_score double, score double")


def query(spark, sf_dir: str) -> DataFrame:
    """The contract's columns for ``documents``."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    out = score(docs, doc_bucket("doc_id", 5) != 1)
    return out.select("doc_id", (~F.col("learnt")).alias("held_out"), "n_tokens", "n_known", "train_tokens", "base_score", "score")
