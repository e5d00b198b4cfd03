"""SimHash near-duplicate detection with pigeonhole blocks (operator 3).

A text's fingerprint sums the hash bits of its word shingles. Two ways to find close
fingerprints share one verifying step:

* ``pigeonhole_keys``: the 64 bits are split into m blocks; fingerprints at d or fewer
  differing bits agree on at least m - d blocks, so each combination of m - d blocks is a
  join key and no close pair is missed. m is chosen from the number of distinct
  fingerprints so that unrelated fingerprints rarely meet; every choice gives the same links.
* ``band_keys``: wide fingerprints of shingle sets for a similarity bound. The exact split would
  need millions of keys there, so blocks are cut from several permutations of the bits until a
  pair at the bound shares a block with the stated probability. Here distances only gather
  texts: those that they connect are compared by their whole shingle sets.

Fingerprints that share a key meet in one bucket. Buckets are split into chunks of bounded
size and every pair of chunks is a group of its own, so a hot key spreads over tasks. A group
verifies all of its Hamming distances and emits one link for each fingerprint that it connects:
connectivity is exact and the output is never larger than the group. What wide fingerprints
connect is dealt the same way, by bytes of shingle sets, and each group of sets is searched for
links by Jaccard similarity; so a set travels once for each chunk it meets and never once a pair.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import SPACE_TABLE, buffers, materialise, mix, pieces, ragged, trim, words
from .graph import BROADCAST_ROWS, components, maybe_broadcast

#: Fingerprints of one chunk of a bucket.
CHUNK = 2048
#: Text bytes of one pass, whose shingles are lists of Python numbers for a moment.
PASS_BYTES = 1 << 20
SEED = 42
#: Bytes of shingle sets of one chunk of connected texts; one wide fingerprint in SAMPLE is counted to find hot keys.
SET_BYTES, SAMPLE = 4 << 20, 16
#: A pair at the similarity bound shares a block with this probability at the expected distance; distances up to so many deviations above it are candidates.
RECALL, SURE = 0.9999, 3.5


def shingle_hashes(raw: np.ndarray, off: np.ndarray, width: int) -> tuple[np.ndarray, np.ndarray]:
    """XXH64 of all word shingles (repeats included) and how many each text has."""
    low, starts, ends, bound = words(raw, off, SPACE_TABLE)
    n = np.diff(bound)
    if not len(starts):
        return np.zeros(0, np.uint64), np.zeros(len(n), np.int64)
    lens = ends - starts
    joined = np.full(int(lens.sum()) + len(lens), 32, np.uint8)
    at = np.zeros(len(lens) + 1, np.int64)
    np.cumsum(lens + 1, out=at[1:])
    joined[ragged(at[:-1], lens)] = low[ragged(starts, lens)]
    count = np.where(n == 0, 0, np.maximum(1, n - width + 1))
    first = ragged(bound[:-1], count)
    last = first + np.repeat(np.minimum(width, np.maximum(n, 1)), count) - 1
    text = joined.tobytes()
    digest = xxhash.xxh64_intdigest
    out = np.fromiter(
        (digest(text[a:b], SEED) for a, b in zip(at[first].tolist(), (at[last] + lens[last]).tolist(), strict=True)), np.uint64, len(first)
    )
    return out, count


def majority_bits(hashes: np.ndarray, count: np.ndarray, words64: int = 1) -> np.ndarray:
    """Fingerprints as (texts, words64) unsigned longs: a bit is set if it is set in over half the hashes."""
    out = np.zeros((len(count), words64), np.uint64)
    full = np.flatnonzero(count)
    if not len(full):
        return out
    seg = np.zeros(len(full), np.int64)
    np.cumsum(count[full][:-1], out=seg[1:])
    for k in range(words64):
        h = hashes if k == 0 else mix(hashes + np.uint64((k * 0x9E3779B97F4A7C15) & (2**64 - 1)))
        bits = np.unpackbits(np.ascontiguousarray(h).view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")
        sums = np.add.reduceat(bits, seg, axis=0, dtype=np.int32)
        set_ = (2 * sums > count[full][:, None]).astype(np.uint8)
        out[full, k] = np.packbits(set_, axis=1, bitorder="little").view(np.uint64).ravel()
    return out


def distinct_sets(hashes: np.ndarray, count: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Sorted distinct hashes of each text and how many each has."""
    owner = np.repeat(np.arange(len(count)), count)
    order = np.lexsort((hashes, owner))
    h, o = hashes[order], owner[order]
    new = np.ones(len(h), bool)
    new[1:] = (h[1:] != h[:-1]) | (o[1:] != o[:-1])
    return h[new], np.bincount(o[new], minlength=len(count))


def _slices(values: np.ndarray, count: np.ndarray) -> list[bytes]:
    raw, edge = values.astype("<u8").tobytes(), (8 * np.concatenate([[0], np.cumsum(count)])).tolist()
    return [raw[a:b] for a, b in zip(edge[:-1], edge[1:], strict=True)]


def fingerprints(docs: DataFrame, width: int = 4, words64: int = 1) -> DataFrame:
    """(doc_id, fp, other columns of ``docs`` but text): fingerprint of every whole text.

    One long for 64 bits. Else binary: 8 * words64 bytes from the distinct shingles, then 8 bytes
    that tell their set apart. Null and empty texts and texts without words get fingerprint zero.
    """
    also = [c for c in docs.columns if c not in ("doc_id", "text")]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in pieces(batches, "text", PASS_BYTES):
            raw, off, _ = buffers(b.column(1))
            found = shingle_hashes(raw, off, width)
            if words64 == 1:
                col = pa.array(majority_bits(*found)[:, 0].view(np.int64))
            else:
                found = distinct_sets(*found)
                own = np.fromiter(map(xxhash.xxh64_intdigest, _slices(*found)), np.uint64, b.num_rows)
                col = pa.array([x.tobytes() for x in np.column_stack([majority_bits(*found, words64), own])], pa.binary())
            yield pa.RecordBatch.from_arrays([b.column(0), col, *b.columns[2:]], ["doc_id", "fp", *also])

    kind = {c: docs.schema[c].dataType.simpleString() for c in ["doc_id", *also]}
    more = "".join(f", {c} {kind[c]}" for c in also)
    return docs.select("doc_id", "text", *also).mapInArrow(run, f"doc_id {kind['doc_id']}, fp {'bigint' if words64 == 1 else 'binary'}{more}")


def blocks_for(n: int, max_diff: int) -> int:
    """Least number of blocks at which a fingerprint meets few unrelated ones among ``n``."""
    for m in range(max_diff + 2, 3 * max_diff + 2):
        if n * math.comb(m, max_diff) / 2.0 ** (64 * (m - max_diff) / m) <= 4:
            return m
    return 3 * max_diff + 1


def pigeonhole_keys(nodes: DataFrame, n: int, max_diff: int) -> DataFrame:
    """(key, fp): one row for each combination of blocks; close fingerprints share a key."""
    m = blocks_for(n, max_diff)
    cuts = [64 * i // m for i in range(m + 1)]
    block = [((1 << (b - a)) - 1) << a for a, b in zip(cuts, cuts[1:], strict=False)]
    masks = [sum(block[i] for i in c) for c in combinations(range(m), m - max_diff)]
    signed = [x - (1 << 64) if x >> 63 else x for x in masks]
    keys = F.array(*[F.xxhash64(F.lit(i), F.col("fp").bitwiseAND(F.lit(x))) for i, x in enumerate(signed)])
    return nodes.select(F.explode(keys).alias("key"), "fp")


def band_plan(n: int, bits: int, similarity: float, recall: float, sure: float) -> tuple[int, int, int]:
    """(bits of a block, blocks, largest Hamming distance) for shingle-set similarity at the bound."""
    share = math.acos(2 * similarity / (1 + similarity)) / math.pi
    width = min(40, max(16, math.ceil(math.log2(max(n, 2))) - 4))
    hit = (1 - share) ** width
    return width, math.ceil(math.log(1 - recall) / math.log(1 - hit)), round(bits * share + sure * math.sqrt(bits * share * (1 - share)))


def band_keys(sims: DataFrame, width: int, bands: int, words64: int) -> DataFrame:
    """(key, fp): blocks of ``width`` bits cut from fixed permutations of the fingerprint's bits."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rng, bits = np.random.default_rng(7), 64 * words64
        per = bits // width
        cuts = np.concatenate([rng.permutation(bits)[: per * width].reshape(per, width) for _ in range(-(-bands // per))])[:bands]
        weight = np.uint64(1) << np.arange(width, dtype=np.uint64)
        for big in batches:
            for at in range(0, big.num_rows, 4096):
                b = big.slice(at, 4096)
                m = np.unpackbits(buffers(b.column(0))[0].reshape(b.num_rows, -1), axis=1, bitorder="little").astype(np.uint64)
                keys = np.stack([mix((m[:, c] * weight).sum(1) + np.uint64(i << 44)) for i, c in enumerate(cuts)], axis=1)
                edges = pa.array(np.arange(b.num_rows + 1, dtype=np.int32) * np.int32(len(cuts)))
                yield pa.RecordBatch.from_arrays([pa.ListArray.from_arrays(edges, pa.array(keys.view(np.int64).ravel())), b.column(0)], ["keys", "fp"])
        trim()

    return sims.select("fp").mapInArrow(run, "keys array<bigint>, fp binary").select(F.explode("keys").alias("key"), "fp")


def forest(fp: np.ndarray, max_diff: int) -> list[tuple[int, int]]:
    """Links, as index pairs, that connect what the graph of rows at ``max_diff`` or fewer differing bits connects.

    fp: (n, words64). Each component is a star around its least fingerprint, so that buckets
    which hold the same fingerprints give the same links.
    """
    if len(fp) == 2:
        return [(0, 1)] if int(np.bitwise_count(fp[0] ^ fp[1]).sum()) <= max_diff else []
    rest, out = np.lexsort(fp.T[::-1]), []
    while len(rest):
        seed, rest = int(rest[0]), rest[1:]
        queue = [seed]
        while queue and len(rest):
            near = np.bitwise_count(fp[rest] ^ fp[queue.pop()]).sum(1) <= max_diff
            found = rest[near].tolist()
            out += [(seed, x) for x in found]
            queue += found
            rest = rest[~near]
    return out


def hot_keys(keyed: DataFrame, one_in: int = 1) -> DataFrame:
    """(key, parts) of the keys that more than CHUNK fingerprints meet, counted on one in ``one_in`` of them.

    Only the size of groups rests on the count, not what is compared.
    """
    bound = CHUNK if one_in == 1 else max(1, CHUNK // one_in // 2)
    return keyed.groupBy("key").count().where(F.col("count") > bound).select("key", F.ceil(F.col("count") * one_in / CHUNK).cast("int").alias("parts"))


def buckets(keyed: DataFrame, hot: DataFrame) -> DataFrame:
    """(fps) of the groups of fingerprints that share a key; those of ``hot`` keys are dealt out as pairs of chunks.

    ``keyed`` has a row (key, fp) for each key of each distinct fingerprint.
    """
    n_hot = hot.count()
    if n_hot:
        near = keyed.join(maybe_broadcast(hot, n_hot), "key", "left").withColumn("parts", F.greatest(F.coalesce("parts", F.lit(1)), F.lit(1)))
        near = near.select("key", "fp", F.explode(chunk_pairs(F.col("fp"), F.col("parts"))).alias("pair"))
        return near.groupBy("key", "pair").agg(F.collect_list("fp").alias("fps")).where(F.size("fps") > 1).select("fps")
    return keyed.groupBy("key").agg(F.collect_list("fp").alias("fps")).where(F.size("fps") > 1).select("fps")


def chunk_pairs(item, parts):
    """The pairs of chunks, out of ``parts``, that an item takes part in."""
    part = F.pmod(F.xxhash64(item, F.lit(1)), parts).cast("int")
    return F.transform(F.sequence(F.lit(0), parts - 1), lambda j: F.struct(F.least(part, j).alias("i"), F.greatest(part, j).alias("j")))


def links(keyed: DataFrame, max_diff: int, words64: int = 1, hot: DataFrame | None = None) -> DataFrame:
    """Links (u, v), by node id, between fingerprints that share a key and differ in few bits."""
    groups = buckets(keyed, materialise(hot_keys(keyed), "hot") if hot is None else hot)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            u: list = []
            v: list = []
            flat = b.column(0).flatten()
            if words64 == 1:
                fp = np.asarray(flat).view(np.uint64).reshape(-1, 1)
            else:
                fp = buffers(flat)[0].view(np.uint64).reshape(-1, words64)
            size = np.asarray(b.column(0).value_lengths(), np.int64)
            end = np.cumsum(size)
            for k in _near_groups(fp, size, end, max_diff).tolist():
                at = int(end[k] - size[k])
                for x, y in forest(fp[at : end[k]], max_diff):
                    u.append(at + x)
                    v.append(at + y)
            if u:
                yield pa.RecordBatch.from_arrays([flat.take(pa.array(u)), flat.take(pa.array(v))], ["a", "b"])
        trim()

    kind = "bigint" if words64 == 1 else "binary"
    found = groups.mapInArrow(run, f"a {kind}, b {kind}")
    node = (lambda c: F.col(c)) if words64 == 1 else (lambda c: F.xxhash64(c))
    return found.select(F.least(node("a"), node("b")).alias("u"), F.greatest(node("a"), node("b")).alias("v")).distinct()


def _near_groups(fp: np.ndarray, size: np.ndarray, end: np.ndarray, max_diff: int, small: int = 32) -> np.ndarray:
    """Groups that may have a link: of the small ones, those with a close pair; all larger ones."""
    found = size > small
    group = np.repeat(np.arange(len(size)), size)
    left = np.repeat(end, size) - np.arange(len(fp))
    left[found[group]] = 0
    for step in range(1, small):
        at = np.flatnonzero(left > step)
        if not len(at):
            break
        near = np.bitwise_count(fp[at] ^ fp[at + step]).sum(1) <= max_diff
        found[group[at[near]]] = True
    return np.flatnonzero(found)


def similar_sets(values: np.ndarray, count: np.ndarray, similarity: float) -> list[tuple[int, int]]:
    """Links, as index pairs, that connect what Jaccard similarities of ``similarity`` or more connect.

    values: the sets' members one set after another, count: the size of each. A set is compared
    with all that no link has reached yet, by one pass over their members. An empty set has no link.
    """
    code = np.asarray(pa.array(values).dictionary_encode().indices)
    flag = np.zeros(int(code.max()) + 1 if len(code) else 0, bool)
    start = np.cumsum(count) - count
    rest, out = np.flatnonzero(count), []
    held = code if len(rest) == len(count) else code[ragged(start[rest], count[rest])]
    while len(rest) > 1:
        seed, rest = int(rest[0]), rest[1:]
        held = held[count[seed] :]
        queue = [seed]
        while queue and len(rest):
            x = queue.pop()
            own = code[start[x] : start[x] + count[x]]
            flag[own] = True
            size = count[rest]
            both = np.add.reduceat(flag[held], np.cumsum(size) - size, dtype=np.int64)
            flag[own] = False
            near = both >= similarity * (count[x] + size - both)
            if near.any():
                found = rest[near].tolist()
                out += [(seed, y) for y in found]
                queue += found
                held, rest = held[np.repeat(~near, size)], rest[~near]
    return out


def similar_links(docs: DataFrame, members: DataFrame, width: int, similarity: float) -> DataFrame:
    """Links (u, v) between members of one group whose whole shingle sets are similar.

    members: (id, g, __id, __hash): node, group, and the doc_id and text hash of a row that has its text.
    """
    meet = docs["doc_id"].eqNullSafe(F.col("__id")) & (docs["__text"] == F.col("__hash"))
    texts = docs.join(maybe_broadcast(members, members.count()), meet).select("id", "g", "text")

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in pieces(batches, "text", PASS_BYTES):
            raw, off, _ = buffers(b.column(2))
            found = _slices(*distinct_sets(*shingle_hashes(raw, off, width)))
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(found, pa.binary())], ["id", "g", "shingles"])
            del raw, off, found
        trim()

    sets = materialise(texts.mapInArrow(read, "id bigint, g bigint, shingles binary"), "sets")
    large = sets.groupBy("g").agg(F.sum(F.length("shingles")).alias("bytes")).where(F.col("bytes") > SET_BYTES)
    large = materialise(large.select("g", F.ceil(F.col("bytes") / SET_BYTES).cast("int").alias("parts")), "large")
    n_large = large.count()
    if n_large:
        dealt = sets.join(maybe_broadcast(large, n_large), "g", "left").withColumn("parts", F.coalesce("parts", F.lit(1)))
        dealt = dealt.select("g", F.explode(chunk_pairs(F.col("id"), F.col("parts"))).alias("pair"), "id", "shingles")
    else:
        dealt = sets.select("g", F.struct(F.lit(0).alias("i"), F.lit(0).alias("j")).alias("pair"), "id", "shingles")
    dealt = dealt.select(F.xxhash64("g", "pair").alias("group"), "g", "id", "shingles")

    def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[int, bytes] = {}
        last = None

        def close() -> pa.RecordBatch:
            ids, data = np.array(list(held), np.int64), list(held.values())
            found = similar_sets(np.frombuffer(b"".join(data), "<u8"), np.array([len(x) // 8 for x in data], np.int64), similarity)
            pair = np.array(found, np.int64).reshape(-1, 2)
            return pa.RecordBatch.from_arrays([pa.array(ids[pair[:, 0]]), pa.array(ids[pair[:, 1]])], ["u", "v"])

        for b in batches:
            for group, g, node, data in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), b.column(2).to_pylist(), b.column(3), strict=True):
                if last != (group, g):
                    if len(held) > 1:
                        yield close()
                    held, last = {}, (group, g)
                held[node] = data.as_buffer().to_pybytes()
        if len(held) > 1:
            yield close()
        held = {}
        trim()

    # groups come one after another, sorted by Spark, so that a task holds one of them at a time
    return dealt.repartition("group", "g").sortWithinPartitions("group", "g").mapInArrow(compare, "u bigint, v bigint")


def similar_roots(docs: DataFrame, nodes: DataFrame, words64: int, width: int, similarity: float, recall: float, sure: float) -> DataFrame:
    """(id, root) of the nodes that similar shingle sets link.

    Nodes whose fingerprints blocks and distances connect are a group; links are sought within groups by whole sets.
    """
    sims = materialise(nodes.select(F.substring("fp", 1, 8 * words64).alias("fp")).distinct(), "sims")
    n = sims.count()
    block, bands, max_diff = band_plan(n, 64 * words64, similarity, recall, sure)
    some = sims.where(F.pmod(F.xxhash64("fp", F.lit(2)), F.lit(SAMPLE)) == 0)
    hot = materialise(hot_keys(band_keys(some, block, bands, words64), SAMPLE), "hot")
    near = components(materialise(links(band_keys(sims, block, bands, words64), max_diff, words64, hot), "near"))
    own = nodes.select("id", "src", F.xxhash64(F.substring("fp", 1, 8 * words64)).alias("sim"))
    own = own.join(maybe_broadcast(near.select(F.col("id").alias("sim"), "root"), near.count()), "sim", "left").select("id", "src", F.coalesce("root", "sim").alias("g"))
    own = materialise(own, "groups")
    shared = materialise(own.groupBy("g").count().where("count > 1").select("g"), "shared")
    members = own.join(maybe_broadcast(shared, shared.count()), "g", "left_semi").select("id", "g", F.col("src.doc_id").alias("__id"), F.col("src.__text").alias("__hash"))
    return components(materialise(similar_links(docs, materialise(members, "members"), width, similarity), "similar"))


def linked(docs: DataFrame, width: int, words64: int, max_diff: int | None, similarity: float, recall: float, sure: float) -> tuple[DataFrame, DataFrame, DataFrame, int]:
    """(fingerprints of all rows with ``docs``' other columns, nodes (fp, rep, id), (id, root) of the linked nodes, number of nodes)."""
    if words64 > 1:
        docs = docs.select("doc_id", "text", F.xxhash64("text").alias("__text"))
    made = materialise(fingerprints(docs, width, words64), "fingerprints")
    node_id = F.col("fp") if words64 == 1 else F.xxhash64("fp")
    source = [] if words64 == 1 else [F.min(F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "__text")).alias("src")]
    nodes = materialise(made.groupBy("fp").agg(F.min("doc_id").alias("rep"), *source).withColumn("id", node_id), "nodes")
    n = nodes.count()
    if max_diff is None:
        return made, nodes, similar_roots(docs, nodes, words64, width, similarity, recall, sure), n
    keyed = pigeonhole_keys(nodes, n, max_diff)
    return made, nodes, components(materialise(links(keyed, max_diff, words64), "edges")), n


def near_duplicates(
    docs: DataFrame,
    width: int = 4,
    words64: int = 1,
    max_diff: int | None = 4,
    similarity: float = 0.8,
    recall: float = RECALL,
    sure: float = SURE,
) -> DataFrame:
    """(doc_id, fp, component_id) of every row of ``docs`` (doc_id, text).

    With ``max_diff``: exact links at that many or fewer differing bits of 64. With
    ``max_diff=None`` (and ``words64`` of 2 or more): links at ``similarity`` or more of the whole
    shingle sets, sought among texts that blocks and distances of ``64 * words64`` bits connect.
    component_id is the least doc_id reachable over links, equal fingerprints (sets, where wide)
    included. Wide fingerprints are identified by a 64-bit hash in the link table. Rows with a null doc_id take part and count as the largest id. An empty table
    gives no rows. Extra columns of ``docs`` are ignored.
    """
    made, nodes, roots, n = linked(docs.select("doc_id", "text"), width, words64, max_diff, similarity, recall, sure)
    n_roots = roots.count()
    least = roots.join(nodes.select("id", "rep"), "id").groupBy("root").agg(F.min("rep").alias("component_id"))
    least = materialise(least, "least")
    member = materialise(
        roots.join(maybe_broadcast(least, least.count()), "root").select("id", "component_id"), "members"
    )
    final = materialise(
        nodes.join(maybe_broadcast(member, n_roots), "id", "left").select("fp", F.coalesce("component_id", "rep").alias("component_id")), "classes"
    )
    wide = n * words64 <= BROADCAST_ROWS
    out = made.join(F.broadcast(final) if wide else final, "fp")
    return out.select("doc_id", "fp" if words64 == 1 else F.substring("fp", 1, 8 * words64).alias("fp"), "component_id")


def keep_one(
    docs: DataFrame,
    width: int = 4,
    words64: int = 1,
    max_diff: int | None = 4,
    similarity: float = 0.8,
    recall: float = RECALL,
    sure: float = SURE,
) -> DataFrame:
    """``docs`` with one row of each near-duplicate group (the least doc_id, nulls last, then the least text hash).

    Columns are those of ``docs``. Rows are told apart by doc_id and a 64-bit hash of the text, so
    that null and repeated ids neither drop nor keep a row of another group.
    """
    made, _, roots, _ = linked(docs.select("doc_id", "text", F.xxhash64("text").alias("__text")), width, words64, max_diff, similarity, recall, sure)
    node_id = F.col("fp") if words64 == 1 else F.xxhash64("fp")
    row = made.select("doc_id", "__text", node_id.alias("id"))
    found = row.join(maybe_broadcast(roots, roots.count()), "id", "left").select("doc_id", "__text", F.coalesce("root", "id").alias("root"))
    found = materialise(found.groupBy("root", "doc_id", "__text").agg(F.count(F.lit(1)).alias("n")), "groups")
    order = F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "__text")
    # groups of one kind of row lose none
    first = materialise(
        found.groupBy("root").agg(F.min(order).alias("first"), F.count(F.lit(1)).alias("kinds")).where("kinds > 1").select("root", "first"), "first"
    )
    gone = materialise(
        found.join(maybe_broadcast(first, first.count()), "root").where(~order.eqNullSafe(F.col("first"))).select(F.col("doc_id").alias("__id"), F.col("__text").alias("__gone")), "gone"
    )
    again = materialise(found.where("n > 1").select(F.col("doc_id").alias("__id"), F.col("__text").alias("__again")), "again")

    def meet(other: DataFrame, name: str):
        return docs["doc_id"].eqNullSafe(other["__id"]) & (F.xxhash64(docs["text"]) == other[name])

    stay = docs.join(maybe_broadcast(gone, gone.count()), meet(gone, "__gone"), "left_anti")
    n = again.count()
    if n:
        twice = stay.join(maybe_broadcast(again, n), meet(again, "__again"), "left_semi").withColumn("__text", F.xxhash64("text")).dropDuplicates(["doc_id", "__text"]).drop("__text")
        stay = stay.join(maybe_broadcast(again, n), meet(again, "__again"), "left_anti").unionByName(twice)
    return stay


def query(spark, sf_dir: str) -> DataFrame:
    """The contract's columns for ``documents``: 4-word shingles, 64 bits, 4 or fewer differing bits."""
    out = near_duplicates(spark.read.parquet(f"{sf_dir}/documents.parquet"), width=4, max_diff=4)
    return out.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")
