"""Hashed text features and small numpy models that the trained operators share.

Training rows are drawn by a 64-bit hash of doc_id at a rate set from counts, so a sample's expected
size stays at its bound for any input, in rows and in bytes of text; only hashed features of
sampled rows reach the driver.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import BYTE_HASH, hash_words, mix, words
from .decontaminate import TABLE as WORD_TABLE

#: log2 of the number of hash buckets.
BITS = 18
_SHIFT = np.uint64(64 - BITS)


def share(bound: int, n: int) -> int | None:
    """The 64-bit hash under which about ``bound`` of ``n`` rows fall; None where all do."""
    return None if n <= bound else -(1 << 63) + max(1, (bound << 64) // n)


def drawn(rows: DataFrame, bound: int, salt: int, most_bytes: int | None = None) -> DataFrame:
    """Rows of a hash sample of about ``bound`` rows at most; all of them if there are no more.

    A row is in by the 64-bit hash of its doc_id alone, so that the sample does not depend on order or
    layout, and its expected size is the bound for any number of rows. ``most_bytes`` bounds the
    texts' bytes as well: the sample ends, in the order of the hash, where they are reached (at
    least one id stays).
    """
    limit = share(bound, rows.count())
    at = F.xxhash64("doc_id", F.lit(salt))
    out = rows if limit is None else rows.where(at < limit)
    if most_bytes is None:
        return out
    sizes = out.select(at.alias("at"), F.coalesce(F.octet_length("text"), F.lit(0)).alias("n")).groupBy("at").agg(F.sum("n").alias("n"))
    total, last = 0, None
    # as many rows as the sample has, two numbers each
    for r in sorted(sizes.collect(), key=lambda r: r["at"]):
        total += r["n"]
        if total > most_bytes and last is not None:
            return out.where(at <= last)
        last = r["at"]
    return out


def text_buckets(raw: np.ndarray, off: np.ndarray, gram: int, lower: bool) -> tuple[np.ndarray, np.ndarray]:
    """(text, bucket) of every word (lowered) and every byte gram of concatenated texts, repeats included."""
    low, starts, ends, bound = words(raw, off, WORD_TABLE)
    texts = np.arange(len(off) - 1, dtype=np.int32)
    owner = np.repeat(texts, np.diff(bound))
    bucket = (hash_words(low, starts, ends) >> _SHIFT).astype(np.int32)
    src = low if lower else raw
    n = len(src) - gram + 1
    if n <= 0:
        return owner, bucket
    value = BYTE_HASH[src]
    h = np.zeros(n, np.uint64)
    for k in range(gram):
        h = h * np.uint64(0x9E3779B97F4A7C15) + value[k : k + n]
    size = np.diff(off)
    whole = np.repeat(texts, size)[:n]
    inside = np.ones(n, bool)
    for k in range(1, gram):
        edge = off[1:-1] - k
        inside[edge[(edge >= 0) & (edge < n)]] = False
    grams = (mix(h) >> _SHIFT).astype(np.int32)
    return np.concatenate([owner, whole[inside]]), np.concatenate([bucket, grams[inside]])


def presence(owner: np.ndarray, bucket: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray]:
    """Distinct buckets of each text: (flat buckets, how many each text has)."""
    key = np.unique(owner.astype(np.int64) << BITS | bucket)
    return (key & ((1 << BITS) - 1)).astype(np.int32), np.bincount(key >> BITS, minlength=n)


def list_column(flat: np.ndarray, count: np.ndarray) -> pa.Array:
    """Arrow list<int> of ragged rows."""
    offsets = np.zeros(len(count) + 1, np.int32)
    np.cumsum(count, out=offsets[1:])
    return pa.ListArray.from_arrays(pa.array(offsets), pa.array(flat, pa.int32()))


class Chosen:
    """Buckets that a model looks at, and dense presence matrices over them."""

    def __init__(self, buckets: np.ndarray) -> None:
        self.table = np.full(1 << BITS, -1, np.int16)
        self.table[buckets] = np.arange(len(buckets))
        self.size = len(buckets)

    @classmethod
    def by_contrast(cls, flat: np.ndarray, count: np.ndarray, first: np.ndarray, most: int, least: int = 5) -> Chosen:
        """The buckets whose presence differs most, in standard deviations, between ``first`` rows and the others."""
        owner = np.repeat(first, count)
        a = np.bincount(flat[owner], minlength=1 << BITS).astype(float)
        b = np.bincount(flat[~owner], minlength=1 << BITS).astype(float)
        na, nb = max(int(first.sum()), 1), max(int((~first).sum()), 1)
        p = (a + b + 1) / (na + nb + 2)
        z = np.abs(a / na - b / nb) / np.sqrt(p * (1 - p) * (1 / na + 1 / nb))
        z[a + b < least] = 0
        order = np.argsort(-z, kind="stable")[:most]
        return cls(np.sort(order[z[order] > 0]))

    def matrix(self, flat: np.ndarray, count: np.ndarray) -> np.ndarray:
        """Presence (0 or 1) of each chosen bucket in each row."""
        out = np.zeros((len(count), self.size), np.float32)
        at = self.table[flat]
        keep = at >= 0
        out[np.repeat(np.arange(len(count)), count)[keep], at[keep]] = 1
        return out

    def sums(self, owner: np.ndarray, bucket: np.ndarray, n: int, weight: np.ndarray) -> np.ndarray:
        """Sum of the weights of the chosen buckets that are present in each text."""
        at = self.table[bucket]
        keep = at >= 0
        key = np.unique(owner[keep].astype(np.int64) * (self.size + 1) + at[keep])
        return np.bincount(key // (self.size + 1), weights=weight[key % (self.size + 1)], minlength=n)


def sigmoid(x: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(x, -40, 40)))


class Adam:
    """Adam steps on one parameter vector."""

    def __init__(self, n: int, rate: float) -> None:
        self.m, self.v, self.t, self.rate = np.zeros(n), np.zeros(n), 0, rate

    def step(self, w: np.ndarray, g: np.ndarray) -> np.ndarray:
        self.t += 1
        self.m = 0.9 * self.m + 0.1 * g
        self.v = 0.999 * self.v + 0.001 * g * g
        return w - self.rate * (self.m / (1 - 0.9**self.t)) / (np.sqrt(self.v / (1 - 0.999**self.t)) + 1e-8)


def fit_logistic(x: np.ndarray, y: np.ndarray, weight: np.ndarray | None = None, l2: float = 1e-3, steps: int = 150, rate: float = 0.1) -> np.ndarray:
    """Weights, the bias last, of an L2-regularised logistic regression."""
    weight = np.ones(len(y)) if weight is None else weight
    total = max(weight.sum(), 1e-9)
    w, adam = np.zeros(x.shape[1] + 1), Adam(x.shape[1] + 1, rate)
    for _ in range(steps):
        r = (sigmoid(x @ w[:-1].astype(x.dtype) + w[-1]) - y) * weight / total
        w = adam.step(w, np.append(r.astype(x.dtype) @ x + l2 * w[:-1], r.sum()))
    return w


def calibrate(f: np.ndarray, y: np.ndarray) -> tuple[float, float]:
    """Platt's scale and shift of a score."""
    if not len(y) or y.min() == y.max():
        return 1.0, 0.0
    s = float(np.std(f)) or 1.0
    w = fit_logistic((f / s)[:, None], y, l2=1e-4, steps=500)
    return float(w[0] / s), float(w[1])
