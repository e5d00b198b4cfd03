"""Quality classifier by co-training of two views (operator 9).

View one is the text's content: words, case-keeping byte grams, and layout figures such as lines,
capitals, marks, repeated lines and the share of distinct words. View two is what is stored beside
the text and never looks into it: language, source, both together, and the declared length in
steps. Both start from the labelled sample; in each
round each view labels the texts of an unlabelled pool that it is surest of, if it has shown on labelled
rows that such labels are right, and the other view learns from them. Each view is then calibrated on labelled rows kept aside and the calibrated
log-odds are combined by a small logistic model.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import SPACE_TABLE, buffers, byte_table, doc_bucket, hash_words, pieces, words
from .learning import Chosen, calibrate, drawn, fit_logistic, list_column, presence, sigmoid, text_buckets

#: Bounds of the labelled sample and of the pool, buckets of the text view, bytes of a gram.
MOST_LABELLED, MOST_POOL, FEATURES, GRAM = 5000, 4000, 512, 4
#: Rounds, and the share of the pool that a view hands over in each.
ROUNDS, SHARE = 5, 0.05
#: Share of right labels, and how many of them, that a view must show on labelled rows before it hands labels over.
SURE, PROVEN = 0.98, 20
#: Bound of the text bytes of each sample.
MOST_BYTES = 64 << 20
#: Hash slots for languages, for sources and for both; steps of the declared length (powers of two).
SLOTS, STEPS = 32, 24
_LINES = byte_table([0x0A], lower=False)
_CLASSES = [
    np.isin(np.arange(256), list(range(65, 91))),
    np.isin(np.arange(256), list(b"#*$%&|<>")),
    np.isin(np.arange(256), list(b"!?=~^_+@\\/[]{}")),
    np.isin(np.arange(256), list(range(48, 58))),
    np.isin(np.arange(256), list(b".,;:")),
]
N_LAYOUT = 7 + len(_CLASSES)


def _distinct(owner: np.ndarray, h: np.ndarray, n: int) -> np.ndarray:
    """Distinct hashes of each text."""
    key = np.unique(owner.astype(np.uint64) << np.uint64(44) | h >> np.uint64(20))
    return np.bincount((key >> np.uint64(44)).astype(np.int64), minlength=n)


def layout(raw: np.ndarray, off: np.ndarray) -> np.ndarray:
    """Dense layout figures of each text, a part of the text view."""
    n = len(off) - 1
    out = np.zeros((n, N_LAYOUT), np.float32)
    low, starts, ends, bound = words(raw, off, SPACE_TABLE)
    owner = np.repeat(np.arange(n), np.diff(bound))
    n_words = np.diff(bound)
    chars = np.bincount(owner, weights=ends - starts, minlength=n)
    for k, c in enumerate(_CLASSES):
        total = np.concatenate([[0], np.cumsum(c[raw], dtype=np.int64)])
        out[:, 7 + k] = np.sqrt((total[off[1:]] - total[off[:-1]]) / np.maximum(chars, 1))
    _, a, b, line_bound = words(raw, off, _LINES)
    n_lines = np.diff(line_bound)
    line_owner = np.repeat(np.arange(n), n_lines)
    some = np.maximum(n_words, 1)
    out[:, 0] = np.log1p(n_words)
    out[:, 1] = np.log1p(chars / some)
    out[:, 2] = np.log1p(n_lines)
    out[:, 3] = np.sqrt(1 - _distinct(line_owner, hash_words(raw, a, b), n) / np.maximum(n_lines, 1)) * (n_lines > 0)
    out[:, 4] = _distinct(owner, hash_words(low, starts, ends), n) / some
    out[:, 5] = np.log1p(n_words / np.maximum(n_lines, 1))
    out[:, 6] = (n_words < 20).astype(np.float32)
    return out


def metadata_view(lang: list, source: list, n_chars: np.ndarray) -> np.ndarray:
    """Dense rows: the declared length and its step, one slot each of the language, the source and of both."""
    n = len(lang)
    out = np.zeros((n, 1 + STEPS + 3 * SLOTS), np.float32)
    length = np.log2(np.maximum(n_chars, 0) + 1.0)
    out[:, 0] = length
    rows = np.arange(n)
    out[rows, 1 + np.minimum(STEPS - 1, length).astype(np.int64)] = 1
    text = [("" if v is None else str(v), "" if w is None else str(w)) for v, w in zip(lang, source, strict=True)]
    for k, values in enumerate(([v for v, _ in text], [w for _, w in text], [f"{v}\0{w}" for v, w in text])):
        at = {v: zlib.crc32(v.encode()) % SLOTS for v in set(values)}
        out[rows, 1 + STEPS + k * SLOTS + np.array([at[v] for v in values], np.int64)] = 1
    return out


@dataclass
class Model:
    """Both views, their scaling and their combination. The text view's weights: chosen buckets, layout figures, bias."""

    chosen: Chosen
    text: np.ndarray
    layout: tuple[np.ndarray, np.ndarray]
    centre: np.ndarray
    scale: np.ndarray
    meta: np.ndarray
    calibration: list[tuple[float, float]]
    mix: np.ndarray

    def scores(self, f_text: np.ndarray, f_meta: np.ndarray) -> np.ndarray:
        """(rows, 3): calibrated text score, calibrated metadata score, combined score."""
        f = np.stack([a * x + b for (a, b), x in zip(self.calibration, (f_text, f_meta), strict=True)], axis=1)
        both = sigmoid(np.clip(f, -8, 8) @ self.mix[:-1] + self.mix[-1])
        return np.column_stack([sigmoid(f), both])


def confident(x: np.ndarray, y: np.ndarray) -> tuple[float, float]:
    """(least probability of good, largest of bad) from which a view's labels can be trusted.

    Judged on labelled rows that the judging fit did not see (two halves): the widest bounds,
    beyond 0.9 and under 0.1, at which SURE of the rows have the label and PROVEN rows do. A view
    that never proves itself gets bounds that no row reaches.
    """
    half = np.arange(len(y)) % 2 == 0
    p = np.full(len(y), 0.5)
    for own in (half, ~half):
        if len(np.unique(y[own])) == 2 and (~own).any():
            w = fit_logistic(x[own], y[own])
            p[~own] = sigmoid(x[~own] @ w[:-1] + w[-1])

    def bound(q: np.ndarray, right: np.ndarray) -> float:
        order = np.argsort(-q, kind="stable")
        hits = np.cumsum(right[order])
        good = np.flatnonzero((hits >= SURE * np.arange(1, len(q) + 1)) & (hits >= PROVEN) & (q[order] > 0.9))
        return float(q[order[good[-1]]]) if len(good) else 2.0

    return bound(p, y == 1), 1 - bound(1 - p, y == 0)


def cotrain(x_t: np.ndarray, x_m: np.ndarray, y: np.ndarray, u_t: np.ndarray, u_m: np.ndarray, rounds: int = ROUNDS, share: float = SHARE) -> tuple[np.ndarray, np.ndarray]:
    """Weights of the text and of the metadata view after rounds of exchanged pseudo-labels."""
    given = [(np.zeros(0, np.int64), np.zeros(0)), (np.zeros(0, np.int64), np.zeros(0))]
    rate = float(y.mean())
    free = np.ones(len(u_t), bool)
    views = ((x_t, u_t), (x_m, u_m))
    trusted = [confident(x, y) for x, _ in views]

    def fit(v: int) -> np.ndarray:
        at, label = given[v]
        x, u = views[v]
        return fit_logistic(np.vstack([x, u[at]]), np.concatenate([y, label]), np.concatenate([np.ones(len(y)), np.full(len(at), 0.5)]))

    w = [fit(0), fit(1)]
    for _ in range(rounds):
        count = int(share * len(u_t))
        if not free.any() or not count:
            break
        for v in (0, 1):
            p = sigmoid(views[v][1] @ w[v][:-1] + w[v][-1])
            idx = np.flatnonzero(free)
            order = idx[np.argsort(p[idx], kind="stable")]
            low, high = order[: max(1, int(count * (1 - rate)))], order[::-1][: max(1, int(count * rate))]
            low, high = low[p[low] <= trusted[v][1]], high[p[high] >= trusted[v][0]]
            at, label = given[1 - v]
            given[1 - v] = (np.concatenate([at, low, high]), np.concatenate([label, np.zeros(len(low)), np.ones(len(high))]))
            free[low] = free[high] = False
        w = [fit(0), fit(1)]
    return w[0], w[1]


def _views(docs: DataFrame) -> DataFrame:
    """(y, buckets, layout, meta) of a bounded sample of rows."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in pieces(batches, "text", 1 << 20):
            raw, off, _ = buffers(b.column(1))
            flat, count = presence(*text_buckets(raw, off, GRAM, False), b.num_rows)
            meta = metadata_view(b.column(2).to_pylist(), b.column(3).to_pylist(), np.array(b.column(4).fill_null(0)))
            dense = [pa.ListArray.from_arrays(pa.array(np.arange(b.num_rows + 1, dtype=np.int32) * np.int32(m.shape[1])), pa.array(m.ravel(), pa.float32())) for m in (layout(raw, off), meta)]
            yield pa.RecordBatch.from_arrays([b.column(0), list_column(flat, count), *dense], ["y", "buckets", "layout", "meta"])

    return docs.mapInArrow(run, "y int, buckets array<int>, layout array<float>, meta array<float>")


def _columns(docs: DataFrame) -> list:
    """text, lang, source, n_chars as the views take them; absent columns count as null."""
    have = set(docs.columns)
    return [
        docs["text"],
        (docs["lang"].cast("string") if "lang" in have else F.lit(None).cast("string")).alias("lang"),
        (docs["source"].cast("string") if "source" in have else F.lit(None).cast("string")).alias("source"),
        (F.coalesce(docs["n_chars"].cast("long"), F.lit(0)) if "n_chars" in have else F.lit(0).cast("long")).alias("n_chars"),
    ]


def train(docs: DataFrame, labels: DataFrame) -> Model | None:
    """Fit on bounded samples of ``docs``; ``labels`` (doc_id, quality) holds the rows that may be learnt from.

    Rows with a null id or label are ignored; repeated labels of a row count as good if any is.
    None where the labels lack one of the classes: there is nothing to tell apart.
    """
    known = labels.where("doc_id is not null and quality is not null").groupBy("doc_id").agg(F.max("quality").cast("int").alias("y"))
    known = drawn(known, MOST_LABELLED, 21)
    rows = docs.where("doc_id is not null")
    # both samples in one pass; the label table is bounded by MOST_LABELLED rows
    order = F.xxhash64("doc_id", F.lit(23)).alias("at")
    labelled = drawn(rows.join(F.broadcast(known), "doc_id"), 2 * MOST_LABELLED, 21, MOST_BYTES).select(F.col("y"), *_columns(docs), order)
    pool = drawn(rows, MOST_POOL, 22, MOST_BYTES).select(F.lit(-1).alias("y"), *_columns(docs), order)
    # in the order of a hash, so that neither the fit nor the rows kept aside depend on how the table lies in files
    got = _views(labelled.unionByName(pool).orderBy("y", "at", F.xxhash64("text")).drop("at")).toArrow()
    y = np.asarray(got.column("y").combine_chunks() if got.num_rows else [], np.int64)
    if not (y == 0).any() or not (y == 1).any():
        return None
    lists = got.column("buckets").combine_chunks()
    flat, count = np.asarray(lists.flatten(), np.int32), np.asarray(lists.value_lengths(), np.int64)
    meta, figures = (np.asarray(got.column(c).combine_chunks().flatten(), np.float32).reshape(len(y), -1) for c in ("meta", "layout"))
    lab = y >= 0
    kept = np.repeat(lab, count)
    chosen = Chosen.by_contrast(flat[kept], count[lab], y[lab] == 0, FEATURES)
    scaled = (figures[lab].mean(0), np.maximum(figures[lab].std(0), 0.05))
    x = np.hstack([chosen.matrix(flat, count), np.clip((figures - scaled[0]) / scaled[1], -8, 8).astype(np.float32)])
    centre, scale = meta[lab].mean(0), np.maximum(meta[lab].std(0), 0.05)
    m = np.clip((meta - centre) / scale, -8, 8)
    # one of four in the order of the hash, within each class
    place = np.zeros(len(y), np.int64)
    for c in (-1, 0, 1):
        place[y == c] = np.arange(int((y == c).sum()))
    aside = lab & (place % 4 == 3)
    if len(np.unique(y[aside])) < 2 or len(np.unique(y[lab & ~aside])) < 2:
        aside = lab
        fit = lab
    else:
        fit = lab & ~aside
    w_t, w_m = cotrain(x[fit], m[fit], y[fit].astype(float), x[~lab], m[~lab])
    f_t, f_m = x[aside] @ w_t[:-1] + w_t[-1], m[aside] @ w_m[:-1] + w_m[-1]
    cal = [calibrate(f_t, y[aside].astype(float)), calibrate(f_m, y[aside].astype(float))]
    f = np.stack([np.clip(cal[0][0] * f_t + cal[0][1], -8, 8), np.clip(cal[1][0] * f_m + cal[1][1], -8, 8)], axis=1)
    return Model(chosen, w_t, scaled, centre, scale, w_m, cal, fit_logistic(f, y[aside].astype(float), l2=1e-3))


NAMES = ("text_score", "meta_score", "score")


def score(docs: DataFrame, model: Model | None, names: tuple[str, str, str] = NAMES) -> DataFrame:
    """``docs`` with the scores of the text view, of the metadata view and of both (0 to 1; higher: good quality likelier).

    Every row is scored over its whole text; null texts count as empty, null or absent lang,
    source and n_chars as unknown. Without a model all scores are 1. Columns of the three
    names are replaced, all others pass through.
    """
    base = docs.drop(*names)
    if model is None:
        return base.withColumns({c: F.lit(1.0) for c in names})
    shared = docs.sparkSession.sparkContext.broadcast(model)
    fields = base.columns
    fed = base.select(*fields, F.struct(*_columns(base)[1:]).alias("__view"))
    schema = base.withColumns({c: F.lit(0.0) for c in names}).schema
    at = fields.index("text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = shared.value
        for b in pieces(batches, "text", 1 << 20):
            raw, off, _ = buffers(b.column(at))
            view = b.column(len(fields))
            lang, source, n_chars = view.flatten()
            meta = metadata_view(lang.to_pylist(), source.to_pylist(), np.array(n_chars))
            f_meta = np.clip((meta - m.centre) / m.scale, -8, 8) @ m.meta[:-1] + m.meta[-1]
            k = m.chosen.size
            f_text = m.chosen.sums(*text_buckets(raw, off, GRAM, False), b.num_rows, np.append(m.text[:k], 0.0))
            f_text += np.clip((layout(raw, off) - m.layout[0]) / m.layout[1], -8, 8) @ m.text[k:-1] + m.text[-1]
            s = m.scores(f_text, f_meta)
            yield pa.RecordBatch.from_arrays([*b.columns[:-1], *(pa.array(s[:, k]) for k in range(3))], schema=pa.schema([*list(b.schema)[:-1], *(pa.field(c, pa.float64()) for c in names)]))

    return fed.mapInArrow(run, schema)


def query(spark, sf_dir: str) -> DataFrame:
    """Scores of all ``documents``; labels of rows whose crc32(doc_id as text) mod 4 is 2 are held out."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet").where(doc_bucket("doc_id", 4) != 2)
    scored = score(docs, train(docs.where(doc_bucket("doc_id", 4) != 2), labels))
    return scored.select(
        "doc_id", (doc_bucket("doc_id", 4) == 2).alias("held_out"), "text_score", "meta_score", "score", (F.col("score") >= 0.5).cast("int").alias("predicted"), (F.col("score") >= 0.5).alias("kept")
    )
