"""Toxicity by non-negative positive-unlabelled learning (operator 6).

Confirmed toxic texts are the positives; texts drawn from the whole corpus, labelled or not,
are the unlabelled sample. A linear model on hashed words and byte grams minimises the
class-prior-corrected risk: prior * loss(positives as 1) plus the loss of the unlabelled as 0
less prior * loss(positives as 0), the latter difference kept from falling below zero. The
prior is the share of toxic rows among labelled training rows unless it is given.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import buffers, doc_bucket, pieces
from .learning import Adam, Chosen, drawn, list_column, presence, sigmoid, text_buckets

#: Bounds of the training samples, buckets that the model looks at, bytes of a gram.
MOST_POSITIVE, MOST_UNLABELLED, FEATURES, GRAM = 3000, 6000, 1024, 5
#: Bound of the text bytes of each sample.
MOST_BYTES = 64 << 20


@dataclass
class Model:
    """Chosen buckets, their weights (a zero for padding last) and the bias."""

    chosen: Chosen
    weight: np.ndarray
    bias: float


def nnpu(x_p: np.ndarray, x_u: np.ndarray, prior: float, l2: float = 2e-4, steps: int = 400, rate: float = 0.05, slack: float = 0.0) -> np.ndarray:
    """Weights, the bias last, that minimise the non-negative PU risk under the logistic loss."""
    n_p, n_u = max(len(x_p), 1), max(len(x_u), 1)
    w, adam = np.zeros(x_u.shape[1] + 1), Adam(x_u.shape[1] + 1, rate)
    w[-1] = np.log(prior / (1 - prior))
    for _ in range(steps):
        near = w[:-1].astype(x_u.dtype)
        f_p, f_u = x_p @ near + w[-1], x_u @ near + w[-1]
        negative = np.logaddexp(0, f_u).sum() / n_u - prior * np.logaddexp(0, f_p).sum() / n_p
        d_u, d_p = sigmoid(f_u) / n_u, -prior * sigmoid(f_p) / n_p
        if negative >= -slack:
            d_p = d_p + prior * (sigmoid(f_p) - 1) / n_p
        else:
            d_u, d_p = -d_u, -d_p
        w = adam.step(w, np.append(d_p.astype(x_p.dtype) @ x_p + d_u.astype(x_u.dtype) @ x_u + l2 * w[:-1], d_p.sum() + d_u.sum()))
    return w


def _features(docs: DataFrame) -> DataFrame:
    """(doc_id, flag, buckets) of a bounded sample of texts."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in pieces(batches, "text", 1 << 20):
            raw, off, _ = buffers(b.column(1))
            flat, count = presence(*text_buckets(raw, off, GRAM, True), b.num_rows)
            yield pa.RecordBatch.from_arrays([b.column(0), list_column(flat, count)], ["flag", "buckets"])

    return docs.select("flag", "text").mapInArrow(run, "flag int, buckets array<int>")


def train(docs: DataFrame, labels: DataFrame, prior: float | None = None) -> Model:
    """Fit on bounded samples; ``labels`` (doc_id, toxic) holds the rows that may be learnt from.

    Rows with a null id or label are ignored, repeated label rows count as toxic if any is.
    Without any positive the model scores every text by the prior alone.
    """
    known = labels.where("doc_id is not null and toxic is not null").groupBy("doc_id").agg(F.max("toxic").alias("toxic"))
    share = known.agg(F.avg("toxic"), F.count(F.lit(1))).first()
    if prior is None:
        prior = min(0.9, max(1e-4, share[0] or 1e-4))
    positive = drawn(known.where("toxic = 1"), MOST_POSITIVE, 11).select("doc_id", F.lit(1).alias("flag"))
    texts = docs.select("doc_id", "text").where("doc_id is not null")
    # both bounds hold for each sample; the positives' ids are at most MOST_POSITIVE or so
    found = drawn(texts.join(F.broadcast(positive), "doc_id"), 2 * MOST_POSITIVE, 11, MOST_BYTES)
    picked = found.unionByName(drawn(texts, MOST_UNLABELLED, 12, MOST_BYTES).withColumn("flag", F.lit(0)))
    # order of a hash: the model does not depend on how the table lies in files
    rows = _features(picked.orderBy("flag", F.xxhash64("doc_id", F.lit(13)), F.xxhash64("text"))).toArrow()
    flag = np.asarray(rows.column("flag").combine_chunks() if rows.num_rows else [], np.int64) == 1
    lists = rows.column("buckets").combine_chunks()
    flat, count = np.asarray(lists.flatten(), np.int32), np.asarray(lists.value_lengths(), np.int64)
    if not flag.any() or flag.all():
        return Model(Chosen(np.zeros(0, np.int64)), np.zeros(1), float(np.log(prior / (1 - prior))))
    chosen = Chosen.by_contrast(flat, count, flag, FEATURES)
    x = chosen.matrix(flat, count)
    w = nnpu(x[flag], x[~flag], prior)
    return Model(chosen, np.append(w[:-1], 0.0), float(w[-1]))


def score(docs: DataFrame, model: Model, column: str = "score") -> DataFrame:
    """``docs`` with a column of scores (0 to 1; higher: toxic likelier) from the text alone.

    Null and empty texts get the score of a text without features. Rows are kept one by one,
    repeated rows too; every text is read whole. A column of the same name is replaced.
    """
    shared = docs.sparkSession.sparkContext.broadcast(model)
    base = docs.drop(column)
    at = base.columns.index("text")
    schema = base.withColumn(column, F.lit(0.0)).schema

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = shared.value
        for b in pieces(batches, "text", 1 << 20):
            raw, off, _ = buffers(b.column(at))
            total = m.chosen.sums(*text_buckets(raw, off, GRAM, True), b.num_rows, m.weight)
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(sigmoid(total + m.bias))], [*b.schema.names, column])

    return base.mapInArrow(run, schema)


def query(spark, sf_dir: str) -> DataFrame:
    """The contract's columns for ``documents``; labels of rows held out are not read into the model."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet").where(doc_bucket("doc_id", 4) != 2)
    scored = score(docs, train(docs.where(doc_bucket("doc_id", 4) != 2), labels))
    return scored.select(
        "doc_id",
        (doc_bucket("doc_id", 4) == 2).alias("held_out"),
        "score",
        F.when(F.col("score") >= 0.3, 1).otherwise(0).alias("predicted"),
    )
