"""A corpus pipeline over ``documents``: toxicity, quality, near-duplicates, decontamination, encoding.

Each stage takes (spark, docs, sf_dir) and returns a DataFrame that is written as Parquet and
read again as the next stage's docs. All stages but the last return the columns of ``docs``.
A row with a null text is a text without words: it is scored like any other and, as a duplicate
of every other such text, kept once at most.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from opframe.llm import cotrain, decontaminate, pieces, simhash, toxicity
from opframe.llm.common import doc_bucket, scratch_dir

#: Scores from which a document is rejected as toxic, and under which it is rejected as of low quality.
TOXIC_FROM, GOOD_FROM = 0.4, 0.5
#: Words of a shingle and of a benchmark window; longs of a fingerprint; similarity of near-duplicates.
SHINGLE, WINDOW, LONGS, SIMILARITY = 5, 10, 4, 0.8
#: SQL cannot express trained models, fingerprints and encoding; tests hold stages against brute force.
ORACLE_SQL: str | None = None


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the positive-unlabelled model does not reject. It learns from three quarters of the labels."""
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet").where(doc_bucket("doc_id", 4) != 2)
    model = toxicity.train(docs.where(doc_bucket("doc_id", 4) != 2), labels)
    return toxicity.score(docs, model, "__toxic").where(F.col("__toxic") < TOXIC_FROM).select(docs.columns)


def keep_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the co-trained classifier accepts; all of them where labels lack a class."""
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet").where(doc_bucket("doc_id", 4) != 2)
    model = cotrain.train(docs.where(doc_bucket("doc_id", 4) != 2), labels)
    scored = cotrain.score(docs, model, ("__text", "__meta", "__quality"))
    return scored.where(F.col("__quality") >= GOOD_FROM).select(docs.columns)


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document, that of the least doc_id, of each group of similar texts."""
    return simhash.keep_one(docs, width=SHINGLE, words64=LONGS, max_diff=None, similarity=SIMILARITY).select(docs.columns)


def drop_benchmark_passages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without the passages that they share with benchmark items."""
    return decontaminate.decontaminate(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"), WINDOW, "spans")


def encode_pieces(spark: SparkSession, docs: DataFrame, sf_dir: str, model: str | None = None) -> DataFrame:
    """doc_id, ids, n_tokens, ids_crc32 and round_trip of each document; the public 32k model unless another is given."""
    if model is None:
        import public_tokenizers

        model = public_tokenizers.path("piece_bpe_32k.model")
    return pieces.encode(docs, model)


STAGES = [
    ("toxicity", drop_toxic),
    ("quality", keep_quality),
    ("near_duplicates", drop_near_duplicates),
    ("decontamination", drop_benchmark_passages),
    ("encoding", encode_pieces),
]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The stages one after another over ``documents``."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES:
        path = scratch_dir(spark, f"stage-{name}")
        stage(spark, docs, sf_dir).write.parquet(path)
        docs = spark.read.parquet(path)
    return docs
