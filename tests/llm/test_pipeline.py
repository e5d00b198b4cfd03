"""The corpus pipeline stage by stage, on planted cases, odd rows and empty tables."""

import random

import pytest

import corpus_pipeline as cp


@pytest.fixture(scope="module")
def folder(spark, tmp_path_factory):
    """The 0.01 tables with planted copies, near copies, benchmark passages and an odd row each."""
    src, out = "/root/testdata/sf0.01", str(tmp_path_factory.mktemp("planted"))
    docs = spark.read.parquet(f"{src}/documents.parquet")
    labels = spark.read.parquet(f"{src}/labels.parquet")
    good = docs.join(labels.where("quality = 1 and toxic = 0"), "doc_id", "left_semi").where("n_chars between 1500 and 6000").orderBy("doc_id").limit(12).collect()
    item = spark.read.parquet(f"{src}/benchmark.parquet").orderBy("item_id").first().text
    rng, rows = random.Random(0), []
    for i, r in enumerate(good):
        rows.append((100_000 + i, r.text, r.lang, r.source, r.n_chars))
        w = r.text.split(" ")
        w[rng.randrange(len(w))] = "changed"
        rows.append((200_000 + i, " ".join(w), r.lang, r.source, r.n_chars))
    fresh = " ".join(rng.choices(good[0].text.split(), k=150))
    rows.append((300_000, f"{fresh}\n{item}\n{fresh[::-1]}", "en", "src1", 900))
    rows += [(400_000, None, None, None, None), (400_001, "", "en", "src1", 0)]
    docs.unionByName(spark.createDataFrame(rows, docs.schema)).write.parquet(f"{out}/documents.parquet")
    for t in ("labels", "benchmark"):
        spark.read.parquet(f"{src}/{t}.parquet").write.parquet(f"{out}/{t}.parquet")
    return out, [r.doc_id for r in good], item


def test_stages(spark, folder):
    sf, good, item = folder
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    labels = spark.read.parquet(f"{sf}/labels.parquet")
    columns, ids = docs.columns, {}
    for name, stage in cp.STAGES[:4]:
        before = {r.doc_id for r in docs.select("doc_id").collect()}
        path = f"{sf}/out-{name}"
        stage(spark, docs, sf).write.parquet(path)
        docs = spark.read.parquet(path)
        assert docs.columns == columns
        ids[name] = {r.doc_id for r in docs.select("doc_id").collect()}
        assert ids[name] <= before
    clean = {r.doc_id for r in labels.where("quality = 1 and toxic = 0").collect()}
    toxic = {r.doc_id for r in labels.where("toxic = 1").collect()}
    junk = {r.doc_id for r in labels.where("quality = 0 and toxic = 0").collect()}
    assert len(clean & ids["toxicity"]) > 0.9 * len(clean) and len(toxic & ids["toxicity"]) < 0.4 * len(toxic)
    passed = clean & ids["toxicity"]
    assert len(passed & ids["quality"]) > 0.95 * len(passed) and len(junk & ids["quality"]) < 0.3 * len(junk)
    for i, g in enumerate(good):
        copies = {g, 100_000 + i, 200_000 + i} & ids["quality"]
        assert len(copies & ids["near_duplicates"]) <= 1
    if 300_000 in ids["near_duplicates"]:
        text = docs.where("doc_id = 300000").first().text
        assert item not in text and len(text) > 500
    out = cp.encode_pieces(spark, docs, sf)
    assert out.count() == docs.count() and out.where("not round_trip").count() == 0


def test_run(spark, folder):
    sf, _, item = folder
    out = cp.run(spark, sf)
    assert out.columns == ["doc_id", "ids", "n_tokens", "ids_crc32", "round_trip"] and 400 < out.count() < 1000
    assert out.groupBy("doc_id").count().where("count > 1").count() == 0


def test_empty_documents(spark, folder, tmp_path):
    sf = folder[0]
    for t in ("documents", "labels", "benchmark"):
        spark.read.parquet(f"{sf}/{t}.parquet").limit(0).write.parquet(f"{tmp_path}/{t}.parquet")
    assert cp.run(spark, str(tmp_path)).count() == 0


def test_stages_keep_extra_columns(spark, folder):
    sf = folder[0]
    docs = spark.read.parquet(f"{sf}/documents.parquet").limit(60).selectExpr("*", "1 as score", "'x' as component_id", "2L as fp", "'k' as __id")
    for _, stage in cp.STAGES[:4]:
        out = stage(spark, docs, sf)
        assert out.columns == docs.columns and out.count() <= 60
