import re

import corpus_pipeline as c
from tests.llm.conftest import ROWS
from tests.llm.test_ngram_join import brute, shingles

SF = "/root/testdata/sf0.001"


def test_stages_one_by_one(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    first = c.quality_stage(spark, docs, SF)
    assert first.columns == docs.columns and 0 < first.count() < docs.count()
    labels = {r["doc_id"]: r["quality"] for r in spark.read.parquet(f"{SF}/labels.parquet").collect()}
    kept = {r["doc_id"] for r in first.collect()}
    clean = [d for d, y in labels.items() if y == 1]
    assert sum(d in kept for d in clean) >= 0.97 * len(clean)
    second = c.exact_stage(spark, docs, SF)
    rows = docs.collect()
    best = {}
    for r in rows:
        k = (r["text"] or "").encode().lower()
        best[k] = max(best.get(k, -1), r["doc_id"])
    assert sorted(r["doc_id"] for r in second.collect()) == sorted(best.values())
    third = c.near_stage(spark, docs, SF)
    groups = brute([(r["doc_id"], r["text"]) for r in rows])
    assert sorted(r["doc_id"] for r in third.collect()) == sorted({int(g) for _, _, g in groups})
    fourth = c.mixing_stage(spark, docs, SF)
    words = lambda df: sum(len(re.findall(r"[^\x20\x09-\x0D]+", r["text"] or "")) for r in df.collect())
    assert 0.88 * words(docs) <= words(fourth) <= 0.97 * words(docs)
    assert fourth.columns == docs.columns and shingles("a b") == {("a", "b")}


def test_run(spark):
    out = c.run(spark, SF)
    assert out.where("piece = 0").count() > 50


def test_empty(spark, tmp_path):
    docs = spark.read.parquet(f"{SF}/documents.parquet").where("false")
    for _, stage in c.STAGES:
        assert stage(spark, docs, SF).count() == 0


def test_stages_on_odd_rows(spark, odd_docs, tmp_path):
    """Null and repeated ids, null, empty and long texts, null leaves, columns named like those used inside."""
    labels = [(i, int(i in (1, 2, 6, 9, 10))) for i in range(1, 11)] + [(None, 1), (3, None)]
    spark.createDataFrame(labels, "doc_id long, quality int").write.parquet(f"{tmp_path}/labels.parquet")
    odd_docs.write.parquet(f"{tmp_path}/documents.parquet")
    docs = spark.read.parquet(f"{tmp_path}/documents.parquet")
    ids = lambda df: sorted(str(r["doc_id"]) for r in df.collect())
    judged = c.quality_stage(spark, docs, str(tmp_path))
    assert judged.columns == docs.columns
    n = {r["text"]: r["count"] for r in judged.groupBy("text").count().collect()}
    assert n and all(k == sum(t == text for _, t, _, _ in ROWS) for text, k in n.items())
    exact = c.exact_stage(spark, docs, str(tmp_path))
    assert exact.columns == docs.columns and ids(exact) == sorted(["2", "4", "5", "None", "6", "8", "9", "10"])
    near = c.near_stage(spark, docs, str(tmp_path))
    assert near.columns == docs.columns and ids(near) == sorted(["1", "3", "4", "5", "6", "7", "9", "None"])
    mixed = c.mixing_stage(spark, docs, str(tmp_path))
    words = lambda df: sum(len((r["text"] or "").split()) for r in df.collect())
    assert mixed.columns == docs.columns and 0.88 * words(docs) <= words(mixed) <= words(docs)
    packed = c.packing_stage(spark, docs, str(tmp_path))
    assert sorted(str(r["doc_id"]) for r in packed.where("piece = 0").collect()) == ids(docs)
    whole = c.run(spark, str(tmp_path)).where("piece = 0")
    assert set(ids(whole)) <= set(ids(judged)) and whole.count() == whole.select("doc_id").distinct().count()
