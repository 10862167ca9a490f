import numpy as np

from tracegroup.llm import quality as q
from tracegroup.llm.queries import held_out, quality_weights, table

SF = "/root/testdata/sf0.01"


def test_held_out_accuracy(spark):
    docs, labels = table(spark, SF, "documents"), table(spark, SF, "labels")
    weights = quality_weights(docs, labels)
    rows = q.score(docs.select("doc_id", "text"), weights).join(labels, "doc_id").where(held_out()).select("score", "quality").collect()
    right = np.mean([(r["score"] >= 0.7) == (r["quality"] == 1) for r in rows])
    assert len(rows) > 50 and right > 0.95


def test_scores_read_only_the_text(spark):
    docs, labels = table(spark, SF, "documents"), table(spark, SF, "labels")
    weights = quality_weights(docs, labels, q.QualityConfig(sample_rows=100, epochs=1))
    part = docs.where("doc_id < 40")
    one = {r[0]: r[-1] for r in q.score(part.select("doc_id", "text"), weights).collect()}
    other = {r[0]: r[-1] for r in q.score(part.selectExpr("doc_id", "text", "'zz' as lang", "0 as source"), weights).collect()}
    assert one == other


def test_odd_rows(odd_docs, no_docs, spark):
    labels = spark.createDataFrame([(1, 1), (4, 0), (5, None), (None, 1), (99, 0), (7, 5)], "doc_id long, quality int")
    w = q.train(odd_docs, labels)
    out = q.score(odd_docs, w)
    assert out.columns == [*odd_docs.columns, "score"]
    assert all(0 <= r["score"] <= 1 for r in out.collect()) and out.count() == odd_docs.count()
    assert q.score(no_docs, w).count() == 0
    none = q.train(odd_docs, labels.where("false"))
    assert {r["score"] for r in q.score(odd_docs, none).collect()} == {0.5}


def test_features_are_per_row():
    from tracegroup.llm.common import bytes_of
    import pyarrow as pa

    texts = ["a a b", "", "b!! b", "a a b"]
    at, row = q.features(*bytes_of(pa.array(texts)), 18)
    per = [sorted(at[row == i]) for i in range(4)]
    assert per[0] == per[3] and not per[1] and len(per[2]) == 3 + 2
