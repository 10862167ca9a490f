"""Queries against their SQL on the smallest tables, and cases made by hand."""

import os

import duckdb
import pytest
from pyspark.sql import functions as F

from tracegroup import catalogue
from tracegroup.functions import frames as ff
from tracegroup.operators import chronology as ch
from tracegroup.operators import index, metrics, pairs, replay
from tracegroup.operators.baselines import set_overlap
from tracegroup.operators.components import components, resolve_roots

SF = "/root/testdata/sf0.001"
SQL = catalogue.oracle_sql()


def shown(v):
    return "null" if v is None else f"{v:.6f}" if isinstance(v, float) else str(v)


@pytest.mark.parametrize("name", sorted(SQL))
def test_query_against_sql(spark, name):
    c = duckdb.connect()
    for t in os.listdir(SF):
        c.execute(f"CREATE VIEW {t.split('.')[0]} AS SELECT * FROM '{SF}/{t}'")
    want = c.execute(SQL[name])
    cols = [d[0] for d in want.description]
    rows = sorted(tuple(map(shown, r)) for r in want.fetchall())
    got = catalogue.queries()[name](spark, SF)
    assert sorted(got.columns) == sorted(cols)
    assert sorted(tuple(shown(r[c]) for c in cols) for r in got.collect()) == rows


def test_frames(spark):
    df = spark.createDataFrame([("a.b.HTTPServer2.readURL",), ("f",), ("C.f",), ("",), ("x.Été.l_éa",)], "f string")
    rows = df.select(ff.parse_frame(F.col("f")).alias("p"), ff.pieces(F.col("f")).alias("s")).collect()
    assert rows[0]["p"].asDict() == {"package": "a.b", "class_name": "HTTPServer2", "method": "readURL"}
    assert rows[0]["s"] == ["a", "b", "http", "server", "2", "read", "url"]
    assert rows[1]["p"]["method"] == "f" and rows[2]["p"]["class_name"] == "C" and rows[3]["s"] == []
    assert rows[4]["s"] == ["x", "été", "l", "éa"]
    text = "java.lang.E: x\n\tat a.b.C.m(F.java:1)\n\tat a.b.C.n(Native)\nCaused by: y\n#1 0x7f in ns::f () from lib"
    got = spark.createDataFrame([(text,)], "t string").select(ff.from_text(F.col("t")).alias("x")).first()[0]
    assert got == ["a.b.C.m", "a.b.C.n", "ns::f"]
    r = spark.createDataFrame([(["a", "a", "b", "a"],)], "f array<string>").select(ff.collapse_recursion(F.col("f")).alias("x")).first()[0]
    assert r == ["a", "b", "a"]


REPORTS = [(1, 10, ["a", "b"], "x"), (2, 20, ["a", "b"], "y"), (3, 20, ["a", "c"], "x"), (4, 30, [], "z"), (5, 40, ["a", "b", "d"], "y"), (6, 50, ["q"], "w")]


def made(spark):
    r = spark.createDataFrame(REPORTS, "report_id long, arrival long, frames array<string>, category_id string")
    return ch.split(ch.numbered(r.withColumn("fp", ff.fingerprint(F.col("frames")))), (0.0, 0.0, 1.0))


def test_replay_by_hand(spark):
    r = made(spark)
    assert [x["arrival_seq"] for x in r.orderBy("report_id").collect()] == [1, 2, 3, 4, 5, 6]
    got = {x["query_seq"]: x for x in replay.run(r, set_overlap).collect()}
    assert 2 not in got  # identical to an earlier report
    assert got[1]["is_new"] and got[1]["predicted"] is None and got[1]["score"] == 0
    assert got[3]["predicted"] == "x" and got[3]["correct"]
    assert got[5]["predicted"] == "x" and got[5]["true_rank"] == 2  # equal scores: the earlier entry first
    assert metrics.acc_at_1(replay.run(r, set_overlap)).first()["acc_at_1"] == 0.5
    assert {tuple(x) for x in ch.identical_shortcut(r).collect()} == {(2, "x")}


def test_roc_and_f1_ties(spark):
    o = spark.createDataFrame([(0.2, True), (0.2, False), (0.9, False), (0.1, True)], "score double, is_new boolean")
    assert metrics.roc_auc(o).first()["auc"] == 0.875
    assert metrics.best_threshold(o).first().asDict() == {"threshold": 0.2, "f1": 0.8}
    assert metrics.roc_auc(o.where("is_new")).first()["auc"] is None


def test_roots_and_components(spark):
    d = spark.createDataFrame([(1, None), (2, 1), (3, 2), (4, 3), (5, None), (6, 5), (7, 99)], "report long, parent long")
    assert {tuple(r) for r in resolve_roots(d).select("report", "root").collect()} == {(1, 1), (2, 1), (3, 1), (4, 1), (5, 5), (6, 5), (7, 99)}
    e = spark.createDataFrame([(i, i + 1) for i in range(40)] + [(100, 90), (7, 7)], "a long, b long")
    got = {r["node"]: r["component"] for r in components(e).collect()}
    assert got == {**{i: 0 for i in range(41)}, 100: 90, 90: 90}


def test_pairs_are_distinct_and_capped(spark):
    rows = [(i, i, [f"f{i}"], "big" if i < 60 else f"c{i // 3}") for i in range(90)]
    r = spark.createDataFrame(rows, "report_id long, arrival long, frames array<string>, category_id string").withColumn("fp", ff.fingerprint(F.col("frames")))
    p = pairs.positive_pairs(r, 50, 3)
    n = {x["category_id"]: x["n"] for x in p.groupBy("category_id").agg(F.count_distinct(F.array_sort(F.array("anchor_fp", "positive_fp"))).alias("n")).collect()}
    assert n.pop("big") == 50 and set(n.values()) == {3}
    t = pairs.triplets(p, r, 3).collect()
    assert t and all(x["negative_category"] != x["category_id"] for x in t)
    b = pairs.batches(p, 16).groupBy("batch").agg(F.count("*").alias("n"), F.max("slot").alias("m")).collect()
    assert sorted(x["n"] for x in b)[:-1] == sorted(x["n"] for x in b)[:-1] and all(x["m"] == x["n"] - 1 for x in b)


def test_index_recall(spark):
    v = spark.read.parquet(f"{SF}/embeddings.parquet").select(F.col("vec_id").alias("id"), F.col("vec_id").alias("seq"), F.col("embedding").alias("vec"))
    q = v.where("id % 20 = 0")
    exact = index.exact_topk(q, v, 5).cache()
    assert index.recall(index.sq8_topk(q, v, 5), exact).first()["recall"] > 0.95
    centroids, cells = index.ivf_build(v, 8)
    assert index.recall(index.ivf_topk(q, cells, centroids, 5, 8, salts=3), exact).first()["recall"] == 1
    assert all(r["c_id"] < r["q_id"] for r in exact.collect())
    assert index.exact_topk(q.where("false"), v, 5).count() == 0


def test_streams(spark, tmp_path):
    from tracegroup.streaming import streams

    events = spark.read.parquet(f"{SF}/events.parquet")
    events.repartition(3).write.parquet(str(tmp_path / "in"))
    s = streams.timed(streams.source(spark, str(tmp_path / "in"), events.schema), lateness="400 days")
    q = streams.error_bursts(s).writeStream.format("memory").queryName("bursts").outputMode("complete").option("checkpointLocation", str(tmp_path / "c")).start()
    q.processAllAvailable()
    q.stop()
    got = {(r[0], r[1]) for r in spark.sql("select unix_micros(w.start), n_errors from bursts").collect()}
    want = {(r["start_us"], r["n_errors"]) for r in catalogue.queries()["burst_windows"](spark, SF).collect()}
    assert got == want
    seen = []
    streams.per_batch(s, lambda df, i: seen.append((i, df.count())), str(tmp_path / "d")).awaitTermination()
    assert sum(n for _, n in seen) == events.count() and len(seen) > 1


def test_batch_borders_do_not_matter(spark):
    from tracegroup.streaming.streams import attach_batch

    r = made(spark).select("arrival_seq", "fp", "frames", "category_id")
    history, rest = r.where("arrival_seq = 1"), r.where("arrival_seq > 1")
    at_once = {x["query_seq"]: x["category_id"] for x in attach_batch(history, rest, set_overlap, 0.3).collect()}
    parts, known = {}, history
    for i in range(2, 7):
        batch = rest.where(f"arrival_seq = {i}")
        one = {x["query_seq"]: x["category_id"] for x in attach_batch(known, batch, set_overlap, 0.3).collect()}
        parts |= one
        known = spark.createDataFrame(known.collect() + batch.withColumn("category_id", F.lit(one[i])).collect(), known.schema)
    assert parts == at_once and at_once[2] == "x" and at_once[6] == "new:6"


def test_sql_functions(spark):
    from tracegroup.functions import sql

    sql.register(spark)
    rows = spark.sql("select * from frames_of_text('  at a.b.C.m(F:1)\nx\n#0 f ()')").collect()
    assert [tuple(r) for r in rows] == [(0, "a.b", "C", "m"), (1, "", "", "f")]
    assert spark.sql("select frame_similarity(array('a','b'), array('a','c'))").first()[0] == 0.5
    assert spark.sql("select vec_max(v) from values (array(1D, 5D)), (array(2D, 3D)) t(v)").first()[0] == [2, 5]


def test_doc_copies_of_large_groups(spark, tmp_path):
    """Over 200 copies, and near copies of them, are one category; no cap on a sentence's documents."""
    from tracegroup.sources.workloads import doc_copies

    rows = [(i, "One here. Two here. Three here." + (f" Own {i}." if i % 2 else "")) for i in range(230)] + [(500, "One here. Other a. Other b. Other c"), (501, "")]
    spark.createDataFrame(rows, "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    got = {r["report_id"]: r["category_id"] for r in doc_copies(spark, str(tmp_path)).collect()}
    assert got == {**dict.fromkeys(range(230), "0"), 500: "500", 501: "501"}
