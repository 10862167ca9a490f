"""The whole method on planted categories: training, search, reranking and decision."""

import random
from dataclasses import replace

import numpy as np
import pytest

from pyspark.sql import functions as F

from tracegroup.functions.frames import fingerprint
from tracegroup.operators import chronology, metrics, pairs, train
from tracegroup.operators.baselines import traces_of
from tracegroup.operators.encoder import EncoderConfig
from tracegroup.plans.two_stage import TwoStage
from tracegroup.sources.storage import written

SMALL = EncoderConfig(vocab=300, token=10, frame=10, trace=16)


def planted(seed=6, categories=24, copies=9):
    """Reports whose category is told by most of their frames; the last few open categories of their own."""
    rng = random.Random(seed)
    verbs, nouns = ["load", "save", "open", "close", "draw", "parse", "send", "read"], ["File", "Page", "User", "Node", "Cache", "Queue", "Frame", "Index"]
    name = lambda: f"app.{rng.choice(nouns)}{rng.choice(nouns)}.{rng.choice(verbs)}{rng.choice(nouns)}"
    bases = [[name() for _ in range(7)] for _ in range(categories)]
    rows = []
    for c, base in enumerate(bases):
        for _ in range(copies):
            rows.append([str(c), [name() if rng.random() < 0.2 else f for f in base]])
    rng.shuffle(rows)
    rows += [[f"new{i}", [name() for _ in range(7)]] for i in range(8)]
    return [(i, i, frames, c) for i, (c, frames) in enumerate(rows)]


@pytest.fixture(scope="module")
def reports(spark):
    df = spark.createDataFrame(planted(), "report_id long, arrival long, frames array<string>, category_id string")
    return written(chronology.split(chronology.numbered(df.withColumn("fp", fingerprint(F.col("frames"))))), "planted-test")


@pytest.fixture(scope="module")
def fitted(reports):
    return TwoStage(SMALL, train.TrainConfig(epochs=6, batch=32, rate=5e-3, most_rows=100_000), k=10).fit(reports)


def test_embedding_finds_the_category(reports, fitted):
    alone = replace_cross(fitted, None)
    row = metrics.acc_at_1(alone.outcomes(reports)).first()
    assert row["acc_at_1"] > 0.7 and row["n_attached"] > 20 and row["n_new"] == 8
    assert np.mean(fitted.log[-3:]) < np.mean(fitted.log[:3])


def replace_cross(fitted, cross):
    return replace(fitted, cross=cross)


def test_reranker_orders_the_same_candidates(reports, fitted):
    queries = chronology.queries_of(reports)
    before = fitted.candidates(reports, queries)
    after = train.rescore(before, fitted.toks, fitted.cross)
    pairs = lambda df: sorted((r["q_fp"], r["c_fp"]) for r in df.collect())
    assert pairs(before) == pairs(after) and after.where("rerank is null or isnan(rerank)").isEmpty()
    assert np.mean(fitted.cross_log[-3:]) < np.mean(fitted.cross_log[:3])
    assert metrics.acc_at_1(fitted.outcomes(reports)).first()["acc_at_1"] > 0.6


def test_candidates_are_earlier_and_at_most_k(reports, fitted):
    queries = chronology.queries_of(reports)
    found = fitted.candidates(reports, queries)
    assert found.groupBy("q_fp").count().where("count > 10").isEmpty()
    seq = reports.groupBy("fp").agg(F.min("arrival_seq").alias("at"))
    late = found.join(seq.toDF("q_fp", "q_at"), "q_fp").join(seq.toDF("c_fp", "c_at"), "c_fp").where("c_at >= q_at")
    assert late.isEmpty()


def test_fixed_thresholds(reports, fitted):
    for threshold, action in ((0.0, "attach"), (1.0, "create")):
        one = replace(fitted, options=replace(fitted.options, threshold=threshold))
        rows = one.decisions(reports).where("predicted is not null").select("action").distinct().collect()
        assert [r["action"] for r in rows] == [action]


@pytest.mark.parametrize("search, least", [("ivf", 0.8), ("lsh", 0.6), ("sq8", 0.95)])
def test_other_indexes_find_most_of_the_nearest(reports, fitted, search, least):
    queries = chronology.queries_of(reports)
    one = replace(fitted, options=replace(fitted.options, search=search))
    names = lambda df: {(r["q_fp"], r["c_fp"]) for r in df.collect()}
    exact, found = names(fitted.candidates(reports, queries)), names(one.candidates(reports, queries))
    assert len(exact & found) >= least * len(exact)


def test_vectors_have_length_one_for_every_trace(reports, fitted):
    rows = fitted.vectors.collect()
    assert len(rows) == traces_of(reports).count()
    assert np.allclose([np.linalg.norm(r["vec"]) for r in rows], 1, atol=1e-5)


def test_training_on_tasks_equals_training_on_the_driver(reports, fitted, spark):
    toks = {r["fp"]: r["toks"] for r in fitted.toks.collect()}
    old = reports.where("part = 'train'").select("fp", "category_id").distinct().orderBy("category_id", "fp").collect()
    firsts = {}
    for r in old:
        firsts.setdefault(r["category_id"], []).append(r["fp"])
    pairs = [(c, v[0], v[1]) for c, v in sorted(firsts.items()) if len(v) > 1][:8]
    config = train.TrainConfig(epochs=1, batch=8, rate=1e-2)
    lists = lambda fp: [[int(x) for x in np.frombuffer(f, np.int32)] if isinstance(f, (bytes, bytearray)) else list(f) for f in toks[fp]]
    df = spark.createDataFrame([(0, c, lists(a), lists(b)) for c, a, b in pairs], "batch long, category_id string, anchor array<array<int>>, positive array<array<int>>")
    model, log = train.fit_embedding_on_tasks(df, SMALL, config, steps=1)
    own = train.TraceEncoder(SMALL)
    rows = df.collect()
    loss, grads = train.contrastive_step(own, [train.as_bytes(r["anchor"]) for r in rows], [train.as_bytes(r["positive"]) for r in rows], [r["category_id"] for r in rows], config)
    adam = train.Adam(own.params, config.rate)
    adam.step(grads)
    assert abs(log[0] - loss) < 1e-9
    assert all(np.allclose(model.params[k], own.params[k], atol=1e-9) for k in own.params)


def test_reranker_on_tasks_equals_the_driver(reports, fitted, spark):
    config = train.TrainConfig(epochs=1, batch=1000, rate=1e-2, task_steps=1)
    old = reports.where("part = 'train'")
    drawn = written(pairs.triplets(pairs.positive_pairs(old, 1), old), "triplets-test")
    dealt = train.token_batches(drawn, fitted.toks, ("anchor", "positive", "negative"), config)
    model, log = train.fit_reranker_on_tasks(dealt, SMALL, config, steps=1)
    own = train.CrossEncoder(SMALL)
    rows = dealt.orderBy("category_id").collect()
    assert len(rows) == drawn.count() > 10 and {r["batch"] for r in rows} == {0}
    loss, grads = train.triplet_step(own, *[[train.as_bytes(r[c]) for r in rows] for c in ("anchor", "positive", "negative")])
    train.Adam(own.params, config.rate).step(grads)
    assert abs(log[0] - loss) < 1e-9
    assert all(np.allclose(model.params[k], own.params[k], atol=1e-6) for k in own.params)


def test_every_pair_is_read_once_an_epoch(reports, fitted):
    config = train.TrainConfig(batch=16, task_steps=3)
    drawn = written(pairs.positive_pairs(reports.where("part = 'train'"), 20), "pairs-test")
    dealt = train.token_batches(drawn, fitted.toks, ("anchor", "positive"), config)
    assert dealt.count() == drawn.count()
    sizes = {r["batch"]: (r["n"], r["turns"]) for r in dealt.groupBy("batch").agg(F.count("*").alias("n"), F.collect_set("turn").alias("turns")).collect()}
    assert all(turns == [b % 3] for b, (_, turns) in sizes.items())
    assert sorted(n for n, _ in sizes.values())[1:] == [16] * (len(sizes) - 1)


def test_training_on_tasks_finds_the_category(reports):
    some = TwoStage(SMALL, train.TrainConfig(epochs=4, batch=32, rate=1e-2, task_steps=8), k=10).fit(reports)
    assert len(some.log) == len(some.cross_log) == 32
    assert np.mean(some.log[-3:]) < np.mean(some.log[:3]) and np.mean(some.cross_log[-3:]) < np.mean(some.cross_log[:3])
    assert metrics.acc_at_1(replace_cross(some, None).outcomes(reports)).first()["acc_at_1"] > 0.6
    logged = train.loss_table(reports.sparkSession, {"embedding": some.log, "reranker": some.cross_log})
    assert logged.count() == 64 and logged.columns == ["model", "step", "loss"]
