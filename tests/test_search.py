"""Exact search on a grid of blocks and parts, and numbering by ranges, against plain versions."""

import random

import numpy as np
from pyspark.sql import functions as F

from tracegroup.operators import chronology, index


def test_places_of_the_greatest():
    rng = np.random.default_rng(2)
    row, score = rng.integers(0, 6, 300), rng.integers(0, 9, 300) / 8
    for k in (1, 4, 500):
        want = [i for i in range(300) if sum(score[(row == row[i])] > score[i]) < k]
        assert sorted(index._kept(row, score, k)) == want
    assert len(index._kept(row[:0], score[:0], 3)) == 0


def test_grid_against_plain(spark, monkeypatch):
    """Several blocks, parts of more than one slab, many equal scores; of those the earliest."""
    monkeypatch.setattr(index, "BLOCK", 9)
    rng = np.random.default_rng(3)
    vec = rng.integers(-2, 3, (12_000, 4)).astype(np.float32)
    rows = [(i, (i * 7919) % 12_007, v.tolist()) for i, v in enumerate(vec)]
    base = spark.createDataFrame(rows, "id long, seq long, vec array<float>")
    asked = base.where("id % 400 = 0")
    for causal in (True, False):
        got = {}
        for r in index.exact_topk(asked, base, 5, causal).collect():
            got.setdefault(r["q_id"], []).append((r["rank"], r["c_id"], r["score"]))
        for q in range(0, 12_000, 400):
            score = np.round(vec.astype(np.float64) @ vec[q].astype(np.float64), 9)
            seq = np.array([r[1] for r in rows])
            allowed = np.flatnonzero(seq < seq[q]) if causal else np.arange(12_000)
            best = sorted(allowed, key=lambda c: (-score[c], seq[c], c))[:5]
            assert sorted(got.get(q, [])) == [(n, c, score[c]) for n, c in enumerate(best, 1)]


def test_similarity_may_be_replaced(spark):
    rows = [(i, i, [float(i), 0.0]) for i in range(20)]
    base = spark.createDataFrame(rows, "id long, seq long, vec array<float>")
    near = lambda q, m: -np.abs(q[:, None, 0] - m[None, :, 0])
    got = {r["q_id"]: r["c_id"] for r in index.exact_topk(base.where("id in (4, 9)"), base, 1, True, near).collect()}
    assert got == {4: 3, 9: 8}


def test_numbers_with_many_reports_at_one_time(spark):
    rng = random.Random(4)
    ids = rng.sample(range(100_000), 3000)
    rows = [(i, 50 if n % 3 else rng.randint(-40, 10**12)) for n, i in enumerate(ids)]
    df = spark.createDataFrame(rows, "report_id long, arrival long").repartition(7)
    got = {r["report_id"]: r["arrival_seq"] for r in chronology.numbered(df).collect()}
    assert got == {i: n for n, (_, i) in enumerate(sorted((a, i) for i, a in rows), 1)}
    assert chronology.numbered(df.where("false")).count() == 0
    assert chronology.numbered(df.withColumn("extra", F.lit("x"))).columns == ["report_id", "arrival", "extra", "arrival_seq"]
