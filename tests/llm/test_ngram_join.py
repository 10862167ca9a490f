import random
import re

import numpy as np
import pytest

from tests.llm.conftest import ROWS
from tracegroup.llm import ngram_join as j

LOW = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def shingles(text):
    w = re.findall(r"[^\x20\x09-\x0D]+", (text or "").translate(LOW))
    k = min(5, len(w))
    return {tuple(w[i : i + k]) for i in range(len(w) - k + 1)} if k else set()


def brute(rows):
    sets = [shingles(t) for _, t in rows]
    group = list(range(len(rows)))
    for a in range(len(rows)):
        for b in range(a):
            both = len(sets[a] & sets[b])
            if sets[a] and sets[b] and 100 * both >= 75 * (len(sets[a]) + len(sets[b]) - both):
                old, new = group[a], group[b]
                group = [new if g == old else g for g in group]
    low = {g: min((rows[i][0] for i in range(len(rows)) if group[i] == g and rows[i][0] is not None), default=None) for g in set(group)}
    return sorted((str(r[0]), len(s), str(low[g])) for r, s, g in zip(rows, sets, group))


def near_rows(seed):
    rng = random.Random(seed)
    words = [f"w{i}" for i in range(400)]
    rows = []
    passage = [rng.choice(words) for _ in range(40)]
    for base in range(12):
        body = [rng.choice(words) for _ in range(rng.randint(3, 120))]
        if base % 3 == 0:
            body = body[:10] + passage + body[10:]
        rows.append(body)
        for _ in range(rng.randint(0, 6)):
            copy = list(body)
            for _ in range(rng.randint(0, max(1, len(copy) // 25))):
                copy[rng.randrange(len(copy))] = rng.choice(words).upper()
            rows.append(copy)
    rng.shuffle(rows)
    return [(i, " ".join(r)) for i, r in enumerate(rows)]


@pytest.mark.parametrize("seed", [1, 2, 3])
def test_against_brute_force(spark, seed, monkeypatch):
    if seed > 1:  # blocks, components and queries dealt out over several groups
        monkeypatch.setattr(j, "BLOCK", 3)
        monkeypatch.setattr(j, "MEMBERS", 50)
        monkeypatch.setattr(j, "QUERIES", 2)
    if seed > 2:  # no stars, so all links are found across components
        monkeypatch.setattr(j, "_stars", lambda nodes: nodes.selectExpr("node as a", "node as b").where("false"))
    rows = near_rows(seed)
    got = j.similar_groups(spark.createDataFrame(rows, "doc_id long, text string")).collect()
    assert sorted((str(r[0]), r[1], str(r[2])) for r in got) == brute(rows)


def test_odd_rows(odd_docs, no_docs):
    rows = [(r[0], r[1]) for r in ROWS]
    got = j.similar_groups(odd_docs).collect()
    assert sorted((str(r[0]), r[1], str(r[2])) for r in got) == brute(rows)
    assert j.similar_groups(no_docs).count() == 0
    kept = j.keep_one(odd_docs)
    assert kept.columns == odd_docs.columns
    assert sorted(str(r["doc_id"]) for r in kept.collect()) == sorted(["1", "3", "4", "5", "6", "7", "9", "None"])


def test_tree_leaves_out_no_pair():
    rng = np.random.default_rng(4)
    points = rng.poisson(3, (300, j.GROUPS)).astype(np.int32)
    points[150:] = points[:150]
    points[150:, 0] += 1
    sizes, parts = points.sum(1).astype(np.int64), np.arange(300)
    found = {(min(a, b), max(a, b)) for x, y in j.CountTree(points, sizes, parts).pairs() for a, b in zip(x.tolist(), y.tolist())}
    want = set()
    for a in range(300):
        for b in range(a + 1, 300):
            if 175 * np.minimum(points[a], points[b]).sum() >= 75 * (sizes[a] + sizes[b]):
                want.add((a, b))
    assert found == want and want


def test_prefixes_of_similar_sets_meet():
    rng = random.Random(9)
    for _ in range(300):
        n = rng.randint(1, 60)
        a = set(range(n))
        b = {x for x in a if rng.random() > 0.12} | set(range(100, 100 + rng.randint(0, 6)))
        if b and j.linked(len(a & b), len(a), len(b)):
            assert set(sorted(a)[: j.prefix_size(len(a))]) & set(sorted(b)[: j.prefix_size(len(b))])


def test_wide_points():
    rng = np.random.default_rng(2)
    small, large = np.unique(rng.integers(0, 1 << 63, 500).astype(np.uint64)), np.unique(rng.integers(0, 1 << 63, 90_000).astype(np.uint64))
    import pyarrow as pa

    points = j.points_of(pa.array([j.counts(small), j.counts(large)], pa.binary()))
    assert points.sum(1).tolist() == [len(small), len(large)] and points.max() > 255
    assert j.overlap(points[0], points[1]) >= len(np.intersect1d(small, large))


def test_index_counts_as_sets_do():
    rng = random.Random(7)
    sets = [np.unique(np.array([rng.randrange(60) for _ in range(rng.randint(1, 50))], np.uint64)) for _ in range(40)]
    index = j.SetIndex(sets)
    for s in sets:
        want = [k for k, x in enumerate(sets) if j.linked(len(np.intersect1d(s, x)), len(s), len(x))]
        assert index.linked(s).tolist() == want
