import random

import pytest
from pyspark.sql import functions as F

from tracegroup.functions.frames import fingerprint
from tracegroup.operators import baselines, grid, replay
from tracegroup.operators import chronology as ch


def _reports(spark, n=260, seed=5):
    rng = random.Random(seed)
    rows = []
    for i in range(n):
        frames = [rng.choice("abcdefghijklmnop") for _ in range(rng.randrange(0, 9))]
        rows.append((i, rng.randrange(40), frames, rng.choice("UVWXYZ")))
    r = spark.createDataFrame(rows, "report_id long, arrival long, frames array<string>, category_id string")
    return ch.split(ch.numbered(r.withColumn("fp", fingerprint(F.col("frames")))))


def _by_pairs(reports, scorer, skip):
    queries = ch.queries_of(reports, "test", skip)
    pairs = scorer(baselines.traces_of(queries), baselines.traces_of(reports))
    return replay.outcomes(queries, replay.ranked(replay.category_scores(replay.earlier_pairs(queries, pairs, ch.index_entries(reports)))))


@pytest.mark.parametrize("small", [False, True])
def test_grid_equals_pairs(spark, monkeypatch, small):
    if small:  # several blocks and parts, a query at a time
        for name, value in (("BLOCK_POSTINGS", 120), ("PART_POSTINGS", 400), ("MEETINGS", 1)):
            monkeypatch.setattr(grid, name, value)
    reports = _reports(spark).localCheckpoint()
    old = reports.where("part = 'train'")
    scorers = {"overlap": baselines.set_overlap, "prefix": baselines.prefix_match, "dampened": baselines.TfIdf(old), "cosine": baselines.TfIdf(old, "cosine"), "align": baselines.TopFrameAlign(old)}
    told = grid.outcomes(reports, scorers, skip_identical=small).collect()
    for system, scorer in scorers.items():
        want = sorted(repr(tuple(r)) for r in _by_pairs(reports, scorer, small).collect())
        assert sorted(repr(tuple(r)[1:]) for r in told if r["system"] == system) == want and want


def test_replay_makes_no_table_of_pairs(spark, monkeypatch):
    def no_pairs(*_):
        raise AssertionError("a table of pairs")

    monkeypatch.setattr(baselines, "_met", no_pairs)
    reports = _reports(spark)
    assert replay.run(reports, baselines.set_overlap, ranks=False).where("predicted is not null").count() > 0


def test_numbering_shuffles_reports_once(spark):
    rows = [(i, i % 3) for i in range(500)]
    r = spark.createDataFrame(rows, "report_id long, arrival long").repartition(7)
    got = ch.numbered(r)
    assert [x["report_id"] for x in got.orderBy("arrival_seq").collect()] == [i for i, a in sorted(rows, key=lambda x: (x[1], x[0]))]
    assert sorted(x["arrival_seq"] for x in got.collect()) == list(range(1, 501))
    assert "row_number" not in got._jdf.queryExecution().optimizedPlan().toString()


def test_nearest_categories_equal_pairs(spark, monkeypatch):
    monkeypatch.setattr(grid, "PART_POSTINGS", 400)
    reports = _reports(spark).localCheckpoint()
    q = ch.queries_of(reports)
    pairs = baselines.prefix_match(baselines.traces_of(q), baselines.traces_of(reports))
    want = replay.ranked(replay.category_scores(replay.earlier_pairs(q, pairs, ch.index_entries(reports)))).where("rank <= 3")
    cols = ["query_seq", "category_id", "score", "cand_seq", "rank"]
    got = sorted(map(repr, grid.nearest(reports, baselines.prefix_match, 3).select(cols).collect()))
    assert got == sorted(map(repr, want.select(cols).collect())) and got


@pytest.mark.parametrize("apart", [False, True])
def test_blocks_are_sent_to_entries_where_they_lie(spark, monkeypatch, apart):
    for name, value in (("SENT_POSTINGS", 60), ("HELD_POSTINGS", 50), ("SENT_KEYS", 4)):
        monkeypatch.setattr(grid, name, value)

    def no_cells(*_):
        raise AssertionError("both sides dealt to cells")

    monkeypatch.setattr(grid, "_cells", no_cells)
    reports = _reports(spark, seed=8).localCheckpoint()
    old, frames = reports.where("part = 'train'"), reports.select("report_id", "arrival", "fp", "frames")
    scorers = {"overlap": baselines.set_overlap, "prefix": baselines.prefix_match, "dampened": baselines.TfIdf(old), "cosine": baselines.TfIdf(old, "cosine"), "align": baselines.TopFrameAlign(old)}
    given = (reports.drop("frames"), frames) if apart else (reports, None)
    told = grid.outcomes(given[0], scorers, ranks=False, frames=given[1]).drop("true_rank").collect()
    for system, scorer in scorers.items():
        want = sorted(repr(tuple(r)) for r in _by_pairs(reports, scorer, True).drop("true_rank").collect())
        assert sorted(repr(tuple(r)[1:]) for r in told if r["system"] == system) == want and want


def test_frequencies_of_any_training_reports(spark):
    """Also where training is not all that arrived up to some report."""
    reports = _reports(spark).localCheckpoint()
    frames = grid._named(reports).withColumn("keys", grid._keys())
    for which in ("arrival_seq <= 100", "arrival_seq % 3 = 0", "false"):
        old = reports.where(which)
        got, n = grid._frequencies(reports, old, frames)
        want = old.select(F.explode(F.array_distinct(grid._keys())).alias("key")).groupBy("key").agg(F.count("*").alias("df"))
        assert n == old.count() and sorted(map(tuple, got.collect())) == sorted(map(tuple, want.collect()))


def test_numbering_leaves_frames_where_they_are(spark):
    from tracegroup.sources import workloads as wl

    reports, frames = wl.keyed(spark, "/root/testdata/sf0.001", "planted_docs")
    assert "frames" not in reports.columns and reports.count() == frames.count() > 0


def test_parts_are_not_broadcast_to_order_lines(spark):
    """However small their file: a repetitive one of a few MB may hold millions of rows."""
    from tracegroup.sources import workloads as wl

    for keyed in (False, True):
        plan = wl.orders_longtail(spark, "/root/testdata/sf0.001", keyed)._jdf.queryExecution().executedPlan().toString()
        assert "SortMergeJoin [l_partkey" in plan and "BroadcastHashJoin [l_partkey" not in plan


def test_rollup_by_region_reads_lines_once(spark, monkeypatch):
    from tracegroup.plans import queries
    from tracegroup.sources import workloads as wl

    read = []
    load = wl.load
    monkeypatch.setattr(wl, "load", lambda spark, sf_dir, name: read.append(name) or load(spark, sf_dir, name))
    assert queries.acc_rollup_region(spark, "/root/testdata/sf0.001").count() > 1
    assert read.count("lineitem") == 1


def test_orders_in_portions_equal_the_whole(spark, monkeypatch):
    from tracegroup.sources import workloads as wl

    made, sf = [], "/root/testdata/sf0.001"
    whole = [sorted(map(repr, t.collect())) for t in wl.keyed(spark, sf, "orders_longtail")]
    monkeypatch.setattr(wl, "PORTION_ORDERS", 1)
    monkeypatch.setitem(wl.WORKLOADS, "orders_longtail", lambda *a, **k: made.append(k["portion"]) or wl.orders_longtail(*a, **k))
    assert [sorted(map(repr, t.collect())) for t in wl.keyed(spark, sf, "orders_longtail")] == whole and whole[0]
    assert made == [(r, 4) for r in range(4)]


def test_written_tables_leave_no_shuffle_files(spark):
    """They would stay on disk until the driver happens to collect its garbage."""
    from pathlib import Path

    from tracegroup.sources import storage

    folders = [str(d) for d in spark.sparkContext._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager().localDirs()]
    files = lambda: {f.name for d in folders for f in Path(d).rglob("shuffle_*.data")}
    df = spark.range(5000).groupBy((F.col("id") % 700).alias("k")).count()
    setting = spark.conf.get(storage._CLEANUP)
    before = files()
    got = storage.written_in_turn([df, df.selectExpr("k + 700 as k", "count")], "turns")
    assert not files() - before and got.count() == 1400 and got.dtypes == df.dtypes
    assert spark.conf.get(storage._CLEANUP) == setting


def test_search_leaves_out_frames_that_most_entries_have(spark):
    """Twins share rare frames, all share twenty frequent ones: as many pairs as that are not looked at, and the best are the same."""
    import numpy as np
    import pyarrow as pa

    rng, rows = np.random.default_rng(3), []
    for i in range(300):
        rare = [1000 + 10 * (i % 150) + j for j in range(5)]
        rows.append([*range(1, 6), *rare, *rng.permutation(20)[: rng.integers(3, 9)] + 50])
    hashed = [[int(x) * 0x9E3779B97F4A7C15 % 2**64 >> 1 for x in r] for r in rows]
    table = lambda rows: pa.table({"keys": pa.array(rows, pa.list_(pa.int64())), "distinct": [len(set(r)) for r in rows], "sum": [0.0] * len(rows), "df": pa.array([[0] * len(r) for r in rows], pa.list_(pa.int64()))})
    for kernel in ({"kind": "overlap"}, {"kind": "prefix"}, {"kind": "dampened"}, {"kind": "align", "alpha": 1.0, "beta": 2.0, "gamma": 0.1}):
        entries, asked = grid.Flat(table(hashed[:150])), grid.Flat(table(hashed[150:]))
        block = grid.Asked(grid.postings(asked, kernel, 100), kernel)
        at, cand = np.full(150, 1000), np.arange(150)
        all_of = lambda bound: [np.concatenate(x) for x in zip(*grid._entries_for(entries, block, entries, 100, "sum", None).scored(bound, at, cand), strict=True)]
        q, c, score = all_of(np.full(150, -1.0))
        best = np.zeros(150)
        np.maximum.at(best, q, score)
        q2, c2, score2 = all_of(best)
        want = {(a, b, s) for a, b, s in zip(q.tolist(), c.tolist(), score.tolist(), strict=True) if s == best[a]}
        assert len(q) == 150 * 150 and want <= set(zip(q2.tolist(), c2.tolist(), score2.tolist(), strict=True)) and len(want) >= 150
        assert kernel["kind"] == "prefix" or len(q2) < 150 * 75


def test_keyed_orders_equal_gathered_ones(spark, monkeypatch):
    from tracegroup.sources import workloads as wl

    monkeypatch.setattr(wl, "GATHERED_LINES", 3)
    for make in (wl.orders_longtail, wl.orders_dense):
        want = make(spark, "/root/testdata/sf0.001").collect()
        got = {r["report_id"]: r for r in make(spark, "/root/testdata/sf0.001", keyed=True).collect()}
        assert len(want) == len(got) > 0
        for r in want:
            g = got[r["report_id"]]
            assert (g["arrival"], g["category_id"], len(g["frames"])) == (r["arrival"], r["category_id"], len(r["frames"]))
            assert [k & 1 for k in g["frames"]] == [".PROMO." in f for f in r["frames"]]


def test_position_effect_gathers_no_arrays_of_names(spark, monkeypatch):
    from tracegroup.plans import probes
    from tracegroup.sources import workloads as wl

    def gathered(*_):
        raise AssertionError("names gathered")

    monkeypatch.setattr(wl, "in_order", gathered)
    assert probes.position_effect(spark, "/root/testdata/sf0.001").count() > 1
