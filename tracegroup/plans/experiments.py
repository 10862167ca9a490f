"""The experiments: accuracy and time of all systems over the workloads, and how each option moves them.

Each gives plain rows; `python -m tracegroup.plans.experiments NAME SF_DIR` prints one as a table.
"""

from __future__ import annotations

import os
import sys
import time
from collections.abc import Callable
from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tracegroup.operators import baselines, index, metrics, neural_baselines, replay, train
from tracegroup.operators import chronology as ch
from tracegroup.plans.queries import kept, scorer
from tracegroup.plans.two_stage import TwoStage
from tracegroup.sources.storage import run_only, written

FLAT = ("overlap", "tfidf", "tfidf_cosine", "align", "prefix", "edit")
SEP = {"orders_longtail": ".", "orders_dense": "."}


def options(name: str, **more) -> TwoStage:
    return TwoStage(sep=SEP.get(name), **more)


def text_embedding_outcomes(reports: DataFrame, k: int = 10) -> DataFrame:
    """The offline stand-in for a hosted text-embedding model, searched like the method's vectors."""
    queries = ch.queries_of(reports)
    vec = written(baselines.text_vectors(baselines.traces_of(reports)), "text-vectors")
    first = reports.groupBy("fp").agg(F.min("arrival_seq").alias("seq")).join(vec, "fp").select(F.col("fp").alias("id"), "seq", "vec")
    q = queries.select(F.col("fp").alias("id")).distinct().join(first, "id")
    found = index.exact_topk(q, first, k).select(F.col("q_id").alias("q_fp"), F.col("c_id").alias("c_fp"), "score")
    return replay.outcomes(queries, replay.ranked(replay.category_scores(replay.earlier_pairs(queries, found, ch.index_entries(reports)))))


def searched_outcomes(reports: DataFrame, search) -> DataFrame:
    """Outcomes of a method that finds candidates itself: search(reports, queries) -> (q_fp, c_fp, score)."""
    queries = ch.queries_of(reports)
    found = replay.earlier_pairs(queries, search(reports, queries), ch.index_entries(reports))
    return replay.outcomes(queries, replay.ranked(replay.category_scores(found)))


def _measured(o: DataFrame) -> dict:
    o = written(o, "outcomes")
    return metrics.acc_at_1(o).first().asDict() | {"auc": metrics.roc_auc(o).first()["auc"]}


def accuracy(spark: SparkSession, sf_dir: str, names: tuple[str, ...] = ("orders_longtail", "planted_docs", "conversation_stacks")) -> list[dict]:
    """Acc@1 and ROC-AUC of every system on every workload."""
    rows = []
    for name in names:
        reports = kept(spark, sf_dir, name)
        for system in FLAT:
            rows.append({"workload": name, "system": system} | _measured(replay.run(reports, scorer(system, reports))))
        rows.append({"workload": name, "system": "text embedding (stand-in)"} | _measured(text_embedding_outcomes(reports)))
        for label, search in (("pairwise frame model", neural_baselines.pairwise_frames), ("package vectors", neural_baselines.package_vectors)):
            rows.append({"workload": name, "system": label} | _measured(searched_outcomes(reports, search)))
        fitted = options(name).fit(reports)
        rows.append({"workload": name, "system": "two-stage"} | _measured(fitted.outcomes(reports)))
        fitted.cross = None
        rows.append({"workload": name, "system": "embedding only"} | _measured(fitted.outcomes(reports)))
    return rows


def candidates_kept(spark: SparkSession, sf_dir: str, name: str = "planted_docs", ks: tuple[int, ...] = (5, 10, 20, 50, 100)) -> list[dict]:
    """Acc@1 of the two stages by the number of candidates."""
    reports = kept(spark, sf_dir, name)
    fitted = options(name).fit(reports)
    rows = []
    for k in ks:
        fitted.options = replace(fitted.options, k=k)
        rows.append({"k": k} | _measured(fitted.outcomes(reports)))
    return rows


def variants(spark: SparkSession, sf_dir: str, name: str = "planted_docs") -> list[dict]:
    """Pools, frame encoders, vocabularies, marker on and off, search."""
    reports = kept(spark, sf_dir, name)
    base = options(name)
    tried = {f"pool {p}": replace(base, encoder=replace(base.encoder, pool=p), reranker=False) for p in ("all", "avg", "max", "hidden")}
    tried["frame encoder mean"] = replace(base, encoder=replace(base.encoder, frame_encoder="mean"), reranker=False)
    tried |= {f"tokens {t}": replace(base, tokens=t, reranker=False) for t in ("frame", "package")}
    tried |= {"reranker with marker": base, "reranker without marker": replace(base, use_marker=False), "ivf search": replace(base, search="ivf", reranker=False)}
    return [{"variant": v} | _measured(o.fit(reports).outcomes(reports)) for v, o in tried.items()]


def timed(make: Callable[[], DataFrame], runs: int = 3) -> float:
    """Median seconds of running a plan, after a warm-up."""
    run_only(make())
    took = []
    for _ in range(runs):
        began = time.time()
        run_only(make())
        took.append(time.time() - began)
    return sorted(took)[len(took) // 2]


def time_per_report(spark: SparkSession, sf_dir: str, name: str = "orders_longtail") -> dict[str, float]:
    """Milliseconds per test report, scoring only, vectors and tokens at hand; retrieval and reranking apart."""
    reports = kept(spark, sf_dir, name)
    queries = written(ch.queries_of(reports), "queries")
    n = max(1, queries.count())
    traces = written(baselines.traces_of(reports), "traces")
    asked = written(baselines.traces_of(queries), "asked")
    out = {s: round(1000 * timed(lambda s=s: scorer(s, reports)(asked, traces), 1) / n, 4) for s in ("tfidf", "align")}
    small = options(name, training=train.TrainConfig(epochs=1, most_rows=300))
    fitted = small.fit(reports)
    out["embedding only"] = round(1000 * timed(lambda: fitted.candidates(reports, queries), 1) / n, 4)
    found = written(fitted.candidates(reports, queries), "candidates")
    rerank = round(1000 * timed(lambda: train.rescore(found, fitted.toks, fitted.cross), 1) / n, 4)
    return out | {"reranking": rerank, "two-stage": round(out["embedding only"] + rerank, 4), "test reports": n}


def scaling(spark: SparkSession, sf_dir: str, name: str = "orders_longtail", folders: tuple[str, ...] = ("sf0.001", "sf0.01", "sf0.1")) -> list[dict]:
    """Time and pair comparisons per report over folders beside sf_dir, by the number of earlier distinct traces."""
    rows = []
    for folder in folders:
        reports = kept(spark, os.path.join(os.path.dirname(sf_dir.rstrip("/")), folder), name)
        queries = written(ch.queries_of(reports), "queries")
        traces, asked = written(baselines.traces_of(reports), "traces"), written(baselines.traces_of(queries), "asked")
        n = max(1, queries.count())
        for system in ("overlap", "tfidf", "align", "prefix"):
            pairs = scorer(system, reports)(asked, traces)
            rows.append({"folder": folder, "system": system, "n_index": traces.count(), "ms_per_report": round(1000 * timed(lambda pairs=pairs: pairs, 1) / n, 4)} | metrics.work_counters(pairs, queries).first().asDict())
    return rows


EXPERIMENTS = {f.__name__: f for f in (accuracy, candidates_kept, variants, scaling)}

if __name__ == "__main__":
    session = SparkSession.builder.master("local[*]").config("spark.driver.memory", "8g").config("spark.sql.shuffle.partitions", "8").config("spark.ui.showConsoleProgress", "false").getOrCreate()
    for row in EXPERIMENTS[sys.argv[1]](session, sys.argv[2]):
        print(row)
