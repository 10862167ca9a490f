"""The engine's queries by name: (spark, sf_dir) -> DataFrame, over whole tables."""

from __future__ import annotations

from collections.abc import Callable
from functools import partial

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from tracegroup.functions import frames as ff
from tracegroup.operators import baselines, bpe, curate, decide, grid, index, losses, metrics, neural_baselines, pairs, replay
from tracegroup.operators import chronology as ch
from tracegroup.operators.components import resolve_roots
from tracegroup.plans.two_stage import TwoStage
from tracegroup.sources import workloads as wl
from tracegroup.sources.storage import load, written

Query = Callable[[SparkSession, str], DataFrame]
REPORT_TABLES = ("orders_longtail", "orders_dense", "planted_docs", "conversation_stacks", "event_errors", "page_dom")
STATS_TABLES = (*REPORT_TABLES, "page_tags", "label_groups")
SYSTEMS = ("align", "overlap", "prefix", "tfidf")
CAP, SEED = 5, 1


def kept(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A workload's reports, written once (by the numbering): replay reads them several times."""
    return wl.reports(spark, sf_dir, name, ("frames", "category_id"))


def scorer(system: str, reports: DataFrame) -> baselines.Scorer:
    old = reports.where("part = 'train'")
    return {"overlap": baselines.set_overlap, "prefix": baselines.prefix_match, "tfidf": baselines.TfIdf(old), "tfidf_cosine": baselines.TfIdf(old, "cosine"), "align": baselines.TopFrameAlign(old), "edit": baselines.EditDistance("frame"), "edit_char": baselines.EditDistance("char")}[system]


def outcome(spark: SparkSession, sf_dir: str, name: str, system: str, part: str = "test", skip: bool = True) -> DataFrame:
    reports, frames = wl.keyed(spark, sf_dir, name)
    return replay.run(reports, scorer(system, reports), part, skip, ranks=False, frames=frames)


def outcomes_of_systems(reports: DataFrame, ranks: bool = False, frames: DataFrame | None = None) -> dict[str, DataFrame]:
    """Outcomes of the test part by system, all worked out in one pass and written once."""
    told = written(grid.outcomes(reports, {s: scorer(s, reports) for s in SYSTEMS}, ranks=ranks, frames=frames), "outcomes")
    return {s: told.where(F.col("system") == s).drop("system") for s in SYSTEMS}


def _each_system(spark: SparkSession, sf_dir: str, name: str, measure: Callable[[DataFrame], DataFrame], ranks: bool = False) -> DataFrame:
    out = None
    reports, frames = wl.keyed(spark, sf_dir, name)
    for system, told in outcomes_of_systems(reports, ranks, frames).items():
        part = measure(told).select(F.lit(system).alias("system"), "*")
        out = part if out is None else out.unionByName(part)
    return out


def report_rows(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return wl.reports(spark, sf_dir, name).select("report_id", "arrival_seq", F.size("frames").cast("long").alias("n_frames"), "fp", "category_id")


def fingerprints(spark: SparkSession, sf_dir: str, name: str = "planted_docs") -> DataFrame:
    return wl.reports(spark, sf_dir, name).groupBy("fp").agg(F.count("*").alias("n_reports"), F.min("arrival_seq").alias("first_seq"))


def identical_shortcut(spark: SparkSession, sf_dir: str, name: str = "planted_docs") -> DataFrame:
    return ch.identical_shortcut(kept(spark, sf_dir, name))


def skip_identical(spark: SparkSession, sf_dir: str, name: str = "planted_docs") -> DataFrame:
    q = ch.queries_of(kept(spark, sf_dir, name))
    return q.select("report_id", "arrival_seq", "is_new")


def chrono_split(spark: SparkSession, sf_dir: str, name: str = "planted_docs") -> DataFrame:
    return wl.reports(spark, sf_dir, name).select("report_id", "arrival_seq", "part")


def shared_traces(spark: SparkSession, sf_dir: str) -> DataFrame:
    return metrics.shared_traces(wl.reports(spark, sf_dir, "page_tags"))


def dataset_stats(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = None
    for name in STATS_TABLES:
        reports = wl.WORKLOADS[name](spark, sf_dir).withColumn("fp", ff.fingerprint(F.col("frames")))
        row = metrics.dataset_stats(reports).select(F.lit(name).alias("workload"), "*")
        out = row if out is None else out.unionByName(row)
    return out


def _part_frames(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "part").select(F.concat_ws(".", "p_brand", "p_type", "p_name").alias("frame")).distinct()


def frame_parts(spark: SparkSession, sf_dir: str) -> DataFrame:
    f = _part_frames(spark, sf_dir).withColumn("p", ff.parse_frame(F.col("frame")))
    return f.select("frame", "p.package", "p.class_name", "p.method")


def frame_pieces(style: str, spark: SparkSession, sf_dir: str) -> DataFrame:
    # names with humps, acronyms and digits, made of the given ones
    f = _part_frames(spark, sf_dir).select(F.concat(F.translate("frame", " #", "_X"), F.lit("."), F.regexp_replace(F.initcap("frame"), "[^A-Za-z0-9]", ""), F.lit("HTTPServer2Go")).alias("frame"))
    return f.select("frame", F.array_join(ff.pieces(F.col("frame"), style), "|").alias("pieces"))


def _counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe.piece_counts(_part_frames(spark, sf_dir).select(ff.pieces(F.col("frame")).alias("pieces")))


def bpe_piece_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _counts(spark, sf_dir)


def bpe_first_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe.first_pairs(_counts(spark, sf_dir))


def bpe_merges(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe.model_tables(spark, bpe.train(_counts(spark, sf_dir)))[0]


def bpe_encoded_lengths(spark: SparkSession, sf_dir: str) -> DataFrame:
    counts = written(_counts(spark, sf_dir), "pieces")
    return bpe.encoded(counts, bpe.train(counts)).select("piece", F.size("tokens").alias("n_tokens"))


def positive_pair_counts(spark: SparkSession, sf_dir: str, name: str = "planted_docs") -> DataFrame:
    return pairs.positive_pairs(kept(spark, sf_dir, name), CAP, SEED).groupBy("category_id").agg(F.count("*").alias("n_pairs"))


def positive_pairs_capped(spark: SparkSession, sf_dir: str, name: str = "planted_docs") -> DataFrame:
    return pairs.positive_pairs(kept(spark, sf_dir, name), CAP, SEED)


def pair_batches(spark: SparkSession, sf_dir: str, name: str = "planted_docs") -> DataFrame:
    drawn = pairs.batches(pairs.positive_pairs(kept(spark, sf_dir, name), CAP, SEED), 64, SEED)
    return drawn.select("anchor_fp", "positive_fp", "category_id", "batch", "slot")


def triplet_draws(spark: SparkSession, sf_dir: str, name: str = "planted_docs") -> DataFrame:
    reports = kept(spark, sf_dir, name)
    return pairs.triplets(pairs.positive_pairs(reports, CAP, SEED), reports, SEED)


def _vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), F.col("vec_id").alias("seq"), F.col("embedding").alias("vec"), "label")


def info_nce_on_embeddings(spark: SparkSession, sf_dir: str) -> DataFrame:
    v = _vectors(spark, sf_dir).withColumn("batch", F.floor(F.col("id") / 32))
    a = v.where("id % 2 = 0").select("batch", F.col("id").alias("anchor"), F.col("vec").alias("av"))
    o = v.where("id % 2 = 1").select("batch", F.col("id").alias("other"), F.col("vec").alias("ov"))
    table = a.join(o, "batch").select("anchor", "other", (F.col("other") == F.col("anchor") + 1).alias("is_positive"), index.cosine(F.col("av"), F.col("ov")).alias("similarity"))
    return losses.info_nce_table(table)


def bce_on_embeddings(spark: SparkSession, sf_dir: str) -> DataFrame:
    v = _vectors(spark, sf_dir).select("id", "vec")
    side = lambda name, shift: v.select((F.col("id") - shift).alias("anchor"), F.col("vec").alias(name))
    t = side("a", 0).where("anchor % 3 = 0").join(side("p", 1), "anchor").join(side("n", 2), "anchor")
    scored = t.select("anchor", F.round(5 * index.cosine(F.col("a"), F.col("p")), 9).alias("positive_score"), F.round(5 * index.cosine(F.col("a"), F.col("n")), 9).alias("negative_score"))
    return losses.bce_table(scored).select("anchor", "loss")


def _pool(how: str, spark: SparkSession, sf_dir: str) -> DataFrame:
    each = _vectors(spark, sf_dir).select("label", F.posexplode("vec").alias("place", "x")).withColumn("x", F.col("x").cast("double"))
    return each.groupBy("label", "place").agg(F.round({"avg": F.avg, "max": F.max}[how]("x"), 6).alias("value"))


def exact_topk_embeddings(spark: SparkSession, sf_dir: str) -> DataFrame:
    v = _vectors(spark, sf_dir)
    return index.exact_topk(v.where("id % 20 = 0"), v, 10, causal=False)


def causal_best_match(spark: SparkSession, sf_dir: str) -> DataFrame:
    v = _vectors(spark, sf_dir)
    return index.exact_topk(v.where("id % 20 = 0"), v, 1, causal=True)


def ivf_full_probe(spark: SparkSession, sf_dir: str) -> DataFrame:
    v = written(_vectors(spark, sf_dir).select("id", "seq", "vec"), "vectors")
    centroids, cells = index.ivf_build(v, 8)
    return index.ivf_topk(v.where("id % 20 = 0"), cells, centroids, 10, len(centroids), causal=False, salts=2)


def ann_recall(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Share of the exact ten nearest that each index finds."""
    v = written(_vectors(spark, sf_dir).select("id", "seq", "vec"), "vectors")
    q = v.where("id % 20 = 0")
    exact = written(index.exact_topk(q, v, 10, causal=False), "exact")
    centroids, cells = index.ivf_build(v, 8)
    found = {"ivf nprobe 6 of 8": index.ivf_topk(q, cells, centroids, 10, 6, causal=False), "lsh 3 bits x 24 tables": index.lsh_topk(q, v, 10, 3, 24, causal=False), "sq8": index.sq8_topk(q, v, 10, causal=False)}
    out = None
    for name, f in found.items():
        row = index.recall(f, exact).select(F.lit(name).alias("method"), "*")
        out = row if out is None else out.unionByName(row)
    return out


def lsh_bucket_keys(spark: SparkSession, sf_dir: str) -> DataFrame:
    return index.lsh_keys(_vectors(spark, sf_dir), 8, 2, 64).select("id", "tab", "bucket")


def category_scores(spark: SparkSession, sf_dir: str) -> DataFrame:
    reports = kept(spark, sf_dir, "conversation_stacks")
    q = ch.queries_of(reports)
    scored = baselines.set_overlap(baselines.traces_of(q), baselines.traces_of(reports))
    return replay.category_scores(replay.earlier_pairs(q, scored, ch.index_entries(reports)))


def _variant_pairs(spark: SparkSession, sf_dir: str, name: str = "planted_docs") -> DataFrame:
    r = wl.WORKLOADS[name](spark, sf_dir)
    side = lambda n, k: r.where(F.col("report_id") % 10 == k).select("category_id", F.col("frames").alias(n))
    return side("q", 1).join(side("k", 0), "category_id")


def _flags(a: str, b: str):
    return F.array_join(F.transform(a, lambda x: F.array_contains(b, x).cast("int").cast("string")), "")


def shared_frame_flags(spark: SparkSession, sf_dir: str, name: str = "planted_docs") -> DataFrame:
    return _variant_pairs(spark, sf_dir, name).select("category_id", _flags("q", "k").alias("query_flags"), _flags("k", "q").alias("candidate_flags"))


def shared_frame_counts(spark: SparkSession, sf_dir: str, name: str = "planted_docs") -> DataFrame:
    return _variant_pairs(spark, sf_dir, name).select("category_id", F.size(F.filter("q", lambda x: F.array_contains("k", x))).cast("long").alias("in_query"), F.size(F.filter("k", lambda x: F.array_contains("q", x))).cast("long").alias("in_candidate"))


def _topk(system: str, name: str, spark: SparkSession, sf_dir: str) -> DataFrame:
    reports, frames = wl.keyed(spark, sf_dir, name)
    return grid.nearest(reports, scorer(system, reports), 10, frames=frames).select("query_seq", "category_id", F.round("score", 6).alias("score"), "cand_seq", F.col("rank").cast("long").alias("rank"))


def char_edit_distance(spark: SparkSession, sf_dir: str) -> DataFrame:
    r = kept(spark, sf_dir, "orders_longtail").select("arrival_seq", ff.concatenated(F.col("frames")).alias("t"))
    before = r.select((F.col("arrival_seq") + 1).alias("arrival_seq"), F.col("t").alias("u"))
    d = F.levenshtein("t", "u")
    return r.join(before, "arrival_seq").select("arrival_seq", d.cast("long").alias("distance"), F.round(1 - d / F.greatest(F.length("t"), F.length("u")), 6).alias("similarity"))


def llm_concat_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    return wl.orders_longtail(spark, sf_dir).select("report_id", ff.concatenated(F.col("frames"), " ; ", 5).alias("text"))


def acc_at_1(name: str, spark: SparkSession, sf_dir: str) -> DataFrame:
    return _each_system(spark, sf_dir, name, metrics.acc_at_1)


def roc_auc(name: str, spark: SparkSession, sf_dir: str) -> DataFrame:
    return _each_system(spark, sf_dir, name, metrics.roc_auc)


def acc_at_k(spark: SparkSession, sf_dir: str, name: str = "planted_docs") -> DataFrame:
    return _each_system(spark, sf_dir, name, metrics.acc_at_k, ranks=True)


def roc_points(spark: SparkSession, sf_dir: str) -> DataFrame:
    return metrics.roc_points(outcome(spark, sf_dir, "orders_longtail", "overlap"))


def f1_curve(name: str, spark: SparkSession, sf_dir: str) -> DataFrame:
    return metrics.f1_curve(outcome(spark, sf_dir, name, "overlap", "validation"))


def best_threshold(name: str, spark: SparkSession, sf_dir: str) -> DataFrame:
    return metrics.best_threshold(outcome(spark, sf_dir, name, "overlap", "validation"))


def decisions(spark: SparkSession, sf_dir: str, name: str = "planted_docs") -> DataFrame:
    t = written(best_threshold(name, spark, sf_dir), "threshold")
    return decide.decide(outcome(spark, sf_dir, name, "overlap"), t).select("query_seq", "true_category", "is_new", "predicted", F.round("score", 6).alias("score"), "action")


def skip_rule_effect(spark: SparkSession, sf_dir: str, name: str = "planted_docs") -> DataFrame:
    reports, frames = wl.keyed(spark, sf_dir, name)
    out = None
    for skip in (True, False):
        row = metrics.acc_at_1(replay.run(reports, baselines.set_overlap, skip_identical=skip, ranks=False, frames=frames)).select(F.lit(skip).alias("skip"), "*")
        out = row if out is None else out.unionByName(row)
    return out


def category_roots(spark: SparkSession, sf_dir: str, name: str = "planted_docs") -> DataFrame:
    o = outcome(spark, sf_dir, name, "overlap")
    return resolve_roots(o.select(F.col("query_seq").alias("report"), F.when(F.col("score") > 0.5, F.col("best_cand")).alias("parent")))


def curate_reviewed(spark: SparkSession, sf_dir: str, name: str = "planted_docs") -> DataFrame:
    reviewed = load(spark, sf_dir, "labels").select(F.col("doc_id").cast("string").alias("category_id"))
    return curate.reviewed_only(wl.WORKLOADS[name](spark, sf_dir), reviewed).select("report_id", "category_id")


def curate_foreign(spark: SparkSession, sf_dir: str) -> DataFrame:
    before = wl.orders_longtail(spark, sf_dir)
    return curate.removed_share(before, curate.drop_foreign(before, ["Brand#1", "Brand#2"]))


def benchmark_probe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return wl.benchmark_probe(spark, sf_dir)


def acc_rollup_region(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Customers are looked up for the reports that are asked, by their order; lines are read once."""
    reports, frames = wl.keyed(spark, sf_dir, "orders_longtail")
    o = written(replay.run(reports, baselines.set_overlap, ranks=False, frames=frames).where("not is_new").select("query_seq", "correct"), "outcomes")
    asked = reports.where("part = 'test'").select(F.col("arrival_seq").alias("query_seq"), "report_id").join(o, "query_seq").select("report_id", "correct")
    told = wl.with_customers(asked.join(wl.orders_table(spark, sf_dir), "report_id"), sf_dir).withColumnsRenamed({"r_name": "region", "c_mktsegment": "segment"})
    return told.rollup("region", "segment").agg(F.round(F.avg(F.col("correct").cast("double")), 6).alias("acc_at_1"), F.count("*").alias("n"), F.grouping_id().cast("long").alias("level"))


def acc_pivot(spark: SparkSession, sf_dir: str) -> DataFrame:
    long = None
    for name in ("orders_longtail", "conversation_stacks"):
        part = acc_at_1(name, spark, sf_dir).select("system", F.lit(name).alias("workload"), "acc_at_1")
        long = part if long is None else long.unionByName(part)
    return long.groupBy("system").pivot("workload", ["orders_longtail", "conversation_stacks"]).agg(F.first("acc_at_1"))


def new_category_rate_hourly(spark: SparkSession, sf_dir: str) -> DataFrame:
    r = ch.truth(kept(spark, sf_dir, "event_errors")).withColumn("hour", F.floor(F.col("arrival") / 3_600_000_000))
    return r.groupBy("hour").agg(F.count("*").alias("n_reports"), F.count(F.when(F.col("is_new"), 1)).alias("n_new"))


def moving_acc(spark: SparkSession, sf_dir: str, name: str = "planted_docs") -> DataFrame:
    return metrics.moving_accuracy(outcome(spark, sf_dir, name, "overlap"))


def session_traces(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = load(spark, sf_dir, "events").withColumn("at", F.col("ts").cast("timestamp"))
    s = e.groupBy("user_id", F.session_window("at", "30 minutes").alias("w")).agg(F.count("*").alias("n_events"), F.count(F.when(F.col("event_type") == "error", 1)).alias("n_errors"))
    return s.select("user_id", F.unix_micros("w.start").alias("start_us"), "n_events", "n_errors")


def burst_windows(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = load(spark, sf_dir, "events").where("event_type = 'error'").withColumn("at", F.col("ts").cast("timestamp"))
    w = e.groupBy(F.window("at", "24 hours", "1 hour").alias("w")).agg(F.count("*").alias("n_errors"))
    return w.select(F.unix_micros("w.start").alias("start_us"), "n_errors")


def arrival_gaps(spark: SparkSession, sf_dir: str) -> DataFrame:
    w = Window.partitionBy("category_id").orderBy("arrival_seq")
    return kept(spark, sf_dir, "conversation_stacks").select("report_id", "category_id", (F.col("arrival_seq") - F.lag("arrival_seq").over(w)).alias("gap"))


def embedding_pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    reports = kept(spark, sf_dir, "whole_docs")
    return TwoStage(reranker=False, sep=None).fit(reports).decisions(reports)


def two_stage_pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    reports = kept(spark, sf_dir, "whole_docs")
    return TwoStage(sep=None).fit(reports).decisions(reports)


def _found(search: Callable, spark: SparkSession, sf_dir: str) -> DataFrame:
    reports = kept(spark, sf_dir, "whole_docs")
    q = ch.queries_of(reports)
    return replay.outcomes(q, replay.ranked(replay.category_scores(replay.earlier_pairs(q, search(reports, q), ch.index_entries(reports)))))


def pairwise_frames(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _found(neural_baselines.pairwise_frames, spark, sf_dir)


def package_vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _found(neural_baselines.package_vectors, spark, sf_dir)


#: Queries on planted_docs that also run on the variants of every document, as NAME_whole_docs.
ON_WHOLE_DOCS = (fingerprints, identical_shortcut, skip_identical, chrono_split, positive_pair_counts, positive_pairs_capped, pair_batches, triplet_draws, shared_frame_flags, shared_frame_counts, acc_at_k, decisions, skip_rule_effect, category_roots, curate_reviewed, moving_acc)


def queries() -> dict[str, Query]:
    found: dict[str, Query] = {f"reports_{name}": partial(_named(report_rows), name) for name in REPORT_TABLES}
    for f in (fingerprints, identical_shortcut, skip_identical, chrono_split, shared_traces, dataset_stats, frame_parts, bpe_piece_counts, bpe_first_pairs, bpe_merges, bpe_encoded_lengths, positive_pair_counts, positive_pairs_capped, pair_batches, triplet_draws, info_nce_on_embeddings, bce_on_embeddings, exact_topk_embeddings, causal_best_match, ivf_full_probe, ann_recall, lsh_bucket_keys, category_scores, shared_frame_flags, shared_frame_counts, char_edit_distance, llm_concat_text, acc_at_k, roc_points, decisions, skip_rule_effect, category_roots, curate_reviewed, curate_foreign, benchmark_probe, acc_rollup_region, acc_pivot, new_category_rate_hourly, moving_acc, session_traces, burst_windows, arrival_gaps, pairwise_frames, package_vectors, embedding_pipeline, two_stage_pipeline):
        found[f.__name__] = f
    for style in ("camel", "snake"):
        found[f"frame_pieces_{style}"] = partial(frame_pieces, style)
    for how in ("avg", "max"):
        found[f"pool_{how}"] = partial(_pool, how)
    for system, name in (("tfidf", "conversation_stacks"), ("tfidf_cosine", "conversation_stacks"), ("align", "conversation_stacks"), ("prefix", "orders_longtail"), ("overlap", "conversation_stacks")):
        found[{"tfidf": "tfidf_topk", "tfidf_cosine": "tfidf_cosine_topk", "align": "top_frame_align", "prefix": "prefix_match", "overlap": "set_overlap"}[system]] = partial(_topk, system, name)
    for name in ("orders_longtail", "planted_docs", "conversation_stacks"):
        found[f"acc_at_1_{name}"] = partial(acc_at_1, name)
        found[f"roc_auc_{name}"] = partial(roc_auc, name)
    for f in ON_WHOLE_DOCS:
        found[f"{f.__name__}_whole_docs"] = partial(f, name="whole_docs")
    for name in ("orders_longtail", "planted_docs", "whole_docs"):
        found[f"f1_curve_{name}"] = partial(f1_curve, name)
        found[f"best_threshold_{name}"] = partial(best_threshold, name)
    return found


def _named(f: Callable) -> Callable:
    return lambda name, spark, sf_dir: f(spark, sf_dir, name)
