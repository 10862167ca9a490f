"""Queries on what the methods stand on: recall of the true category, work, unknown names, places of deciding frames, copies; and twins over all documents."""

from __future__ import annotations

from functools import partial

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tracegroup.functions.frames import pieces
from tracegroup.operators import baselines, bpe, metrics, replay, train
from tracegroup.operators import chronology as ch
from tracegroup.plans import experiments, oracles
from tracegroup.plans import queries as plans
from tracegroup.sources import workloads as wl
from tracegroup.sources.storage import written

CANDIDATES = (5, 10, 20, 50, 100)
COUNTED = ("orders_longtail", "whole_docs")


def true_category_recall(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Share of attached reports whose category is among the first k: what reranking k candidates can reach at most."""
    shares = lambda o: metrics.acc_at_k(o, CANDIDATES).select(*[F.col(f"acc_at_{k}").alias(f"recall_at_{k}") for k in CANDIDATES])
    return plans._each_system(spark, sf_dir, "orders_longtail", shares, ranks=True)


def work_per_report(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pair comparisons of each system, in all and per kept test report."""
    out = None
    for name in COUNTED:
        reports = plans.kept(spark, sf_dir, name)
        queries = ch.queries_of(reports)
        for system in plans.SYSTEMS:
            pairs = plans.scorer(system, reports)(baselines.traces_of(queries), baselines.traces_of(reports))
            row = metrics.work_counters(pairs, queries).select(F.lit(name).alias("workload"), F.lit(system).alias("system"), "*")
            out = row if out is None else out.unionByName(row)
    return out


def _frame_counts(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """(frame, old, new): how often each frame stands in reports of the train and of the test part."""
    flat = plans.kept(spark, sf_dir, name).select("part", F.explode("frames").alias("frame"))
    return flat.groupBy("frame").agg(F.count(F.when(F.col("part") == "train", 1)).alias("old"), F.count(F.when(F.col("part") == "test", 1)).alias("new"))


def unknown_rate(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Share of the test part's frames, packages and signs that a closed vocabulary of the train part lacks."""
    out = None
    for name in COUNTED:
        counts = written(_frame_counts(spark, sf_dir, name), "frame-counts")
        units = {"frame": F.col("frame"), "package": F.split("frame", r"\.")[0], "sign": F.explode(F.split("frame", ""))}
        for unit, taken in units.items():
            per = counts.select(taken.alias("u"), "old", "new").groupBy("u").agg(F.sum("old").alias("old"), F.sum("new").alias("new"))
            row = per.agg(F.lit(name).alias("workload"), F.lit(unit).alias("tokenizer"), F.round(F.sum(F.when(F.col("old") == 0, F.col("new")).otherwise(0)) / F.sum("new"), 6).alias("unknown_rate"))
            out = row if out is None else out.unionByName(row)
    return out


def unknown_rate_byte_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same for tokens of a byte-pair model of the train part, which splits unseen names into known tokens."""
    out = None
    for name in COUNTED:
        cut = pieces(F.col("frame"), sep=experiments.SEP.get(name))
        counts = written(_frame_counts(spark, sf_dir, name).select("old", "new", F.explode(cut).alias("piece")).groupBy("piece").agg(F.sum("old").alias("old"), F.sum("new").alias("new")), "piece-counts")
        model = bpe.train(counts.where("old > 0").select("piece", F.col("old").alias("n")))
        tokens = bpe.encoded(counts.where("new > 0"), model).join(counts, "piece")
        unknown = F.size(F.filter("tokens", lambda t: t == bpe.UNKNOWN))
        row = tokens.agg(F.lit(name).alias("workload"), F.round(F.sum(unknown * F.col("new")) / F.sum(F.size("tokens") * F.col("new")), 6).alias("unknown_rate"))
        out = row if out is None else out.unionByName(row)
    return out


def position_effect(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Accuracy on orders_dense by where the first deciding frame stands, two places a bucket."""
    reports, frames = wl.keyed(spark, sf_dir, "orders_dense")
    first = F.array_position(F.transform("frames", wl.decides), True)
    places = frames.groupBy("fp").agg(F.first(F.floor((first - 1) / 2)).alias("pos_bucket"))
    place = reports.where("part = 'test'").select(F.col("arrival_seq").alias("query_seq"), "fp").join(places, "fp").drop("fp")
    out = None
    for system, told in plans.outcomes_of_systems(reports, frames=frames).items():
        o = told.where("not is_new").join(place, "query_seq")
        row = o.groupBy("pos_bucket").agg(F.round(F.avg(F.col("correct").cast("double")), 6).alias("acc_at_1"), F.count("*").alias("n")).select(F.lit(system).alias("system"), "*")
        out = row if out is None else out.unionByName(row)
    return out


def stats_doc_copies(spark: SparkSession, sf_dir: str) -> DataFrame:
    return metrics.dataset_stats(wl.reports(spark, sf_dir, "doc_copies"))


def edit_distance_replayed(unit: str, spark: SparkSession, sf_dir: str) -> DataFrame:
    """Edit distance as a baseline: accuracy of attaching to the category of the trace that takes the fewest edits."""
    reports = plans.kept(spark, sf_dir, "orders_longtail")
    return metrics.acc_at_1(replay.run(reports, baselines.EditDistance(unit)))


def text_embedding(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Outcomes of the text-embedding baseline with its offline stand-in."""
    return experiments.text_embedding_outcomes(plans.kept(spark, sf_dir, "whole_docs"))


def training_loss(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Loss of every step of both models, trained on the tasks over all pairs drawn from conversation_stacks."""
    fitted = plans.TwoStage(training=train.TrainConfig(epochs=2, task_steps=4), sep=None).fit(plans.kept(spark, sf_dir, "conversation_stacks"))
    return train.loss_table(spark, {"embedding": fitted.log, "reranker": fitted.cross_log})


def queries() -> dict[str, plans.Query]:
    plain = (true_category_recall, work_per_report, unknown_rate, unknown_rate_byte_pairs, position_effect, stats_doc_copies, text_embedding, training_loss)
    found: dict[str, plans.Query] = {f.__name__: f for f in plain}
    found["acc_at_1_edit_chars"] = partial(edit_distance_replayed, "char")
    found["acc_at_1_edit_frames"] = partial(edit_distance_replayed, "frame")
    found["acc_at_1_doc_copies"] = partial(plans.acc_at_1, "doc_copies")
    found["roc_auc_doc_copies"] = partial(plans.roc_auc, "doc_copies")
    return found


#: Categories are the smallest reachable ids over pairs of documents whose sentence sets have Jaccard 0.5 or more.
_COPIES = f"""w7 AS (SELECT doc_id, {oracles._SENTENCES} AS frames FROM documents), w8 AS (SELECT doc_id, len(list_distinct(frames)) AS n, unnest(list_distinct(frames)) AS frame FROM w7),
     w9 AS (SELECT a.doc_id AS x, b.doc_id AS y FROM w8 a JOIN w8 b USING (frame) WHERE a.doc_id <> b.doc_id GROUP BY a.doc_id, b.doc_id HAVING 2 * count(*) >= any_value(a.n) + any_value(b.n) - count(*)),
     w10(x, y) AS (SELECT doc_id, doc_id FROM w7 UNION SELECT w10.x, w9.y FROM w10 JOIN w9 ON w10.y = w9.x),
     w AS (SELECT doc_id AS report_id, doc_id AS arrival, any_value(frames) AS frames, min(y)::VARCHAR AS category_id FROM w7 JOIN w10 ON doc_id = x GROUP BY doc_id)"""
_UNITS = {"frame": "frame", "package": "string_split(frame, '.')[1]", "sign": "unnest(string_split(frame, ''))"}
#: Of equal scores the edit twin decides as the replay does; names are plain ASCII, where both engines count alike.
_EDIT = "v0 AS (SELECT fp, unnest(list_distinct(frames)) AS frame FROM t), v1 AS (SELECT DISTINCT a.fp AS q_fp, b.fp AS c_fp FROM v0 a JOIN v0 b USING (frame) WHERE a.fp IN (SELECT fp FROM q)), v2 AS (SELECT fp, array_to_string(frames, chr(10)) AS txt FROM t), s AS (SELECT q_fp, c_fp, 1 - levenshtein(x.txt, y.txt) / greatest(length(x.txt), length(y.txt), 1) AS score FROM v1 JOIN v2 x ON x.fp = q_fp JOIN v2 y ON y.fp = c_fp)"


def _unknown(name: str, unit: str) -> str:
    return f"SELECT * FROM (WITH {oracles.reports(name)}, x AS (SELECT frame, count(*) FILTER (part = 'train') AS old, count(*) FILTER (part = 'test') AS new FROM (SELECT part, unnest(frames) AS frame FROM r) GROUP BY frame), y AS (SELECT u, sum(old) AS old, sum(new) AS new FROM (SELECT {_UNITS[unit]} AS u, old, new FROM x) GROUP BY u) SELECT '{name}' AS workload, '{unit}' AS tokenizer, round(coalesce(sum(new) FILTER (old = 0), 0) / sum(new), 6) AS unknown_rate FROM y)"


def oracle_sql() -> dict[str, str]:
    oracles.WORKLOADS.setdefault("doc_copies", _COPIES)
    oracles.SCORERS.setdefault("edit_char", _EDIT)
    recalls = ", ".join(f"round(avg((coalesce(true_rank, 99999999) <= {k})::INT), 6) AS recall_at_{k}" for k in CANDIDATES)
    work = [f"SELECT * FROM (WITH {oracles.replayed(n, s)}, x AS (SELECT count(*) AS comparisons FROM s), y AS (SELECT count(*) AS n_queries FROM q) SELECT '{n}' AS workload, '{s}' AS system, comparisons, n_queries, round(comparisons / n_queries, 6) AS per_query FROM x, y)" for n in COUNTED for s in plans.SYSTEMS]
    places = [f"SELECT * FROM (WITH {oracles.replayed('orders_dense', s)} SELECT '{s}' AS system, floor((list_position(list_transform(q.frames, lambda f: contains(f, '.PROMO.')), true) - 1) / 2)::BIGINT AS pos_bucket, round(avg(correct::INT), 6) AS acc_at_1, count(*) AS n FROM u JOIN q ON q.arrival_seq = query_seq WHERE NOT u.is_new GROUP BY 2)" for s in plans.SYSTEMS]
    out = {
        "true_category_recall": oracles._systems("orders_longtail", recalls, "WHERE NOT is_new"),
        "work_per_report": " UNION ALL ".join(work),
        "unknown_rate": " UNION ALL ".join(_unknown(n, u) for n in COUNTED for u in _UNITS),
        "position_effect": " UNION ALL ".join(places),
        "stats_doc_copies": f"WITH RECURSIVE {oracles.reports('doc_copies')}, g AS (SELECT category_id, count(*) AS n, count(DISTINCT fp) AS u FROM r GROUP BY category_id) SELECT sum(n)::BIGINT AS n_reports, (SELECT count(DISTINCT fp) FROM r) AS n_unique, count(*) AS n_categories, round(avg(n), 6) AS avg_reports, round(avg(u), 6) AS avg_unique FROM g",
        "acc_at_1_edit_chars": f"WITH {oracles.replayed('orders_longtail', 'edit_char')} SELECT {oracles._ACC} FROM u",
        "acc_at_1_doc_copies": oracles._systems("doc_copies", oracles._ACC).replace("(WITH ", "(WITH RECURSIVE "),
        "roc_auc_doc_copies": oracles._aucs("doc_copies").replace("(WITH ", "(WITH RECURSIVE "),
    }
    known = oracles.oracle_sql()
    for f in plans.ON_WHOLE_DOCS:
        out[f"{f.__name__}_whole_docs"] = oracles.on_whole_docs(known[f.__name__])
    for name in ("f1_curve", "best_threshold"):
        out[f"{name}_whole_docs"] = oracles.on_whole_docs(known[f"{name}_planted_docs"])
    return out
