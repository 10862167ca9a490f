"""Queries that compare systems and parts, and relational operations over reports, each with its SQL twin."""

from __future__ import annotations

from functools import partial

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tracegroup.operators import metrics, temporal
from tracegroup.plans import oracles
from tracegroup.plans import queries as plans
from tracegroup.sources import workloads as wl
from tracegroup.sources.storage import load

TEN_MINUTES = 600_000_000
#: Workloads whose accuracy the main catalogue does not register.
MORE = ("orders_dense", "event_errors", "page_dom", "whole_docs")


def _events(spark: SparkSession, sf_dir: str, kind: str) -> DataFrame:
    e = load(spark, sf_dir, "events").where(F.col("event_type") == kind)
    return e.select("event_id", "user_id", F.unix_micros(F.col("ts").cast("timestamp")).alias("at"))


def bursts_after_errors(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Banded range join: clicks in the ten minutes from each error on."""
    errors = _events(spark, sf_dir, "error").select("event_id", F.col("at").alias("error_at"))
    clicks = _events(spark, sf_dir, "click").select(F.col("at").alias("click_at"))
    met = temporal.range_join(errors, clicks, "error_at", "click_at", TEN_MINUTES)
    return met.groupBy("event_id").agg(F.count("*").alias("n_clicks"), F.min(F.col("click_at") - F.col("error_at")).alias("first_gap"))


def last_purchase_before_error(spark: SparkSession, sf_dir: str) -> DataFrame:
    """As-of join: the latest purchase of the error's user that is not after it."""
    right = _events(spark, sf_dir, "purchase").withColumnRenamed("event_id", "purchase_id")
    return temporal.as_of_join(_events(spark, sf_dir, "error"), right, "user_id", "at", "purchase_id").select("event_id", "purchase_id", "since")


def systems_side_by_side(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Full outer comparison: per report, what two systems say where either attaches it (score above a quarter)."""
    reports = plans.kept(spark, sf_dir, "conversation_stacks")
    sides = [plans.replay.run(reports, plans.scorer(s, reports)).where("score > 0.25").select("query_seq", F.col("predicted").alias(s), F.col("correct").alias(f"{s}_correct")) for s in ("overlap", "align")]
    return sides[0].join(sides[1], "query_seq", "full")


def trace_length_percentiles(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = None
    for name in ("orders_dense", "whole_docs", "page_dom"):
        n = F.size("frames").cast("double")
        at = [F.round(F.percentile(n, p), 6).alias(f"p{int(100 * p)}") for p in (0.5, 0.9, 0.99)]
        row = wl.WORKLOADS[name](spark, sf_dir).agg(F.lit(name).alias("workload"), *at, F.count("*").alias("n"))
        out = row if out is None else out.unionByName(row)
    return out


def reports_cube(spark: SparkSession, sf_dir: str) -> DataFrame:
    r = wl.reports(spark, sf_dir, "event_errors").select("part", "category_id")
    return r.cube("part", "category_id").agg(F.count("*").alias("n"), F.grouping_id().cast("long").alias("level"))


def category_sets(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Set operations: categories of both the train and the test part, of the test part alone, and of either."""
    r = plans.kept(spark, sf_dir, "orders_longtail")
    old, new = (r.where(F.col("part") == p).select("category_id") for p in ("train", "test"))
    kinds = {"both": old.intersect(new), "test only": new.subtract(old), "either": old.union(new).distinct()}
    out = None
    for kind, df in kinds.items():
        part = df.select(F.lit(kind).alias("kind"), "category_id")
        out = part if out is None else out.unionByName(part)
    return out


def sampled_reports(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Stratified sampling: of each category the tenth of its reports, at least one, whose ids hash lowest."""
    r = wl.orders_dense(spark, sf_dir).select("report_id", "category_id", F.md5(F.col("report_id").cast("string")).alias("h"))
    order = plans.Window.partitionBy("category_id").orderBy("h", "report_id")
    n = F.count("*").over(plans.Window.partitionBy("category_id"))
    return r.withColumn("place", F.row_number().over(order)).withColumn("n", n).where("place <= greatest(1, floor(n / 10))").select("report_id", "category_id")


def acc_by_category_size(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Accuracy of attached reports by how many train reports their category has."""
    reports, frames = wl.keyed(spark, sf_dir, "orders_longtail")
    size = reports.where("part = 'train'").groupBy("category_id").agg(F.count("*").alias("n_train"))
    out = None
    for system, told in plans.outcomes_of_systems(reports, frames=frames).items():
        o = told.where("not is_new")
        o = o.join(size, o["true_category"] == size["category_id"], "left").withColumn("n_train", F.coalesce("n_train", F.lit(0)))
        band = F.when(F.col("n_train") == 0, "0").when(F.col("n_train") == 1, "1").when(F.col("n_train") < 5, "2-4").when(F.col("n_train") < 20, "5-19").otherwise("20 and more")
        part = o.groupBy(band.alias("train_reports")).agg(F.round(F.avg(F.col("correct").cast("double")), 6).alias("acc_at_1"), F.count("*").alias("n")).select(F.lit(system).alias("system"), "*")
        out = part if out is None else out.unionByName(part)
    return out


def queries() -> dict[str, plans.Query]:
    plain = (bursts_after_errors, last_purchase_before_error, systems_side_by_side, trace_length_percentiles, reports_cube, category_sets, sampled_reports, acc_by_category_size)
    found: dict[str, plans.Query] = {f.__name__: f for f in plain}
    found["reports_whole_docs"] = lambda spark, sf_dir: plans.report_rows(spark, sf_dir, "whole_docs")
    for name in MORE:
        found[f"acc_at_1_{name}"] = partial(plans.acc_at_1, name)
        if name != "event_errors" and name != "orders_dense":  # their test parts open no category
            found[f"roc_auc_{name}"] = partial(plans.roc_auc, name)
    return found


def oracle_sql() -> dict[str, str]:
    at = "SELECT event_id, user_id, epoch_us(ts) AS at_ FROM events WHERE event_type ="
    band = "CASE WHEN coalesce(n_train, 0) = 0 THEN '0' WHEN n_train = 1 THEN '1' WHEN n_train < 5 THEN '2-4' WHEN n_train < 20 THEN '5-19' ELSE '20 and more' END"
    side = lambda s: f"(WITH {oracles.replayed('conversation_stacks', s)} SELECT query_seq, predicted AS {s}, correct AS {s}_correct FROM u WHERE score > 0.25)"
    sizes = [f"SELECT * FROM (WITH {oracles.replayed('orders_longtail', s)}, z AS (SELECT category_id, count(*) AS n_train FROM r WHERE part = 'train' GROUP BY category_id) SELECT '{s}' AS system, {band} AS train_reports, round(avg(correct::INT), 6) AS acc_at_1, count(*) AS n FROM u LEFT JOIN z ON true_category = z.category_id WHERE NOT is_new GROUP BY 2)" for s in plans.SYSTEMS]
    lengths = [f"SELECT * FROM (WITH {oracles.WORKLOADS[n]} SELECT '{n}' AS workload, {', '.join(f'round(quantile_cont(len(frames)::DOUBLE, {p}), 6) AS p{int(100 * p)}' for p in (0.5, 0.9, 0.99))}, count(*) AS n FROM w)" for n in ("orders_dense", "whole_docs", "page_dom")]
    out = {
        "bursts_after_errors": f"WITH e AS ({at} 'error'), c AS ({at} 'click') SELECT e.event_id, count(*) AS n_clicks, min(c.at_ - e.at_) AS first_gap FROM e JOIN c ON c.at_ >= e.at_ AND c.at_ < e.at_ + {TEN_MINUTES} GROUP BY e.event_id",
        "last_purchase_before_error": f"WITH e AS ({at} 'error'), p AS (SELECT user_id, at_, max(event_id) AS purchase_id FROM ({at} 'purchase') GROUP BY ALL) SELECT e.event_id, purchase_id, p.at_ AS since FROM e ASOF LEFT JOIN p ON e.user_id = p.user_id AND e.at_ >= p.at_",
        "systems_side_by_side": f"SELECT coalesce(a.query_seq, b.query_seq) AS query_seq, overlap, overlap_correct, align, align_correct FROM {side('overlap')} a FULL JOIN {side("align")} b ON a.query_seq = b.query_seq",
        "trace_length_percentiles": " UNION ALL ".join(lengths),
        "reports_cube": f"WITH {oracles.reports('event_errors')} SELECT part, category_id, count(*) AS n, grouping_id(part, category_id) AS level FROM r GROUP BY CUBE (part, category_id)",
        "category_sets": f"WITH {oracles.reports('orders_longtail')}, o AS (SELECT category_id FROM r WHERE part = 'train'), t AS (SELECT category_id FROM r WHERE part = 'test') SELECT 'both' AS kind, category_id FROM (SELECT * FROM o INTERSECT SELECT * FROM t) UNION ALL SELECT 'test only', category_id FROM (SELECT * FROM t EXCEPT SELECT * FROM o) UNION ALL SELECT 'either', category_id FROM (SELECT * FROM o UNION SELECT * FROM t)",
        "sampled_reports": f"WITH {oracles.WORKLOADS['orders_dense']}, x AS (SELECT report_id, category_id, row_number() OVER (PARTITION BY category_id ORDER BY md5(report_id::VARCHAR), report_id) AS place, count(*) OVER (PARTITION BY category_id) AS n FROM w) SELECT report_id, category_id FROM x WHERE place <= greatest(1, n // 10)",
        "acc_by_category_size": " UNION ALL ".join(sizes),
        "reports_whole_docs": f"WITH {oracles.reports('whole_docs')} SELECT report_id, arrival_seq, len(frames) AS n_frames, fp, category_id FROM r",
    }
    for name in MORE:
        out[f"acc_at_1_{name}"] = oracles._systems(name, oracles._ACC)
        if name != "event_errors" and name != "orders_dense":
            out[f"roc_auc_{name}"] = oracles._aucs(name)
    return out
