"""Connected components and roots of attachment chains."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tracegroup.sources.storage import written


def components(edges: DataFrame, what: str = "components", most_rounds: int = 60) -> DataFrame:
    """(node, component): the smallest node reachable over the edges (a, b), for every node of an edge.

    Alternates large-star and small-star steps: each node's larger neighbours, then its smaller ones,
    are hung on the smallest one known. Both are a min per node and an equi-join, so no group is ever
    gathered; rounds grow with the logarithm of a component's diameter.
    """
    pairs = written(edges.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).where("a < b").distinct(), what)
    before = None
    for _ in range(most_rounds):
        both = pairs.select(F.col("b").alias("u"), F.col("a").alias("v")).unionByName(pairs.select(F.col("a").alias("u"), F.col("b").alias("v")))
        low = both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("low"))
        large = both.where("v > u").join(low, "u").select(F.col("low").alias("a"), F.col("v").alias("b")).where("a < b").distinct()
        low2 = large.groupBy(F.col("b").alias("u")).agg(F.min("a").alias("low"))
        small = large.join(low2, large["b"] == low2["u"]).select("low", F.col("a").alias("x"), "b")
        nxt = small.select(F.col("low").alias("a"), "b").unionByName(small.select(F.col("low").alias("a"), F.col("x").alias("b"))).where("a < b").distinct()
        pairs = written(nxt, what)
        now = pairs.agg(F.count("*"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first()
        if now == before:
            break
        before = now
    else:
        raise RuntimeError(f"components did not settle in {most_rounds} rounds")
    stars = pairs.groupBy(F.col("b").alias("node")).agg(F.min("a").alias("component"))
    return stars.unionByName(pairs.select(F.col("a").alias("node"), F.col("a").alias("component")).distinct())


def resolve_roots(decisions: DataFrame, most_rounds: int = 60) -> DataFrame:
    """(report, root) from (report, parent or null): the report that opened the category a chain of attachments ends in.

    Pointers double: each round a report's parent becomes its parent's parent. Parents are earlier
    reports, so chains end; rounds grow with the logarithm of the longest chain.
    """
    now = decisions.select("report", F.coalesce("parent", "report").alias("root"))
    for _ in range(most_rounds):
        now = written(now, "roots")
        up = now.select(F.col("report").alias("via"), F.col("root").alias("above"))
        nxt = now.join(up, now["root"] == up["via"], "left").select("report", F.coalesce("above", "root").alias("root"), (F.coalesce("above", "root") != F.col("root")).alias("moved"))
        nxt = written(nxt, "roots")
        now = nxt.select("report", "root")
        if nxt.where("moved").isEmpty():
            return now
    raise RuntimeError(f"roots did not settle in {most_rounds} rounds")
