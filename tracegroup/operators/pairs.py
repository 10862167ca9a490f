"""Training pairs, batches and triplets, drawn by arithmetic hashes so that every draw can be repeated anywhere.

A category's pairs are never enumerated beyond the cap: pairs are numbered, and numbers are drawn.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

PRIME = 1_000_003


def ordinals(traces: DataFrame) -> DataFrame:
    """(category_id, cat, fp, i, n): distinct traces of each category numbered from 0, and categories numbered from 0.

    Numbers within a category need its traces in order; a category is split over the tasks by ranges of fp
    when counted, so only counts per range meet.
    """
    rows = traces.select("category_id", "fp").distinct().withColumn("range", F.substring("fp", 1, 2))
    counts = rows.groupBy("category_id", "range").agg(F.count("*").alias("k"))
    before = counts.withColumn("before", F.coalesce(F.sum("k").over(Window.partitionBy("category_id").orderBy("range").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))).withColumn("n", F.sum("k").over(Window.partitionBy("category_id")))
    rank = F.row_number().over(Window.partitionBy("category_id", "range").orderBy("fp")) - 1
    numbered = rows.withColumn("rank", rank).join(before, ["category_id", "range"]).select("category_id", "fp", (F.col("rank") + F.col("before")).cast("long").alias("i"), "n")
    names = traces.select("category_id").distinct().withColumn("block", F.substring(F.md5(F.col("category_id").cast("binary")), 1, 2))
    sizes = names.groupBy("block").agg(F.count("*").alias("k")).withColumn("first", F.coalesce(F.sum("k").over(Window.orderBy("block").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)))
    cat = names.withColumn("r", F.row_number().over(Window.partitionBy("block").orderBy("category_id")) - 1).join(sizes, "block").select("category_id", (F.col("r") + F.col("first")).cast("long").alias("cat"))
    return numbered.join(cat, "category_id")


def default_cap(reports: DataFrame) -> int:
    """Half the square of the mean number of distinct traces per category, 200 at most."""
    mean = reports.groupBy("category_id").agg(F.count_distinct("fp").alias("u")).agg(F.avg("u")).first()[0] or 1.0
    return max(1, min(200, int(-(-mean * mean // 2))))


def pair_numbers(categories: DataFrame, cap: int, seed: int) -> DataFrame:
    """(category_id, n, p): all n(n-1)/2 pair numbers where they are at most `cap`, else `cap` distinct drawn ones."""
    c = categories.select("category_id", "cat", "n").distinct().withColumn("all", F.expr("n * (n - 1) div 2")).where("n > 1")
    few = c.where(F.col("all") <= cap).select("category_id", "n", F.explode(F.expr("sequence(0L, `all` - 1L)")).alias("p"))
    # a step that shares no divisor with the number of pairs visits distinct numbers
    stride = lambda: F.expr(f"pmod(cat * 7919 + {seed} * 104729, {PRIME}) + 1")
    many = c.where(F.col("all") > cap).withColumn("s", F.filter(F.transform(F.sequence(F.lit(0), F.lit(60)), lambda d: stride() + d), lambda s: _coprime(s, F.col("all")))[0])
    drawn = many.withColumn("t", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(cap - 1).cast("long")))).select("category_id", "n", F.expr("pmod(s + t * pmod(s, `all`), `all`)").alias("p"))
    return few.unionByName(drawn)


def _coprime(a: Column, b: Column) -> Column:
    """Whether two numbers share no divisor: Euclid's steps, enough of them for 64 bits."""
    step = F.aggregate(F.sequence(F.lit(0), F.lit(90)), F.struct(a.cast("long").alias("x"), b.cast("long").alias("y")), lambda acc, _: F.when(acc["y"] == 0, acc).otherwise(F.struct(acc["y"].alias("x"), F.try_mod(acc["x"], acc["y"]).alias("y"))))
    return step["x"] == 1


def unranked(p: Column) -> tuple[Column, Column]:
    """The pair (i, j), j < i, of number p = i(i-1)/2 + j; the root is set right by one where it was rounded."""
    guess = F.floor((1 + F.sqrt(1 + 8 * p.cast("double"))) / 2).cast("long")
    i = F.when(guess * (guess - 1) / 2 > p, guess - 1).when(guess * (guess + 1) / 2 <= p, guess + 1).otherwise(guess)
    return i, (p - i * (i - 1) / 2).cast("long")


def positive_pairs(reports: DataFrame, cap: int, seed: int = 1) -> DataFrame:
    """(category_id, anchor_fp, positive_fp, p): pairs of distinct traces of a category, at most `cap` each; an arithmetic bit says which is the anchor."""
    known = ordinals(reports)
    i, j = unranked(F.col("p"))
    drawn = pair_numbers(known, cap, seed).select("category_id", "p", i.alias("i"), j.alias("j"))
    side = known.select("category_id", "i", "fp")
    a = side.toDF("category_id", "i", "a")
    b = side.toDF("category_id", "j", "b")
    both = drawn.join(a, ["category_id", "i"]).join(b, ["category_id", "j"])
    flip = F.pmod(F.col("p") * 7919 + F.lit(seed * 31), F.lit(2)) == 1
    return both.select("category_id", F.when(flip, F.col("b")).otherwise(F.col("a")).alias("anchor_fp"), F.when(flip, F.col("a")).otherwise(F.col("b")).alias("positive_fp"), "p")


def batches(pairs: DataFrame, size: int, seed: int = 1) -> DataFrame:
    """pairs with batch and slot, in an order of hashes. Each batch is the other's negatives; the last may be smaller.

    Ranks come from counts per hash range, so no task sorts all pairs.
    """
    h = F.md5(F.concat_ws("|", F.lit(str(seed)), "anchor_fp", "positive_fp", "category_id").cast("binary"))
    rows = pairs.withColumn("h", h).withColumn("range", F.substring("h", 1, 2))
    first = rows.groupBy("range").agg(F.count("*").alias("k")).select("range", F.coalesce(F.sum("k").over(Window.orderBy("range").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("first"))
    rank = F.row_number().over(Window.partitionBy("range").orderBy("h")) - 1
    at = rows.withColumn("rank", rank).join(first, "range").withColumn("at", F.col("rank") + F.col("first"))
    return at.select(*pairs.columns, F.floor(F.col("at") / size).cast("long").alias("batch"), F.pmod("at", F.lit(size)).cast("int").alias("slot"))


def triplets(pairs: DataFrame, reports: DataFrame, seed: int = 1) -> DataFrame:
    """pairs with a negative: a category drawn evenly among the others, then a trace of it; one that equals the anchor is left out."""
    known = ordinals(reports)
    cats = known.select("category_id", "cat", "n").distinct()
    count = cats.agg(F.count("*").alias("n_cats"))
    p = pairs.join(cats.select("category_id", "cat"), "category_id").join(F.broadcast(count), F.lit(True)).where("n_cats > 1")
    d = F.expr(f"pmod(cat * 7919 + p * 104729 + {seed} * 1299709, n_cats - 1)")
    p = p.withColumn("d", d).withColumn("neg_cat", F.col("d") + (F.col("d") >= F.col("cat")).cast("long"))
    other = cats.select(F.col("cat").alias("neg_cat"), F.col("category_id").alias("negative_category"), F.col("n").alias("neg_n"))
    p = p.join(other, "neg_cat").withColumn("neg_i", F.expr(f"pmod(cat * 15485863 + p * 7919 + {seed} * 31, neg_n)"))
    trace = known.select(F.col("category_id").alias("negative_category"), F.col("i").alias("neg_i"), F.col("fp").alias("negative_fp"))
    return p.join(trace, ["negative_category", "neg_i"]).where("negative_fp != anchor_fp").select(*pairs.columns, "negative_fp", "negative_category")
