"""Mixing sources to target weights: budgets down a domain-language-source tree, then a token prefix of seeded epochs per leaf.

All of it is windows over one row per child and sums over one row per document; no group of documents is gathered.
"""

from __future__ import annotations

from collections.abc import Mapping
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from tracegroup.llm.common import mask_of, masked, written

LEVELS = ("domain", "lang", "source")


@dataclass(frozen=True)
class MixConfig:
    """weights: per level, whole numbers by name (others weigh 1; 0 leaves a branch out).

    target: tokens wanted, as a share of all tokens (`share_of_all` in thousandths) or as a number (`tokens`).
    most_epochs bounds how often a document may be used. seed orders each epoch.
    """

    weights: Mapping[str, Mapping[str, int]] = field(default_factory=dict)
    share_of_all: int = 1000
    tokens: int | None = None
    most_epochs: int = 2
    seed: int = 17
    #: Documents of a leaf are summed by the first `digits` hex digits of their place in the epoch.
    digits: int = 3


def weight_of(level: str, name: Column, weights: Mapping[str, Mapping[str, int]]) -> Column:
    out = F.lit(1).cast("long")
    for key, w in weights.get(level, {}).items():
        out = F.when(name == key, F.lit(w).cast("long")).otherwise(out)
    return out


def share(children: DataFrame, parent: list[str], child: str, weights: Mapping[str, Mapping[str, int]]) -> DataFrame:
    """Split each parent's `budget` over its children by weight, none above its `room`.

    Children are taken from the one that its share fills first; as long as a child's share of what is left
    would overfill it, it gets its room and the rest goes on to its siblings. Only what all siblings
    together cannot take is missing from the parent, and its parent has seen that, as rooms are summed up
    the tree before budgets go down. Whole numbers throughout; a child of weight 0 gets nothing.
    """
    c = children.withColumn("w", weight_of(child, F.col(child), weights)).withColumn("r", F.when(F.col("w") > 0, F.col("room")).otherwise(F.lit(0).cast("long")))
    fill = F.when(F.col("w") > 0, F.col("r") / F.col("w")).otherwise(F.lit(-1.0))
    order = Window.partitionBy(*parent).orderBy(fill, child)
    before = F.coalesce(F.sum("r").over(order.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    rest = F.sum("w").over(order.rowsBetween(Window.currentRow, Window.unboundedFollowing))
    c = c.withColumn("before", before).withColumn("rest", rest)
    full = (F.col("w") > 0) & (F.col("r").cast("decimal(38,0)") * F.col("rest") <= F.col("w").cast("decimal(38,0)") * (F.col("budget") - F.col("before")))
    c = c.withColumn("full", full)
    every = Window.partitionBy(*parent)
    taken = F.coalesce(F.sum(F.when(F.col("full"), F.col("r"))).over(every), F.lit(0))
    open_w = F.coalesce(F.sum(F.when(~F.col("full"), F.col("w"))).over(every), F.lit(0))
    c = c.withColumn("taken", taken).withColumn("open_w", open_w)
    part = F.floor(F.try_divide(F.col("w").cast("decimal(38,0)") * (F.col("budget") - F.col("taken")), F.col("open_w").cast("decimal(38,0)")))
    got = F.when(F.col("full"), F.col("r")).when(F.col("open_w") > 0, F.least(F.col("r"), F.greatest(part.cast("long"), F.lit(0).cast("long")))).otherwise(F.lit(0).cast("long"))
    return c.select(*parent, child, "room", got.cast("long").alias("got"))


def budgets(leaves: DataFrame, config: MixConfig) -> DataFrame:
    """(domain, lang, source, tokens, budget) from leaves (domain, lang, source, tokens)."""
    room = leaves.withColumn("room", F.col("tokens") * config.most_epochs)
    by_lang = room.groupBy("domain", "lang").agg(F.sum("room").alias("room"))
    by_domain = by_lang.groupBy("domain").agg(F.sum("room").alias("room"))
    if config.tokens is not None:
        wanted = leaves.agg(F.lit(config.tokens).cast("long").alias("budget"))
    else:
        wanted = leaves.agg(F.floor(F.coalesce(F.sum("tokens"), F.lit(0)) * config.share_of_all / 1000).cast("long").alias("budget"))
    # one row beside one row per domain
    top = by_domain.join(F.broadcast(wanted), F.lit(True))
    domains = share(top.withColumn("all", F.lit(0)), ["all"], "domain", config.weights).select("domain", F.col("got").alias("budget"))
    langs = share(by_lang.join(domains, "domain"), ["domain"], "lang", config.weights).select("domain", "lang", F.col("got").alias("budget"))
    out = share(room.join(langs, ["domain", "lang"]), ["domain", "lang"], "source", config.weights)
    return out.select(*LEVELS, F.col("got").alias("budget")).join(leaves, list(LEVELS))


def mix(docs: DataFrame, domain: Column, config: MixConfig = MixConfig(), id_col: str = "doc_id", text: str = "text") -> DataFrame:
    """Per row of docs: id, domain, lang, source, n_tokens (words), budget of its leaf, copies.

    copies: how often the mix has the row, 0 to most_epochs. Full epochs have all rows of a leaf; of the last,
    those come in, in the order of md5(seed, epoch, id), before which the epoch's tokens are below what is left.
    A null language or source is the name '' ; null texts have no tokens and come in with the row after which
    they stand. Rows of equal id stand together in the order and come in together.
    Extra columns are not read; empty tables give empty results.
    """
    words = F.regexp_count(F.coalesce(F.col(f"`{text}`"), F.lit("")), F.lit(r"[^\x20\x09-\x0D]+")).cast("long")
    light = docs.select(F.col(f"`{id_col}`").cast("long").alias("id"), F.coalesce(domain, F.lit("")).alias("domain"), F.coalesce(F.col("lang"), F.lit("")).alias("lang"), F.coalesce(F.col("source"), F.lit("")).alias("source"), words.alias("n_tokens"))
    light = written(light, "mix-rows")
    leaves = written(light.groupBy(*LEVELS).agg(F.sum("n_tokens").alias("tokens")), "mix-leaves")
    plan = budgets(leaves, config).withColumn("epochs", F.when(F.col("tokens") > 0, F.floor(F.col("budget") / F.col("tokens"))).otherwise(0).cast("long"))
    plan = written(plan.withColumn("left", F.col("budget") - F.col("epochs") * F.col("tokens")).drop("tokens"), "mix-plan")
    placed = light.join(plan, list(LEVELS)).withColumn("place", F.md5(F.concat_ws("|", F.lit(str(config.seed)), F.col("epochs").cast("string"), F.coalesce(F.col("id").cast("string"), F.lit("null"))).cast("binary")))
    placed = placed.withColumn("bucket", F.substring("place", 1, config.digits))
    order = Window.partitionBy(*LEVELS).orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)
    buckets = placed.groupBy(*LEVELS, "bucket").agg(F.sum("n_tokens").alias("t"), F.first("left").alias("left"))
    buckets = buckets.withColumn("before", F.coalesce(F.sum("t").over(order), F.lit(0)))
    # of each leaf, one bucket at most is cut; buckets before it come in whole
    edge = buckets.where("before < left and before + t >= left").select(*LEVELS, F.col("bucket").alias("edge"), F.col("before").alias("edge_before"))
    cut = written(edge, "mix-edges")
    told = placed.join(cut, list(LEVELS), "left")
    whole = told.where("edge is null or bucket != edge")
    inside = F.when(F.col("left") <= 0, False).when(F.col("edge").isNull(), True).otherwise(F.col("bucket") < F.col("edge"))
    names = ["id", *LEVELS, "n_tokens", "budget", "epochs"]
    rest = told.where("bucket = edge")
    ids = rest.groupBy(*LEVELS, "edge", "place").agg(F.sum("n_tokens").alias("t"))
    sums = ids.withColumn("at", F.coalesce(F.sum("t").over(Window.partitionBy(*LEVELS).orderBy("place").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)))
    near = rest.join(sums.select(*LEVELS, "place", "at"), [*LEVELS, "place"]).select(*names, (F.col("edge_before") + F.col("at") < F.col("left")).alias("more"))
    out = whole.select(*names, inside.alias("more")).unionByName(near)
    return out.select(F.col("id").alias(id_col), *LEVELS, "n_tokens", "budget", (F.col("epochs") + F.col("more").cast("long")).alias("copies"))


def mixed(docs: DataFrame, domain: Column, config: MixConfig) -> DataFrame:
    """docs without the rows that the mix leaves out, for most_epochs = 1. Columns as given; only rows that may be left out are shuffled.

    Rows of equal id come in together within a leaf, so a row is told by its id and its leaf, a null id too.
    """
    key = {"id": F.col("doc_id").cast("long"), "domain": F.coalesce(domain, F.lit("")), "lang": F.coalesce(F.col("lang"), F.lit("")), "source": F.coalesce(F.col("source"), F.lit(""))}
    out = mix(docs, domain, config).where("copies = 0").select(F.col("doc_id").alias("left out id"), *[F.col(c).alias(f"left out {c}") for c in LEVELS]).distinct()
    out = written(out, "mix-out")
    near, sure = masked(docs, F.xxhash64(*key.values()), mask_of(out, F.xxhash64(*[F.col(f"left out {c}") for c in key])))
    same = F.lit(True)
    for c, value in key.items():
        same = same & value.eqNullSafe(F.col(f"left out {c}"))
    return sure.unionByName(near.join(out, same, "left_anti"))
