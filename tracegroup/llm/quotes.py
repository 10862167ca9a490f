"""Chat formatting by quotation linking, in DataFrame functions only.

Quoted lines are told by their `>` marks. Neighbouring lines of one level are a passage; passages and
single lines are hashed after normalisation and joined to the message of the same conversation that first said them, as
a paragraph or a line, so a quotation links also if it was wrapped anew. Messages come back without quotes, with the
message that they answer, and threads() orders them so that an answer follows what it answers.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from tracegroup.llm.common import mask_of, masked
from tracegroup.operators.components import resolve_roots

_MARK = r"^\s*>"
_QUOTING = r"(?m)^\s*>"
_MARKS = r"^\s*((?:>\s?)+)"
#: A line that introduces a quotation, such as "On Monday, someone wrote:".
_INTRO = r"(?i)^\s*(on .*|.* )?wrote:\s*$"


_COUNTS = {"quotedFalse": "n_quoted", "linkedFalse": "n_linked", "quotedTrue": "n_passages", "linkedTrue": "n_passages_linked"}


def quote_level(line: Column) -> Column:
    """Number of leading `>` marks; white space between them is allowed."""
    return F.length(F.regexp_replace(F.regexp_extract(line, _MARKS, 1), r"[^>]", ""))


def normalised(line: Column) -> Column:
    """Without marks, lower case, white space runs as one space, no space at the ends."""
    return F.trim(F.regexp_replace(F.lower(F.regexp_replace(line, _MARKS, "")), r"\s+", " "))


def unquoted(lines: Column) -> Column:
    """The text of the lines that are neither quoted nor introduce a quotation, without empty lines at its ends."""
    following = F.concat(F.slice(lines, 2, F.greatest(F.size(lines) - 1, F.lit(0))), F.array(F.lit("")))
    pairs = F.arrays_zip(lines.alias("line"), following.alias("next"))
    kept = F.filter(pairs, lambda p: ~p["line"].rlike(_MARK) & ~(p["line"].rlike(_INTRO) & p["next"].rlike(_MARK)))
    return F.regexp_replace(F.array_join(F.transform(kept, lambda p: p["line"]), "\n"), r"^\s+|\s+$", "")


def passages(text: Column) -> Column:
    """Longest runs of lines of one level that are not empty, as (level, said), said being their normalised lines with spaces between.

    Each line carries its level at both ends; where the levels on both sides of a line feed agree, one replacement joins the lines.
    """
    lines = F.split(F.translate(text, "\x01\x02\x03", "   "), "\n")

    def marked(line: Column) -> Column:
        said, level = normalised(line), quote_level(line).cast("string")
        return F.when(said == "", F.lit("")).otherwise(F.concat(F.lit("\x01"), level, F.lit("\x02"), said, F.lit("\x03"), level))

    joined = F.regexp_replace(F.array_join(F.transform(lines, marked), "\n"), "\x03(\\d+)\n\x01\\1\x02", " ")
    runs = F.filter(F.split(joined, "\n"), lambda x: x != "")
    return F.transform(runs, lambda x: F.struct(F.regexp_extract(x, "^\x01(\\d+)\x02", 1).cast("int").alias("level"), F.regexp_replace(x, "^\x01\\d+\x02|\x03\\d+$", "").alias("said")))


def linked_messages(messages: DataFrame, conv: str = "conv_id", turn: str = "turn", role: str = "role", text: str = "text") -> DataFrame:
    """Per row of messages: conv_id, turn, role, body, reply_to, n_quoted, n_linked, deepest, rendered, n_passages, n_passages_linked.

    body: the text without quoted lines. reply_to: the latest earlier turn that one of the message's
    least-nested quoted lines or passages was first said in; null if none links, when the message simply follows
    the turn before it. n_quoted counts quoted lines that are not empty, n_linked those that link,
    deepest is the deepest level; n_passages and n_passages_linked count quoted passages. A passage links to an equal
    paragraph or line. Quotations link within a conversation only. rendered is the message in chat
    form. As an answer's turn is above its original's, (conv_id, turn) is a reply order.

    Null text counts as empty, a null role as ''; rows of null conversation or turn stay but do not link.
    Repeated rows stay, each with the same values. Of equal lines in several messages the first is the
    original. No conversation is gathered: originals are a minimum per line, links a maximum per message.
    """
    m = messages.select(F.col(f"`{conv}`").alias("conv_id"), F.col(f"`{turn}`").alias("turn"), F.coalesce(F.col(f"`{role}`"), F.lit("")).alias("role"), F.coalesce(F.col(f"`{text}`"), F.lit("")).alias("text"))
    named = m.where("conv_id is not null and turn is not null").select("conv_id", "turn", "text", F.xxhash64("text").alias("tk"))
    # where nobody quotes, nothing links: only conversations that may hold a quotation are taken apart
    quoting = named.where(F.col("text").rlike(_QUOTING)).select("conv_id")
    named = masked(named, F.xxhash64("conv_id"), mask_of(quoting, F.xxhash64("conv_id")))[0]
    lines = named.select("conv_id", "turn", "tk", F.explode(F.split("text", "\n")).alias("line"))
    lines = lines.select("conv_id", "turn", "tk", F.lit(False).alias("whole"), quote_level(F.col("line")).alias("level"), normalised(F.col("line")).alias("said")).where("said != ''")
    runs = named.select("conv_id", "turn", "tk", F.explode(passages(F.col("text"))).alias("p")).select("conv_id", "turn", "tk", F.lit(True).alias("whole"), "p.level", "p.said")
    hashed = lines.unionByName(runs).select("conv_id", "turn", "tk", "whole", "level", F.sha2("said", 256).alias("h"))
    first = hashed.where("level = 0").groupBy("conv_id", "h").agg(F.min("turn").alias("origin"))
    quoted = hashed.where("level > 0").groupBy("conv_id", "turn", "tk", "whole", "level", "h").agg(F.count("*").alias("n"))
    met = quoted.join(first, ["conv_id", "h"], "left").withColumn("origin", F.when(F.col("origin") < F.col("turn"), F.col("origin")))
    # counts are per distinct message, so repeated rows are divided out below
    per = met.groupBy("conv_id", "turn", "tk").agg(
        F.min(F.when(F.col("origin").isNotNull(), F.struct("level", (-F.col("origin")).alias("o")))).alias("best"),
        *[F.sum(F.when(F.col("whole") == w, F.col("n")).otherwise(0)).alias(f"quoted{w}") for w in (False, True)],
        *[F.sum(F.when(F.col("origin").isNotNull() & (F.col("whole") == w), F.col("n")).otherwise(0)).alias(f"linked{w}") for w in (False, True)],
        F.max("level").alias("deepest"),
    )
    rows = m.withColumn("tk", F.xxhash64("text"))
    times = rows.where(F.col("text").rlike(_QUOTING)).groupBy("conv_id", "turn", "tk").agg(F.count("*").alias("times"))
    per = per.join(times, ["conv_id", "turn", "tk"]).select("conv_id", "turn", "tk", (-F.col("best.o")).alias("reply_to"), "deepest", *[F.floor(F.col(c) / F.col("times")).alias(n) for c, n in _COUNTS.items()])
    body = unquoted(F.split("text", "\n"))
    out = rows.join(per, ["conv_id", "turn", "tk"], "left").withColumn("body", body)
    return out.select(
        "conv_id",
        "turn",
        "role",
        "body",
        F.col("reply_to").cast("long").alias("reply_to"),
        F.coalesce("n_quoted", F.lit(0)).cast("long").alias("n_quoted"),
        F.coalesce("n_linked", F.lit(0)).cast("long").alias("n_linked"),
        F.coalesce("deepest", F.lit(0)).cast("int").alias("deepest"),
        F.concat(F.lit("<|"), "role", F.lit("|>\n"), "body", F.lit("\n")).alias("rendered"),
        F.coalesce("n_passages", F.lit(0)).cast("long").alias("n_passages"),
        F.coalesce("n_passages_linked", F.lit(0)).cast("long").alias("n_passages_linked"),
    )


def threads(linked: DataFrame) -> DataFrame:
    """linked with `thread`, the turn that the chain of answers begins with, and its own turn for a message that answers none.

    (conv_id, thread, turn) is an order in which each thread stands together and an answer follows its original. Chains are
    followed by pointer doubling over the (conv_id, turn) of answers, so no conversation is gathered; a turn that is no answer ends
    a chain. Rows of null conversation or turn have no thread.
    """
    key = lambda turn: F.struct("conv_id", F.col(turn).alias("turn"))
    known = linked.where("conv_id is not null and turn is not null and reply_to is not null").groupBy("conv_id", "turn").agg(F.max("reply_to").alias("reply_to"))
    roots = resolve_roots(known.select(key("turn").alias("report"), key("reply_to").alias("parent")))
    named = roots.select(F.col("report.conv_id").alias("c"), F.col("report.turn").alias("t"), F.col("root.turn").alias("root"))
    own = F.when(F.col("conv_id").isNotNull(), F.coalesce("root", "turn"))
    return linked.join(named, (linked["conv_id"] == named["c"]) & (linked["turn"] == named["t"]), "left").withColumn("thread", own).drop("c", "t", "root")


def in_order(linked: DataFrame) -> DataFrame:
    """linked in the order of its conversations and, after threads(), of their threads, spread by range."""
    order = [c for c in ("conv_id", "thread", "turn") if c in linked.columns]
    return linked.repartitionByRange(*order).sortWithinPartitions(*order)


def write_conversations(linked: DataFrame, path: str) -> None:
    """Write rendered messages so that a conversation's turns (or, after threads(), its threads) stand together and in order, spread by range."""
    in_order(linked).write.mode("overwrite").parquet(path)
