"""Reports made from the given tables: (report_id, arrival, frames, category_id, meta), then numbered, split and fingerprinted."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from tracegroup.functions.frames import fingerprint
from tracegroup.operators.chronology import numbered, split
from tracegroup.operators.components import components
from tracegroup.sources.storage import load, written_in_turn

#: Orders are put together from their lines in up to PORTIONS portions, fewer where these would have under PORTION_ORDERS orders.
PORTIONS, PORTION_ORDERS = 4, 500_000
Portion = tuple[int, int]
WHOLE: Portion = (0, 1)
#: Lines whose orders are put together at a time, or those of one order if these are more.
GATHERED_LINES = 100_000


def in_order(rows: DataFrame, key: str, position: Column, value: Column, name: str) -> DataFrame:
    """(key, name): the values of a key as an array, by position."""
    return rows.groupBy(key).agg(F.transform(F.sort_array(F.collect_list(F.struct(position.alias("p"), value.alias("v")))), lambda x: x["v"]).alias(name))


def _in_portion(rows: DataFrame, key: str, portion: Portion) -> DataFrame:
    """The rows of a portion's orders: (which, of how many)."""
    return rows if portion == WHOLE else rows.where(F.pmod(F.xxhash64(F.col(key).cast("long")), F.lit(portion[1])) == portion[0])


def _order_portions(spark: SparkSession, sf_dir: str) -> list[Portion]:
    n = min(PORTIONS, max(1, load(spark, sf_dir, "orders").count() // PORTION_ORDERS))
    return [(r, n) for r in range(n)]


def _order_lines(spark: SparkSession, sf_dir: str, frame: Column, label: Column, portion: Portion = WHOLE) -> DataFrame:
    """Lines with the frame and the mark of their part.

    Frames are made before parts meet lines, and parts are not broadcast, however small their file: there may be many.
    """
    lines = _in_portion(load(spark, sf_dir, "lineitem"), "l_orderkey", portion).select("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey")
    parts = load(spark, sf_dir, "part").select("p_partkey", frame.alias("frame"), F.when(F.col("p_type") == "PROMO", label).alias("mark"))
    return lines.join(parts.hint("merge"), lines["l_partkey"] == parts["p_partkey"]).drop("p_partkey")


def orders_table(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(report_id, arrival, o_custkey, o_orderpriority) of each order."""
    return load(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("report_id"), F.unix_seconds(F.col("o_orderdate").cast("timestamp")).alias("arrival"), "o_custkey", "o_orderpriority")


def with_customers(orders: DataFrame, sf_dir: str) -> DataFrame:
    """orders with c_mktsegment, n_name and r_name of their customer, null where there is none. Customers are not broadcast either."""
    spark = orders.sparkSession
    customers = load(spark, sf_dir, "customer").select("c_custkey", "c_nationkey", "c_mktsegment")
    nations = load(spark, sf_dir, "nation").select("n_nationkey", "n_name", "n_regionkey")
    regions = load(spark, sf_dir, "region").select("r_regionkey", "r_name")
    return orders.join(customers.hint("merge"), orders["o_custkey"] == customers["c_custkey"], "left").join(nations, F.col("c_nationkey") == F.col("n_nationkey"), "left").join(regions, F.col("n_regionkey") == F.col("r_regionkey"), "left")


_GATHERED = "report_id long, arrival long, frames array<long>, category_id string"


def _reports_of(rows: pa.Table) -> pa.RecordBatch:
    """Reports of the orders of rows (report_id, arrival, line, frame, mark), those of an order together, it itself before its lines."""
    ids, line, mark = rows.column("report_id").to_numpy(), rows.column("line").to_numpy(), rows.column("mark").combine_chunks()
    fresh = np.append(True, ids[1:] != ids[:-1])
    group = np.cumsum(fresh) - 1
    n_lines = np.bincount(group[line], minlength=group[-1] + 1)
    last = np.append(np.flatnonzero(fresh)[1:], len(ids))
    marked = np.flatnonzero(mark.is_valid().to_numpy(zero_copy_only=False) & line)
    opens = np.flatnonzero(np.append(True, group[marked][1:] != group[marked][:-1])[: len(marked)])
    second = np.append(opens[1:], len(marked)) - opens > 1
    then = marked[np.minimum(opens + 1, len(marked) - 1)]
    names = pc.binary_join_element_wise(mark.take(pa.array(marked[opens])), mark.take(pa.array(then, mask=~second)), ">", null_handling="skip")
    named = np.full(len(last), -1)
    named[group[marked[opens]]] = np.where(pc.not_equal(names, "").to_numpy(zero_copy_only=False), np.arange(len(opens)), -1)
    orders = np.flatnonzero(~line)
    orders = orders[named[group[orders]] >= 0]
    n = n_lines[group[orders]]
    upto = np.cumsum(n)
    at = np.repeat((last - n_lines)[group[orders]] - (upto - n), n) + np.arange(n.sum())
    frames = pa.ListArray.from_arrays(pa.array(np.append(0, upto), pa.int32()), rows.column("frame").combine_chunks().take(pa.array(at)))
    return pa.RecordBatch.from_arrays([pa.array(ids[orders]), rows.column("arrival").combine_chunks().take(pa.array(orders)), frames, names.take(pa.array(named[group[orders]])).cast(pa.string())], ["report_id", "arrival", "frames", "category_id"])


def _gathered(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    held, n = [], 0
    for batch in batches:
        if batch.num_rows:
            held.append(batch)
            n += batch.num_rows
            if n >= GATHERED_LINES:
                rows = pa.Table.from_batches(held)
                ids = rows.column("report_id").to_numpy()
                cut = int(np.searchsorted(ids, ids[-1], "left"))  # the last order may go on
                if cut:
                    yield _reports_of(rows.slice(0, cut))
                held, n = rows.slice(cut).combine_chunks().to_batches(), 0
    if held:
        yield _reports_of(pa.Table.from_batches(held))


def _keyed_orders(spark: SparkSession, sf_dir: str, frame: Column, label: Column, portion: Portion) -> DataFrame:
    """Reports of orders with frames as hashes whose last bit says whether the name has the type PROMO (`decides`).

    Orders and their lines are dealt out and sorted together, and tasks cut the rows into reports: that takes less than gathering arrays.
    """
    name = F.xxhash64(frame).bitwiseAND(F.lit(-2)).bitwiseOR(F.contains(frame, F.lit(".PROMO.")).cast("long"))
    lines = _order_lines(spark, sf_dir, name, label, portion).select(F.col("l_orderkey").cast("long").alias("report_id"), F.lit(None).cast("long").alias("arrival"), F.lit(True).alias("line"), "l_linenumber", "l_partkey", "l_suppkey", "frame", "mark")
    none = [F.lit(None).cast(lines.schema[c].dataType).alias(c) for c in lines.columns[3:]]
    orders = _in_portion(orders_table(spark, sf_dir), "report_id", portion).select(F.col("report_id").cast("long").alias("report_id"), "arrival", F.lit(False).alias("line"), *none)
    dealt = lines.unionByName(orders).where("report_id is not null").repartition("report_id")
    rows = dealt.sortWithinPartitions("report_id", "line", "l_linenumber", "l_partkey", "l_suppkey", "frame", "mark")
    found = rows.select("report_id", "arrival", "line", "frame", "mark").mapInArrow(_gathered, _GATHERED)
    return found.withColumn("meta", F.lit(None).cast("map<string,string>"))


def decides(key: Column) -> Column:
    """Whether the name of a keyed order's frame has the type PROMO."""
    return key.bitwiseAND(F.lit(1)) == 1


def _orders(spark: SparkSession, sf_dir: str, label: Column, keyed: bool = False, portion: Portion = WHOLE) -> DataFrame:
    """Reports of orders, or of a portion of them; with `keyed`, frames are hashed before they are gathered and no meta is looked up."""
    frame = F.concat_ws(".", "p_brand", "p_type", "p_name")
    if keyed:
        return _keyed_orders(spark, sf_dir, frame, label, portion)
    place = F.struct("l_linenumber", "l_partkey", "l_suppkey")
    # lines are dealt out by order as flat rows; gathered before that, most arrays would hold one line and only be larger
    rows = _order_lines(spark, sf_dir, frame, label, portion).repartition("l_orderkey")
    found = in_order(rows, "l_orderkey", place, F.struct("frame", "mark"), "lines")
    marks = F.filter(F.transform("lines", lambda x: x["mark"]), lambda m: m.isNotNull())
    found = found.select(F.col("l_orderkey").alias("report_id"), F.transform("lines", lambda x: x["frame"]).alias("frames"), F.array_join(F.slice(marks, 1, 2), ">").alias("category_id")).where("category_id != ''")
    orders = _in_portion(orders_table(spark, sf_dir), "report_id", portion)
    meta = F.create_map(F.lit("priority"), "o_orderpriority", F.lit("segment"), "c_mktsegment", F.lit("nation"), "n_name", F.lit("region"), "r_name")
    return found.join(with_customers(orders, sf_dir).select("report_id", "arrival", meta.alias("meta")), "report_id").select("report_id", "arrival", "frames", "category_id", "meta")


def _second_word() -> Column:
    return F.split("p_name", " ")[1]


def orders_longtail(spark: SparkSession, sf_dir: str, keyed: bool = False, portion: Portion = WHOLE) -> DataFrame:
    return _orders(spark, sf_dir, F.concat("p_brand", F.lit(" "), _second_word()), keyed, portion)


def orders_dense(spark: SparkSession, sf_dir: str, keyed: bool = False, portion: Portion = WHOLE) -> DataFrame:
    return _orders(spark, sf_dir, _second_word(), keyed, portion)


def sentences(text: Column) -> Column:
    return F.filter(F.transform(F.split(F.coalesce(text, F.lit("")), r"[.\n]+"), lambda x: F.trim(x)), lambda x: x != "")


def planted_docs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Variants of the documents with 5 to 100 sentences, as the fixtures define them."""
    return _variants(spark, sf_dir, "size(s) between 5 and 100")


def whole_docs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Variants of every document that has a sentence, however many."""
    return _variants(spark, sf_dir, "size(s) > 0")


def _variants(spark: SparkSession, sf_dir: str, which: str) -> DataFrame:
    docs = load(spark, sf_dir, "documents").select("doc_id", sentences(F.col("text")).alias("s")).where(which)
    copies = docs.select("doc_id", "s", F.explode(F.sequence(F.lit(0).cast("long"), F.col("doc_id") % 5)).alias("k"))
    drop = lambda i: (F.col("doc_id") * 7919 + F.col("k") * 104729 + i.cast("long") * 1299709) % 1000003 % 5 == 0
    kept = F.when(F.col("k") == 0, F.col("s")).otherwise(F.filter("s", lambda x, i: ~drop(i + 1)))
    arrival = (F.col("doc_id") * 7919 + F.col("k") * 104729) % 1000003
    return copies.select((F.col("doc_id") * 10 + F.col("k")).alias("report_id"), arrival.alias("arrival"), kept.alias("frames"), F.col("doc_id").cast("string").alias("category_id"), F.create_map(F.lit("variant"), F.col("k").cast("string")).alias("meta"))


def doc_copies(spark: SparkSession, sf_dir: str, keyed: bool = False) -> DataFrame:
    """Categories are components of documents whose distinct sentences have Jaccard 0.5 or more.

    Equal sets are one node; two others can only reach 0.5 if they share one of their n // 2 + 1 rarest sentences. Sentences are
    told apart by 64-bit hashes (a collision among n has odds of n²/2^65), so that sets and pairs of sets move no text.
    With `keyed`, frames are the hashes too.
    """
    hashed = lambda c: F.transform(c, lambda x: F.xxhash64(x))
    docs = load(spark, sf_dir, "documents").select(F.col("doc_id").alias("report_id"), F.col("doc_id").alias("arrival"), sentences(F.col("text")).alias("frames"))
    sets = docs.select("report_id", F.array_sort(F.array_distinct(hashed("frames"))).alias("d")).where("size(d) > 0")
    if keyed:
        docs = docs.withColumn("frames", hashed("frames"))
    heads = sets.groupBy("d").agg(F.min("report_id").alias("head"))
    equal = sets.join(heads, "d").where("head < report_id").select(F.col("head").alias("a"), F.col("report_id").alias("b"))
    postings = heads.select("head", F.explode("d").alias("frame"))
    df = postings.groupBy("frame").agg(F.count("*").alias("df"))
    ordered = postings.join(df, "frame").groupBy("head").agg(F.sort_array(F.collect_list(F.struct("df", "frame"))).alias("o"))
    rare = ordered.select("head", F.explode(F.slice("o", F.lit(1), F.floor(F.size("o") / 2).cast("int") + 1)).alias("x")).select("head", F.col("x.frame").alias("frame"))
    ids = rare.select("frame", F.col("head").alias("a")).join(rare.select("frame", F.col("head").alias("b")), "frame").where("a < b").select("a", "b").distinct()
    left, right = heads.toDF("da", "a"), heads.toDF("db", "b")
    both = ids.join(left, "a").join(right, "b").withColumn("i", F.size(F.array_intersect("da", "db")))
    edges = both.where("2 * i >= size(da) + size(db) - i").select("a", "b").unionByName(equal)
    named = components(edges, "doc-copies")
    return docs.join(named, docs["report_id"] == named["node"], "left").select("report_id", "arrival", "frames", F.coalesce("component", "report_id").cast("string").alias("category_id"), F.map_from_arrays(F.array().cast("array<string>"), F.array().cast("array<string>")).alias("meta"))


def conversation_stacks(spark: SparkSession, sf_dir: str) -> DataFrame:
    said = load(spark, sf_dir, "conversations").select("conv_id", "turn", F.concat_ws(".", "role", "text").alias("frame"))
    upto = Window.partitionBy("conv_id").orderBy("turn").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    stacked = said.select("conv_id", "turn", F.reverse(F.transform(F.sort_array(F.collect_list(F.struct("turn", "frame")).over(upto)), lambda x: x["frame"])).alias("frames"))
    return stacked.select((F.col("conv_id") * 1000 + F.col("turn")).alias("report_id"), ((F.col("conv_id") + 3 * F.col("turn")) * 1000000 + F.col("conv_id")).alias("arrival"), "frames", F.col("conv_id").cast("string").alias("category_id"), F.create_map(F.lit("turn"), F.col("turn").cast("string")).alias("meta"))


def event_errors(spark: SparkSession, sf_dir: str) -> DataFrame:
    k = F.from_json("props", "k int")["k"]
    events = load(spark, sf_dir, "events").select("event_id", F.unix_micros(F.col("ts").cast("timestamp")).alias("arrival"), "user_id", "event_type", F.concat("event_type", F.lit(".k"), (k % 10).cast("string")).alias("frame"))
    past = Window.partitionBy("user_id").orderBy("arrival", "event_id").rowsBetween(-8, 0)
    held = events.select("event_id", "arrival", "user_id", "event_type", F.reverse(F.collect_list(F.struct("frame", "event_type")).over(past)).alias("last")).where("event_type = 'error'")
    others = F.filter(F.transform(F.slice("last", 2, 8), lambda x: x["event_type"]), lambda t: t != "error")
    return held.select(F.col("event_id").alias("report_id"), "arrival", F.transform("last", lambda x: x["frame"]).alias("frames"), F.array_join(F.slice(others, 1, 2), ">").alias("category_id"), F.create_map(F.lit("user"), F.col("user_id").cast("string")).alias("meta"))


def _pages(spark: SparkSession, sf_dir: str, pattern: str) -> DataFrame:
    pages = load(spark, sf_dir, "pages")
    tags = F.transform(F.regexp_extract_all(F.coalesce("html", F.lit("")), F.lit(pattern), 0), lambda x: F.trim(F.substring(x, 2, 1000000)))
    host = F.regexp_extract(F.coalesce("url", F.lit("")), "://([^/?#]*)", 1)
    return pages.select(F.col("page_id").alias("report_id"), F.col("page_id").alias("arrival"), tags.alias("frames"), host.alias("category_id"), F.create_map(F.lit("url"), "url").alias("meta"))


def page_dom(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _pages(spark, sf_dir, r"<[a-z][a-z0-9]*[^>]*>[^<]{0,24}")


def page_tags(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _pages(spark, sf_dir, r"<[a-z][a-z0-9]*")


def label_groups(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, labels = load(spark, sf_dir, "documents"), load(spark, sf_dir, "labels")
    return docs.join(labels, "doc_id").select(F.col("doc_id").alias("report_id"), F.col("doc_id").alias("arrival"), sentences(F.col("text")).alias("frames"), F.concat_ws(",", F.col("quality").cast("string"), F.col("toxic").cast("string")).alias("category_id"), F.create_map(F.lit("lang"), "lang").alias("meta"))


def benchmark_probe(spark: SparkSession, sf_dir: str, n: int = 8) -> DataFrame:
    """(item_id, doc_id): documents that contain a benchmark passage.

    Passages and documents meet at a run of n words from inside the passage, which stands whole in any
    document that has it; containment is then looked up. Passages too short for that are few words long
    and are held against the documents that have their inner word.
    """
    words = lambda c: F.split(c, " ")
    items = load(spark, sf_dir, "benchmark").select("item_id", F.col("text").alias("passage")).where("passage is not null").withColumn("w", words(F.col("passage")))
    inside = F.slice("w", 2, F.greatest(F.least(F.size("w") - 2, F.lit(n)), F.lit(1)))
    keyed = items.where("size(w) >= 3").select("item_id", "passage", F.size(inside).alias("m"), F.xxhash64(inside).alias("key"))
    docs = load(spark, sf_dir, "documents").select("doc_id", "text").withColumn("w", words(F.coalesce("text", F.lit(""))))
    used = keyed.select("m").distinct()
    runs = docs.join(F.broadcast(used), F.lit(True)).where("size(w) >= m").select("doc_id", F.explode(F.array_distinct(F.transform(F.expr("sequence(1, size(w) - m + 1)"), lambda i: F.xxhash64(F.slice("w", i, F.col("m")))))).alias("key"))
    met = runs.join(keyed, "key").select("doc_id", "item_id", "passage").distinct()
    short = items.where("size(w) < 3")
    found = met.join(docs.select("doc_id", "text"), "doc_id").where("contains(text, passage)").select("item_id", "doc_id")
    if short.isEmpty():
        return found
    return found.unionByName(docs.join(F.broadcast(short), F.expr("contains(text, passage)")).select("item_id", "doc_id"))


WORKLOADS = {
    "orders_longtail": orders_longtail,
    "orders_dense": orders_dense,
    "planted_docs": planted_docs,
    "whole_docs": whole_docs,
    "doc_copies": doc_copies,
    "conversation_stacks": conversation_stacks,
    "event_errors": event_errors,
    "page_dom": page_dom,
    "page_tags": page_tags,
    "label_groups": label_groups,
}


def reports(spark: SparkSession, sf_dir: str, name: str, columns: tuple[str, ...] = ()) -> DataFrame:
    """A workload with arrival_seq, fp and part; of the others only `columns`, if given."""
    found = WORKLOADS[name](spark, sf_dir).withColumn("fp", fingerprint(F.col("frames")))
    return split(numbered(found.select("report_id", "arrival", "fp", *columns) if columns else found))


def keyed(spark: SparkSession, sf_dir: str, name: str) -> tuple[DataFrame, DataFrame]:
    """(reports, frames): a workload as `reports` gives it, but for its frames, and beside it (report_id, arrival, fp, frames).

    Frames are 64-bit hashes of their names (63 bits and a mark for orders) and fp is 128 bits of them in order. They are written where they are read and not
    dealt out with the numbering, so that neither names nor frames are shuffled for it. Orders come portion by portion, each a
    scan of the lines, as lines are shuffled twice, by part and by order, and what is on disk at a time is a portion of that.
    """
    if name in ("orders_longtail", "orders_dense"):
        found = [WORKLOADS[name](spark, sf_dir, keyed=True, portion=p) for p in _order_portions(spark, sf_dir)]
    elif name == "doc_copies":
        found = [doc_copies(spark, sf_dir, keyed=True)]
    else:
        found = [WORKLOADS[name](spark, sf_dir).withColumn("frames", F.transform("frames", lambda x: F.when(x.isNotNull(), F.xxhash64(x))))]
    fp = F.unhex(F.md5(F.concat_ws(",", F.col("frames").cast("array<string>"))))
    found = written_in_turn([f.withColumn("fp", fp).select("report_id", "arrival", "fp", "frames", "category_id") for f in found], "keyed")
    return split(numbered(found.drop("frames"))), found.drop("category_id")
