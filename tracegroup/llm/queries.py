"""Queries over whole tables, one per operator, and their SQL where SQL can express them."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from tracegroup.llm import exact_dedup, licenses, media, mixing, ngram_join, packing, quality, quotes, suffix_dedup, urls
from tracegroup.llm.common import written

Query = Callable[[SparkSession, str], DataFrame]


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def held_out() -> Column:
    """Rows that labels are not learned from: crc32 of the id as text leaves 2 when divided by 4. A null id is not held out."""
    return F.coalesce(F.crc32(F.col("doc_id").cast("string").cast("binary")) % 4 == 2, F.lit(False))


def op1_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    groups = exact_dedup.exact_groups(table(spark, sf_dir, "documents"))
    return groups.select("doc_id", "keep_id", "group_size", "kept", "text_sha256")


def quality_weights(docs: DataFrame, labels: DataFrame, config: quality.QualityConfig = quality.QualityConfig()):
    return quality.train(docs.select("doc_id", "text"), labels.select("doc_id", "quality").where(~held_out()), config)


def op3_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    weights = quality_weights(docs, table(spark, sf_dir, "labels"))
    scored = quality.score(docs, weights).select("doc_id", held_out().alias("held_out"), "score")
    return scored.withColumn("predicted", (F.col("score") >= 0.7).cast("int"))


#: The rules of the query, as (host, path, verdict).
SITE_RULES = (("org", "/", "allow"), ("example.org", "/es/", "block"), ("example.org", "/en/1", "block"), ("com", "/fr/", "allow"), ("com", "/de/", "block"))


def op5_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    judged = urls.judge(table(spark, sf_dir, "pages"), [urls.site_rule(*r) for r in SITE_RULES])
    return judged.select("page_id", "host", "path", "rule", "verdict")


def op7_media(spark: SparkSession, sf_dir: str) -> DataFrame:
    return media.digests(media.with_media(table(spark, sf_dir, "documents")))


def op8_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(table(spark, sf_dir, "documents"))


def op2_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return suffix_dedup.without_repeats(table(spark, sf_dir, "documents"), rest=True)


def op4_licenses(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = licenses.scan(table(spark, sf_dir, "documents"))
    return found.select("doc_id", "licence", "dice", F.size("matches").cast("long").alias("n_matches"), F.transform("matches", lambda m: F.concat_ws(":", m["template"], m["low"].cast("string"), m["high"].cast("string"))).alias("matches"))


def op6_ngram_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ngram_join.similar_groups(table(spark, sf_dir, "documents")).select("doc_id", "n_shingles", "component_id")


def domain() -> Column:
    """The top level of the mix: a source's number, divided by four, names its domain."""
    return F.expr("element_at(array('web', 'books', 'code', 'news'), pmod(coalesce(try_cast(regexp_extract(source, '([0-9]+)$', 1) as int), 0), 4) + 1)")


#: Target weights of the query; names that are not listed weigh 1.
WEIGHTS = {"domain": {"web": 4, "books": 2}, "lang": {"en": 3, "de": 2}}


def op9_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix(table(spark, sf_dir, "documents"), domain(), mixing.MixConfig(WEIGHTS))


def op10_quotes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Messages without their quotations, thread by thread; they are written once, as threads and their order read them several times."""
    linked = written(quotes.linked_messages(table(spark, sf_dir, "conversations")).drop("n_passages", "n_passages_linked"), "linked")
    return quotes.in_order(quotes.threads(linked)).drop("thread")


def quoting_turns(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The given conversations (which quote nothing) with quotations put in: every turn quotes one or two turns before it, whole, in one line or wrapped anew, by its numbers."""
    m = table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", F.coalesce("text", F.lit("")).alias("text"))
    back = F.lit(1) + F.pmod(F.col("conv_id") + F.col("turn"), F.lit(2))
    said = m.select(F.col("conv_id").alias("c"), F.col("turn").alias("t"), F.col("text").alias("old"))
    met = m.withColumn("from", F.col("turn") - back).join(said, (F.col("conv_id") == F.col("c")) & (F.col("from") == F.col("t")), "left")
    kind = F.pmod(F.col("conv_id") * 7 + F.col("turn"), F.lit(3))
    one_line, wrapped = F.translate("old", "\n", " "), F.regexp_replace("old", " ", "\n> ")
    quoted = F.when(kind == 0, F.concat(F.lit("> "), F.regexp_replace("old", "\n", "\n> "))).when(kind == 1, F.concat(F.lit(">> "), one_line)).otherwise(F.concat(F.lit("> "), F.regexp_replace(wrapped, "\n([^>])", "\n> $1")))
    return met.select("conv_id", "turn", "role", F.when(F.col("old").isNull(), F.col("text")).otherwise(F.concat(F.lit("They wrote:\n"), quoted, F.lit("\n\n"), F.col("text"))).alias("text"))


def planted_quotes(spark: SparkSession, sf_dir: str) -> DataFrame:
    linked = quotes.linked_messages(quoting_turns(spark, sf_dir))
    return quotes.threads(linked).select("conv_id", "turn", "body", "reply_to", "n_quoted", "n_linked", "deepest", "n_passages", "n_passages_linked", "thread")


def queries() -> dict[str, Query]:
    ops = (op1_exact_dedup, op2_suffix_dedup, op3_quality, op4_licenses, op5_url_filter, op6_ngram_join, op7_media, op8_packing, op9_mixing, op10_quotes, planted_quotes)
    return {f.__name__: f for f in ops}


_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"

_EXACT = f"""
WITH n AS (SELECT doc_id, translate(coalesce(text, ''), '{_UPPER}', '{_LOWER}') AS t FROM documents),
     g AS (SELECT t, max(doc_id) AS keep_id, count(*) AS group_size FROM n GROUP BY t)
SELECT doc_id, keep_id, group_size, doc_id = keep_id AS kept, sha256(t) AS text_sha256 FROM n JOIN g USING (t)
"""

_RULES = ", ".join(f"('{h}', '{p}', '{v}')" for h, p, v in SITE_RULES)
_URLS = rf"""
WITH u AS (SELECT page_id, CASE WHEN instr(coalesce(url, ''), '://') > 0 THEN substr(url, instr(url, '://') + 3) ELSE '' END AS rest FROM pages),
     p AS (SELECT page_id, translate(regexp_extract(rest, '^([^/?#]*)', 1), '{_UPPER}', '{_LOWER}') AS host, regexp_extract(rest, '^[^/?#]*([^?#]*)', 1) AS path FROM u),
     r(rhost, rpath, verdict) AS (VALUES {_RULES}),
     fit AS (SELECT page_id, max_by(rhost || rpath, length(rhost || rpath)) AS rule, max_by(verdict, length(rhost || rpath)) AS verdict
             FROM p JOIN r ON (host = rhost OR ends_with(host, '.' || rhost)) AND starts_with(path, rpath) GROUP BY page_id)
SELECT p.page_id, host, path, rule,
       coalesce(fit.verdict, CASE WHEN contains('.' || host || path, '.spam-farm.') OR contains('.' || host || path, '.cheap-pills.') OR contains('.' || host || path, '.casino')
            OR contains('.' || host || path, '/wp-login') OR contains('.' || host || path, '/cgi-bin/') THEN 'block' ELSE 'allow' END) AS verdict
FROM p LEFT JOIN fit ON p.page_id = fit.page_id
"""



def _share(name: str, rows: str, parent: str, child: str) -> str:
    """The split of budgets over children, as the CTEs that end in `name`."""
    weights = " ".join(f"WHEN '{k}' THEN {w}" for k, w in WEIGHTS.get(child, {}).items())
    weight = f"CASE {child} {weights} ELSE 1 END" if weights else "1"
    keys = ", ".join(f"k.{c}" for c in ["all_", "domain", "lang", "source"][: 1 + ["domain", "lang", "source"].index(child) + 1][1:])
    return f"""
     {name}_1 AS (SELECT *, {weight} AS w FROM ({rows})),
     {name}_2 AS (SELECT *, coalesce(sum(room) OVER (PARTITION BY {parent} ORDER BY room / w, {child} ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS before_,
                         sum(w) OVER (PARTITION BY {parent} ORDER BY room / w, {child} ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS rest FROM {name}_1),
     {name}_3 AS (SELECT *, room::HUGEINT * rest <= w::HUGEINT * (budget - before_) AS full_ FROM {name}_2),
     {name}_4 AS (SELECT *, coalesce(sum(room) FILTER (full_) OVER (PARTITION BY {parent}), 0) AS taken, coalesce(sum(w) FILTER (NOT full_) OVER (PARTITION BY {parent}), 0) AS open_w FROM {name}_3),
     {name} AS (SELECT {keys}, CASE WHEN full_ THEN room WHEN open_w > 0 THEN least(room, greatest((w::HUGEINT * (budget - taken)) // open_w, 0)) ELSE 0 END AS budget FROM {name}_4 k)"""


_MIX = rf"""
WITH rows_ AS (SELECT doc_id, ['web', 'books', 'code', 'news'][coalesce(try_cast(regexp_extract(source, '([0-9]+)$', 1) AS INT), 0) % 4 + 1] AS domain, coalesce(lang, '') AS lang, coalesce(source, '') AS source,
                      len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+')) AS n_tokens FROM documents),
     leaves AS (SELECT domain, lang, source, sum(n_tokens)::BIGINT AS tokens FROM rows_ GROUP BY ALL),
     {_share("d", "SELECT 0 AS all_, domain, sum(tokens * 2) AS room, (SELECT sum(tokens) FROM leaves) AS budget FROM leaves GROUP BY domain", "all_", "domain").strip()},
     {_share("l", "SELECT domain, lang, sum(tokens * 2) AS room, any_value(budget) AS budget FROM leaves JOIN d USING (domain) GROUP BY domain, lang", "domain", "lang").strip()},
     {_share("s", "SELECT domain, lang, source, tokens * 2 AS room, budget FROM leaves JOIN l USING (domain, lang)", "domain, lang", "source").strip()},
     plan AS (SELECT domain, lang, source, s.budget, CASE WHEN tokens > 0 THEN s.budget // tokens ELSE 0 END AS epochs, s.budget - CASE WHEN tokens > 0 THEN s.budget // tokens ELSE 0 END * tokens AS left_ FROM s JOIN leaves USING (domain, lang, source)),
     placed AS (SELECT r.*, p.budget, p.epochs, p.left_, md5('17|' || p.epochs || '|' || coalesce(doc_id::VARCHAR, 'null')) AS place FROM rows_ r JOIN plan p USING (domain, lang, source)),
     summed AS (SELECT *, coalesce(sum(n_tokens) OVER (PARTITION BY domain, lang, source ORDER BY place RANGE BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW EXCLUDE GROUP), 0) AS at_ FROM placed)
SELECT doc_id, domain, lang, source, n_tokens, budget::BIGINT AS budget, (epochs + CASE WHEN left_ > 0 AND at_ < left_ THEN 1 ELSE 0 END)::BIGINT AS copies FROM summed
"""

_QUOTES = r"""
WITH m AS (SELECT row_number() OVER () AS r, conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text, string_split(coalesce(text, ''), chr(10)) AS lines FROM conversations),
     e AS (SELECT r, conv_id, turn, unnest(lines) AS line FROM m),
     n AS (SELECT r, conv_id, turn, length(regexp_replace(regexp_extract(line, '^\s*((?:>\s?)+)', 1), '[^>]', '', 'g')) AS level,
                  trim(regexp_replace(lower(regexp_replace(line, '^\s*((?:>\s?)+)', '')), '\s+', ' ', 'g')) AS said FROM e),
     o AS (SELECT conv_id, said, min(turn) AS origin FROM n WHERE level = 0 AND said <> '' GROUP BY ALL),
     q AS (SELECT r, level, CASE WHEN origin < n.turn THEN origin END AS origin FROM n LEFT JOIN o ON n.conv_id = o.conv_id AND n.said = o.said WHERE level > 0 AND n.said <> '' AND n.conv_id IS NOT NULL AND turn IS NOT NULL),
     p AS (SELECT r, arg_min(origin, (level, -origin)) FILTER (origin IS NOT NULL) AS reply_to, count(*) AS n_quoted, count(origin) AS n_linked, max(level) AS deepest FROM q GROUP BY r),
     b AS (SELECT r, regexp_replace(array_to_string(list_filter(lines, lambda x, i: NOT regexp_matches(x, '^\s*>') AND NOT (regexp_matches(x, '^\s*(on .*|.* )?wrote:\s*$', 'i') AND regexp_matches(coalesce(lines[i + 1], ''), '^\s*>'))), chr(10)), '^\s+|\s+$', '', 'g') AS body FROM m)
SELECT conv_id, turn, role, body, reply_to, coalesce(n_quoted, 0) AS n_quoted, coalesce(n_linked, 0) AS n_linked, coalesce(deepest, 0)::INT AS deepest, '<|' || role || '|>' || chr(10) || body || chr(10) AS rendered
FROM m JOIN b USING (r) LEFT JOIN p USING (r)
"""

#: The same over quotations put into the given turns; passages are runs of lines of one level, told by windows.
_PLANTED = r"""
WITH RECURSIVE k AS (SELECT conv_id, turn, role, coalesce(text, '') AS text, turn - 1 - (conv_id + turn) % 2 AS f, (conv_id * 7 + turn) % 3 AS kind FROM conversations),
     m AS (SELECT row_number() OVER () AS r, k.conv_id, k.turn,
                  CASE WHEN o.text IS NULL THEN k.text ELSE 'They wrote:' || chr(10) || CASE k.kind WHEN 0 THEN '> ' || replace(o.text, chr(10), chr(10) || '> ') WHEN 1 THEN '>> ' || replace(o.text, chr(10), ' ')
                       ELSE '> ' || regexp_replace(replace(o.text, ' ', chr(10) || '> '), '\n([^>])', chr(10) || '> \1', 'g') END || chr(10) || chr(10) || k.text END AS text
           FROM k LEFT JOIN k o ON k.conv_id = o.conv_id AND k.f = o.turn),
     l AS (SELECT r, conv_id, turn, string_split(text, chr(10)) AS lines FROM m),
     e AS (SELECT r, conv_id, turn, unnest(lines) AS line, generate_subscripts(lines, 1) AS pos FROM l),
     n AS (SELECT r, conv_id, turn, pos, length(regexp_replace(regexp_extract(line, '^\s*((?:>\s?)+)', 1), '[^>]', '', 'g')) AS level,
                  trim(regexp_replace(lower(regexp_replace(line, '^\s*((?:>\s?)+)', '')), '\s+', ' ', 'g')) AS said FROM e),
     g AS (SELECT *, CASE WHEN said = '' THEN -1 ELSE level END AS mark FROM n),
     h AS (SELECT *, CASE WHEN mark = lag(mark) OVER (PARTITION BY r ORDER BY pos) THEN 0 ELSE 1 END AS fresh FROM g),
     i AS (SELECT *, sum(fresh) OVER (PARTITION BY r ORDER BY pos) AS run FROM h),
     u AS (SELECT r, conv_id, turn, false AS whole, level, said FROM n WHERE said <> '' UNION ALL
           SELECT r, conv_id, turn, true, level, string_agg(said, ' ' ORDER BY pos) FROM i WHERE said <> '' GROUP BY r, conv_id, turn, level, run),
     o AS (SELECT conv_id, said, min(turn) AS origin FROM u WHERE level = 0 GROUP BY ALL),
     q AS (SELECT u.r, u.whole, u.level, CASE WHEN origin < u.turn THEN origin END AS origin FROM u LEFT JOIN o ON u.conv_id = o.conv_id AND u.said = o.said WHERE level > 0),
     p AS (SELECT r, arg_min(origin, (level, -origin)) FILTER (origin IS NOT NULL) AS reply_to, count(*) FILTER (NOT whole) AS n_quoted, count(origin) FILTER (NOT whole) AS n_linked, max(level) AS deepest,
                  count(*) FILTER (whole) AS n_passages, count(origin) FILTER (whole) AS n_passages_linked FROM q GROUP BY r),
     b AS (SELECT r, regexp_replace(array_to_string(list_filter(lines, lambda x, i: NOT regexp_matches(x, '^\s*>') AND NOT (regexp_matches(x, '^\s*(on .*|.* )?wrote:\s*$', 'i') AND regexp_matches(coalesce(lines[i + 1], ''), '^\s*>'))), chr(10)), '^\s+|\s+$', '', 'g') AS body FROM l),
     t AS (SELECT m.r, m.conv_id, m.turn, reply_to FROM m LEFT JOIN p USING (r)),
     c(conv_id, turn, at_) AS (SELECT conv_id, turn, turn FROM t UNION ALL SELECT c.conv_id, c.turn, t.reply_to FROM c JOIN t ON c.conv_id = t.conv_id AND c.at_ = t.turn WHERE t.reply_to IS NOT NULL),
     d AS (SELECT conv_id, turn, min(at_) AS thread FROM c GROUP BY ALL)
SELECT m.conv_id, m.turn, body, reply_to, coalesce(n_quoted, 0) AS n_quoted, coalesce(n_linked, 0) AS n_linked, coalesce(deepest, 0)::INT AS deepest, coalesce(n_passages, 0) AS n_passages, coalesce(n_passages_linked, 0) AS n_passages_linked, thread
FROM m JOIN b USING (r) LEFT JOIN p USING (r) JOIN d ON m.conv_id = d.conv_id AND m.turn = d.turn
"""

#: Five-word shingles, pairs by shared shingles, and the smallest id over the links.
_JACCARD = rf"""
WITH RECURSIVE w AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), '{_UPPER}', '{_LOWER}'), '[^\x20\x09-\x0D]+') AS ws FROM documents),
     s AS (SELECT DISTINCT doc_id, unnest(CASE WHEN len(ws) = 0 THEN [] WHEN len(ws) < 5 THEN [array_to_string(ws, ' ')] ELSE list_transform(range(1, len(ws) - 3), lambda i: array_to_string(ws[i:i + 4], ' ')) END) AS g FROM w),
     n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
     p AS (SELECT a.doc_id AS x, b.doc_id AS y, count(*) AS both_ FROM s a JOIN s b ON a.g = b.g AND a.doc_id <> b.doc_id GROUP BY ALL),
     links AS (SELECT x, y FROM p JOIN n a ON x = a.doc_id JOIN n b ON y = b.doc_id WHERE 100 * both_ >= 75 * (a.n + b.n - both_)),
     reach(x, y) AS (SELECT doc_id, doc_id FROM documents UNION SELECT r.x, l.y FROM reach r JOIN links l ON r.y = l.x)
SELECT d.doc_id, coalesce(n.n, 0) AS n_shingles, m.c AS component_id FROM documents d LEFT JOIN n ON d.doc_id = n.doc_id JOIN (SELECT x, min(y) AS c FROM reach GROUP BY x) m ON d.doc_id = m.x
"""


def oracle_sql() -> dict[str, str]:
    return {"op1_exact_dedup": _EXACT, "op5_url_filter": _URLS, "op6_ngram_join": _JACCARD, "op9_mixing": _MIX, "op10_quotes": _QUOTES, "planted_quotes": _PLANTED}
