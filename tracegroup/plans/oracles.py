"""SQL twins of the engine's queries, for DuckDB on the same tables."""

from __future__ import annotations

_LINES = """w1 AS (SELECT l_orderkey, concat_ws('.', p_brand, p_type, p_name) AS frame, CASE WHEN p_type = 'PROMO' THEN {label} END AS mark, (l_linenumber, l_partkey, l_suppkey) AS o FROM lineitem JOIN part ON l_partkey = p_partkey),
     w2 AS (SELECT l_orderkey AS report_id, list(frame ORDER BY o) AS frames, array_to_string((list(mark ORDER BY o) FILTER (mark IS NOT NULL))[1:2], '>') AS category_id FROM w1 GROUP BY l_orderkey),
     w AS (SELECT report_id, epoch(o_orderdate)::BIGINT AS arrival, frames, category_id FROM w2 JOIN orders ON report_id = o_orderkey WHERE category_id <> '')"""
_SENTENCES = r"list_filter(list_transform(string_split_regex(coalesce(text, ''), '[.\n]+'), lambda x: trim(x)), lambda x: x <> '')"

#: CTEs that end in w (report_id, arrival, frames, category_id).
WORKLOADS = {
    "orders_longtail": _LINES.format(label="p_brand || ' ' || string_split(p_name, ' ')[2]"),
    "orders_dense": _LINES.format(label="string_split(p_name, ' ')[2]"),
    "planted_docs": f"""w3 AS (SELECT doc_id, {_SENTENCES} AS s FROM documents),
     w4 AS (SELECT doc_id, s, unnest(range(doc_id % 5 + 1)) AS k FROM w3 WHERE len(s) BETWEEN 5 AND 100),
     w AS (SELECT doc_id * 10 + k AS report_id, (doc_id * 7919 + k * 104729) % 1000003 AS arrival, CASE WHEN k = 0 THEN s ELSE list_filter(s, lambda x, i: (doc_id * 7919 + k * 104729 + i * 1299709) % 1000003 % 5 <> 0) END AS frames, doc_id::VARCHAR AS category_id FROM w4)""",
    "conversation_stacks": """w AS (SELECT a.conv_id * 1000 + a.turn AS report_id, (a.conv_id + 3 * a.turn) * 1000000 + a.conv_id AS arrival, list(b.role || '.' || b.text ORDER BY b.turn DESC) AS frames, a.conv_id::VARCHAR AS category_id
           FROM conversations a JOIN conversations b ON a.conv_id = b.conv_id AND b.turn <= a.turn GROUP BY a.conv_id, a.turn)""",
    "event_errors": r"""w5 AS (SELECT event_id, epoch_us(ts) AS arrival, user_id, event_type, event_type || '.k' || (regexp_extract(props, '"k": *(\d+)', 1)::INT % 10) AS frame FROM events),
     w6 AS (SELECT event_id, arrival, event_type, list_reverse(list({'f': frame, 't': event_type}) OVER (PARTITION BY user_id ORDER BY arrival, event_id ROWS BETWEEN 8 PRECEDING AND CURRENT ROW)) AS last FROM w5),
     w AS (SELECT event_id AS report_id, arrival, list_transform(last, lambda x: x.f) AS frames, array_to_string(list_filter(list_transform(last[2:], lambda x: x.t), lambda t: t <> 'error')[1:2], '>') AS category_id FROM w6 WHERE event_type = 'error')""",
    "page_dom": r"w AS (SELECT page_id AS report_id, page_id AS arrival, list_transform(regexp_extract_all(html, '<[a-z][a-z0-9]*[^>]*>[^<]{0,24}'), lambda x: trim(substr(x, 2))) AS frames, regexp_extract(url, '://([^/?#]*)', 1) AS category_id FROM pages)",
    "page_tags": r"w AS (SELECT page_id AS report_id, page_id AS arrival, list_transform(regexp_extract_all(html, '<[a-z][a-z0-9]*'), lambda x: trim(substr(x, 2))) AS frames, regexp_extract(url, '://([^/?#]*)', 1) AS category_id FROM pages)",
    "label_groups": f"w AS (SELECT doc_id AS report_id, doc_id AS arrival, {_SENTENCES} AS frames, quality::VARCHAR || ',' || toxic::VARCHAR AS category_id FROM documents JOIN labels USING (doc_id))",
}
WORKLOADS["whole_docs"] = WORKLOADS["planted_docs"].replace("len(s) BETWEEN 5 AND 100", "len(s) > 0")


def reports(name: str) -> str:
    """CTEs up to r: numbered, fingerprinted, split."""
    return f"""{WORKLOADS[name]},
     r AS (SELECT *, CASE WHEN arrival_seq * 1000 <= 700 * n_all THEN 'train' WHEN arrival_seq * 1000 <= 800 * n_all THEN 'validation' ELSE 'test' END AS part
           FROM (SELECT *, sha256(array_to_string(frames, chr(1))) AS fp, row_number() OVER (ORDER BY arrival, report_id) AS arrival_seq, count(*) OVER () AS n_all FROM w))"""


_FLAT = "f AS (SELECT fp, len(list_distinct(frames)) AS n, unnest(list_distinct(frames)) AS frame FROM t)"
_DF = "df AS (SELECT frame, count(*) AS df FROM (SELECT unnest(list_distinct(frames)) AS frame FROM r WHERE part = 'train') GROUP BY frame), nt AS (SELECT count(*) AS nt FROM r WHERE part = 'train')"
_TF = f"{_DF}, f AS (SELECT fp, frame, count(*) AS tf, any_value(n) AS n FROM (SELECT fp, len(frames) AS n, unnest(frames) AS frame FROM t) GROUP BY fp, frame), g AS (SELECT f.*, 1 + ln(nt / (coalesce(df, 0) + 1)) AS idf FROM f LEFT JOIN df USING (frame), nt)"

#: CTEs that end in s (q_fp, c_fp, score), from t (fp, frames), q (queries) and r.
SCORERS = {
    "overlap": f"{_FLAT}, s AS (SELECT a.fp AS q_fp, b.fp AS c_fp, count(*) / (any_value(a.n) + any_value(b.n) - count(*)) AS score FROM f a JOIN f b USING (frame) WHERE a.fp IN (SELECT fp FROM q) GROUP BY ALL)",
    "tfidf": f"{_TF}, s AS (SELECT a.fp AS q_fp, b.fp AS c_fp, sum(sqrt(b.tf) * b.idf * b.idf / sqrt(b.n)) AS score FROM g a JOIN g b USING (frame) WHERE a.fp IN (SELECT fp FROM q) GROUP BY ALL)",
    "tfidf_cosine": f"{_TF}, m AS (SELECT fp, sqrt(sum((tf * idf) ** 2)) AS l FROM g GROUP BY fp), s AS (SELECT a.fp AS q_fp, b.fp AS c_fp, sum(a.tf * a.idf * b.tf * b.idf) / (any_value(x.l) * any_value(y.l)) AS score FROM g a JOIN g b USING (frame) JOIN m x ON a.fp = x.fp JOIN m y ON b.fp = y.fp WHERE a.fp IN (SELECT fp FROM q) GROUP BY a.fp, b.fp)",
    "align": f"""{_DF}, o AS (SELECT fp, frame, pos, row_number() OVER (PARTITION BY fp, frame ORDER BY pos) AS nth FROM (SELECT fp, unnest(frames) AS frame, generate_subscripts(frames, 1) AS pos FROM t)),
     g AS (SELECT o.*, pos::DOUBLE ** (-1.0) * exp(-2.0 * coalesce(df, 0) / nt) AS wt FROM o LEFT JOIN df USING (frame), nt), m AS (SELECT fp, sum(wt) AS l FROM g GROUP BY fp),
     s AS (SELECT a.fp AS q_fp, b.fp AS c_fp, sum((a.wt + b.wt) * exp(-0.1 * abs(a.pos - b.pos))) / (any_value(x.l) + any_value(y.l)) AS score FROM g a JOIN g b ON a.frame = b.frame AND a.nth = b.nth JOIN m x ON a.fp = x.fp JOIN m y ON b.fp = y.fp WHERE a.fp IN (SELECT fp FROM q) GROUP BY a.fp, b.fp)""",
    "prefix": "s AS (SELECT a.fp AS q_fp, b.fp AS c_fp, coalesce(list_position(list_transform(list_zip(a.frames, b.frames), lambda z: z[1] IS NOT DISTINCT FROM z[2]), false) - 1, len(a.frames)) / greatest(len(a.frames), len(b.frames)) AS score FROM t a JOIN t b ON a.frames[1] = b.frames[1] WHERE a.fp IN (SELECT fp FROM q) AND len(a.frames) > 0)",
}


def replayed(name: str, system: str, part: str = "test", skip: bool = True) -> str:
    """CTEs up to k (ranked categories) and u (outcomes)."""
    only = "WHERE first_fp" if skip else ""
    return f"""{reports(name)},
     q AS (SELECT * FROM (SELECT r.*, arrival_seq = min(arrival_seq) OVER (PARTITION BY category_id) AS is_new, arrival_seq = min(arrival_seq) OVER (PARTITION BY fp) AS first_fp FROM r) {only} {"AND" if skip else "WHERE"} part = '{part}'),
     t AS (SELECT fp, any_value(frames) AS frames FROM r GROUP BY fp),
     i AS (SELECT fp, category_id, min(arrival_seq) AS first_seq FROM r GROUP BY fp, category_id),
     {SCORERS[system]},
     p AS (SELECT q.arrival_seq AS query_seq, i.category_id, i.first_seq AS cand_seq, round(score, 9) AS score FROM q JOIN s ON q.fp = q_fp JOIN i ON i.fp = c_fp WHERE i.first_seq < q.arrival_seq),
     c AS (SELECT query_seq, category_id, max(score) AS score, arg_max(cand_seq, (score, -cand_seq)) AS cand_seq FROM p GROUP BY query_seq, category_id),
     k AS (SELECT *, row_number() OVER (PARTITION BY query_seq ORDER BY score DESC, cand_seq, category_id) AS rank FROM c),
     u AS (SELECT q.arrival_seq AS query_seq, q.category_id AS true_category, is_new, b.category_id AS predicted, coalesce(b.score, 0.0) AS score, b.cand_seq AS best_cand, o.rank AS true_rank, coalesce(b.category_id = q.category_id, false) AS correct
           FROM q LEFT JOIN k b ON b.query_seq = q.arrival_seq AND b.rank = 1 LEFT JOIN k o ON o.query_seq = q.arrival_seq AND o.category_id = q.category_id)"""


_ACC = "round(avg(correct::INT) FILTER (NOT is_new), 6) AS acc_at_1, count(*) FILTER (NOT is_new) AS n_attached, count(*) FILTER (is_new) AS n_new"
_ACCK = ", ".join(f"round(avg((coalesce(true_rank, 99999999) <= {k})::INT), 6) AS acc_at_{k}" for k in (1, 3, 5, 10)) + ", round(avg(coalesce(1 / true_rank, 0.0)), 6) AS mrr"
_AUC = "SELECT round(CASE WHEN a * c > 0 THEN (SELECT sum(x.n_a * (y.n_c * CASE WHEN y.score < x.score THEN 1 WHEN y.score = x.score THEN 0.5 ELSE 0 END)) FROM gs x, gs y) / (a * c) END, 6) AS auc, a::BIGINT AS n_attached, c::BIGINT AS n_new FROM (SELECT sum(n_a) AS a, sum(n_c) AS c FROM gs)"
_G = "gs AS (SELECT score, count(*) FILTER (NOT is_new) AS n_a, count(*) FILTER (is_new) AS n_c FROM u GROUP BY score)"
_CURVE = f"{_G}, v AS (SELECT score, (sum(n_c) OVER o)::DOUBLE AS tp, (sum(n_a) OVER o)::DOUBLE AS fp_, (SELECT sum(n_c) FROM gs)::DOUBLE AS c, (SELECT sum(n_a) FROM gs)::DOUBLE AS a FROM gs WINDOW o AS (ORDER BY score)), f1 AS (SELECT score AS threshold, round(CASE WHEN tp + fp_ > 0 THEN tp / (tp + fp_) END, 6) AS precision, round(CASE WHEN c > 0 THEN tp / c END, 6) AS recall, round(coalesce(CASE WHEN tp + fp_ + c > 0 THEN 2 * tp / (tp + fp_ + c) END, 0.0), 6) AS f1 FROM v)"
SYSTEMS = ("align", "overlap", "prefix", "tfidf")


def _systems(name: str, measure: str, where: str = "") -> str:
    return " UNION ALL ".join(f"SELECT * FROM (WITH {replayed(name, s)} SELECT '{s}' AS system, {measure} FROM u {where})" for s in SYSTEMS)


def _aucs(name: str) -> str:
    return " UNION ALL ".join(f"SELECT * FROM (WITH {replayed(name, s)}, {_G} SELECT '{s}' AS system, z.* FROM ({_AUC}) z)" for s in SYSTEMS)


def _topk(system: str, name: str) -> str:
    return f"WITH {replayed(name, system)} SELECT query_seq, category_id, round(score, 6) AS score, cand_seq, rank FROM k WHERE rank <= 10"


def on_whole_docs(sql: str) -> str:
    """A twin on planted_docs, on the variants of every document."""
    return sql.replace(WORKLOADS["planted_docs"], WORKLOADS["whole_docs"])


_PAIRS = f"""{reports("planted_docs")},
     tr AS (SELECT DISTINCT category_id, fp FROM r),
     cn AS (SELECT category_id, row_number() OVER (ORDER BY substr(md5(category_id), 1, 2), category_id) - 1 AS cat FROM (SELECT DISTINCT category_id FROM tr)),
     o AS (SELECT category_id, fp, cat, row_number() OVER (PARTITION BY category_id ORDER BY fp) - 1 AS i, count(*) OVER (PARTITION BY category_id) AS n FROM tr JOIN cn USING (category_id)),
     cc AS (SELECT DISTINCT category_id, cat, n, n * (n - 1) // 2 AS all_ FROM o WHERE n > 1),
     pn AS (SELECT category_id, n, unnest(range(all_)) AS p FROM cc WHERE all_ <= 5
            UNION ALL SELECT category_id, n, (s + t * (s % all_)) % all_ FROM (SELECT *, list_filter(list_transform(range(61), lambda d: (cat * 7919 + 104729) % 1000003 + 1 + d), lambda x: gcd(x, all_) = 1)[1] AS s, unnest(range(5)) AS t FROM cc WHERE all_ > 5)),
     ij AS (SELECT *, p - i_ * (i_ - 1) // 2 AS j_ FROM (SELECT *, (SELECT max(x) FROM range(1, 200) z(x) WHERE x * (x - 1) // 2 <= p) AS i_ FROM pn)),
     pp AS (SELECT ij.category_id, CASE WHEN (p * 7919 + 31) % 2 = 1 THEN b.fp ELSE a.fp END AS anchor_fp, CASE WHEN (p * 7919 + 31) % 2 = 1 THEN a.fp ELSE b.fp END AS positive_fp, p FROM ij JOIN o a ON a.category_id = ij.category_id AND a.i = i_ JOIN o b ON b.category_id = ij.category_id AND b.i = j_)"""

_DOT = "list_dot_product(a.embedding::DOUBLE[], b.embedding::DOUBLE[])"
_COS = "(list_dot_product(a.{0}::DOUBLE[], {1}::DOUBLE[]) / sqrt(list_dot_product(a.{0}::DOUBLE[], a.{0}::DOUBLE[]) * list_dot_product({1}::DOUBLE[], {1}::DOUBLE[])))"


def _nearest(k: int, causal: bool) -> str:
    return f"SELECT q_id, c_id, score, rank::INT AS rank FROM (SELECT a.vec_id AS q_id, b.vec_id AS c_id, round({_DOT}, 9) AS score, row_number() OVER (PARTITION BY a.vec_id ORDER BY round({_DOT}, 9) DESC, b.vec_id) AS rank FROM embeddings a JOIN embeddings b ON {'b.vec_id < a.vec_id' if causal else 'true'} WHERE a.vec_id % 20 = 0) WHERE rank <= {k}"


_PART = "p AS (SELECT DISTINCT concat_ws('.', p_brand, p_type, p_name) AS frame FROM part)"
_NAMES = r"""p0 AS (SELECT DISTINCT concat_ws('.', p_brand, p_type, p_name) AS frame FROM part),
     p AS (SELECT translate(frame, ' #', '_X') || '.' || regexp_replace(array_to_string(list_transform(string_split(frame, ' '), lambda x: upper(x[1]) || lower(x[2:])), ' '), '[^A-Za-z0-9]', '', 'g') || 'HTTPServer2Go' AS frame FROM p0)"""
_HUMPS = "frame"
for _a, _b in ((r"([\p{Ll}\p{Nd}])(\p{Lu})", r"\1 \2"), (r"(\p{Lu})(\p{Lu}\p{Ll})", r"\1 \2"), (r"(\p{L})(\p{Nd})", r"\1 \2"), (r"(\p{Nd})(\p{L})", r"\1 \2")):
    _HUMPS = f"regexp_replace({_HUMPS}, '{_a}', '{_b}', 'g')"


def _pieces(expression: str) -> str:
    return rf"list_transform(list_filter(string_split_regex({expression}, '[^\p{{L}}\p{{Nd}}]+'), lambda x: x <> ''), lambda x: lower(x))"


_COUNTS = f"{_PART}, e AS (SELECT unnest({_pieces(_HUMPS)}) AS piece FROM p), pc AS (SELECT piece, count(*) AS n FROM e GROUP BY piece)"
_VARIANTS = f"{WORKLOADS['planted_docs']}, v AS (SELECT x.category_id, x.frames AS q, y.frames AS k FROM w x JOIN w y USING (category_id) WHERE x.report_id % 10 = 1 AND y.report_id % 10 = 0)"


def _flags(a: str, b: str) -> str:
    return f"array_to_string(list_transform({a}, lambda x: CASE WHEN list_contains({b}, x) THEN '1' ELSE '0' END), '')"


def oracle_sql() -> dict[str, str]:
    names = ("orders_longtail", "orders_dense", "planted_docs", "conversation_stacks", "event_errors", "page_dom")
    out = {f"reports_{n}": f"WITH {reports(n)} SELECT report_id, arrival_seq, len(frames) AS n_frames, fp, category_id FROM r" for n in names}
    out["fingerprints"] = f"WITH {reports('planted_docs')} SELECT fp, count(*) AS n_reports, min(arrival_seq) AS first_seq FROM r GROUP BY fp"
    out["identical_shortcut"] = f"WITH {reports('planted_docs')} SELECT report_id, known AS category_id FROM (SELECT report_id, row_number() OVER o AS n, first_value(category_id) OVER o AS known FROM r WINDOW o AS (PARTITION BY fp ORDER BY arrival_seq)) WHERE n > 1"
    out["skip_identical"] = f"WITH {reports('planted_docs')} SELECT report_id, arrival_seq, NOT EXISTS (FROM r x WHERE x.category_id = r.category_id AND x.arrival_seq < r.arrival_seq) AS is_new FROM r WHERE part = 'test' AND NOT EXISTS (FROM r x WHERE x.fp = r.fp AND x.arrival_seq < r.arrival_seq)"
    out["chrono_split"] = f"WITH {reports('planted_docs')} SELECT report_id, arrival_seq, part FROM r"
    out["shared_traces"] = f"WITH {reports('page_tags')} SELECT fp, count(DISTINCT category_id) AS n_categories FROM r GROUP BY fp HAVING count(DISTINCT category_id) > 1"
    out["dataset_stats"] = " UNION ALL ".join(f"SELECT * FROM (WITH {reports(n)}, g AS (SELECT category_id, count(*) AS n, count(DISTINCT fp) AS u FROM r GROUP BY category_id) SELECT '{n}' AS workload, sum(n)::BIGINT AS n_reports, (SELECT count(DISTINCT fp) FROM r) AS n_unique, count(*) AS n_categories, round(avg(n), 6) AS avg_reports, round(avg(u), 6) AS avg_unique FROM g)" for n in (*names, "page_tags", "label_groups"))
    out["frame_parts"] = f"WITH {_PART}, s AS (SELECT frame, string_split(frame, '.') AS x FROM p) SELECT frame, array_to_string(x[:len(x) - 2], '.') AS package, coalesce(x[len(x) - 1], '') AS class_name, x[len(x)] AS method FROM s"
    out["frame_pieces_camel"] = f"WITH {_NAMES} SELECT frame, array_to_string({_pieces(_HUMPS)}, '|') AS pieces FROM p"
    out["frame_pieces_snake"] = f"WITH {_NAMES} SELECT frame, array_to_string({_pieces('frame')}, '|') AS pieces FROM p"
    out["bpe_piece_counts"] = f"WITH {_COUNTS} SELECT piece, n FROM pc"
    out["bpe_first_pairs"] = f"WITH {_COUNTS}, x AS (SELECT piece || '▁' AS s, n FROM pc), y AS (SELECT s, n, unnest(range(1, length(s))) AS i FROM x) SELECT s[i] AS left, s[i + 1] AS right, sum(n)::BIGINT AS n FROM y GROUP BY ALL"
    out["positive_pair_counts"] = f"WITH {reports('planted_docs')}, g AS (SELECT category_id, count(DISTINCT fp) AS n FROM r GROUP BY category_id) SELECT category_id, least(n * (n - 1) // 2, 5)::BIGINT AS n_pairs FROM g WHERE n > 1"
    out["positive_pairs_capped"] = f"WITH {_PAIRS} SELECT category_id, anchor_fp, positive_fp, p FROM pp"
    out["pair_batches"] = f"WITH {_PAIRS} SELECT anchor_fp, positive_fp, category_id, (n - 1) // 64 AS batch, ((n - 1) % 64)::INT AS slot FROM (SELECT *, row_number() OVER (ORDER BY md5('1|' || anchor_fp || '|' || positive_fp || '|' || category_id)) AS n FROM pp)"
    out["triplet_draws"] = f"""WITH {_PAIRS}, ca AS (SELECT DISTINCT category_id, cat, n FROM o), nc AS (SELECT count(*) AS nc FROM ca),
     td AS (SELECT pp.*, ca.cat, (ca.cat * 7919 + p * 104729 + 1299709) % (nc - 1) AS d FROM pp JOIN ca USING (category_id), nc),
     te AS (SELECT td.*, x.category_id AS negative_category, (td.cat * 15485863 + p * 7919 + 31) % x.n AS ni FROM td JOIN ca x ON x.cat = td.d + (td.d >= td.cat)::INT)
     SELECT te.category_id, anchor_fp, positive_fp, p, o.fp AS negative_fp, negative_category FROM te JOIN o ON o.category_id = negative_category AND o.i = ni WHERE o.fp <> anchor_fp"""
    cos = _COS.format("embedding", "b.embedding")
    out["info_nce_on_embeddings"] = f"WITH x AS (SELECT a.vec_id AS anchor, b.vec_id = a.vec_id + 1 AS pos, {cos} / 0.1 AS x FROM embeddings a JOIN embeddings b ON a.vec_id // 32 = b.vec_id // 32 WHERE a.vec_id % 2 = 0 AND b.vec_id % 2 = 1) SELECT anchor, round(-max(x) FILTER (pos) + ln(sum(exp(x)) FILTER (NOT pos)), 6) AS loss FROM x GROUP BY anchor HAVING count(*) FILTER (NOT pos) > 0"
    out["bce_on_embeddings"] = f"WITH x AS (SELECT a.vec_id AS anchor, round(5 * {cos}, 9) AS p, round(5 * {_COS.format('embedding', 'c.embedding')}, 9) AS n FROM embeddings a JOIN embeddings b ON b.vec_id = a.vec_id + 1 JOIN embeddings c ON c.vec_id = a.vec_id + 2 WHERE a.vec_id % 3 = 0) SELECT anchor, round(ln(1 + exp(-p)) + ln(1 + exp(n)), 6) AS loss FROM x"
    for how in ("avg", "max"):
        out[f"pool_{how}"] = f"SELECT label, (i - 1)::INT AS place, round({how}(embedding[i]::DOUBLE), 6) AS value FROM embeddings, range(1, 65) z(i) GROUP BY ALL"
    out["exact_topk_embeddings"] = out["ivf_full_probe"] = _nearest(10, False)
    out["causal_best_match"] = _nearest(1, True)
    out["lsh_bucket_keys"] = "WITH s AS (SELECT vec_id, p, sum(embedding[d + 1]::DOUBLE * ((p * 7919 + d * 104729 + p * d * 31 + 1299709) % 1000003 % 1001 - 500)) AS x FROM embeddings, range(16) a(p), range(64) b(d) GROUP BY ALL) SELECT vec_id AS id, (p // 8)::INT AS tab, sum(CASE WHEN x > 0 THEN 1 << (p % 8) ELSE 0 END)::BIGINT AS bucket FROM s GROUP BY ALL"
    out["category_scores"] = f"WITH {replayed('conversation_stacks', 'overlap')} SELECT query_seq, category_id, score, cand_seq FROM c"
    out["shared_frame_flags"] = f"WITH {_VARIANTS} SELECT category_id, {_flags('q', 'k')} AS query_flags, {_flags('k', 'q')} AS candidate_flags FROM v"
    out["shared_frame_counts"] = f"WITH {_VARIANTS} SELECT category_id, len(list_filter(q, lambda x: list_contains(k, x))) AS in_query, len(list_filter(k, lambda x: list_contains(q, x))) AS in_candidate FROM v"
    out["tfidf_topk"], out["tfidf_cosine_topk"] = _topk("tfidf", "conversation_stacks"), _topk("tfidf_cosine", "conversation_stacks")
    out["top_frame_align"], out["set_overlap"], out["prefix_match"] = _topk("align", "conversation_stacks"), _topk("overlap", "conversation_stacks"), _topk("prefix", "orders_longtail")
    out["char_edit_distance"] = f"WITH {reports('orders_longtail')}, x AS (SELECT arrival_seq, array_to_string(frames, chr(10)) AS t FROM r) SELECT x.arrival_seq, levenshtein(x.t, y.t) AS distance, round(1 - levenshtein(x.t, y.t) / greatest(length(x.t), length(y.t)), 6) AS similarity FROM x JOIN x y ON y.arrival_seq = x.arrival_seq - 1"
    out["llm_concat_text"] = f"WITH {WORKLOADS['orders_longtail']} SELECT report_id, array_to_string(frames[:5], ' ; ') AS text FROM w"
    for n in ("orders_longtail", "planted_docs", "conversation_stacks"):
        out[f"acc_at_1_{n}"], out[f"roc_auc_{n}"] = _systems(n, _ACC), _aucs(n)
    out["acc_at_k"] = _systems("planted_docs", _ACCK, "WHERE NOT is_new")
    out["roc_points"] = f"WITH {replayed('orders_longtail', 'overlap')}, {_CURVE} SELECT score, round(CASE WHEN c > 0 THEN tp / c END, 6) AS tpr, round(CASE WHEN a > 0 THEN fp_ / a END, 6) AS fpr FROM v"
    for n in ("orders_longtail", "planted_docs"):
        curve = f"WITH {replayed(n, 'overlap', 'validation')}, {_CURVE}"
        out[f"f1_curve_{n}"] = f"{curve} SELECT threshold, precision, recall, f1 FROM f1"
        out[f"best_threshold_{n}"] = f"{curve} SELECT arg_max(threshold, (f1, -threshold)) AS threshold, max(f1) AS f1 FROM f1"
    out["decisions"] = f"WITH z AS ({out['best_threshold_planted_docs']}), y AS (WITH {replayed('planted_docs', 'overlap')} SELECT * FROM u) SELECT query_seq, true_category, is_new, predicted, round(score, 6) AS score, CASE WHEN predicted IS NOT NULL AND score > coalesce((SELECT threshold FROM z), 0) THEN 'attach' ELSE 'create' END AS action FROM y"
    out["skip_rule_effect"] = " UNION ALL ".join(f"SELECT * FROM (WITH {replayed('planted_docs', 'overlap', 'test', s)} SELECT {str(s).lower()} AS skip, {_ACC} FROM u)" for s in (True, False))
    out["category_roots"] = f"WITH RECURSIVE y AS (WITH {replayed('planted_docs', 'overlap')} SELECT query_seq AS report, CASE WHEN score > 0.5 THEN best_cand END AS parent FROM u), z(report, at_) AS (SELECT report, report FROM y UNION ALL SELECT z.report, y.parent FROM z JOIN y ON y.report = z.at_ WHERE y.parent IS NOT NULL) SELECT report, min(at_) AS root FROM z GROUP BY report"
    out["curate_reviewed"] = f"WITH {WORKLOADS['planted_docs']} SELECT report_id, category_id FROM w WHERE category_id IN (SELECT doc_id::VARCHAR FROM labels)"
    out["curate_foreign"] = f"WITH {WORKLOADS['orders_longtail']}, x AS (SELECT len(list_filter(frames, lambda f: NOT (starts_with(f, 'Brand#1') OR starts_with(f, 'Brand#2')))) = 0 AS ok FROM w) SELECT count(*) AS reports, count(*) FILTER (ok) AS kept, round(1 - count(*) FILTER (ok) / count(*), 6) AS removed_share FROM x"
    out["benchmark_probe"] = "SELECT item_id, doc_id FROM benchmark b JOIN documents d ON contains(d.text, b.text)"
    out["acc_rollup_region"] = f"WITH y AS (WITH {replayed('orders_longtail', 'overlap')} SELECT u.*, q.report_id FROM u JOIN q ON q.arrival_seq = query_seq WHERE NOT u.is_new) SELECT r_name AS region, c_mktsegment AS segment, round(avg(correct::INT), 6) AS acc_at_1, count(*) AS n, grouping_id(r_name, c_mktsegment) AS level FROM y JOIN orders ON report_id = o_orderkey LEFT JOIN customer ON o_custkey = c_custkey LEFT JOIN nation ON c_nationkey = n_nationkey LEFT JOIN region ON n_regionkey = r_regionkey GROUP BY ROLLUP (r_name, c_mktsegment)"
    out["acc_pivot"] = f"SELECT x.system, x.acc_at_1 AS orders_longtail, y.acc_at_1 AS conversation_stacks FROM ({_systems('orders_longtail', _ACC)}) x JOIN ({_systems('conversation_stacks', _ACC)}) y ON x.system = y.system"
    out["new_category_rate_hourly"] = f"WITH {reports('event_errors')}, x AS (SELECT arrival // 3600000000 AS hour, arrival_seq = min(arrival_seq) OVER (PARTITION BY category_id) AS is_new FROM r) SELECT hour, count(*) AS n_reports, count(*) FILTER (is_new) AS n_new FROM x GROUP BY hour"
    out["moving_acc"] = f"WITH {replayed('planted_docs', 'overlap')} SELECT query_seq, round(avg(correct::INT) OVER (ORDER BY query_seq RANGE BETWEEN 199 PRECEDING AND CURRENT ROW), 6) AS moving_acc FROM u WHERE NOT is_new"
    out["session_traces"] = "WITH x AS (SELECT user_id, epoch_us(ts) AS t, event_type, CASE WHEN epoch_us(ts) - lag(epoch_us(ts)) OVER o < 1800000000 THEN 0 ELSE 1 END AS first FROM events WINDOW o AS (PARTITION BY user_id ORDER BY ts)), y AS (SELECT *, sum(first) OVER (PARTITION BY user_id ORDER BY t) AS s FROM x) SELECT user_id, min(t) AS start_us, count(*) AS n_events, count(*) FILTER (event_type = 'error') AS n_errors FROM y GROUP BY user_id, s"
    out["burst_windows"] = "SELECT ((epoch_us(ts) // 3600000000) - h) * 3600000000 AS start_us, count(*) AS n_errors FROM events, range(24) z(h) WHERE event_type = 'error' GROUP BY 1"
    out["arrival_gaps"] = f"WITH {reports('conversation_stacks')} SELECT report_id, category_id, arrival_seq - lag(arrival_seq) OVER (PARTITION BY category_id ORDER BY arrival_seq) AS gap FROM r"
    return out
