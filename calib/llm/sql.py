"""DuckDB SQL for those queries of this subpackage that SQL can express."""

from calib.llm.rules import STOP_WORDS, THRESHOLDS
from calib.llm.url_filter import BLOCKED_HOSTS, RULES

WORD = r"'[^\x20\x09-\x0D]+'"
_LIST = lambda xs: "(" + ", ".join(f"'{x}'" for x in dict.fromkeys(xs)) + ")"

_MEASURES = f"""WITH d AS (SELECT doc_id, coalesce(text, '') AS t FROM documents),
w AS (SELECT doc_id, t, regexp_extract_all(t, {WORD}) AS w, list_filter(string_split(t, chr(10)), lambda x: regexp_matches(x, {WORD})) AS l FROM d),
g AS (SELECT doc_id, i, array_to_string(w[i:i + 7], ' ') AS s FROM w, unnest(generate_series(1, len(w) - 7)) AS u(i)),
r AS (SELECT doc_id, i FROM g QUALIFY count(*) OVER (PARTITION BY doc_id, s) > 1),
c AS (SELECT doc_id, count(DISTINCT i + k) AS n FROM r, range(0, 8) AS k(k) GROUP BY doc_id),
m AS (SELECT doc_id, len(w) AS n_words, coalesce(list_sum(list_transform(w, lambda x: length(x))), 0)::BIGINT AS word_chars,
  (length(t) - length(translate(t, '#*$%&|<>', '')))::BIGINT AS n_symbols, (len(l) - len(list_distinct(l)))::BIGINT AS n_dup_lines, coalesce(c.n, 0)::BIGINT AS n_repeat_words,
  len(l) AS n_lines, len(list_filter(w, lambda x: lower(x) IN {_LIST(STOP_WORDS)})) AS n_stop, length(regexp_replace(t, '[^\\p{{L}}]+', '', 'g')) AS letters, length(regexp_replace(t, '[^\\p{{Lu}}]+', '', 'g')) AS upper_letters
  FROM w LEFT JOIN c USING (doc_id)),
q AS (SELECT *, word_chars / nullif(n_words, 0) AS mean_word_length, n_symbols / nullif(n_words, 0) AS symbols_per_word, n_stop / nullif(n_words, 0) AS stop_word_ratio,
  n_repeat_words / nullif(n_words, 0) AS repeat_word_ratio, n_dup_lines / nullif(n_lines, 0) AS dup_line_ratio, upper_letters / nullif(letters, 0) AS upper_ratio, n_words < 20 OR 100 * n_repeat_words > 30 * n_words AS base_failed FROM m)"""
_VERDICT = " AND ".join(f"coalesce({m} {op} {v}, true)" for _, m, lo, hi in THRESHOLDS for op, v in ((">=", lo), ("<=", hi)) if v is not None)

_RULES = ", ".join(f"('{v}', '{h}', '{p}')" for v, h, p in RULES)

ORACLES: dict[str, str] = {
    "op3_quality_rules": f"{_MEASURES} SELECT doc_id, n_words::BIGINT AS n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, NOT base_failed AND {_VERDICT} AS kept FROM q",
    "op5_top_k": """WITH v AS (SELECT vec_id, list_transform(embedding, lambda x: floor(64 * x::DOUBLE)) AS v FROM embeddings WHERE embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0),
        s AS (SELECT q.vec_id AS query_id, c.vec_id AS vec_id, list_dot_product(q.v, c.v)::BIGINT AS score FROM v q JOIN v c ON q.vec_id <> c.vec_id WHERE q.vec_id % 20 = 0)
        SELECT query_id, (row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id))::INT AS rank, vec_id, score FROM s QUALIFY row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) <= 20""",
    "op7_url_filter": f"""WITH u AS (SELECT page_id, CASE WHEN strpos(url, '://') > 0 THEN substr(url, strpos(url, '://') + 3) ELSE '' END AS r FROM pages),
        p AS (SELECT page_id, translate(regexp_extract(r, '^([^/?#]*)', 1), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host, regexp_extract(r, '^[^/?#]*([^?#]*)', 1) AS path FROM u),
        f AS (SELECT page_id, arg_max(h || x, length(h || x)) AS rule, arg_max(v, length(h || x)) AS v FROM p JOIN (VALUES {_RULES}) t(v, h, x) ON (host = h OR ends_with(host, '.' || h)) AND starts_with(path, x) GROUP BY page_id),
        b AS (SELECT DISTINCT page_id FROM p JOIN (SELECT unnest({list(BLOCKED_HOSTS)}) AS h) ON host = h OR ends_with(host, '.' || h))
        SELECT page_id, host, path, rule, CASE WHEN rule IS NOT NULL THEN v WHEN b.page_id IS NOT NULL THEN 'block' ELSE 'allow' END AS verdict FROM p LEFT JOIN f USING (page_id) LEFT JOIN b USING (page_id)""",
    "token_counts_of_words": f"""WITH d AS (SELECT source, lang, list_sum(list_transform(list_distinct(string_split(text, chr(10))), lambda x: len(regexp_extract_all(x, {WORD})))) AS clean, row_number() OVER (PARTITION BY text ORDER BY doc_id) AS rn FROM documents)
        SELECT source, lang, 'words_v1' AS tokenizer, count(*) AS n_docs, coalesce(sum(clean), 0)::BIGINT AS n_tokens FROM d WHERE rn = 1 GROUP BY source, lang""",
}
