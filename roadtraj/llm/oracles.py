"""DuckDB SQL of those training-data queries that SQL can express whole."""

from __future__ import annotations

from roadtraj.llm.quality import RULES, STOP_WORDS

_WORDS = r"list_filter(string_split_regex(coalesce(text, ''), '[\x20\x09-\x0D]+'), lambda x: x <> '')"

SUBSTRINGS = rf"""
WITH d AS (SELECT row_number() OVER () AS r, doc_id, {_WORDS} AS w FROM documents),
s AS (SELECT r, doc_id, unnest(range(1, len(w) - 48)) AS i, w FROM d WHERE len(w) >= 50),
h AS (SELECT r, doc_id, i, md5(array_to_string(w[i:i + 49], ' ')) AS k FROM s),
f AS (SELECT r, i FROM (SELECT *, min(doc_id) OVER (PARTITION BY k) AS first FROM h) WHERE first < doc_id),
g AS (SELECT DISTINCT r, unnest(range(i, i + 50)) AS p FROM f),
u AS (SELECT r, unnest(w) AS x, unnest(range(1, len(w) + 1)) AS p FROM d),
k AS (SELECT u.r, count(g.p) AS n_removed, string_agg(x, ' ' ORDER BY u.p) FILTER (g.p IS NULL) AS kept FROM u LEFT JOIN g ON u.r = g.r AND u.p = g.p GROUP BY u.r)
SELECT doc_id, CAST(len(w) AS BIGINT) AS n_words, coalesce(n_removed, 0) AS n_removed, sha256(coalesce(kept, '')) AS kept_sha256 FROM d LEFT JOIN k ON d.r = k.r"""

CHAT = r"""
WITH c AS (SELECT conv_id, turn, role, coalesce(text, '') AS text FROM conversations UNION ALL
  SELECT -1, k, CASE k WHEN 0 THEN 'user' ELSE 'assistant' END, '</s>[INST] ok [/INST]' FROM range(2) t(k)),
n AS (SELECT *, 13 + length(coalesce(role, '')) + length(text) + length(regexp_replace(coalesce(role, '') || text, '[^\\<|\[]+', '', 'g')) AS size FROM c),
s AS (SELECT *, sum(size) OVER (PARTITION BY conv_id ORDER BY turn, role, text) AS upto FROM n)
SELECT conv_id, count(*) AS n_turns, sha256(string_agg(coalesce(role, '') || chr(10) || text || chr(10), '' ORDER BY turn, role, text)) AS turns_sha256,
  CAST(coalesce(sum(length(text)) FILTER (role = 'assistant'), 0) AS BIGINT) AS loss_chars, sha256(coalesce(string_agg(text, '' ORDER BY turn, role, text) FILTER (role = 'assistant'), '')) AS loss_sha256,
  CAST(coalesce(sum(upto) FILTER (role = 'assistant'), 0) AS BIGINT) AS formatted_chars FROM s GROUP BY conv_id"""

_BOUNDS = " AND ".join(f"{m} {op} {b}" for m, least, most in RULES for op, b in ((">=", least), ("<=", most)) if b is not None)
_STOP = ", ".join(f"'{w}'" for w in dict.fromkeys(STOP_WORDS))

QUALITY = rf"""
WITH d AS (SELECT row_number() OVER () AS r, doc_id, {_WORDS} AS w, coalesce(text, '') AS t,
  list_filter(string_split(coalesce(text, ''), chr(10)), lambda l: regexp_matches(l, '[^\x20\x09-\x0D]')) AS l FROM documents),
g AS (SELECT r, unnest(range(1, len(w) - 1)) AS i, w FROM d WHERE len(w) >= 3),
k AS (SELECT r, i, count(*) OVER (PARTITION BY r, w[i], w[i + 1], w[i + 2]) AS n FROM g),
c AS (SELECT r, count(DISTINCT i + j) AS n_repeat_words FROM k, range(3) o(j) WHERE n > 1 GROUP BY r),
m AS (SELECT doc_id, CAST(len(w) AS BIGINT) AS n_words, CAST(length(array_to_string(w, '')) AS BIGINT) AS word_chars, CAST(length(regexp_replace(t, '[^#*$%&|<>]+', '', 'g')) AS BIGINT) AS n_symbols,
  CAST(len(l) - len(list_distinct(l)) AS BIGINT) AS n_dup_lines, coalesce(n_repeat_words, 0) AS n_repeat_words, len(l) AS n_lines, len(list_intersect(w, [{_STOP}])) AS n_stop_kinds FROM d LEFT JOIN c ON d.r = c.r),
x AS (SELECT *, 100.0 * n_repeat_words / greatest(n_words, 1) AS repeat_percent, word_chars / greatest(n_words, 1) AS mean_word_chars, n_symbols / greatest(n_words, 1) AS symbol_ratio, n_dup_lines / greatest(n_lines, 1) AS dup_line_ratio FROM m)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, NOT (n_words >= 50 AND repeat_percent <= 50) AS base_failed, {_BOUNDS} AS kept FROM x"""

TOP_K = """
WITH v AS (SELECT vec_id, list_transform(embedding, lambda x: floor(256 * CAST(x AS DOUBLE))) AS w FROM embeddings),
s AS (SELECT q.vec_id AS query_id, c.vec_id, CAST(list_inner_product(q.w, c.w) AS BIGINT) AS score FROM v q JOIN v c ON q.vec_id % 50 = 0 AND c.vec_id <> q.vec_id)
SELECT query_id, CAST(row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS INT) AS rank, vec_id, score FROM s QUALIFY rank <= 5"""

SUFFIXES = """
WITH d AS (SELECT row_number() OVER () AS r, doc_id, lower(hex(encode(coalesce(text, '')))) AS x FROM documents),
s AS (SELECT r, unnest(range(0, length(x) // 2 - 199)) AS i, x FROM d WHERE length(x) >= 400),
h AS (SELECT r, i, md5(substr(x, 2 * i + 1, 400)) AS k FROM s),
f AS (SELECT r, i FROM (SELECT *, count(*) OVER (PARTITION BY k) AS n FROM h) WHERE n > 1),
j AS (SELECT r, i, lag(i) OVER (PARTITION BY r ORDER BY i) AS was FROM f),
n AS (SELECT r, i, sum(CASE WHEN was IS NULL OR i - was > 200 THEN 1 ELSE 0 END) OVER (PARTITION BY r ORDER BY i) AS span FROM j),
b AS (SELECT r, span, min(i) AS a, max(i) + 200 AS z FROM n GROUP BY r, span),
k AS (SELECT b.r, a, z, coalesce(lag(z) OVER (PARTITION BY b.r ORDER BY a), 0) AS before FROM b),
p AS (SELECT k.r, count(*) AS n_spans, sum(z - a) AS n_removed, string_agg(substr(x, 2 * before + 1, 2 * (a - before)), '' ORDER BY a) || substr(any_value(x), 2 * max(z) + 1) AS kept FROM k JOIN d ON k.r = d.r GROUP BY k.r)
SELECT doc_id, length(x) // 2 AS n_bytes, CAST(coalesce(n_removed, 0) AS BIGINT) AS n_removed, coalesce(n_spans, 0) AS n_spans, sha256(unhex(coalesce(kept, x))) AS kept_sha256 FROM d LEFT JOIN p ON d.r = p.r"""

JACCARD = rf"""
WITH RECURSIVE d AS (SELECT doc_id, list_filter(string_split_regex(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x20\x09-\x0D]+'), lambda x: x <> '') AS w FROM documents),
g AS (SELECT DISTINCT doc_id, w[i] || ' ' || w[i + 1] || ' ' || w[i + 2] AS k FROM (SELECT doc_id, w, unnest(range(1, len(w) - 1)) AS i FROM d WHERE len(w) >= 3)
  UNION SELECT doc_id, array_to_string(w, ' ') FROM d WHERE len(w) BETWEEN 1 AND 2),
n AS (SELECT doc_id, count(*) AS size FROM g GROUP BY doc_id),
o AS (SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS met FROM g a JOIN g b ON a.k = b.k AND a.doc_id < b.doc_id GROUP BY a.doc_id, b.doc_id),
l AS (SELECT a, b FROM o JOIN n x ON x.doc_id = a JOIN n y ON y.doc_id = b WHERE 100 * met >= 90 * (x.size + y.size - met)),
e AS (SELECT a, b FROM l UNION SELECT b, a FROM l),
t(a, b) AS (SELECT a, b FROM e UNION SELECT t.a, e.b FROM t JOIN e ON t.b = e.a)
SELECT d.doc_id, coalesce(size, 0) AS n_shingles, least(d.doc_id, (SELECT min(b) FROM t WHERE t.a = d.doc_id)) AS component_id FROM d LEFT JOIN n ON d.doc_id = n.doc_id"""
