"""DuckDB SQL of the queries that SQL can express."""

from __future__ import annotations

LEDGER = r"""
WITH w AS (
  SELECT doc_id, coalesce(text, '') AS t, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS ws FROM documents
), win AS (
  SELECT doc_id, i, array_to_string(ws[i:i+7], ' ') AS k
  FROM (SELECT doc_id, ws, unnest(range(1, len(ws) - 6)) AS i FROM w)
), rep AS (
  SELECT doc_id, i FROM (SELECT doc_id, i, count(*) OVER (PARTITION BY doc_id, k) AS c FROM win) WHERE c > 1
), cov AS (
  SELECT doc_id, count(DISTINCT i + j) AS n FROM rep, range(0, 8) AS r(j) GROUP BY doc_id
), ln AS (
  SELECT doc_id, count(*) AS n, count(DISTINCT l) AS d
  FROM (SELECT doc_id, unnest(string_split(t, chr(10))) AS l FROM w) WHERE regexp_matches(l, '[^\x20\x09-\x0D]') GROUP BY doc_id
), m AS (
  SELECT w.doc_id, len(ws)::BIGINT AS n_words, length(array_to_string(ws, ''))::BIGINT AS word_chars,
    (length(t) - length(regexp_replace(t, '[#*$%&|<>]', '', 'g')))::BIGINT AS n_symbols,
    coalesce(ln.n, 0)::BIGINT AS n_lines, coalesce(ln.n - ln.d, 0)::BIGINT AS n_dup_lines, coalesce(cov.n, 0)::BIGINT AS n_repeat_words
  FROM w LEFT JOIN ln USING (doc_id) LEFT JOIN cov USING (doc_id)
), b AS (
  SELECT *, (n_words < 20)::INT AS b0, (100 * n_repeat_words > 30 * n_words)::INT AS b1, (100 * n_symbols > 15 * word_chars)::INT AS b2,
    (n_lines >= 4 AND 100 * n_dup_lines > 50 * n_lines)::INT AS b3, (word_chars < 2 * n_words OR word_chars > 25 * n_words)::INT AS b4,
    (100 * n_symbols > 40 * n_words)::INT AS b5 FROM m
)
"""
QUALITY = LEDGER + """
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, b0 + b1 > 0 AS base_failed, b0 + b1 = 0 AS kept_v1,
  b0 + b1 + b2 = 0 AND b3 + b4 + b5 < 2 AS kept, (b0 + 2 * b1 + 4 * b2 + 8 * b3 + 16 * b4 + 32 * b5)::BIGINT AS fail_bits FROM b
"""
ABLATION = LEDGER + """
, r AS (
  SELECT b0 + b1 + b2 > 0 OR b3 + b4 + b5 > 1 AS all_rules, [b0, b1, b2, b3, b4, b5] AS f,
    [b1 + b2 > 0 OR b3 + b4 + b5 > 1, b0 + b2 > 0 OR b3 + b4 + b5 > 1, b0 + b1 > 0 OR b3 + b4 + b5 > 1,
     b0 + b1 + b2 > 0 OR b4 + b5 > 1, b0 + b1 + b2 > 0 OR b3 + b5 > 1, b0 + b1 + b2 > 0 OR b3 + b4 > 1] AS less FROM b
), i AS (
  SELECT unnest(['too_short', 'repeats_itself', 'symbol_heavy', 'repeated_lines', 'word_length', 'pipe_table']) AS rule, unnest(range(1, 7)) AS k
)
SELECT count(*) AS n, count(*) FILTER (all_rules) AS rejected, rule, count(*) FILTER (f[k] = 1) AS failed, count(*) FILTER (less[k]) AS rejected_without,
  count(*) FILTER (all_rules AND NOT less[k]) AS only_by_rule FROM r, i GROUP BY rule
"""

#: The turns as a recursion over slots: at step n shard n mod 16 takes the first slot of its order that is free.
SHARDING = """
WITH RECURSIVE s AS (
  SELECT i::INT AS i, 'shard-' || lpad(i::VARCHAR, 3, '0') AS name FROM range(0, 16) AS r(i)
), p AS (
  SELECT i, ('0x' || substr(md5(name || '/offset'), 1, 8))::BIGINT % 1601 AS o, ('0x' || substr(md5(name || '/step'), 1, 8))::BIGINT % 1600 + 1 AS d FROM s
), orders AS (
  SELECT i, list((o + d * j) % 1601 ORDER BY j) AS pref FROM p, range(0, 1601) AS r(j) GROUP BY i
), fill AS (
  SELECT -1 AS n, -1::BIGINT AS slot, []::BIGINT[] AS taken
  UNION ALL
  SELECT f.n + 1, x.slot, list_append(f.taken, x.slot)
  FROM fill f, LATERAL (SELECT list_filter(pref, lambda v: NOT list_contains(f.taken, v))[1] AS slot FROM orders WHERE i = (f.n + 1) % 16) x
  WHERE f.n < 1600
)
SELECT doc_id, source, k.slot::INT AS slot, (f.n % 16)::INT AS shard
FROM (SELECT doc_id, source, ('0x' || substr(md5(coalesce(doc_id::VARCHAR, 'null')), 1, 8))::BIGINT % 1601 AS slot FROM documents) k JOIN fill f USING (slot)
"""

SUBSTRING = r"""
WITH w AS (
  SELECT doc_id, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS ws FROM documents
), win AS (
  SELECT doc_id, i, array_to_string(ws[i:i+12], ' ') AS k FROM (SELECT doc_id, ws, unnest(range(1, len(ws) - 11)) AS i FROM w)
), early AS (
  SELECT k, min(doc_id) AS f FROM win GROUP BY k
), gone AS (
  SELECT DISTINCT doc_id, i + j AS p FROM win JOIN early USING (k), range(0, 13) AS r(j) WHERE f < doc_id
), placed AS (
  SELECT doc_id, unnest(ws) AS word, unnest(range(1, len(ws) + 1)) AS p FROM w
), kept AS (
  SELECT doc_id, count(*) AS n, string_agg(word, ' ' ORDER BY p) AS t FROM placed ANTI JOIN gone USING (doc_id, p) GROUP BY doc_id
)
SELECT doc_id, len(ws)::BIGINT AS n_words, (len(ws) - coalesce(n, 0))::BIGINT AS n_removed, sha256(coalesce(t, '')) AS kept_sha256
FROM w LEFT JOIN kept USING (doc_id)
"""

NEAR = r"""
WITH RECURSIVE w AS (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS ws FROM documents
), sh AS MATERIALIZED (
  SELECT DISTINCT doc_id, array_to_string(ws[i:i+4], ' ') AS k FROM (SELECT doc_id, ws, unnest(range(1, greatest(len(ws) - 3, 2))) AS i FROM w WHERE len(ws) > 0)
), n AS MATERIALIZED (
  SELECT doc_id, count(*) AS n FROM sh GROUP BY doc_id
), link AS MATERIALIZED (
  SELECT p.a, p.b FROM (SELECT x.doc_id AS a, y.doc_id AS b, count(*) AS c FROM sh x JOIN sh y ON x.k = y.k AND x.doc_id <> y.doc_id GROUP BY 1, 2) p
  JOIN n na ON na.doc_id = p.a JOIN n nb ON nb.doc_id = p.b WHERE 100 * c >= 85 * (na.n + nb.n - c)
), reach AS (
  SELECT doc_id AS a, doc_id AS b FROM documents UNION SELECT r.a, l.b FROM reach r JOIN link l ON l.a = r.b
)
SELECT d.doc_id, coalesce(n.n, 0)::BIGINT AS n_shingles, r.c AS component_id, r.c = d.doc_id AS kept
FROM documents d LEFT JOIN n USING (doc_id) JOIN (SELECT a, min(b) AS c FROM reach GROUP BY a) r ON r.a = d.doc_id
"""

ORACLES = {"op8_near_dedup": NEAR, "op3_substring": SUBSTRING, "op10_quality": QUALITY, "op2_sharding": SHARDING, "quality_ablation": ABLATION}
