"""SQL (DuckDB) for the training-data queries that SQL can express."""

from __future__ import annotations

from .quality import MAX_LOST, MIN_LINE_WORDS, NOTICES

WORD = r"[^\x20\x09-\x0D]+"
BLANKS = " || ".join(f"chr({c})" for c in (32, 9, 10, 11, 12, 13))
NOTICES_SQL = NOTICES.replace("'", "''")
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
ENDS = ", ".join(f"'{x}'" for x in (".", "!", "?", "…", '"', "''", "”", "’", "»", ")", ":", ";", "。", "！", "？"))

QUALITY = f"""
WITH d AS (SELECT doc_id, coalesce(text, '') AS t FROM documents),
w AS (SELECT doc_id, t, regexp_extract_all(t, '{WORD}') AS ws FROM d),
g AS (SELECT doc_id, i, count(*) OVER (PARTITION BY doc_id, s) AS n FROM (SELECT doc_id, i, array_to_string(ws[i:i + 7], ' ') AS s FROM (SELECT doc_id, ws, unnest(range(1, len(ws) - 6)) AS i FROM w))),
rep AS (SELECT doc_id, count(DISTINCT p) AS n FROM (SELECT doc_id, unnest(range(i, i + 8)) AS p FROM g WHERE n > 1) GROUP BY doc_id),
l AS (SELECT doc_id, unnest(string_split(t, chr(10))) AS line, unnest(range(len(string_split(t, chr(10))))) AS pos FROM d),
lw AS (SELECT *, regexp_extract_all(line, '{WORD}') AS ws, row_number() OVER (PARTITION BY doc_id, line ORDER BY pos) AS nth FROM l),
lm AS (SELECT doc_id, nth, len(ws) AS n, list_sum(list_transform(ws, lambda x: strlen(x))) AS bytes, len(list_filter(ws, lambda x: x IN ('|', '»', '›', '·', '•'))) AS bars,
  regexp_matches(translate(line, '{UPPER}', '{LOWER}'), '{NOTICES_SQL}') AS notice, right(ws[len(ws)], 1) IN ({ENDS}) AS ends, len(regexp_extract_all(line, '[!?#*$%&<>]')) AS marks FROM lw WHERE len(ws) > 0),
lf AS (SELECT *, (bars >= 2 AND 8 * bars >= n) OR notice OR (n >= {MIN_LINE_WORDS} AND (NOT ends OR 2 * marks > n)) AS fails FROM lm),
a AS (SELECT doc_id, sum(bytes) AS size, count_if(nth > 1) AS dup, count_if(fails) AS failed, coalesce(sum(CASE WHEN fails THEN bytes END), 0) AS lost FROM lf GROUP BY doc_id),
m AS (SELECT w.doc_id, len(ws) AS n_words, coalesce(list_sum(list_transform(ws, lambda x: length(x))), 0) AS word_chars, len(regexp_extract_all(t, '[#*$%&|<>]')) AS n_symbols, coalesce(dup, 0) AS dup, coalesce(rep.n, 0) AS rep, coalesce(size, 0) AS size, coalesce(failed, 0) AS failed, coalesce(lost, 0) AS lost
  FROM w LEFT JOIN rep ON rep.doc_id = w.doc_id LEFT JOIN a ON a.doc_id = w.doc_id)
SELECT doc_id, CAST(n_words AS BIGINT) AS n_words, CAST(word_chars AS BIGINT) AS word_chars, CAST(n_symbols AS BIGINT) AS n_symbols, CAST(dup AS BIGINT) AS n_dup_lines, CAST(rep AS BIGINT) AS n_repeat_words,
n_words < 20 OR 100 * rep > 30 * n_words AS base_failed, NOT (n_words < 20 OR 100 * rep > 30 * n_words) AND lost <= {MAX_LOST} * size AS kept, CAST(failed AS BIGINT) AS n_failed_lines, CAST(lost AS BIGINT) AS n_lost_bytes FROM m"""

CHAT = """
WITH c AS (SELECT DISTINCT conv_id AS p, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations WHERE conv_id IS NOT NULL AND turn IS NOT NULL),
la AS (SELECT p, max(turn) AS lt, arg_max(text, (turn, text)) AS answer FROM c WHERE role = 'assistant' GROUP BY p),
k AS (SELECT c.*, la.lt, coalesce(s.answer, '') AS stale FROM c JOIN la ON la.p = c.p LEFT JOIN la s ON s.p = xor(c.p, 1) WHERE turn <= la.lt),
t AS (SELECT DISTINCT * FROM (SELECT p, turn, role, text, 'chosen' AS side FROM k UNION ALL SELECT p, turn, role, CASE WHEN turn = lt AND role = 'assistant' THEN stale ELSE text END, 'rejected' FROM k)),
df AS (SELECT p, min(turn) AS split FROM (SELECT p, turn FROM (SELECT p, turn, list(role || chr(0) || text ORDER BY role, text) FILTER (side = 'chosen') AS a, list(role || chr(0) || text ORDER BY role, text) FILTER (side = 'rejected') AS b FROM t GROUP BY p, turn) WHERE a IS DISTINCT FROM b) GROUP BY p),
m AS (SELECT t.*, CASE WHEN split IS NULL OR turn < split THEN 'prompt' ELSE side END AS part FROM t LEFT JOIN df USING (p) WHERE side = 'chosen' OR turn >= split),
r AS (SELECT p, part, turn // 256 AS segment, turn, role, text, '<|' || role || '|>' || chr(10) || text || '<|end|>' || chr(10) AS shown, length('<|' || role || '|>' || chr(10)) AS head FROM m),
o AS (SELECT *, sum(length(shown)) OVER (PARTITION BY p, part, segment ORDER BY turn, role, text) AS upto FROM r)
SELECT p AS pair_id, part, segment, count(*) AS n_turns, string_agg(shown, '' ORDER BY turn, role, text) AS text,
coalesce(string_agg(CASE WHEN part <> 'prompt' AND role = 'assistant' THEN CAST(CAST(upto - length(shown) + head AS BIGINT) AS VARCHAR) || '-' || CAST(CAST(upto AS BIGINT) AS VARCHAR) END, ',' ORDER BY turn, role, text), '') AS loss_spans FROM o GROUP BY p, part, segment"""

SEARCH = """
WITH v AS (SELECT vec_id, list_transform(embedding, lambda x: floor(256 * CAST(x AS DOUBLE))) AS x FROM embeddings
  WHERE vec_id IS NOT NULL AND embedding IS NOT NULL AND len(embedding) > 0 AND len(list_filter(embedding, lambda x: x IS NULL OR isnan(x) OR isinf(x))) = 0),
s AS (SELECT q.vec_id AS q, c.vec_id AS k, CAST(list_dot_product(q.x, c.x) AS BIGINT) AS score FROM v q JOIN v c ON q.vec_id % 50 = 0 AND c.vec_id <> q.vec_id)
SELECT q AS query_id, CAST(rn AS INTEGER) AS rank, k AS vec_id, score FROM (SELECT *, row_number() OVER (PARTITION BY q ORDER BY score DESC, k) AS rn FROM s) WHERE rn <= 5"""

# texts are cut into pieces of 400 bytes and the 49 that follow, so that no function sees a long string;
# two 64-bit hashes stand for a window, and flagged windows are merged to spans
SPANS = """
WITH d AS (SELECT doc_id, hex(encode(coalesce(text, ''))) AS h FROM documents),
c AS (SELECT doc_id, j, substr(h, 800 * j + 1, 898) AS p FROM (SELECT *, unnest(range((strlen(h) + 799) // 800)) AS j FROM d)),
b AS (SELECT doc_id, 400 * j + i AS i, hash(w) AS w1, hash(w || '#') AS w2 FROM (SELECT doc_id, j, i, substr(p, 2 * i + 1, 100) AS w FROM (SELECT doc_id, j, p, unnest(range(least(400, strlen(p) // 2 - 49))) AS i FROM c WHERE strlen(p) >= 100))),
f AS (SELECT w1, w2, min(doc_id) AS m FROM b GROUP BY w1, w2 HAVING min(doc_id) < max(doc_id)),
g AS (SELECT DISTINCT b.doc_id, i FROM b JOIN f ON f.w1 = b.w1 AND f.w2 = b.w2 WHERE f.m < b.doc_id),
r AS (SELECT doc_id, i, CASE WHEN i - lag(i) OVER (PARTITION BY doc_id ORDER BY i) <= 50 THEN 0 ELSE 1 END AS n FROM g),
s AS (SELECT doc_id, min(i) AS a, max(i) + 50 AS z FROM (SELECT *, sum(n) OVER (PARTITION BY doc_id ORDER BY i) AS run FROM r) GROUP BY doc_id, run),
k AS (SELECT doc_id, a, z, lead(a) OVER (PARTITION BY doc_id ORDER BY a) AS next, row_number() OVER (PARTITION BY doc_id ORDER BY a) AS nth FROM s),
a AS (SELECT d.doc_id, any_value(h) AS h, sum(z - a) AS n_removed, count(*) AS n_spans, string_agg(CASE WHEN nth = 1 THEN substr(h, 1, 2 * a) ELSE '' END || substr(h, 2 * z + 1, 2 * (coalesce(next, strlen(h) // 2) - z)), '' ORDER BY a) AS kept FROM d JOIN k ON k.doc_id = d.doc_id GROUP BY d.doc_id)
SELECT d.doc_id, strlen(d.h) // 2 AS n_bytes, CAST(coalesce(n_removed, 0) AS BIGINT) AS n_removed, CAST(coalesce(n_spans, 0) AS BIGINT) AS n_spans, sha256(unhex(coalesce(kept, d.h))) AS kept_sha256 FROM d LEFT JOIN a USING (doc_id)"""

LINES = f"""
WITH d AS (SELECT doc_id, string_split(coalesce(text, ''), chr(10)) AS ls FROM documents),
l AS (SELECT doc_id, unnest(ls) AS line, unnest(range(len(ls))) AS pos FROM d),
k AS (SELECT *, translate(trim(line, {BLANKS}), '{UPPER}', '{LOWER}') AS key FROM l),
f AS (SELECT key, min(doc_id) AS m FROM k WHERE length(key) >= 10 GROUP BY key HAVING count(DISTINCT doc_id) > 1),
g AS (SELECT doc_id, pos, line, coalesce(f.m < doc_id, false) AS gone FROM k LEFT JOIN f ON f.key = k.key)
SELECT doc_id, count(*) AS n_lines, CAST(count_if(gone) AS BIGINT) AS n_dropped, sha256(coalesce(string_agg(CASE WHEN NOT gone THEN line END, chr(10) ORDER BY pos), '')) AS kept_sha256 FROM g GROUP BY doc_id"""

WINDOWS = f"""
WITH d AS (SELECT doc_id, regexp_extract_all(coalesce(text, ''), '{WORD}') AS ws FROM documents),
b AS (SELECT doc_id, i, ws[i] AS c, CASE WHEN i + 19 <= len(ws) THEN array_to_string(ws[i:i + 19], ' ') END AS w FROM (SELECT *, unnest(range(1, len(ws) + 1)) AS i FROM d)),
g AS (SELECT doc_id, i, c, CASE WHEN w IS NOT NULL AND row_number() OVER (PARTITION BY w ORDER BY doc_id, i) > 1 THEN 1 ELSE 0 END AS flag FROM b),
r AS (SELECT *, max(flag) OVER (PARTITION BY doc_id ORDER BY i ROWS BETWEEN 19 PRECEDING AND CURRENT ROW) AS gone FROM g),
a AS (SELECT doc_id, sum(gone) AS n_removed, string_agg(CASE WHEN gone = 0 THEN c END, ' ' ORDER BY i) AS kept FROM r GROUP BY doc_id)
SELECT doc_id, CAST(len(ws) AS BIGINT) AS n_words, CAST(coalesce(n_removed, 0) AS BIGINT) AS n_removed, sha256(coalesce(kept, '')) AS kept_sha256 FROM d LEFT JOIN a USING (doc_id)"""

ORACLES = {
    "op3_line_quality": QUALITY,
    "op4_chat_preferences": CHAT,
    "op5_top_k": SEARCH,
    "op6_suffix_dedup": SPANS,
    "op8_line_dedup": LINES,
    "op10_window_dedup": WINDOWS,
}
