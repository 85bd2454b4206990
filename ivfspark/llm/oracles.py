"""DuckDB SQL for the corpus queries that SQL can express."""

ORACLES: dict[str, str] = {}

ORACLES["op8_host_quality"] = r"""
WITH d AS (
  SELECT row_number() OVER () AS rid, doc_id, source, coalesce(text, '') AS body,
         regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS words FROM documents),
win AS (
  SELECT rid, i, words[i] AS a, words[i + 1] AS b, words[i + 2] AS c
  FROM (SELECT rid, words, unnest(range(1, len(words) - 1)) AS i FROM d WHERE len(words) >= 3)),
rep AS (
  SELECT rid, i FROM (SELECT rid, i, count(*) OVER (PARTITION BY rid, a, b, c) AS n FROM win) WHERE n > 1),
cov AS (
  SELECT rid, count(DISTINCT p) AS n_repeat_words FROM (SELECT rid, i + unnest([0, 1, 2]) AS p FROM rep) GROUP BY rid),
lin AS (
  SELECT rid, l FROM (SELECT rid, unnest(string_split(body, chr(10))) AS l FROM d)
  WHERE regexp_matches(l, '[^\x20\x09-\x0D]')),
dup AS (SELECT rid, count(*) AS n_lines, count(*) - count(DISTINCT l) AS n_dup_lines FROM lin GROUP BY rid),
m AS (
  SELECT d.rid, doc_id, source, len(words) AS n_words, length(array_to_string(words, '')) AS word_chars,
         length(body) - length(regexp_replace(body, '[#*$%&|<>]', '', 'g')) AS n_symbols,
         coalesce(n_lines, 0) AS n_lines, coalesce(n_dup_lines, 0) AS n_dup_lines,
         coalesce(n_repeat_words, 0) AS n_repeat_words
  FROM d LEFT JOIN dup USING (rid) LEFT JOIN cov USING (rid)),
f AS (
  SELECT *, n_words < 50 OR 100 * n_repeat_words > 50 * n_words AS base_failed,
    CAST(10 * n_symbols > n_words AS INT) + CAST(10 * n_symbols > 3 * n_words AS INT)
    + CAST(10 * n_dup_lines > 3 * n_lines AS INT)
    + CAST(word_chars < 3 * n_words OR word_chars > 12 * n_words AS INT)
    + CAST(10 * n_repeat_words > 3 * n_words AS INT) AS n_soft FROM m),
h AS (SELECT source, count(*) AS n, sum(CAST(base_failed OR n_soft > 0 AS INT)) AS k FROM f GROUP BY source),
pr AS (SELECT avg(k / n) AS m, var_pop(k / n) AS v FROM h),
st AS (SELECT m, CASE WHEN v > 0 AND m * (1 - m) > v THEN m * (1 - m) / v - 1 ELSE 1 END AS s FROM pr),
r AS (SELECT source, (k + s * m) / (n + s) AS rate FROM h, st)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed,
       NOT base_failed AND n_soft <= CASE WHEN rate > 0.5 THEN 0 ELSE 1 END AS kept
FROM f JOIN r ON f.source IS NOT DISTINCT FROM r.source
"""

ORACLES["op6_chat_format"] = r"""
WITH t AS (
  SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
  UNION ALL SELECT -7, 0, 'user', '\### Assistant: </turn> ok'
  UNION ALL SELECT -7, 1, 'assistant', '\### Assistant: </turn> ok'),
e AS (
  SELECT *, length(replace(replace(text, '\', '\\'), '<|', '<\|')) + length(role) + length('<|turn|>') + 1
            + length('<|end|>') + 1 AS n FROM t)
SELECT conv_id, count(*) AS n_turns,
  sha256(string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn, role, text)) AS turns_sha256,
  CAST(coalesce(sum(length(text)) FILTER (role = 'assistant'), 0) AS BIGINT) AS loss_chars,
  sha256(coalesce(string_agg(text, '' ORDER BY turn, role, text) FILTER (role = 'assistant'), '')) AS loss_sha256,
  CAST(sum(n) AS BIGINT) AS formatted_chars
FROM e GROUP BY conv_id
"""

ORACLES["op9_line_dedup"] = r"""
WITH d AS (SELECT row_number() OVER () AS rid, doc_id, coalesce(text, '') AS body FROM documents),
l AS (
  SELECT rid, doc_id, i, string_split(body, chr(10))[i] AS line
  FROM (SELECT *, unnest(range(1, len(string_split(body, chr(10))) + 1)) AS i FROM d)),
k AS (
  SELECT *, translate(regexp_replace(regexp_replace(line, '^[\x20\x09-\x0D]+', ''), '[\x20\x09-\x0D]+$', ''),
    'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS key FROM l),
c AS (
  SELECT key, max(doc_id) AS keeper FROM k WHERE length(key) >= 20
  GROUP BY key HAVING count(DISTINCT rid) >= 3)
SELECT doc_id, count(*) AS n_lines, count(*) FILTER (c.key IS NOT NULL AND doc_id IS DISTINCT FROM keeper) AS n_dropped,
  sha256(coalesce(string_agg(line, chr(10) ORDER BY i) FILTER (c.key IS NULL OR doc_id IS NOT DISTINCT FROM keeper), '')) AS kept_sha256
FROM k LEFT JOIN c ON k.key = c.key GROUP BY rid, doc_id
"""

ORACLES["op5_suffix_dedup"] = r"""
WITH d AS MATERIALIZED (SELECT row_number() OVER () AS rid, doc_id, encode(coalesce(text, '')) AS b FROM documents),
w AS MATERIALIZED (SELECT rid, i, md5(b[i:i + 399]) AS m FROM (SELECT rid, b, unnest(range(1, octet_length(b) - 398)) AS i FROM d WHERE octet_length(b) >= 400)),
r AS MATERIALIZED (SELECT rid, i FROM w JOIN (SELECT m FROM w GROUP BY m HAVING count(*) > 1) USING (m)),
e AS (SELECT rid, i, CASE WHEN i <= 400 + lag(i) OVER (PARTITION BY rid ORDER BY i) THEN 0 ELSE 1 END AS f FROM r),
sp AS MATERIALIZED (SELECT rid, min(i) AS a, max(i) + 399 AS z FROM (SELECT rid, i, sum(f) OVER (PARTITION BY rid ORDER BY i) AS q FROM e) GROUP BY rid, q),
st AS (SELECT rid, sum(z - a + 1)::BIGINT AS n_removed, count(*) AS n_spans, max(z) AS last FROM sp GROUP BY rid),
kp AS (SELECT rid, a AS o, hex(b[coalesce(lag(z) OVER (PARTITION BY rid ORDER BY a), 0) + 1:a - 1]) AS s FROM sp JOIN d USING (rid)
  UNION ALL SELECT rid, last + 1, hex(b[last + 1:]) FROM st JOIN d USING (rid)),
kh AS (SELECT rid, string_agg(s, '' ORDER BY o) AS s FROM kp GROUP BY rid),
ww AS MATERIALIZED (SELECT row_number() OVER () AS rid, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS w FROM documents),
wr AS MATERIALIZED (SELECT rid, i, md5(array_to_string(w[i:i + 50], ' ')) AS m FROM (SELECT rid, w, unnest(range(1, len(w) - 49)) AS i FROM ww WHERE len(w) >= 51)),
ws AS MATERIALIZED (SELECT rid, i FROM wr JOIN (SELECT m FROM wr GROUP BY m HAVING min(rid) < max(rid)) USING (m)),
wc AS (SELECT rid, sum(least(51, coalesce(nx - i, 51)))::BIGINT AS n_shared_words FROM (SELECT rid, i, lead(i) OVER (PARTITION BY rid ORDER BY i) AS nx FROM ws) GROUP BY rid)
SELECT doc_id, octet_length(b)::BIGINT AS n_bytes, coalesce(n_removed, 0) AS n_removed, coalesce(n_spans, 0) AS n_spans,
  CASE WHEN n_spans IS NULL THEN sha256(b) ELSE sha256(unhex(s)) END AS kept_sha256, coalesce(n_shared_words, 0) AS n_shared_words
FROM d LEFT JOIN st USING (rid) LEFT JOIN kh USING (rid) LEFT JOIN wc USING (rid)
"""

ORACLES["op10_decontamination"] = r"""
WITH d AS (SELECT row_number() OVER () AS rid, doc_id,
    regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM documents),
b AS (SELECT coalesce(item_id::VARCHAR, '') AS item,
    regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM benchmark),
k AS (SELECT item, w, least(len(w), 10) AS n, unnest(range(1, len(w) - least(len(w), 10) + 2)) AS i FROM b WHERE len(w) > 0),
v AS MATERIALIZED (SELECT DISTINCT item, n, array_to_string(w[i:i + n - 1], ' ') AS key FROM k),
s AS (SELECT rid, w, n, unnest(range(1, len(w) - n + 2)) AS i FROM d, (SELECT DISTINCT n FROM v) WHERE len(w) >= n),
g AS MATERIALIZED (SELECT rid, n, i, array_to_string(w[i:i + n - 1], ' ') AS key FROM s),
h AS MATERIALIZED (SELECT rid, g.n, i, item FROM g JOIN v ON g.n = v.n AND g.key = v.key),
c AS (SELECT rid, count(DISTINCT p) AS n_hit FROM (SELECT rid, unnest(range(i, i + n)) AS p FROM h) GROUP BY rid),
t AS (SELECT rid, count(*) AS n_items, string_agg(item, ',' ORDER BY item) AS items FROM (SELECT DISTINCT rid, item FROM h) GROUP BY rid)
SELECT doc_id, len(w) AS n_words, coalesce(n_hit, 0) AS n_hit, coalesce(n_items, 0) AS n_items, sha256(coalesce(items, '')) AS items_sha256, n_hit IS NOT NULL AS contaminated
FROM d LEFT JOIN c USING (rid) LEFT JOIN t USING (rid)
"""
