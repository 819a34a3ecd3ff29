"""DuckDB SQL for the corpus operators' queries that SQL can express."""

OP6 = """
WITH parts AS (
  SELECT page_id, url,
    CASE WHEN contains(url, '://') THEN translate(regexp_extract(substr(url, strpos(url, '://') + 3), '^[^/?#]*'), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') ELSE '' END AS host,
    CASE WHEN contains(url, '://') THEN regexp_extract(substr(url, strpos(url, '://') + 3), '^[^/?#]*([^?#]*)', 1) ELSE '' END AS path
  FROM pages),
rules(rule_host, rule_path, verdict) AS (VALUES
  ('com', '/', 'allow'), ('example.com', '/en/', 'block'), ('www.example.com', '/en/', 'allow'), ('net', '/es/', 'block'), ('net', '/fr/', 'block')),
fits AS (
  SELECT page_id, arg_max(rule_host || rule_path, length(rule_host || rule_path)) AS rule, arg_max(verdict, length(rule_host || rule_path)) AS verdict
  FROM parts JOIN rules ON (host = rule_host OR ends_with(host, '.' || rule_host)) AND starts_with(path, rule_path)
  GROUP BY page_id),
listed AS (SELECT DISTINCT host AS name FROM parts WHERE contains(host, '-')),
tracked AS (SELECT DISTINCT host || path AS address FROM parts WHERE regexp_matches(url, '[?&](ref|utm_source)=')),
bad AS (SELECT DISTINCT page_id FROM parts JOIN listed ON host = name OR ends_with(host, '.' || name)
  UNION SELECT page_id FROM parts JOIN tracked ON host || path = address)
SELECT p.page_id, p.host, p.path, f.rule, coalesce(f.verdict, CASE WHEN b.page_id IS NULL THEN 'allow' ELSE 'block' END) AS verdict
FROM parts p LEFT JOIN fits f ON p.page_id = f.page_id LEFT JOIN bad b ON p.page_id = b.page_id
"""

OP10 = r"""
WITH turns AS (
  SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
  UNION ALL SELECT -1, 0, 'user', '</s>[INST] ok [/INST]'
  UNION ALL SELECT -1, 1, 'assistant', '</s>[INST] ok [/INST]'),
escaped AS (
  SELECT *, length(regexp_replace(text, '([<\[])(\\*(?:SYS\]|/SYS\]|INST\]|/INST\]|ROLE\]|/ROLE\]|/TURN\]|s>|/s>))', '\1\\\2', 'g')) AS n,
    lag(role, 1, '') OVER (PARTITION BY conv_id ORDER BY turn, role, text) AS before
  FROM turns),
framed AS (
  SELECT *, n + CASE role WHEN 'system' THEN 6 + 8 WHEN 'user' THEN 7 + 9 WHEN 'assistant' THEN 4 + 6 ELSE length(role) + 26 END AS whole,
    CASE before WHEN '' THEN role IN ('system', 'user') WHEN 'system' THEN role = 'user' WHEN 'user' THEN role = 'assistant' WHEN 'assistant' THEN role = 'user' ELSE false END AS allowed
  FROM escaped)
SELECT conv_id, count(*) AS n_turns,
  sha256(string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn, role, text)) AS turns_sha256,
  coalesce(sum(length(text)) FILTER (role = 'assistant'), 0)::BIGINT AS loss_chars,
  sha256(coalesce(string_agg(text, '' ORDER BY turn, role, text) FILTER (role = 'assistant'), '')) AS loss_sha256,
  sum(whole)::BIGINT AS formatted_chars,
  bool_and(allowed) AND arg_max(role, turn) = 'assistant' AS valid
FROM framed GROUP BY conv_id
"""

#: Strings of 200 bytes by their MD5; a run of removed bytes is a row, kept bytes are joined as hexadecimal digits.
OP1 = """
WITH whole AS MATERIALIZED (
  SELECT row_number() OVER () AS r, doc_id, encode(coalesce(text, '')) AS b FROM documents),
windows AS (
  SELECT r, unnest(range(1, octet_length(b) - 198)) AS p, b FROM whole WHERE octet_length(b) >= 200),
hashed AS MATERIALIZED (SELECT r, p, md5(b[p:p + 199]) AS h FROM windows),
repeated AS (SELECT r, p FROM hashed WHERE h IN (SELECT h FROM hashed GROUP BY h HAVING count(*) > 1)),
marked AS (SELECT r, p, CASE WHEN p <= lag(p) OVER (PARTITION BY r ORDER BY p) + 200 THEN 0 ELSE 1 END AS opens FROM repeated),
numbered AS (SELECT r, p, sum(opens) OVER (PARTITION BY r ORDER BY p) AS run FROM marked),
runs AS (SELECT r, min(p) AS lo, max(p) + 199 AS hi FROM numbered GROUP BY r, run),
pieces AS (
  SELECT r, lo, hi, coalesce(lag(hi) OVER (PARTITION BY r ORDER BY lo), 0) + 1 AS since FROM runs
  UNION ALL SELECT w.r, octet_length(b) + 1, octet_length(b), coalesce(max(hi), 0) + 1 FROM whole w LEFT JOIN runs u ON w.r = u.r GROUP BY w.r, b)
SELECT w.doc_id, octet_length(w.b) AS n_bytes, sum(p.hi - p.lo + 1)::BIGINT AS n_removed, count(*) - 1 AS n_spans,
  sha256(unhex(string_agg(CASE WHEN p.lo > p.since THEN hex(w.b[p.since:p.lo - 1]) ELSE '' END, '' ORDER BY p.lo))) AS kept_sha256
FROM whole w JOIN pieces p ON w.r = p.r
GROUP BY w.r, w.doc_id, octet_length(w.b)
"""

#: Whole shingle sets and every pair that shares a shingle, by exact counts.
SIMILAR = r"""
WITH words AS MATERIALIZED (
  SELECT row_number() OVER () AS r, doc_id,
    regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS w
  FROM documents),
sets AS MATERIALIZED (
  SELECT r, doc_id, list_sort(list_distinct(CASE WHEN len(w) = 0 THEN [] WHEN len(w) < 5 THEN [md5(array_to_string(w, ' '))]
    ELSE list_transform(range(1, len(w) - 3), lambda j: md5(array_to_string(w[j:j + 4], ' '))) END)) AS s
  FROM words),
classes AS MATERIALIZED (SELECT s, min(doc_id) AS class_id, len(s) AS n FROM sets GROUP BY s),
shingles AS MATERIALIZED (SELECT class_id, n, unnest(s) AS x FROM classes),
links AS (
  SELECT a.class_id AS a, b.class_id AS b FROM shingles a JOIN shingles b ON a.x = b.x AND a.class_id < b.class_id
  WHERE 5 * least(a.n, b.n) >= 4 * greatest(a.n, b.n)
  GROUP BY a.class_id, b.class_id, a.n, b.n HAVING 5 * count(*) >= 4 * (a.n + b.n - count(*))),
counts AS (SELECT class_id, count(*) AS n_links FROM (SELECT a AS class_id FROM links UNION ALL SELECT b FROM links) GROUP BY class_id)
SELECT d.doc_id, c.class_id, coalesce(n_links, 0)::BIGINT AS n_links
FROM sets d JOIN classes c ON d.s = c.s LEFT JOIN counts ON c.class_id = counts.class_id
"""
