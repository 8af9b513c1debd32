"""DuckDB SQL for the operators that SQL can express."""

from __future__ import annotations

from spurline.llm.licenses import TEMPLATES

_TRANSLATE = "translate({0}, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"

OP2 = rf"""
WITH RECURSIVE base AS (
  SELECT page_id, url,
    {_TRANSLATE.format("coalesce(regexp_extract(url, '(?s)^.*?://([^/?#]*)', 1), '')")} AS host,
    coalesce(regexp_extract(url, '(?s)^.*?://[^/?#]*([^?#]*)', 1), '') AS path
  FROM pages),
policy(rule, says) AS (VALUES ('org/', 'allow'), ('example.org/es/', 'block'), ('example.org/en/1', 'block'), ('com/fr/', 'allow'), ('com/de/', 'block')),
fitting AS (
  SELECT b.page_id, rule, says, row_number() OVER (PARTITION BY b.page_id ORDER BY length(rule) DESC, rule) AS place
  FROM base b JOIN policy p ON (b.host = split_part(p.rule, '/', 1) OR ends_with(b.host, '.' || split_part(p.rule, '/', 1)))
    AND starts_with(b.path, substr(p.rule, strpos(p.rule, '/')))),
labels_of_hosts AS (SELECT page_id, list_reverse(string_split(host, '.')) AS ls FROM base WHERE contains(coalesce(url, ''), '://')),
segments AS (SELECT page_id, list_filter(string_split(path, '/'), lambda s: s <> '' AND NOT regexp_matches(s, '^\d+(\.\w+)?$')) AS ss FROM base WHERE contains(coalesce(url, ''), '://')),
tokens AS (
  SELECT DISTINCT page_id, token FROM (
    SELECT page_id, 'host' || (i - 1) || ':' || ls[i] AS token FROM labels_of_hosts, unnest(range(1, len(ls) + 1)) u(i)
      WHERE ls[i] <> ''
    UNION ALL SELECT page_id, 'path' || (i - 1) || ':' || ss[i] FROM segments, unnest(range(1, len(ss) + 1)) u(i)
    UNION ALL SELECT page_id, 'query:' || split_part(k, '=', 1) FROM (SELECT page_id, unnest(string_split(regexp_extract(url, '(?s)\?([^#]*)', 1), '&')) AS k FROM base WHERE contains(coalesce(url, ''), '://')) WHERE k <> ''
    UNION ALL SELECT page_id, 'scheme:' || lower(regexp_extract(url, '(?s)^([A-Za-z]+)://', 1)) FROM base WHERE contains(coalesce(url, ''), '://')
    UNION ALL SELECT page_id, 'ending:' || regexp_extract(path, '\.(\w+)$', 1) FROM base WHERE contains(coalesce(url, ''), '://'))
  WHERE NOT ends_with(token, ':')),
taught AS (SELECT page_id, says = 'block' AS blocked FROM fitting WHERE place = 1 AND page_id IN (SELECT page_id FROM tokens)),
need AS (SELECT greatest(0.005 * count(*), 5) AS least FROM taught),
t AS MATERIALIZED (SELECT page_id, token, blocked FROM tokens JOIN taught USING (page_id)),
combos(ts, page_id, blocked) AS (
  SELECT [token], page_id, blocked FROM t
  UNION ALL SELECT list_append(c.ts, t.token), c.page_id, c.blocked FROM combos c JOIN t ON t.page_id = c.page_id AND t.token > c.ts[-1]),
mined AS (SELECT ts, count(*) FILTER (blocked) * 1.0 / count(*) AS confidence FROM combos, need GROUP BY ts, least HAVING count(*) FILTER (blocked) >= least - 1e-9 AND count(*) FILTER (blocked) >= 0.8 * count(*)),
rules AS (SELECT ts, confidence FROM mined m WHERE NOT EXISTS (SELECT 1 FROM mined s WHERE len(s.ts) < len(m.ts) AND list_has_all(m.ts, s.ts) AND s.confidence >= m.confidence)),
page_tokens AS (SELECT page_id, list(token) AS have FROM tokens GROUP BY page_id),
hits AS (SELECT page_id, array_to_string(ts, ' + ') AS mined_rule, confidence, row_number() OVER (PARTITION BY page_id ORDER BY confidence DESC, array_to_string(ts, ' + ') DESC) AS place FROM page_tokens JOIN rules ON list_has_all(have, ts))
SELECT b.page_id, b.host, b.path, f.rule, coalesce(f.says, CASE WHEN h.mined_rule IS NOT NULL THEN 'block' ELSE 'allow' END) AS verdict, h.mined_rule, CAST(h.confidence AS DOUBLE) AS confidence
FROM base b LEFT JOIN fitting f ON f.page_id = b.page_id AND f.place = 1 LEFT JOIN hits h ON h.page_id = b.page_id AND h.place = 1
"""

_MARK = r"""regexp_replace(regexp_replace({0}, '(<)(\\*/?s>|\\*\|[^|<>\[]*\|>)', '\1\\\2', 'g'), '(\[)(\\*/?INST\])', '\1\\\2', 'g')"""

OP3 = rf"""
WITH turns AS (
  SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
  UNION ALL VALUES (-7, 0, 'user', '</s>[INST] ok [/INST]'), (-7, 1, 'assistant', '</s>[INST] ok [/INST]')),
shaped AS (SELECT *, {_MARK.format("text")} AS safe, replace(replace({_MARK.format("role")}, '\', '\\'), chr(10), '\n') AS safe_role FROM turns)
SELECT conv_id, count(*) AS n_turns,
  sha256(string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn NULLS FIRST, role, safe)) AS turns_sha256,
  CAST(coalesce(sum(length(text)) FILTER (role = 'assistant'), 0) AS BIGINT) AS loss_chars,
  sha256(coalesce(string_agg(text, '' ORDER BY turn NULLS FIRST, safe) FILTER (role = 'assistant'), '')) AS loss_sha256,
  CAST(sum(length(safe) + length(safe_role) + 17) AS BIGINT) AS formatted_chars
FROM shaped GROUP BY conv_id
"""


def _templates() -> str:
    return ", ".join("('{}', '{}')".format(k, v.replace("'", "''")) for k, v in TEMPLATES.items())


OP9 = rf"""
WITH plain AS (SELECT doc_id, row_number() OVER () AS row_no, regexp_replace(lower(text), '[^\p{{L}}\p{{N}}\n]+', ' ', 'g') AS p FROM documents),
split AS (SELECT doc_id, row_no, p, string_split(p, chr(10)) AS ls, string_split(regexp_replace(p, '\n( ?\n)+', chr(1), 'g'), chr(1)) AS ps FROM plain),
units AS (
  SELECT doc_id, row_no, 'line' AS unit, i - 1 AS unit_no, ls[i] AS t FROM split, unnest(range(1, len(ls) + 1)) u(i)
  UNION ALL SELECT doc_id, row_no, 'paragraph', i - 1, replace(ps[i], chr(10), ' ') FROM split, unnest(range(1, len(ps) + 1)) u(i) WHERE contains(ps[i], chr(10))
  UNION ALL SELECT doc_id, row_no, 'document', 0, replace(p, chr(10), ' ') FROM split WHERE len(ps) > 1),
words AS (SELECT doc_id, row_no, unit, unit_no, string_split(regexp_replace(trim(t), ' +', ' ', 'g'), ' ') AS w FROM units WHERE trim(t) <> ''),
sized AS (SELECT *, len(w) - 1 AS n FROM words WHERE len(w) BETWEEN 2 AND 300),
grams AS (SELECT doc_id, row_no, unit, unit_no, n, w[i] || ' ' || w[i + 1] AS g, count(*) AS k FROM sized, unnest(range(1, n + 1)) u(i) GROUP BY ALL),
templates(license, body) AS (VALUES {_templates()}),
template_words AS (SELECT license, list_filter(string_split(regexp_replace(lower(body), '[^0-9a-z]+', ' ', 'g'), ' '), lambda x: x <> '') AS w FROM templates),
template_grams AS (SELECT license, len(w) - 1 AS m, w[i] || ' ' || w[i + 1] AS g, count(*) AS k FROM template_words, unnest(range(1, len(w))) u(i) GROUP BY ALL),
scored AS (SELECT doc_id, row_no, unit, unit_no, license, 2.0 * sum(least(grams.k, template_grams.k)) / (n + m) AS dice FROM grams JOIN template_grams USING (g) GROUP BY doc_id, row_no, unit, unit_no, license, n, m)
SELECT doc_id, unit, unit_no, license, round(CAST(dice AS DOUBLE), 6) AS dice FROM (
  SELECT *, row_number() OVER (PARTITION BY row_no, unit, unit_no ORDER BY dice DESC, license) AS place FROM scored WHERE dice >= 0.8 - 1e-12) WHERE place = 1
"""

ORACLES = {"op2_urls": OP2, "op3_chat": OP3, "op9_licenses": OP9}
