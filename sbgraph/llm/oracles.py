"""DuckDB SQL for the operators whose results SQL can express."""

from __future__ import annotations

from .quality_rules import BASE, RULES, STANDARD

_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
_SPACED = r"[^\x20\x09-\x0D]+"
_ALNUM = r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+"
_BITS = " | ".join(f"(CASE WHEN {r.fails} THEN {1 << k} ELSE 0 END)" for k, r in enumerate(RULES))

QUALITY = rf"""
WITH d AS (SELECT row_number() OVER () AS r, doc_id, coalesce(text, '') AS t FROM documents),
w AS (SELECT r, doc_id, t, regexp_extract_all(t, '{_SPACED}') AS ws, list_filter(string_split(t, chr(10)), lambda x: regexp_matches(x, '{_SPACED}')) AS ls FROM d),
p AS (SELECT r, i, list_slice(ws, i, i + 7) AS win FROM w, unnest(range(1, len(ws) - 6)) u(i) WHERE len(ws) >= 8),
q AS (SELECT r, i FROM (SELECT r, i, count(*) OVER (PARTITION BY r, win) AS c FROM p) WHERE c > 1),
n AS (SELECT r, sum(step) AS n_repeat_words FROM (SELECT r, least(8, i - coalesce(lag(i) OVER (PARTITION BY r ORDER BY i), i - 8)) AS step FROM q) GROUP BY r),
m AS (SELECT w.doc_id, len(ws) AS n_words, coalesce(list_sum(list_transform(ws, lambda x: length(x))), 0) AS word_chars, len(regexp_extract_all(t, '[#*$%&|<>]')) AS n_symbols, len(ls) - len(list_distinct(ls)) AS n_dup_lines, len(ls) AS n_lines, coalesce(n.n_repeat_words, 0) AS n_repeat_words,
len(regexp_extract_all(t, '\p{{Lu}}')) AS n_upper, len(regexp_extract_all(t, '[!?=_~^]')) AS n_marks, len(regexp_extract_all(t, '\p{{L}}')) AS n_letters, len(list_filter(range(2, len(ws) + 1), lambda i: ws[i] = ws[i - 1])) AS n_same_next FROM w LEFT JOIN n ON n.r = w.r),
f AS (SELECT *, {_BITS} AS failed FROM m)
SELECT doc_id, CAST(n_words AS BIGINT) AS n_words, CAST(word_chars AS BIGINT) AS word_chars, CAST(n_symbols AS BIGINT) AS n_symbols, CAST(n_dup_lines AS BIGINT) AS n_dup_lines, CAST(n_repeat_words AS BIGINT) AS n_repeat_words, failed & {BASE.mask} <> 0 AS base_failed, failed & {STANDARD.mask} = 0 AS kept, CAST(failed AS BIGINT) AS failed FROM f
"""

_BY_RULE = " UNION ALL ".join(f"SELECT '{r.name}' AS rule, CAST(count(*) FILTER (failed & {1 << k} <> 0) AS BIGINT) AS fails, CAST(count(*) FILTER (failed = {1 << k}) AS BIGINT) AS fails_alone, count(*) AS docs FROM b" for k, r in enumerate(RULES))
ABLATION = f"WITH b AS ({QUALITY}) {_BY_RULE}"

NGRAM_JOIN = rf"""
WITH RECURSIVE d AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), '{_UPPER}', '{_LOWER}'), '{_SPACED}') AS ws FROM documents),
s AS (SELECT DISTINCT doc_id, CASE WHEN len(ws) >= 5 THEN list_slice(ws, i, i + 4) ELSE ws END AS g FROM d, unnest(range(1, greatest(2, len(ws) - 3))) u(i) WHERE len(ws) > 0),
n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
o AS (SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS k FROM s a JOIN s b ON a.g = b.g AND a.doc_id < b.doc_id GROUP BY 1, 2),
l AS (SELECT a, b FROM o JOIN n x ON x.doc_id = a JOIN n y ON y.doc_id = b WHERE 100 * k >= 75 * (x.n + y.n - k)),
e AS (SELECT a, b FROM l UNION ALL SELECT b, a FROM l),
reach AS (SELECT a AS root, a AS node FROM e UNION SELECT r.root, e.b FROM reach r JOIN e ON e.a = r.node),
c AS (SELECT node, min(root) AS c FROM reach GROUP BY node),
m AS (SELECT a, count(*) AS k FROM e GROUP BY a)
SELECT d.doc_id, coalesce(n.n, 0) AS n_shingles, coalesce(c.c, d.doc_id) AS component_id, coalesce(m.k, 0) AS n_links FROM d LEFT JOIN n ON n.doc_id = d.doc_id LEFT JOIN c ON c.node = d.doc_id LEFT JOIN m ON m.a = d.doc_id
"""

_WORDS = "regexp_extract_all(translate(coalesce(text, ''), '{0}', '{1}'), '{2}')".format(_UPPER, _LOWER, _ALNUM)

DECONTAMINATION = rf"""
WITH b AS (SELECT item_id, {_WORDS} AS ws FROM benchmark),
k AS (SELECT DISTINCT item_id, list_slice(ws, i, i + least(10, len(ws)) - 1) AS win, least(10, len(ws)) AS n FROM b, unnest(range(1, len(ws) - least(10, len(ws)) + 2)) u(i) WHERE len(ws) > 0),
d AS (SELECT row_number() OVER () AS r, doc_id, {_WORDS} AS ws FROM documents),
p AS (SELECT r, i, z.n, list_slice(ws, i, i + z.n - 1) AS win FROM d, (SELECT DISTINCT n FROM k) z, unnest(range(1, len(ws) + 1)) u(i) WHERE i + z.n - 1 <= len(ws)),
h AS (SELECT r, i, p.n, item_id FROM p JOIN k ON k.n = p.n AND k.win = p.win),
c AS (SELECT r, count(DISTINCT j) AS n_hit FROM h, unnest(range(i, i + n)) u(j) GROUP BY r),
t AS (SELECT r, count(*) AS n_items, string_agg(x, ',' ORDER BY x) AS ids FROM (SELECT DISTINCT r, CAST(item_id AS VARCHAR) AS x FROM h) GROUP BY r)
SELECT d.doc_id, CAST(len(ws) AS BIGINT) AS n_words, coalesce(n_hit, 0) AS n_hit, coalesce(n_items, 0) AS n_items, sha256(coalesce(ids, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated FROM d LEFT JOIN c ON c.r = d.r LEFT JOIN t ON t.r = d.r
"""

SECRETS = r"""
SELECT doc_id, CAST(len(list_filter(regexp_extract_all(t, '(?i)(password|passwd|secret|token|api_?key)["'']?\x20*[:=]\x20*["'']?([A-Za-z0-9+/_.=-]+)', 2), lambda x: length(x) >= 6)) AS BIGINT) AS n_assign,
CAST(len(list_filter(regexp_extract_all(t, 'AKIA[A-Z0-9]+'), lambda x: length(x) >= 20)) AS BIGINT) AS n_access, CAST(len(list_filter(regexp_extract_all(t, '[0-9a-f]+'), lambda x: length(x) >= 24)) AS BIGINT) AS n_hex
FROM (SELECT doc_id, coalesce(text, '') AS t FROM documents)
"""

#: A source's share is capped in the order of cap over weight, so sums before it in that order decide.
TARGETS = rf"""
WITH s AS (SELECT source, CAST(sum(len(regexp_extract_all(coalesce(text, ''), '{_SPACED}'))) AS BIGINT) AS n FROM documents GROUP BY source),
w AS (SELECT n, (row_number() OVER (ORDER BY source NULLS LAST) - 1) % 3 + 1 AS w FROM s),
c AS (SELECT *, sum(n) OVER () AS whole, sum(w) OVER () AS weights, coalesce(sum(3 * n) OVER o, 0) AS spent, coalesce(sum(w) OVER o, 0) AS gone FROM w WINDOW o AS (ORDER BY n / w ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)),
k AS (SELECT *, (whole - spent) / (weights - gone) * w > 3 * n AS capped FROM c),
l AS (SELECT n, w, capped, (whole - sum(CASE WHEN capped THEN 3 * n ELSE 0 END) OVER ()) / sum(CASE WHEN capped THEN 0 ELSE w END) OVER () AS level FROM k)
SELECT n AS source_size, round(CASE WHEN capped THEN 3.0 * n ELSE level * w END, 3) AS target, true AS near FROM l
"""

SQL = {"op1_quality_rules": QUALITY, "op2_ngram_join": NGRAM_JOIN, "op7_decontamination": DECONTAMINATION, "quality_ablation": ABLATION, "secret_base_counts": SECRETS, "mixing_targets": TARGETS}
