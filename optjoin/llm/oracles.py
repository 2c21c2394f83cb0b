"""DuckDB SQL for the queries that SQL can express, from their definitions and not from their code."""

from .lm import ALPHA
from .quality import RULES, STOP_WORDS

_WORDS = r"list_filter(regexp_split_to_array(coalesce(text, ''), '[\x20\x09-\x0D]+'), lambda x: x <> '')"

OP2 = """
WITH d AS (SELECT doc_id, hex(encode(coalesce(text, ''))) AS x FROM documents),
u AS (SELECT doc_id, base, substr(x, 2 * base + 1, 610) AS y FROM (SELECT doc_id, x, unnest(range(0, length(x) // 2 - 49, 256)) AS base FROM d)),
v AS (SELECT doc_id, base + i AS p, substr(y, 2 * i + 1, 100) AS s FROM (SELECT doc_id, base, y, unnest(range(0, length(y) // 2 - 49)) AS i FROM u)),
m AS (SELECT s, min(doc_id) AS least FROM v GROUP BY s HAVING count(*) > 1),
r AS (SELECT v.doc_id, p, lag(p) OVER (PARTITION BY v.doc_id ORDER BY p) AS before FROM v JOIN m USING (s) WHERE m.least < v.doc_id),
k AS (SELECT doc_id, p, count(*) FILTER (before IS NULL OR p > before + 50) OVER (PARTITION BY doc_id ORDER BY p) AS span FROM r),
n AS (SELECT doc_id, min(p) AS a, max(p) + 50 AS b FROM k GROUP BY doc_id, span),
c AS (SELECT doc_id, list(a ORDER BY a) AS begins, [0] || list(b ORDER BY a) AS ends, sum(b - a) AS n_removed, count(*) AS n_spans FROM n GROUP BY doc_id),
w AS (SELECT d.doc_id, x, coalesce(begins, []) || [length(x) // 2] AS begins, coalesce(ends, [0]) AS ends, coalesce(n_removed, 0) AS n_removed, coalesce(n_spans, 0) AS n_spans FROM d LEFT JOIN c USING (doc_id))
SELECT doc_id, (length(x) // 2)::BIGINT AS n_bytes, n_removed::BIGINT AS n_removed, n_spans::BIGINT AS n_spans,
  sha256(unhex(array_to_string(list_transform(range(1, len(ends) + 1), lambda j: substr(x, 2 * ends[j] + 1, 2 * (begins[j] - ends[j]))), ''))) AS kept_sha256 FROM w
"""

OP4 = rf"""
WITH d AS (SELECT doc_id, {_WORDS} AS w FROM documents),
v AS (SELECT doc_id, p, array_to_string(w[p:p + 49], ' ') AS s FROM (SELECT doc_id, w, unnest(range(1, len(w) - 48)) AS p FROM d)),
m AS (SELECT s, min(doc_id) AS least FROM v GROUP BY s HAVING count(*) > 1),
r AS (SELECT v.doc_id, v.p FROM v JOIN m USING (s) WHERE m.least < v.doc_id),
gone AS (SELECT DISTINCT doc_id, unnest(range(p, p + 50)) AS i FROM r),
e AS (SELECT doc_id, unnest(w) AS word, unnest(range(1, len(w) + 1)) AS i FROM d),
k AS (SELECT e.doc_id, count(*) FILTER (gone.i IS NOT NULL) AS n, coalesce(string_agg(e.word, ' ' ORDER BY e.i) FILTER (gone.i IS NULL), '') AS kept
  FROM e LEFT JOIN gone ON e.doc_id = gone.doc_id AND e.i = gone.i GROUP BY e.doc_id)
SELECT d.doc_id, len(d.w)::BIGINT AS n_words, coalesce(k.n, 0)::BIGINT AS n_removed, sha256(coalesce(k.kept, '')) AS kept_sha256 FROM d LEFT JOIN k USING (doc_id)
"""

_STOPS = ", ".join(f"'{x}'" for x in sorted({*STOP_WORDS}))
_VERDICT = " AND ".join(f"({r.denominator} = 0 OR ({r.numerator} >= {r.low}::DOUBLE * {r.denominator} AND {r.numerator} <= {r.high}::DOUBLE * {r.denominator}))" for r in RULES)

OP7 = rf"""
WITH d AS (SELECT doc_id, coalesce(text, '') AS text FROM documents),
p AS (SELECT doc_id, text, {_WORDS} AS w, list_filter(string_split(text, chr(10)), lambda x: regexp_matches(x, '[^\x20\x09-\x0D]')) AS l FROM d),
v AS (SELECT doc_id, i, array_to_string(w[i:i + 7], ' ') AS s FROM (SELECT doc_id, w, unnest(range(1, len(w) - 6)) AS i FROM p)),
r AS (SELECT doc_id, i FROM v QUALIFY count(*) OVER (PARTITION BY doc_id, s) > 1),
c AS (SELECT doc_id, count(DISTINCT j) AS n FROM (SELECT doc_id, unnest(range(i, i + 8)) AS j FROM r) GROUP BY doc_id),
m AS (SELECT p.doc_id, len(w)::BIGINT AS n_words, length(array_to_string(w, ''))::BIGINT AS word_chars,
  length(regexp_replace(text, '[^#*$%&|<>]', '', 'g'))::BIGINT AS n_symbols, (len(l) - len(list_distinct(l)))::BIGINT AS n_dup_lines,
  coalesce(c.n, 0)::BIGINT AS n_repeat_words, len(l) AS n_lines, len(list_filter(w, lambda x: x IN ({_STOPS}))) AS n_stop_words,
  len(list_filter(w, lambda x: regexp_matches(x, '\p{{L}}'))) AS n_letter_words,
  len(list_filter(l, lambda x: ends_with(x, '...') OR ends_with(x, '…'))) AS n_ellipsis_lines,
  len(list_filter(l, lambda x: starts_with(x, '- ') OR starts_with(x, '* ') OR starts_with(x, '• '))) AS n_bullet_lines
  FROM p LEFT JOIN c USING (doc_id)),
b AS (SELECT *, n_words < 20 OR 100 * n_repeat_words > 30 * n_words AS base_failed FROM m)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, NOT base_failed AND {_VERDICT} AS kept FROM b
"""

OP1 = """
WITH d AS (SELECT page_id, coalesce(html, '') AS html FROM pages), h AS (SELECT *, sha1(html) AS x FROM d),
m AS (SELECT x, min(page_id) AS least FROM h GROUP BY x),
b AS (SELECT h.*, m.least, row_number() OVER (PARTITION BY h.x ORDER BY page_id) AS nth FROM h JOIN m USING (x))
SELECT page_id, octet_length(encode(html))::BIGINT AS payload_bytes,
  array_to_string(list_transform(range(0, 32), lambda i: substr('ABCDEFGHIJKLMNOPQRSTUVWXYZ234567', 1 + ((('0x' || substr(x, 5 * (i // 4) + 1, 5))::BIGINT >> (15 - 5 * (i % 4))) & 31)::BIGINT, 1)), '') AS payload_digest,
  CASE WHEN nth = 1 THEN 'response' ELSE 'revisit' END AS record_type, CASE WHEN nth > 1 THEN least END AS refers_to FROM b
"""

OP5 = rf"""
WITH d AS (SELECT doc_id, {_WORDS} AS w FROM documents),
t AS (SELECT doc_id, i, w[i] AS a, w[i + 1] AS b, w[i + 2] AS c FROM (SELECT doc_id, w, unnest(range(1, len(w) + 1)) AS i FROM d)),
o AS (SELECT doc_id, i, count(*) OVER () - count(*) OVER (PARTITION BY doc_id) AS other_words,
  count(*) OVER (PARTITION BY a) - count(*) OVER (PARTITION BY doc_id, a) AS o1,
  CASE WHEN b IS NOT NULL THEN count(*) OVER (PARTITION BY a, b) - count(*) OVER (PARTITION BY doc_id, a, b) END AS o2,
  CASE WHEN c IS NOT NULL THEN count(*) OVER (PARTITION BY a, b, c) - count(*) OVER (PARTITION BY doc_id, a, b, c) END AS o3 FROM t),
e AS (SELECT *, lag(o1) OVER v AS word_before, lag(o2) OVER v AS pair, lag(o2, 2) OVER v AS pair_before, lag(o3, 2) OVER v AS triple FROM o WINDOW v AS (PARTITION BY doc_id ORDER BY i)),
s AS (SELECT doc_id, sum(ln(CASE WHEN triple > 0 THEN triple::DOUBLE / pair_before WHEN pair > 0 THEN {ALPHA}::DOUBLE ** least(i - 2, 1) * pair / word_before
  ELSE {ALPHA}::DOUBLE ** least(i - 1, 2) * greatest(o1, 0.5::DOUBLE) / greatest(other_words, 1) END)) AS total FROM e GROUP BY doc_id)
SELECT d.doc_id, len(d.w)::BIGINT AS n_words, round(coalesce(s.total, 0::DOUBLE), 4) AS log_score, CASE WHEN len(d.w) > 0 THEN round(exp(-s.total / len(d.w)), 2) END AS perplexity FROM d LEFT JOIN s USING (doc_id)
"""

ORACLES: dict[str, str] = {"op1_warc": OP1, "op2_suffix_array_dedup": OP2, "op4_substring_dedup": OP4, "op5_lm_scoring": OP5, "op7_quality_rules": OP7}
