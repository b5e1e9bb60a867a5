"""DuckDB twins of the operators that SQL expresses in full, for tables of a size that SQL can hold."""

from __future__ import annotations

from . import metric_tree, mixing

_AZ, _az = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
_WORD = r"[^\x20\x09-\x0D]+"

NGRAM_JOIN = f"""
WITH RECURSIVE w AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), '{_AZ}', '{_az}'), '{_WORD}') AS ws FROM documents),
s AS MATERIALIZED (SELECT DISTINCT doc_id, unnest(CASE WHEN len(ws) >= 5 THEN list_transform(range(1, len(ws) - 3), lambda i: array_to_string(ws[i:i + 4], ' '))
  WHEN len(ws) > 0 THEN [array_to_string(ws, ' ')] ELSE [] END) AS g FROM w),
n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
p AS (SELECT a.doc_id AS x, b.doc_id AS y, count(*) AS o FROM s a JOIN s b ON a.g = b.g AND a.doc_id <> b.doc_id GROUP BY 1, 2),
e AS MATERIALIZED (SELECT x, y FROM p JOIN n nx ON nx.doc_id = x JOIN n ny ON ny.doc_id = y WHERE 100 * o >= 80 * (nx.n + ny.n - o)),
r(x, y) AS (SELECT doc_id, doc_id FROM documents UNION SELECT r.x, e.y FROM r JOIN e ON e.x = r.y)
SELECT d.doc_id, CAST(coalesce(any_value(n.n), 0) AS BIGINT) AS n_shingles, min(r.y) AS component_id
FROM documents d LEFT JOIN n ON n.doc_id = d.doc_id JOIN r ON r.x = d.doc_id GROUP BY d.doc_id"""

_DIGIT = "substr('ABCDEFGHIJKLMNOPQRSTUVWXYZ234567', CAST((CAST('0x' || substr(h, 5 * i + 1, 5) AS BIGINT) >> {shift}) & 31 AS INTEGER) + 1, 1)"
WARC = f"""
WITH p AS (SELECT page_id, coalesce(html, '') AS html, sha1(coalesce(html, '')) AS h, min(page_id) OVER (PARTITION BY coalesce(html, '')) AS rep FROM pages)
SELECT page_id, CAST(strlen(html) AS BIGINT) AS payload_bytes,
  array_to_string(list_transform(range(8), lambda i: {' || '.join(_DIGIT.format(shift=s) for s in (15, 10, 5, 0))}), '') AS payload_digest,
  CASE WHEN page_id = rep THEN 'response' ELSE 'revisit' END AS record_type, CASE WHEN page_id <> rep THEN rep END AS refers_to, true AS digests_hold
FROM p"""

_UNITS = "".join(
    f"""g{k} AS (SELECT d.source, CAST(sum(size) AS BIGINT) AS big, CAST(sum(CAST(floor(size * sqrt(size)) AS BIGINT)) AS BIGINT) AS gone FROM d JOIN u{k - 1} u ON u.source IS NOT DISTINCT FROM d.source
  WHERE sqrt(size) * u.scale >= 1 GROUP BY d.source),
u{k} AS MATERIALIZED (SELECT u.source, source_size, powers, target, whole, all_rest, (all_rest - coalesce(big, 0)) / greatest(powers - coalesce(gone, 0), 1) AS scale, u.scale AS bar, all_rest - coalesce(big, 0) AS rest
  FROM u{k - 1} u LEFT JOIN g{k} g ON g.source IS NOT DISTINCT FROM u.source),
"""
    for k in range(1, mixing.UNITS + 1)
)
MIX = f"""
WITH d AS MATERIALIZED (SELECT doc_id, source, CAST(len(regexp_extract_all(coalesce(text, ''), '{_WORD}')) AS BIGINT) AS size,
  (CAST(CAST('0x' || substr(sha256(concat_ws('|', 'mix-1', coalesce(CAST(doc_id AS VARCHAR), 'null'), sha256(coalesce(text, '')))), 1, 13) AS BIGINT) AS DOUBLE) + 5e-1) / 4503599627370496e0 AS u FROM documents),
per AS (SELECT source, CAST(sum(size) AS BIGINT) AS source_size, CAST(sum(CAST(floor(size * sqrt(size)) AS BIGINT)) AS BIGINT) AS powers FROM d GROUP BY source),
f AS (SELECT *, cap / weight AS fill FROM (SELECT *, [3e0, 1e0, 2e0][(row_number() OVER (ORDER BY source NULLS LAST) - 1) % 3 + 1] AS weight, 2e0 * source_size AS cap FROM per)),
l AS (SELECT *, (CAST(sum(source_size) OVER () AS DOUBLE) * 15e-1 - coalesce(sum(cap) OVER (ORDER BY fill, source NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0e0))
  / sum(weight) OVER (ORDER BY fill, source NULLS LAST ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS level FROM f),
t AS MATERIALIZED (SELECT source, source_size, powers, least(cap, weight * coalesce(max(CASE WHEN level <= fill THEN level END) OVER (), fill)) AS target FROM l),
v AS (SELECT *, floor(CASE WHEN source_size > 0 THEN target / source_size ELSE 0e0 END) AS whole FROM t),
u0 AS MATERIALIZED (SELECT *, target - whole * source_size AS all_rest, (target - whole * source_size) / greatest(powers, 1) AS scale, 0e0 AS bar, target - whole * source_size AS rest FROM v),
{_UNITS}
q AS (SELECT d.*, u.source_size, u.target, u.whole, u.rest, sqrt(size) * u.bar >= 1 AS sure, least(1 - 1e-6, greatest(1e-6, u.scale * sqrt(size))) AS p
  FROM d JOIN u{mixing.UNITS} u ON u.source IS NOT DISTINCT FROM d.source),
k AS MATERIALIZED (SELECT *, o / (1 + o) AS rk FROM (SELECT *, (u / (1 - u)) / (p / (1 - p)) AS o FROM q)),
b AS (SELECT source, floor(rk * 1073741824e0) AS bin, sum(size) AS words, any_value(rest) AS rest, max(rk) AS top FROM k WHERE size > 0 AND rest > 0 AND NOT sure GROUP BY source, bin),
z AS (SELECT *, coalesce(sum(words) OVER (PARTITION BY source ORDER BY bin ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS before FROM b),
x AS (SELECT source, rest - before < before + words - rest AS open, CASE WHEN rest - before < before + words - rest THEN bin / 1073741824e0 ELSE top END AS cut FROM z WHERE before < rest AND before + words >= rest)
SELECT doc_id, size, source_size, target, CAST((whole + CASE WHEN sure OR rest > 0 AND coalesce(CASE WHEN open THEN rk < cut ELSE rk <= cut END, false) THEN 1 ELSE 0 END) * size AS BIGINT) AS taken
FROM k LEFT JOIN x ON x.source IS NOT DISTINCT FROM k.source"""

SQL = {"op3_ngram_join": NGRAM_JOIN, "op4_top_k": metric_tree.SQL, "op7_warc": WARC, "op8_mix": MIX}
