"""DuckDB SQL of the queries that SQL can express."""

from __future__ import annotations

from .queries import LISTED, RULES

_WORD = r"'[^\x20\x09-\x0D]+'"
_LOWER = "translate({}, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"


def _op1() -> str:
    """Bytes are handled as pairs of hex digits."""
    return """
WITH d AS (SELECT doc_id, hex(encode(coalesce(text, ''))) AS h FROM documents),
w AS (SELECT doc_id, p, substr(h, 2 * p - 1, 100) AS s FROM (SELECT doc_id, h, unnest(range(1, CAST(length(h) // 2 AS BIGINT) - 48)) AS p FROM d WHERE length(h) >= 100)),
f AS (SELECT s, min(doc_id) AS first FROM w GROUP BY 1),
hit AS (SELECT w.doc_id, w.p FROM w JOIN f USING (s) WHERE w.doc_id > f.first),
g AS (SELECT doc_id, p, sum(new) OVER (PARTITION BY doc_id ORDER BY p) AS k
  FROM (SELECT doc_id, p, CASE WHEN p <= lag(p) OVER (PARTITION BY doc_id ORDER BY p) + 50 THEN 0 ELSE 1 END AS new FROM hit)),
span AS (SELECT doc_id, min(p) AS a, max(p) + 49 AS b FROM g GROUP BY doc_id, k),
piece AS (SELECT doc_id, a, substr(h, 2 * before + 1, 2 * (a - before - 1)) AS t
  FROM (SELECT span.*, h, coalesce(lag(b) OVER (PARTITION BY doc_id ORDER BY a), 0) AS before FROM span JOIN d USING (doc_id))),
cut AS (SELECT doc_id, string_agg(t, '' ORDER BY a) AS t FROM piece GROUP BY 1),
sums AS (SELECT doc_id, sum(b - a + 1) AS removed, count(*) AS spans, max(b) AS upto FROM span GROUP BY 1)
SELECT doc_id, CAST(length(h) // 2 AS BIGINT) AS n_bytes, CAST(coalesce(removed, 0) AS BIGINT) AS n_removed, CAST(coalesce(spans, 0) AS BIGINT) AS n_spans,
  sha256(unhex(coalesce(t, '') || substr(h, 2 * coalesce(upto, 0) + 1))) AS kept_sha256
FROM d LEFT JOIN sums USING (doc_id) LEFT JOIN cut USING (doc_id)"""


def _op3() -> str:
    words = rf"regexp_extract_all({_LOWER.format('coalesce(text, {0})').format(chr(39) * 2)}, '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+')"
    return f"""
WITH d AS (SELECT doc_id, {words} AS w FROM documents),
i AS (SELECT CAST(item_id AS VARCHAR) AS item, {words} AS w FROM benchmark),
win AS (
  SELECT DISTINCT item, array_to_string(list_slice(w, s, s + least(10, len(w)) - 1), ' ') AS g, least(10, len(w)) AS n
  FROM (SELECT item, w, unnest(range(1, greatest(len(w) - 9, 1) + 1)) AS s FROM i WHERE len(w) > 0)),
sizes AS (SELECT DISTINCT n FROM win),
occ AS (SELECT doc_id, n, s, array_to_string(list_slice(w, s, s + n - 1), ' ') AS g
  FROM (SELECT doc_id, w, n, unnest(range(1, len(w) - n + 2)) AS s FROM d, sizes WHERE len(w) >= n)),
hits AS (SELECT doc_id, item, s, n FROM occ JOIN win USING (n, g)),
hit AS (SELECT doc_id, count(DISTINCT p) AS n_hit FROM (SELECT doc_id, unnest(range(s, s + n)) AS p FROM hits) GROUP BY 1),
items AS (SELECT doc_id, count(DISTINCT item) AS n_items, string_agg(DISTINCT item, ',' ORDER BY item) AS ids FROM hits GROUP BY 1)
SELECT doc_id, CAST(len(w) AS BIGINT) AS n_words, CAST(coalesce(n_hit, 0) AS BIGINT) AS n_hit, CAST(coalesce(n_items, 0) AS BIGINT) AS n_items,
  sha256(coalesce(ids, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated
FROM d LEFT JOIN hit USING (doc_id) LEFT JOIN items USING (doc_id)"""


def _op5() -> str:
    ordered = sorted(RULES, key=lambda r: (-len(r.text), -len(r.host), r.text))
    fits = [f"WHEN (host = '{r.host}' OR ends_with(host, '.{r.host}')) AND starts_with(path, '{r.path}') THEN" for r in ordered]
    rule = " ".join(f"{f} '{r.text}'" for f, r in zip(fits, ordered, strict=True))
    verdict = " ".join(f"{f} '{r.verdict}'" for f, r in zip(fits, ordered, strict=True))
    listed = " OR ".join(f"host = '{x[:-1]}' OR ends_with(host, '.{x[:-1]}')" for x in LISTED)
    return rf"""
WITH u AS (SELECT page_id, CASE WHEN contains(url, '://') THEN substr(url, instr(url, '://') + 3) ELSE '' END AS rest FROM pages),
p AS (SELECT page_id, {_LOWER.format("regexp_extract(rest, '^([^/?#]*)', 1)")} AS host, regexp_extract(rest, '^[^/?#]*([^?#]*)', 1) AS path FROM u)
SELECT page_id, host, path, CASE {rule} END AS rule, CASE {verdict} WHEN {listed} THEN 'block' ELSE 'allow' END AS verdict FROM p"""


def _op10() -> str:
    return f"""
WITH d AS (SELECT doc_id, source, CAST(len(regexp_extract_all(coalesce(text, ''), {_WORD})) AS BIGINT) AS size,
    (CAST('0x' || substr(md5('mix-1:' || coalesce(CAST(doc_id AS VARCHAR), '')), 1, 12) AS UBIGINT) + 0.5::DOUBLE) / 281474976710656 AS u FROM documents),
s AS (SELECT source, CAST(sum(size) AS BIGINT) AS source_size, row_number() OVER (ORDER BY source NULLS LAST) - 1 AS k FROM d GROUP BY 1),
w AS (SELECT *, CASE k % 3 WHEN 0 THEN 5.0::DOUBLE WHEN 1 THEN 2.0::DOUBLE ELSE 1.0::DOUBLE END AS weight FROM s),
r AS (SELECT *, 2.0::DOUBLE * source_size AS cap, 2.0::DOUBLE * source_size / weight AS ratio FROM w),
l AS (SELECT *, ((SELECT sum(source_size) FROM s) * 1.5::DOUBLE - coalesce(sum(cap) OVER (o ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)) / sum(weight) OVER (o ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS level
  FROM r WINDOW o AS (ORDER BY ratio, source NULLS LAST)),
g AS (SELECT source, source_size, least(cap, coalesce((SELECT arg_min(level, ratio) FROM l WHERE ratio > level) * weight, cap)) AS target FROM l),
t AS (SELECT *, CASE WHEN source_size > 0 THEN floor(target / source_size) ELSE 0 END AS whole, CASE WHEN source_size > 0 THEN target / source_size ELSE 0 END AS ratio FROM g),
q AS (SELECT d.doc_id, d.source, size, u, source_size, target, whole, least(greatest(ratio - whole, 1e-12::DOUBLE), 1 - 1e-12::DOUBLE) AS p, target - whole * source_size AS rest FROM d JOIN t ON d.source IS NOT DISTINCT FROM t.source),
c AS (SELECT *, sum(size) OVER (PARTITION BY source ORDER BY u / (1 - u) / (p / (1 - p)), doc_id, size ROWS UNBOUNDED PRECEDING) AS upto FROM q),
x AS (SELECT *, CAST(whole AS BIGINT) + CASE WHEN rest > 0 AND upto - size / 2.0::DOUBLE <= rest THEN 1 ELSE 0 END AS copies FROM c)
SELECT doc_id, size, source_size, target, CAST(copies * size AS BIGINT) AS taken, CAST(copies AS BIGINT) AS copies FROM x"""


def oracle_sql() -> dict[str, str]:
    return {"op1_suffix_dedup": _op1(), "op3_decontamination": _op3(), "op5_url_filter": _op5(), "op10_mixing": _op10()}
