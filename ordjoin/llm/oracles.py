"""SQL (DuckDB) for the results of the duplicate operators, over whole tables."""

from __future__ import annotations

WORD = r"'[^\x20\x09-\x0D]+'"
_ROWS = "d AS (SELECT row_number() OVER () AS r, doc_id, coalesce(text, '') AS t FROM documents)"
_WORDS = f"w AS (SELECT r, doc_id, unnest(regexp_extract_all(t, {WORD})) AS word, generate_subscripts(regexp_extract_all(t, {WORD}), 1) AS pos FROM d)"


def substring_dedup(window: int = 50) -> str:
    """Words covered by a window that also starts in a document with a smaller id; windows by their words."""
    return f"""WITH {_ROWS}, {_WORDS},
win AS (SELECT r, doc_id, pos, CASE WHEN count(*) OVER ahead = {window} THEN md5(string_agg(word, ' ') OVER ahead) END AS s FROM w
  WINDOW ahead AS (PARTITION BY r ORDER BY pos ROWS BETWEEN CURRENT ROW AND {window - 1} FOLLOWING)),
low AS (SELECT s, min(doc_id) AS least FROM win WHERE s IS NOT NULL GROUP BY s),
hit AS (SELECT r, pos, least < win.doc_id AS known FROM win LEFT JOIN low USING (s)),
gone AS (SELECT r, pos, coalesce(bool_or(known) OVER (PARTITION BY r ORDER BY pos ROWS BETWEEN {window - 1} PRECEDING AND CURRENT ROW), false) AS g FROM hit),
left_over AS (SELECT r, count(*) AS n, count(*) FILTER (WHERE g) AS k, string_agg(word, ' ' ORDER BY pos) FILTER (WHERE NOT g) AS text FROM gone JOIN w USING (r, pos) GROUP BY r)
SELECT doc_id, coalesce(n, 0) AS n_words, coalesce(k, 0) AS n_removed, sha256(coalesce(text, '')) AS kept_sha256 FROM d LEFT JOIN left_over USING (r)"""


def suffix_dedup(window: int = 200) -> str:
    """Bytes covered by a string that starts twice; strings by a hash built from those of half their length."""
    steps, have, sql = [1], 1, []
    while have * 2 <= window:
        have *= 2
        steps.append(have)
    for a, b in zip(steps, steps[1:], strict=False):
        sql.append(f"h{b} AS (SELECT r, pos, byte, hash(h, lead(h, {a}) OVER (PARTITION BY r ORDER BY pos)) AS h FROM h{a})")
    return f"""WITH {_ROWS}, h1 AS (SELECT r, unnest(regexp_extract_all(hex(encode(t)), '..')) AS byte, generate_subscripts(regexp_extract_all(hex(encode(t)), '..'), 1) AS pos, hash(byte) AS h FROM d),
{", ".join(sql)},
win AS (SELECT r, pos, byte, CASE WHEN lead(1, {window - 1}) OVER ahead IS NOT NULL THEN hash(h, lead(h, {window - have}) OVER ahead) END AS s FROM h{have} WINDOW ahead AS (PARTITION BY r ORDER BY pos)),
often AS (SELECT s FROM win WHERE s IS NOT NULL GROUP BY s HAVING count(*) > 1),
hit AS (SELECT r, pos, byte, often.s IS NOT NULL AS known FROM win LEFT JOIN often USING (s)),
gone AS (SELECT r, pos, byte, bool_or(known) OVER (PARTITION BY r ORDER BY pos ROWS BETWEEN {window - 1} PRECEDING AND CURRENT ROW) AS g FROM hit),
edge AS (SELECT r, pos, byte, g, g AND NOT coalesce(lag(g) OVER (PARTITION BY r ORDER BY pos), false) AS opens FROM gone),
left_over AS (SELECT r, count(*) AS n, count(*) FILTER (WHERE g) AS k, count(*) FILTER (WHERE opens) AS spans, string_agg(byte, '' ORDER BY pos) FILTER (WHERE NOT g) AS text FROM edge GROUP BY r)
SELECT doc_id, coalesce(n, 0) AS n_bytes, coalesce(k, 0) AS n_removed, coalesce(spans, 0) AS n_spans, sha256(unhex(coalesce(text, ''))) AS kept_sha256 FROM d LEFT JOIN left_over USING (r)"""


def near_duplicates(width: int = 4, percent: int = 85) -> str:
    """Shingle sets, links by shared shingles, and what links reach."""
    ahead = f"(PARTITION BY r ORDER BY pos ROWS BETWEEN CURRENT ROW AND {width - 1} FOLLOWING)"
    low = "translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"
    return f"""WITH RECURSIVE d AS (SELECT row_number() OVER () AS r, doc_id, {low} AS t FROM documents), {_WORDS},
many AS (SELECT r, count(*) AS words FROM w GROUP BY r),
gram AS (SELECT r, string_agg(word, ' ') OVER {ahead} AS g, count(*) OVER {ahead} AS n, pos FROM w),
s AS MATERIALIZED (SELECT DISTINCT r, md5_number(g) AS g FROM gram JOIN many USING (r) WHERE n = {width} OR (words < {width} AND pos = 1)),
size AS (SELECT r, count(*) AS n, md5(string_agg(g, ' ' ORDER BY g)) AS whole FROM s GROUP BY r),
shared AS (SELECT a.r AS x, b.r AS y, count(*) AS c FROM s a JOIN s b ON a.g = b.g AND a.r < b.r GROUP BY 1, 2),
one_way AS (SELECT x, y FROM shared JOIN size p ON p.r = x JOIN size q ON q.r = y WHERE 100 * c >= {percent} * (p.n + q.n - c)),
link AS MATERIALIZED (SELECT x, y FROM one_way UNION ALL SELECT y, x FROM one_way),
reach AS (SELECT r AS x, r AS y FROM d UNION SELECT reach.x, link.y FROM reach JOIN link ON link.x = reach.y),
class AS (SELECT x AS r, min(doc_id) AS least FROM reach JOIN d ON d.r = y GROUP BY x),
degree AS (SELECT x AS r, count(DISTINCT q.whole) FILTER (WHERE q.whole <> p.whole) AS n_links FROM link JOIN size p ON p.r = x JOIN size q ON q.r = y GROUP BY x)
SELECT doc_id, coalesce(n, 0) AS n_shingles, least AS component_id, coalesce(n_links, 0) AS n_links FROM d JOIN class USING (r) LEFT JOIN size USING (r) LEFT JOIN degree USING (r)"""
