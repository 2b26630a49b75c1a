"""DuckDB SQL for the queries whose results SQL can express, over whole tables."""

from __future__ import annotations

_LETTERS = "ABCDEFGHIJKLMNOPQRSTUVWXYZ234567"

#: SHA-1 has 40 hex digits; five of them, 20 bits, are four base-32 digits.
WARC_REVISITS = f"""
WITH rows AS (SELECT page_id, coalesce(html, '') AS body FROM pages),
hashed AS (SELECT page_id, strlen(body) AS payload_bytes, sha1(body) AS h FROM rows),
digested AS (SELECT page_id, payload_bytes, array_to_string([
    substr('{_LETTERS}', 1 + ((CAST('0x' || substr(h, 5 * (i // 4) + 1, 5) AS BIGINT) >> (15 - 5 * (i % 4))) & 31), 1) FOR i IN range(32)], '') AS payload_digest FROM hashed),
led AS (SELECT *, min(page_id) OVER (PARTITION BY payload_digest) AS least FROM digested)
SELECT page_id, payload_bytes, payload_digest, CASE WHEN page_id = least THEN 'response' ELSE 'revisit' END AS record_type, CASE WHEN page_id = least THEN NULL ELSE least END AS refers_to, TRUE AS intact FROM led
"""

_LOWER = "translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"
#: Equal sets are one node; nodes that share a shingle are counted, links are spread until nothing changes.
JACCARD_COMPONENTS = rf"""
WITH RECURSIVE worded AS MATERIALIZED (SELECT doc_id, regexp_extract_all({_LOWER}, '[^\x20\x09-\x0D]+') AS w FROM documents),
sets AS MATERIALIZED (SELECT doc_id, list_sort(list_distinct(CASE WHEN len(w) = 0 THEN [] WHEN len(w) < 5 THEN [array_to_string(w, ' ')]
    ELSE [w[i] || ' ' || w[i + 1] || ' ' || w[i + 2] || ' ' || w[i + 3] || ' ' || w[i + 4] FOR i IN range(1, len(w) - 3)] END)) AS s FROM worded),
nodes AS MATERIALIZED (SELECT min(doc_id) AS node, s, len(s) AS n FROM sets WHERE len(s) > 0 GROUP BY s),
tokens AS MATERIALIZED (SELECT node, n, md5_number(t) AS t FROM (SELECT node, n, unnest(s) AS t FROM nodes)),
pairs AS MATERIALIZED (SELECT a.node AS a, b.node AS b, a.n AS na, b.n AS nb, count(*) AS c FROM tokens a JOIN tokens b ON a.t = b.t AND a.node < b.node AND 100 * least(a.n, b.n) >= 75 * greatest(a.n, b.n) GROUP BY ALL),
links AS MATERIALIZED (SELECT a, b FROM pairs WHERE 100 * c >= 75 * (na + nb - c) UNION ALL SELECT b, a FROM pairs WHERE 100 * c >= 75 * (na + nb - c)),
reach AS (SELECT node AS a, node AS b FROM nodes UNION SELECT r.a, l.b FROM reach r JOIN links l ON r.b = l.a),
least AS (SELECT a AS node, min(b) AS component_id FROM reach GROUP BY a)
SELECT sets.doc_id, len(sets.s) AS n_shingles, coalesce(least.component_id, sets.doc_id) AS component_id
FROM sets LEFT JOIN nodes ON sets.s = nodes.s LEFT JOIN least ON nodes.node = least.node
"""


def _any_case(word: str) -> str:
    return "".join(f"[{c}{c.upper()}]" if c.isalpha() else c for c in word)


_KEYWORD = "(" + "|".join(map(_any_case, ("password", "passwd", "secret", "token"))) + f"|{_any_case('api')}_?{_any_case('key')})"
#: kind, its place, pattern, group that holds the value, least characters of it.
_RULES = (
    ("assign", 0, _KEYWORD + r"[\"'']?\x20*[:=]\x20*[\"'']?([A-Za-z0-9+/_.=-]+)", 2, 6),
    ("access", 1, r"AKIA[A-Z0-9]+", 0, 20),
    ("hex", 2, r"[0-9a-f]+", 0, 24),
    ("pem", 3, r"-----BEGIN [A-Z ]*PRIVATE KEY-----(?:[A-Za-z0-9+/=:,\x20\t\n\x0B\f\r-]*?-----END [A-Z ]*PRIVATE KEY-----)?", 0, 1),
    ("jwt", 4, r"eyJ[A-Za-z0-9_-]{8,}\.[A-Za-z0-9_-]{8,}\.[A-Za-z0-9_-]{8,}", 0, 1),
    ("forge", 5, r"gh[pousr]_[A-Za-z0-9]{36,}", 0, 1),
)


def _spans(kind: str, number: int, pattern: str, group: int, least: int) -> str:
    """doc_id, kind, number, start, stop: lengths of the stretches between matches and of the matches give the offsets."""
    return rf"""SELECT doc_id, '{kind}' AS kind, {number} AS number, pre + gap AS start, pre + gap + hit AS stop FROM (
        SELECT doc_id, i, gap, hit, val, coalesce(sum(gap + hit) OVER (PARTITION BY doc_id ORDER BY i ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS pre FROM (
            SELECT doc_id, i, length(gaps[i]) AS gap, length(hits[i]) AS hit, length(vals[i]) AS val FROM (
                SELECT doc_id, hits, vals, gaps, unnest(range(1, len(hits) + 1)) AS i FROM (
                    SELECT doc_id, regexp_extract_all(text, '{pattern}') AS hits, regexp_extract_all(text, '{pattern}', {group}) AS vals, string_split_regex(text, '{pattern}') AS gaps FROM documents)))) WHERE val >= {least}"""


SECRET_SPANS = f"""
WITH spans AS ({" UNION ALL ".join(_spans(*r) for r in _RULES)}),
told AS (SELECT doc_id, number, start, kind, kind || ':' || CAST(start AS BIGINT) || ':' || CAST(stop AS BIGINT) AS said FROM spans),
summed AS (SELECT doc_id, count(*) FILTER (kind = 'assign') AS n_assign, count(*) FILTER (kind = 'access') AS n_access, count(*) FILTER (kind = 'hex') AS n_hex,
    coalesce(string_agg(said, ',' ORDER BY start, number) FILTER (number < 3), '') AS base, string_agg(said, ',' ORDER BY start, number) AS spans FROM told GROUP BY doc_id)
SELECT d.doc_id, coalesce(n_assign, 0) AS n_assign, coalesce(n_access, 0) AS n_access, coalesce(n_hex, 0) AS n_hex, sha256(coalesce(base, '')) AS base_sha256, coalesce(spans, '') AS spans
FROM documents d LEFT JOIN summed s ON d.doc_id = s.doc_id
"""

#: Sources are capped in the order of size over weight, as long as what is left for the others gives them more than that.
MIXING = rf"""
WITH rows AS (SELECT doc_id, source, CAST(len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+')) AS BIGINT) AS size, md5(concat_ws('|', CAST(doc_id AS VARCHAR), coalesce(text, ''))) AS h FROM documents),
totals AS (SELECT source, CAST(sum(size) AS BIGINT) AS source_size FROM rows GROUP BY source),
weighed AS (SELECT *, CAST([3, 1, 2][1 + (row_number() OVER (ORDER BY encode(source) NULLS LAST) - 1) % 3] AS DOUBLE) AS w FROM totals),
ordered AS (SELECT *, 2.0 * source_size / w AS ratio FROM weighed),
before AS (SELECT *, (SELECT 1.5 * sum(source_size) FROM totals) AS total, coalesce(sum(2.0 * source_size) OVER o, 0) AS gone, (SELECT sum(w) FROM weighed) - coalesce(sum(w) OVER o, 0) AS left_w
    FROM ordered WINDOW o AS (ORDER BY ratio RANGE BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW EXCLUDE GROUP)),
capped AS (SELECT *, (total - gone) / left_w > ratio AS over FROM before),
unit AS (SELECT (any_value(total) - coalesce(sum(2.0 * source_size) FILTER (over), 0)) / sum(w) FILTER (NOT over) AS u FROM capped),
targets AS (SELECT source, source_size, CASE WHEN over THEN 2.0 * source_size ELSE w * u END AS target, CAST('0x' || substr(md5('11|' || coalesce('s' || source, '-')), 1, 7) AS BIGINT) / 268435456.0::DOUBLE AS start
    FROM capped, unit),
placed AS (SELECT *, row_number() OVER (PARTITION BY source ORDER BY size, h, doc_id) - 1 AS k FROM rows)
SELECT doc_id, size, source_size, target, CAST(size * (floor(start + rate * (k + 1)) - floor(start + rate * k)) AS BIGINT) AS taken FROM (
    SELECT p.*, t.source_size, t.target, t.start, CASE WHEN t.source_size > 0 THEN t.target / t.source_size ELSE 0 END AS rate FROM placed p JOIN targets t ON p.source IS NOT DISTINCT FROM t.source)
"""

ORACLES = {"op9_mixing_sources": MIXING, "op3_warc_revisits": WARC_REVISITS, "op8_ngram_jaccard_join": JACCARD_COMPONENTS, "op10_secret_scans": SECRET_SPANS, "secret_ledger_increment": SECRET_SPANS}
