"""DuckDB SQL of the operators that SQL can express over whole tables."""

from __future__ import annotations

from proxembed.llm.secret_scan import ACCESS, ASSIGN, HEX, PEM
from proxembed.llm.warc import ALPHABET


def _quoted(pattern: str) -> str:
    return "'" + pattern.replace("'", "''") + "'"


def _base32(hexed: str) -> str:
    bits = lambda k: f"('0x' || substr({hexed}, {5 * k + 1}, 5))::BIGINT"
    return " || ".join(f"substr('{ALPHABET}', (({bits(k)} >> {n}) & 31)::INTEGER + 1, 1)" for k in range(8) for n in (15, 10, 5, 0))


WARC = f"""WITH p AS (SELECT page_id, coalesce(html, '') AS html, sha1(coalesce(html, '')) AS h FROM pages),
t AS (SELECT h, max(page_id) AS top, count(*) AS n FROM p GROUP BY h)
SELECT page_id, strlen(html)::BIGINT AS payload_bytes, {_base32('p.h')} AS payload_digest,
       CASE WHEN n > 1 AND page_id <> top THEN 'revisit' ELSE 'response' END AS record_type,
       CASE WHEN n > 1 AND page_id <> top THEN top END AS refers_to
FROM p JOIN t ON p.h = t.h"""


def _spans(kind: str, rank: int, pattern: str, group: int, least: int) -> str:
    """Matches of a kind with their places: the text is cut at marks put around each match, and lengths are summed."""
    return f"""SELECT doc_id, {rank} AS rank, '{kind}' AS kind, coalesce(sum(length(part)) OVER (PARTITION BY doc_id ORDER BY k ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::BIGINT AS a, length(part) AS n,
    k % 2 = 0 AND length(regexp_extract(part, {_quoted(pattern)}, {group})) >= {least} AS hit
FROM (SELECT doc_id, generate_subscripts(parts, 1) AS k, unnest(parts) AS part FROM (SELECT doc_id, string_split(regexp_replace(text, {_quoted(pattern)}, chr(1) || '\\0' || chr(1), 'g'), chr(1)) AS parts FROM d))"""


SECRETS = f"""WITH d AS (SELECT doc_id, replace(coalesce(text, ''), chr(1), chr(2)) AS text FROM documents),
s AS ({_spans('assign', 0, ASSIGN, 2, 6)} UNION ALL {_spans('access', 1, ACCESS, 1, 20)} UNION ALL {_spans('hex', 2, HEX.replace('{24,}+', '{24,}'), 1, 24)} UNION ALL {_spans('pem', 3, PEM, 1, 40)}),
f AS (SELECT doc_id, count(*) FILTER (kind = 'assign') AS n_assign, count(*) FILTER (kind = 'access') AS n_access, count(*) FILTER (kind = 'hex') AS n_hex,
      string_agg(kind || ':' || a || ':' || (a + n), ',' ORDER BY a, rank) FILTER (kind <> 'pem') AS base, string_agg(kind || ':' || a || ':' || (a + n), ',' ORDER BY a, rank) AS spans FROM s WHERE hit GROUP BY doc_id)
SELECT d.doc_id, coalesce(n_assign, 0)::BIGINT AS n_assign, coalesce(n_access, 0)::BIGINT AS n_access, coalesce(n_hex, 0)::BIGINT AS n_hex, sha256(coalesce(base, '')) AS base_sha256, coalesce(spans, '') AS spans
FROM d LEFT JOIN f ON d.doc_id = f.doc_id"""

JACCARD = r"""WITH RECURSIVE w AS (SELECT doc_id, list_filter(regexp_split_to_array(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x20\x09-\x0D]+'), lambda x: x <> '') AS words FROM documents),
c AS (SELECT doc_id, words, len(words) AS n FROM w),
s AS (SELECT DISTINCT doc_id, sha256(list_aggregate(words[k:k + 4], 'string_agg', ' ')) AS shingle FROM (SELECT doc_id, words, unnest(generate_series(1, greatest(n - 4, 1))) AS k FROM c WHERE n > 0)),
z AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
shared AS (SELECT x.doc_id AS a, y.doc_id AS b, count(*) AS same FROM s x JOIN s y ON x.shingle = y.shingle AND x.doc_id <> y.doc_id GROUP BY ALL),
links AS (SELECT a, b FROM shared JOIN z p ON p.doc_id = a JOIN z q ON q.doc_id = b WHERE 100 * same >= 75 * (p.n + q.n - same)),
reach(a, b) AS (SELECT a, b FROM links UNION SELECT r.a, l.b FROM reach r JOIN links l ON r.b = l.a)
SELECT c.doc_id, coalesce(z.n, 0)::BIGINT AS n_shingles, least(c.doc_id, coalesce(m.low, c.doc_id)) AS component_id
FROM c LEFT JOIN z ON z.doc_id = c.doc_id LEFT JOIN (SELECT a, min(b) AS low FROM reach GROUP BY a) m ON m.a = c.doc_id"""


def oracle_sql() -> dict[str, str]:
    return {"op1_warc_segments": WARC, "op2_secret_ledger": SECRETS, "op4_parity_join": JACCARD}
