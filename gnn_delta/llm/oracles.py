"""SQL (DuckDB) for the text queries that SQL can express, over the same tables."""

from __future__ import annotations


def exact_dedup() -> str:
    return """
        WITH t AS (SELECT doc_id, translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS body FROM documents),
        g AS (SELECT body, max(doc_id) AS keep_id, count(*) AS group_size FROM t GROUP BY body)
        SELECT t.doc_id, g.keep_id, CAST(g.group_size AS BIGINT) AS group_size, t.doc_id = g.keep_id AS kept, sha256(t.body) AS text_sha256
        FROM t JOIN g USING (body)"""


def word_spans(window: int = 20) -> str:
    """All windows of words, the first place of each, and the words that later places cover."""
    return f"""
        WITH w AS (SELECT doc_id, regexp_extract_all(coalesce(text, ''), '[^\\x20\\x09-\\x0D]+') AS words FROM documents),
        p AS (SELECT doc_id, words, unnest(range(1, len(words) + 1)) AS i FROM w),
        e AS (SELECT doc_id, i, words[i] AS word, CASE WHEN i + {window - 1} <= len(words) THEN array_to_string(words[i : i + {window - 1}], ' ') END AS edge FROM p),
        f AS (SELECT *, edge IS NOT NULL AND row_number() OVER (PARTITION BY edge ORDER BY doc_id, i) > 1 AS later FROM e),
        c AS (SELECT doc_id, i, word, bool_or(later) OVER (PARTITION BY doc_id ORDER BY i ROWS BETWEEN {window - 1} PRECEDING AND CURRENT ROW) AS gone FROM f),
        k AS (SELECT doc_id, count(*) AS n, count(*) FILTER (gone) AS r, string_agg(word, ' ' ORDER BY i) FILTER (NOT gone) AS kept FROM c GROUP BY doc_id)
        SELECT documents.doc_id, coalesce(n, 0) AS n_words, coalesce(r, 0) AS n_removed, sha256(coalesce(kept, '')) AS kept_sha256
        FROM documents LEFT JOIN k ON k.doc_id = documents.doc_id"""


def byte_spans(window: int = 100, piece: int = 500) -> str:
    """The same for strings of bytes, as hexadecimal digits cut into pieces first."""
    return f"""
        WITH h AS (SELECT doc_id, hex(encode(coalesce(text, ''))) AS x, CAST(octet_length(encode(coalesce(text, ''))) AS BIGINT) AS n FROM documents),
        s AS (SELECT doc_id, n, a, substr(x, 2 * a + 1, {2 * (piece + window - 1)}) AS x FROM (SELECT *, unnest(range(0, n, {piece})) AS a FROM h)),
        b AS (SELECT doc_id, n, a, x, unnest(range(0, least({piece}, n - a))) AS j FROM s),
        e AS (SELECT doc_id, a + j AS i, substr(x, 2 * j + 1, 2) AS byte, CASE WHEN a + j + {window} <= n THEN md5_number(substr(x, 2 * j + 1, {2 * window})) END AS m FROM b),
        f AS (SELECT doc_id, i, byte, m IS NOT NULL AND row_number() OVER (PARTITION BY m ORDER BY doc_id, i) > 1 AS later FROM e),
        c AS (SELECT doc_id, i, byte, bool_or(later) OVER (PARTITION BY doc_id ORDER BY i ROWS BETWEEN {window - 1} PRECEDING AND CURRENT ROW) AS gone FROM f),
        d AS (SELECT *, gone AND NOT coalesce(lag(gone) OVER (PARTITION BY doc_id ORDER BY i), false) AS head FROM c),
        k AS (SELECT doc_id, count(*) FILTER (gone) AS r, count(*) FILTER (head) AS spans, string_agg(byte, '' ORDER BY i) FILTER (NOT gone) AS kept FROM d GROUP BY doc_id)
        SELECT h.doc_id, h.n AS n_bytes, coalesce(r, 0) AS n_removed, coalesce(spans, 0) AS n_spans, sha256(unhex(coalesce(kept, ''))) AS kept_sha256
        FROM h LEFT JOIN k ON k.doc_id = h.doc_id"""


ORACLES = {"op1_substring_dedup": word_spans(), "op4_exact_dedup": exact_dedup(), "op10_suffix_dedup": byte_spans()}
