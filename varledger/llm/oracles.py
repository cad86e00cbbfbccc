"""DuckDB SQL for the contract queries that SQL can express on whole tables."""

from __future__ import annotations

#: Words of every text: runs of anything but space and bytes 9 to 13.
_WORDS = r"""
words AS (
    SELECT row_number() OVER () AS r, doc_id,
           list_filter(string_split_regex(coalesce(text, ''), '[\x20\x09-\x0D]+'), lambda x: x <> '') AS w,
           coalesce(text, '') AS text
    FROM documents
)"""

SUBSTRING_DEDUP = f"""
WITH {_WORDS},
starts AS (
    SELECT r, doc_id, w, unnest(range(1, len(w) - 11)) AS i FROM words WHERE len(w) >= 13
),
windows AS (SELECT r, doc_id, i, array_to_string(w[i:i + 12], ' ') AS win FROM starts),
late AS (
    SELECT r, i FROM (SELECT r, doc_id, i, min(doc_id) OVER (PARTITION BY win) AS low FROM windows) WHERE doc_id > low
),
gone AS (SELECT DISTINCT r, p FROM (SELECT r, unnest(range(i, i + 13)) AS p FROM late)),
gone_of AS (SELECT r, list(p) AS ps, count(*) AS n FROM gone GROUP BY r)
SELECT doc_id, CAST(len(w) AS BIGINT) AS n_words, CAST(coalesce(n, 0) AS BIGINT) AS n_removed,
       sha256(array_to_string(list_filter(w, lambda x, i: ps IS NULL OR NOT list_contains(ps, i)), ' ')) AS kept_sha256
FROM words LEFT JOIN gone_of USING (r)
"""

QUALITY_RULES = rf"""
WITH {_WORDS},
wins AS (
    SELECT r, i, array_to_string(w[i:i + 7], ' ') AS win
    FROM (SELECT r, w, unnest(range(1, len(w) - 6)) AS i FROM words WHERE len(w) >= 9)
),
twice AS (SELECT r, i FROM (SELECT r, i, count(*) OVER (PARTITION BY r, win) AS n FROM wins) WHERE n > 1),
covered AS (SELECT r, count(DISTINCT p) AS n FROM (SELECT r, unnest(range(i, i + 8)) AS p FROM twice) GROUP BY r),
lines AS (SELECT r, list_filter(string_split(text, chr(10)), lambda x: regexp_matches(x, '[^\x20\x09-\x0D]')) AS l FROM words),
base AS (
    SELECT doc_id, text, w, CAST(len(w) AS BIGINT) AS n_words,
           CAST(length(array_to_string(w, '')) AS BIGINT) AS word_chars,
           CAST(length(regexp_replace(text, '[^#*$%&|<>]', '', 'g')) AS BIGINT) AS n_symbols,
           CAST(len(l) - len(list_distinct(l)) AS BIGINT) AS n_dup_lines, len(l) AS n_lines,
           CAST(coalesce(n, 0) AS BIGINT) AS n_repeat_words
    FROM words JOIN lines USING (r) LEFT JOIN covered USING (r)
),
judged AS (
    SELECT *, n_words < 20 OR 100 * n_repeat_words > 30 * n_words AS base_failed,
           len(list_filter(w, lambda x: regexp_matches(x, '\p{{L}}'))) AS with_letter,
           length(regexp_replace(text, '[^\p{{Lu}}]', '', 'g')) AS capitals
    FROM base
)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed,
       NOT (base_failed OR n_symbols > 0.1 * n_words OR n_dup_lines > 0.34 * n_lines
            OR word_chars < 2.5 * n_words OR word_chars > 12 * n_words
            OR with_letter < 0.7 * n_words OR capitals * 2 > word_chars) AS kept
FROM judged
"""

TOP_K = """
WITH v AS (
    SELECT vec_id, list_transform(embedding, lambda x: CAST(floor(256 * CAST(x AS DOUBLE)) AS BIGINT)) AS q
    FROM embeddings
    WHERE embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0
),
scored AS (
    SELECT a.vec_id AS query_id, b.vec_id, CAST(list_sum(list_transform(list_zip(a.q, b.q), lambda p: p[1] * p[2])) AS BIGINT) AS score
    FROM v a JOIN v b ON a.vec_id % 50 = 0 AND a.vec_id <> b.vec_id
)
SELECT query_id, CAST(rank AS INTEGER) AS rank, vec_id, score
FROM (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS rank FROM scored)
WHERE rank <= 5
"""

JACCARD = rf"""
WITH RECURSIVE {_WORDS.replace("coalesce(text, ''), '[", "translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[")},
shingles AS (
    SELECT DISTINCT r, array_to_string(w[i:i + 4], ' ') AS s
    FROM (SELECT r, w, unnest(range(1, greatest(len(w) - 3, 2))) AS i FROM words WHERE len(w) > 0)
),
sizes AS (SELECT r, count(*) AS n FROM shingles GROUP BY r),
pairs AS (
    SELECT a.r AS a, b.r AS b, count(*) AS o FROM shingles a JOIN shingles b ON a.s = b.s AND a.r < b.r GROUP BY a.r, b.r
),
links AS (
    SELECT a, b FROM pairs JOIN sizes x ON x.r = a JOIN sizes y ON y.r = b WHERE 100 * o >= 80 * (x.n + y.n - o)
),
edges AS (SELECT a, b FROM links UNION SELECT b, a FROM links),
reach AS (SELECT r AS a, r AS b FROM words UNION SELECT reach.a, edges.b FROM reach JOIN edges ON reach.b = edges.a),
low AS (SELECT a, min(doc_id) AS component_id FROM reach JOIN words ON b = r GROUP BY a)
SELECT doc_id, CAST(coalesce(n, 0) AS BIGINT) AS n_shingles, component_id
FROM words JOIN low ON a = words.r LEFT JOIN sizes ON sizes.r = words.r
"""

WARC_PAGES = """
WITH p AS (
    SELECT page_id, CAST(strlen(coalesce(html, '')) AS BIGINT) AS payload_bytes, sha1(coalesce(html, '')) AS payload_digest
    FROM pages
),
k AS (SELECT *, max(page_id) OVER (PARTITION BY payload_digest) AS kept FROM p)
SELECT page_id, payload_bytes, payload_digest,
       CASE WHEN payload_bytes >= 1000 AND page_id <> kept THEN 'revisit' ELSE 'response' END AS record_type,
       CASE WHEN payload_bytes >= 1000 AND page_id <> kept THEN kept END AS refers_to
FROM k
"""

SQL = {
    "op1_substring_dedup": SUBSTRING_DEDUP,
    "op2_quality_rules": QUALITY_RULES,
    "op3_top_k_search": TOP_K,
    "op4_jaccard_join": JACCARD,
    "op10_warc_pages": WARC_PAGES,
}
