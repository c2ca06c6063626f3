"""SQL of the same rows as the queries that SQL can express, over whole tables and whole texts; the rows of a table are told apart by a number."""

from __future__ import annotations

_WORDS = r"regexp_extract_all({}, '[^\x20\x09-\x0D]+')"
_FOLDED = "translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"

#: Every string of 200 bytes with its place; runs of places that touch are one removed span.
DEDUP = """
    WITH d AS (SELECT doc_id, row_number() OVER () AS rid, encode(coalesce(text, '')) AS b FROM documents),
    p AS (SELECT rid, b, unnest(range(0, octet_length(b) - 199)) AS i FROM d WHERE octet_length(b) >= 200),
    s AS (SELECT rid, i, b[i + 1 : i + 200] AS s FROM p),
    t AS (SELECT rid, i FROM s WHERE s IN (SELECT s FROM s GROUP BY s HAVING count(*) > 1)),
    f AS (SELECT rid, i, CASE WHEN i <= lag(i) OVER w + 200 THEN 0 ELSE 1 END AS fresh FROM t WINDOW w AS (PARTITION BY rid ORDER BY i)),
    g AS (SELECT rid, i, sum(fresh) OVER (PARTITION BY rid ORDER BY i ROWS UNBOUNDED PRECEDING) AS k FROM f),
    r AS (SELECT rid, k, min(i) AS lo, max(i) + 200 AS hi FROM g GROUP BY rid, k),
    e AS (SELECT rid, lo, hi, true AS gone FROM r UNION ALL SELECT rid, octet_length(b), octet_length(b), false FROM d),
    c AS (SELECT e.rid, lo, hi, gone, b[coalesce(lag(hi) OVER (PARTITION BY e.rid ORDER BY lo, hi), 0) + 1 : lo] AS piece FROM e JOIN d ON e.rid = d.rid),
    k AS (SELECT rid, sum(hi - lo)::BIGINT AS n_removed, count_if(gone)::BIGINT AS n_spans, unhex(string_agg(hex(piece), '' ORDER BY lo, hi)) AS kept FROM c GROUP BY rid)
    SELECT doc_id, octet_length(b)::BIGINT AS n_bytes, n_removed, n_spans, sha256(kept) AS kept_sha256 FROM d JOIN k ON d.rid = k.rid"""

#: SHA-1 in base32: each five hexadecimal digits are four of its letters.
ARCHIVES = """
    WITH p AS (SELECT page_id, coalesce(html, '') AS h FROM pages),
    d AS (SELECT page_id, octet_length(encode(h))::BIGINT AS n, sha1(h) AS hex, max(page_id) OVER (PARTITION BY h) AS leader FROM p),
    f AS (SELECT *, leader IS NOT NULL AND coalesce(page_id < leader, true) AS again,
                 [('0x' || hex[5 * (i // 4) + 1 : 5 * (i // 4) + 5])::BIGINT >> (15 - 5 * (i % 4)) & 31 FOR i IN range(0, 32)] AS five FROM d)
    SELECT page_id, n AS payload_bytes, array_to_string(['ABCDEFGHIJKLMNOPQRSTUVWXYZ234567'[x + 1] FOR x IN five], '') AS payload_digest,
           CASE WHEN again THEN 'revisit' ELSE 'response' END AS record_type, CASE WHEN again THEN leader END::BIGINT AS refers_to FROM f"""

#: Shared shingles counted by a join on the shingle, then what can be reached.
JACCARD = f"""
    WITH RECURSIVE w AS (SELECT doc_id, row_number() OVER () AS rid, {_WORDS.format(_FOLDED)} AS w FROM documents),
    s AS (SELECT DISTINCT rid, unnest(CASE WHEN len(w) = 0 THEN [] WHEN len(w) < 4 THEN [array_to_string(w, ' ')] ELSE [array_to_string(w[i : i + 3], ' ') FOR i IN range(1, len(w) - 2)] END) AS s FROM w),
    n AS (SELECT rid, count(*) AS n FROM s GROUP BY rid),
    i AS (SELECT a.rid AS a, b.rid AS b, count(*) AS n FROM s a JOIN s b ON a.s = b.s AND a.rid <> b.rid GROUP BY 1, 2),
    l AS (SELECT i.a, i.b FROM i JOIN n x ON x.rid = i.a JOIN n y ON y.rid = i.b WHERE 100 * i.n >= 85 * (x.n + y.n - i.n)),
    r AS (SELECT a, b FROM l UNION SELECT r.a, l.b FROM r JOIN l ON r.b = l.a),
    c AS (SELECT a, min(w.doc_id) AS least FROM r JOIN w ON r.b = w.rid GROUP BY a)
    SELECT w.doc_id, coalesce(n.n, 0)::BIGINT AS n_shingles, least(w.doc_id, coalesce(c.least, w.doc_id)) AS component_id
    FROM w LEFT JOIN n ON w.rid = n.rid LEFT JOIN c ON w.rid = c.a"""


def _under(width: int) -> str:
    """(rid, n): words under windows of ``width`` words that stand in the text twice or more."""
    return f"""SELECT rid, count(DISTINCT i + k)::BIGINT AS n FROM (
        SELECT rid, i, count(*) OVER (PARTITION BY rid, g) AS copies FROM (
          SELECT rid, i, array_to_string(w[i : i + {width - 1}], ' ') AS g FROM (SELECT rid, w, unnest(range(1, len(w) - {width - 2})) AS i FROM w WHERE len(w) >= {width}))), range(0, {width}) x(k)
      WHERE copies > 1 GROUP BY rid"""


#: The longest repeat is the longest run of equal three-word windows at one distance, and two words.
QUALITY = f"""
    WITH w AS (SELECT doc_id, row_number() OVER () AS rid, coalesce(text, '') AS text, {_WORDS.format("coalesce(text, '')")} AS w FROM documents),
    u AS ({_under(3)}), v AS ({_under(8)}),
    t AS (SELECT rid, i, array_to_string(w[i : i + 2], ' ') AS g FROM (SELECT rid, w, unnest(range(1, len(w) - 1)) AS i FROM w WHERE len(w) >= 3)),
    q AS (SELECT a.rid, a.i, b.i - a.i AS d FROM t a JOIN t b ON a.rid = b.rid AND a.g = b.g AND a.i < b.i),
    z AS (SELECT rid, d, i - row_number() OVER (PARTITION BY rid, d ORDER BY i) AS k FROM q),
    y AS (SELECT rid, max(n) + 2 AS longest FROM (SELECT rid, count(*) AS n FROM z GROUP BY rid, d, k) GROUP BY rid),
    o AS (SELECT rid, (len(x) - len(list_distinct(x)))::BIGINT AS n FROM (SELECT rid, [x FOR x IN str_split(text, chr(10)) IF regexp_matches(x, '[^\\x20\\x09-\\x0D]')] AS x FROM w)),
    m AS (SELECT doc_id, len(w)::BIGINT AS n_words, length(array_to_string(w, ''))::BIGINT AS word_chars, len(regexp_extract_all(text, '[#*$%&|<>]'))::BIGINT AS n_symbols, o.n AS n_dup_lines,
                 coalesce(u.n, 0) AS n_repeat_words, coalesce(v.n, 0) AS covered_words, coalesce(y.longest, 0)::BIGINT AS longest_repeat
          FROM w JOIN o ON o.rid = w.rid LEFT JOIN u ON u.rid = w.rid LEFT JOIN v ON v.rid = w.rid LEFT JOIN y ON y.rid = w.rid),
    b AS (SELECT *, n_words < 50 OR 100 * n_repeat_words > 50 * n_words AS base_failed FROM m)
    SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed,
           NOT (base_failed OR 10 * covered_words > 4 * n_words OR longest_repeat > 300) AS kept, covered_words, longest_repeat FROM b"""

#: Brute force over all pairs of queries and vectors.
TOP_K = """
    WITH v AS (
      SELECT vec_id, [floor(256 * x::DOUBLE) FOR x IN embedding] AS e FROM embeddings
      WHERE vec_id IS NOT NULL AND embedding IS NOT NULL AND len([x FOR x IN embedding IF x IS NULL OR NOT isfinite(x)]) = 0),
    s AS (
      SELECT q.vec_id AS query_id, c.vec_id, list_dot_product(q.e, c.e)::BIGINT AS score
      FROM v q JOIN v c ON q.vec_id <> c.vec_id WHERE q.vec_id % 50 = 0),
    r AS (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS rank FROM s)
    SELECT query_id, rank::INTEGER AS rank, vec_id, score FROM r WHERE rank <= 5"""

SQL = {
    "op1_suffix_merge_dedup": DEDUP,
    "op2_chunked_warc": ARCHIVES,
    "op4_adaptive_prefix_join": JACCARD,
    "op7_vector_approximation": TOP_K,
    "op10_suffix_repetition": QUALITY,
}
