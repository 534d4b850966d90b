"""DuckDB statements for the queries that SQL can express, written from the contracts and not from the operators."""

from __future__ import annotations

from shardweave.llm.rules import STOP_WORDS

_WORD = r"'[^\x20\x09-\x0D]+'"
_STOPS = ", ".join(f"'{w}'" for w in STOP_WORDS)

MIXING_SQL = rf"""
WITH t AS (
  SELECT doc_id, source, coalesce(text, '') AS t, len(regexp_extract_all(coalesce(text, ''), {_WORD})) AS size,
    list_filter(string_split(coalesce(text, ''), chr(10)), lambda x: regexp_matches(x, {_WORD})) AS lines
  FROM documents
), d AS (
  SELECT *, CASE WHEN len(lines) = 0 THEN 0.0::DOUBLE ELSE (len(lines) - len(list_distinct(lines)))::DOUBLE / len(lines) END AS again,
    CASE WHEN size = 0 THEN 0.0::DOUBLE ELSE length(regexp_replace(t, '[^#*$%&|<>]+', '', 'g'))::DOUBLE / size END AS symbols
  FROM t
), k AS (
  SELECT doc_id, source, size,
    -ln((('0x' || substr(md5('42|' || coalesce(doc_id::VARCHAR, 'null') || '|' || md5(t)), 1, 13))::BIGINT + 0.5::DOUBLE) / 4503599627370496::DOUBLE)
    / greatest(0.05::DOUBLE, CASE WHEN t = '' THEN 0.0::DOUBLE ELSE length(regexp_replace(t, '[^\p{{L}}]+', '', 'g'))::DOUBLE / length(t) END
      * (1 - again) * (1 - least(1.0::DOUBLE, symbols))) AS key
  FROM d
), s AS (
  SELECT source, sum(size)::BIGINT AS source_size, row_number() OVER (ORDER BY source NULLS LAST) AS nth FROM d GROUP BY source
), w AS (
  SELECT *, CASE (nth - 1) % 3 WHEN 0 THEN 5.0::DOUBLE WHEN 1 THEN 2.0::DOUBLE ELSE 1.0::DOUBLE END AS weight, 3.0::DOUBLE * source_size AS cap FROM s
), r AS (
  SELECT *, (sum(source_size) OVER ()
      - coalesce(sum(cap) OVER (ORDER BY cap / weight, source NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0.0))
    / (sum(weight) OVER ()
      - coalesce(sum(weight) OVER (ORDER BY cap / weight, source NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0.0)) AS level
  FROM w
), g AS (
  SELECT source, source_size, least(cap, (SELECT coalesce(arg_min(level, cap / weight), 'inf'::DOUBLE) FROM r AS q WHERE q.cap > q.level * q.weight) * weight) AS target
  FROM r
), e AS (
  SELECT k.doc_id, k.size, g.source_size, g.target,
    CASE WHEN g.source_size = 0 THEN 0.0::DOUBLE ELSE floor(g.target / g.source_size) END AS epochs,
    coalesce(sum(k.size) OVER (PARTITION BY k.source ORDER BY k.key, k.doc_id::VARCHAR, k.size ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS before
  FROM k JOIN g ON k.source IS NOT DISTINCT FROM g.source
)
SELECT doc_id, size::BIGINT AS size, source_size, target,
  (size * (epochs + CASE WHEN target - epochs * source_size > 0 AND before + size / 2.0::DOUBLE <= target - epochs * source_size THEN 1 ELSE 0 END))::BIGINT AS taken
FROM e
"""

WARC_SQL = """
WITH p AS (
  SELECT page_id, encode(coalesce(html, '')) AS body FROM pages
), q AS (
  SELECT page_id, octet_length(body)::BIGINT AS payload_bytes, sha1(body) AS payload_digest FROM p
), m AS (
  SELECT *, max(page_id) OVER (PARTITION BY payload_digest, payload_bytes) AS newest FROM q
)
SELECT page_id, payload_bytes, payload_digest,
  CASE WHEN payload_bytes >= 1000 AND page_id <> newest THEN 'revisit' ELSE 'response' END AS record_type,
  CASE WHEN payload_bytes >= 1000 AND page_id <> newest THEN newest END AS refers_to
FROM m
"""

RULES_SQL = rf"""
WITH t AS (
  SELECT doc_id, coalesce(text, '') AS text, regexp_extract_all(coalesce(text, ''), {_WORD}) AS w,
    list_filter(string_split(coalesce(text, ''), chr(10)), lambda x: regexp_matches(x, {_WORD})) AS lines
  FROM documents
), win AS (
  SELECT doc_id, i, array_to_string(w[i : i + 4], ' ') AS g
  FROM (SELECT doc_id, w, unnest(range(1, len(w) - 3)) AS i FROM t WHERE len(w) >= 5)
), twice AS (
  SELECT doc_id, i FROM win QUALIFY count(*) OVER (PARTITION BY doc_id, g) > 1
), spots AS (
  SELECT doc_id, count(DISTINCT i + o)::BIGINT AS n FROM twice, range(0, 5) AS s(o) GROUP BY doc_id
), c AS (
  SELECT t.doc_id, len(w)::BIGINT AS n_words, length(array_to_string(w, ''))::BIGINT AS word_chars,
    length(regexp_replace(text, '[^#*$%&|<>]+', '', 'g'))::BIGINT AS n_symbols,
    (len(lines) - len(list_distinct(lines)))::BIGINT AS n_dup_lines, len(lines) AS n_lines, coalesce(spots.n, 0)::BIGINT AS n_repeat_words,
    len(list_filter(w, lambda x: lower(x) IN ({_STOPS}))) AS n_stop, len(list_filter(w, lambda x: ends_with(x, '!!'))) AS n_shouted
  FROM t LEFT JOIN spots USING (doc_id)
)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words,
  n_words < 10 OR 100 * n_repeat_words > 20 * n_words AS base_failed,
  n_words >= 10 AND 100 * n_repeat_words <= 20 * n_words
    AND word_chars >= 2 * n_words AND word_chars <= 12 * n_words AND 100 * n_symbols <= 10 * n_words AND 100 * n_dup_lines <= 40 * n_lines
    AND (100 * n_stop >= 2 * n_words OR n_words < 50) AND 100 * n_shouted <= 30 * n_words AS kept
FROM c
"""

BALLTREE_SQL = """
WITH v AS (
  SELECT vec_id, list_transform(embedding, lambda x: floor(256 * x::DOUBLE)) AS x FROM embeddings
  WHERE embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0
), s AS (
  SELECT q.vec_id AS query_id, c.vec_id, list_inner_product(q.x, c.x)::BIGINT AS score
  FROM v AS q JOIN v AS c ON q.vec_id % 50 = 0 AND q.vec_id <> c.vec_id
), r AS (
  SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id)::INTEGER AS rank FROM s
)
SELECT query_id, rank, vec_id, score FROM r WHERE rank <= 5
"""


def _crc32(digits: str) -> str:
    """The checksum of hexadecimal bytes in DuckDB, byte by byte; ``tab`` must be in scope."""
    start = f"list_transform(range(length({digits}) // 2), lambda i: ('0x' || substr({digits}, 2 * i + 1, 2))::BIGINT)"
    return f"xor(list_reduce(list_prepend(4294967295::BIGINT, {start}), lambda a, x: xor(a >> 8, tab[(xor(a, x) & 255) + 1])), 4294967295)"


JUMP_SQL = f"""
WITH RECURSIVE t AS (
  SELECT list(v ORDER BY n) AS tab FROM (
    SELECT n, list_reduce(list_prepend(n, range(8)), lambda c, k: CASE WHEN c & 1 = 1 THEN xor(c >> 1, 3988292384) ELSE c >> 1 END) AS v
    FROM (SELECT unnest(range(256)) AS n))
), h AS MATERIALIZED (
  SELECT doc_id, hex(encode(coalesce(text, ''))) AS of_text FROM documents
), e AS (
  SELECT doc_id, length(of_text) // 2 + 16 AS size, {_crc32("of_text")}::BIGINT AS text_crc32 FROM h, t
), n AS MATERIALIZED (
  SELECT *, hex(encode(coalesce(doc_id, 0)::VARCHAR || '|' || size || '|' || text_crc32)) AS of_row FROM e
), d AS (
  SELECT doc_id, size, text_crc32, {_crc32("of_row")} % 1024 AS bucket FROM n, t
), j AS (
  SELECT doc_id, n, doc_id::HUGEINT AS key, -1::BIGINT AS b, 0::BIGINT AS ahead FROM (SELECT DISTINCT doc_id FROM documents), (VALUES (40), (41)) AS s(n)
  UNION ALL
  SELECT doc_id, n, next, ahead, floor((ahead + 1) * (2147483648::DOUBLE / ((next // 8589934592) + 1)::DOUBLE))::BIGINT
  FROM (SELECT *, (key * 2862933555777941757 + 1) % 18446744073709551616::HUGEINT AS next FROM j WHERE ahead < n)
), g AS (
  SELECT doc_id, max(b) FILTER (n = 40)::INTEGER AS shard, max(b) FILTER (n = 41)::INTEGER AS grown_shard FROM j GROUP BY doc_id
)
SELECT doc_id, size::BIGINT AS size, text_crc32::BIGINT AS text_crc32, 'key' AS law, shard, grown_shard,
  row_number() OVER (PARTITION BY shard ORDER BY bucket, doc_id, size, text_crc32) - 1 AS slot
FROM d JOIN g USING (doc_id)
"""
