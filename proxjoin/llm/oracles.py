"""DuckDB SQL for the corpus queries that SQL can express on whole tables."""

from __future__ import annotations

OP1 = """
WITH s AS (
  SELECT doc_id, source, CAST(len(regexp_extract_all(coalesce(text, ''), '[^\\x20\\x09-\\x0D]+')) AS BIGINT) AS size FROM documents
), b AS (
  SELECT source, CAST(sum(size) AS BIGINT) AS source_size FROM s GROUP BY source
), r AS (
  SELECT source, source_size, 1 + (row_number() OVER (ORDER BY source NULLS LAST) - 1) % 3 AS w, 3 * source_size AS lim FROM b
), f AS (
  SELECT *, row_number() OVER (ORDER BY lim / w, source NULLS LAST) AS place,
    (CAST(sum(source_size) OVER () AS DOUBLE) - coalesce(sum(lim) OVER q, 0)) / (sum(w) OVER () - coalesce(sum(w) OVER q, 0)) AS level
  FROM r WINDOW q AS (ORDER BY lim / w, source NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)
), o AS (
  SELECT place AS at, level AS water FROM f WHERE lim / w >= level ORDER BY place LIMIT 1
), t AS (
  SELECT source, source_size, CASE WHEN o.at IS NULL OR place < o.at THEN CAST(lim AS DOUBLE) ELSE least(CAST(lim AS DOUBLE), w * o.water) END AS target
  FROM f LEFT JOIN o ON true
), c AS (
  SELECT s.doc_id, s.size, t.source_size, t.target, CASE WHEN t.source_size > 0 THEN t.target / t.source_size ELSE 0.0 END AS rate,
    CAST('0x' || substr(md5('20:' || coalesce(CAST(s.doc_id AS VARCHAR), 'null')), 1, 13) AS BIGINT) / 4503599627370496.0 AS u
  FROM s JOIN t ON s.source IS NOT DISTINCT FROM t.source
), k AS (
  SELECT *, CAST(floor(rate) + CASE WHEN u < rate - floor(rate) THEN 1 ELSE 0 END AS INTEGER) AS copies FROM c
)
SELECT doc_id, size, source_size, target, CAST(size * copies AS BIGINT) AS taken, copies FROM k
"""

OP10 = """
WITH n AS (
  SELECT doc_id, regexp_replace(coalesce(text, ''), '[\\x20\\x09-\\x0D]+', ' ', 'g') AS content FROM documents
)
SELECT doc_id, min(doc_id) OVER w AS keep_id, CAST(count(*) OVER w AS BIGINT) AS group_size, doc_id = min(doc_id) OVER w AS kept, sha256(content) AS text_sha256
FROM n WINDOW w AS (PARTITION BY content)
"""

#: For tables whose doc_ids are unique and not null, as the given ones; tests/llm has brute force for the others.
OP9 = """
WITH d AS (
  SELECT doc_id, regexp_extract_all(coalesce(text, ''), '[^\\x20\\x09-\\x0D]+') AS w FROM documents
), s AS (
  SELECT doc_id, unnest(range(1, len(w) - 18)) AS i, unnest(list_transform(range(1, len(w) - 18), lambda x: array_to_string(w[x : x + 19], ' '))) AS span FROM d
), r AS (
  SELECT doc_id, i, row_number() OVER (PARTITION BY span ORDER BY doc_id, i) AS place FROM s
), gone AS (
  SELECT DISTINCT doc_id, unnest(range(i, i + 20)) AS i FROM r WHERE place > 1
), listed AS (
  SELECT doc_id, unnest(w) AS word, unnest(range(1, len(w) + 1)) AS i FROM d
), k AS (
  SELECT doc_id, string_agg(word, ' ' ORDER BY i) AS kept, count(*) AS n FROM listed ANTI JOIN gone USING (doc_id, i) GROUP BY doc_id
)
SELECT doc_id, CAST(len(w) AS BIGINT) AS n_words, CAST(len(w) - coalesce(n, 0) AS BIGINT) AS n_removed, sha256(coalesce(kept, '')) AS kept_sha256
FROM d LEFT JOIN k USING (doc_id)
"""


def oracle_sql() -> dict[str, str]:
    return {"op1_source_mixing": OP1, "op9_substring_dedup": OP9, "op10_exact_dedup": OP10}
