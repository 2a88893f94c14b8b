"""DuckDB SQL for those operators that SQL can express."""

_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"

OP6 = rf"""
WITH item AS (
  SELECT item_id, regexp_extract_all(translate(coalesce(text, ''), '{_UPPER}', '{_LOWER}'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w
  FROM benchmark WHERE item_id IS NOT NULL
), win AS (
  SELECT DISTINCT item_id, least(10, len(w)) AS n, array_to_string(w[i:i + least(10, len(w)) - 1], ' ') AS g
  FROM item, unnest(range(1, greatest(len(w) - 9, 1) + 1)) AS r(i) WHERE len(w) > 0
), doc AS (
  SELECT row_number() OVER () AS row_id, doc_id, regexp_extract_all(translate(coalesce(text, ''), '{_UPPER}', '{_LOWER}'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w
  FROM documents
), gram AS (
  SELECT row_id, i, n, array_to_string(w[i:i + n - 1], ' ') AS g
  FROM (SELECT row_id, w, unnest(range(1, len(w) + 1)) AS i FROM doc), (SELECT DISTINCT n FROM win)
  WHERE i + n - 1 <= len(w)
), occ AS (
  SELECT row_id, i, n, item_id FROM gram JOIN win USING (n, g)
), hit AS (
  SELECT row_id, count(DISTINCT i + k) AS n_hit FROM (SELECT DISTINCT row_id, i, n FROM occ), unnest(range(0, n)) AS r(k) GROUP BY 1
), named AS (
  SELECT row_id, count(*) AS n_items, string_agg(item_id::VARCHAR, ',' ORDER BY item_id::VARCHAR) AS ids
  FROM (SELECT DISTINCT row_id, item_id FROM occ) GROUP BY 1
)
SELECT doc_id, len(w)::BIGINT AS n_words, coalesce(n_hit, 0)::BIGINT AS n_hit, coalesce(n_items, 0)::BIGINT AS n_items,
  sha256(coalesce(ids, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated
FROM doc LEFT JOIN hit USING (row_id) LEFT JOIN named USING (row_id)
"""

OP5 = r"""
WITH doc AS (
  SELECT row_number() OVER () AS row_id, doc_id, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS w FROM documents
), win AS (
  SELECT row_id, doc_id, i - 1 AS s, md5(array_to_string(w[i:i + 49], ' ')) AS h
  FROM (SELECT row_id, doc_id, w, unnest(range(1, len(w) - 48)) AS i FROM doc WHERE len(w) >= 50)
), rep AS (
  SELECT h, min(doc_id) AS least FROM win GROUP BY 1 HAVING count(DISTINCT row_id) > 1
), hit AS (
  SELECT row_id, doc_id, s, least, lag(s) OVER (PARTITION BY row_id ORDER BY s) AS before FROM win JOIN rep USING (h)
), island AS (
  SELECT *, sum(CASE WHEN before IS NULL OR s > before + 50 THEN 1 ELSE 0 END) OVER (PARTITION BY row_id ORDER BY s) AS k FROM hit
)
SELECT doc_id, min(s)::BIGINT AS from_word, (max(s) + 50)::BIGINT AS to_word, min(least) AS first_doc_id
FROM island GROUP BY row_id, doc_id, k
"""

ORACLES = {"op5_suffix_repeats": OP5, "op6_decontaminate": OP6}
