"""DuckDB SQL for the operators that SQL can express."""

LOWER = "translate({}, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"

OP1 = rf"""
WITH l AS (
  SELECT doc_id, generate_subscripts(s, 1) AS i, unnest(s) AS line
  FROM (SELECT doc_id, string_split(coalesce(text, ''), chr(10)) AS s FROM documents)
), k AS (
  SELECT doc_id, i, line, {LOWER.format(r"regexp_replace(line, '^[\x20\x09-\x0D]+|[\x20\x09-\x0D]+$', '', 'g')")} AS key FROM l
), f AS (
  SELECT key FROM k WHERE length(key) >= 1 GROUP BY key HAVING count(DISTINCT doc_id) >= 10
)
SELECT doc_id, count(*) AS n_lines, count(f.key) AS n_dropped,
       sha256(coalesce(string_agg(line, chr(10) ORDER BY i) FILTER (f.key IS NULL), '')) AS kept_sha256
FROM k LEFT JOIN f ON k.key = f.key GROUP BY doc_id
"""

WORDS = "regexp_extract_all(" + LOWER.format("coalesce(text, '')") + r", '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+')"

OP3 = f"""
WITH d AS (SELECT doc_id, {WORDS} AS ws FROM documents),
b AS (SELECT item_id, {WORDS} AS ws FROM benchmark),
n AS (
  SELECT DISTINCT item_id, k, array_to_string(ws[p : p + k - 1], ' ') AS span
  FROM (SELECT item_id, ws, least(10, len(ws)) AS k, unnest(range(1, greatest(len(ws) - 9, 1) + 1)) AS p FROM b WHERE len(ws) > 0)
), w AS (
  SELECT doc_id, generate_subscripts(ws, 1) AS p, unnest(ws) AS word FROM d
), r AS (
  SELECT doc_id, p, list(word) OVER (PARTITION BY doc_id ORDER BY p ROWS BETWEEN CURRENT ROW AND 9 FOLLOWING) AS ahead FROM w
), h AS (
  SELECT r.doc_id, r.p, s.k, n.item_id
  FROM r JOIN (SELECT DISTINCT k FROM n) s ON len(r.ahead) >= s.k JOIN n ON n.k = s.k AND n.span = array_to_string(r.ahead[1 : s.k], ' ')
), q AS (
  SELECT doc_id, count(DISTINCT place) AS n_hit FROM (SELECT doc_id, unnest(range(p, p + k)) AS place FROM h) GROUP BY doc_id
), i AS (
  SELECT doc_id, count(*) AS n_items, string_agg(item, ',' ORDER BY item) AS items
  FROM (SELECT DISTINCT doc_id, CAST(item_id AS VARCHAR) AS item FROM h) GROUP BY doc_id
)
SELECT d.doc_id, CAST(len(ws) AS BIGINT) AS n_words, coalesce(n_hit, 0) AS n_hit, coalesce(n_items, 0) AS n_items,
       sha256(coalesce(items, '')) AS items_sha256, n_hit IS NOT NULL AS contaminated
FROM d LEFT JOIN q ON d.doc_id = q.doc_id LEFT JOIN i ON d.doc_id = i.doc_id
"""

OP7 = """
WITH d AS (SELECT doc_id, hex(encode(coalesce(text, ''))) AS h FROM documents),
w AS (SELECT doc_id, p, md5_number(substr(h, 2 * p - 1, 200)) AS m FROM (SELECT doc_id, h, unnest(range(1, length(h) // 2 - 98)) AS p FROM d)),
later AS (SELECT doc_id, p FROM w QUALIFY row_number() OVER (PARTITION BY m ORDER BY doc_id, p) > 1),
islands AS (
  SELECT doc_id, min(p) AS a, max(p) + 100 AS b
  FROM (
    SELECT doc_id, p, sum(fresh) OVER (PARTITION BY doc_id ORDER BY p) AS island
    FROM (SELECT doc_id, p, CASE WHEN p <= lag(p) OVER (PARTITION BY doc_id ORDER BY p) + 100 THEN 0 ELSE 1 END AS fresh FROM later)
  ) GROUP BY doc_id, island
), cuts AS (
  SELECT doc_id, coalesce(lag(b) OVER (PARTITION BY doc_id ORDER BY a), 1) AS s, a AS e
  FROM (SELECT doc_id, a, b FROM islands UNION ALL SELECT doc_id, length(h) // 2 + 1, NULL FROM d)
), kept AS (
  SELECT d.doc_id, sha256(unhex(coalesce(string_agg(substr(h, 2 * s - 1, 2 * (e - s)), '' ORDER BY s), ''))) AS kept_sha256
  FROM d JOIN cuts ON d.doc_id = cuts.doc_id GROUP BY d.doc_id
), sums AS (SELECT doc_id, CAST(sum(b - a) AS BIGINT) AS n_removed, count(*) AS n_spans FROM islands GROUP BY doc_id)
SELECT d.doc_id, length(h) // 2 AS n_bytes, coalesce(n_removed, 0) AS n_removed, coalesce(n_spans, 0) AS n_spans, kept_sha256
FROM d JOIN kept ON d.doc_id = kept.doc_id LEFT JOIN sums ON d.doc_id = sums.doc_id
"""

OP9 = f"""
WITH n AS (SELECT doc_id, {LOWER.format("coalesce(text, '')")} AS t FROM documents),
g AS (SELECT t, max(doc_id) AS keep_id, count(*) AS group_size FROM n GROUP BY t)
SELECT doc_id, keep_id, group_size, doc_id IS NOT DISTINCT FROM keep_id AS kept, sha256(n.t) AS text_sha256
FROM n JOIN g ON n.t = g.t
"""

OP10 = r"""
WITH d AS (
  SELECT doc_id, source, len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+')) AS size,
         md5(coalesce(CAST(doc_id AS VARCHAR), '')) AS h
  FROM documents
), s AS (
  SELECT source, CAST(sum(size) AS BIGINT) AS source_size,
         CAST((row_number() OVER (ORDER BY source NULLS LAST) - 1) % 3 AS INTEGER) AS place
  FROM d GROUP BY source
), w AS (
  SELECT *, CASE place WHEN 0 THEN 5 WHEN 1 THEN 2 ELSE 1 END AS weight FROM s
), p AS (
  SELECT *, (SELECT CAST(sum(source_size) AS BIGINT) FROM w) AS total,
         CAST(coalesce(sum(3 * source_size) OVER o, 0) AS BIGINT) AS capped,
         (SELECT CAST(sum(weight) AS BIGINT) FROM w) - CAST(coalesce(sum(weight) OVER o, 0) AS BIGINT) AS open_weight
  FROM w WINDOW o AS (ORDER BY source_size::DOUBLE / weight, source NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)
), level AS (
  SELECT total - capped AS rest, open_weight
  FROM p WHERE (total - capped)::DOUBLE * weight <= (3 * source_size)::DOUBLE * open_weight::DOUBLE
  ORDER BY source_size::DOUBLE / weight, source NULLS LAST LIMIT 1
), t AS (
  SELECT source, source_size, place,
         CASE WHEN rest::DOUBLE * weight > (3 * source_size)::DOUBLE * open_weight::DOUBLE THEN (3 * source_size)::DOUBLE
              ELSE rest::DOUBLE * weight / open_weight::DOUBLE END AS target
  FROM w, level
), x AS (
  SELECT d.*, t.source_size, t.target, t.place,
         CAST(sum(size) OVER (PARTITION BY d.source ORDER BY h, size ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS BIGINT) - size AS start
  FROM d JOIN t ON d.source IS NOT DISTINCT FROM t.source
), y AS (
  SELECT *, CASE WHEN source_size > 0 THEN CAST(floor(target) AS BIGINT) // source_size ELSE 0 END AS rounds FROM x
), z AS (
  SELECT *, rounds * size + greatest(0, least(size, CAST(floor(target) AS BIGINT) - rounds * source_size - start)) AS taken,
         start / target AS u FROM y
)
SELECT doc_id, size, source_size, target, CAST(taken AS BIGINT) AS taken,
       CASE WHEN taken > 0 THEN round(CASE place
         WHEN 0 THEN (sqrt(2.25 + -2.0 * u) - 1.5) / -1.0
         WHEN 1 THEN u
         ELSE (sqrt(0.25 + 2.0 * u) - 0.5) / 1.0 END, 9) + 0.0 END AS first_position
FROM z
"""


def oracle_sql() -> dict[str, str]:
    return {"op1_line_dedup": OP1, "op3_decontamination": OP3, "op7_suffix_dedup": OP7, "op9_exact_dedup": OP9, "op10_mixing": OP10}
