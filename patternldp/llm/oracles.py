"""DuckDB SQL for the queries that SQL can express."""

ORACLES: dict[str, str] = {}

ORACLES["op3_host_quality"] = r"""
WITH base AS (
  SELECT row_number() OVER () AS rid, doc_id, source, coalesce(text, '') AS t FROM documents
), words AS (
  SELECT rid, regexp_extract_all(t, '[^\x20\x09-\x0D]+') AS w FROM base
), wins AS (
  SELECT rid, i, array_to_string(w[i:i+4], ' ') AS g
  FROM (SELECT rid, w, unnest(range(1, greatest(len(w) - 3, 1))) AS i FROM words)
), twice AS (
  SELECT rid, i FROM (SELECT rid, i, count(*) OVER (PARTITION BY rid, g) AS c FROM wins) WHERE c > 1
), covered AS (
  SELECT rid, count(DISTINCT i + j) AS n FROM twice, (SELECT unnest(range(0, 5)) AS j) GROUP BY rid
), lines AS (
  SELECT rid, line, count(*) AS c
  FROM (SELECT rid, unnest(string_split(t, chr(10))) AS line FROM base)
  WHERE regexp_matches(line, '[^\x20\x09-\x0D]') GROUP BY rid, line
), dups AS (
  SELECT rid, sum(c - 1) AS n_dup, sum(c) AS n_lines FROM lines GROUP BY rid
), m AS (
  SELECT b.rid, b.doc_id, b.source, CAST(len(w) AS BIGINT) AS n_words,
         CAST(len(array_to_string(w, '')) AS BIGINT) AS word_chars,
         CAST(len(t) - len(regexp_replace(t, '[#*$%&|<>]', '', 'g')) AS BIGINT) AS n_symbols,
         CAST(coalesce(n_dup, 0) AS BIGINT) AS n_dup_lines,
         CAST(coalesce(n, 0) AS BIGINT) AS n_repeat_words, coalesce(n_lines, 0) AS n_lines
  FROM base b JOIN words USING (rid) LEFT JOIN covered USING (rid) LEFT JOIN dups USING (rid)
), hosts AS (
  SELECT source, count(*) AS n, sum(CAST(n_words < 10 AS INT)) AS f1,
         sum(CAST(100 * n_repeat_words > 20 * n_words AS INT)) AS f2,
         sum(CAST(n_symbols > n_words AS INT)) AS f3, sum(CAST(2 * n_dup_lines > n_lines AS INT)) AS f4
  FROM m GROUP BY source
), long AS (
  UNPIVOT hosts ON f1, f2, f3, f4 INTO NAME rule VALUE f
), prior AS (
  SELECT rule, avg(f / n) AS mu, var_pop(f / n) AS v, avg(1 / n) AS chance FROM long GROUP BY rule
), verdict AS (
  SELECT source, max(rate - 2.0 * sqrt(rate * (1 - rate) / (n + s + 1)) - mu) > 0.2 AS bad
  FROM (SELECT *, (f + mu * s) / (n + s) AS rate FROM (SELECT *, greatest(1.0, least(1e6, mu * (1 - mu) / greatest(v - mu * (1 - mu) * chance, 1e-12) - 1)) AS s FROM long JOIN prior USING (rule)))
  GROUP BY source
)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words,
       (n_words < 10 OR 100 * n_repeat_words > 20 * n_words) AS base_failed,
       NOT (n_words < 10 OR 100 * n_repeat_words > 20 * n_words) AND NOT bad AS kept
FROM m JOIN verdict ON m.source IS NOT DISTINCT FROM verdict.source
"""

ORACLES["op10_warc"] = r"""
WITH p AS (
  SELECT page_id, coalesce(html, '') AS h, sha1(coalesce(html, '')) AS hex FROM pages
), top AS (
  SELECT hex, max(page_id) AS top FROM p GROUP BY hex
), bits AS (
  SELECT page_id, hex, array_to_string(list_transform(string_split(hex, ''),
         lambda c: lpad(bin(instr('0123456789abcdef', c) - 1), 4, '0')), '') AS b FROM p
), coded AS (
  SELECT page_id, array_to_string(list_transform(range(0, 32),
         lambda i: substr('ABCDEFGHIJKLMNOPQRSTUVWXYZ234567',
              1 + CAST(list_sum(list_transform(range(0, 5), lambda j: CAST(substr(b, CAST(5 * i + j + 1 AS INT), 1) AS INT) * (16 // CAST(pow(2, j) AS INT)))) AS INT), 1)), '') AS d
  FROM bits
)
SELECT p.page_id, CAST(octet_length(encode(h)) AS BIGINT) AS payload_bytes, d AS payload_digest,
       CASE WHEN p.page_id = top THEN 'response' ELSE 'revisit' END AS record_type,
       CASE WHEN p.page_id = top THEN NULL ELSE top END AS refers_to
FROM p JOIN top USING (hex) JOIN coded ON coded.page_id = p.page_id
"""
