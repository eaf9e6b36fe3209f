"""Query op7: documents without the lines that repeat an earlier line up to one word."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from .common import load
from .lines import dedupe_lines, digest_rows

#: DuckDB: the same rule with whole strings in place of hashes.
ORACLE = r"""
WITH lines AS (
  SELECT doc_id, generate_subscripts(l, 1) - 1 AS line, unnest(l) AS text
  FROM (SELECT doc_id, string_split(coalesce(text, ''), chr(10)) AS l FROM documents)),
words AS (
  SELECT doc_id, line, text, list_filter(regexp_split_to_array(text, '[\x20\x09\x0B\x0C\x0D]+'), lambda x: x <> '') AS w FROM lines),
filled AS (SELECT doc_id, line, w, array_to_string(w, ' ') AS s FROM words WHERE len(w) >= 1),
places AS (SELECT doc_id, line, s, row_number() OVER (PARTITION BY s ORDER BY doc_id, line) AS nth FROM filled),
firsts AS (SELECT l.doc_id, l.line, l.w, l.s FROM filled l JOIN places p ON p.doc_id = l.doc_id AND p.line = l.line WHERE p.nth = 1 AND len(l.w) >= 5),
variants AS (
  SELECT doc_id, line, i, array_to_string(list_concat(w[1:i-1], w[i+1:]), ' ') AS v
  FROM (SELECT doc_id, line, w, unnest(range(1, len(w) + 1)) AS i FROM firsts)
  UNION ALL SELECT doc_id, line, unnest(range(1, len(w) + 2)) AS i, s AS v FROM firsts),
near AS (
  SELECT DISTINCT doc_id, line FROM (
    SELECT doc_id, line, row_number() OVER (PARTITION BY i, v ORDER BY doc_id, line) AS nth FROM variants) WHERE nth > 1),
judged AS (
  SELECT l.doc_id, l.line, l.text, coalesce(p.nth > 1, false) AS exact, n.doc_id IS NOT NULL AS near
  FROM lines l LEFT JOIN places p ON p.doc_id = l.doc_id AND p.line = l.line LEFT JOIN near n ON n.doc_id = l.doc_id AND n.line = l.line)
SELECT doc_id, count(*)::BIGINT AS n_lines, count(*) FILTER (exact)::BIGINT AS n_exact, count(*) FILTER (near)::BIGINT AS n_near,
  sha256(coalesce(string_agg(text, chr(10) ORDER BY line) FILTER (NOT exact AND NOT near), '')) AS kept_sha256
FROM judged GROUP BY doc_id
"""


def op7_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return digest_rows(dedupe_lines(load(spark, sf_dir, "documents")))
