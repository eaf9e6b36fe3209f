"""Query op9: documents without byte strings that earlier documents hold."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from .common import load
from .substrings import without_repeats

#: DuckDB: every window of 50 bytes, as 100 hexadecimal digits, against the smallest document that holds it.
ORACLE = """
WITH texts AS (SELECT doc_id, hex(encode(coalesce(text, ''))) AS h FROM documents),
parts AS (SELECT doc_id, c, substring(h, 2 * c + 1, 610) AS h FROM (SELECT doc_id, h, unnest(range(0, len(h) // 2 - 49, 256)) AS c FROM texts)),
windows AS (SELECT doc_id, c + i AS i, substring(h, 2 * i + 1, 100) AS w FROM (SELECT doc_id, c, h, unnest(range(0, least(256, len(h) // 2 - 49))) AS i FROM parts)),
firsts AS (SELECT w, min(doc_id) AS doc FROM windows GROUP BY w),
hits AS (SELECT doc_id, i FROM windows JOIN firsts USING (w) WHERE doc < doc_id),
marked AS (SELECT doc_id, i, coalesce(i > 50 + lag(i) OVER (PARTITION BY doc_id ORDER BY i), true)::INTEGER AS fresh FROM hits),
numbered AS (SELECT doc_id, i, sum(fresh) OVER (PARTITION BY doc_id ORDER BY i) AS span FROM marked),
spans AS (SELECT doc_id, min(i) AS a, max(i) + 50 AS b FROM numbered GROUP BY doc_id, span),
ends AS (SELECT doc_id, a, b FROM spans UNION ALL SELECT doc_id, len(h) // 2, NULL FROM texts),
kept AS (SELECT doc_id, a, b, coalesce(lag(b) OVER (PARTITION BY doc_id ORDER BY a, b NULLS LAST), 0) AS z FROM ends)
SELECT doc_id, (any_value(len(h)) // 2)::BIGINT AS n_bytes, coalesce(sum(b - a), 0)::BIGINT AS n_removed, count(b)::BIGINT AS n_spans,
  sha256(unhex(string_agg(substring(h, 2 * z + 1, 2 * (a - z)), '' ORDER BY a, b NULLS LAST))) AS kept_sha256
FROM kept JOIN texts USING (doc_id) GROUP BY doc_id
"""


def op9_suffix_array(spark: SparkSession, sf_dir: str) -> DataFrame:
    return without_repeats(load(spark, sf_dir, "documents"))
