"""Queries over whole tables with production parameters, one for each operator."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import table


def op1_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .packing import pack

    return pack(table(spark, sf_dir, "documents"))


def op2_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .quality import score_quality

    return score_quality(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op3_revisits(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .revisit import records_of_pages, resolve_revisits

    found = resolve_revisits(records_of_pages(table(spark, sf_dir, "pages")))
    lines = F.transform(F.array_sort(F.map_entries("headers")), lambda e: F.concat(e["key"], F.lit(": "), e["value"]))
    return found.withColumn("headers", F.array_join(lines, "; "))


OP3_SQL = r"""
WITH u0 AS (SELECT page_id, md5(coalesce(html, '')) AS digest, CAST(length(coalesce(html, '')) AS VARCHAR) AS n,
  regexp_replace(regexp_replace(url, '#.*$', ''), '^[A-Za-z][A-Za-z0-9+.-]*://', '') AS bare FROM pages),
u1 AS (SELECT page_id, digest, n,
  regexp_replace(regexp_replace(lower(regexp_extract(bare, '^[^/?]*', 0)), ':(80|443)$', ''), '^www[0-9]*\.', '') AS host,
  regexp_replace(regexp_extract(bare, '^[^/?]*([^?]*)', 1), '/+$', '') AS path,
  array_to_string(list_sort(list_filter(string_split(regexp_extract(bare, '\?(.*)$', 1), '&'), lambda p: p <> '' AND NOT regexp_matches(p, '^(utm_[a-z]+|ref)='))), '&') AS query FROM u0),
u AS (SELECT page_id, digest, n, host || path || CASE WHEN query <> '' THEN '?' || query ELSE '' END AS u FROM u1),
v AS (SELECT *, page_id * 2 + 1 AS record_id, CASE WHEN page_id % 11 = 0 THEN page_id * 2 - 1 ELSE page_id * 2 + 2001 END AS ts FROM u),
j AS (SELECT v.record_id, v.u, v.ts, v.digest, o.page_id * 2 AS oid, o.digest AS od, o.n,
  row_number() OVER (PARTITION BY v.record_id ORDER BY o.page_id DESC NULLS LAST) AS k
  FROM v LEFT JOIN u o ON o.u = v.u AND o.page_id * 2 < v.ts)
SELECT record_id, u AS canonical_url, ts, oid AS original_id, oid AS original_ts,
  CASE WHEN oid IS NULL THEN 'no_original' WHEN od = digest THEN 'resolved' ELSE 'mismatch' END AS status,
  CASE WHEN od = digest THEN 'cache-control: max-age=300; content-length: ' || n || '; content-type: text/html; date: ' || CAST(ts AS VARCHAR) || '; etag: ' || od END AS headers
FROM j WHERE k = 1
"""


def op4_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .pii import find_spans

    return find_spans(table(spark, sf_dir, "documents"))


def op5_multi_index(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .multi_index import search

    return search(table(spark, sf_dir, "embeddings"), F.col("vec_id") % 50 == 0)


def op6_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .exact_dedup import exact_dedup

    return exact_dedup(table(spark, sf_dir, "documents")).withColumnRenamed("digest", "text_sha256")


OP6_SQL = r"""
WITH d AS (SELECT doc_id, regexp_replace(coalesce(text, ''), '[ \t\n\x0B\f\r]+', ' ', 'g') AS t FROM documents),
g AS (SELECT t, min(doc_id) AS keep_id, CAST(count(*) AS BIGINT) AS group_size FROM d GROUP BY t)
SELECT d.doc_id, g.keep_id, g.group_size, d.doc_id = g.keep_id AS kept, sha256(d.t) AS text_sha256
FROM d JOIN g USING (t)
"""

def op7_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    from .bpe import digests

    return digests(table(spark, sf_dir, "documents"), public_tokenizers.path("byte_bpe_multi_50k.tiktoken"), public_tokenizers.PATTERN)


def op8_suffix_tree(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .suffix_tree import score_texts

    return score_texts(table(spark, sf_dir, "documents"))


def op9_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .simhash import near_duplicates

    return near_duplicates(table(spark, sf_dir, "documents"))


def op10_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .language import predict_language

    return predict_language(table(spark, sf_dir, "documents"))


QUERIES = {f.__name__: f for f in (op1_packing, op2_quality, op3_revisits, op4_pii, op5_multi_index, op6_exact_dedup, op7_byte_bpe, op8_suffix_tree, op9_simhash, op10_language)}
ORACLES = {"op3_revisits": OP3_SQL, "op6_exact_dedup": OP6_SQL}
