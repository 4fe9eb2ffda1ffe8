"""Registered queries of the corpus operators: whole tables, production parameters."""

from __future__ import annotations

from collections.abc import Callable

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from nearcohort.llm import (
    bpe,
    decontaminate,
    exact_dedup,
    licenses,
    ngram_join,
    passages,
    quality,
    sharding,
    urls,
    warc,
)

SHARDS = 40


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_ngram_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    """doc_id, n_shingles, component_id, class_id of every document."""
    return ngram_join.jaccard_classes(_table(spark, sf_dir, "documents"))


def op2_benchmark_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every document with every benchmark item that it contains."""
    return decontaminate.contaminated(_table(spark, sf_dir, "documents"), _table(spark, sf_dir, "benchmark"))


def op3_bpe_round_trip(spark: SparkSession, sf_dir: str) -> DataFrame:
    """doc_id, n_tokens, ids_sha256, decoded_sha256 of every document."""
    return bpe.round_trip(_table(spark, sf_dir, "documents"), public_tokenizers.path("byte_bpe_50k.json"))


def op4_quality_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    """doc_id, held_out, score, predicted of every document."""
    docs = _table(spark, sf_dir, "documents")
    return quality.score(docs, quality.fit(docs, _table(spark, sf_dir, "labels")))


def op5_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """doc_id, keep_id, group_size, kept, text_sha256 of every document; the largest id stays."""
    return exact_dedup.duplicate_groups(_table(spark, sf_dir, "documents"), keep="largest")


def op6_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every repeated span of every document."""
    return passages.repeated_spans(_table(spark, sf_dir, "documents"))


def op7_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every covered license template with its span, for every document."""
    return licenses.license_spans(_table(spark, sf_dir, "documents"))


def op8_vector_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All documents in shards 0 to 39 of nearly equal bytes."""
    return (sharding.shard(_table(spark, sf_dir, "documents"), SHARDS)
            .select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", "slot",
                    F.lit(None).cast("int").alias("grown_shard"), "n_words"))


def op9_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    """page_id, host, path, rule, verdict and term counts of every page."""
    return urls.judge(_table(spark, sf_dir, "pages"))


def op10_warc_round_trip(spark: SparkSession, sf_dir: str) -> DataFrame:
    """page_id, payload_bytes, payload_digest, record_type, refers_to of every page."""
    return warc.archive_round_trip(_table(spark, sf_dir, "pages")).select(
        "page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    f.__name__: f
    for f in (op1_ngram_jaccard_join, op2_benchmark_decontamination, op3_bpe_round_trip, op4_quality_classifier,
              op5_exact_dedup, op6_substring_dedup, op7_license_scan, op8_vector_sharding, op9_url_filter,
              op10_warc_round_trip)
}

_WORDS = ("regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), "
          "'[^\\x20\\x09-\\x0D]+')")
_SHINGLES = ("CASE WHEN len(w) = 0 THEN [] WHEN len(w) < 5 THEN [array_to_string(w, ' ')] ELSE "
             "list_distinct(list_transform(range(1, len(w) - 3), lambda i: array_to_string(w[i:i + 4], ' '))) END")

ORACLES: dict[str, str] = {
    "op1_ngram_jaccard_join": f"""
WITH RECURSIVE s AS (SELECT doc_id, {_SHINGLES} AS g FROM (SELECT doc_id, {_WORDS} AS w FROM documents)),
n AS (SELECT doc_id, CAST(len(g) AS BIGINT) AS n, md5(array_to_string(list_sort(g), chr(10))) AS sig FROM s),
k AS (SELECT n.*, CASE WHEN n = 0 THEN doc_id ELSE min(doc_id) OVER (PARTITION BY n, sig) END AS class_id FROM n),
e AS MATERIALIZED (SELECT k.doc_id, k.n, unnest(s.g) AS h FROM k JOIN s USING (doc_id) WHERE k.doc_id = k.class_id),
p AS MATERIALIZED (
  SELECT a.doc_id AS a, b.doc_id AS b FROM e a JOIN e b ON a.h = b.h AND a.doc_id <> b.doc_id
  GROUP BY a.doc_id, b.doc_id, a.n, b.n HAVING 100 * count(*) >= 80 * (a.n + b.n - count(*))),
r AS (SELECT a AS id, b AS m FROM p UNION SELECT r.id, p.b FROM r JOIN p ON r.m = p.a)
SELECT k.doc_id, k.n AS n_shingles, least(k.class_id, coalesce(c.m, k.class_id)) AS component_id, k.class_id
FROM k LEFT JOIN (SELECT id, min(m) AS m FROM r GROUP BY id) c ON c.id = k.class_id""",
    "op2_benchmark_decontamination": f"""
WITH d AS (SELECT doc_id, {_WORDS} AS w FROM documents),
b AS (SELECT item_id, least(len(w), 5) AS k, w FROM (SELECT item_id, {_WORDS} AS w FROM benchmark) WHERE len(w) > 0),
be AS (SELECT item_id, k, unnest(list_distinct(list_transform(range(1, len(w) - k + 2), lambda i: array_to_string(w[i:i + k - 1], ' ')))) AS h FROM b),
q AS (SELECT item_id, k, count(*) AS n FROM be GROUP BY ALL),
de AS (SELECT doc_id, k, unnest(list_distinct(list_transform(range(1, len(w) - k + 2), lambda i: array_to_string(w[i:i + k - 1], ' ')))) AS h
       FROM d CROSS JOIN (SELECT DISTINCT k FROM b) WHERE len(w) >= k)
SELECT doc_id, item_id, n AS n_item, count(*) AS n_shared, count(*) / CAST(n AS DOUBLE) AS containment
FROM de JOIN be USING (k, h) JOIN q USING (item_id, k) GROUP BY doc_id, item_id, n HAVING 100 * count(*) >= 80 * n""",
    "op5_exact_dedup": """
WITH t AS (SELECT doc_id, coalesce(text, '') AS text FROM documents)
SELECT doc_id, max(doc_id) OVER (PARTITION BY text) AS keep_id, count(*) OVER (PARTITION BY text) AS group_size,
       doc_id = max(doc_id) OVER (PARTITION BY text) AS kept, sha256(text) AS text_sha256 FROM t""",
    "op9_url_filter": urls.judge_sql(),
    "op10_warc_round_trip": """
WITH t AS (SELECT page_id, coalesce(html, '') AS html FROM pages),
u AS (SELECT page_id, html, CASE WHEN strlen(html) >= 100 THEN min(page_id) OVER (PARTITION BY html) ELSE page_id END AS base FROM t)
SELECT page_id, strlen(html) AS payload_bytes, sha256(html) AS payload_digest,
       CASE WHEN base = page_id THEN 'response' ELSE 'revisit' END AS record_type,
       CASE WHEN base = page_id THEN NULL ELSE base END AS refers_to FROM u""",
}
