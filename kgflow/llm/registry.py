"""Queries of the text-preparation operators, one per operator, over whole tables."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from kgflow.llm import ann, bpe, decontam, fixity, license, lines, neardup, substring, toxicity, urlfilter
from kgflow.session import ship


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return ship(spark).read.parquet(f"{sf_dir}/{name}.parquet")


def op2_url_filters(spark: SparkSession, sf_dir: str) -> DataFrame:
    return urlfilter.judge(table(spark, sf_dir, "pages"), urlfilter.rule_table(spark))


def op1_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    out = toxicity.score(docs, toxicity.train(docs, table(spark, sf_dir, "labels")))
    return out.select("doc_id", F.col("_severity").alias("severity"), F.col("_grade").alias("grade"), F.col("_toxic").alias("toxic"))


def op5_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = decontam.contaminated(table(spark, sf_dir, "documents").select("doc_id", "text"), table(spark, sf_dir, "benchmark"))
    return out.select("doc_id", (F.size("_found") > 0).alias("contaminated"), F.col("_found.item").alias("items"), F.array_min("_found.edits").alias("least_edits"))


def op3_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return license.digest(license.scan(table(spark, sf_dir, "documents")))


#: Bytes that the damaged replica has at the end of a record, if the record's hash picks it (one in 64).
DAMAGE = "<!-- bit rot -->"


def op4_warc_fixity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Audits pages against a replica in which records picked by a hash of their url and id are damaged."""
    pages = table(spark, sf_dir, "pages").select("page_id", "url", "html")
    hit = F.conv(F.substring(F.md5(F.concat_ws(" ", F.col("page_id").cast("string"), "url")), 1, 4), 16, 10).cast("long") % 64 == 0
    replica = pages.withColumn("html", F.when(hit, F.concat(F.coalesce("html", F.lit("")), F.lit(DAMAGE))).otherwise(F.col("html")))
    return fixity.audit(pages, replica, "page_id", ["url", "html"]).select(F.col("id").cast("long").alias("page_id"), "length", "expected", "found", "status")


def op6_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = substring.deduplicate(table(spark, sf_dir, "documents"))
    return out.select("doc_id", "n_words", "n_removed", F.sha2("kept_text", 256).alias("kept_sha256"))


def op7_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe.round_trip_digests(table(spark, sf_dir, "documents"))


def op8_hnsw_neighbours(spark: SparkSession, sf_dir: str) -> DataFrame:
    vectors = table(spark, sf_dir, "embeddings").select("vec_id", "embedding")
    return ann.nearest(vectors, vectors.where(F.col("vec_id") % 20 == 0), 20)


def op9_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = lines.deduplicate(table(spark, sf_dir, "documents").select("doc_id", "text"))
    return out.select("doc_id", F.col("_lines").alias("n_lines"), F.col("_removed").alias("n_removed"), F.sha2(F.coalesce("text", F.lit("")), 256).alias("kept_sha256"))


def op10_minhash_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return neardup.label_documents(table(spark, sf_dir, "documents"), 85)


OP4_ORACLE = r"""
WITH r AS (
  SELECT page_id, url, html, CASE WHEN ('0x' || substr(md5(concat_ws(' ', page_id::VARCHAR, url)), 1, 4))::BIGINT % 64 = 0 THEN coalesce(html, '') || '<!-- bit rot -->' ELSE html END AS html2 FROM pages),
f AS (
  SELECT *, 'WARC/1.1' || chr(10) || coalesce(strlen(page_id::VARCHAR)::VARCHAR || chr(10) || page_id::VARCHAR, '-' || chr(10)) || coalesce(strlen(url)::VARCHAR || chr(10) || url, '-' || chr(10)) AS head FROM r),
x AS (
  SELECT page_id, head || coalesce(strlen(html)::VARCHAR || chr(10) || html, '-' || chr(10)) AS a, head || coalesce(strlen(html2)::VARCHAR || chr(10) || html2, '-' || chr(10)) AS b FROM f)
SELECT page_id, strlen(a)::BIGINT AS length, sha256(a) AS expected, sha256(b) AS found, CASE WHEN a = b THEN 'intact' ELSE 'corrupt' END AS status FROM x
"""


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {
        "op1_toxicity": op1_toxicity,
        "op2_url_filters": op2_url_filters,
        "op3_license_scan": op3_license_scan,
        "op4_warc_fixity": op4_warc_fixity,
        "op5_decontamination": op5_decontamination,
        "op6_substring_dedup": op6_substring_dedup,
        "op7_byte_bpe": op7_byte_bpe,
        "op8_hnsw_neighbours": op8_hnsw_neighbours,
        "op9_line_dedup": op9_line_dedup,
        "op10_minhash_near_dedup": op10_minhash_near_dedup,
    }


def oracle_sql() -> dict[str, str]:
    return {
        "op2_url_filters": urlfilter.ORACLE,
        "op3_license_scan": license.oracle(),
        "op4_warc_fixity": OP4_ORACLE,
        "op6_substring_dedup": substring.ORACLE,
        "op9_line_dedup": lines.ORACLE,
        "op10_minhash_near_dedup": neardup.ORACLE,
    }
