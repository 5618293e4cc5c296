"""The operators applied to their whole tables, and their SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from erfocus.llm import decontaminate, license_scan, line_dedup, lm_score, packing, quality, simhash, suffix_dedup, url_filter, warc


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontaminate.digest(decontaminate.scan(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark")))


def op2_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash.near_duplicates(table(spark, sf_dir, "documents"))


def op3_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = line_dedup.line_report(table(spark, sf_dir, "documents"))
    return found.select("doc_id", "n_lines", "n_boilerplate", "n_removed", F.sha2(F.col("cleaned_text").cast("binary"), 256).alias("text_sha256"))


def op4_lm_score(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    model = lm_score.train(docs.where(~lm_score.held_out("doc_id")))
    return lm_score.score(docs, model)


def op5_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    return url_filter.judge(table(spark, sf_dir, "pages"))


def op6_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(table(spark, sf_dir, "documents"))


def op7_suffix_array(spark: SparkSession, sf_dir: str) -> DataFrame:
    return suffix_dedup.repeated_spans(table(spark, sf_dir, "documents"))


def op8_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return license_scan.scan(table(spark, sf_dir, "documents"))


def op9_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    return warc.round_trip(table(spark, sf_dir, "pages"))


def op10_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality.judge(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


QUERIES = {f.__name__: f for f in (op1_decontamination, op2_simhash, op3_line_dedup, op4_lm_score, op5_url_filter, op6_packing, op7_suffix_array, op8_license_scan, op9_warc, op10_quality_rules)}

ORACLE_SQL = {
    "op1_decontamination": decontaminate.DIGEST_SQL,
    "op3_line_dedup": line_dedup.REPORT_SQL,
    "op5_url_filter": url_filter.VERDICT_SQL,
    "op8_license_scan": license_scan.scan_sql(),
    "op9_warc": warc.ROUND_TRIP_SQL,
    "op10_quality_rules": quality.judge_sql(),
}
