"""Queries of the operators of this subpackage, one each, over their whole tables; SQL where it can say the same."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

import corpus_pipeline
from writelite.llm import bpe, decontam, fingerprint, licenses, lines, ngram_join, quality, sharding, substring, token_store
from writelite.llm.common import documents


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


QUERIES = {
    "op1_quality_rules": lambda spark, d: quality.report(documents(spark, d), _table(spark, d, "labels")),
    "op2_ngram_jaccard_join": lambda spark, d: ngram_join.report(documents(spark, d)),
    "op3_byte_bpe": lambda spark, d: bpe.report(documents(spark, d)),
    "op4_license_scan": lambda spark, d: licenses.report(documents(spark, d)),
    "op5_token_store": lambda spark, d: token_store.report(documents(spark, d)),
    "op6_substring_dedup": lambda spark, d: substring.report(documents(spark, d)),
    "op7_line_dedup": lambda spark, d: lines.report(documents(spark, d)),
    "op7_line_dedup_distinct": lambda spark, d: lines.report(documents(spark, d), distinct=True),
    "op8_decontamination": lambda spark, d: decontam.report(documents(spark, d), _table(spark, d, "benchmark")),
    "op9_sharding": lambda spark, d: sharding.shard(documents(spark, d)),
    "op10_fingerprints": lambda spark, d: fingerprint.with_edits(documents(spark, d)),
    "op10_near_texts": lambda spark, d: fingerprint.near_report(documents(spark, d)),
    "pipeline": corpus_pipeline.run,
}

SQL = {"op4_license_scan": licenses.report_sql(), "op7_line_dedup": lines.REPORT_SQL, "op7_line_dedup_distinct": lines.DISTINCT_SQL}
if corpus_pipeline.ORACLE_SQL:
    SQL["pipeline"] = corpus_pipeline.ORACLE_SQL
