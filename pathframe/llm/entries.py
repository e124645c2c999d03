"""Queries opN_<name> over the whole tables, and the SQL for those that SQL can express."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from . import counts, decontaminate, licenses, minhash, pages, private, quality, store, transducer, urls
from .common import table


def op1_minhash_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return minhash.find_near_copies(table(spark, sf_dir, "documents"))


def op2_token_id_output(spark: SparkSession, sf_dir: str) -> DataFrame:
    return store.read_documents(spark, store.write_tokens(table(spark, sf_dir, "documents")))


def op3_html_extraction(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pages.extract(table(spark, sf_dir, "pages"))


def op4_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return counts.count_tokens(table(spark, sf_dir, "documents"))


def op5_bpe_transducer(spark: SparkSession, sf_dir: str) -> DataFrame:
    return transducer.encode_texts(table(spark, sf_dir, "documents"))


def op9_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontaminate.scan_documents(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"), spans=True)


def op6_url_filters(spark: SparkSession, sf_dir: str) -> DataFrame:
    return urls.judge_urls(table(spark, sf_dir, "pages"))


def op7_license_scans(spark: SparkSession, sf_dir: str) -> DataFrame:
    return licenses.scan_licenses(table(spark, sf_dir, "documents"))


def op8_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return quality.judge_quality(docs, quality.learn_from(docs, table(spark, sf_dir, "labels")))


def op10_private_data(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return private.find_private(docs, private.fit(docs))


_QUERIES = (
    op1_minhash_near_dedup, op2_token_id_output, op3_html_extraction, op4_token_counts, op5_bpe_transducer, op6_url_filters,
    op7_license_scans, op8_quality_rules, op9_decontamination, op10_private_data,
)


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {f.__name__: f for f in _QUERIES}


def oracle_sql() -> dict[str, str]:
    return {"op6_url_filters": urls.SQL, "op7_license_scans": licenses.oracle_sql()}
