"""One query per operator, over its whole table with production parameters, and its SQL where there is one."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from . import bloom_lm, chat_format, decontaminate, language_id, mixture, quartile_digest, secret_scan, ship_by_value, simhash, suffix_dedup, url_filter

ship_by_value()

Query = Callable[[SparkSession, str], DataFrame]


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def queries() -> dict[str, Query]:
    documents = lambda f: lambda spark, d: f(table(spark, d, "documents"))
    return {
        "op1_url_filters": lambda spark, d: url_filter.report(spark, table(spark, d, "pages")),
        "op2_chat_formatting": lambda spark, d: chat_format.render(table(spark, d, "conversations")),
        "op3_benchmark_decontamination": lambda spark, d: decontaminate.report(table(spark, d, "documents"), table(spark, d, "benchmark")),
        "op4_simhash_near_dedup": documents(simhash.report),
        "op5_lm_scoring": documents(bloom_lm.report),
        "op6_source_mixing": documents(mixture.report),
        "op7_secret_scans": documents(secret_scan.report),
        "op8_language_id": documents(language_id.report),
        "op9_suffix_array_dedup": documents(suffix_dedup.report),
        "op10_document_fingerprints": documents(quartile_digest.report),
    }


def oracle_sql() -> dict[str, str]:
    return {
        "op1_url_filters": url_filter.sql(),
        "op2_chat_formatting": chat_format.SQL,
        "op6_source_mixing": mixture.sql(),
    }
