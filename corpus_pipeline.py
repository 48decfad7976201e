"""From raw documents to a training mixture: five stages, each written and read again by the next.

1. language: documents whose language is not recognised go.
2. near_duplicates: one document of each SimHash component stays.
3. decontamination: documents contaminated by benchmark passages go.
4. secrets: findings of the secret scan are masked in the texts.
5. mixture: documents that target weights take, with how often each comes.

Every stage but the last returns the columns of ``documents``.

Edge cases, stage by stage: texts that are null or hold no letter have no language and go (1); rows that share a doc_id but not the text
are judged by their texts, repeated rows count as one, rows without a doc_id stay (2); texts without words are clean (3) and
without findings stay as they are (4); rows without a language, source or tokens belong to a leaf of their own (5).  Extra columns
are kept by every stage, whatever their names; an empty table gives an empty one.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession

from ruleclosure.durable import forget, shared_folder
from ruleclosure.llm import decontaminate, language_id, mixture, secret_scan, ship_by_value, simhash

ship_by_value()


def language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return language_id.keep_known(docs)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return simhash.keep_first(docs)


def decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return decontaminate.drop_contaminated(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return secret_scan.redact(docs)


def mixing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return mixture.select(docs)


STAGES = [
    ("language", language),
    ("near_duplicates", near_duplicates),
    ("decontamination", decontamination),
    ("secrets", secrets),
    ("mixture", mixing),
]

#: SQL has no language models or fingerprints; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``; each stage's files go once the next one has written its own."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    folder = f"{shared_folder(spark)}/pipeline-{uuid.uuid4().hex}"
    for k, (name, stage) in enumerate(STAGES):
        stage(spark, docs, sf_dir).write.parquet(f"{folder}/{k}-{name}")
        docs = spark.read.parquet(f"{folder}/{k}-{name}")
        if k:
            forget(spark, f"{folder}/{k - 1}-{STAGES[k - 1][0]}")
    return docs
