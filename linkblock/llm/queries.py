"""The ten opN queries and their SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from linkblock.llm import bpe, brown, licenses, media, mixing, ordinal, rules, secrets, simhash, urls
from linkblock.llm.common import documents


def op1_licenses(spark: SparkSession, sf_dir: str) -> DataFrame:
    return licenses.scan_licenses(documents(spark, sf_dir))


def op2_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = simhash.near_duplicates(documents(spark, sf_dir))
    return found.select("doc_id", simhash.hex_digits(F.col("fp")).alias("fingerprint"), "component_id")


def op3_urls(spark: SparkSession, sf_dir: str) -> DataFrame:
    return urls.judge_urls(spark.read.parquet(f"{sf_dir}/pages.parquet"))


def op4_quality_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    return ordinal.judge_documents(docs, ordinal.fit(docs, spark.read.parquet(f"{sf_dir}/labels.parquet")))


def op5_media(spark: SparkSession, sf_dir: str) -> DataFrame:
    return media.store_texts(documents(spark, sf_dir))


def op6_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix_documents(documents(spark, sf_dir))


def op7_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rules.judge_quality(documents(spark, sf_dir))


def op8_brown(spark: SparkSession, sf_dir: str) -> DataFrame:
    return brown.train_and_score(documents(spark, sf_dir))


def op9_secrets(spark: SparkSession, sf_dir: str) -> DataFrame:
    return secrets.find_secrets(documents(spark, sf_dir))


def op10_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe.round_trip(documents(spark, sf_dir), *bpe.public_vocabulary())


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {f.__name__: f for f in (op1_licenses, op2_simhash, op3_urls, op4_quality_classifier, op5_media, op6_mixing, op7_quality, op8_brown, op9_secrets, op10_bpe)}


def oracle_sql() -> dict[str, str]:
    return {"op3_urls": urls.oracle(), "op7_quality": rules.oracle()}
