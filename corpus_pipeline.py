"""A training corpus from documents: five stages, each over all that the one before kept.

quality classifier -> SimHash near-dedup -> secret scan -> mixing -> byte-level
BPE. Every stage's result is written as Parquet in the shared checkpoint folder
and read again as the next one's documents.
"""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from linkblock.llm import bpe, mixing, ordinal, secrets, simhash
from linkblock.runtime import ensure_checkpoint_dir

Stage = Callable[[SparkSession, DataFrame, str], DataFrame]


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keep documents whose probability of the top grade is at least a half."""
    model = ordinal.fit(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    return ordinal.select_documents(docs, model)


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keep the document of the least id of every group of near copies."""
    return simhash.one_of_each(docs)


def secret_scan(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Replace every secret in the texts by its kind; all documents stay."""
    return secrets.redact_documents(docs)


def mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Repeat or leave out documents so that sources meet their target words."""
    return mixing.repeat_documents(docs)


def tokens(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token ids of every document of the mix: doc_id, n_tokens, digests of ids and of decoded bytes."""
    return bpe.round_trip(docs, *bpe.public_vocabulary())


STAGES: list[tuple[str, Stage]] = [
    ("quality_classifier", quality), ("simhash_near_dedup", near_dedup), ("secret_scan", secret_scan), ("source_mixing", mix), ("byte_bpe", tokens),
]

#: Hashed sketches, trained weights and merges aren't expressible in SQL; tests hold run() against a brute-force version.
ORACLE_SQL: str | None = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The stages in order over sf_dir's documents."""
    ensure_checkpoint_dir(spark)
    base = f"{spark.sparkContext.getCheckpointDir()}/pipeline-{uuid.uuid4().hex}"
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for at, (name, stage) in enumerate(STAGES):
        stage(spark, docs, sf_dir).write.parquet(f"{base}/{at}-{name}")
        docs = spark.read.parquet(f"{base}/{at}-{name}")
    return docs.select(*(F.col(c) for c in docs.columns))
