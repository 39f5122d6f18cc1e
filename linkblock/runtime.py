"""Session helpers: where to cut lineage, and how."""

from __future__ import annotations

import tempfile

from pyspark.sql import DataFrame, SparkSession


def ensure_checkpoint_dir(spark: SparkSession) -> None:
    """Use the session's spark.checkpoint.dir; fall back only in local mode.

    A machine-local folder would lose data when an executor is lost, so a
    cluster session without the setting is an error rather than a guess.
    """
    sc = spark.sparkContext
    if sc.getCheckpointDir():
        return
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named is None:
        if not sc.master.startswith("local[") and sc.master != "local":
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
        named = tempfile.mkdtemp(prefix="linkblock-checkpoint-")
    sc.setCheckpointDir(named)


def settle(df: DataFrame) -> DataFrame:
    """Write df to the shared checkpoint folder and read from there afterwards."""
    ensure_checkpoint_dir(df.sparkSession)
    return df.checkpoint(eager=True)


def spread(df: DataFrame) -> DataFrame:
    """df over as many partitions as there are cores, if it has fewer: small files of one row group would keep one core busy.

    For tables read from files or settled, whose partitions are known without
    running anything. Larger inputs have more partitions and stay as they are.
    """
    cores = df.sparkSession.sparkContext.defaultParallelism
    return df.repartition(cores) if df.rdd.getNumPartitions() < cores else df
