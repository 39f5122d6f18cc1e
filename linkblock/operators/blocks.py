"""Blocks as partitions and covers: overlap, largest blocks, splitting, and turning a cover into a partition."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from linkblock.operators.components import connected_components


def overlap(blocks: DataFrame) -> DataFrame:
    """(blocks_per_record, n): how many records are in how many blocks."""
    return blocks.groupBy("rec_id").agg(F.count_distinct("block_id").alias("blocks_per_record")).groupBy("blocks_per_record").agg(F.count("*").alias("n"))


def top_blocks(blocks: DataFrame, k: int) -> DataFrame:
    """The k largest blocks (block_id, n), ties by id: a report."""
    return blocks.groupBy("block_id").agg(F.count("*").alias("n")).orderBy(F.desc("n"), "block_id").limit(k)


def split_large(blocks: DataFrame, max_size: int, second: DataFrame) -> DataFrame:
    """(block_id, sub, rec_id): blocks over max_size are split by a second key (rec_id, sub_key); others keep sub 0.

    Nothing is dropped: records of a split block all stay in one of its parts.
    """
    sizes = blocks.groupBy("block_id").agg(F.count("*").alias("n"))
    return blocks.join(sizes, "block_id").join(second, "rec_id", "left").select("block_id", F.when(F.col("n") > max_size, F.coalesce("sub_key", F.lit(0))).otherwise(F.lit(0)).cast("bigint").alias("sub"), "rec_id")


def to_partition(records: DataFrame, pairs: DataFrame) -> DataFrame:
    """(rec_id, component): connected components of the pairs; records without a pair are their own component."""
    found = connected_components(pairs, "id_lo", "id_hi")
    return records.select("rec_id").join(found, F.col("rec_id") == F.col("node"), "left").select("rec_id", F.coalesce("root", "rec_id").alias("component"))
