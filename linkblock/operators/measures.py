"""Recall, split rate, reduction ratio, precision, block profiles and sketch errors, from integer counts."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

_6 = lambda c: F.round(c, 6)


def recall(hit: Column, true: Column) -> Column:
    return hit / F.nullif(true, F.lit(0))


def split_rate(hit: Column, true: Column) -> Column:
    return 1 - recall(hit, true)


def reduction_ratio(pairs: Column, n: Column) -> Column:
    return 1 - pairs / F.nullif(n * (n - 1) / 2, F.lit(0.0))


def precision(hit: Column, pairs: Column) -> Column:
    return hit / F.nullif(pairs, F.lit(0))


def f1(hit: Column, true: Column, pairs: Column) -> Column:
    return 2 * hit / F.nullif(true + pairs, F.lit(0))


def quality(pairs: DataFrame, truth: DataFrame, n: int | DataFrame, method: str) -> DataFrame:
    """One row: method, n_pairs, n_true, n_hit, recall, rr, prec. pairs and truth: (id_lo, id_hi), each pair once."""
    marked = pairs.select("id_lo", "id_hi", F.lit(1).alias("p")).join(truth.select("id_lo", "id_hi", F.lit(1).alias("t")), ["id_lo", "id_hi"], "full")
    total = marked.agg(F.count("p").alias("n_pairs"), F.count("t").alias("n_true"), F.count(F.when(F.col("p").isNotNull() & F.col("t").isNotNull(), 1)).alias("n_hit"))
    rows = n if isinstance(n, DataFrame) else None
    total = total.join(F.broadcast(rows.agg(F.count("*").alias("n_rows")))) if rows is not None else total.withColumn("n_rows", F.lit(n))
    return total.select(
        F.lit(method).alias("method"), "n_pairs", "n_true", "n_hit", _6(recall(F.col("n_hit"), F.col("n_true"))).alias("recall"),
        _6(reduction_ratio(F.col("n_pairs"), F.col("n_rows"))).alias("rr"), _6(precision(F.col("n_hit"), F.col("n_pairs"))).alias("prec"),
    )


def partition_quality(blocks: DataFrame, truth: DataFrame, method: str) -> DataFrame:
    """The same for a partition (block_id, rec_id): pairs are counted by block size and never made."""
    sizes = blocks.groupBy("block_id").agg(F.count("*").alias("b"))
    counted = sizes.agg(F.coalesce(F.sum(F.expr("b * (b - 1) div 2")), F.lit(0)).alias("n_pairs"), F.coalesce(F.sum("b"), F.lit(0)).alias("n_rows"))
    lo = blocks.select(F.col("rec_id").alias("id_lo"), F.col("block_id").alias("x"))
    hi = blocks.select(F.col("rec_id").alias("id_hi"), F.col("block_id").alias("y"))
    hits = truth.join(lo, "id_lo", "left").join(hi, "id_hi", "left").agg(F.count("*").alias("n_true"), F.count(F.when(F.col("x") == F.col("y"), 1)).alias("n_hit"))
    return counted.join(F.broadcast(hits)).select(
        F.lit(method).alias("method"), "n_pairs", "n_true", "n_hit", _6(recall(F.col("n_hit"), F.col("n_true"))).alias("recall"),
        _6(reduction_ratio(F.col("n_pairs"), F.col("n_rows"))).alias("rr"), _6(precision(F.col("n_hit"), F.col("n_pairs"))).alias("prec"),
    )


def entity_split(blocks: DataFrame, df: DataFrame, id_col: str, entity: str) -> DataFrame:
    """(n_entities, n_split): entities of two or more records that no single block holds whole."""
    members = df.select(F.col(id_col).alias("rec_id"), F.col(entity).alias("e"))
    size = members.groupBy("e").agg(F.count("*").alias("size")).where("size > 1")
    best = blocks.join(members, "rec_id").groupBy("e", "block_id").agg(F.count("*").alias("held")).groupBy("e").agg(F.max("held").alias("held"))
    return size.join(best, "e", "left").agg(F.count("*").alias("n_entities"), F.count(F.when(F.coalesce("held", F.lit(0)) < F.col("size"), 1)).alias("n_split"))


def block_profile(blocks: DataFrame, method: str) -> DataFrame:
    """method, n_blocks, mean, p50, p99, max of block sizes, and the share of pairs in the largest block."""
    sizes = blocks.groupBy("block_id").agg(F.count("*").alias("b"))
    pairs = F.expr("b * (b - 1) div 2")
    return sizes.agg(
        F.count("*").alias("n_blocks"), _6(F.avg("b")).alias("mean"), F.percentile("b", F.lit(0.5)).alias("p50"), F.percentile("b", F.lit(0.99)).alias("p99"),
        F.max("b").alias("max"), _6(F.max(pairs) / F.nullif(F.sum(pairs), F.lit(0))).alias("top_share"),
    ).select(F.lit(method).alias("method"), "n_blocks", "mean", "p50", "p99", "max", "top_share")


def sketch_error(pairs: DataFrame, estimate: str, exact: str) -> DataFrame:
    """(n, bias, sd) of estimate minus exact."""
    return pairs.agg(F.count("*").alias("n"), _6(F.avg(F.col(estimate) - F.col(exact))).alias("bias"), _6(F.stddev_pop(F.col(estimate) - F.col(exact))).alias("sd"))
