"""From buckets and blocks to candidate pairs, each once."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from linkblock.operators import bands, cells
from linkblock.runtime import settle


def all_pairs(df: DataFrame, id_col: str, max_rows: int = 5_000) -> DataFrame:
    """(id_lo, id_hi) of all pairs: the exact baseline, refused above max_rows."""
    n = df.count()
    if n > max_rows:
        raise ValueError(f"{n} rows make {n * (n - 1) // 2} pairs; all_pairs takes {max_rows} rows at most")
    return df.select(F.col(id_col).alias("id_lo")).join(df.select(F.col(id_col).alias("id_hi")), F.col("id_lo") < F.col("id_hi"))


def from_keys(df: DataFrame, id_col: str, keys: Column, cap: int | None = None, chunk: int | None = None) -> tuple[DataFrame, DataFrame]:
    """(pairs (id_lo, id_hi, first_table), buckets over cap (table_no, bucket_key, n)).

    A pair is emitted only in the first table whose keys agree, which needs no
    distinct over pairs. Rows are dealt in groups (of about `chunk` rows, or
    what a cell may hold) and every two groups meet in a cell of their own, so
    that a row travels with its keys once a group and no task makes all pairs
    of a hot bucket. The keys (8 bytes a table and row) are written once, as
    they cost much to make. With a cap, buckets over it make no pairs here;
    they are returned for split_large() instead of being lost.
    """
    # Written before the nulls go: a filter on the keys would be pushed below them and make them twice.
    rows = settle(df.select(F.col(id_col).cast("bigint").alias("id"), keys.alias("ks"))).where("ks IS NOT NULL")
    n, tables = rows.agg(F.count("*"), F.coalesce(F.max(F.size("ks")), F.lit(0))).first()
    pairs = cells.emit(rows, tables, n, max(1, -(-n // chunk)) if chunk else None)
    sizes = rows.select(F.posexplode("ks").alias("table_no", "bucket_key")).groupBy("table_no", "bucket_key").agg(F.count("*").alias("n"))
    if not cap:
        return pairs, sizes.limit(0)
    large = sizes.where(F.col("n") > cap)
    keyed = pairs.join(rows.select(F.col("id").alias("id_lo"), "ks"), "id_lo").select("id_lo", "id_hi", "first_table", F.get("ks", F.col("first_table")).alias("bucket_key"))
    return keyed.join(large.withColumnRenamed("table_no", "first_table"), ["first_table", "bucket_key"], "left_anti").select("id_lo", "id_hi", "first_table"), large


def from_signatures(df: DataFrame, id_col: str, sig: Column, k: int, tables: int, layout: str = "contiguous") -> DataFrame:
    """(id_lo, id_hi, first_table) for a signature column."""
    return from_keys(df, id_col, bands.keys(sig, k, tables, layout))[0]


def from_buckets(buckets: DataFrame) -> DataFrame:
    """(id_lo, id_hi, first_table) from (table_no, bucket_key, rec_id) rows, by a least over tables."""
    a = buckets.select("table_no", "bucket_key", F.col("rec_id").alias("id_lo"))
    b = buckets.select("table_no", "bucket_key", F.col("rec_id").alias("id_hi"))
    return a.join(b, ["table_no", "bucket_key"]).where("id_lo < id_hi").groupBy("id_lo", "id_hi").agg(F.min("table_no").alias("first_table"))


def from_blocks(blocks: DataFrame) -> DataFrame:
    """(id_lo, id_hi) of (block_id, rec_id) rows, each pair once also where blocks overlap."""
    a = blocks.select("block_id", F.col("rec_id").alias("id_lo"))
    b = blocks.select("block_id", F.col("rec_id").alias("id_hi"))
    return a.join(b, "block_id").where("id_lo < id_hi").select("id_lo", "id_hi").distinct()
