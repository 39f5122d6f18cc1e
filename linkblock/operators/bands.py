"""(K, L) banding: K values of a signature make a table's key, L tables."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from linkblock.functions.tokens import let


def band(sig: Column, k: int, tables: int, t: Column, layout: str = "contiguous") -> Column:
    """The k values of table t: neighbours, or every tables-th (stride)."""
    if layout == "stride":
        return F.transform(F.sequence(F.lit(0), F.lit(k - 1)), lambda i: F.get(sig, t + i * tables))
    return F.slice(sig, t * k + 1, F.lit(k))


def keys(sig: Column, k: int, tables: int, layout: str = "contiguous") -> Column:
    """array<bigint> of the tables' bucket keys (64-bit: 32 are too few beyond 10^9 records). Null for a null signature."""
    return let(sig, lambda s: F.when(s.isNotNull(), F.transform(F.sequence(F.lit(0), F.lit(tables - 1)), lambda t: F.xxhash64(t, band(s, k, tables, t, layout)))))


def shown_keys(sig: Column, k: int, tables: int) -> Column:
    """array<string> of the tables' values, for keys that another engine can make too."""
    text = lambda s, t: F.array_join(F.transform(band(s, k, tables, t), lambda v: v.cast("string")), "-")
    return let(sig, lambda s: F.when(s.isNotNull(), F.transform(F.sequence(F.lit(0), F.lit(tables - 1)), lambda t: text(s, t))))


def bucketize(df: DataFrame, id_col: str, sig: Column, k: int, tables: int, layout: str = "contiguous", empty: str = "skip") -> DataFrame:
    """(table_no, bucket_key, rec_id). A record without a signature has no bucket ('skip') or one of its own in each table ('own')."""
    own = F.transform(F.sequence(F.lit(0), F.lit(tables - 1)), lambda t: F.xxhash64(F.lit("own"), t, F.col(id_col)))
    made = keys(sig, k, tables, layout)
    return df.select(F.col(id_col).alias("rec_id"), F.posexplode(F.coalesce(made, own) if empty == "own" else made).alias("table_no", "bucket_key")).select("table_no", "bucket_key", "rec_id")


def collision_probability(s: Column, k: int | Column, tables: int | Column) -> Column:
    """1 - (1 - s^k)^tables: the chance to share a bucket at similarity s."""
    k = F.lit(k) if isinstance(k, int) else k
    tables = F.lit(tables) if isinstance(tables, int) else tables
    return 1 - F.pow(1 - F.pow(s, k), tables)
