"""Joins that Spark has no operator for: dates within a range, and the latest earlier row."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def date_range_pairs(df: DataFrame, id_col: str, day: str, keys: list[str], days: int) -> DataFrame:
    """(id_lo, id_hi, days) of pairs that agree on keys and lie at most `days` apart.

    Days are put in bins of that width; one side probes its own and the two
    neighbouring bins, so the range condition becomes an equi-join.
    """
    rows = df.where(F.col(day).isNotNull()).select(F.col(id_col).alias("id"), F.unix_date(day).alias("d"), *keys)
    width = max(1, days)
    here = F.floor(F.col("d") / width)
    a = rows.select(F.col("id").alias("id_lo"), F.col("d").alias("da"), *keys, here.alias("bin"))
    b = rows.select(F.col("id").alias("id_hi"), F.col("d").alias("db"), *keys, F.explode(F.array(here - 1, here, here + 1)).alias("bin"))
    apart = F.abs(F.col("da") - F.col("db"))
    return a.join(b, [*keys, "bin"]).where((F.col("id_lo") < F.col("id_hi")) & (apart <= days)).select("id_lo", "id_hi", apart.alias("days"))


def as_of(left: DataFrame, right: DataFrame, id_col: str, keys: list[str], day: str) -> DataFrame:
    """left's rows with prior_id: right's row of the same keys with the latest day not after, the larger id among equals.

    Both sides are laid in one order and the last right row is carried on: one
    exchange by key, no range join. Rows without a day find nothing.
    """
    l = left.select(F.col(id_col).alias(id_col), *keys, F.col(day).alias("_day"), F.lit(1).alias("_side"))
    r = right.where(F.col(day).isNotNull()).select(F.col(id_col).alias(id_col), *keys, F.col(day).alias("_day"), F.lit(0).alias("_side"))
    w = Window.partitionBy(*keys).orderBy(F.col("_day").asc_nulls_first(), "_side", id_col).rowsBetween(Window.unboundedPreceding, 0)
    laid = l.unionByName(r).withColumn("prior_id", F.last(F.when(F.col("_side") == 0, F.col(id_col)), ignorenulls=True).over(w))
    return laid.where("_side = 1").select(id_col, *keys, F.col("_day").alias(day), "prior_id")
