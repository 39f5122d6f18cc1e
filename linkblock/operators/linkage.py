"""What follows blocking: scoring inside blocks, entities, and the cost of a slow linkage method."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from linkblock.operators.blocks import to_partition


def score_pairs(pairs: DataFrame, df: DataFrame, id_col: str, fields: list[str], least: int) -> DataFrame:
    """pairs with agree (number of equal fields, nulls agree with nothing) and match (agree >= least)."""
    side = lambda s: df.select(F.col(id_col).alias(f"id_{s}"), *(F.col(f).alias(f"{f}_{s}") for f in fields))
    agree: Column = reduce(lambda a, b: a + b, (F.coalesce((F.col(f"{f}_lo") == F.col(f"{f}_hi")).cast("int"), F.lit(0)) for f in fields))
    return pairs.select("id_lo", "id_hi").join(side("lo"), "id_lo").join(side("hi"), "id_hi").select("id_lo", "id_hi", agree.alias("agree"), (agree >= least).alias("match"))


def entities(records: DataFrame, scored: DataFrame) -> DataFrame:
    """(rec_id, component) after closing matches transitively."""
    return to_partition(records, scored.where("match").select("id_lo", "id_hi"))


def linkage_hours(blocks: DataFrame, method: str, low: float = 12.0, high: float = 24.0, at: int = 500) -> DataFrame:
    """method, hours_low, hours_high: `low` to `high` hours for a block of `at` records, in proportion to block size (an assumption)."""
    sizes = blocks.groupBy("block_id").agg(F.count("*").alias("b")).where("b > 1")
    total = F.coalesce(F.sum("b"), F.lit(0)) / at
    return sizes.agg(F.round(total * low, 6).alias("hours_low"), F.round(total * high, 6).alias("hours_high")).select(F.lit(method).alias("method"), "hours_low", "hours_high")
