"""Connected components of an edge table by alternating star contraction.

Large-star hooks every neighbour above a node to the smallest node of its
neighbourhood, small-star does the same with the neighbours below; both keep
the components and shrink their depth, so O(log n) rounds suffice. Each round
is two aggregations and two equi-joins on narrow rows; lineage is cut in the
shared checkpoint folder and only one row of round totals meets the driver.

A hub's neighbours may be a third of all rows. Its least neighbour is found by
partial sums, and as that table is settled, both sides of the join that hands
it out are plain exchanges: adaptive execution splits the hub over tasks.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from linkblock.runtime import settle


def _star(edges: DataFrame, keep_above: bool) -> DataFrame:
    """edges (a > b). Hook the chosen neighbours of each node to its least neighbour."""
    both = edges.select(F.col("a").alias("n"), F.col("b").alias("m"))
    if keep_above:
        both = both.unionByName(edges.select(F.col("b").alias("n"), F.col("a").alias("m")))
    least = settle(both.groupBy("n").agg(F.least(F.min("m"), F.first("n")).alias("low")))
    hooked = both.join(least, "n")
    if keep_above:
        hooked = hooked.where("m > n").select(F.col("m").alias("a"), F.col("low").alias("b"))
    else:
        hooked = hooked.select(F.col("m").alias("a"), F.col("low").alias("b")).unionByName(
            least.select(F.col("n").alias("a"), F.col("low").alias("b"))
        )
    return hooked.where("a > b").distinct()


def connected_components(edges: DataFrame, left: str, right: str, max_rounds: int = 60) -> DataFrame:
    """Rows (node, root): every node on an edge with the least node it reaches.

    Self-links and links with a null end are ignored, repeated and reversed
    links count once; an empty table gives an empty result.
    """
    now = settle(
        edges.select(
            F.greatest(left, right).alias("a"), F.least(left, right).alias("b"),
        ).where(F.col(left).isNotNull() & F.col(right).isNotNull() & (F.col(left) != F.col(right)))
        .select("a", "b").distinct()
    )
    before = None
    for _ in range(max_rounds):
        total = now.agg(F.count("*").alias("n"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)")).alias("h")).first()
        if (total["n"], total["h"]) == before or not total["n"]:
            break
        before = (total["n"], total["h"])
        now = settle(_star(_star(now, True), False))
    else:
        raise RuntimeError("components did not settle")
    return now.select(F.col("a").alias("node"), F.col("b").alias("root")).unionByName(
        now.select(F.col("b").alias("node"), F.col("b").alias("root")).distinct()
    )
