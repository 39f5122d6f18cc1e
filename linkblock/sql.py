"""SQL surface: table functions and scalar functions by name."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

from linkblock.functions.names import PRESETS, name_cost_udf


@udtf(returnType="gram string")
class Shingles:
    """Contiguous substrings of k characters; none for null or shorter texts."""

    def eval(self, text: str, k: int):
        for i in range(len(text or "") - k + 1):
            yield (text[i : i + k],)


def register(spark: SparkSession) -> None:
    """shingles(text, k) and name_cost(a, b) in SQL."""
    spark.udtf.register("shingles", Shingles)
    spark.udf.register("name_cost", name_cost_udf(PRESETS["equal"]))
