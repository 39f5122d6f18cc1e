"""Reading the given tables, and the derived person reports with planted duplicates."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from linkblock.functions.hashing import base32

#: The letters that hex digits 0-f become, and what each is mistaken for.
LETTERS = "ابتثجحخدذرزسشصضط"
MISTAKEN = "بتثبحخجذدزرشسضصص"
HEX = "0123456789abcdef"


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read_csv(spark: SparkSession, path: str, schema: T.StructType | str) -> DataFrame:
    """CSV with a declared schema; a row that doesn't fit is an error, not a guess."""
    return spark.read.schema(schema).option("mode", "FAILFAST").option("header", True).csv(path)


def read_json(spark: SparkSession, path: str, schema: T.StructType | str) -> DataFrame:
    return spark.read.schema(schema).option("mode", "FAILFAST").json(path)


def from_rows(spark: SparkSession, rows: list[tuple], schema: T.StructType | str) -> DataFrame:
    return spark.createDataFrame(rows, schema)


def reports(spark: SparkSession, sf_dir: str) -> DataFrame:
    """rec_id, k (hidden entity), list, given, family, event_date, place: three noisy lists of the same people.

    One aggregation (earliest order of a person) and one join; everything else
    is computed from hashes of the key, row by row.
    """
    first = load(spark, sf_dir, "orders").groupBy("o_custkey").agg(F.min("o_orderdate").cast("date").alias("day"))
    people = load(spark, sf_dir, "customer").join(first, F.col("c_custkey") == F.col("o_custkey"), "left")
    k = F.col("c_custkey").cast("bigint")
    s = k.cast("string")
    chance = lambda tag, out_of=100: base32(F.concat(F.lit(tag), s)) % out_of
    spelled = lambda text, n: F.translate(F.substring(F.md5(text.cast("binary")), 1, n), HEX, LETTERS)
    given = spelled(s, 6)
    family = spelled(F.concat(F.lit("f"), (k % 97).cast("string")), 5)
    at = chance("p", 6).cast("int")
    slipped = F.concat(F.substring(given, F.lit(1), at), F.translate(F.substring(given, at + 1, F.lit(1)), LETTERS, MISTAKEN), F.substring(given, at + 2, F.lit(6)))
    place = F.col("c_nationkey").cast("int")
    row = lambda name, n, g, f, d, p: F.struct(
        (3 * k + n).alias("rec_id"), k.alias("k"), F.lit(name).alias("list"), g.alias("given"), f.alias("family"), d.alias("event_date"), p.cast("int").alias("place")
    )
    lists = (
        (chance("A") < 60, row("A", 0, given, family, F.col("day"), place)),
        (chance("B") < 40, row("B", 1, F.when(chance("t") < 60, slipped).otherwise(given), family, F.when(chance("d") < 25, F.date_add("day", 1)).otherwise(F.col("day")), place)),
        (chance("C") < 25, row("C", 2, given, F.when(chance("m") < 70, family).otherwise(F.lit("")), F.col("day"), F.when(chance("q") < 20, (place + 1) % 25).otherwise(place))),
    )
    present = F.filter(F.array(*(F.when(keep, r) for keep, r in lists)), lambda r: r.isNotNull())
    return people.select(F.explode(present).alias("r")).select("r.*")


def report_truth(reports_df: DataFrame) -> DataFrame:
    """(id_lo, id_hi) of all pairs of reports of one entity; at most three pairs an entity."""
    ids = reports_df.groupBy("k").agg(F.array_sort(F.collect_list("rec_id")).alias("ids")).where(F.size("ids") > 1)
    pairs = F.flatten(F.transform("ids", lambda a, i: F.transform(F.slice("ids", i + 2, F.size("ids")), lambda b: F.struct(a.alias("id_lo"), b.alias("id_hi")))))
    return ids.select(F.explode(pairs).alias("p")).select("p.*")


def train_half(entity: Column) -> Column:
    """Whether an entity is in the half that rules and parameters may be chosen on."""
    return base32(F.concat(F.lit("half"), entity.cast("string"))) % 2 == 0


def clean(df: DataFrame, *text_cols: str) -> DataFrame:
    """Blank strings become null, outer blanks go."""
    for c in text_cols:
        df = df.withColumn(c, F.nullif(F.trim(F.col(c)), F.lit("")))
    return df


def latest_per(df: DataFrame, key: str, by: str, tie: str) -> DataFrame:
    return df.withColumn("_n", F.row_number().over(Window.partitionBy(key).orderBy(F.desc(by), tie))).where("_n = 1").drop("_n")
