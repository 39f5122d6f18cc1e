"""Shared reading, naming and Arrow helpers of the training-data operators."""

from __future__ import annotations

import uuid
from collections.abc import Iterable, Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import IntegralType, NullType

from linkblock.runtime import ensure_checkpoint_dir

#: ASCII upper to lower case; all other bytes stay as they are.
LOWER = bytes(b + 32 if 65 <= b <= 90 else b for b in range(256))

#: White space of the word contracts, as Spark SQL writes it in a class.
SPACE = " \\x09-\\x0D"

UPPER_AZ, LOWER_AZ = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def whole_id(df: DataFrame, id_col: str) -> Column:
    """The id column as a bigint. Ids of other than whole numbers are refused here, before any job fails on one of them."""
    kind = df.schema[id_col].dataType
    if not isinstance(kind, (IntegralType, NullType)):
        raise TypeError(f"{id_col} is {kind.simpleString()}, ids must be whole numbers: give rows a bigint key first and join other ids back by it")
    return df[id_col].cast("bigint")


def narrow(docs: DataFrame, id_col: str, text_col: str, **more: str) -> DataFrame:
    """Only what an operator needs, under its own names, so that other columns of docs can't clash."""
    return docs.select(
        whole_id(docs, id_col).alias("doc_id"), docs[text_col].cast("string").alias("text"),
        *(docs[c].alias(name) for name, c in more.items()),
    )


def as_bytes(df: DataFrame, *keep: str) -> DataFrame:
    """doc_id, text as UTF-8 bytes (null: empty) for Arrow stages: no decoding on the way."""
    return df.select("doc_id", F.coalesce(F.col("text"), F.lit("")).cast("binary").alias("text"), *keep)


def lower_ascii(c: Column) -> Column:
    return F.translate(c, UPPER_AZ, LOWER_AZ)


def let(value: Column, body) -> Column:
    """body(v) with v bound to value, computed once for the row however often body uses it."""
    return F.transform(F.array(value), body)[0]


def written(df: DataFrame) -> DataFrame:
    """df as a table of its own in the shared checkpoint folder: columns stay compressed, which a checkpoint's rows don't."""
    ensure_checkpoint_dir(df.sparkSession)
    path = f"{df.sparkSession.sparkContext.getCheckpointDir()}/table-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def batch(schema: pa.Schema, columns: Iterable) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(c, type=f.type) for c, f in zip(columns, schema, strict=True)], schema=schema)


def per_document(df: DataFrame, work, schema: str, *keep: str, rows: int = 512) -> DataFrame:
    """One output row a document: work(bytes) gives the columns after doc_id and keep.

    Batches are cut into slices of `rows` documents, so what a worker holds is
    one slice of texts besides the batch that Arrow has handed over.
    """
    from pyspark.sql.pandas.types import to_arrow_schema
    from pyspark.sql.types import StructType

    arrow = to_arrow_schema(StructType.fromDDL(schema))
    n = 1 + len(keep)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for at in range(0, whole.num_rows, rows):
                part = whole.slice(at, rows)
                made = [work(x) for x in part.column("text").to_pylist()]
                head = [part.column(c).cast(arrow.field(c).type) for c in ("doc_id", *keep)]
                tail = [pa.array([m[i] for m in made], type=arrow.field(n + i).type) for i in range(len(arrow) - n)]
                yield pa.RecordBatch.from_arrays(head + tail, schema=arrow)

    return as_bytes(df, *keep).mapInArrow(run, schema)
