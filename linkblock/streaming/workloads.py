"""Streaming workloads: each reads events or documents as a stream to its end and returns what it made.

The stream's state and output live in the shared folder; a restarted run goes
on from its checkpoint. Each has a batch answer that it must equal.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from linkblock.functions import tokens
from linkblock.operators import bands, sketch
from linkblock.plans import query
from linkblock.plans import sqltext as S
from linkblock.plans.operators import scratch
from linkblock.plans.sketches import B, K, TABLES
from linkblock.plans.texts import GRAM
from linkblock.sources.tables import load


def event_stream(spark: SparkSession, sf_dir: str, per_batch: int = 1) -> DataFrame:
    """events as a stream with ts as an instant, which watermarks need."""
    schema = load(spark, sf_dir, "events").schema
    rows = spark.readStream.schema(schema).option("pathGlobFilter", "events.parquet").option("maxFilesPerTrigger", per_batch).parquet(sf_dir)
    return rows.withColumn("ts", F.col("ts").cast("timestamp"))


def to_end(df: DataFrame, spark: SparkSession, name: str, mode: str, between: Callable[[], None] | None = None) -> DataFrame:
    """Run a stream over all there is and read its result: the last full result (complete) or all appended rows.

    between: what happens after the first run, before the stream goes on from its checkpoint.
    """
    base = scratch(spark, name)

    def write(batch: DataFrame, batch_id: int) -> None:
        # A batch that is run again overwrites its own folder: exactly once in effect.
        batch.write.mode("overwrite").parquet(f"{base}/rows" if mode == "complete" else f"{base}/rows/batch={batch_id}")

    for after in (between, None) if between else (None,):
        df.writeStream.outputMode(mode).foreachBatch(write).option("checkpointLocation", f"{base}/state").trigger(availableNow=True).start().awaitTermination()
        if after:
            after()
    return spark.read.schema(df.schema).parquet(f"{base}/rows").select(*df.columns)


def _shown(df: DataFrame, *times: str) -> DataFrame:
    for t in times:
        df = df.withColumn(t, F.date_format(t, "yyyy-MM-dd HH:mm:ss"))
    return df


@query("SELECT strftime(time_bucket(INTERVAL 1 HOUR, ts), '%Y-%m-%d %H:%M:%S') AS start, event_type, count(*) AS n FROM events GROUP BY ALL")
def stream_tumbling(spark: SparkSession, sf_dir: str) -> DataFrame:
    made = event_stream(spark, sf_dir).withWatermark("ts", "1 hour").groupBy(F.window("ts", "1 hour").alias("w"), "event_type").agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "event_type", "n")
    return _shown(to_end(made, spark, "tumbling", "complete"), "start")


@query("SELECT strftime(b - to_minutes(30 * i), '%Y-%m-%d %H:%M:%S') AS start, count(*) AS n FROM (SELECT time_bucket(INTERVAL 30 MINUTE, ts) AS b FROM events), range(2) r(i) GROUP BY ALL")
def stream_sliding(spark: SparkSession, sf_dir: str) -> DataFrame:
    made = event_stream(spark, sf_dir).withWatermark("ts", "1 hour").groupBy(F.window("ts", "1 hour", "30 minutes").alias("w")).agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "n")
    return _shown(to_end(made, spark, "sliding", "complete"), "start")


@query("""WITH e AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 2 HOUR THEN 0 ELSE 1 END AS new FROM events),
s AS (SELECT user_id, ts, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM e)
SELECT user_id, strftime(min(ts), '%Y-%m-%d %H:%M:%S') AS start, count(*) AS n FROM s GROUP BY user_id, k""")
def stream_session(spark: SparkSession, sf_dir: str) -> DataFrame:
    made = event_stream(spark, sf_dir).groupBy(F.session_window("ts", "2 hours").alias("w"), "user_id").agg(F.count("*").alias("n")).select("user_id", F.col("w.start").alias("start"), "n")
    return _shown(to_end(made, spark, "session", "complete"), "start")


@query("SELECT strftime(b, '%Y-%m-%d %H:%M:%S') AS start, count(*) AS n FROM (SELECT time_bucket(INTERVAL 1 HOUR, ts) AS b FROM events) WHERE b + INTERVAL 1 HOUR <= (SELECT max(ts) - INTERVAL 10 MINUTE FROM events) GROUP BY b")
def stream_late_drop(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events arrive; after them, those of a day before the last and older once more: late by then, they are dropped.

    Only windows that the watermark has passed come out, with the counts of the first arrival alone.
    """
    path, events = scratch(spark, "late-events"), load(spark, sf_dir, "events").select("event_id", F.col("ts").cast("timestamp").alias("ts"))
    events.write.parquet(path)

    def late() -> None:
        last = events.agg(F.max("ts").alias("last"))
        events.join(F.broadcast(last)).where("ts < last - INTERVAL 1 DAY").drop("last").write.mode("append").parquet(path)

    arriving = spark.readStream.schema(events.schema).parquet(path)
    made = arriving.withWatermark("ts", "10 minutes").groupBy(F.window("ts", "1 hour").alias("w")).agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "n")
    return _shown(to_end(made, spark, "late", "append", late), "start")


@query("SELECT user_id, event_type, count(*) AS n FROM (SELECT DISTINCT event_id, user_id, event_type FROM events) GROUP BY ALL")
def stream_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events sent twice (here: the stream joined to itself by union) count once."""
    e = event_stream(spark, sf_dir).select("event_id", "user_id", "event_type", "ts")
    once = e.union(event_stream(spark, sf_dir).select("event_id", "user_id", "event_type", "ts")).withWatermark("ts", "3650 days").dropDuplicatesWithinWatermark(["event_id"])
    return to_end(once.select("event_id", "user_id", "event_type"), spark, "dedup", "append").groupBy("user_id", "event_type").agg(F.count("*").alias("n"))


_HALVES = "a.rec_id % 2 = 0 AND b.rec_id % 2 = 1"


@query(f"WITH {S.doc_grams(GRAM)}, {S.bins(B)}, {S.filled(B, 'probe')}, {S.band_keys(K)} SELECT DISTINCT a.rec_id AS indexed_id, b.rec_id AS new_id FROM bands a JOIN bands b ON a.table_no = b.table_no AND a.key = b.key WHERE {_HALVES}")
def stream_incremental_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Documents of odd id arrive as a stream, are sketched without state and meet the bucket index of the others."""
    def buckets(df: DataFrame) -> DataFrame:
        sets = df.select(F.col("doc_id").alias("rec_id"), tokens.distinct_hashes(tokens.word_grams(F.col("text"), GRAM)).alias("h"))
        return bands.bucketize(sets.select("rec_id", sketch.one_pass_sketch(F.col("h"), B).alias("sig")), "rec_id", F.col("sig"), K, TABLES)

    stored = load(spark, sf_dir, "documents")
    path = scratch(spark, "index")
    buckets(stored.where("doc_id % 2 = 0")).write.partitionBy("table_no").parquet(path)
    index = spark.read.parquet(path).withColumnRenamed("rec_id", "indexed_id")
    # A plain file holds the whole table here, a folder of files elsewhere: both are a stream of documents.
    arriving = spark.readStream.schema(stored.schema).option("pathGlobFilter", "*.parquet").parquet(f"{sf_dir}/documents.parquet*")
    found = buckets(arriving.where("doc_id % 2 = 1")).join(index, ["table_no", "bucket_key"]).select("indexed_id", F.col("rec_id").alias("new_id"))
    return to_end(found, spark, "pairs", "append").distinct()


@query("SELECT user_id, count(*) AS n, round(max(value), 6) AS most FROM events GROUP BY user_id")
def stream_user_state(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A running count and maximum of each user kept as custom state; the last row of each user is the batch answer.

    A user's rows of a batch come in Arrow chunks, so a busy user needs no more memory than a quiet one.
    """
    import pandas as pd
    from pyspark.sql.streaming.state import GroupStateTimeout

    def step(key, chunks, state):
        n, most = state.get if state.exists else (0, float("-inf"))
        for rows in chunks:
            n, most = n + len(rows), max(most, float(rows["value"].max()))
        state.update((n, most))
        yield pd.DataFrame({"user_id": [key[0]], "n": [n], "most": [most]})

    rows = event_stream(spark, sf_dir).select("user_id", "value")
    made = rows.groupBy("user_id").applyInPandasWithState(step, "user_id bigint, n bigint, most double", "n bigint, most double", "update", GroupStateTimeout.NoTimeout)
    last = to_end(made, spark, "users", "update").groupBy("user_id").agg(F.max("n").alias("n"), F.max("most").alias("most"))
    return last.select("user_id", "n", F.round("most", 6).alias("most"))
