"""Structured Streaming over the events table: each query replays it to the end and returns the sink's rows.

Sources are file streams with explicit schemas, progress lives in checkpoints of
the shared folder, and every stateful query is bounded by a watermark or by keys.
"""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..session import shared_dir

SNIPPET = "concat_ws('#', event_type, props)"


def folder(spark: SparkSession, stem: str) -> str:
    return f"{shared_dir(spark).rstrip('/')}/{stem}_{uuid.uuid4().hex}"


def source(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The events as a stream with an instant ``at`` and a snippet fingerprint ``h``."""
    path = f"{sf_dir}/events.parquet"
    schema = spark.read.parquet(path).schema
    stream = spark.readStream.schema(schema).option("pathGlobFilter", "*.parquet")
    raw = stream.parquet(path) if spark._jvm.org.apache.hadoop.fs.Path(path).getFileSystem(spark._jsc.hadoopConfiguration()).getFileStatus(spark._jvm.org.apache.hadoop.fs.Path(path)).isDirectory() else spark.readStream.schema(schema).option("pathGlobFilter", "events.parquet").parquet(sf_dir)
    return raw.withColumn("at", F.col("ts").cast("timestamp")).withColumn("h", F.md5(F.expr(SNIPPET)))


def drain(stream: DataFrame, mode: str) -> DataFrame:
    """Run a stream to the end of its input into a table in memory and return it."""
    spark, name = stream.sparkSession, f"sink_{uuid.uuid4().hex}"
    q = stream.writeStream.format("memory").queryName(name).outputMode(mode).option("checkpointLocation", folder(spark, "progress")).trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.table(name)


def to_files(stream: DataFrame) -> DataFrame:
    """Run an append stream into Parquet files and read them back (exactly once by the sink's log)."""
    spark = stream.sparkSession
    out = folder(spark, "sunk")
    stream.writeStream.format("parquet").outputMode("append").option("path", out).option("checkpointLocation", folder(spark, "progress")).trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(stream.schema).parquet(out)


def to_last_batch(stream: DataFrame) -> DataFrame:
    """Run a stream in complete mode to the end of its input; each batch owns a folder in the shared folder, the last one has the result.

    Rows go from executors to files: ``drain`` holds them all in the driver.
    """
    spark, out, numbers = stream.sparkSession, folder(stream.sparkSession, "complete"), []

    def batch(df: DataFrame, number: int) -> None:
        df.write.mode("overwrite").parquet(f"{out}/batch={number}")
        numbers.append(number)

    stream.writeStream.foreachBatch(batch).outputMode("complete").option("checkpointLocation", folder(spark, "progress")).trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{out}/batch={max(numbers)}") if numbers else spark.createDataFrame([], stream.schema)


def cmw_counts(spark: SparkSession, d: str) -> DataFrame:
    return drain(source(spark, d).groupBy("h").agg(F.count("*").alias("size")), "complete")


def tumbling(spark: SparkSession, d: str, slide: str | None = None) -> DataFrame:
    w = F.window("at", "1 hour", slide) if slide else F.window("at", "1 hour")
    g = source(spark, d).withWatermark("at", "1 hour").groupBy(w.alias("w"), "event_type").agg(F.count("*").alias("n"))
    return drain(g.select(F.unix_micros("w.start").alias("start"), "event_type", "n"), "complete")


def sessions(spark: SparkSession, d: str) -> DataFrame:
    """Events of a user less than half an hour apart; sessions that touch are merged, hence the gap of a microsecond less."""
    g = source(spark, d).withWatermark("at", "1 hour").groupBy(F.session_window("at", "1799999999 microseconds").alias("w"), "user_id").agg(F.count("*").alias("n"))
    return to_last_batch(g.select(F.unix_micros("w.start").alias("start"), "user_id", "n"))


def late_rows(spark: SparkSession, d: str) -> DataFrame:
    """Windows closed by the watermark: rows later than the delay no longer count."""
    g = source(spark, d).withWatermark("at", "1 hour").groupBy(F.window("at", "1 day").alias("w")).agg(F.count("*").alias("n"))
    return to_files(g.select(F.unix_micros("w.start").alias("start"), "n"))


def dedup(spark: SparkSession, d: str) -> DataFrame:
    """A replay that delivers some rows twice, made unique within the watermark."""
    e = source(spark, d)
    twice = e.withColumn("copy", F.explode(F.when(F.col("event_id") % 7 == 0, F.array(F.lit(1), F.lit(2))).otherwise(F.array(F.lit(1)))))
    return to_files(twice.withWatermark("at", "60 days").dropDuplicatesWithinWatermark(["event_id"]).select("event_id", "user_id"))


def static_join(spark: SparkSession, d: str, known: DataFrame) -> DataFrame:
    """Arriving snippets against a table of known groups."""
    return to_files(source(spark, d).select("event_id", "h").join(known, "h"))


def stream_join(spark: SparkSession, d: str) -> DataFrame:
    """Equal snippets of two users within ten minutes; both sides watermarked, state bounded by the interval."""
    e = source(spark, d)
    x = e.select(F.col("event_id").alias("a"), F.col("user_id").alias("ua"), F.col("h").alias("ha"), F.col("at").alias("ta")).withWatermark("ta", "60 days")
    y = e.select(F.col("event_id").alias("b"), F.col("user_id").alias("ub"), F.col("h").alias("hb"), F.col("at").alias("tb")).withWatermark("tb", "60 days")
    return to_files(x.join(y, F.expr("ha = hb AND ua <> ub AND tb > ta AND tb <= ta + INTERVAL 10 MINUTES")).select("a", "b"))


def first_seen(spark: SparkSession, d: str) -> DataFrame:
    """Custom state by fingerprint: first user by time and the running size; state is bounded by the fingerprints and never forgotten.

    A group's rows come in several pieces in no order, so the least (ts, event_id) is kept over all of them and in the state.
    """
    e = source(spark, d).select("h", "event_id", "user_id", F.unix_micros("at").alias("ts"))
    out = e.groupBy("h").applyInPandasWithState(seen_first, "h string, first_user long, size long", "ts long, event_id long, first_user long, size long", "update", GroupStateTimeout.NoTimeout)
    return drain(out, "update")


def seen_first(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
    """A row ``(h, first_user, size)`` for all pieces of a key; state ``(ts, event_id, first_user, size)``."""
    ts, event, first, size = state.get if state.exists else (None, None, None, 0)
    for b in batches:
        low = b.sort_values(["ts", "event_id"]).iloc[0]
        if ts is None or (low["ts"], low["event_id"]) < (ts, event):
            ts, event, first = int(low["ts"]), int(low["event_id"]), int(low["user_id"])
        size += len(b)
    state.update((ts, event, first, size))
    yield pd.DataFrame({"h": [key[0]], "first_user": [first], "size": [size]})


def upsert(spark: SparkSession, d: str) -> DataFrame:
    """Group counts by ``foreachBatch``: each batch owns a folder by its id, so a retried batch replaces itself."""
    out = folder(spark, "upsert")

    def batch(df: DataFrame, number: int) -> None:
        df.groupBy("h").agg(F.count("*").alias("n")).write.mode("overwrite").parquet(f"{out}/batch={number}")

    source(spark, d).writeStream.foreachBatch(batch).option("checkpointLocation", folder(spark, "progress")).trigger(availableNow=True).start().awaitTermination()
    return spark.read.parquet(out).groupBy("h").agg(F.sum("n").alias("size"))
