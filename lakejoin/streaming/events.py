"""Streaming refresh of profiles: counts are additive, so a stream's profile equals that of the batch."""

from __future__ import annotations

import uuid

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupStateTimeout

from ..operators import profile
from ..session import shared_dir
from ..sources.lake import melt


def event_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    schema = spark.read.parquet(f"{sf_dir}/events.parquet").schema
    read = spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(f"{sf_dir}/events.parquet*")
    return read.withColumn("ts", F.col("ts").cast("timestamp"))  # watermarks need a zoned type


def run_to_end(stream: DataFrame, mode: str) -> DataFrame:
    """Drain what is there into files of the shared folder and read them back; exactly once by the sink's own log."""
    spark = stream.sparkSession
    root = f"{shared_dir(spark)}/stream-{uuid.uuid4().hex}"
    if mode == "append":
        writer = stream.writeStream.format("parquet").outputMode("append").option("path", f"{root}/out")
        writer.option("checkpointLocation", f"{root}/state").trigger(availableNow=True).start().awaitTermination()
    else:
        # whole results replace one another by batch number, so a replayed batch writes the same folder again
        keep = lambda df, n: df.write.mode("overwrite").parquet(f"{root}/out/batch={n}")
        writer = stream.writeStream.foreachBatch(keep).outputMode("complete").option("checkpointLocation", f"{root}/state")
        writer.trigger(availableNow=True).start().awaitTermination()
    found = spark.read.parquet(f"{root}/out")
    if mode != "append":
        last = found.agg(F.max("batch")).first()[0]
        found = found.where(F.col("batch") == last).drop("batch")
    return found


def incremental_frequencies(stream: DataFrame, dataset: str) -> DataFrame:
    """Frequency table of the string columns of a stream: each batch adds its counts under its own number, so a
    replay writes the same rows again, and totals are the sum."""
    spark = stream.sparkSession
    root = f"{shared_dir(spark)}/stream-{uuid.uuid4().hex}"

    def add(batch: DataFrame, number: int) -> None:
        profile.frequencies(melt(batch, dataset)).write.mode("overwrite").parquet(f"{root}/counts/batch={number}")

    stream.writeStream.foreachBatch(add).option("checkpointLocation", f"{root}/state").trigger(availableNow=True).start().awaitTermination()
    return spark.read.parquet(f"{root}/counts").groupBy("dataset", "attr", "value").agg(F.sum("cnt").alias("cnt"))


def windows(stream: DataFrame, length: str = "1 day", slide: str | None = None, late: str = "2 days") -> DataFrame:
    """Events and distinct users by window and type; state older than the watermark goes."""
    timed = stream.withWatermark("ts", late)
    return timed.groupBy(F.window("ts", length, slide or length), "event_type").agg(F.count(F.lit(1)).alias("n"), F.approx_count_distinct("user_id").alias("users"))


def sessions(stream: DataFrame, gap: str = "30 minutes", late: str = "2 days") -> DataFrame:
    return stream.withWatermark("ts", late).groupBy(F.session_window("ts", gap), "user_id").agg(F.count(F.lit(1)).alias("n"))


def deduplicated(stream: DataFrame, late: str = "2 days") -> DataFrame:
    return stream.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def enriched(stream: DataFrame, profiles: DataFrame) -> DataFrame:
    """Stream-static join: each event's type with the profile of its column."""
    types = profiles.where("attr = 'event_type'").select("attr", "cardinality", "entropy")
    return stream.withColumn("attr", F.lit("event_type")).join(types, "attr", "left")


def daily_on_time(stream: DataFrame, late: str) -> DataFrame:
    """Closed days and their events; a row older than the watermark when it comes is dropped, so its day never changes again."""
    return stream.withWatermark("ts", late).groupBy(F.window("ts", "1 day")).agg(F.count(F.lit(1)).alias("n"))


def first_seen(stream: DataFrame, column: str) -> DataFrame:
    """(value, first_ts): every distinct value of a column once, when it is first seen, by arbitrary state: a flag for each value."""

    def see(key, parts, state):
        ts = min(p["ts"].min() for p in parts)
        if not state.exists:
            state.update((True,))
            yield pd.DataFrame({"value": [key[0]], "first_ts": [ts]})

    rows = stream.select(F.col(column).alias("value"), "ts").where(F.col("value").isNotNull())
    return rows.groupBy("value").applyInPandasWithState(see, "value string, first_ts timestamp", "seen boolean", "append", GroupStateTimeout.NoTimeout)
