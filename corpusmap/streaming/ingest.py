"""Chronological ingestion and volumes over streams."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def read_feed(spark: SparkSession, folder: str, schema, files_per_batch: int | None = None) -> DataFrame:
    reader = spark.readStream.schema(schema)
    if files_per_batch:
        reader = reader.option("maxFilesPerTrigger", files_per_batch)
    return reader.parquet(folder)


def with_lateness(feed: DataFrame, time: str = "ts", delay: str = "1 day") -> DataFrame:
    """Event time as a timestamp with a watermark; rows behind it are dropped and counted by the query's progress."""
    return feed.withColumn(time, F.col(time).cast("timestamp")).withWatermark(time, delay)


def keep_first(feed: DataFrame, keys: list[str]) -> DataFrame:
    """The first row of each key inside the watermark's delay; state goes with the watermark."""
    return feed.dropDuplicatesWithinWatermark(keys)


def keep_least(feed: DataFrame, keys: list[str], order: str) -> DataFrame:
    """The smallest ``order`` of each key so far, whatever the order in which rows, files and batches come; for :func:`run_updates`.

    One state per key, as for a stream without a watermark; a null ``order`` comes last.
    """
    return feed.groupBy(*keys).agg(F.min(order).alias(order))


def keep_singletons(feed: DataFrame, keys: list[str], time: str = "ts", period: str = "1 day") -> DataFrame:
    """Keys that one period holds exactly once, given out when the watermark has passed the period."""
    return (feed.groupBy(F.window(time, period).alias("period"), *keys).agg(F.count(F.lit(1)).alias("n")).filter("n = 1")
            .select(F.col("period.start").alias("period"), *keys))


def volume(events: DataFrame, kind: str, by: list[str], time: str = "ts") -> DataFrame:
    """Rows and values per tumbling (1 day), sliding (2 days by 1 day) or session (6 hours apart) window."""
    slot = {"tumbling": F.window(time, "1 day"), "sliding": F.window(time, "2 days", "1 day"), "session": F.session_window(time, "6 hours")}[kind]
    out = events.groupBy(slot.alias("w"), *by).agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("value"), 4).alias("total"))
    return out.select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), *by, "n", "total")


def run_available(out: DataFrame, path: str, checkpoint: str, mode: str = "append") -> None:
    """Write what is there to Parquet and stop; a second run goes on from the checkpoint."""
    query = out.writeStream.format("parquet").option("path", path).option("checkpointLocation", checkpoint).outputMode(mode).trigger(availableNow=True).start()
    query.awaitTermination()


def run_updates(least: DataFrame, path: str, checkpoint: str) -> None:
    """Write what :func:`keep_least` changes to a folder per micro-batch; a retried batch replaces its own, a second run goes on from the checkpoint."""
    def batch(df: DataFrame, n: int) -> None:
        df.write.mode("overwrite").parquet(f"{path}/batch={n}")

    query = least.writeStream.option("checkpointLocation", checkpoint).outputMode("update").foreachBatch(batch).trigger(availableNow=True).start()
    query.awaitTermination()


def read_least(spark: SparkSession, path: str, least: DataFrame, keys: list[str], order: str) -> DataFrame:
    """What :func:`run_updates` wrote, brought to one row per key."""
    return spark.read.schema(least.schema).parquet(f"{path}/batch=*").groupBy(*keys).agg(F.min(order).alias(order))


def ingest_periods(feed: DataFrame, path: str, checkpoint: str, survivors) -> None:
    """Each micro-batch is one or more whole periods: ``survivors`` is applied and their partitions are replaced, so a retry changes nothing."""
    def batch(df: DataFrame, _: int) -> None:
        survivors(df).write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("period").parquet(path)

    query = feed.writeStream.option("checkpointLocation", checkpoint).foreachBatch(batch).trigger(availableNow=True).start()
    query.awaitTermination()
