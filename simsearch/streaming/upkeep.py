"""Streams of new strings into the index and the clusters, streams of queries, and windowed counts of events."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def append_stream(spark: SparkSession, source: str, schema, apply, checkpoint: str) -> None:
    """Each batch of new files once: apply(batch, batch_id) under a checkpoint, until the files are done."""
    stream = spark.readStream.schema(schema).parquet(source)
    stream.writeStream.foreachBatch(apply).option("checkpointLocation", checkpoint).trigger(availableNow=True).start().awaitTermination()


def _events(spark: SparkSession, sf_dir: str) -> DataFrame:
    schema = spark.read.parquet(f"{sf_dir}/events.parquet").schema
    stream = spark.readStream.schema(schema).option("pathGlobFilter", "events.parquet").parquet(sf_dir)
    return stream.withColumn("ts", F.col("ts").cast("timestamp"))  # a watermark wants a time zone


def run_to_table(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Everything that is there now, into a memory table. Windows are closed only by later rows, so results of open
    windows need mode 'complete'."""
    name = f"stream_{uuid.uuid4().hex}"
    stream.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True).start().awaitTermination()
    return stream.sparkSession.table(name)


def run_to_files(stream: DataFrame, path: str, mode: str = "append") -> DataFrame:
    """As ``run_to_table``, but every batch's result becomes files under path, a folder that all executors share, as does the
    state: nothing comes to the driver. In mode 'complete' the last batch holds everything."""
    spark, written = stream.sparkSession, []

    def keep(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/batch-{number}")  # a batch that is tried again replaces its files
        written.append(f"{path}/batch-{number}")

    stream.writeStream.foreachBatch(keep).outputMode(mode).option("checkpointLocation", f"{path}/progress").trigger(availableNow=True).start().awaitTermination()
    kept = written[-1:] if mode == "complete" else sorted(set(written))
    return spark.read.schema(stream.schema).parquet(*kept) if kept else spark.createDataFrame([], stream.schema)


def tumbling(spark, sf_dir, size: str = "1 hour") -> DataFrame:
    counts = _events(spark, sf_dir).withWatermark("ts", "1 hour").groupBy(F.window("ts", size), "event_type").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("value"), 4).alias("total"))
    return run_to_table(counts, "complete").select(F.date_format("window.start", "yyyy-MM-dd HH:mm:ss").alias("start"), "event_type", "n", "total")


def sliding(spark, sf_dir, size: str = "2 hours", step: str = "1 hour") -> DataFrame:
    counts = _events(spark, sf_dir).withWatermark("ts", "1 hour").groupBy(F.window("ts", size, step)).agg(F.count(F.lit(1)).alias("n"))
    return run_to_table(counts, "complete").select(F.date_format("window.start", "yyyy-MM-dd HH:mm:ss").alias("start"), "n")


def sessions(spark, sf_dir, path: str, gap: str = "30 minutes") -> DataFrame:
    counts = _events(spark, sf_dir).withWatermark("ts", "1 hour").groupBy(F.session_window("ts", gap), "user_id").agg(F.count(F.lit(1)).alias("n"))
    return run_to_files(counts.select("user_id", F.date_format("session_window.start", "yyyy-MM-dd HH:mm:ss").alias("start"), "n"), path, "complete")


def deduplicated(spark, sf_dir, path: str) -> DataFrame:
    once = _events(spark, sf_dir).select("event_id", "event_type", "ts").withWatermark("ts", "1 hour").dropDuplicatesWithinWatermark(["event_id"])
    return run_to_files(once.select("event_type"), path).groupBy("event_type").agg(F.count(F.lit(1)).alias("n"))
