"""Streams of events: windowed features, late rows, duplicates, and joins of streams."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..session import shared_dir


def event_stream(spark: SparkSession, path: str, schema, files_per_trigger: int = 1) -> DataFrame:
    """Parquet files of events as a stream; ts becomes a timestamp, as watermarks need."""
    raw = spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(path)
    return raw.withColumn("ts", F.col("ts").cast("timestamp"))


def hourly(events: DataFrame, late: str = "1 hour") -> DataFrame:
    """Features by user and hour: count, mean, low, high of value."""
    x = events.withWatermark("ts", late) if events.isStreaming else events
    return _stats(x.groupBy(F.window("ts", "1 hour"), "user_id"))


def sliding(events: DataFrame, late: str = "1 hour") -> DataFrame:
    x = events.withWatermark("ts", late) if events.isStreaming else events
    return _stats(x.groupBy(F.window("ts", "1 hour", "15 minutes"), "event_type"))


def sessions(events: DataFrame, gap: str = "30 minutes", late: str = "1 hour") -> DataFrame:
    x = events.withWatermark("ts", late) if events.isStreaming else events
    return x.groupBy(F.session_window("ts", gap).alias("window"), "user_id").agg(F.count("*").alias("n"))


def _stats(grouped) -> DataFrame:
    return grouped.agg(F.count("*").alias("n"), F.avg("value").alias("mean"), F.min("value").alias("low"), F.max("value").alias("high"))


def distinct_events(events: DataFrame, late: str = "1 hour") -> DataFrame:
    """Each event once, with state no older than the watermark."""
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def clicks_then_purchases(events: DataFrame, most: str = "1 hour") -> DataFrame:
    """A purchase of a user within an hour after a click, as a join of two streams with bounded state."""
    click = events.where("event_type = 'click'").select(F.col("user_id").alias("u"), F.col("ts").alias("click_ts"))
    buy = events.where("event_type = 'purchase'").select("event_id", "user_id", F.col("ts").alias("buy_ts"))
    if events.isStreaming:
        click, buy = click.withWatermark("click_ts", most), buy.withWatermark("buy_ts", most)
    on = (F.col("u") == F.col("user_id")) & (F.col("buy_ts") >= F.col("click_ts")) & (F.col("buy_ts") <= F.col("click_ts") + F.expr(f"INTERVAL {most}"))
    return buy.join(click, on).select("event_id", "user_id", "click_ts", "buy_ts")


def run_to_table(stream: DataFrame, mode: str = "append", name: str = "out") -> DataFrame:
    """Runs a stream over all that is there and gives what it wrote; its checkpoint and output lie in the shared folder.
    Update and complete modes keep the last batch's rows of each key by rewriting, so they are for small results."""
    spark, base = stream.sparkSession, f"{shared_dir(stream.sparkSession)}/treeline-stream-{name}-{uuid.uuid4().hex}"
    out, check = f"{base}/out", f"{base}/check"
    if mode == "append":
        q = stream.writeStream.outputMode("append").format("parquet").option("path", out).option("checkpointLocation", check).trigger(availableNow=True).start()
    else:

        def write(batch: DataFrame, number: int) -> None:
            batch.write.mode("overwrite").parquet(f"{out}/batch={number}")  # the number makes a repeated batch harmless

        q = stream.writeStream.outputMode(mode).foreachBatch(write).option("checkpointLocation", check).trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.schema(stream.schema).parquet(out) if mode == "append" else spark.read.parquet(out)


def late_rows(progress: list) -> int:
    """Rows that came after their watermark, from a query's recent progress."""
    return sum(s.get("numRowsDroppedByWatermark", 0) for p in progress for s in p.get("stateOperators", []))
