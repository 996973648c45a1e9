"""The stage log as a stream: windowed funnel, completion within a day, and idempotent commits."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

EVENT = "event_id bigint, ts timestamp_ntz, user_id bigint, event_type string, value double, props string"


def source(spark: SparkSession, sf_dir: str, files_a_batch: int = 1000) -> DataFrame:
    raw = spark.readStream.schema(EVENT).option("pathGlobFilter", "*.parquet").option("maxFilesPerTrigger", files_a_batch).parquet(f"{sf_dir}/events.parquet*")
    return raw.withColumn("ts", F.col("ts").cast("timestamp"))


def drained(stream: DataFrame, mode: str) -> DataFrame:
    """What a stream has given when all available files are read, as a table in the shared folder.

    In complete mode every micro-batch holds the whole result, so the last one counts; in append mode all batches do.
    """
    from ..operators.crawl import shared_dir

    spark = stream.sparkSession
    at = f"{shared_dir(spark)}/stream/{uuid.uuid4().hex}"

    numbers = []

    def put(batch: DataFrame, number: int) -> None:
        numbers.append(number)
        batch.write.mode("overwrite").parquet(f"{at}/out/batch={number}")  # a repeated batch replaces itself

    query = stream.writeStream.outputMode(mode).trigger(availableNow=True).option("checkpointLocation", f"{at}/state").foreachBatch(put).start()
    query.awaitTermination()
    if mode == "complete":
        return spark.read.schema(stream.schema).parquet(f"{at}/out/batch={max(numbers)}") if numbers else spark.createDataFrame([], stream.schema)
    return spark.read.schema(stream.schema).option("basePath", f"{at}/out").parquet(f"{at}/out/batch=*").select(*stream.columns)


def funnel(events: DataFrame, late: str = "1 hour", width: str = "1 day") -> DataFrame:
    """Events by window and stage; works on a stream (complete mode) and on a table."""
    e = events.withWatermark("ts", late) if events.isStreaming else events
    return e.groupBy(F.window("ts", width).alias("w"), F.col("event_type").alias("stage")).agg(F.count(F.lit(1)).alias("n")).select(F.date_format("w.start", "yyyy-MM-dd").alias("window_start"), "stage", "n")


def completion(events: DataFrame, within: str = "24 hours") -> DataFrame:
    """Submissions (click) and whether the same user completes (purchase) within the time."""
    done = events.where("event_type = 'purchase'").select(F.col("user_id").alias("u"), F.col("ts").alias("t"))
    asked = events.where("event_type = 'click'").select("event_id", "user_id", "ts")
    hit = asked.join(done, (F.col("user_id") == F.col("u")) & (F.col("t") >= F.col("ts")) & (F.col("t") <= F.col("ts") + F.expr(f"INTERVAL {within}")), "left_semi").select("event_id").withColumn("done", F.lit(1))
    return asked.join(hit, "event_id", "left").select("event_id", F.coalesce("done", F.lit(0)).alias("done"))


def completed(events: DataFrame, within: str = "24 hours", late: str = "24 hours") -> DataFrame:
    """event_id of each click of a stream that a purchase of the same user follows in time: a join of two streams.

    State is kept for as long as the watermarks allow a partner to come; append mode.
    """
    done = events.where("event_type = 'purchase'").select(F.col("user_id").alias("u"), F.col("ts").alias("t")).withWatermark("t", late)
    asked = events.where("event_type = 'click'").select("event_id", "user_id", "ts").withWatermark("ts", late)
    on = (F.col("user_id") == F.col("u")) & (F.col("t") >= F.col("ts")) & (F.col("t") <= F.col("ts") + F.expr(f"INTERVAL {within}"))
    return asked.join(done, on, "left_semi").select("event_id")


def sessions(events: DataFrame, gap: str = "30 minutes", late: str = "1 hour") -> DataFrame:
    """Sessions of each user: start, end of the last event and number of events; works on a stream (append mode) and on a table."""
    e = events.withWatermark("ts", late) if events.isStreaming else events
    s = e.groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.count(F.lit(1)).alias("n"), F.max("ts").alias("last_ts"))
    return s.select("user_id", F.col("w.start").alias("first_ts"), "last_ts", "n")


def late_split(events: DataFrame, late: str = "1 hour") -> DataFrame:
    """events with a mark late where a user's earlier event (by event_id) is ahead of them by more than the allowed time."""
    from pyspark.sql import Window as W

    ahead = F.max("ts").over(W.partitionBy("user_id").orderBy("event_id").rowsBetween(W.unboundedPreceding, -1))
    return events.withColumn("late", F.coalesce(F.col("ts") < ahead - F.expr(f"INTERVAL {late}"), F.lit(False)))
