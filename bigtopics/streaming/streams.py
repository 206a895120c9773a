"""Structured Streaming: windows over query events, dedupe, profiles of users, prediction of new queries."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..sources.files import scratch


def replay(spark: SparkSession, path: str, schema) -> DataFrame:
    """A Parquet folder or file pattern as a stream."""
    return spark.readStream.schema(schema).parquet(path)


def drained(stream: DataFrame, name: str, mode: str = "append") -> DataFrame:
    """Runs a stream over what is there now and returns what it wrote."""
    spark = stream.sparkSession
    out, rows = scratch(spark, name), scratch(spark, name + "-log")
    if mode == "append":
        q = stream.writeStream.format("parquet").option("path", out).option("checkpointLocation", rows).trigger(availableNow=True).start()
    else:

        def put(batch: DataFrame, _: int) -> None:
            batch.write.mode("overwrite").parquet(out)

        q = stream.writeStream.outputMode(mode).foreachBatch(put).option("checkpointLocation", rows).trigger(availableNow=True).start()
    q.awaitTermination()
    if q.exception():
        raise q.exception()
    return spark.read.schema(stream.schema).parquet(out)


def tumbling(events: DataFrame, width: str = "1 hour") -> DataFrame:
    """start, event_type, n, total."""
    g = events.groupBy(F.window("ts", width).alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("value"), 4).alias("total"))
    return g.select(F.col("w.start").alias("start"), "event_type", "n", "total")


def sliding(events: DataFrame, width: str = "2 hours", slide: str = "1 hour") -> DataFrame:
    return events.groupBy(F.window("ts", width, slide).alias("w")).agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("start"), "n")


def sessions(events: DataFrame, gap: str = "30 minutes") -> DataFrame:
    """user_id, start, n of each run of events without a pause of the gap."""
    return events.groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.count(F.lit(1)).alias("n")).select("user_id", F.col("w.start").alias("start"), "n")


def unique_queries(events: DataFrame, keys: list[str], late: str = "1 hour") -> DataFrame:
    """The first of equal keys within the watermark."""
    return events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", late).dropDuplicatesWithinWatermark(keys)


def predict_stream(queries: DataFrame, predict: Callable[[DataFrame], DataFrame], name: str = "predictions") -> DataFrame:
    """Applies a batch predictor to each micro-batch of a stream of queries and returns all results."""
    spark = queries.sparkSession
    out, log = scratch(spark, name), scratch(spark, name + "-log")

    def put(batch: DataFrame, n: int) -> None:
        predict(batch).write.mode("overwrite").parquet(f"{out}/batch={n}")

    queries.writeStream.foreachBatch(put).option("checkpointLocation", log).trigger(availableNow=True).start().awaitTermination()
    return spark.read.parquet(out).drop("batch")


def updated(stream: DataFrame, name: str) -> DataFrame:
    """All rows a stream of aggregates emits in update mode, with the number of their micro-batch; the last of a key is its value."""
    out, log = scratch(stream.sparkSession, name), scratch(stream.sparkSession, name + "-log")

    def put(batch: DataFrame, n: int) -> None:
        batch.write.mode("overwrite").parquet(f"{out}/batch={n}")

    stream.writeStream.outputMode("update").foreachBatch(put).option("checkpointLocation", log).trigger(availableNow=True).start().awaitTermination()
    return stream.sparkSession.read.parquet(out)
