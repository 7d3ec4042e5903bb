"""The incremental path: commits and events that keep arriving."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import DataStreamWriter

from ..functions.text import digest
from ..sources.tables import TABLES


def event_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    """events as a stream; ts becomes a session timestamp, which watermarks need."""
    raw = spark.readStream.schema(TABLES["events"]).parquet(f"{sf_dir}/events.parque[t]")  # a glob: a plain path would have to be a folder
    return raw.withColumn("ts", F.col("ts").cast("timestamp"))


def daily_rates(events: DataFrame, late: str = "7 days", positive: str = "error") -> DataFrame:
    """day, n, n_positive, mean value per tumbling day."""
    per = events.withWatermark("ts", late).groupBy(F.window("ts", "1 day")).agg(F.count(F.lit(1)).alias("n"), F.count_if(F.col("event_type") == positive).alias("n_positive"))
    return per.select(F.date_format("window.start", "yyyy-MM-dd").alias("day"), "n", "n_positive")


def sliding_rates(events: DataFrame, late: str = "7 days", width: str = "7 days", step: str = "1 day") -> DataFrame:
    per = events.withWatermark("ts", late).groupBy(F.window("ts", width, step), "event_type").agg(F.count(F.lit(1)).alias("n"))
    return per.select(F.date_format("window.start", "yyyy-MM-dd").alias("first_day"), "event_type", "n")


def sessions(events: DataFrame, gap: str = "30 minutes", late: str = "1 day") -> DataFrame:
    """user_id, starts, n: bursts of activity."""
    per = events.withWatermark("ts", late).groupBy("user_id", F.session_window("ts", gap)).agg(F.count(F.lit(1)).alias("n"))
    return per.select("user_id", F.date_format("session_window.start", "yyyy-MM-dd HH:mm:ss").alias("starts"), "n")


def first_seen(events: DataFrame, key: str = "digest", late: str = "1 day") -> DataFrame:
    """Rows whose digest has not been seen within the watermark; state is bounded by it."""
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark([key])


def with_event_digest(events: DataFrame) -> DataFrame:
    return events.withColumn("digest", digest(F.concat_ws("|", "event_type", F.col("user_id").cast("string"))))


def dedup_against_table(batch: DataFrame, seen_path: str, key: str = "digest") -> DataFrame:
    """For foreachBatch: rows of a micro-batch that neither the table nor the batch itself holds yet; unbounded history
    lives in the table, not in stream state."""
    spark = batch.sparkSession
    fresh = batch.dropDuplicates([key])
    try:
        return fresh.join(spark.read.parquet(seen_path).select(key), key, "left_anti")
    except Exception as missing:
        if "PATH_NOT_FOUND" not in str(missing):
            raise
        return fresh


def _place(spark: SparkSession, name: str) -> str:
    base = spark.conf.get("spark.checkpoint.dir", None) or tempfile.mkdtemp(prefix="stream-")
    return f"{base.rstrip('/')}/{name}-{uuid.uuid4().hex}"


def drain(stream: DataFrame, name: str, mode: str = "complete", prepare: Callable[[DataFrame], DataFrame] | None = None) -> DataFrame:
    """Run a stream over what is there now and return the result as a table.

    mode "complete" keeps the last full result, "append" what each micro-batch adds (a distributed parquet sink)."""
    spark = stream.sparkSession
    out, log = _place(spark, name), _place(spark, f"{name}-log")
    writer: DataStreamWriter = stream.writeStream.outputMode(mode).trigger(availableNow=True).option("checkpointLocation", log)
    if mode == "complete":
        writer = writer.foreachBatch(lambda df, n: (prepare(df) if prepare else df).write.mode("overwrite").parquet(out))
        schema = (prepare(stream) if prepare else stream).schema
        query = writer.start()
    else:
        schema = stream.schema
        query = writer.format("parquet").start(out)
    query.awaitTermination()
    return spark.read.schema(schema).parquet(out)


def label_corrections(predictions: DataFrame, truth: DataFrame, within: str = "7 days") -> DataFrame:
    """Stream-stream join: predictions with truth that arrives up to ``within`` later."""
    p = predictions.withWatermark("ts", "1 day").select("event_id", F.col("ts").alias("predicted_at"), "pred")
    t = truth.withWatermark("ts", "1 day").select(F.col("event_id").alias("truth_id"), F.col("ts").alias("known_at"), "label")
    return p.join(t, F.expr(f"event_id = truth_id AND known_at >= predicted_at AND known_at <= predicted_at + INTERVAL {within}"))
