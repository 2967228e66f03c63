"""Streams over the events table: windows with watermarks, deduplication, joins, mergeable partials."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..core.session import new_path

#: Longer than the span of the given events, so that none of them is late. Shorter bounds drop what is later.
LATE = "40 days"


def events_stream(spark: SparkSession, sf_dir: str, files: str = "events.parquet", per_batch: int = 8) -> DataFrame:
    """The events as a stream of files, ``per_batch`` of them a batch; ``at`` is the event time."""
    schema = spark.read.parquet(f"{sf_dir}/{files}").schema
    stream = spark.readStream.schema(schema).option("maxFilesPerTrigger", per_batch).option("pathGlobFilter", files).parquet(sf_dir)
    at = F.expr("cast(unix_micros(timestamp '1970-01-01 00:00:00+00:00') + timestampdiff(MICROSECOND, timestamp_ntz'1970-01-01 00:00:00', cast(ts as timestamp_ntz)) as bigint)")
    return stream.withColumn("us", at).withColumn("at", F.timestamp_micros("us")).withColumn("val", F.round(F.col("value") * 100).cast("long"))


def hourly_counts(spark: SparkSession, sf_dir: str, late: str = LATE, **options) -> DataFrame:
    """Tumbling windows of an hour per event type; an event that comes more than ``late`` behind the latest of
    the batches before may find its window closed, and is then dropped."""
    windowed = events_stream(spark, sf_dir, **options).withWatermark("at", late).groupBy("event_type", F.window("at", "1 hour").alias("w"))
    counted = windowed.agg(F.count("*").alias("n"), F.sum("val").alias("s"))
    return counted.select("event_type", F.floor(F.unix_micros(F.col("w.start")) / 3_600_000_000).cast("long").alias("hour"), "n", "s")


def run_available(df: DataFrame, mode: str, keys: list[str] | None = None) -> DataFrame:
    """Run a stream over what is there and return the result as a table in the shared folder.

    Every batch writes its output there: append adds up, complete leaves the last, update the last row of
    each of the ``keys``."""
    spark = df.sparkSession
    path, batches = new_path(spark, "stream"), []

    def write(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/data/batch={number}")
        batches.append(number)

    df.writeStream.foreachBatch(write).outputMode(mode).option("checkpointLocation", f"{path}/log").trigger(availableNow=True).start().awaitTermination()
    if not batches:
        return spark.createDataFrame([], df.schema)
    out = spark.read.option("basePath", f"{path}/data").schema(df.schema.add("batch", "long")).parquet(f"{path}/data")
    if mode == "complete":
        out = out.where(F.col("batch") == max(batches))
    elif mode == "update":
        newest = F.row_number().over(Window.partitionBy(*(keys or df.columns)).orderBy(F.desc("batch")))
        out = out.withColumn("__k", newest).where("__k = 1").drop("__k")
    return out.drop("batch")


def merge_partials(spark: SparkSession, sf_dir: str, path: str) -> DataFrame:
    """Per-user multiplicities: each batch writes its partial counts, reading combines them (L692)."""

    def write(batch: DataFrame, number: int) -> None:
        batch.groupBy("user_id").agg(F.count("*").alias("mult")).write.mode("overwrite").parquet(f"{path}/data/batch={number}")

    query = events_stream(spark, sf_dir).writeStream.foreachBatch(write).option("checkpointLocation", f"{path}/log").trigger(availableNow=True).start()
    query.awaitTermination()
    return spark.read.parquet(f"{path}/data").groupBy("user_id").agg(F.sum("mult").alias("mult"))


def sliding_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    windowed = events_stream(spark, sf_dir).withWatermark("at", LATE).groupBy("event_type", F.window("at", "2 hours", "1 hour").alias("w"))
    return windowed.agg(F.count("*").alias("n")).select("event_type", F.floor(F.unix_micros(F.col("w.start")) / 3_600_000_000).cast("long").alias("hour"), "n")


def session_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    windowed = events_stream(spark, sf_dir).withWatermark("at", LATE).groupBy("user_id", F.session_window("at", "1 hour").alias("w"))
    return windowed.agg(F.count("*").alias("n")).select("user_id", F.unix_micros(F.col("w.start")).alias("first_us"), "n")


def errors_then_purchases(spark: SparkSession, sf_dir: str) -> DataFrame:
    """State is bounded by both watermarks and the hour."""
    side = lambda kind, name: events_stream(spark, sf_dir).where(F.col("event_type") == kind).select(F.col("event_id").alias(f"{name}_id"), F.col("user_id").alias(f"{name}_user"), F.col("at").alias(f"{name}_at")).withWatermark(f"{name}_at", LATE)
    within = F.expr("error_user = purchase_user and purchase_at >= error_at and purchase_at <= error_at + interval 1 hour")
    return side("error", "error").join(side("purchase", "purchase"), within).select("error_id", "purchase_id")
