"""Streams of captures and predictions (an extension; the batch operators stay the reference).

Late rows beyond the watermark are dropped; duplicates within it count once. With an `availableNow` trigger a stream gives what the
batch gives."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..sources.tables import SCHEMAS


def captures_stream(spark: SparkSession, folder: str, files_per_trigger: int = 1) -> DataFrame:
    """`events` files as they arrive, with a time-zoned event time."""
    raw = spark.readStream.schema(SCHEMAS["events"]).option("maxFilesPerTrigger", files_per_trigger).parquet(folder)
    return raw.withColumn("ts", F.col("ts").cast("timestamp"))


def daily_density(events: DataFrame, late: str = "10 minutes") -> DataFrame:
    """Views per region and day, each event once."""
    unique = events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])
    return unique.groupBy(F.window("ts", "1 day"), F.pmod("user_id", F.lit(8)).alias("region")).agg(F.count("*").alias("n"))


def sliding_rate(log: DataFrame, late: str = "10 minutes") -> DataFrame:
    """Switch rate over an hour, every ten minutes; rows are (ts, model, transform, pred0, pred)."""
    changed = F.when(~F.col("pred").eqNullSafe(F.col("pred0")), 1).otherwise(0)
    return log.withWatermark("ts", late).groupBy(F.window("ts", "1 hour", "10 minutes"), "model", "transform").agg(F.count("*").alias("n"), F.sum(changed).alias("switched"))


def sessions(events: DataFrame, gap: str = "30 minutes", late: str = "10 minutes") -> DataFrame:
    return events.withWatermark("ts", late).groupBy("user_id", F.session_window("ts", gap)).agg(F.count("*").alias("n"))


def seen_in_training(events: DataFrame, training_sites: DataFrame) -> DataFrame:
    """Arriving views whose site is a training site: a stream-static semi-join without state."""
    site = F.concat_ws("|", F.col("user_id").cast("string"), F.date_format("ts", "yyyy-MM-dd"))
    return events.withColumn("site", site).join(training_sites.select("site"), "site", "left_semi")


def write_batches(stream: DataFrame, path: str, checkpoint: str):
    """Complete results after every micro-batch, replaced as a whole, until the input is used up."""
    return stream.writeStream.outputMode("complete").foreachBatch(lambda df, _: df.write.mode("overwrite").parquet(path)).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
