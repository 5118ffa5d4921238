"""Event streams as transactions of windows, and the margins of their items."""

from __future__ import annotations

import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..sources.files import shared_folder
from ..sources.views import table


def event_stream(spark: SparkSession, sf_dir: str, late: str | None = "1 hour") -> DataFrame:
    """The events table, one file or a folder of files, as a stream; with a watermark if `late` is given."""
    schema = table(spark, sf_dir, "events").schema
    stream = spark.readStream.schema(schema).parquet(f"{sf_dir}/events.parquet*")
    return stream.withWatermark("ts", late) if late else stream


def window_counts(events: DataFrame, window: Column) -> DataFrame:
    """(start, event_type, cnt) of each window; for batch and stream alike."""
    return events.groupBy(window.alias("w"), "event_type").agg(F.count("*").alias("cnt")).select(F.col("w.start").alias("start"), "event_type", "cnt")


def replayed(stream: DataFrame, keys: list[str], value: str) -> DataFrame:
    """What a streaming aggregation gives once all its files have been read: the last value of every key.

    Each micro-batch writes the keys that it changed to its own folder of the shared one, over what an
    earlier try of the batch left; nothing passes through the driver.
    """
    root = f"{shared_folder(stream.sparkSession)}/stream-{uuid.uuid4().hex}"

    def keep(changed: DataFrame, batch: int) -> None:
        changed.write.mode("overwrite").parquet(f"{root}/changes/batch={batch}")

    running = stream.writeStream.outputMode("update").foreachBatch(keep).option("checkpointLocation", f"{root}/state").trigger(availableNow=True).start()
    running.awaitTermination()
    changes = stream.sparkSession.read.parquet(f"{root}/changes")
    return changes.groupBy(*keys).agg(F.max_by(value, "batch").alias(value))
