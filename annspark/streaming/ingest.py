"""Structured Streaming ingestion into an index directory, with refreshes when their trigger is due."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery

from annspark.operators import refresh
from annspark.sources import layout

VECTORS = "id long, v array<double>, batch int"


def arrivals(df: DataFrame, path: str) -> int:
    """Cut (id, v, batch) into one arrival file a batch, in order; returns the number of batches."""
    n = df.agg(F.max("batch")).first()[0] + 1
    for i in range(n):
        df.where(F.col("batch") == i).select("id", "v", "batch").coalesce(1).write.mode("append").parquet(path)
    return n


def insert(batch: DataFrame, batch_id: int, path: str, trigger: refresh.Trigger | None = None, raw: DataFrame | None = None, **options) -> int:
    """Add one batch to the live epoch, then refresh if the trigger is due; returns the epoch that is live afterwards.

    The counters of the trigger are the manifest's: rows inserted since the epoch opened, and their mean coarse affinity against that of
    its first rows. ``raw`` has the vectors (id, v) to refresh from; None takes them from the codes.
    """
    spark = batch.sparkSession
    layout.append(batch.select("id", "v"), path, batch_id)
    now = layout.live(spark, path)
    if trigger is not None and trigger.due(now.index.inserted, now.affinity_then, now.affinity_now):
        return layout.refresh(spark, path, raw, **options).epoch
    return now.index.epoch


def start(
    spark: SparkSession, source: str, path: str, checkpoint: str, refresh_when: refresh.Trigger | None = None, raw: DataFrame | None = None, options: dict | None = None, after: Callable[[DataFrame, int], None] | None = None, **trigger
) -> StreamingQuery:
    """Each micro-batch goes to the epoch that is live when it comes, by its batch id: at-least-once delivery, exactly-once state.

    ``refresh_when`` refreshes inside the stream, after the batch that makes it due; ``options`` are those of ``refresh.run``.
    """

    def take(batch: DataFrame, batch_id: int) -> None:
        insert(batch, batch_id, path, refresh_when, raw, **(options or {}))
        if after is not None:
            after(batch, batch_id)

    stream = spark.readStream.schema(VECTORS).option("maxFilesPerTrigger", 1).parquet(source)
    return stream.writeStream.foreachBatch(take).option("checkpointLocation", checkpoint).trigger(**(trigger or {"availableNow": True})).start()
