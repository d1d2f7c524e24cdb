"""Event-time plans over the events table: windows, late rows, duplicates, joins, and a stateful drift monitor."""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from annspark.sources import datasets as ds

EVENTS = "event_id long, ts timestamp, user_id long, event_type string, value double"


def files(spark: SparkSession, sf_dir: str, path: str, late: bool = False) -> str:
    """The events in arrival files of some days each; ``late``: every fiftieth row arrives in the last file, long after its time."""
    e = ds.table(spark, sf_dir, "events").select("event_id", F.col("ts").cast("timestamp").alias("ts"), "user_id", "event_type", "value")
    day = F.least(F.lit(3), F.floor((F.dayofmonth("ts") - 1) / 8)).cast("int")
    e = e.withColumn("part", F.when(F.col("event_id") % 50 == 0, 4).otherwise(day) if late else day)
    for i in range(5 if late else 4):
        e.where(F.col("part") == i).drop("part").coalesce(1).write.mode("append").parquet(path)
    return path


def stream(spark: SparkSession, path: str) -> DataFrame:
    return spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", 1).parquet(path)


def run_to(df: DataFrame, path: str) -> DataFrame:
    """As ``run`` in append mode, but results go to files under ``path`` and keys are held by RocksDB: neither has to fit a heap."""
    name = "spark.sql.streaming.stateStore.providerClass"
    before = df.sparkSession.conf.get(name)
    df.sparkSession.conf.set(name, "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    try:
        q = df.writeStream.format("parquet").option("path", f"{path}/rows").option("checkpointLocation", f"{path}/state").outputMode("append").trigger(availableNow=True).start()
        q.awaitTermination()
    finally:
        df.sparkSession.conf.set(name, before)
    return df.sparkSession.read.schema(df.schema).parquet(f"{path}/rows")


def run(df: DataFrame, mode: str = "append") -> DataFrame:
    """Everything that is there now, through the streaming engine, as a table in the driver's memory."""
    name = "annspark_" + uuid.uuid4().hex
    q = df.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True).start()
    q.awaitTermination()
    return df.sparkSession.table(name)


def tumbling(events: DataFrame, width: str = "6 hours", delay: str = "1 day") -> DataFrame:
    return events.withWatermark("ts", delay).groupBy(F.window("ts", width), "event_type").agg(F.count("*").alias("n")).select(F.col("window.start").alias("start"), "event_type", "n")


def deduplicated(events: DataFrame, delay: str = "1 day") -> DataFrame:
    return events.withWatermark("ts", delay).dropDuplicatesWithinWatermark(["event_id"])


def with_static(events: DataFrame, static: DataFrame) -> DataFrame:
    return events.join(static, "event_id")


def joined(left: DataFrame, right: DataFrame, within: str = "1 hour", delay: str = "2 hours") -> DataFrame:
    """Signups and purchases of one user within an hour, both sides bounded by watermarks."""
    a = left.where("event_type = 'signup'").select(F.col("event_id").alias("a"), F.col("user_id").alias("ua"), F.col("ts").alias("ta")).withWatermark("ta", delay)
    b = right.where("event_type = 'purchase'").select(F.col("event_id").alias("b"), F.col("user_id").alias("ub"), F.col("ts").alias("tb")).withWatermark("tb", delay)
    return a.join(b, F.expr(f"ua = ub AND tb >= ta AND tb <= ta + INTERVAL {within}")).select("a", "b")


def drift(assigned: DataFrame, alarm: float = 0.1) -> DataFrame:
    """(cell, n, affinity, alarm): running mean affinity per cell, and whether it fell by ``alarm`` from its first batch: a sign to refresh."""

    def update(key: tuple, parts: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        first, n, total = state.get if state.exists else (None, 0, 0.0)
        for p in parts:
            n, total = n + len(p), total + float(p["ip"].sum())
            first = float(p["ip"].mean()) if first is None else first
        state.update((first, n, total))
        yield pd.DataFrame({"cell": [key[0]], "n": [n], "affinity": [total / n], "alarm": [first - total / n >= alarm]})

    return assigned.groupBy("cell").applyInPandasWithState(update, "cell long, n long, affinity double, alarm boolean", "first double, n long, total double", "update", GroupStateTimeout.NoTimeout)
