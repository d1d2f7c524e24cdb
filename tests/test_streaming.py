"""Streams against the batch that they stand for."""

from pyspark.sql import functions as F

from annspark.plans import indexed
from annspark.sources import datasets as ds
from annspark.streaming import events
from tests.conftest import SF


def test_late_rows_are_dropped(spark):
    e = ds.table(spark, SF, "events")
    got = sum(r.n for r in indexed.st_watermark_late(spark, SF).collect())
    on_time = e.where("event_id % 50 <> 0").count()
    # windows that the watermark has not closed are not out yet; late rows never are
    assert 0.8 * on_time < got <= on_time


def test_tumbling_stream_is_the_batch(spark, tmp_path):
    src = events.files(spark, SF, str(tmp_path / "e"))
    out = {(r.start, r.event_type): r.n for r in events.run(events.tumbling(events.stream(spark, src))).collect()}
    e = ds.table(spark, SF, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    batch = {(r.start, r.event_type): r.n for r in e.groupBy(F.window("ts", "6 hours"), "event_type").agg(F.count("*").alias("n")).select(F.col("window.start").alias("start"), "event_type", "n").collect()}
    assert out and all(batch[k] == n for k, n in out.items()) and len(out) > 0.8 * len(batch)
