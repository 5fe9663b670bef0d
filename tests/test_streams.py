"""Late rows: what comes a batch after the watermark has passed its window is dropped."""

import datetime
import time

from tabseek.streaming import feedback

SCHEMA = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"


def _batch(spark, path, rows):
    """One file, so that one micro-batch reads it."""
    values = [(i, datetime.datetime(2024, 1, 1, h, m, tzinfo=datetime.timezone.utc), 1, "view", 1.0, '{"k": 1}') for i, h, m in rows]
    spark.createDataFrame(values, SCHEMA).coalesce(1).write.mode("append").parquet(path)
    time.sleep(1.1)  # files are read in order of their times


def test_late_rows_are_dropped_and_batches_keep_them(spark, tmp_path):
    path = str(tmp_path / "events")
    for rows in ([(1, 10, 0), (2, 13, 0)], [(4, 13, 30)], [(3, 10, 5)], [(5, 15, 30)], [(6, 15, 40)]):
        _batch(spark, path, rows)
    stream = spark.readStream.schema(SCHEMA).option("maxFilesPerTrigger", 1).parquet(path)
    query = feedback.tumbling(stream).writeStream.format("memory").queryName("late_rows").outputMode("append").option("checkpointLocation", str(tmp_path / "log")).trigger(availableNow=True).start()
    query.awaitTermination()
    streamed = {r.start.hour: r.n for r in spark.table("late_rows").collect()}
    whole = {r.start.hour: r.n for r in feedback.tumbling(spark.read.parquet(path)).collect()}
    ten, one = sorted(whole)[0], sorted(whole)[1]
    assert (whole[ten], whole[one]) == (2, 2)
    assert (streamed[ten], streamed[one]) == (1, 2)


def test_daily_wins_of_nothing(spark):
    assert feedback.daily_wins(spark.createDataFrame([], SCHEMA)).collect() == []
