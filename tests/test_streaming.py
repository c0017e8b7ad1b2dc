"""Late rows and restarts of streams."""

from pyspark.sql import functions as F

from thriftline.streaming import events


def _stream(spark, path, schema):
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(path)


def test_rows_behind_the_watermark_are_dropped(spark, tmp_path):
    schema = "ts timestamp, event_type string"
    path = str(tmp_path / "in")
    # A batch drops what is behind the watermark that the batch before it worked with.
    batches = [[("2024-01-01 00:10:00", "a"), ("2024-01-01 06:00:00", "a")], [("2024-01-01 05:30:00", "near")], [("2024-01-01 00:20:00", "late"), ("2024-01-02 12:00:00", "a")]]
    for n, rows in enumerate(batches):
        spark.createDataFrame(rows, "ts string, event_type string").withColumn("ts", F.col("ts").cast("timestamp")).coalesce(1).write.mode("append").parquet(path)
        # Files are read in order of their times.
        import time

        time.sleep(1.1)
        del n
    counted = events.drained(events.tumbling(_stream(spark, path, schema), "1 hour", "1 hour"))
    assert sorted(r["event_type"] for r in counted.collect()) == ["a", "a", "near"]


def test_a_stream_that_starts_again_goes_on(spark, tmp_path):
    schema, path, base = "event_id long, value_c long", str(tmp_path / "in"), str(tmp_path / "base")
    by, seen = [F.col("value_c").desc(), F.col("event_id")], []
    for turn in range(3):
        rows = [(10 * turn + i, (7 * i + 3 * turn) % 11) for i in range(10)]
        seen += rows
        spark.createDataFrame(rows, schema).coalesce(1).write.mode("append").parquet(path)
        got = events.merged_topk(_stream(spark, path, schema), by, 4, base)
        assert sorted(map(tuple, got.collect())) == sorted(sorted(seen, key=lambda r: (-r[1], r[0]))[:4])
