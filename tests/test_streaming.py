"""Streams give the batch answer over what is there; late rows are dropped; a restart goes on."""

import datetime as dt

from pyspark.sql import functions as F

from cotengine.streaming import streams

SCHEMA = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"


def _rows(day, n, first):
    return [(first + i, dt.datetime(2024, 1, day, 1), 5 + i % 3, "view", 1.0, '{"k": 3}') for i in range(n)]


def test_late_rows_and_restart(spark, tmp_path):
    src, check = str(tmp_path / "in"), str(tmp_path / "c")

    def add(day, n, first):
        spark.createDataFrame(_rows(day, n, first), SCHEMA).coalesce(1).write.mode("append").parquet(src)

    def run(out):
        stream = streams.curve(streams.file_stream(spark, src, spark.createDataFrame([], SCHEMA).schema), late="1 day")
        return streams.upsert_sink(stream, str(tmp_path / out), check)

    add(1, 4, 0)
    run("out").awaitTermination()
    add(10, 5, 10)
    run("out").awaitTermination()
    add(2, 7, 20)  # later than the watermark by days
    add(20, 1, 40)
    run("out").awaitTermination()
    got = {r.start.day: r.n for r in spark.read.parquet(str(tmp_path / "out") + "/*").collect()}
    assert got.get(1) == 4 and got.get(10) == 5 and 2 not in got


def test_full_groups(spark, tmp_path):
    src = str(tmp_path / "in")
    spark.createDataFrame(_rows(1, 14, 0), SCHEMA).coalesce(1).write.parquet(src)
    stream = streams.marked(streams.file_stream(spark, src, spark.createDataFrame([], SCHEMA).schema))
    out = streams.run_available(streams.full_groups(stream, 4), "groups4", "append", str(tmp_path / "c"))
    assert {r.prompt: r.c for r in out.groupBy("prompt").agg(F.count("*").alias("c")).collect()} == {5: 1, 6: 1, 7: 1}
