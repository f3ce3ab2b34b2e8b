"""Streams of several files end where batches do; late rows are dropped."""

import datetime as dt

from pyspark.sql import functions as F

from vertexlog.streaming import events as streams


def test_several_files_fold_like_a_batch(spark, tmp_path):
    start = dt.datetime(2024, 1, 1)
    rows = [(i, start + dt.timedelta(minutes=7 * i), i % 3, "view", 1.0, "{}") for i in range(300)]
    table = spark.createDataFrame(rows, "event_id bigint, ts timestamp, user_id bigint, event_type string, value double, props string")
    for k in range(3):
        table.where(f"event_id div 100 = {k}").coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    stream = streams.source(spark, str(tmp_path / "in"), table)
    got = streams.collected(streams.windowed_fold(stream, "1 day", late="10 days"), "complete")
    expected = table.groupBy(F.window("ts", "1 day").alias("w"), F.col("user_id").alias("dst")).agg(F.count("*").alias("n"))
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, expected.collect()))


def test_rows_behind_the_watermark_are_dropped(spark, tmp_path):
    schema = "event_id bigint, ts timestamp, user_id bigint, event_type string, value double, props string"
    one = lambda i, day: spark.createDataFrame([(i, dt.datetime(2024, 1, day), 0, "view", 1.0, "{}")], schema).coalesce(1)
    source, seen = str(tmp_path / "in"), []
    where = str(tmp_path / "check")
    for i, day in ((0, 1), (1, 20), (2, 1), (3, 28)):
        one(i, day).write.mode("append").parquet(source)
        stream = streams.source(spark, source, one(0, 1))
        query = (
            streams.windowed_fold(stream, "1 day", late="2 days").writeStream.outputMode("append")
            .foreachBatch(lambda d, n: seen.extend(r["n"] for r in d.collect())).option("checkpointLocation", where).trigger(availableNow=True).start()
        )
        query.awaitTermination()
    assert seen.count(1) >= 1 and 2 not in seen


def test_rows_behind_the_watermark_are_counted(spark, tmp_path):
    schema = "event_id bigint, ts timestamp, user_id bigint, event_type string, value double, props string"
    make = lambda users, day: spark.createDataFrame([(u, dt.datetime(2024, 1, day), u, "view", 1.0, "{}") for u in users], schema).coalesce(1)
    source, lost = str(tmp_path / "in"), []
    for users, day in (([0], 1), ([0], 20), ([0, 1, 2], 1), ([0], 28)):
        make(users, day).write.mode("append").parquet(source)
        fold = streams.windowed_fold(streams.source(spark, source, make([0], 1)), "1 day", late="2 days")
        lost.append(streams.drain(fold, lambda d, n: d.count(), checkpoint=str(tmp_path / "check")))
    assert lost == [0, 0, 3, 0]


def test_as_of_picks_the_last_purchase_before(spark):
    t = lambda d, h: dt.datetime(2024, 1, d, h)
    rows = [(0, t(1, 1), "view"), (1, t(1, 2), "purchase"), (2, t(1, 3), "view"), (3, t(2, 1), "view"), (4, t(2, 2), "purchase"), (5, t(2, 3), "view")]
    table = spark.createDataFrame(rows, "event_id bigint, ts timestamp, event_type string")
    assert sorted(map(tuple, streams.as_of(table).collect())) == [(1, 2), (1, 3), (4, 5)]
