"""Streams against their batch twins, over several micro-batches and in any order."""

from pyspark.sql import functions as F

from lpstream.operators import sketch as sk
from lpstream.sources import updates as up
from lpstream.sources.replay import ReplaySource
from lpstream.streaming import streams


def split(spark, sf, path, parts=4):
    """events as several files of one folder."""
    spark.read.parquet(f"{sf}/events.parquet").repartition(parts, "event_id").write.parquet(f"{path}/events.parquet")
    return str(path)


def cells(df):
    return {(r.rep, r.bucket, r.col_id): int(r.val) for r in df.filter("val <> 0").collect()}


def test_stream_is_batch_over_micro_batches(spark, sf, tmp_path):
    d = split(spark, sf, tmp_path)
    want = cells(sk.build(up.user_days(spark, sf), streams.SPEC))
    assert cells(streams.sketch_update(spark, d)) == want
    assert cells(streams.foreach_batch(spark, d)) == want


def test_late_rows_drop_only_from_windows(spark, tmp_path, sf):
    d = split(spark, sf, tmp_path)
    windowed = streams.late_data(spark, d).agg(F.sum("n")).first()[0] or 0
    assert windowed <= spark.read.parquet(f"{sf}/events.parquet").count()
    assert streams.dedup(spark, sf).count() == spark.read.parquet(f"{sf}/events.parquet").count()


def test_replay_source_batch_and_stream(spark, tmp_path):
    spark.dataSource.register(ReplaySource)
    batch = spark.read.format("replay_updates").option("count", 900).option("partitions", 3).load()
    q = spark.readStream.format("replay_updates").option("count", 900).load().writeStream.format("memory").queryName("replayed").start()
    try:
        for _ in range(60):
            if spark.table("replayed").count() >= 900:
                break
            q.awaitTermination(1)
    finally:
        q.stop()
    assert sorted(map(tuple, spark.table("replayed").collect())) == sorted(map(tuple, batch.collect()))


def test_set_values_in_any_order(spark, sf, tmp_path):
    """Files out of the order of events, and groups that come in several frames."""
    e = spark.read.parquet(f"{sf}/events.parquet").withColumn("user_id", F.col("user_id") % 2)
    e.repartition(3, "event_id").write.parquet(f"{tmp_path}/events.parquet")
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", 7)
    try:
        got = sorted(map(tuple, streams.set_value_state(spark, str(tmp_path)).collect()))
    finally:
        spark.conf.unset("spark.sql.execution.arrow.maxRecordsPerBatch")
    e.createOrReplaceTempView("set_values")
    want = spark.sql("select event_id, round(value - coalesce(lag(value) over (partition by user_id, event_type order by ts, event_id), 0), 6) as delta from set_values")
    assert got == sorted(map(tuple, want.collect()))
