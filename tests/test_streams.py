"""Streams that are drained to a whole table."""

from pyspark.sql import functions as F

from slicelink.streaming import online


def test_complete_tables_are_files_not_driver_rows(spark, sf):
    key = "spark.sql.streaming.stateStore.providerClass"
    before = spark.conf.get(key, None)
    out = online.drain(online.monitor(online.events(spark, sf), "session", delay="60 days", keys=("user_id",)), "complete", "whole")
    assert spark.conf.get(key, None) == before
    assert out.inputFiles()
    assert out.agg(F.sum("n")).first()[0] == spark.read.parquet(f"{sf}/events.parquet").count()


def test_complete_without_rows(spark, sf):
    none = online.events(spark, sf).where("event_id < 0")
    assert online.drain(online.monitor(none, delay="60 days"), "complete", "none").count() == 0


def test_update_keeps_every_change(spark, sf, tmp_path):
    part = spark.read.parquet(f"{sf}/events.parquet").orderBy("ts").coalesce(1)
    for k in (0, 1):
        part.where(f"event_id % 2 = {k}").write.mode("append").parquet(str(tmp_path))
    rows = online.read_stream(spark, str(tmp_path), part.schema).withColumn("at", F.col("ts").cast("timestamp"))
    got = online.drain(online.monitor(rows, delay="60 days"), "update", "changes").groupBy("start", "event_type").agg(F.max("n").alias("n"))
    assert got.agg(F.sum("n")).first()[0] == part.count()
