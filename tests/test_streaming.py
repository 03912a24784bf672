"""Streams against batch runs over the same rows."""

from pyspark.sql import functions as F

from derivatrace.streaming import stream
from derivatrace.workloads.fixture import DEEP

DATA = "/root/testdata/sf0.001"


def batch(spark):
    return spark.read.parquet(f"{DATA}/events.parquet").withColumn("ts", F.col("ts").cast("timestamp"))


def test_facts_and_consequences(spark):
    streamed = stream.drain(stream.closed(stream.event_facts(stream.event_stream(spark, DATA)), DEEP))
    missed, beyond = stream.reconcile(streamed, stream.closed(stream.event_facts(batch(spark)), DEEP))
    assert missed.isEmpty() and beyond.isEmpty()


def test_repeated_files_add_nothing(spark, tmp_path):
    rows = spark.read.parquet(f"{DATA}/events.parquet")
    for i in range(2):
        rows.coalesce(1).write.parquet(str(tmp_path / f"e{i}"))
    source = stream.event_stream(spark, str(tmp_path / "*"), "*.parquet")
    stored = stream.drain(stream.event_facts(source), store=True)
    once = stream.drain(stream.once(stream.event_facts(source), "60 days"))
    want = stream.event_facts(batch(spark)).count()
    assert stored.count() == once.count() == want


def test_windows_sessions_and_joins(spark):
    rows, whole = stream.event_stream(spark, DATA), batch(spark)
    closed_windows = stream.drain(stream.windowed(stream.event_facts(rows), "1 day", delay="1 hour"))
    every = stream.windowed(stream.event_facts(whole), "1 day")
    assert closed_windows.count() > 0 and closed_windows.exceptAll(every).isEmpty()
    assert stream.windowed(stream.event_facts(whole), "1 day", "12 hours").count() > every.count()
    assert stream.sessions(whole).agg(F.sum("n_events")).first()[0] == whole.count()
    joined = stream.drain(stream.followed_by_purchase(rows, stream.event_stream(spark, DATA)))
    assert joined.exceptAll(stream.followed_by_purchase(whole, whole)).isEmpty() and joined.count() > 0
