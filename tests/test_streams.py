"""Streams of files see the events in order of time."""

from pyspark.sql import functions as F

from binsketch.plans import streams
from binsketch.session import ship


def test_files_come_in_order_of_time(spark, sf):
    """Each file is stamped in a later second than all files with earlier events."""
    ship(spark)
    files = spark.read.parquet(streams._as_files(spark, sf)).groupBy("_metadata.file_name").agg(F.max("_metadata.file_modification_time").alias("at"), F.min("ts").alias("low"), F.max("ts").alias("high"), F.count("*").alias("n")).orderBy("low").collect()
    assert len(files) == 4 and sum(r.n for r in files) == spark.read.parquet(f"{sf}/events.parquet").count()
    assert all(a.high < b.low and a.at.replace(microsecond=0) < b.at.replace(microsecond=0) for a, b in zip(files, files[1:]))


def test_events_without_time_stay(spark, tmp_path):
    rows = spark.createDataFrame([(i, None if i % 3 == 0 else f"2024-01-{i + 1:02d} 10:00:00", i, "view", 1.0, None) for i in range(20)], "event_id long, ts string, user_id long, event_type string, value double, props string")
    rows.withColumn("ts", F.col("ts").cast("timestamp_ntz")).write.parquet(f"{tmp_path}/events.parquet")
    assert sorted(r.event_id for r in spark.read.parquet(streams._as_files(spark, str(tmp_path))).collect()) == list(range(20))


def test_tasks_share_a_batch_of_arrivals(spark, tmp_path, monkeypatch):
    """A file of new documents is a batch; its rows lie in groups, so that more than one task reads them."""
    import glob

    import pyarrow.parquet as pq
    from pyspark.sql import functions as F

    from binsketch.plans import streams

    monkeypatch.setattr(streams, "GROUP", 100_000)
    docs = spark.range(6000).select(F.col("id").alias("doc_id"), F.repeat(F.md5(F.col("id").cast("string")), 8).alias("text"))
    streams.arrivals(docs, 3, f"{tmp_path}/a")
    files = [pq.ParquetFile(f) for f in glob.glob(f"{tmp_path}/a/*.parquet")]
    assert len(files) == 3 and sum(f.metadata.num_rows for f in files) == 6000 and all(f.num_row_groups > 2 for f in files)
