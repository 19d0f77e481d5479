"""Sketches of streams: windows, sessions, running state, scoring of new sets."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..operators.sets import digest_id
from ..tables import fresh_path

EVENTS = "event_id bigint, ts timestamp_ntz, user_id bigint, event_type string, value double, props string"


def event_elements(events: DataFrame, size: int) -> DataFrame:
    """ts (as a timestamp: watermarks refuse the zone-less kind), set_id, elem: what a user did, as elements."""
    what = F.concat_ws("|", "event_type", F.coalesce("props", F.lit("")))
    return events.select(F.col("ts").cast("timestamp").alias("ts"), F.col("user_id").alias("set_id"), digest_id(what, size).alias("elem"))


def windowed_sketch(elements: DataFrame, permuter, k: int, duration: str, slide: str | None = None, watermark: str | None = None) -> DataFrame:
    """window_start, set_id, bin, offset: one sketch for each window and set; late elements only lower minima while the state lives."""
    rows = elements.withWatermark("ts", watermark) if watermark else elements
    pos = permuter.pos(F.col("elem"))
    width = permuter.size // k
    w = F.window("ts", duration, slide) if slide else F.window("ts", duration)
    cells = rows.withColumn("pos", pos).groupBy(w.alias("w"), "set_id", F.expr(f"pos div {width}").cast("int").alias("bin"))
    return cells.agg(F.min(F.col("pos") % F.lit(width)).alias("offset")).select(F.col("w.start").alias("window_start"), "set_id", "bin", "offset")


def session_sketch(elements: DataFrame, permuter, k: int, gap: str, watermark: str | None = None) -> DataFrame:
    """session_start, session_end, set_id, n, and the session's sketch as a sorted array of (bin, offset)."""
    rows = elements.withWatermark("ts", watermark) if watermark else elements
    width = permuter.size // k
    rows = rows.withColumn("pos", permuter.pos(F.col("elem")))
    cell = F.struct(F.expr(f"pos div {width}").cast("int").alias("bin"), (F.col("pos") % F.lit(width)).alias("offset"))
    s = rows.groupBy(F.session_window("ts", gap).alias("s"), "set_id").agg(F.count(F.lit(1)).alias("n"), F.sort_array(F.collect_set(cell)).alias("cells"))
    least = F.aggregate("cells", F.array().cast("array<struct<bin:int,offset:bigint>>"), lambda acc, c: F.when((F.size(acc) > 0) & (F.try_element_at(acc, F.lit(-1))["bin"] == c["bin"]), acc).otherwise(F.concat(acc, F.array(c))))
    return s.select(F.col("s.start").alias("session_start"), F.col("s.end").alias("session_end"), "set_id", "n", least.alias("sketch"))


def running_sketch(elements: DataFrame, permuter, k: int, ttl_ms: int | None = None) -> DataFrame:
    """set_id, filled, updates: each set's sketch kept as state (``ttl_ms`` of quiet drop it); a row whenever it changes.

    State is k values a set at most; minima make replays harmless.
    """
    width = permuter.size // k
    cells = elements.withColumn("pos", permuter.pos(F.col("elem"))).select("set_id", F.expr(f"pos div {width}").cast("int").alias("bin"), (F.col("pos") % F.lit(width)).alias("offset"))

    def step(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            state.remove()
            return
        bins, offsets, updates = state.get if state.exists else ([], [], 0)
        now = dict(zip(bins, offsets, strict=True))
        for rows in batches:
            for b, o in rows.groupby("bin")["offset"].min().items():  # k at most
                if b not in now or o < now[b]:
                    now[int(b)] = int(o)
                    updates += 1
        state.update((list(now), list(now.values()), updates))
        if ttl_ms:
            state.setTimeoutDuration(ttl_ms)
        yield pd.DataFrame({"set_id": [key[0]], "filled": [len(now)], "updates": [updates]})

    return cells.groupBy("set_id").applyInPandasWithState(step, "set_id long, filled int, updates long", "bins array<int>, offsets array<long>, updates long", "update", GroupStateTimeout.ProcessingTimeTimeout if ttl_ms else GroupStateTimeout.NoTimeout)


def events_stream(spark: SparkSession, folder: str, files_at_once: int = 1) -> DataFrame:
    return spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", files_at_once).parquet(folder)


def drained(stream: DataFrame, name: str, mode: str = "append") -> DataFrame:
    """Run a stream over what there is, into a Parquet table of the shared folder (append) or through foreachBatch (other modes), and read it."""
    spark = stream.sparkSession
    path, check = fresh_path(spark, name), fresh_path(spark, f"{name}-state")
    writer = stream.writeStream.option("checkpointLocation", check).trigger(availableNow=True)
    if mode == "append":
        query = writer.outputMode("append").format("parquet").option("path", path).start()
    else:
        query = writer.outputMode(mode).foreachBatch(lambda df, n: df.write.mode("overwrite").parquet(f"{path}/batch={n}")).start()
    query.awaitTermination()
    return spark.read.schema(stream.schema).parquet(path)


def deduplicated(events: DataFrame, watermark: str = "2 days") -> DataFrame:
    """Events once each, as long as copies come within the watermark."""
    rows = events.withColumn("at", F.col("ts").cast("timestamp")).withWatermark("at", watermark)
    return rows.dropDuplicatesWithinWatermark(["event_id"]) if events.isStreaming else rows.dropDuplicates(["event_id"])


def matched(sketches: DataFrame, index: DataFrame) -> DataFrame:
    """A stream of index rows of new sets against a stored index: stream-static join; the batch's pairs may repeat across tables."""
    q = sketches.select("table_no", "bucket", F.col("set_id").alias("query_id"))
    return q.join(index, ["table_no", "bucket"]).select("query_id", "set_id")


def met(left: DataFrame, right: DataFrame, key: list[str], within: str = "1 day", watermark: str = "2 days") -> DataFrame:
    """Two streams of rows (ts, set_id, key): pairs that agree on the key no more than ``within`` apart (stream-stream interval join).

    State is what the watermark keeps of either side.
    """
    a = left.withWatermark("ts", watermark).select(F.col("ts").alias("ts_a"), F.col("set_id").alias("a"), *(F.col(c).alias(f"{c}_a") for c in key))
    b = right.withWatermark("ts", watermark).select(F.col("ts").alias("ts_b"), F.col("set_id").alias("b"), *(F.col(c).alias(f"{c}_b") for c in key))
    near = F.expr(f"ts_b >= ts_a - interval {within} AND ts_b <= ts_a + interval {within}")
    same = near
    for c in key:
        same = same & (F.col(f"{c}_a") == F.col(f"{c}_b"))
    return a.join(b, same).select("a", "b", "ts_a", "ts_b")
