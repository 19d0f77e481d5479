"""Streaming queries, each equal to its batch answer."""

from __future__ import annotations

import time

from pyspark.sql import functions as F

from ..functions.permute import Digest
from ..operators import lsh, sets, sketch
from ..sources.tables import table
from ..streaming import sketches as st
from ..tables import fresh_path, written
from .base import D, band_sql, query, r6, shingle_sql, sketch_sql

SIZE, BINS = 1 << 10, 16
USER = Digest(SIZE, 41)
ELEMS = f"ev AS (SELECT ts, user_id AS set_id, ('0x' || substring(md5('e:' || concat_ws('|', event_type, coalesce(props, ''))), 1, 7))::BIGINT % {SIZE} AS elem FROM events), p AS (SELECT *, {USER.sql('elem')} AS pos FROM ev)"
CELL = f"CAST(pos // {SIZE // BINS} AS INTEGER) AS bin, min(pos % {SIZE // BINS}) AS \"offset\""


def _as_files(spark, sf_dir, files: int = 4) -> str:
    """The events as a folder of files in order of time, for a stream to take one by one.

    A stream takes files by their modification times, so each is written after the one before it, in another
    second (some stores stamp whole seconds): files of one job finish in any order, and what comes after a later
    file is too late for the watermark.
    """
    path, events = fresh_path(spark, "events"), table(spark, sf_dir, "events")
    at = F.unix_micros(F.col("ts").cast("timestamp"))
    cuts = events.select(F.percentile_approx(at, [i / files for i in range(1, files)])).first()[0] or []
    part = sum((F.coalesce(at > cut, F.lit(False)).cast("int") for cut in sorted(set(cuts))), F.lit(0))
    for i in range(len(set(cuts)) + 1):
        if i:
            time.sleep(1.01 - time.time() % 1)
        events.filter(part == i).repartition(1).sortWithinPartitions("ts").write.mode("append").parquet(path)
    return path


@query(f"WITH {ELEMS} SELECT date_trunc('day', ts) AS day, set_id, {CELL} FROM p GROUP BY 1, 2, 3")
def user_window_sketches(spark, sf_dir):
    rows = st.windowed_sketch(st.event_elements(table(spark, sf_dir, "events"), SIZE), USER, BINS, "1 day")
    return rows.select(F.col("window_start").cast("timestamp_ntz").alias("day"), "set_id", "bin", "offset")


@query(f"WITH {ELEMS}, w AS (SELECT date_trunc('day', ts) - to_days(CAST(unnest(range(7)) AS INTEGER)) AS day, set_id, pos FROM p) SELECT day, count(*) AS cells FROM (SELECT day, set_id, {CELL} FROM w GROUP BY 1, 2, 3) GROUP BY 1")
def sliding_window_cells(spark, sf_dir):
    rows = st.windowed_sketch(st.event_elements(table(spark, sf_dir, "events"), SIZE), USER, BINS, "7 days", "1 day")
    return rows.groupBy(F.col("window_start").cast("timestamp_ntz").alias("day")).agg(F.count(F.lit(1)).alias("cells"))


@query(f"""WITH {ELEMS}, g AS (SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY set_id ORDER BY ts) < INTERVAL 6 HOUR THEN 0 ELSE 1 END AS fresh FROM p),
s AS (SELECT *, sum(fresh) OVER (PARTITION BY set_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS nr FROM g)
SELECT set_id, min(ts) AS session_start, count(*) AS n, count(DISTINCT pos // {SIZE // BINS}) AS filled FROM s GROUP BY set_id, nr""")
def user_session_sketches(spark, sf_dir):
    rows = st.session_sketch(st.event_elements(table(spark, sf_dir, "events"), SIZE), USER, BINS, "6 hours")
    return rows.select("set_id", F.col("session_start").cast("timestamp_ntz").alias("session_start"), "n", F.size("sketch").cast("long").alias("filled"))


@query(f"WITH {ELEMS} SELECT date_trunc('day', ts) AS day, set_id, {CELL} FROM p GROUP BY 1, 2, 3")
def stream_window_sketches(spark, sf_dir):
    """The same rows as the batch, from a stream of files through partial minima that are merged when read."""
    stream = st.events_stream(spark, _as_files(spark, sf_dir))
    cells = st.event_elements(stream, SIZE).withColumn("pos", USER.pos(F.col("elem"))).select(F.date_trunc("day", "ts").alias("day"), "set_id", F.expr(f"pos div {SIZE // BINS}").cast("int").alias("bin"), (F.col("pos") % F.lit(SIZE // BINS)).alias("offset"))
    rows = st.drained(cells, "cells")
    return rows.groupBy(F.col("day").cast("timestamp_ntz").alias("day"), "set_id", "bin").agg(F.min("offset").alias("offset"))


@query(f"WITH {ELEMS}, t AS (SELECT max(ts) - INTERVAL 2 DAY AS mark FROM ev) SELECT date_trunc('day', ts) AS day, set_id, {CELL} FROM p, t WHERE date_trunc('day', ts) + INTERVAL 1 DAY <= mark GROUP BY 1, 2, 3")
def stream_watermarked(spark, sf_dir):
    """Windows that the watermark has closed, in append mode."""
    stream = st.events_stream(spark, _as_files(spark, sf_dir))
    rows = st.drained(st.windowed_sketch(st.event_elements(stream, SIZE), USER, BINS, "1 day", watermark="2 days"), "windows")
    return rows.select(F.col("window_start").cast("timestamp_ntz").alias("day"), "set_id", "bin", "offset")


@query(f"WITH {ELEMS}, b AS (SELECT ts, set_id, elem FROM ev WHERE set_id % 5 = 0), c AS (SELECT ts, set_id, elem FROM ev WHERE set_id % 5 = 1) SELECT b.set_id AS a, c.set_id AS b, count(*) AS n FROM b JOIN c ON b.elem = c.elem AND c.ts BETWEEN b.ts - INTERVAL 1 HOUR AND b.ts + INTERVAL 1 HOUR GROUP BY 1, 2")
def stream_pairs(spark, sf_dir):
    """Two streams of users' elements: who did the same within an hour of each other (stream-stream join)."""
    folder = _as_files(spark, sf_dir)
    of = lambda r: st.event_elements(st.events_stream(spark, folder), SIZE).filter(F.col("set_id") % 5 == r)
    rows = st.drained(st.met(of(0), of(1), ["elem"], "1 hour"), "met")
    return rows.groupBy("a", "b").agg(F.count(F.lit(1)).alias("n"))


@query(f"WITH {ELEMS} SELECT set_id, CAST(count(DISTINCT pos // {SIZE // BINS}) AS INTEGER) AS filled FROM p GROUP BY 1")
def stream_running_sketch(spark, sf_dir):
    """Each user's running state: the last row of each, over all micro-batches."""
    stream = st.events_stream(spark, _as_files(spark, sf_dir), 2)
    rows = st.drained(st.running_sketch(st.event_elements(stream, SIZE), USER, BINS), "running", "update")
    return rows.groupBy("set_id").agg(F.max("filled").alias("filled"))


@query("SELECT count(*) AS events, count(DISTINCT event_id) AS ids FROM events")
def stream_deduplicated(spark, sf_dir):
    """Files replayed once more come out once."""
    stream = st.events_stream(spark, _as_files(spark, sf_dir), 4)
    rows = st.drained(st.deduplicated(stream.unionByName(st.events_stream(spark, _as_files(spark, sf_dir), 4)), "60 days").select("event_id"), "once")
    return rows.agg(F.count(F.lit(1)).alias("events"), F.countDistinct("event_id").alias("ids"))


BN = shingle_sql("benchmark", "item_id", "text", 3, "bn")
#: Windows of twice so many shingles, one starting at each multiple; bins, bits and tables of their index.
STRIDES, WK, WB = (8, 16, 32), 16, 16
FEW = Digest(D, 7)
WINDOWS = f"""wd AS (SELECT doc_id, regexp_extract_all(lower(text), '[\\p{{L}}\\p{{N}}]+') AS ws FROM documents),
sp AS (SELECT doc_id, i - 1 AS p, ('0x' || substring(md5('e:' || array_to_string(ws[i:i + 2], ' ')), 1, 7))::BIGINT % {D} AS elem FROM (SELECT doc_id, ws, unnest(range(1, len(ws) - 1)) AS i FROM wd WHERE len(ws) >= 3)),
win AS (""" + " UNION ALL ".join(f"SELECT doc_id * 4000000 + {n * 1_000_000} + p // {s} - {back} AS set_id, elem FROM sp WHERE p // {s} >= {back}" for n, s in enumerate(STRIDES) for back in (0, 1)) + ")"
WINDEX = f"{WINDOWS}, {sketch_sql('win', FEW.sql('elem'), WK, name='wk')}, {band_sql('wk', WB, 1, 'wi')}, {BN}, {sketch_sql('bn', FEW.sql('elem'), WK, name='bk')}, {band_sql('bk', WB, 1, 'qi')}"
HELD = f"""{WINDEX}, cand AS (SELECT DISTINCT qi.set_id AS query_id, wi.set_id // 4000000 AS set_id FROM qi JOIN wi USING (table_no, bucket)),
b AS (SELECT DISTINCT set_id, elem FROM bn), n AS (SELECT set_id, count(*) AS f FROM b GROUP BY 1), d AS (SELECT DISTINCT doc_id, elem FROM sp),
hit AS (SELECT query_id, cand.set_id, count(*) AS a FROM cand JOIN b ON b.set_id = query_id JOIN d ON d.doc_id = cand.set_id AND d.elem = b.elem GROUP BY 1, 2)"""


def window_index(docs):
    """Index rows of windows of the documents at three sizes; set_id is doc_id * 4,000,000 plus the window's number."""
    return lsh.build_index(sketch.bin_minima(sets.window_sets(docs, "doc_id", "text", D, 3, STRIDES), FEW, WK), WB, 1, WK)


@query(f"WITH {HELD} SELECT query_id, hit.set_id, round(a / f::DOUBLE, 6) AS contained FROM hit JOIN n ON n.set_id = query_id WHERE a >= 0.5 * f")
def stream_new_points(spark, sf_dir):
    """Benchmark items arrive as a stream; each batch is sketched and looked up in the stored index of the documents' windows
    (an item is alike to a window that holds it, not to a long document), and what is found is counted exactly."""
    docs = table(spark, sf_dir, "documents")
    index = written(window_index(docs), "index")
    items, path, check = fresh_path(spark, "items"), fresh_path(spark, "found"), fresh_path(spark, "found-state")
    table(spark, sf_dir, "benchmark").select("item_id", "text").repartition(3, "item_id").write.parquet(items)

    def look_up(batch, n):
        shingles = written(sets.word_sets(batch, "item_id", "text", D, 3).distinct(), "item-shingles")
        q = lsh.build_index(sketch.bin_minima(shingles, FEW, WK), WB, 1, WK)
        found = written(st.matched(q, index).select("query_id", F.expr("set_id div 4000000").alias("set_id")).distinct(), "candidates")
        near = docs.join(found.select(F.col("set_id").alias("doc_id")).distinct(), "doc_id", "left_semi")
        own = sets.word_sets(near, "doc_id", "text", D, 3).distinct()
        asked = found.join(shingles.select(F.col("set_id").alias("query_id"), "elem"), "query_id")
        shared = asked.join(own, ["set_id", "elem"]).groupBy("query_id", "set_id").agg(F.count(F.lit(1)).alias("a"))
        f = shingles.groupBy(F.col("set_id").alias("query_id")).agg(F.count(F.lit(1)).alias("f"))
        shared.join(f, "query_id").filter("a >= 0.5 * f").select("query_id", "set_id", r6(F.col("a") / F.col("f"), "contained")).write.mode("overwrite").parquet(f"{path}/batch={n}")

    stream = spark.readStream.schema("item_id long, text string").option("maxFilesPerTrigger", 1).parquet(items)
    stream.writeStream.option("checkpointLocation", check).trigger(availableNow=True).foreachBatch(look_up).start().awaitTermination()
    return spark.read.schema("query_id long, set_id long, contained double").parquet(path).select("query_id", "set_id", "contained")


#: Bytes of a group of rows in a file of arrivals: tasks share a file by these.
GROUP = 4 << 20


def arrivals(docs, batches: int, folder: str) -> None:
    """The documents as that many files, each of which a stream takes as a batch and many tasks can read."""
    docs.select("doc_id", "text").repartition(batches, "doc_id").write.option("parquet.block.size", GROUP).parquet(folder)


@query()
def new_point_cost(spark, sf_dir):
    """Seconds for each newly arrived document to be sketched at k = 512 and coded, by batches of a stream: one permutation and k permutations."""
    from ..functions.permute import Affine

    folder = fresh_path(spark, "arrivals")
    arrivals(table(spark, sf_dir, "documents"), 3, folder)
    many = [Affine(D, 2 * (1_000_003 * (j + 1) % (1 << 22)) + 1, 12_345 + j) for j in range(512)]
    rows: list[tuple] = []
    for name, of in (("one permutation", lambda w: sketch.bin_minima(w, many[0], 512)), ("k permutations", lambda w: sketch.classic(w, many))):

        def step(batch, n, name=name, of=of):
            points, t = batch.count(), time.perf_counter()
            of(sets.word_sets(batch, "doc_id", "text", D)).select("set_id", "bin", F.col("offset").bitwiseAND(F.lit(255)).alias("code")).write.format("noop").mode("overwrite").save()
            rows.append((name, int(n), points, time.perf_counter() - t))

        stream = spark.readStream.schema("doc_id long, text string").option("maxFilesPerTrigger", 1).parquet(folder)
        stream.writeStream.option("checkpointLocation", fresh_path(spark, "arrivals-state")).trigger(availableNow=True).foreachBatch(step).start().awaitTermination()
    t = spark.createDataFrame(rows, "method string, batch int, points long, seconds double")
    return t.withColumn("ms_per_point", F.try_divide(F.col("seconds") * 1000, "points"))


@query(f"""WITH {ELEMS}, d AS (SELECT date_trunc('day', ts) AS day, CAST(pos // {SIZE // 64} AS INTEGER) AS bin, min(pos) AS p FROM p GROUP BY 1, 2), n AS (SELECT day, count(*) AS c FROM d GROUP BY 1),
m AS (SELECT x.day, count(*) FILTER (x.p = y.p) AS n_mat, count(*) AS n_both FROM d x JOIN d y ON y.bin = x.bin AND y.day = x.day + INTERVAL 1 DAY GROUP BY 1)
SELECT m.day, round(n_mat::DOUBLE / (a.c + b.c - n_both), 6) AS r FROM m JOIN n a ON a.day = m.day JOIN n b ON b.day = m.day + INTERVAL 1 DAY""")
def window_drift(spark, sf_dir):
    """Resemblance of what all users did on consecutive days."""
    e = st.event_elements(table(spark, sf_dir, "events"), SIZE).withColumn("set_id", F.lit(0).cast("long"))
    d = written(st.windowed_sketch(e, USER, 64, "1 day").select(F.unix_date(F.to_date("window_start")).alias("day"), "bin", "offset"), "days")
    n = d.groupBy("day").agg(F.count(F.lit(1)).alias("c"))
    nxt = d.select((F.col("day") - 1).alias("day"), "bin", F.col("offset").alias("y"))
    m = d.join(nxt, ["day", "bin"]).groupBy("day").agg(F.count_if(F.col("offset") == F.col("y")).alias("n_mat"), F.count(F.lit(1)).alias("both"))
    t = m.join(n, "day").join(n.select((F.col("day") - 1).alias("day"), F.col("c").alias("c2")), "day")
    return t.select(F.date_from_unix_date("day").cast("timestamp_ntz").alias("day"), F.round(F.col("n_mat") / (F.col("c") + F.col("c2") - F.col("both")), 6).alias("r"))
