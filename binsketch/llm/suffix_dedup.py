"""Removal of repeated byte strings by suffix sorting.

A byte goes if a string of 100 bytes over it also starts earlier in the corpus.
Equal strings pick the same anchor: the least-hashed 28 bytes within them. Only
anchors that occur twice matter; the stretch of text around each of them, with
all strings that picked it, goes where equal anchors meet. There blocks of
stretches are suffix-sorted in two stages, and neighbours in the order whose
common prefix has 100 bytes are repeats. Stretches of anchors too frequent for
one block are cut in short parts instead; equal parts collapse, and what is left
is told apart by its full 100 bytes, which is sorting into buckets of full depth,
summed before they are sent. Whole copies of a document go beforehand.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import claim, free_name, map_batches, parts_for, scratch, texts_of, tidy, written
from .jaccard_join import MOST_BROADCAST_IDS
from .shingles import _table, mixed
from .suffix_order import common_prefixes, two_stage_order, words_at

LENGTH, GRAM = 100, 28
PICKS = LENGTH - GRAM + 1
AT_ONCE, BLOCK_BYTES, HELD, ROWS = 1 << 19, 1 << 20, 120_000, 20_000
HOT_LEAST, HOT_KEYS, SUB = 1024, 4_000_000, 4
MIX = _table(20240103, 6)
EMPTY_SHA = hashlib.sha256(b"").hexdigest()
SURE = 1 << 62


def gram_hashes(data: np.ndarray) -> np.ndarray:
    """Hash of the 28 bytes from each place on (the last 27 places have none)."""
    w = np.lib.stride_tricks.as_strided(data, (len(data) - 7, 8), (1, 1)).copy().view("<u8").ravel()
    n = len(data) - GRAM + 1
    return mixed(w[:n] * MIX[0] + w[8 : n + 8] * MIX[1] + w[16 : n + 16] * MIX[2] + w[20 : n + 20] * MIX[3])


def anchors(blobs: list[bytes]) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Of each run of strings with the same anchor: blob number, first start, count, anchor's distance from that start, anchor's hash."""
    size = np.array([len(b) for b in blobs])
    data = np.frombuffer(b"".join(blobs), np.uint8)
    none = (np.empty(0, np.int64),) * 4 + (np.empty(0, np.uint64),)
    if not (size >= LENGTH).any():
        return none
    first = np.r_[0, np.cumsum(size)]
    h = gram_hashes(data)
    low = (h & np.uint64(0xFFFFFFFF00000000)) | np.arange(len(h), dtype=np.uint64)
    span = 1
    while span * 2 <= PICKS:  # least of ``span`` neighbours
        low = np.minimum(low[:-span], low[span:])
        span *= 2
    if span < PICKS:
        low = np.minimum(low[: len(low) - (PICKS - span)], low[PICKS - span :])
    edge = np.zeros(len(data) + 1, np.int8)
    long = size >= LENGTH
    edge[first[:-1][long]] += 1
    edge[first[1:][long] - LENGTH + 1] -= 1
    s = np.flatnonzero(np.cumsum(edge[:-1], dtype=np.int8))
    at = (low[s] & np.uint64(0xFFFFFFFF)).astype(np.int64)
    fresh = np.flatnonzero(np.r_[True, (at[1:] != at[:-1]) | (s[1:] != s[:-1] + 1)])
    start, at = s[fresh], at[fresh]
    blob = np.searchsorted(first, start, "right") - 1
    return blob, start - first[blob], np.diff(np.r_[fresh, len(s)]), at - start, h[at]


def pieces_of(raw: list[bytes]) -> Iterator[tuple[list[tuple[int, int]], list[bytes]]]:
    """Stretches of about AT_ONCE bytes, with each one's number in ``raw`` and where it starts there.

    A long text is cut so that each of its strings lies in one stretch: neighbours overlap by a string less one byte.
    """
    where, blobs, size = [], [], 0
    for i, r in enumerate(raw):
        for at in range(0, max(len(r) - LENGTH + 1, 1), AT_ONCE):
            blob = r[at : at + AT_ONCE + LENGTH - 1] if len(r) > AT_ONCE else r
            where.append((i, at))
            blobs.append(blob)
            size += len(blob)
            if size >= AT_ONCE:
                yield where, blobs
                where, blobs, size = [], [], 0
            if blob is r:
                break
    if blobs:
        yield where, blobs


def repeated_anchors(docs: DataFrame) -> DataFrame:
    """key, doc_id, packed (first start, distance, count) of every anchor that occurs twice or more.

    A task tells its own repeats at once and sends one row of each of its keys, so
    that a frequent key is one row a task.
    """
    kind = "route long, key long, doc_id long, packed long"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        claim("anchors")
        held: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
        size = 0

        def sent() -> pa.RecordBatch:
            key, doc, packed = (np.concatenate(c) for c in zip(*held, strict=True))
            order = np.argsort(key, kind="stable")
            key, doc, packed = key[order], doc[order], packed[order]
            first = np.r_[True, key[1:] != key[:-1]]
            own = ~first | np.r_[~first[1:], False]
            route = np.where(first, key, mixed(doc.view(np.uint64) * MIX[4] + packed.view(np.uint64) * MIX[5]))
            cols = route.view(np.int64), key.view(np.int64), doc, packed | np.where(own, SURE, 0)
            return pa.RecordBatch.from_arrays([pa.array(c) for c in cols], names=["route", "key", "doc_id", "packed"])

        for batch in batches:
            ids = batch.column("doc_id").to_numpy(zero_copy_only=False).astype(np.int64)
            raw = [t.encode() for t in texts_of(batch)]
            for where, blobs in pieces_of(raw):
                blob, start, count, far, key = anchors(blobs)
                number, at = np.array(where, np.int64).reshape(-1, 2).T
                held.append((key, ids[number[blob]], at[blob] + start << 16 | far << 8 | count))
                size += len(key)
            if size >= 4 * HELD:
                yield sent()
                held, size = [], 0
        if held:
            yield sent()

    def told(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        last, waiting = None, None  # the route of the last row, and that row if it stands alone so far
        for batch in batches:
            route = batch.column("route").to_numpy()
            sure = batch.column("packed").to_numpy() >= SURE
            again = np.r_[last == route[0], route[1:] == route[:-1]]
            keep = sure | again | np.r_[route[1:] == route[:-1], False]
            if again[0] and waiting is not None:
                yield waiting
            last = int(route[-1])
            waiting = None if keep[-1] else batch.slice(len(route) - 1).select(["key", "doc_id", "packed"])
            yield batch.select(["key", "doc_id", "packed"]).filter(pa.array(keep))

    rows = docs.mapInArrow(tidy(run), kind).repartition(parts_for(docs), "route").sortWithinPartitions("route")
    found = rows.mapInArrow(tidy(told), "key long, doc_id long, packed long")
    return written(found.withColumn("packed", F.col("packed").bitwiseAND(F.lit(SURE - 1))), "anchors")


def stretches(docs: DataFrame, found: DataFrame, hot: np.ndarray) -> DataFrame:
    """Of each repeated anchor its stretch of text: kind 0 (key, doc_id, start, count, bytes); kind 1: a part of the stretch
    of a hot anchor, SUB strings in step with the anchor; kind 2: what an equal part of a hot anchor in this task comes before (no bytes)."""
    shared = docs.sparkSession.sparkContext.broadcast(hot)
    lists = found.groupBy("doc_id").agg(F.collect_list(F.struct("key", "packed")).alias("found"))
    kind = "kind int, key long, doc_id long, start long, count long, bytes binary"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: dict[bytes, tuple[int, ...]] = {}
        out: list[tuple] = []

        def put(where: dict[bytes, tuple[int, ...]], content: bytes, own: tuple[int, ...]) -> None:
            """The earliest of equal contents stays; the other one is a repeat."""
            other = where.get(content)
            if other is None:
                where[content] = own
                return
            if own < other:
                where[content], own = own, other
            out.append((2, 0, own[0], own[1], own[2], None))

        def parts() -> None:
            """Stretches of frequent anchors, collapsed, in short parts that collapse again."""
            cut: dict[bytes, tuple[int, ...]] = {}
            for content, (doc, start, count, far) in seen.items():
                k = 0
                while k < count:
                    n = min(SUB - (k - far) % SUB, count - k)
                    core = k + SUB - 1 - (k - far) % SUB  # what all strings of a place in step have in common
                    put(cut, content[k : k + n + LENGTH - 1], (doc, start + k, n, hashlib.blake2b(content[core : core + LENGTH - SUB + 1], digest_size=8).digest()))
                    k += n
            out.extend((1, int.from_bytes(core, "little", signed=True), *own, content) for content, (*own, core) in cut.items())
            seen.clear()

        def sent() -> Iterator[pa.RecordBatch]:
            for i in range(0, len(out), ROWS):
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*out[i : i + ROWS], strict=True), (pa.int32(), *[pa.int64()] * 4, pa.binary()), strict=True)], names=["kind", "key", "doc_id", "start", "count", "bytes"])
            out.clear()

        frequent = set(shared.value.tolist())
        for batch in batches:
            for doc, text, rows in zip(batch.column("doc_id").to_pylist(), texts_of(batch), batch.column("found"), strict=True):
                raw = text.encode()
                flat = rows.values
                keys, packed = flat.field("key").to_pylist(), flat.field("packed").to_pylist()
                for key, p in zip(keys, packed, strict=True):
                    start, count = p >> 16, p & 255
                    content = raw[start : start + count + LENGTH - 1]
                    if key in frequent:
                        put(seen, content, (doc, start, count, p >> 8 & 255))
                    else:
                        out.append((0, key, doc, start, count, content))
                if len(seen) >= HELD:
                    parts()
                if len(out) >= ROWS:
                    yield from sent()
        parts()
        yield from sent()

    return written(docs.join(lists, "doc_id").select("doc_id", "text", "found").mapInArrow(tidy(run), kind), "stretches")


SPAN = "doc_id long, start long, end long"


def sorted_repeats(rows: DataFrame) -> DataFrame:
    """Spans (doc_id, start, end) that repeat earlier ones, of stretches sorted by key: whole groups are put in blocks."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = ("key", "doc_id", "start", "count", "bytes")
        held: list[list[pa.Array]] = []  # a block so far; it ends with the end of a group
        size = 0
        for batch in batches:
            cols = [batch.column(c) for c in names]
            key = cols[0].to_numpy()
            weight = np.cumsum(np.asarray(cols[3]) + LENGTH - 1)
            at = 0
            for cut in np.flatnonzero(key[1:] != key[:-1]) + 1:
                if size + weight[cut - 1] - (weight[at - 1] if at else 0) >= BLOCK_BYTES:
                    held.append([c.slice(at, cut - at) for c in cols])
                    yield span_batch(block_repeats(*gathered(held)))
                    held, size, at = [], 0, int(cut)
            if at == 0 and held and held[-1][0][-1] != cols[0][0] and size >= BLOCK_BYTES:
                yield span_batch(block_repeats(*gathered(held)))
                held, size = [], 0
            held.append([c.slice(at) for c in cols])
            size += int(weight[-1] - (weight[at - 1] if at else 0))
        if held:
            yield span_batch(block_repeats(*gathered(held)))

    return rows.mapInArrow(tidy(run), SPAN)


def gathered(held: list[list[pa.Array]]) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Bytes, and document, start and count of each stretch, of the groups with two or more."""
    key, doc, start, count = (np.concatenate([h[k].to_numpy() for h in held]) for k in range(4))
    again = np.r_[False, key[1:] == key[:-1]]
    several = again | np.r_[again[1:], False]
    content = pa.chunked_array([h[4] for h in held]).filter(pa.array(several)).to_pylist()
    return np.frombuffer(b"".join(content), np.uint8), doc[several], start[several], count[several].astype(np.int64)


def span_batch(spans: np.ndarray) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(np.ascontiguousarray(spans[:, k])) for k in range(3)], names=["doc_id", "start", "end"])


def block_repeats(text: np.ndarray, doc: np.ndarray, start: np.ndarray, count: np.ndarray) -> np.ndarray:
    """Spans of the strings of a block that occur earlier in it: suffix order, then neighbours with a common prefix of a string."""
    if not len(doc):
        return np.empty((0, 3), np.int64)
    words = words_at(text, LENGTH)
    size = count + LENGTH - 1
    first = np.r_[0, np.cumsum(size)[:-1]]
    edge = np.zeros(len(text) + 1, np.int8)
    np.add.at(edge, first, 1)
    np.add.at(edge, first + count, -1)
    counts = np.cumsum(edge[:-1], dtype=np.int8) > 0
    order = two_stage_order(text, words, LENGTH, first, first + count - 1)
    order = order[counts[order]]
    same = common_prefixes(order, text, words, LENGTH) >= LENGTH
    tied = same | np.r_[same[1:], False]
    order, group = order[tied], np.cumsum(~same)[tied]
    owner = np.searchsorted(first, order, "right") - 1
    d, s = doc[owner], start[owner] + order - first[owner]
    rank = np.lexsort((s, d, group))
    g, d, s = group[rank], d[rank], s[rank]
    head = np.r_[True, g[1:] != g[:-1]][: len(g)]
    lead = np.flatnonzero(head)[np.cumsum(head) - 1] if len(g) else np.empty(0, np.int64)
    later = (d != d[lead]) | (s != s[lead])
    d, s = d[later], s[later]
    rank = np.lexsort((s, d))
    d, s = d[rank], s[rank]
    run = np.flatnonzero(np.r_[True, (d[1:] != d[:-1]) | (s[1:] > s[:-1] + 1)][: len(d)])
    last = np.r_[run[1:], len(d)] - 1 if len(d) else run
    return np.stack([d[run], s[run], s[last] + LENGTH], axis=1) if len(d) else np.empty((0, 3), np.int64)


def hot_repeats(rows: DataFrame) -> DataFrame:
    """The same for hot anchors: equal parts collapse to the earliest; of those that share their middle
    with another part, the strings by 128-bit hashes."""
    part = rows.filter("kind = 1").select("key", "bytes", "doc_id", "start", "count")
    first = written(part.groupBy("bytes").agg(F.min("key").alias("core"), F.min(F.struct("doc_id", "start", "count")).alias("first"), F.count(F.lit(1)).alias("n")), "hot-parts")
    spans = later(part, first, ["bytes"]).select("doc_id", "start", (F.col("start") + F.col("count") + LENGTH - 1).alias("end"))

    def strings(batch):
        out: list[tuple] = []
        for content, own in zip(batch.column("bytes").to_pylist(), batch.column("first").to_pylist(), strict=True):
            for k in range(own["count"]):
                a, b = np.frombuffer(hashlib.blake2b(content[k : k + LENGTH], digest_size=16).digest(), np.int64)
                out.append((int(a), int(b), own["doc_id"], own["start"] + k))
        yield dict(zip(("h1", "h2", "doc_id", "start"), zip(*out, strict=True) if out else [[]] * 4, strict=True))

    shared = written(first.groupBy("core").agg(F.count(F.lit(1)).alias("n")).filter("n > 1").select("core"), "hot-cores")
    open_parts = first.join(shared, "core", "left_semi").select("bytes", "first")
    string = written(map_batches(open_parts, strings, "h1 long, h2 long, doc_id long, start long"), "hot-strings")
    once = written(string.groupBy("h1", "h2").agg(F.min(F.struct("doc_id", "start")).alias("first"), F.count(F.lit(1)).alias("n")), "hot-firsts")
    return spans.unionByName(later(string, once, ["h1", "h2"]).select("doc_id", "start", (F.col("start") + LENGTH).alias("end")))


def later(rows: DataFrame, first: DataFrame, key: list[str]) -> DataFrame:
    """Rows whose key has an earlier row."""
    both = rows.join(first.filter("n > 1"), key)
    return both.filter((F.col("doc_id") != F.col("first.doc_id")) | (F.col("start") != F.col("first.start")))


def repeats(docs: DataFrame) -> tuple[DataFrame, DataFrame, DataFrame]:
    """facts (doc_id, n_bytes, sha, copy_of: the smallest doc_id with the same text if smaller), spans (doc_id, start, end; they may overlap)
    of documents that are no copies, and those documents' rows."""
    docs = docs.filter("doc_id is not null").select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce("text", F.lit("")).alias("text"))
    with scratch(docs.sparkSession) as temp:
        facts = written(docs.select("doc_id", F.octet_length("text").cast("long").alias("n_bytes"), F.sha2(F.col("text").cast("binary"), 256).alias("sha")), "facts")
        many = written(facts.groupBy("sha").agg(F.min("doc_id").alias("copy_of"), F.count(F.lit(1)).alias("n")).filter("n > 1").select("sha", "copy_of"), "copied")
        facts = written(facts.join(many, "sha", "left").withColumn("copy_of", F.when(F.col("copy_of") < F.col("doc_id"), F.col("copy_of"))), "facts")
        copies = facts.filter("copy_of is not null").select("doc_id").distinct()
        ones = some_docs(docs, temp.keep(written(copies, "copies")), "left_anti")
        found = repeated_anchors(ones)
        counts = found.groupBy("key").agg(F.count(F.lit(1)).alias("n"))
        limit = max(HOT_LEAST, found.count() // HOT_KEYS)
        hot = np.array(sorted(r.key for r in counts.filter(F.col("n") > limit).collect()), np.int64)
        near = some_docs(ones, written(found.select("doc_id").distinct(), "near-ids"), "left_semi")
        rows = stretches(near, found, hot)
        cold = sorted_repeats(rows.filter("kind = 0").drop("kind").repartition(parts_for(rows), "key").sortWithinPartitions("key"))
        local = rows.filter("kind = 2").select("doc_id", "start", (F.col("start") + F.col("count") + LENGTH - 1).alias("end"))
        spans = cold.unionByName(local)
        if len(hot):
            spans = spans.unionByName(hot_repeats(rows))
        return temp.keep(facts), temp.keep(written(spans, "spans")), ones


def some_docs(docs: DataFrame, ids: DataFrame, how: str) -> DataFrame:
    """Rows of docs whose id is in ``ids`` (left_semi) or not (left_anti); ids are broadcast up to a checked size, joined beyond it."""
    return docs.join(F.broadcast(ids) if ids.count() <= MOST_BROADCAST_IDS else ids, "doc_id", how)


def merged(spans: list[tuple[int, int]]) -> list[tuple[int, int]]:
    out: list[tuple[int, int]] = []
    for a, b in sorted(spans):
        if out and a <= out[-1][1]:
            out[-1] = out[-1][0], max(b, out[-1][1])
        else:
            out.append((a, b))
    return out


def kept_bytes(raw: bytes, spans: list[tuple[int, int]]) -> bytes:
    parts, at = [], 0
    for a, b in spans:
        parts.append(raw[at:a])
        at = b
    return b"".join([*parts, raw[at:]])


def cut_texts(ones: DataFrame, spans: DataFrame) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept (binary) of the documents that spans touch."""
    lists = spans.groupBy("doc_id").agg(F.collect_set(F.struct("start", "end")).alias("spans"))
    touched = some_docs(ones, written(spans.select("doc_id").distinct(), "touched-ids"), "left_semi").join(lists, "doc_id")

    def run(batch):
        out = {k: [] for k in ("n_bytes", "n_removed", "n_spans", "kept")}
        for text, rows in zip(texts_of(batch), batch.column("spans").to_pylist(), strict=True):
            raw = text.encode()
            own = merged([(r["start"], r["end"]) for r in rows])
            out["n_bytes"].append(len(raw))
            out["n_removed"].append(sum(b - a for a, b in own))
            out["n_spans"].append(len(own))
            out["kept"].append(kept_bytes(raw, own))
        yield {"doc_id": batch.column("doc_id")} | out

    return map_batches(touched.select("doc_id", "text", "spans"), run, "doc_id long, n_bytes long, n_removed long, n_spans long, kept binary")


def removal_digests(docs: DataFrame) -> DataFrame:
    """One row per document: doc_id, n_bytes, n_removed, n_spans, kept_sha256.

    Null text counts as empty; rows without a doc_id are left out; of rows with one
    doc_id none is earlier. Other columns are ignored; an empty table gives no rows.
    A copy of an earlier document goes as a whole if it has 100 bytes.
    """
    with scratch(docs.sparkSession) as temp:
        return temp.keep(written(_removal_digests(docs), "removals"))


def _removal_digests(docs: DataFrame) -> DataFrame:
    facts, spans, ones = repeats(docs)
    cut = written(cut_texts(ones, spans).select("doc_id", "n_bytes", "n_removed", "n_spans", F.sha2("kept", 256).alias("kept_sha256")), "cut")
    whole = some_docs(facts, cut.select("doc_id").distinct(), "left_anti")
    goes = F.col("copy_of").isNotNull() & (F.col("n_bytes") >= LENGTH)
    rest = whole.select("doc_id", "n_bytes", F.when(goes, F.col("n_bytes")).otherwise(F.lit(0)).cast("long").alias("n_removed"), F.when(goes, 1).otherwise(0).cast("long").alias("n_spans"), F.when(goes, F.lit(EMPTY_SHA)).otherwise(F.col("sha")).alias("kept_sha256"))
    return cut.unionByName(rest)


def cleaned(docs: DataFrame) -> DataFrame:
    """docs without the repeated bytes, in the same columns (n_chars, where there is one, follows the text).

    Halves of characters at a cut go too. A document that loses all its text is
    left out; one that had none stays.
    """
    facts, spans, _ = repeats(docs)
    gone = written(facts.filter((F.col("copy_of").isNotNull()) & (F.col("n_bytes") >= LENGTH)).select("doc_id").distinct(), "gone-ids")
    touched = written(spans.select("doc_id").distinct(), "touched-ids")
    rest = some_docs(some_docs(docs, gone, "left_anti"), touched, "left_anti")
    names, kinds = docs.columns, dict(docs.dtypes)
    own = free_name("spans", names)
    lists = spans.groupBy("doc_id").agg(F.collect_set(F.struct("start", "end")).alias(own))
    cut = some_docs(some_docs(docs, touched, "left_semi"), gone, "left_anti").join(lists, "doc_id")

    inner = {f"c{i}": c for i, c in enumerate(names)}  # Arrow functions take no dots in names
    at = {c: i for i, c in inner.items()}

    def run(batch):
        texts = [kept_bytes(t.encode(), merged([(r["start"], r["end"]) for r in rows])).decode("utf-8", "ignore") for t, rows in zip(texts_of(batch, at["text"]), batch.column("spans").to_pylist(), strict=True)]
        new = {i: batch.column(i) for i in inner} | {at["text"]: texts}
        if "n_chars" in at:
            new[at["n_chars"]] = [len(t) for t in texts]
        yield new

    kept = cut.select(*(F.col(f"`{c}`").alias(i) for i, c in inner.items()), F.col(own).alias("spans"))
    shorter = map_batches(kept, run, ", ".join(f"{i} {kinds[c]}" for i, c in inner.items())).filter(F.col(at["text"]) != "")
    return rest.select(*(f"`{c}`" for c in names)).union(shorter.select(*(F.col(i).alias(c) for i, c in inner.items())))
