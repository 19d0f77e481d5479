"""Token files: Simple-8b words with per-block offsets.

File: magic, version, ids and blocks and documents as four little-endian words,
then per document its id and length, per block the index of its first word,
then the words. A block holds 128 ids (the last fewer). A word is a 4-bit
selector and 60 bits; selector 15 is the escape: its 60 bits hold one id.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import as_array, parts_for, texts_of, tidy, written
from .memo import json_encoder

#: Fixed values of the word format: ids in a word by selector (0 and 1: runs of the id 0); 60 bits are shared out evenly.
COUNTS = np.array([240, 120, 60, 30, 20, 15, 12, 10, 8, 7, 6, 5, 4, 3, 2, 1])
BITS = np.array([0, 0, *(60 // COUNTS[2:])])
MAGIC, BLOCK, HEAD = 0x73386231, 128, 32
FILE_IDS = 8_000_000  # ids held by one task before it writes a file


def packed(ids: np.ndarray, at_once: int = 4096 * BLOCK) -> tuple[np.ndarray, np.ndarray]:
    """Words, and each block's first word; ``at_once`` ids (whole blocks) at a time, which bounds the memory."""
    words, offsets, n = [], [], 0
    for a in range(0, max(len(ids), 1), at_once):
        w, o = packed_blocks(ids[a : a + at_once])
        words.append(w)
        offsets.append(o + np.uint32(n))
        n += len(w)
    return np.concatenate(words), np.concatenate(offsets)


def packed_blocks(ids: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Words, and each block's first word. The largest count that fits is taken at each place; all blocks advance together."""
    n = len(ids)
    if not n:
        return np.empty(0, "<u8"), np.empty(0, "<u4")
    if int(ids.max()) >> 60:
        raise ValueError("ids of 60 bits at most")
    padded = np.concatenate([ids.astype(np.uint64), np.zeros(COUNTS[0], np.uint64)])
    places = np.arange(n)
    left = np.minimum(BLOCK - places % BLOCK, n - places)
    best = np.full(n, len(COUNTS) - 1, np.int8)
    for s in range(len(COUNTS) - 2, -1, -1):
        count, bits = int(COUNTS[s]), int(BITS[s])
        if count > BLOCK:
            continue
        bad = np.zeros(n + count + 1, np.int32)
        np.cumsum(padded[: n + count] >= np.uint64(1 << bits), out=bad[1:])
        best[(bad[count : n + count] == bad[:n]) & (left >= count)] = s
    starts = np.arange(0, n, BLOCK)
    ends, at = np.minimum(starts + BLOCK, n), starts.copy()
    rows, of_block = [], []
    live = np.arange(len(starts))
    while len(live):
        rows.append(at[live])
        of_block.append(live)
        at[live] += COUNTS[best[at[live]]]
        live = live[at[live] < ends[live]]
    place, block = np.concatenate(rows), np.concatenate(of_block)
    order = np.argsort(place)
    place, block = place[order], block[order]
    selector = best[place]
    words = selector.astype(np.uint64) << np.uint64(60)
    for s in range(2, len(COUNTS)):
        own = np.flatnonzero(selector == s)
        for lane in range(int(COUNTS[s])) if len(own) else ():
            words[own] |= padded[place[own] + lane] << np.uint64(lane * BITS[s])
    return words.astype("<u8"), np.searchsorted(block, np.arange(len(starts))).astype("<u4")


def unpacked(words: np.ndarray) -> np.ndarray:
    """Ids of whole words, all words of a selector at once."""
    selector = (words >> np.uint64(60)).astype(np.int8)
    counts = COUNTS[selector]
    ends = np.cumsum(counts)
    out = np.zeros(int(ends[-1]) if len(ends) else 0, "<u4")
    for s in range(2, len(COUNTS)):
        own = np.flatnonzero(selector == s)
        mask, first = np.uint64((1 << int(BITS[s])) - 1), ends[own] - COUNTS[s]
        for lane in range(int(COUNTS[s])) if len(own) else ():
            out[first + lane] = words[own] >> np.uint64(lane * BITS[s]) & mask
    return out


def file_bytes(doc_ids: list[int], lengths: list[int], ids: np.ndarray) -> bytes:
    words, offsets = packed(ids)
    head = np.array([MAGIC, len(ids), len(offsets), len(doc_ids)], "<u8")
    table = np.array([doc_ids, lengths], "<i8").T
    return b"".join(x.tobytes() for x in (head, table, offsets, words))


def opened(blob: bytes) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """doc ids, lengths, block offsets and words of a file; ValueError if it is damaged."""
    magic, n, blocks, docs = (int(x) for x in np.frombuffer(blob, "<u8", 4)) if len(blob) >= HEAD else (0, 0, 0, 0)
    if magic != MAGIC:
        raise ValueError("not a token file")
    at = HEAD + 16 * docs
    table = np.frombuffer(blob, "<i8", 2 * docs, HEAD).reshape(-1, 2)
    offsets = np.frombuffer(blob, "<u4", blocks, at)
    words = np.frombuffer(blob, "<u8", offset=at + 4 * blocks)
    if int(table[:, 1].sum()) != n:
        raise ValueError("a token file whose lengths don't add up")
    return table[:, 0], table[:, 1], offsets, words


def some_blocks(offsets: np.ndarray, words: np.ndarray, first: int, last: int) -> np.ndarray:
    """Ids of the blocks ``first`` to ``last`` - 1, without reading others."""
    end = int(offsets[last]) if last < len(offsets) else len(words)
    return unpacked(words[int(offsets[first]) : end])


def ids_of(blob: bytes, doc: int) -> np.ndarray:
    """Ids of the ``doc``-th document of a file, through the block offsets."""
    _, lengths, offsets, words = opened(blob)
    start = int(lengths[:doc].sum())
    end = start + int(lengths[doc])
    if start == end:
        return np.empty(0, "<u4")
    first = start // BLOCK
    ids = some_blocks(offsets, words, first, (end - 1) // BLOCK + 1)
    return ids[start - first * BLOCK : end - first * BLOCK]


def write_token_files(docs: DataFrame, vocabulary: str, id_col: str = "doc_id", text_col: str = "text", end_id: int = 0, file_ids: int = FILE_IDS) -> DataFrame:
    """Encode all documents and keep them as files; returns the files' table.

    Documents are dealt by ranges of their id, so that files follow each other in
    ascending id (ties: by text). Rows: part, seq (files of a part in order),
    n_ids, before (ids of the part's earlier files), first_doc, blob. They are Parquet rows in the shared folder, whose
    committer makes retried or doubled tasks harmless. Null text counts as empty:
    it holds the end id only. An empty table gives no files. A file holds at most
    ``file_ids`` ids and the rest of its last document.
    """
    kind = "part int, seq int, n_ids long, before long, first_doc long, blob binary"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        enc, part, seq = json_encoder(vocabulary), TaskContext.get().partitionId(), 0
        doc_ids, rows, held, before = [], [], 0, 0

        def flushed():
            lengths = [len(r) for r in rows]
            blob = file_bytes(doc_ids, lengths, np.concatenate(rows))
            cols = ([part], pa.int32()), ([seq], pa.int32()), ([sum(lengths)], pa.int64()), ([before], pa.int64()), ([doc_ids[0]], pa.int64()), ([blob], pa.binary())
            return pa.RecordBatch.from_arrays([as_array(*c) for c in cols], names=["part", "seq", "n_ids", "before", "first_doc", "blob"])

        for batch in batches:
            for doc, text in zip(batch.column(id_col).to_pylist(), texts_of(batch, text_col), strict=True):
                ids = enc.ids(text)
                rows.append(np.append(ids, ids.dtype.type(end_id)))
                doc_ids.append(doc)
                held += len(rows[-1])
                if held >= file_ids:
                    yield flushed()
                    doc_ids, rows, held, before, seq = [], [], 0, before + held, seq + 1
        if rows:
            yield flushed()

    dealt = docs.select(id_col, text_col).repartitionByRange(parts_for(docs.select(id_col, text_col)), id_col).sortWithinPartitions(id_col, text_col)
    return written(dealt.mapInArrow(tidy(run), kind), "token-files")


def read_token_files(files: DataFrame) -> DataFrame:
    """One row per document, from the files alone: doc_id, start, n_tokens, ids_crc32.

    start counts the ids of all documents before it: a file knows those of its part, and the parts' sums (a row for each
    partition that the driver has scheduled) are added up on the driver.
    """
    sums = files.groupBy("part").agg(F.sum("n_ids").alias("n")).orderBy("part").toArrow()
    part_of, n = sums.column("part").to_numpy(), sums.column("n").to_numpy()
    shared = files.sparkSession.sparkContext.broadcast((part_of, np.cumsum(n) - n))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known, starts = shared.value
        for batch in batches:
            for part, before, blob in zip(*(batch.column(c).to_pylist() for c in ("part", "before", "blob")), strict=True):
                docs, lengths, _, words = opened(blob)
                ids, ends = unpacked(words), np.cumsum(lengths)
                crc = [zlib.crc32(ids[e - n : e].tobytes()) for e, n in zip(ends, lengths, strict=True)]
                cols = docs, int(starts[np.searchsorted(known, part)]) + before + ends - lengths, lengths, crc
                yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in cols], names=["doc_id", "start", "n_tokens", "ids_crc32"])

    return files.select("part", "before", "blob").mapInArrow(tidy(run), "doc_id long, start long, n_tokens long, ids_crc32 long")


def token_digests(docs: DataFrame, vocabulary: str, end_id: int = 0) -> DataFrame:
    """Encode, write, read back: the digest rows of ``read_token_files``."""
    return read_token_files(write_token_files(docs, vocabulary, end_id=end_id))


__all__ = ["file_bytes", "ids_of", "opened", "packed", "read_token_files", "token_digests", "unpacked", "write_token_files"]
