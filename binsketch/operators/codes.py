"""Few bits a value: truncation, packing, hole coding, and expansion for linear models."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.ml.feature import CountVectorizerModel, Normalizer
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Bits that a task holds unpacked, a byte each.
UNPACKED = 1 << 24


def low_bits(sketch: DataFrame, b: int) -> DataFrame:
    """set_id, bin, code: the b low bits of each value (also from b' > b bits down to b)."""
    value = "code" if "code" in sketch.columns else "offset"
    return sketch.select("set_id", "bin", F.col(value).bitwiseAND(F.lit((1 << b) - 1)).cast("int").alias("code"))


def blank(codes: DataFrame) -> DataFrame:
    """Holes stay absent (all-zero blocks): adds scale = 1 / sqrt(k - holes) of the set."""
    n = codes.groupBy("set_id").agg(F.count("bin").alias("nonempty"))
    return codes.join(n, "set_id").select("set_id", "bin", "code", (1 / F.sqrt("nonempty")).alias("scale"))


def noise(codes: DataFrame, k: int, b: int, seed: int, portable: bool = False) -> DataFrame:
    """Holes become random codes, the same ones whenever computed again; every scale is 1 / sqrt(k).

    ``portable`` draws from md5, which other engines have too.
    """
    grid = codes.select("set_id").distinct().select("set_id", F.explode(F.sequence(F.lit(0), F.lit(k - 1))).alias("bin"))
    if portable:
        text = F.concat_ws(":", F.lit(f"n{seed}"), F.col("set_id").cast("string"), F.col("bin").cast("string"))
        drawn = F.conv(F.substring(F.md5(text.cast("binary")), 1, 7), 16, 10).cast("long")
    else:
        drawn = F.xxhash64("set_id", "bin", F.lit(seed))
    filled = grid.join(codes, ["set_id", "bin"], "left")
    return filled.select("set_id", "bin", F.coalesce("code", drawn.bitwiseAND(F.lit((1 << b) - 1)).cast("int")).alias("code"), F.lit(1 / np.sqrt(k)).alias("scale"))


def expand_long(coded: DataFrame, b: int) -> DataFrame:
    """set_id, idx, val: one place of each block of 2^b, the code counted from the block's end."""
    return coded.select("set_id", (F.col("bin").cast("long") * F.lit(1 << b) + F.lit((1 << b) - 1) - F.col("code")).alias("idx"), F.col("scale").alias("val"))


def onehot_full(sketch: DataFrame, width: int) -> DataFrame:
    """set_id, idx: each whole value as one of D dimensions of its bin; dot products count matches. Never dense."""
    return sketch.select("set_id", (F.col("bin").cast("long") * F.lit(width) + F.col("offset")).alias("idx"))


def to_vectors(coded: DataFrame, k: int, b: int) -> DataFrame:
    """set_id, features: sparse vectors of 2^b * k, unit length, so that nonempty blocks weigh 1 / sqrt(k - holes).

    The vocabulary of k * 2^b names is the only thing that is broadcast.
    """
    m = 1 << b
    names = [f"{j}:{m - 1 - c}" for j in range(k) for c in range(m)]
    rows = coded.groupBy("set_id").agg(F.collect_list(F.concat_ws(":", "bin", "code")).alias("names"))
    counted = CountVectorizerModel.from_vocabulary(names, "names", "counts")
    return Normalizer(p=2.0, inputCol="counts", outputCol="features").transform(counted.transform(rows)).select("set_id", "features")


def to_binary(codes: DataFrame, k: int, b: int) -> DataFrame:
    """set_id, codes (ceil(b k / 8) bytes), holes (a mask of k bits), nonempty."""
    rows = codes.groupBy("set_id").agg(F.sort_array(F.collect_list(F.struct("bin", "code"))).alias("c"))
    schema, some = "set_id long, codes binary, holes binary, nonempty int", max(1, UNPACKED // (k * b))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in (x.slice(i, some) for x in batches for i in range(0, x.num_rows, some)):
            lists = batch.column("c")
            flat, n = lists.flatten(), batch.num_rows
            row = np.repeat(np.arange(n), np.diff(np.asarray(lists.offsets)))
            bins, values = np.asarray(flat.field("bin"), np.int64), np.asarray(flat.field("code"), np.int64)
            bits = np.zeros((n, k, b), np.uint8)
            bits[row, bins] = values[:, None] >> np.arange(b) & 1
            hole = np.ones((n, k), np.uint8)
            hole[row, bins] = 0
            packed, mask = np.packbits(bits.reshape(n, -1), axis=1, bitorder="little"), np.packbits(hole, axis=1, bitorder="little")
            cols = batch.column("set_id"), pa.array([r.tobytes() for r in packed], pa.binary()), pa.array([r.tobytes() for r in mask], pa.binary()), pa.array((k - hole.sum(axis=1)).astype(np.int32))
            yield pa.RecordBatch.from_arrays([cols[0].cast(pa.int64()), *cols[1:]], names=["set_id", "codes", "holes", "nonempty"])

    return rows.mapInArrow(run, schema)


def from_binary(packed: DataFrame, k: int, b: int) -> DataFrame:
    """set_id, bin, code again."""
    some = max(1, UNPACKED // (k * b))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in (x.slice(i, some) for x in batches for i in range(0, x.num_rows, some)):
            n = batch.num_rows
            raw = np.stack([np.frombuffer(x, np.uint8) for x in batch.column("codes").to_pylist()]) if n else np.zeros((0, -(-b * k // 8)), np.uint8)
            mask = np.stack([np.frombuffer(x, np.uint8) for x in batch.column("holes").to_pylist()]) if n else np.zeros((0, -(-k // 8)), np.uint8)
            bits = np.unpackbits(raw, axis=1, bitorder="little")[:, : k * b].reshape(n, k, b)
            full = np.unpackbits(mask, axis=1, bitorder="little")[:, :k] == 0
            row, at = np.nonzero(full)
            code = (bits[row, at].astype(np.int64) << np.arange(b)).sum(axis=1)
            ids = np.asarray(batch.column("set_id"))
            yield pa.RecordBatch.from_arrays([pa.array(ids[row], pa.int64()), pa.array(at, pa.int32()), pa.array(code, pa.int32())], names=["set_id", "bin", "code"])

    return packed.mapInArrow(run, "set_id long, bin int, code int")


def storage_bits(n: int, k: int, b: int) -> int:
    return n * b * k


def permuter_bytes(size: int, k: int = 1, entry: int = 4) -> int:
    return size * k * entry
