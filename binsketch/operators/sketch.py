"""Binned-minimum sketches and the classic one, as rows (set_id, bin, offset); a hole is an absent row."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.permute import Affine, Digest, unsigned_bin, unsigned_order

#: Rows of (set_id, elem) whose positions are taken at a time, and positions that a worker remembers.
ROWS, REMEMBERED = 8192, 1 << 23
#: Permutations that are worked on at once, so that their positions stay in a core's cache.
AT_ONCE = 16


def bin_minima(sets: DataFrame, permuter, k: int, reindex: bool = True) -> DataFrame:
    """One permutation, k equal bins, the least position of each bin (from the bin's start if ``reindex``).

    D not divisible by k: bin = floor(pos * k / D). Repeated elements and their
    order don't matter, so nothing is made distinct: one exchange, after partial minima.
    """
    size = permuter.size
    p = sets.filter("elem is not null").select("set_id", permuter.pos(F.col("elem")).alias("pos"))
    if size == 1 << 64:
        bits = k.bit_length() - 1
        if 1 << bits != k:
            raise ValueError("the 64-bit universe takes powers of two as k")
        p = p.select("set_id", unsigned_bin(F.col("pos"), bits).alias("bin"), (F.shiftleft("pos", bits) if reindex and bits else F.col("pos")).alias("pos"))
        least = p.groupBy("set_id", "bin").agg(F.min(unsigned_order(F.col("pos"))).alias("o"))
        return least.select("set_id", "bin", unsigned_order(F.col("o")).alias("offset"))
    if size % k == 0:
        bin_of, start = F.expr(f"pos div {size // k}"), F.col("bin").cast("long") * F.lit(size // k)
    else:
        bin_of, start = F.expr(f"pos * {k} div {size}"), F.ceil(F.col("bin").cast("long") * F.lit(size) / F.lit(k))
    least = p.withColumn("bin", bin_of.cast("int")).groupBy("set_id", "bin").agg(F.min("pos").alias("pos"))
    return least.select("set_id", "bin", ((F.col("pos") - start) if reindex else F.col("pos")).cast("long").alias("offset"))


def striped(sets: DataFrame, permuters: list, k: int) -> DataFrame:
    """m permutations of k/m bins each, side by side: fewer holes for m times the hashing."""
    m = len(permuters)
    if k % m:
        raise ValueError("k must be a multiple of the number of permutations")
    each, size = k // m, permuters[0].size
    pos = F.explode(F.array(*[F.struct(F.lit(j).alias("stripe"), p.pos(F.col("elem")).alias("pos")) for j, p in enumerate(permuters)]))
    rows = sets.select("set_id", pos.alias("p")).select("set_id", "p.stripe", "p.pos")
    bin_of = F.expr(f"stripe * {each} + pos * {each} div {size}").cast("int")
    least = rows.withColumn("bin", bin_of).groupBy("set_id", "bin").agg(F.min("pos").alias("pos"))
    return least.select("set_id", "bin", (F.col("pos") - F.ceil(F.expr(f"cast(bin % {each} as bigint) * {size}") / F.lit(each))).cast("long").alias("offset"))


def ragged_bounds(size: int, k: int, seed: int) -> list[int]:
    """Starts of k bins whose widths are multinomial over D."""
    widths = np.random.default_rng(seed).multinomial(size, [1 / k] * k)
    return [0, *np.cumsum(widths)[:-1].tolist()]


def ragged(sets: DataFrame, permuter, bounds: list[int]) -> DataFrame:
    """Bins of given starts (ascending): counted off an array of k bounds that rides in the plan, no join."""
    starts = F.array(*[F.lit(int(b)) for b in bounds])
    p = sets.select("set_id", permuter.pos(F.col("elem")).alias("pos"))
    # the last start that is not above the position; empty bins share a start and the last of them wins
    bin_of = F.size(F.filter(starts, lambda s: s <= F.col("pos"))) - 1
    least = p.withColumn("bin", bin_of.cast("int")).groupBy("set_id", "bin").agg(F.min("pos").alias("pos"))
    return least.select("set_id", "bin", (F.col("pos") - F.element_at(starts, F.col("bin") + 1)).cast("long").alias("offset"))


def hashed_bins(sets: DataFrame, bin_permuter, permuter, k: int) -> DataFrame:
    """Each element is hashed to a bin and permuted within it: the form that needs no D."""
    p = sets.select("set_id", F.pmod(bin_permuter.pos(F.col("elem")), F.lit(k)).cast("int").alias("bin"), permuter.pos(F.col("elem")).alias("pos"))
    return p.groupBy("set_id", "bin").agg(F.min("pos").alias("offset"))


def classic(sets: DataFrame, permuters: list) -> DataFrame:
    """k permutations, one minimum each (bin is the permutation's number): k times the hashing.

    Minima are taken over an Arrow batch's runs of a set, and one exchange brings a set's minima together. Affine permutations
    of powers of two go by ``affine_minima``; of others each distinct element of a batch is hashed once (a worker remembers some).
    A set whose elements are all null has none.
    Universes of 2^31 at most and permutations that numpy can compute; others go by ``classic_columns``.
    """
    if not all(p.size <= 1 << 31 and (isinstance(p, Digest) or hasattr(p, "numpy")) for p in permuters):
        return classic_columns(sets, permuters)
    k, kind, affine = len(permuters), sets.schema["set_id"].dataType.simpleString(), all(isinstance(p, Affine) and p.size & (p.size - 1) == 0 for p in permuters)

    def least(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known: dict[int, np.ndarray] = {}
        for batch in (b.slice(i, ROWS) for b in batches for i in range(0, b.num_rows, ROWS)):
            code = batch.column("set_id").dictionary_encode(null_encoding="encode")
            owner, elem = code.indices.to_numpy(), batch.column("elem").to_numpy()
            some, at = np.unique(elem, return_inverse=True)
            key = np.unique(owner.astype(np.int64) * len(some) + at)
            row = key // len(some)
            starts = np.flatnonzero(np.r_[True, row[1:] != row[:-1]])
            if affine:
                out = affine_minima(permuters, some[key % len(some)], starts)
                yield pa.RecordBatch.from_arrays([code.dictionary.take(pa.array(row[starts])), pa.array([r.tobytes() for r in out], pa.binary())], names=["set_id", "least"])
                continue
            fresh = np.array([x for x in some.tolist() if x not in known], np.int64)
            if len(known) + len(fresh) > REMEMBERED // k:
                known.clear()
                fresh = some
            if len(fresh):
                table = np.stack([positions(p, fresh) for p in permuters], axis=1).astype(np.int32)
                known.update(zip(fresh.tolist(), table))
            table = np.stack([known[x] for x in some.tolist()])
            out = np.minimum.reduceat(table[key % len(some)], starts, axis=0)
            yield pa.RecordBatch.from_arrays([code.dictionary.take(pa.array(row[starts])), pa.array([r.tobytes() for r in out], pa.binary())], names=["set_id", "least"])

    def merged(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in (b.slice(i, some) for b in batches for i in range(0, b.num_rows, some)):
            lists = batch.column("parts")
            flat = np.frombuffer(b"".join(lists.flatten().to_pylist()), np.int32).reshape(-1, k)
            n = lists.value_lengths().to_numpy()
            out = np.minimum.reduceat(flat, np.cumsum(n) - n, axis=0)
            at = pa.array(np.repeat(np.arange(len(out)), k))
            yield pa.RecordBatch.from_arrays([batch.column("set_id").take(at), pa.array(np.tile(np.arange(k, dtype=np.int32), len(out))), pa.array(out.reshape(-1).astype(np.int64))], names=["set_id", "bin", "offset"])

    some = max(1, (1 << 18) // k)
    parts = sets.filter("elem is not null").select("set_id", F.col("elem").cast("long").alias("elem")).mapInArrow(least, f"set_id {kind}, least binary")
    return parts.groupBy("set_id").agg(F.collect_list("least").alias("parts")).mapInArrow(merged, f"set_id {kind}, bin int, offset long")


def affine_minima(permuters: list[Affine], elems: np.ndarray, starts: np.ndarray) -> np.ndarray:
    """The least position of each run of ``elems`` (from ``starts`` on), a row for each run and a column for each permutation of a power of two.

    Positions are the high bits of 32-bit products: what is beyond the universe falls off, so nothing is divided.
    """
    shift = np.array([33 - p.size.bit_length() for p in permuters], np.uint32)
    a, b = (np.array([getattr(p, x) % p.size << int(s) for p, s in zip(permuters, shift, strict=True)], np.uint32)[:, None] for x in "ab")
    x, out = elems.astype(np.uint32), np.zeros((len(permuters), len(starts)), np.uint32)
    for j in range(0, len(permuters), AT_ONCE):
        pos = a[j : j + AT_ONCE] * x
        pos += b[j : j + AT_ONCE]
        out[j : j + AT_ONCE] = np.minimum.reduceat(pos, starts, axis=1)
    return np.ascontiguousarray((out >> shift[:, None]).T).astype(np.int32)


def positions(permuter, elems: np.ndarray) -> np.ndarray:
    from .blocks import digests

    return digests(permuter, elems) if isinstance(permuter, Digest) else permuter.numpy(elems)


def classic_columns(sets: DataFrame, permuters: list) -> DataFrame:
    """``classic`` with columns only. The parameters ride in the plan."""
    least = [F.min(p.pos(F.col("elem"))).alias(f"m{j}") for j, p in enumerate(permuters)]
    wide = sets.groupBy("set_id").agg(*least)
    return wide.select("set_id", F.posexplode(F.array(*[F.col(f"m{j}") for j in range(len(permuters))])).alias("bin", "offset"))


def merge(a: DataFrame, b: DataFrame) -> DataFrame:
    """The sketch of each set's union: minima of minima."""
    return a.unionByName(b).groupBy("set_id", "bin").agg(F.min("offset").alias("offset"))


def coarsen(raw: DataFrame, size: int, k_from: int, k_to: int) -> DataFrame:
    """k_from bins of raw positions rolled up to k_to bins, re-indexed: the same as sketching with k_to."""
    if k_from % k_to or size % k_from:
        raise ValueError("k_to must divide k_from, and k_from D")
    least = raw.withColumn("bin", F.expr(f"bin div {k_from // k_to}").cast("int")).groupBy("set_id", "bin").agg(F.min("offset").alias("pos"))
    return least.select("set_id", "bin", (F.col("pos") - F.col("bin").cast("long") * F.lit(size // k_to)).cast("long").alias("offset"))


def sparsify(sets: DataFrame, permuter, k: int) -> DataFrame:
    """set_id, elem: the original matrix with all but the bin minima zeroed (min_by keeps the element)."""
    pos = permuter.pos(F.col("elem"))
    rows = sets.select("set_id", "elem", pos.alias("pos")).withColumn("bin", F.expr(f"pos * {k} div {permuter.size}"))
    return rows.groupBy("set_id", "bin").agg(F.min_by("elem", "pos").alias("elem")).select("set_id", "elem")


def holes(sketch: DataFrame, k: int) -> DataFrame:
    """set_id, nonempty, holes."""
    return sketch.groupBy("set_id").agg(F.count("bin").cast("int").alias("nonempty")).withColumn("holes", F.lit(k) - F.col("nonempty"))


def wide(sketch: DataFrame, k: int) -> DataFrame:
    """set_id, offsets: an array of k, null for a hole."""
    pairs = F.map_from_entries(F.collect_list(F.struct("bin", "offset")))
    return sketch.groupBy("set_id").agg(pairs.alias("m")).select("set_id", F.transform(F.sequence(F.lit(0), F.lit(k - 1)), lambda j: F.try_element_at(F.col("m"), j)).alias("offsets"))


def long(rows: DataFrame) -> DataFrame:
    """The rows of a wide sketch, holes left out."""
    return rows.select("set_id", F.posexplode("offsets").alias("bin", "offset")).filter("offset is not null")


def bin_minima_rows(rows: DataFrame, permuter, k: int, id_col: str = "set_id", elems_col: str = "elems") -> DataFrame:
    """The row-local form: (set_id, elems array) to (set_id, offsets array of k). No exchange at all.

    The kernel permutes a whole Arrow batch at once and takes the minima of runs
    of equal (row, bin). Null or empty arrays give k holes.
    """
    size = permuter.size
    if size % k:
        raise ValueError("k must divide D")
    width = size // k

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            lists = batch.column(elems_col)
            flat, n = np.asarray(lists.flatten(), np.int64), batch.num_rows
            lengths = np.array([0 if x is None else x for x in lists.value_lengths().to_pylist()], np.int64)
            row, pos = np.repeat(np.arange(n), lengths), permuter.numpy(flat)
            cell = row * k + pos // width
            out = np.full(n * k, size, np.int64)
            np.minimum.at(out, cell, pos % width)
            values = pa.array(out, mask=out == size)
            yield pa.RecordBatch.from_arrays([batch.column(id_col).cast(pa.int64()), pa.ListArray.from_arrays(pa.array(np.arange(0, n * k + 1, k), pa.int32()), values)], names=["set_id", "offsets"])

    return rows.select(id_col, elems_col).mapInArrow(run, "set_id long, offsets array<long>")
