"""Settings of search tables compared by blocks of packed sets: which of them bring two sets together, and how many sets a query meets.

A way is a kind of sketch, a rule for holes, b, k and L. Ways that differ in L alone share their first tables, so each
pair's tables are compared once. Neither buckets nor candidates pass a shuffle; only counts do.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.parquet as pq
from pyarrow import fs
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..tables import written
from . import blocks

#: Sets and queries of a task at most.
SETS, QUERIES = 16_384, 4096


def classic_minima(permuters: list) -> Callable:
    """``extra`` of ``blocks.packed``: the least position of each permutation."""

    def least(ids: np.ndarray, row: np.ndarray, elem: np.ndarray, minima: np.ndarray) -> np.ndarray:
        starts = np.searchsorted(row, np.arange(len(ids)))
        return np.stack([np.minimum.reduceat(p.numpy(elem), starts) for p in permuters], axis=1).astype("<i4") if len(ids) else np.zeros((0, len(permuters)), "<i4")

    return least


@dataclass
class Ways:
    """(source, policy, b, k, L) of all ways, in order, and where their tables lie; ``classic`` tables are made of ``extra``."""

    settings: list[tuple[int, int, int]]
    bins: int
    permutations: int

    def __post_init__(self):
        self.kinds: list[tuple[str, str, int, int, int]] = []  # source, policy, b, k, most tables
        self.all: list[tuple[str, str, int, int, int]] = []
        self.at: list[tuple[int, int]] = []  # the columns of each way's tables
        first = 0
        for source, policy, room in (("one permutation", "skip_band", self.bins), ("one permutation", "sentinel", self.bins), ("classic", "none", self.permutations)):
            for b, k in dict.fromkeys(s[:2] for s in self.settings):
                fit = sorted(L for x, y, L in self.settings if (x, y) == (b, k) and k * L <= room)
                if fit:
                    self.kinds.append((source, policy, b, k, fit[-1]))
                    self.all += [(source, policy, b, k, L) for L in fit]
                    self.at += [(first, first + L) for L in fit]
                    first += fit[-1]

    def buckets(self, minima: np.ndarray, extra: np.ndarray) -> np.ndarray:
        """A row for each set, a column for each table of each kind; -1 where the set has no bucket."""
        out = []
        for source, policy, b, k, L in self.kinds:
            bins = (extra if source == "classic" else minima)[:, : k * L].reshape(len(minima), L, k).astype(np.int64)
            code, width = bins & ((1 << b) - 1), b
            if policy == "sentinel":
                code, width = np.where(bins < 0, 0, code + 1), b + 1
            has = (bins >= 0).any(axis=2) if policy == "sentinel" else (bins >= 0).all(axis=2)
            out.append(np.where(has, (code << (width * np.arange(k))).sum(axis=2), -1))
        return np.concatenate(out, axis=1)

    def shared(self) -> Callable:
        """``measure`` of ``blocks.measured``: ways, a bit for each way that brings the pair together (62 ways at most)."""
        if len(self.all) > 62:
            raise ValueError("a bit for each way")
        last: list[tuple[blocks.Block, np.ndarray]] = []

        def tables(x: blocks.Block) -> np.ndarray:
            for block, own in last:
                if block is x:
                    return own
            last.append((x, self.buckets(x.minima, x.extra)))
            del last[:-2]
            return last[-1][1]

        def measure(x: blocks.Block, i: np.ndarray, y: blocks.Block, j: np.ndarray) -> dict[str, np.ndarray]:
            out = np.zeros(len(i), np.int64)
            p, q = tables(x), tables(y)
            for s in range(0, len(i), 4096):
                u = p[i[s : s + 4096]]
                same = (u == q[j[s : s + 4096]]) & (u >= 0)
                for n, (a, z) in enumerate(self.at):
                    out[s : s + 4096] |= same[:, a:z].any(axis=1).astype(np.int64) << n
            return {"ways": out}

        return measure

    def met(self, own: np.ndarray, ids: np.ndarray, asked: np.ndarray, names: np.ndarray) -> np.ndarray:
        """For each way, how many of the sets with buckets ``own`` the queries with buckets ``asked`` meet in some table, themselves not counted."""
        coded, wanted = np.empty(own.shape[::-1], np.uint16), np.empty(asked.shape[::-1], np.uint16)
        for t in range(own.shape[1]):  # 65,534 sets at most: buckets of one table fit 16 bits
            some, coded[t] = np.unique(own[:, t], return_inverse=True)
            at = np.minimum(np.searchsorted(some, asked[:, t]), len(some) - 1)
            wanted[t] = np.where((some[at] == asked[:, t]) & (asked[:, t] >= 0), at, 65_535)
        place = {x: n for n, x in enumerate(ids.tolist())}
        ends = {z: n for n, (_, z) in enumerate(self.at)}
        firsts = {a for a, _ in self.at}
        out, hit, same = np.zeros(len(self.at), np.int64), np.zeros(len(ids), bool), np.zeros(len(ids), bool)
        for q, name in enumerate(names.tolist()):
            me = place.get(name)
            for t, code in enumerate(wanted[:, q].tolist()):
                if t in firsts:
                    hit[:] = False
                if code != 65_535:
                    np.equal(coded[t], code, out=same)
                    np.logical_or(hit, same, out=hit)
                if t + 1 in ends:
                    out[ends[t + 1]] += np.count_nonzero(hit) - (me is not None and bool(hit[me]))
        return out


def light(files: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Ids, minima and ``extra`` of packed sets."""
    parts = []
    for name in files:
        store, path = fs.FileSystem.from_uri(name)
        parts.append(pq.read_table(path, columns=["set_id", "sketch", "extra"], filesystem=store, partitioning=None))
    t = pa.concat_tables(parts)
    minima, extra = (np.frombuffer(b"".join(t.column(c).to_pylist()), np.int32).reshape(t.num_rows, -1) for c in ("sketch", "extra"))
    return t.column("set_id").to_numpy(), minima, extra


def files_of(sets: DataFrame, most: int) -> list[list[str]]:
    """Files of a written table, together up to ``most`` rows each time (or single)."""
    out, room = [], 0
    for r in sets.groupBy(F.col("_metadata.file_path").alias("f")).agg(F.count(F.lit(1)).alias("n")).orderBy("f").collect():
        if not out or r.n > room:
            out.append([])
            room = most
        out[-1].append(r.f)
        room -= r.n
    return out


def candidates(sets: DataFrame, ways: Ways, condition: str) -> DataFrame:
    """way, candidates, used (whether any set has a bucket): ``packed`` sets that those of ``condition`` meet, by number of the way."""
    spark, n = sets.sparkSession, sets.filter(condition).count()
    queries = written(sets.filter(condition).repartition(max(1, n // QUERIES * 2)), "packed-queries")
    asked = files_of(queries, QUERIES) or [[]]
    tasks = [(x, y) for x in files_of(sets, SETS) for y in asked]
    schema = "way int, n long, used boolean"
    if not tasks:
        return spark.createDataFrame([], "way int, candidates long, used boolean")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for task in (t for batch in batches for t in batch.to_pylist()):
            ids, minima, extra = light(task["x"])
            own = ways.buckets(minima, extra)
            count = np.zeros(len(ways.at), np.int64)
            if task["y"]:
                names, minima, extra = light(task["y"])
                asked = ways.buckets(minima, extra)
                for s in range(0, len(ids), SETS):
                    count += ways.met(own[s : s + SETS], ids[s : s + SETS], asked, names)
            used = [bool((own[:, a:z] >= 0).any()) for a, z in ways.at]
            yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(count), dtype=np.int32)), pa.array(count), pa.array(used)], names=["way", "n", "used"])

    rows = spark.createDataFrame(spark.sparkContext.parallelize(tasks, len(tasks)), "x array<string>, y array<string>")
    return rows.mapInArrow(run, schema).groupBy("way").agg(F.sum("n").alias("candidates"), F.max("used").alias("used"))
