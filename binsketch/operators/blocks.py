"""Pairs of sets that share a bucket, and what two sketches tell of them, by blocks of sets.

Sets are packed, a row each, into files of a table of the shared folder. A task takes two
blocks of files, finds the pairs that share a bucket in some table and measures them there:
neither buckets nor pairs with their bins pass through a shuffle, and a pair is made once.
Blocks are bounded, their pairs grow with the square of the table, as the pairs do.
"""

from __future__ import annotations

import hashlib
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.parquet as pq
from pyarrow import fs
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..tables import written
from .sets import tokens

#: Sets in a file and at most in a block; pairs that are found and that are measured at a time.
FILE_SETS, BLOCK_SETS, FOUND, MEASURED = 2048, 32_768, 1 << 20, 1 << 15
PACKED = "set_id long, elems binary, sketch binary, extra binary"
#: Measures that change places when the second set has the smaller id.
TWINS = {"n_emp_i": "n_emp_j", "n_emp_j": "n_emp_i", "f1": "f2", "f2": "f1"}


def digests(permuter, elems: np.ndarray) -> np.ndarray:
    """``permuter.pos`` (a ``Digest``) of integers."""
    some, back = np.unique(elems, return_inverse=True)
    seed = b"%d:" % permuter.seed
    return (first_bits([seed + b"%d" % x for x in some.tolist()]) % permuter.size)[back]


def first_bits(texts: list[bytes]) -> np.ndarray:
    """The first 28 bits of each md5."""
    md5 = hashlib.md5
    return np.frombuffer(b"".join([md5(x).digest()[:4] for x in texts]), ">u4").astype(np.int64) >> 4


def shingle_ids(words: list[str], w: int, size: int) -> np.ndarray:
    """Distinct ids of w consecutive words, as ``digest_id`` of ``shingles`` gives them."""
    parts = set(words) if w == 1 else set(map(" ".join, zip(*(words[j:] for j in range(w)))))
    return np.unique(first_bits([b"e:" + x.encode() for x in parts]) % size)


def packed(docs: DataFrame, id_col: str, text_col: str, size: int, w: int, permuter, k: int, extra: Callable | None = None, elems: bool = False) -> DataFrame:
    """``PACKED`` rows of the documents' distinct w-shingles, written: minima of k bins (-1: a hole), ``extra(ids, rows, elems, minima)``
    (an array with a row for each set) and, where asked for, the elements in order. Rows of one id are one set; sets without elements have no row."""
    n = docs.count()

    def ids(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in (b.slice(i, 1024) for b in batches for i in range(0, b.num_rows, 1024)):
            own = [shingle_ids(x, w, size) for x in batch.column("e").to_pylist()]
            ends = np.cumsum([0, *map(len, own)])
            lists = pa.ListArray.from_arrays(pa.array(ends, pa.int32()), pa.array(np.concatenate([np.zeros(0, np.int64), *own]), pa.int32()))
            yield pa.RecordBatch.from_arrays([batch.column("set_id"), lists], names=["set_id", "e"])

    words = docs.filter(F.col(id_col).isNotNull()).select(F.col(id_col).cast("long").alias("set_id"), tokens(F.col(text_col)).alias("e")).filter(F.size("e") >= w)
    rows = words.mapInArrow(ids, "set_id long, e array<int>")
    whole = rows.repartition(max(1, -(-n // FILE_SETS)), "set_id").groupBy("set_id").agg(F.flatten(F.collect_list("e")).alias("e"))
    width = permuter.size // k

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in (b.slice(i, 1024) for b in batches for i in range(0, b.num_rows, 1024)):
            lists, names = batch.column("e"), batch.column("set_id").to_numpy()
            key = np.unique(np.repeat(np.arange(len(names)), np.diff(lists.offsets.to_numpy())) * size + lists.flatten().to_numpy())
            row, elem = key // size, key % size
            pos = digests(permuter, elem)
            least = np.full(len(names) * k, width, np.int64)
            np.minimum.at(least, row * k + pos // width, pos % width)
            least = np.where(least == width, -1, least).astype(np.int32).reshape(-1, k)
            ends = np.searchsorted(row, np.arange(len(names) + 1))
            own = elem.astype(np.int32)
            more = extra(names, row, elem, least) if extra else None
            blobs = [own[a:b].tobytes() if elems else b"" for a, b in zip(ends, ends[1:])], [x.tobytes() for x in least], [x.tobytes() if extra else b"" for x in (more if extra else least)]
            yield pa.RecordBatch.from_arrays([pa.array(names, pa.int64()), *(pa.array(x, pa.binary()) for x in blobs)], names=["set_id", "elems", "sketch", "extra"])

    return written(whole.mapInArrow(run, PACKED), "packed-sets")


def packed_rows(rows: DataFrame, permuter, k: int, about: int) -> DataFrame:
    """``PACKED`` rows of sets given as (set_id, elem), written; ``about`` so many sets. The rows pass one exchange."""
    from .sketch import bin_minima

    dealt = rows.repartition(max(1, -(-about // FILE_SETS)), "set_id")
    whole = bin_minima(dealt, permuter, k).groupBy("set_id").agg(F.collect_list("bin").alias("bins"), F.collect_list("offset").alias("offsets"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            bins, offsets = batch.column("bins"), batch.column("offsets")
            least = np.full((batch.num_rows, k), -1, np.int32)
            least[np.repeat(np.arange(batch.num_rows), np.diff(bins.offsets.to_numpy())), bins.flatten().to_numpy()] = offsets.flatten().to_numpy()
            none = pa.array([b""] * batch.num_rows, pa.binary())
            yield pa.RecordBatch.from_arrays([batch.column("set_id").cast(pa.int64()), none, pa.array([x.tobytes() for x in least], pa.binary()), none], names=["set_id", "elems", "sketch", "extra"])

    return written(whole.mapInArrow(run, PACKED), "packed-sets")


@dataclass
class Block:
    """Sets of some files, by id."""

    ids: np.ndarray
    minima: np.ndarray
    extra: np.ndarray | None
    flat: np.ndarray
    bounds: np.ndarray

    @classmethod
    def read(cls, files: list[str], k: int, kind: str | None) -> Block:
        parts = []
        for name in files:
            store, path = fs.FileSystem.from_uri(name)
            parts.append(pq.read_table(path, filesystem=store, partitioning=None))
        t = pa.concat_tables(parts).sort_by("set_id").combine_chunks()
        blobs = [b"".join(t.column(c).to_pylist()) for c in ("elems", "sketch", "extra")]
        lengths = np.array([len(x) // 4 for x in t.column("elems").to_pylist()], np.int64)
        ids = t.column("set_id").to_numpy()
        return cls(ids, np.frombuffer(blobs[1], np.int32).reshape(-1, k), np.frombuffer(blobs[2], kind).reshape(len(ids), -1) if kind else None, np.frombuffer(blobs[0], np.int32), np.r_[0, np.cumsum(lengths)])

    def buckets(self, b: int, band: int) -> np.ndarray:
        """A row for each set, a column for each table; -1 for a band with a hole."""
        bins = self.minima.reshape(len(self.ids), -1, band).astype(np.int64)
        key = ((bins & ((1 << b) - 1)) << (b * np.arange(band))).sum(axis=2)
        return np.where((bins >= 0).all(axis=2), key, -1)


def found(x: Block, y: Block, same: bool, b: int, band: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Places in ``x`` and in ``y`` of the pairs that share a bucket, each once, those of one set of ``x`` together."""
    left, right = x.buckets(b, band), y.buckets(b, band)
    order = np.argsort(right, axis=0, kind="stable")
    low, n = np.zeros(left.shape, np.int64), np.zeros(left.shape, np.int64)
    for t in range(left.shape[1]):
        keys = right[order[:, t], t]
        low[:, t] = np.searchsorted(keys, left[:, t], "left")
        n[:, t] = np.where(left[:, t] < 0, 0, np.searchsorted(keys, left[:, t], "right") - low[:, t])
    ends, a = np.cumsum(n.sum(axis=1)), 0
    while a < len(left):
        z = max(a + 1, int(np.searchsorted(ends, (ends[a - 1] if a else 0) + FOUND, "right")))
        keys = []
        for t in range(left.shape[1]):
            size = n[a:z, t]
            at = np.repeat(low[a:z, t] - (np.cumsum(size) - size), size) + np.arange(size.sum())
            keys.append(np.repeat(np.arange(a, z), size) * len(right) + order[at, t])
        key = np.unique(np.concatenate(keys))
        i, j = key // len(right), key % len(right)
        if same:
            i, j = i[i < j], j[i < j]
        if len(i):
            yield i, j
        a = z


def counters(mask: int | None = None) -> Callable:
    """n_mat, n_both, n_emp, n_emp_i, n_emp_j from minima (or those bits of them)."""

    def measure(x: Block, i: np.ndarray, y: Block, j: np.ndarray) -> dict[str, np.ndarray]:
        u, v, k = x.minima[i], y.minima[j], x.minima.shape[1]
        both = (u >= 0) & (v >= 0)
        same = (u == v if mask is None else (u & mask) == (v & mask)) & both
        c = [(s >= 0).sum(axis=1) for s in (u, v)]
        n = both.sum(axis=1)
        return {"n_mat": same.sum(axis=1), "n_both": n, "n_emp": k - c[0] - c[1] + n, "n_emp_i": k - c[0], "n_emp_j": k - c[1]}

    return measure


def exact(size: int) -> Callable:
    """f1, f2, a: both sizes and that of the intersection."""
    mark = np.zeros(0, bool)

    def measure(x: Block, i: np.ndarray, y: Block, j: np.ndarray) -> dict[str, np.ndarray]:
        nonlocal mark
        if not len(mark):
            mark = np.zeros(size, bool)
        fx, fy, a = np.diff(x.bounds), np.diff(y.bounds), np.zeros(len(i), np.int64)
        starts = np.flatnonzero(np.r_[True, i[1:] != i[:-1]])
        for s, e in zip(starts, np.r_[starts[1:], len(i)]):
            own = x.flat[x.bounds[i[s]] : x.bounds[i[s] + 1]]
            mark[own] = True
            length = fy[j[s:e]]
            first = np.cumsum(length) - length
            hit = mark[y.flat[np.repeat(y.bounds[j[s:e]] - first, length) + np.arange(length.sum())]]
            a[s:e] = np.add.reduceat(hit, first, dtype=np.int64)
            mark[own] = False
        return {"f1": fx[i], "f2": fy[j], "a": a}

    return measure


def spans(starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """The numbers from each start to its end, one span after another."""
    n = ends - starts
    return np.repeat(starts - (np.cumsum(n) - n), n) + np.arange(n.sum())


def cut(n: np.ndarray) -> tuple[list[int], list[int]]:
    """Runs of entries that hold FOUND together at most, or are single."""
    ends, starts = np.r_[0, np.cumsum(n)], [0] if len(n) else []
    while starts and (z := max(starts[-1] + 1, int(np.searchsorted(ends, ends[starts[-1]] + FOUND, "right")) - 1)) < len(n):
        starts.append(z)
    return starts, [*starts[1:], len(n)] if starts else []


def alike(size: int, min_r: float) -> Callable:
    """``find`` of ``measured``: all pairs with a resemblance of ``min_r`` or more (above 0), each once, and f1, f2, a; elements are below ``size``, 2^24 at most.

    An exact prefix filter: with one order of both blocks' elements, rare ones first, two such sets share one of the
    first f - ceil(min_r f) + 1 of each; every survivor is counted. Copies stand for each other until they are given out.
    """
    count = exact(size)
    if size > 1 << 24:
        raise ValueError("elements of 24 bits")

    def copies(x: Block) -> tuple[np.ndarray, np.ndarray]:
        """Places in order of their groups of equal sets, and where each group begins."""
        n: dict[bytes, int] = {}
        own = np.array([n.setdefault(hashlib.sha256(x.flat[a:z].tobytes()).digest(), len(n)) for a, z in zip(x.bounds, x.bounds[1:])], np.int64)
        return np.argsort(own, kind="stable"), np.r_[0, np.cumsum(np.bincount(own, minlength=len(n)))]

    def prefixes(x: Block, some: np.ndarray, often: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Elements of the sets' prefixes, but for those that are in no other set, and the sets' numbers in ``some``."""
        out = [(np.zeros(0, np.int32), np.zeros(0, np.int32))]
        for s in range(0, len(some), 1024):
            f = np.diff(x.bounds)[some[s : s + 1024]]
            row, first = np.repeat(np.arange(len(f)), f), np.cumsum(f) - f
            elem = x.flat[np.repeat(x.bounds[some[s : s + 1024]] - first, f) + np.arange(f.sum())]
            key = np.sort(row << 44 | np.minimum(often[elem], (1 << 20) - 1).astype(np.int64) << 24 | elem)
            key = key[np.arange(len(key)) - first[row] < (f - np.ceil(min_r * f - 1e-9) + 1)[row]]
            key = key[(key >> 24 & ((1 << 20) - 1)) > 1]
            out.append(((key & ((1 << 24) - 1)).astype(np.int32), (s + (key >> 44)).astype(np.int32)))
        return tuple(np.concatenate(c) for c in zip(*out))

    def find(x: Block, y: Block, same: bool) -> Iterator[tuple[np.ndarray, np.ndarray, dict]]:
        often = np.bincount(x.flat, minlength=size).astype(np.int32)
        if not same:
            often += np.bincount(y.flat, minlength=size).astype(np.int32)
        (px, gx), (py, gy) = own = copies(x), copies(x if same else y)
        sx, sy = (p[g[:-1]] for p, g in own)
        fx, fy = np.diff(x.bounds)[sx], np.diff(y.bounds)[sy]
        left, row = prefixes(x, sx, often)
        right, owner = (left, row) if same else prefixes(y, sy, often)
        del often

        def given(g: np.ndarray, h: np.ndarray, shared: np.ndarray, equal: bool) -> Iterator[tuple[np.ndarray, np.ndarray, dict]]:
            """The pairs of all copies of the groups g and h."""
            for first, last in zip(*cut(gx[g + 1] - gx[g])):
                p = np.repeat(np.arange(first, last), (gx[g + 1] - gx[g])[first:last])
                i = px[spans(gx[g[first:last]], gx[g[first:last] + 1])]
                for s, e in zip(*cut((gy[h + 1] - gy[h])[p])):
                    q = h[p[s:e]]
                    m = np.repeat(np.arange(s, e), gy[q + 1] - gy[q])
                    k, j = i[m], py[spans(gy[q], gy[q + 1])]
                    if equal:
                        m, k, j = (v[k < j] for v in (m, k, j))
                    yield k, j, {"f1": fx[g[p[m]]], "f2": fy[h[p[m]]], "a": shared[p[m]]}

        lists = np.argsort(right, kind="stable")
        right, owner = right[lists], owner[lists]
        low = np.searchsorted(right, left, "left")
        n = np.searchsorted(right, left, "right") - low
        of, step = np.searchsorted(row, np.arange(len(fx) + 1)), max(1, 16 * FOUND // max(1, len(fy)))
        for a in range(0, len(fx), step):
            z = min(a + step, len(fx))
            met, s, ends = np.zeros((z - a) * len(fy), bool), of[a], np.r_[0, np.cumsum(n[of[a] : of[z]])]
            while s < of[z]:
                e = max(s + 1, of[a] + int(np.searchsorted(ends, ends[s - of[a]] + FOUND, "right")) - 1)
                at = np.repeat(low[s:e] - (np.cumsum(n[s:e]) - n[s:e]), n[s:e]) + np.arange(n[s:e].sum())
                met[np.repeat((row[s:e] - a).astype(np.int64), n[s:e]) * len(fy) + owner[at]] = True
                s = e
            i, j = np.divmod(np.flatnonzero(met), max(1, len(fy)))
            i += a
            fit = np.minimum(fx[i], fy[j]) >= min_r * np.maximum(fx[i], fy[j]) - 1e-9
            if same:
                fit &= i < j
            i, j = i[fit], j[fit]
            for s in range(0, len(i), MEASURED):
                g, h = i[s : s + MEASURED], j[s : s + MEASURED]
                shared = count(x, sx[g], y, sy[h])["a"]
                near = shared / (fx[g] + fy[h] - shared) >= min_r
                yield from given(g[near], h[near], shared[near], False)
        if same:
            i = np.flatnonzero(np.diff(gx) > 1)
            yield from given(i, i, fx[i], True)
    return find


def linked(find: Callable, keep: Callable) -> Callable:
    """``find`` of so few of its pairs that they connect as all pairs do that ``keep`` (a mask of places in both blocks and what is known) admits."""

    def few(x: Block, y: Block, same: bool) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        root, shift = np.arange(len(x.ids) + (0 if same else len(y.ids))), 0 if same else len(x.ids)

        def top(v: int) -> int:
            while root[v] != v:
                root[v] = v = root[root[v]]
            return v

        for i, j, known in find(x, y, same):
            for s in range(0, len(i), 4096):
                u, v, of = i[s : s + 4096], j[s : s + 4096], {name: c[s : s + 4096] for name, c in known.items()}
                while (root != (up := root[root])).any():
                    root[:] = up
                far = np.flatnonzero(root[u] != root[v + shift])
                far = far[keep(x, u[far], y, v[far], {name: c[far] for name, c in of.items()})]
                new = []
                for n, a, z in zip(far.tolist(), u[far].tolist(), (v[far] + shift).tolist()):
                    a, z = top(a), top(z)
                    if a != z:
                        root[max(a, z)] = min(a, z)
                        new.append(n)
                if new:
                    yield u[new], v[new]

    return few


def bucket_or_short(b: int, band: int) -> Callable:
    """``keep`` of ``linked``: pairs that share a bucket, of which one lacks a band, or that are copies."""

    def keep(x: Block, i: np.ndarray, y: Block, j: np.ndarray, known: dict) -> np.ndarray:
        out = (known["a"] == known["f1"]) & (known["a"] == known["f2"])
        for s in range(0, len(i), 4096):
            u, v = (Block(z.ids[p], z.minima[p], None, z.flat[:0], z.bounds[:1]).buckets(b, band) for z, p in ((x, i[s : s + 4096]), (y, j[s : s + 4096])))
            out[s : s + 4096] |= ((u == v) & (u >= 0)).any(axis=1) | (u < 0).any(axis=1) | (v < 0).any(axis=1)
        return out

    return keep


def striped(permuters: list, ms: tuple, k: int) -> Callable:
    """``extra`` of ``packed``: for each m of ``ms`` the least positions of ``sketch.striped`` with m permuters and k bins; -1 for a hole."""

    def minima(ids: np.ndarray, row: np.ndarray, elem: np.ndarray, least: np.ndarray) -> np.ndarray:
        size, out = permuters[0].size, np.full((len(ids), len(ms), k), permuters[0].size, np.int32)
        for n, p in enumerate(permuters):
            pos = digests(p, elem)
            for at, m in enumerate(ms):
                if n < m:
                    np.minimum.at(out, (row, at, n * (k // m) + pos * (k // m) // size), pos.astype(np.int32))
        return np.where(out == size, -1, out).reshape(len(ids), -1)

    return minima


def striped_counters(ms: tuple, k: int) -> Callable:
    """For each m: mat, emp, emp_i and emp_j with its number, of ``striped`` minima."""

    def measure(x: Block, i: np.ndarray, y: Block, j: np.ndarray) -> dict[str, np.ndarray]:
        out = {f"{c}{m}": np.zeros(len(i), np.int64) for m in ms for c in ("mat", "emp", "emp_i", "emp_j")}
        for s in range(0, len(i), 4096):
            for n, m in enumerate(ms):
                u, v = (z.extra[p[s : s + 4096], n * k : (n + 1) * k] for z, p in ((x, i), (y, j)))
                some, both = [(w >= 0).sum(axis=1) for w in (u, v)], ((u >= 0) & (v >= 0)).sum(axis=1)
                for c, value in (("mat", ((u == v) & (u >= 0)).sum(axis=1)), ("emp", k - some[0] - some[1] + both), ("emp_i", k - some[0]), ("emp_j", k - some[1])):
                    out[f"{c}{m}"][s : s + 4096] = value
        return out

    return measure


def beside(*extras: Callable) -> Callable:
    """Several ``extra`` one after another."""
    return lambda *args: np.concatenate([e(*args) for e in extras], axis=1)


def projected(permuters: list) -> Callable:
    """``extra`` of ``packed``: ``linear_sketch.projection_sums``."""

    def sums(ids: np.ndarray, row: np.ndarray, elem: np.ndarray, least: np.ndarray) -> np.ndarray:
        return np.stack([np.bincount(row, 1 - 2 * (p.numpy(elem) // (p.size // 2)), len(ids)) for p in permuters], axis=1).astype("<i4")

    return sums


def dots_of(parts: dict[str, tuple[int, int]]) -> Callable:
    """Inner products of parts of ``extra``, by name."""

    def measure(x: Block, i: np.ndarray, y: Block, j: np.ndarray) -> dict[str, np.ndarray]:
        out = {name: np.zeros(len(i), np.int64) for name in parts}
        for s in range(0, len(i), 4096):
            u, v = x.extra[i[s : s + 4096]].astype(np.int64), y.extra[j[s : s + 4096]].astype(np.int64)
            for name, (a, z) in parts.items():
                out[name][s : s + 4096] = np.einsum("ij,ij->i", u[:, a:z], v[:, a:z])
        return out

    return measure


def summed(bin_hash, k: int, sign_hash=None) -> Callable:
    """``extra`` of ``packed``: how many elements fall in each of k hashed bins, each counting +1 or -1 where a sign is given."""

    def sums(ids: np.ndarray, row: np.ndarray, elem: np.ndarray, minima: np.ndarray) -> np.ndarray:
        sign = 1 - 2 * (digests(sign_hash, elem) % 2) if sign_hash else None
        cell = row * k + digests(bin_hash, elem) % k
        return np.rint(np.bincount(cell, sign, len(ids) * k)).astype("<i4").reshape(-1, k)

    return sums


def noisy(b: int, seed: int) -> Callable:
    """``extra`` of ``packed``: b bits (8 at most) of each minimum, and of md5 for a hole, as ``codes.noise`` draws them portably."""

    def filled(ids: np.ndarray, row: np.ndarray, elem: np.ndarray, minima: np.ndarray) -> np.ndarray:
        out, (r, c) = minima.copy(), np.nonzero(minima < 0)
        out[r, c] = first_bits([b"n%d:%d:%d" % (seed, *x) for x in zip(ids[r].tolist(), c.tolist())])
        return (out & ((1 << b) - 1)).astype("u1")

    return filled


def dots() -> Callable:
    """dot: the inner product of ``extra``."""
    return lambda x, i, y, j: {"dot": np.einsum("ij,ij->i", x.extra[i].astype(np.int64), y.extra[j].astype(np.int64))}


def equal_codes() -> Callable:
    """n_mat: places at which ``extra`` agrees."""
    return lambda x, i, y, j: {"n_mat": (x.extra[i] == y.extra[j]).sum(axis=1)}


def measured(sets: DataFrame, k: int, b: int, band: int, measures: list[Callable], columns: str, kind: str | None = None, find: Callable | None = None, block: int | None = None) -> DataFrame:
    """i < j of all pairs of ``packed`` sets that share a bucket of ``band`` bins, ``b`` bits each, or that ``find`` gives, with ``columns`` from
    the measures (or from ``find``); ``kind`` is numpy's name for the numbers of ``extra``, ``block`` the sets of a block at most."""
    spark = sets.sparkSession
    sizes = sorted((r.f, r.n) for r in sets.groupBy(F.col("_metadata.file_path").alias("f")).agg(F.count(F.lit(1)).alias("n")).collect())
    schema, names = f"i long, j long, {columns}", [c.split()[0] for c in columns.split(", ")]
    kinds = [pa.int32() if c.split()[1] == "int" else pa.int64() for c in columns.split(", ")]
    blocks: list[list[str]] = []
    room, most = 0, max(FILE_SETS, min(block or BLOCK_SETS, sum(n for _, n in sizes) // 6))
    for name, n in sizes:
        if not blocks or n > room:
            blocks.append([])
            room = most
        blocks[-1].append(name)
        room -= n
    tasks = [(blocks[x], blocks[y], x == y) for x in range(len(blocks)) for y in range(x, len(blocks))]
    if not tasks:
        return spark.createDataFrame([], schema)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for task in (t for batch in batches for t in batch.to_pylist()):
            x = Block.read(task["x"], k, kind)
            y = x if task["same"] else Block.read(task["y"], k, kind)
            for left, right, *known in find(x, y, task["same"]) if find else found(x, y, task["same"], b, band):
                for s in range(0, len(left), MEASURED):
                    i, j = left[s : s + MEASURED], right[s : s + MEASURED]
                    values = {name: v[s : s + MEASURED] for more in known for name, v in more.items()} | {name: v for m in measures for name, v in m(x, i, y, j).items()}
                    ids, other = x.ids[i], y.ids[j]
                    turned = ids > other
                    out = [np.where(turned, values[TWINS[c]], values[c]) if c in TWINS else values[c] for c in names]
                    yield pa.RecordBatch.from_arrays([pa.array(np.minimum(ids, other)), pa.array(np.maximum(ids, other)), *(pa.array(v, t) for v, t in zip(out, kinds))], names=["i", "j", *names])

    rows = spark.sparkContext.parallelize(tasks, len(tasks))
    return spark.createDataFrame(rows, "x array<string>, y array<string>, same boolean").mapInArrow(run, schema)
