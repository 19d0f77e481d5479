"""Experiment grids: many fits on the coded sketches of all labelled rows, a task for each cell.

A sketch is taken once, at the largest k and eight bits; every smaller k and b is
rolled up and masked from it inside the task. Codes and labels lie in tables of the
shared folder: a task reads one of them a few rows at a time and fits in rounds over
parts of the rows. Parts are kept between rounds if they take HELD bytes at most,
else they are read again in each; whatever the number of rows, a task holds some
numbers for each and one part.
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

ROUNDS, SMOOTH, STILL = 60, 0.5, 1e-3
#: Rows that are read, entries that are worked on at a time.
READ, ENTRIES = 1024, 1 << 20
#: Bytes of parts that are kept between rounds, bins of all rows of a part, its rows at most.
HELD, PART, PART_ROWS = 64 << 20, 1 << 24, 1 << 16
RESULT = "method string, solver string, k int, b int, c double, rep int, n_train int, n int, nonzeros double, accuracy double, balanced double, auc double, majority double"


def labelled(labels: DataFrame) -> DataFrame:
    """set_id, label, a row for each set; rows without either are left out."""
    return labels.filter("set_id is not null and label is not null").groupBy("set_id").agg(F.max("label").alias("label"))


@dataclass
class Coded:
    """Eight low bits of each bin's minimum, and which bins have one; rows in the order of ``ids``."""

    ids: np.ndarray
    codes: np.ndarray
    filled: np.ndarray

    def at(self, k: int, nested: bool) -> tuple[np.ndarray, np.ndarray]:
        """k bins: neighbours merge (the first filled one holds the least position); permutations are just fewer."""
        n, top = self.codes.shape
        if not nested or k == top:
            return self.codes[:, :k], self.filled[:, :k]
        filled = self.filled.reshape(n, k, top // k)
        first = filled.argmax(axis=2)[..., None]
        return np.take_along_axis(self.codes.reshape(n, k, top // k), first, 2)[..., 0], filled.any(axis=2)


def collected(packed: DataFrame, k: int) -> Coded:
    """The rows of ``codes.to_binary`` with 8 bits on the driver; the caller bounds them."""
    t = packed.orderBy("set_id").toArrow()
    raw = np.frombuffer(b"".join(t.column("codes").to_pylist()), np.uint8).reshape(-1, k)
    mask = np.frombuffer(b"".join(t.column("holes").to_pylist()), np.uint8).reshape(-1, k // 8)
    return Coded(t.column("set_id").to_numpy(), raw, np.unpackbits(mask, axis=1, bitorder="little") == 0)


def batches_of(files: list[str], columns: list[str]) -> Iterator[pa.RecordBatch]:
    for name in files:
        store, path = fs.FileSystem.from_uri(name)
        with store.open_input_file(path) as f:
            yield from pq.ParquetFile(f).iter_batches(READ, columns=columns, use_threads=False)


def files_of(table: DataFrame) -> list[str]:
    return sorted(r[0] for r in table.select("_metadata.file_path").distinct().collect())


@dataclass
class Stored:
    """A written table of ``codes.to_binary`` rows with 8 bits of k bins, for tasks to read."""

    files: list[str]
    k: int

    @classmethod
    def of(cls, table: DataFrame, k: int) -> Stored:
        return cls(files_of(table), k)

    def ids(self) -> np.ndarray:
        return np.sort(np.concatenate([np.zeros(0, np.int64), *(b.column(0).to_numpy() for b in batches_of(self.files, ["set_id"]))]))

    def at(self, k: int, nested: bool, ids: np.ndarray, wanted: np.ndarray | None = None) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
        """Places in ``ids`` of some rows (those ``wanted``), their codes at k bins and which bins are filled, a part of the rows after another."""
        for b in batches_of(self.files, ["set_id", "codes", "holes"]):
            if wanted is not None:
                b = b.filter(pa.array(wanted[np.searchsorted(ids, b.column(0).to_numpy())]))
            if not b.num_rows:
                continue
            raw = np.frombuffer(b"".join(b.column("codes").to_pylist()), np.uint8).reshape(-1, self.k)
            mask = np.frombuffer(b"".join(b.column("holes").to_pylist()), np.uint8).reshape(len(raw), -1)
            own = Coded(b.column("set_id").to_numpy(), raw, np.unpackbits(mask, axis=1, bitorder="little")[:, : self.k] == 0)
            yield np.searchsorted(ids, own.ids), *own.at(k, nested)


@dataclass
class Design:
    """Rows of a sparse matrix: flat column indexes, their rows, one scale a row."""

    index: np.ndarray
    row: np.ndarray
    scale: np.ndarray
    dims: int

    @property
    def nbytes(self) -> int:
        return self.index.nbytes + self.row.nbytes

    def margins(self, w: np.ndarray) -> np.ndarray:
        out = np.zeros(len(self.scale))
        for a in range(0, len(self.row), ENTRIES):
            out += np.bincount(self.row[a : a + ENTRIES], w[self.index[a : a + ENTRIES]], len(out))
        return out * self.scale

    def back(self, g: np.ndarray) -> np.ndarray:
        out, g = np.zeros(self.dims), g * self.scale
        for a in range(0, len(self.row), ENTRIES):
            out += np.bincount(self.index[a : a + ENTRIES], g[self.row[a : a + ENTRIES]], self.dims)
        return out

    def masked(self, b: int) -> Design:
        """From eight bits a bin to b of them."""
        return self if b == 8 else Design(self.index >> 8 << b | self.index & ((1 << b) - 1), self.row, self.scale, self.dims >> 8 << b)


class Dense:
    """Rows without holes, a byte for each bin, by columns; bins of few bits share a byte, so that one look gives the sum of their weights."""

    def __init__(self, columns: np.ndarray, b: int):
        k, n = columns.shape
        self.b, self.dims, self.scale = b, k << b, np.full(n, 1 / np.sqrt(k))
        self.group = next(g for g in (8 // b, 1) if k % g == 0)
        self.columns, low = np.zeros((k // self.group, n), np.uint8), np.uint8((1 << b) - 1)
        for i in range(self.group):
            self.columns |= (low - (columns[i :: self.group] & low)) << np.uint8(b * (self.group - 1 - i))

    @property
    def nbytes(self) -> int:
        return self.columns.nbytes

    def margins(self, w: np.ndarray) -> np.ndarray:
        w = w.reshape(-1, self.group, 1 << self.b)
        sums = w[:, 0]
        for i in range(1, self.group):
            sums = (sums[:, :, None] + w[:, i, None, :]).reshape(len(w), -1)
        out, seen = np.zeros(len(self.scale)), np.zeros(len(self.scale))
        for own, column in zip(sums, self.columns):
            out += np.take(own, column, out=seen, mode="clip")
        return out * self.scale

    def back(self, g: np.ndarray) -> np.ndarray:
        g, width = g * self.scale, 1 << self.b * self.group
        sums = np.stack([np.bincount(column, g, width) for column in self.columns]).reshape(-1, *[1 << self.b] * self.group)
        return np.stack([sums.sum(axis=tuple(a for a in range(1, self.group + 1) if a != i + 1)) for i in range(self.group)], axis=1).reshape(-1)


@dataclass
class Filled:
    """Eight bits of each bin of rows without holes, by columns."""

    columns: np.ndarray

    @property
    def nbytes(self) -> int:
        return self.columns.nbytes

    def masked(self, b: int) -> Dense:
        return Dense(self.columns, b)


class Parts:
    """Designs of some rows after another, with the rows' places: kept if they take ``HELD`` bytes at most, else made again each time."""

    def __init__(self, make: Callable[[], Iterator[tuple]], n: int, dims: int):
        self.make, self.n, self.dims = make, n, dims
        self.held: list[tuple] | None = None

    def __iter__(self) -> Iterator[tuple]:
        if self.held is not None:
            yield from self.held
            return
        held, size = [], 0
        for rows, x in self.make():
            size += x.nbytes
            if size <= HELD:
                held.append((rows, x))
            else:
                held.clear()
            yield rows, x
        if size <= HELD:
            self.held = held

    def masked(self, b: int) -> Parts:
        return Parts(lambda: ((rows, x.masked(b)) for rows, x in self), self.n, self.dims >> 8 << b)

    def margins(self, w: np.ndarray) -> np.ndarray:
        out = np.zeros(self.n)
        for rows, x in self:
            out[rows] = x.margins(w)
        return out

    def back(self, g: np.ndarray) -> np.ndarray:
        out = np.zeros(self.dims)
        for rows, x in self:
            out += x.back(g[rows])
        return out


def drawn(rep: int, k: int, places: np.ndarray) -> np.ndarray:
    """Codes for the holes of the rows at ``places``: what one generator draws for all rows in turn, whichever are asked for."""
    bits, after, words = np.random.default_rng([rep, k]).bit_generator, 0, -(-k // 8)
    out = np.zeros((len(places), words), "<u8")
    for i in np.argsort(places, kind="stable").tolist():
        place = int(places[i])
        if place != after:
            bits.advance((place - after) * words)
        out[i], after = bits.random_raw(words), place + 1
    return out.view(np.uint8)[:, :k]


def filled_columns(part: Stored, k: int, nested: bool, ids: np.ndarray, noise: np.random.Generator | None) -> np.ndarray | None:
    """Codes of eight bits by rows, holes drawn by ``noise``; None if there are holes and no noise."""
    out = noise.integers(0, 256, (len(ids), k), dtype=np.uint8) if noise else np.zeros((len(ids), k), np.uint8)
    for place, code, filled in part.at(k, nested, ids):
        if noise is None and not filled.all():
            return None
        out[place] = np.where(filled, code, out[place])
    return out


def blank_design(part: Stored, k: int, nested: bool, ids: np.ndarray) -> Design:
    """``design`` of the filled bins alone, at eight bits, in four bytes for an index and for a row."""
    index, rows, n = [], [], np.zeros(len(ids))
    for place, code, filled in part.at(k, nested, ids):
        row, at = np.nonzero(filled)
        index.append((at * 256 + 255 - code[row, at]).astype(np.int32))
        rows.append(place[row].astype(np.int32))
        n[place] = filled.sum(axis=1)
    none = [np.zeros(0, np.int32)]
    return Design(np.concatenate(index or none), np.concatenate(rows or none), 1 / np.sqrt(np.maximum(n, 1)), k << 8)


def design(codes: np.ndarray, filled: np.ndarray, b: int, noise: np.random.Generator | None = None) -> Design:
    """Expanded places: blank coding leaves holes out and scales by the filled bins, noise coding draws codes for them."""
    n, k = codes.shape
    code = codes & np.uint8((1 << b) - 1)
    if noise is not None:
        code = np.where(filled, code, noise.integers(0, 1 << b, (n, k), dtype=np.uint8))
        filled = np.ones_like(filled)
    row, at = np.nonzero(filled)
    index = at * (1 << b) + (1 << b) - 1 - code[row, at]
    return Design(index, row, 1 / np.sqrt(np.maximum(filled.sum(axis=1), 1)), k << b)


def distinct(some: Iterator[np.ndarray]) -> np.ndarray:
    held, waiting = [np.zeros(0, np.int64)], 0
    for x in some:
        held.append(np.unique(x))
        waiting += len(held[-1])
        if waiting > max(ENTRIES, len(held[0])):
            held, waiting = [np.unique(np.concatenate(held))], 0
    return np.unique(np.concatenate(held))


def steepest(x: Design | Dense | Parts, n: int) -> float:
    """The largest eigenvalue of the products of the n rows."""
    v = np.random.default_rng(0).normal(size=n)
    for _ in range(6):
        v = x.margins(x.back(v / np.linalg.norm(v)))
    return float(np.linalg.norm(v))


def fit(x: Design | Dense | Parts, y: np.ndarray, c: float, solver: str, w: np.ndarray | None = None, largest: float | None = None) -> np.ndarray:
    """Weights that minimise |w|^2 / 2 + c * (sum of losses): logistic, or hinge rounded off over SMOOTH. Accelerated gradients, all rows in each round.

    ``largest`` is what ``steepest`` gives, if known."""
    largest = steepest(x, len(y)) if largest is None else largest
    steep = 1 + c * 1.05 * largest * (0.25 if solver == "logistic" else 1 / SMOOTH)
    push = (np.sqrt(steep) - 1) / (np.sqrt(steep) + 1)
    w = np.zeros(x.dims) if w is None else w
    ahead = w
    for _ in range(ROUNDS):
        back = np.zeros(x.dims)
        for rows, part in x if isinstance(x, Parts) else [(slice(None), x)]:
            own = y[rows]
            margin = own * part.margins(ahead)
            slope = -1 / (1 + np.exp(np.clip(margin, -30, 30))) if solver == "logistic" else -np.clip((1 - margin) / SMOOTH, 0, 1)
            back += part.back(slope * own)
        new = ahead - (ahead + c * back) / steep
        moved = np.linalg.norm(new - w)
        ahead, w = new + push * (new - w), new
        if moved <= STILL * max(np.linalg.norm(w), 1e-9):
            break
    return w


def measures(score: np.ndarray, y: np.ndarray) -> tuple[float, float, float, float]:
    """Accuracy, balanced accuracy, area under the curve, the majority's share."""
    right, one = (score > 0) == (y > 0), y > 0
    values, place = np.unique(score, return_inverse=True)
    count = np.bincount(place)
    rank = (np.cumsum(count) - (count - 1) / 2)[place]
    p, q = int(one.sum()), int((~one).sum())
    auc = (rank[one].sum() - p * (p + 1) / 2) / (p * q) if p and q else float("nan")
    parts = [right[s].mean() for s in (one, ~one) if s.any()]
    return float(right.mean()), float(np.mean(parts)), float(auc), max(p, q) / len(y)


def coded_parts(part: Stored, method: str, k: int, rep: int, ids: np.ndarray, some: np.ndarray) -> Parts:
    """Rows ``some`` of ``ids``, eight bits a bin: without holes by columns (noise fills them), else entries of the filled bins."""
    number = np.full(len(ids), -1)
    number[some] = np.arange(len(some))
    most = max(1, min(PART_ROWS, PART // k))

    def made(places: list[np.ndarray], code: np.ndarray, filled: np.ndarray) -> tuple[np.ndarray, Filled | Design]:
        place = np.concatenate(places)
        if method == "noise":
            code = np.where(filled, code, drawn(rep, k, place))
        if method == "noise" or method == "classic" and filled.all():
            return number[place], Filled(np.ascontiguousarray(code.T))
        row, at = np.nonzero(filled)
        scale = 1 / np.sqrt(np.maximum(filled.sum(axis=1), 1))
        return number[place], Design((at * 256 + 255 - code[row, at]).astype(np.int32), row.astype(np.int32), scale, k << 8)

    def make() -> Iterator[tuple]:
        held: list[tuple] = []
        for own in part.at(k, method != "classic", ids, number >= 0):
            if held and sum(len(h[0]) for h in held) + len(own[0]) > most:
                places, *rest = zip(*held, strict=True)
                yield made(list(places), *(np.concatenate(x) for x in rest))
                held = []
            held.append(own)
        if held:
            places, *rest = zip(*held, strict=True)
            yield made(list(places), *(np.concatenate(x) for x in rest))

    return Parts(make, len(some), k << 8)


def unhashed_parts(files: list[str], ids: np.ndarray, values: np.ndarray, some: np.ndarray) -> Parts:
    """Rows ``some`` of the original data: each of ``values`` a column of its own, rows of unit length."""
    number = np.full(len(ids), -1)
    number[some] = np.arange(len(some))

    def made(held: list[tuple]) -> tuple[np.ndarray, Design]:
        rows, count, elems = (np.concatenate(x) for x in zip(*held, strict=True))
        index = np.searchsorted(values, elems).astype(np.int32)
        return rows, Design(index, np.repeat(np.arange(len(count), dtype=np.int32), count), 1 / np.sqrt(np.maximum(count, 1)), len(values))

    def make() -> Iterator[tuple]:
        held: list[tuple] = []
        for b in batches_of(files, ["set_id", "elems"]):
            rows = number[np.searchsorted(ids, b.column(0).to_numpy())]
            lists = b.filter(pa.array(rows >= 0)).column(1)
            held.append((rows[rows >= 0], lists.value_lengths().to_numpy(), lists.flatten().to_numpy()))
            if sum(len(h[2]) for h in held) > PART // 8:
                yield made(held)
                held = []
        if held:
            yield made(held)

    return Parts(make, len(some), len(values))


def parts_of(part, method: str, k: int, rep: int, test_of):
    """ids, which of them are tested, entries a row, and a function from b to the designs of training and of tested rows."""
    if method == "original":
        ids, values = distinct(b.column(0).to_numpy() for b in batches_of(part, ["set_id"])), distinct(b.column(0).flatten().to_numpy() for b in batches_of(part, ["elems"]))
    else:
        ids = part.ids()
    test = test_of(ids)
    train, probe = np.flatnonzero(~test), np.flatnonzero(test)
    a, z = (unhashed_parts(part, ids, values, some) if method == "original" else coded_parts(part, method, k, rep, ids, some) for some in (train, probe))
    entries = float(k)
    if method in ("blank", "original"):
        entries = sum(len(x.index) for own in (a, z) for _, x in own) / max(len(ids), 1)
    return ids, train, probe, entries, lambda b: (a, z) if method == "original" or method == "blank" and b == 8 else (a.masked(b), z.masked(b))


def signs(files: list[str], ids: np.ndarray) -> np.ndarray:
    """1 or -1 for each of ``ids``, from written (set_id, label) rows."""
    out = np.full(len(ids), -1.0)
    for b in batches_of(files, ["set_id", "label"]):
        some = b.column(0).to_numpy()[b.column(1).to_numpy() > 0]
        at = np.minimum(np.searchsorted(ids, some), max(len(ids) - 1, 0))
        out[at[ids[at] == some] if len(ids) else at[:0]] = 1.0
    return out


def run_cells(spark, data: dict, labels: dict[int, float] | list[str], test_of, cells: list[tuple], costs: list[float]) -> DataFrame:
    """One row per (cell, cost): RESULT. ``data`` maps (method's data, rep) to ``Stored``, or for "original" to the files of (set_id, elems) rows;
    a cell is (method, solver, k, b, rep). ``labels`` are the files of (set_id, label) rows, or few labels by id, which are broadcast.

    Methods: "blank" and "noise" read the binned sketch, "classic" the k-permutation one, "original" the unhashed rows.
    ``test_of`` tells by ids which rows are tested. Cells that differ in b alone are one task, so that a task reads once; the largest begin first.
    """
    known_to = spark.sparkContext.broadcast(labels) if isinstance(labels, dict) else None
    kinds = [pa.string(), pa.string(), pa.int32(), pa.int32(), pa.float64(), pa.int32(), pa.int32(), pa.int32(), *[pa.float64()] * 5]
    tasks: dict[tuple, list[int]] = {}
    for method, solver, k, b, rep in cells:
        tasks.setdefault((method, solver, k, rep), []).append(b)
    work = sorted(((*t, bs) for t, bs in tasks.items()), key=lambda t: (-t[2], t[0] == "blank"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for task in (t for batch in batches for t in batch.to_pylist()):
            method, solver, k, rep = (task[c] for c in ("method", "solver", "k", "rep"))
            part = data["original", 0] if method == "original" else data["classic" if method == "classic" else "binned", rep]
            ids, train, probe, entries, at = parts_of(part, method, k, rep, test_of)
            y = np.array([1.0 if known_to.value[int(i)] > 0 else -1.0 for i in ids]) if known_to else signs(labels, ids)
            for b in task["bs"]:
                a, z = at(b)
                w, rows, largest = None, [], steepest(a, len(train))
                for c in sorted(costs):
                    w = fit(a, y[train], c, solver, w, largest)
                    rows.append((method, solver, k, b, c, rep, len(train), len(probe), entries, *measures(z.margins(w), y[probe])))
                yield pa.RecordBatch.from_arrays([pa.array(v, t) for v, t in zip(zip(*rows, strict=True), kinds, strict=True)], names=[f.split()[0] for f in RESULT.split(", ")])

    rows = spark.sparkContext.parallelize(work, len(work))
    return spark.createDataFrame(rows, "method string, solver string, k int, rep int, bs array<int>").mapInArrow(run, RESULT)


def classic_codes(rows: DataFrame, k: int, seed: int, id_col: str = "set_id", elems_col: str = "elems") -> DataFrame:
    """set_id, codes, holes like ``codes.to_binary`` with 8 bits, of k multiply-shift permutations: row-local, k times the hashing."""
    r = np.random.default_rng(seed)
    a, shift = r.integers(0, 1 << 63, k, dtype=np.uint64) * np.uint64(2) + np.uint64(1), r.integers(0, 1 << 63, k, dtype=np.uint64)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = []
            for elems in batch.column(elems_col).to_pylist():
                e = np.unique(np.array(elems or [], np.int64)).view(np.uint64)
                least = np.zeros(k, np.uint64)
                for at in range(0, k if len(e) else 0, 256):
                    least[at : at + 256] = ((a[at : at + 256, None] * e + shift[at : at + 256, None]) >> np.uint64(40)).min(axis=1)
                out.append(((least & np.uint64(255)).astype(np.uint8).tobytes(), np.packbits(np.full(k, not len(e))).tobytes()))
            yield pa.RecordBatch.from_arrays([batch.column(id_col).cast(pa.int64()), *(pa.array(c, pa.binary()) for c in zip(*out, strict=True))], names=["set_id", "codes", "holes"])

    return rows.select(id_col, elems_col).mapInArrow(run, "set_id long, codes binary, holes binary")
