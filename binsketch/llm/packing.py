"""Lexical retrieval packing: windows filled with a seed document and its BM25 neighbours.

Documents are encoded once into a table of the shared folder. Document
frequencies and lengths are counted over all of it. Windows are made in rounds:
the first unused documents are a round's seeds, every task scores them against
all blocks of its part of the table that can hold one of their best unused
documents, and the driver merges these lists and fills the seeds' windows one after another, best
first; what doesn't fit is cut and stays for another window. A seed whose list
others have used up before its window is full waits for the next round. What is
left in the end and fits in one index is packed by one task.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import map_batches, texts_of, tidy, written
from .memo import json_encoder

K1, B = 1.2, 0.75
SHARD_TOKENS = 3_000_000
#: Documents that a task holds at a time, and of them (of one group) in a block; seeds in a block.
CHUNK, ROWS, SEED_ROWS = 16_384, 256, 1024
#: A block is read for a seed if its bound reaches the seed's list. A ``Scorer`` with a spread leaves out more, and finds less; no query asks for it:
#: there, a block is read if the mean of its scores and so many of their deviations reach the seed's list.
#: Blocks of the seed's group whose documents weigh as much as the seed, but for the share ``ALIKE``, are read as well: near copies lie there.
#: Tasks that hold fewer than ``FEW`` documents at a time go by bounds alone. Deviations are measured on ``PROBES`` of the seeds.
SPREAD, FEW, PROBES, ALIKE = 2.5, 4096, 24, 0.05
#: Terms in more than this share of a block's documents are multiplied as columns, at most so many.
COMMON, COLUMNS = 0.02, 2048
#: Groups of documents alike, and about how many documents they are fitted on. They decide what is scored together, not what is found.
GROUPS, SAMPLE = 24, 2048
#: Seeds in a round (as many as that share of the windows if more, up to the last number), windows that a seed's list fills at first.
SEEDS, SHARE, MOST_SEEDS, SLACK = 8192, 16, 16_384, 8
PIECES = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long"
CODED = "doc_id long, ids binary, n int, terms binary, counts binary"


def encoded(docs: DataFrame, vocabulary: str, end_id: int, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, ids (little-endian 16-bit, with the end id), their number, distinct terms and counts. Null text counts as empty: the end id only."""

    def run(batch):
        enc = json_encoder(vocabulary)
        if enc.kind.itemsize != 2:
            raise ValueError("packing holds ids of 16 bits")
        found, sizes = enc.many(texts_of(batch, text_col))
        owner, ends = np.repeat(np.arange(len(sizes)), sizes), np.cumsum(sizes + 1)
        ids = np.full(ends[-1] if len(ends) else 0, end_id, enc.kind)
        ids[np.arange(len(found)) + owner] = found
        key = np.sort((np.repeat(np.arange(len(sizes), dtype=np.uint32), sizes + 1) << np.uint32(16)) | ids)
        first = np.flatnonzero(np.r_[True, key[1:] != key[:-1]][: len(key)])
        key, counts = key[first], np.diff(np.r_[first, len(key)])
        held = np.cumsum(np.bincount(key >> np.uint32(16), minlength=len(sizes)))
        yield {"doc_id": batch.column(id_col), "ids": blobs(ids, ends), "n": (sizes + 1).astype(np.int32), "terms": blobs(key.astype("<u2"), held), "counts": blobs(counts.astype("<u4"), held)}

    return map_batches(docs.select(F.col(id_col).cast("long").alias(id_col), text_col), run, CODED)


def blobs(values: np.ndarray, ends: np.ndarray) -> pa.Array:
    """A binary column of ``values``, cut at ``ends``."""
    return pa.Array.from_buffers(pa.large_binary(), len(ends), [None, pa.py_buffer(np.r_[0, ends].astype(np.int64) * values.itemsize), pa.py_buffer(np.ascontiguousarray(values))]).cast(pa.binary())


def entries(column: pa.Array, kind: str) -> tuple[np.ndarray, np.ndarray]:
    """The numbers of a binary column one after another, and where each row's begin (and the last one's end)."""
    if not len(column):
        return np.zeros(0, kind), np.zeros(1, np.int64)
    _, at, data = column.buffers()
    ends = np.frombuffer(at, np.int64 if pa.types.is_large_binary(column.type) else np.int32)[column.offset : column.offset + len(column) + 1].astype(np.int64)
    own = np.frombuffer(data, np.uint8)[ends[0] : ends[-1]].view(kind)
    return own, (ends - ends[0]) // np.dtype(kind).itemsize


def corpus_counts(coded: DataFrame) -> tuple[int, int, dict[int, int]]:
    """Documents, tokens and each term's document frequency over all of ``coded``; as many rows as the vocabulary has."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen, docs, tokens = np.zeros(65536, np.int64), 0, 0
        for batch in batches:
            seen += np.bincount(entries(batch.column("terms"), "<u2")[0], minlength=65536)
            docs, tokens = docs + batch.num_rows, tokens + int(batch.column("n").to_numpy().sum(dtype=np.int64))
        at = np.flatnonzero(seen)
        yield pa.RecordBatch.from_arrays([pa.array(np.r_[-2, -1, at]), pa.array(np.r_[docs, tokens, seen[at]])], names=["term", "n"])

    rows = {r.term: r.n for r in coded.select("n", "terms").mapInArrow(tidy(run), "term long, n long").groupBy("term").agg(F.sum("n").alias("n")).collect()}
    return rows.pop(-2, 0), rows.pop(-1, 0), rows


def weights(terms: np.ndarray, counts: np.ndarray, owner: np.ndarray, lengths: np.ndarray, idf: np.ndarray, mean_length: float) -> np.ndarray:
    """BM25 weight of each term in its document."""
    damp = K1 * (1 - B + B * lengths / max(mean_length, 1.0))
    return (idf[terms] * counts * (K1 + 1) / (counts + damp[owner])).astype(np.float32)


class Index:
    """Inverted BM25 index of documents that one task holds."""

    def __init__(self, docs: list[np.ndarray], idf: np.ndarray, mean_length: float, found: list[tuple[np.ndarray, np.ndarray]] | None = None, lengths: np.ndarray | None = None):
        """``docs``, or their distinct terms and counts with their lengths."""
        if found is None:
            found, lengths = [np.unique(d, return_counts=True) for d in docs], np.array([len(d) for d in docs])
        docs, sizes = found, np.array([len(t) for t, _ in found])
        terms, counts = np.concatenate([t for t, _ in found]), np.concatenate([c for _, c in found])
        owner = np.repeat(np.arange(len(docs)), sizes)
        weight = weights(terms, counts, owner, lengths, idf, mean_length)
        self.bounds = np.r_[0, np.cumsum(sizes)]
        self.terms = terms
        order = np.argsort(terms, kind="stable")
        self.owners, self.scores = owner[order], weight[order]
        self.lists = np.r_[0, np.cumsum(np.bincount(terms, minlength=65536))]
        self.n = len(docs)

    def neighbours(self, seed: int) -> np.ndarray:
        """Score of each document for all distinct terms of the seed."""
        terms = self.terms[self.bounds[seed] : self.bounds[seed + 1]]
        at = np.concatenate([np.arange(self.lists[t], self.lists[t + 1]) for t in terms])
        return np.bincount(self.owners[at], self.scores[at], self.n)


def pack_shard(docs: list[np.ndarray], index: Index, window: int) -> Iterator[list[tuple[int, int, int]]]:
    """Windows as lists of (document, start, length). All but the last are full; each id lies in one of them."""
    yield from pack_rest(index, window, np.zeros(len(docs), np.int64), np.array([len(d) for d in docs]))


def pack_rest(index: Index, window: int, start: np.ndarray, left: np.ndarray) -> Iterator[list[tuple[int, int, int]]]:
    """``pack_shard`` of what is left of each document from ``start`` on."""
    for d in np.flatnonzero(left >= window):  # a long document fills windows of its own
        for _ in range(left[d] // window):
            yield [(int(d), int(start[d]), window)]
            start[d] += window
        left[d] %= window
    first = 0
    while True:
        while first < len(left) and not left[first]:
            first += 1
        if first == len(left):
            return
        room, pieces = window, []

        def take(d: int) -> None:
            nonlocal room
            n = min(room, int(left[d]))
            pieces.append((int(d), int(start[d]), n))  # noqa: B023
            start[d] += n
            left[d] -= n
            room -= n

        score = index.neighbours(first)
        take(first)
        if room:
            score[left == 0] = 0
            near = np.flatnonzero(score)
            for d in near[np.argsort(-score[near], kind="stable")]:
                take(d)
                if not room:
                    break
        while room:  # no neighbour is left: the next documents
            rest = np.flatnonzero(left)
            if not len(rest):
                break
            for d in rest:
                take(d)
                if not room:
                    break
        yield pieces


def columns_of(often: np.ndarray) -> np.ndarray:
    """Each term's place among ``often``, or -1."""
    column = np.full(65536, -1, np.int32)
    column[often] = np.arange(len(often))
    return column


def frequent(held: np.ndarray, n: int) -> np.ndarray:
    """Terms that more than ``COMMON`` of ``n`` documents hold, as counted in ``held``, the most frequent first."""
    often = np.flatnonzero(held > COMMON * n)
    return often[np.argsort(-held[often], kind="stable")][:COLUMNS]


def runs(begins: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """Places begins[0], begins[0] + 1 and so on, ``sizes[0]`` of them, then those of the next."""
    return np.repeat(begins - np.cumsum(sizes) + sizes, sizes) + np.arange(sizes.sum())


class Block:
    """Documents of one group, ready to be scored: frequent terms (``column`` tells them) as columns of a matrix, the others as inverted lists."""

    def __init__(self, place: np.ndarray, terms: np.ndarray, weight: np.ndarray, owner: np.ndarray, total: np.ndarray, group: int, column: np.ndarray, n_rare: int):
        """``column`` holds the place of a term among the frequent ones, or -1 less its place among the others."""
        self.place, self.total, self.least, self.group, n = place, total.max(), total.min(), group, len(place)
        at = column[terms]
        common = at >= 0
        width = int(column.max()) + 1
        self.used = np.flatnonzero(np.bincount(at[common], minlength=width))
        slot = np.zeros(width, np.int64)
        slot[self.used] = np.arange(len(self.used))
        self.matrix = np.zeros((n, len(self.used)), np.float32)
        self.matrix[owner[common], slot[at[common]]] = weight[common]
        rare = -1 - at[~common]
        order = np.argsort(rare, kind="stable")
        self.owners, self.weights = owner[~common][order], weight[~common][order]
        self.lists = np.r_[0, np.cumsum(np.bincount(rare, minlength=n_rare))]
        held = np.flatnonzero(np.diff(self.lists))
        # what a term adds to a score here: at most, in the mean, and the variance of it
        self.common, self.rare = np.zeros((3, width), np.float32), np.zeros((3, n_rare + 1), np.float32)
        if len(self.used):
            self.common[:, self.used] = self.matrix.max(axis=0), self.matrix.mean(axis=0), self.matrix.var(axis=0)
        if len(held):
            mean = np.add.reduceat(self.weights, self.lists[held]) / n
            self.rare[:, held] = np.maximum.reduceat(self.weights, self.lists[held]), mean, np.add.reduceat(self.weights**2, self.lists[held]) / n - mean**2

    def scores(self, wanted: np.ndarray, some: np.ndarray, rare: np.ndarray, row: np.ndarray) -> np.ndarray:
        """This block's scores for the seeds ``some``, rows of ``wanted``; the i-th of them also holds the infrequent terms rare[row == i]."""
        found = wanted[some].take(self.used, axis=1) @ self.matrix.T
        sizes = self.lists[rare + 1] - self.lists[rare]
        own = runs(self.lists[rare], sizes)
        np.add.at(found.reshape(-1), np.repeat(row * len(self.place), sizes) + self.owners[own], self.weights[own])  # few: the frequent terms are columns
        return found


class Questions:
    """The terms of a block of seeds, as columns and lists of a chunk's blocks."""

    def __init__(self, asked: np.ndarray, sizes: np.ndarray, column: np.ndarray, n_rare: int):
        self.n, row, at = len(sizes), np.repeat(np.arange(len(sizes)), sizes), column[asked]
        common = at >= 0
        self.wanted = np.zeros((self.n, int(column.max()) + 1), np.float32)
        self.wanted[row[common], at[common]] = 1
        self.rare, self.row = -1 - at[~common], row[~common]
        self.rare, self.row = self.rare[self.rare < n_rare], self.row[self.rare < n_rare]
        self.null = n_rare

    def sums(self, blocks: list[Block], of: int) -> np.ndarray:
        """What the blocks' terms add for each seed (0: at most, 1: in the mean, 2: variance)."""
        out = self.wanted @ np.stack([b.common[of] for b in blocks], axis=1)
        row = np.r_[np.arange(self.n), self.row]  # a term that no block holds is the first of each seed
        order = np.argsort(row, kind="stable")
        values = np.stack([b.rare[of] for b in blocks], axis=1)[np.r_[np.full(self.n, self.null), self.rare][order]]
        return out + np.add.reduceat(values, np.searchsorted(row[order], np.arange(self.n)), axis=0)

    def scores(self, block: Block, some: np.ndarray) -> np.ndarray:
        at = np.full(self.n, -1)
        at[some] = np.arange(len(some))
        here = at[self.row] >= 0
        return block.scores(self.wanted, some, self.rare[here], at[self.row[here]])


def ranked(seed: np.ndarray, docs: np.ndarray, values: np.ndarray) -> np.ndarray:
    """The order by seed, falling (positive) value and document."""
    key = (seed.astype(np.uint64) << np.uint64(32)) | (np.uint64(0xFFFFFFFF) - np.ascontiguousarray(values).view(np.uint32))
    order = np.argsort(key)
    key = key[order]
    same = key[1:] == key[:-1]
    tied = np.flatnonzero(np.r_[same, False] | np.r_[False, same])
    order[tied] = order[tied][np.lexsort((docs[order[tied]], key[tied]))]
    return order


class Lists:
    """Each seed's best documents, best first and ties to smaller numbers, as far as they hold ``tokens`` unused tokens."""

    def __init__(self, n: int, tokens: int):
        self.n, self.tokens = n, tokens
        self.seed, self.docs, self.values = np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0, np.float32)
        self.floor, self.more = np.zeros(n, np.float32), np.zeros(n, bool)  # value of the last one of a full list; what may be missing
        self.new: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
        self.waiting = 0

    def add(self, seed: np.ndarray, docs: np.ndarray, values: np.ndarray) -> None:
        if len(seed):
            self.new.append((seed, docs, values))
            self.waiting += len(seed)

    def cut(self, left: np.ndarray) -> None:
        """Take in what was added, and leave out what lies behind a full list."""
        seed, docs, values = (np.concatenate(x) for x in zip((self.seed, self.docs, self.values), *self.new, strict=True))
        self.new, self.waiting = [], 0
        order = ranked(seed, docs, values)
        seed, docs, values = seed[order], docs[order], values[order]
        sizes = left[docs].astype(np.int64)
        before = np.cumsum(sizes) - sizes
        bounds = np.searchsorted(seed, np.arange(self.n + 1))
        before -= np.r_[before, 0][bounds[:-1]][seed]
        kept = before < self.tokens
        self.more[seed[~kept]] = True
        last = kept & (before + sizes >= self.tokens)
        self.floor[seed[last]] = values[last]
        self.more[seed[last]] = True  # what is behind a full list is not looked at
        self.seed, self.docs, self.values = seed[kept], docs[kept], values[kept]

    def see(self, which: np.ndarray, score: np.ndarray, docs: np.ndarray, seeds: np.ndarray, left: np.ndarray) -> None:
        """Scores of ``docs``, a row for each seed of ``which``."""
        least = np.maximum(self.floor[which], np.finfo(np.float32).tiny)
        k = min(256, len(docs) - 1)
        fresh = np.flatnonzero(self.floor[which] == 0)
        if k and len(fresh):  # of many, the best will do if they fill a list
            kth = np.partition(score[fresh], len(docs) - k, axis=1)[:, len(docs) - k]
            best = score[fresh] >= np.maximum(kth, least[fresh])[:, None]
            held = best @ left[docs].astype(np.float64)
            least[fresh] = np.where(held - left[seeds[which[fresh]]] >= self.tokens, np.maximum(kth, least[fresh]), least[fresh])
        at = np.flatnonzero(score >= least[:, None])
        row, at = np.divmod(at, len(docs))
        values, seed, near = score[row, at], which[row], docs[at]
        other = near != seeds[seed]
        self.add(seed[other], near[other], values[other])

    def bounds(self) -> np.ndarray:
        return np.searchsorted(self.seed, np.arange(self.n + 1))


class Scorer:
    """Lists of documents for seeds. Documents of one group lie together in blocks, those of much weight first, and a block that can't reach a seed's list,
    or with ``spread`` is not likely to, is left out for that seed."""

    def __init__(self, idf: np.ndarray, mean_length: float, spread: float | None = None):
        self.idf, self.mean_length, self.spread = idf, mean_length, spread
        self.scored = 0  # pairs; for tests

    def blocks(self, place: np.ndarray, group: np.ndarray, terms: np.ndarray, ends: np.ndarray, counts: np.ndarray, lengths: np.ndarray) -> Iterator[Block]:
        sizes = np.diff(ends)
        owner = np.repeat(np.arange(len(place)), sizes)
        weight = weights(terms, counts, owner, lengths, self.idf, self.mean_length)
        total = np.bincount(owner, weight, len(place))
        held = np.bincount(terms, minlength=65536)
        self.column = columns_of(frequent(held, len(place)))
        rare = np.flatnonzero(self.column < 0)
        rare = rare[np.argsort(held[rare] == 0, kind="stable")]
        self.column[rare] = -1 - np.arange(len(rare))
        self.n_rare = int((held[rare] > 0).sum())
        order = np.lexsort((place, -total, group))
        for some in np.split(order, np.flatnonzero(np.diff(group[order])) + 1):
            for rows in (some[i : i + ROWS] for i in range(0, len(some), ROWS)):
                at = runs(ends[rows], sizes[rows])
                yield Block(place[rows], terms[at], weight[at], np.repeat(np.arange(len(rows)), sizes[rows]), total[rows], int(group[rows[0]]), self.column, self.n_rare)

    def deviations(self, blocks: list[Block], seeds: np.ndarray, asked: np.ndarray, bounds: np.ndarray) -> np.ndarray:
        """How far the scores of a block stray from their mean, in deviations that terms independent of each other would have; by seeds that suit the block."""
        some = np.arange(0, len(seeds), max(1, len(seeds) // (10 * PROBES)))
        own = Questions(asked[runs(bounds[some], np.diff(bounds)[some])], np.diff(bounds)[some], self.column, self.n_rare)
        mean, variance = own.sums(blocks, 1), own.sums(blocks, 2)
        out = np.ones(len(blocks), np.float32)
        for b, block in enumerate(blocks):
            near = np.argsort(-mean[:, b], kind="stable")[:PROBES]
            off = own.scores(block, near) - mean[near, b][:, None]
            out[b] = np.sqrt((off**2).mean(axis=1).sum() / max(variance[near, b].sum(), 1e-9))
            self.scored += off.size
        return out

    def look(self, best: list[Lists], blocks: list[Block], seeds: np.ndarray, asked: np.ndarray, bounds: np.ndarray, left: np.ndarray, group: np.ndarray | None = None, weighs: np.ndarray | None = None) -> None:
        """Fill ``best``, one for each block of seeds, from ``blocks``; seed i asks for the terms from bounds[i] to bounds[i + 1] of ``asked``,
        and is of ``group[i]`` and ``weighs[i]`` in all if these are known."""
        total = np.array([b.total for b in blocks])
        likely = self.spread is not None and sum(len(b.place) for b in blocks) >= FEW
        stray = self.spread * self.deviations(blocks, seeds, asked, bounds) if likely else None
        many = np.array([len(b.place) >= ROWS // 8 for b in blocks])
        for k, mine in enumerate(best):
            a, n = k * SEED_ROWS, mine.n
            own = Questions(asked[bounds[a] : bounds[a + n]], np.diff(bounds[a : a + n + 1]), self.column, self.n_rare)
            most = reach = np.minimum(own.sums(blocks, 0), total) * 1.0001  # sums in another order may differ
            if likely:
                reach = np.minimum(most, np.where(many, own.sums(blocks, 1) + stray * np.sqrt(np.maximum(own.sums(blocks, 2), 0)), np.inf))
                if group is not None:
                    weight = weighs[a : a + n, None]
                    alike = (group[a : a + n, None] == [b.group for b in blocks]) & (weight * (1 + ALIKE) >= [b.least for b in blocks]) & (weight * (1 - ALIKE) <= total)
                    reach[alike] = most[alike]
            seen = reach <= 0
            size = 0

            def visit(b: int, some: np.ndarray) -> None:
                score = own.scores(blocks[b], some)  # noqa: B023
                mine.see(some, score, blocks[b].place, seeds[a : a + n], left)  # noqa: B023
                seen[some, b] = True  # noqa: B023
                self.scored += score.size

            fresh = np.flatnonzero(mine.floor == 0)
            if len(fresh):  # what suits a seed best comes first
                top = np.argsort(-reach[fresh], axis=1, kind="stable")[:, :2]
                for b in np.unique(top):
                    if len(some := (here := fresh[(top == b).any(axis=1)])[~seen[here, b]]):
                        visit(b, some)
                mine.cut(left)
            for b in np.argsort(-reach.mean(axis=0), kind="stable"):
                some = np.flatnonzero(~seen[:, b] & (reach[:, b] >= mine.floor))
                if not len(some):
                    continue
                visit(b, some)
                size = size or max(len(mine.seed), 1)
                if mine.waiting > size // 2:
                    mine.cut(left)
                    size = max(len(mine.seed), 1)
            if mine.waiting:
                mine.cut(left)


def groups(terms: np.ndarray, owner: np.ndarray, weight: np.ndarray, n: int, centres: np.ndarray, column: np.ndarray) -> np.ndarray:
    """The centre to which each document is nearest by angle."""
    return (matrix_of(terms, owner, weight, n, column, centres.shape[1]) @ centres.T).argmax(axis=1).astype(np.int8)


def matrix_of(terms: np.ndarray, owner: np.ndarray, weight: np.ndarray, n: int, column: np.ndarray, width: int) -> np.ndarray:
    out, at = np.zeros((n, width), np.float32), column[terms]
    out[owner[at >= 0], at[at >= 0]] = weight[at >= 0]
    return out


def centres_of(sample: np.ndarray) -> np.ndarray:
    """Unit vectors, ``GROUPS`` at most, around which the rows of ``sample`` lie. They decide what is scored together, not what is found."""
    rows = sample / np.maximum(np.linalg.norm(sample, axis=1, keepdims=True), 1e-9)
    if not len(rows):
        return np.zeros((1, sample.shape[1]), np.float32)
    centres = rows[:1]
    while len(centres) < min(GROUPS, len(rows)):
        centres = np.vstack([centres, rows[(rows @ centres.T).max(axis=1).argmin()][None]])
    for _ in range(8):
        near = (rows @ centres.T).argmax(axis=1)
        sums = np.stack([rows[near == c].sum(axis=0) for c in range(len(centres))])
        centres = np.where((near == np.arange(len(centres))[:, None]).any(axis=1)[:, None], sums / np.maximum(np.linalg.norm(sums, axis=1, keepdims=True), 1e-9), centres)
    return centres.astype(np.float32)


def numbers(rows: np.ndarray, parts: np.ndarray, firsts: np.ndarray) -> np.ndarray:
    """Places of documents in the order of the table, from the row ids that it was written with."""
    return firsts[np.searchsorted(parts, rows >> 33)] + (rows & ((1 << 33) - 1))


LISTS = "seed int, docs binary, scores binary, more boolean"


def listed(lists: Lists, first: int = 0) -> Iterator[pa.RecordBatch]:
    """A row for each seed that has a list; seeds are counted from ``first``."""
    bounds = lists.bounds()
    here = np.flatnonzero(np.diff(bounds))
    of = lambda x: pa.array([x[bounds[i] : bounds[i + 1]].tobytes() for i in here], pa.binary())
    yield pa.RecordBatch.from_arrays([pa.array((here + first).astype(np.int32)), of(lists.docs), of(lists.values), pa.array(lists.more[here])], names=["seed", "docs", "scores", "more"])


class Rounds:
    """Windows of a written table, made in rounds on the driver from lists that all tasks give."""

    def __init__(self, coded: DataFrame, window: int):
        self.coded, self.window, self.context = coded, window, coded.sparkSession.sparkContext
        n_docs, n_tokens, frequency = corpus_counts(coded)
        idf = np.zeros(65536, np.float64)
        for term, n in frequency.items():
            idf[term] = np.log1p((n_docs - n + 0.5) / (n + 0.5))
        self.idf, self.mean_length = idf, n_tokens / max(n_docs, 1)
        self.scorer = self.context.broadcast(Scorer(idf, self.mean_length))
        sizes = self.sizes(n_docs, frequency).toArrow()
        order = np.argsort(sizes.column("no").to_numpy())
        self.rows, lengths, self.group, self.weighs = (sizes.column(c).to_numpy()[order] for c in ("no", "n", "group", "weighs"))
        self.left = lengths.astype(np.int64)
        self.start = np.zeros(n_docs, np.int64)
        self.parts, self.firsts = np.unique(self.rows >> 33, return_index=True)
        self.count, self.made = 0, []

    def sizes(self, n_docs: int, frequency: dict[int, int]) -> DataFrame:
        """no, n, group and weight (of all its terms) of each document. Groups are fitted on some ``SAMPLE`` documents, dealt by a hash."""
        held = np.zeros(65536, np.int64)
        held[list(frequency)] = list(frequency.values())
        often = frequent(held, n_docs)
        column, idf, mean_length = columns_of(often), self.idf, self.mean_length

        def weighed(batch: pa.RecordBatch) -> tuple[np.ndarray, np.ndarray, np.ndarray, int]:
            (terms, ends), (counts, _) = entries(batch.column("terms"), "<u2"), entries(batch.column("counts"), "<u4")
            owner = np.repeat(np.arange(batch.num_rows), np.diff(ends))
            return terms, owner, weights(terms, counts, owner, batch.column("n").to_numpy(), idf, mean_length), batch.num_rows

        table = self.coded.select("no", "n", "terms", "counts")
        some = table.filter(F.pmod(F.xxhash64("no"), F.lit(max(1, n_docs // SAMPLE))) == 0).toArrow().to_batches()
        shared = self.context.broadcast(centres_of(np.vstack([np.zeros((0, len(often)), np.float32), *(matrix_of(*weighed(b), column, len(often)) for b in some)])))

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for whole in batches:
                for batch in (whole.slice(i, ROWS) for i in range(0, whole.num_rows, ROWS)):
                    terms, owner, weight, n = weighed(batch)
                    weighs = np.bincount(owner, weight, n).astype(np.float32)
                    yield pa.RecordBatch.from_arrays([batch.column("no"), batch.column("n"), pa.array(groups(terms, owner, weight, n, shared.value, column)), pa.array(weighs)], names=["no", "n", "group", "weighs"])

        return table.mapInArrow(tidy(run), "no long, n int, group byte, weighs float")

    def keep(self, docs: np.ndarray, start: np.ndarray, length: np.ndarray, sequence: np.ndarray, offset: np.ndarray) -> None:
        self.made.append([np.asarray(x, np.int64) for x in (self.rows[docs], start, length, sequence, offset)])

    def fill_long(self) -> None:
        """A long document fills windows of its own."""
        many = self.left // self.window
        docs = np.repeat(np.arange(len(many)), many)
        at = (np.arange(len(docs)) - np.repeat(np.cumsum(many) - many, many)) * self.window
        self.keep(docs, at, np.full(len(docs), self.window), np.arange(len(docs)), np.zeros(len(docs)))
        self.start, self.left, self.count = many * self.window, self.left % self.window, len(docs)

    def unused(self, columns: list[str]) -> DataFrame:
        """place and ``columns`` of the documents that have tokens left."""
        state = self.context.broadcast((self.left > 0, self.parts, self.firsts))

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            some, parts, firsts = state.value
            for batch in batches:
                place = numbers(batch.column("no").to_numpy(), parts, firsts)
                yield pa.RecordBatch.from_arrays([pa.array(place), *batch.columns[1:]], names=["place", *batch.schema.names[1:]]).filter(pa.array(some[place]))

        kinds = {x.split()[0]: x for x in CODED.split(", ")}
        return self.coded.select("no", *columns).mapInArrow(tidy(run), ", ".join(["place long", *(kinds[c] for c in columns)]))

    def lists(self, seeds: np.ndarray, tokens: int) -> Lists:
        """The best unused documents of the whole table for each seed."""
        shared = self.context.broadcast((seeds, self.left.astype(np.int32), self.group, self.weighs[seeds], self.parts, self.firsts))
        left_over = self.coded.filter(F.col("no") >= int(self.rows[np.argmax(self.left > 0)]))

        def ask(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            seeds, _, _, _, parts, firsts = shared.value
            for batch in batches:
                place = numbers(batch.column("no").to_numpy(), parts, firsts)
                yield pa.RecordBatch.from_arrays([pa.array(place), batch.column("terms")], names=["place", "terms"]).filter(pa.array(np.isin(place, seeds)))

        asked = left_over.filter(F.col("no") <= int(self.rows[seeds.max()])).select("no", "terms").mapInArrow(tidy(ask), "place long, terms binary").toArrow()
        of = dict(zip(asked.column("place").to_pylist(), asked.column("terms").to_pylist(), strict=True))
        found = [np.frombuffer(of[int(s)], "<u2") for s in seeds]
        questions, scorer = self.context.broadcast((np.concatenate(found), np.r_[0, np.cumsum([len(t) for t in found])])), self.scorer

        def chunks(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            """Unused documents, ``CHUNK`` at a time."""
            _, left, _, _, parts, firsts = shared.value
            held: list[pa.RecordBatch] = []
            for batch in batches:
                place = numbers(batch.column("no").to_numpy(), parts, firsts)
                rest = pa.RecordBatch.from_arrays([pa.array(place), *batch.columns[1:]], names=["place", *batch.schema.names[1:]]).filter(pa.array(left[place] > 0))
                while rest.num_rows:
                    some = rest.slice(0, CHUNK - sum(b.num_rows for b in held))
                    rest = rest.slice(some.num_rows)
                    held.append(some)
                    if sum(b.num_rows for b in held) == CHUNK:
                        yield pa.concat_batches(held)
                        held = []
            if held:
                yield pa.concat_batches(held)

        def score(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            seeds, left, group, weighs, _, _ = shared.value
            best = [Lists(min(SEED_ROWS, len(seeds) - a), tokens) for a in range(0, len(seeds), SEED_ROWS)]
            for batch in chunks(batches):
                place, (terms, ends), (counts, _) = batch.column("place").to_numpy(), entries(batch.column("terms"), "<u2"), entries(batch.column("counts"), "<u4")
                blocks = list(scorer.value.blocks(place, group[place], terms, ends, counts, batch.column("n").to_numpy()))
                scorer.value.look(best, blocks, seeds, *questions.value, left, group[seeds], weighs)
            for k, mine in enumerate(best):
                yield from listed(mine, k * SEED_ROWS)

        def merge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            yield from listed(joined(batches, len(seeds), tokens, shared.value[1]))

        tasks = self.context.defaultParallelism
        lists = left_over.select("no", "n", "terms", "counts").coalesce(tasks).mapInArrow(tidy(score), LISTS)
        if tasks > 32:  # else the driver merges few lists
            lists = lists.repartition(tasks, "seed").mapInArrow(tidy(merge), LISTS)
        best = joined(lists.toArrow().to_batches(), len(seeds), tokens, self.left)
        for b in (shared, questions):
            b.destroy()
        return best

    def round(self, seeds: np.ndarray, tokens: int) -> int:
        """Fill the windows of ``seeds`` one after another; how many got one."""
        order = np.argsort(self.group[seeds], kind="stable")  # those of one group are asked for together
        best, done, out, after = self.lists(seeds[order], tokens), 0, [], 0
        bounds = best.bounds()
        for i, seed in zip(np.argsort(order), seeds, strict=True):
            if not self.left[seed]:
                continue
            near = best.docs[bounds[i] : bounds[i + 1]]
            near = near[self.left[near] > 0]
            free = self.window - self.left[seed]
            ends = np.cumsum(self.left[near])
            if free and best.more[i] and (not len(near) or ends[-1] < free):
                continue  # its next best are not in the list
            take = [seed, *near[: int(np.searchsorted(ends, free)) + 1].tolist()] if free else [seed]
            if free and (not len(near) or ends[-1] < free):  # no neighbour is left: the next documents
                used, held = set(take), int(self.left[take].sum())
                while after < len(self.left) and not self.left[after]:
                    after += 1
                at = after
                while held < self.window and at < len(self.left):
                    if self.left[at] and at not in used:
                        take.append(at)
                        held += int(self.left[at])
                    at += 1
            offset = 0
            for d in take:
                n = min(self.window - offset, int(self.left[d]))
                out.append((d, self.start[d], n, self.count, offset))
                self.start[d] += n
                self.left[d] -= n
                offset += n
            self.count, done = self.count + 1, done + 1
        self.keep(*(np.array(x, np.int64) for x in zip(*out, strict=True)))
        return done

    def rest(self) -> None:
        """Pack what is left with one index."""
        shared = self.context.broadcast((self.start, self.left))
        window, idf, mean_length = self.window, self.idf, self.mean_length

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            rows = sorted((r for b in batches for r in zip(*(b.column(c).to_pylist() for c in ("place", "n", "terms", "counts")), strict=True)), key=lambda r: r[0])
            if not rows:
                return
            place = np.array([r[0] for r in rows])
            index = Index([], idf, mean_length, [(np.frombuffer(t, "<u2"), np.frombuffer(c, "<u4")) for *_, t, c in rows], np.array([r[1] for r in rows]))
            out = []
            for k, pieces in enumerate(pack_rest(index, window, shared.value[0][place], shared.value[1][place])):
                offset = 0
                for d, s, n in pieces:
                    out.append((place[d], s, n, k, offset))
                    offset += n
            yield pa.RecordBatch.from_arrays([pa.array(np.array(c, np.int64)) for c in zip(*out, strict=True)], names=["place", "start", "length", "sequence", "offset"])

        got = self.unused(["n", "terms", "counts"]).repartition(1).mapInArrow(tidy(run), "place long, start long, length long, sequence long, offset long").toArrow()
        place, start, length, sequence, offset = (got.column(i).to_numpy() for i in range(5))
        self.keep(place, start, length, sequence + self.count, offset)


def joined(batches: Iterable[pa.RecordBatch], n: int, tokens: int, left: np.ndarray) -> Lists:
    """Lists of all tasks as one."""
    best = Lists(n, tokens)
    for batch in batches:
        (docs, ends), (values, _) = entries(batch.column("docs"), "<i8"), entries(batch.column("scores"), "<f4")
        seed = batch.column("seed").to_numpy().astype(np.int64)
        best.add(np.repeat(seed, np.diff(ends)), docs, values)
        best.more[seed] |= batch.column("more").to_numpy(zero_copy_only=False)
    best.cut(left)
    return best


def packed(docs: DataFrame, vocabulary: str, window: int = 4096, end_id: int = 2, id_col: str = "doc_id", text_col: str = "text", shard_tokens: int = SHARD_TOKENS) -> DataFrame:
    """Pack all documents: one row per piece (doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset).

    Neighbours are the best of the whole table: blocks are left out by exact bounds alone. The last sequence alone may be shorter
    than ``window``. Null or empty texts hold the end id. Repeated rows are documents
    of their own. Other columns are ignored; an empty table gives no rows. Up to
    ``shard_tokens`` tokens are packed by one task. The driver holds two numbers a
    document, and five a piece; the cost of the lists grows with the square of the table.
    """
    spark = docs.sparkSession
    coded = written(encoded(docs, vocabulary, end_id, id_col, text_col).withColumn("no", F.monotonically_increasing_id()), "packing-ids")
    work = Rounds(coded, window)
    if not len(work.left):
        return spark.createDataFrame([], PIECES)
    work.fill_long()
    most = max(SEEDS, min(MOST_SEEDS, int(work.left.sum()) // window // SHARE))
    seeds, slack = most, SLACK
    while (tokens := int(work.left.sum())) > shard_tokens:
        first = np.flatnonzero(work.left)[: max(64, min(seeds, tokens // window // 4))]
        done = work.round(first, slack * window)
        # copies of one document ask for the same ones: fewer seeds with longer lists then
        if done < len(first) // 2 and seeds > 128:
            seeds, slack = seeds // 2, slack * 2
        elif done > len(first) * 3 // 4 and seeds < most:
            seeds, slack = seeds * 2, slack // 2
    if tokens:
        work.rest()
    made = pa.table([pa.array(np.concatenate(c)) for c in zip(*work.made, strict=True)], names=["no", "start", "length", "sequence", "offset"])
    pieces = spark.createDataFrame(made).groupBy("no").agg(F.collect_list(F.struct("start", "length", "sequence", "offset")).alias("pieces"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = []
            for name, n, blob, some in zip(*(batch.column(c).to_pylist() for c in ("doc_id", "n", "ids", "pieces")), strict=True):
                ids = np.frombuffer(blob, "<u2").astype("<u4")
                out += [(name, p["start"], p["length"], zlib.crc32(ids[p["start"] : p["start"] + p["length"]].tobytes()), n, p["sequence"], p["offset"]) for p in some]
            yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in zip(*out, strict=True)] if out else [pa.array([], pa.int64())] * 7, names=[x.split()[0] for x in PIECES.split(", ")])

    return coded.select("no", "doc_id", "n", "ids").join(pieces, "no").select("doc_id", "n", "ids", "pieces").mapInArrow(tidy(run), PIECES)
