"""Exact top-k inner products by a uniform threshold in three phases.

A vector's components are dealt to lists; a list scores a candidate by the inner
product over its own components. Each task holds the lists of its candidates,
longest part first. Phase one gathers local score lists: every list gives the
best entries of its head, and these alone are scored in full; the k-th best of
them all is a cutoff that no answer falls below. Phase two broadcasts it: an
answer must reach cutoff / lists in some list, so each list is read only as far
as its lengths allow that, and entries that fall short are dropped. Phase three
adds the scores of the remaining lists for what is left, and ranks.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import fresh_path, tidy

#: Queries of a round and their bytes (they are broadcast), queries and candidates scored together, head entries for each answer asked for.
QUERIES_AT_ONCE, QUERY_BYTES, TILE, BLOCK, HEAD = 16_384, 64_000_000, 512, 4096, 64
PAIRS_AT_ONCE, DENSE = 1 << 14, 8
NO_CUTOFF = np.iinfo(np.int64).min


def quantised(vectors: DataFrame, id_col: str = "vec_id", vector_col: str = "embedding") -> DataFrame:
    """id and whole-number components floor(256 * x); vectors null or with null or non-finite components go."""
    x = F.col(vector_col)
    sound = x.isNotNull() & F.forall(x, lambda v: v.isNotNull() & ~F.isnan(v) & (F.abs(v.cast("double")) < F.lit(float("inf"))))
    return vectors.filter(F.col(id_col).isNotNull() & F.coalesce(sound, F.lit(False))).select(F.col(id_col).cast("long").alias("vec_id"), F.transform(x, lambda v: F.floor(v.cast("double") * 256).cast("long")).alias("v"))


def matrix(column: pa.Array, width: int) -> np.ndarray:
    """Rows of a list column; missing components are 0, those beyond ``width`` meet no partner."""
    flat, offsets = np.asarray(column.flatten()), np.asarray(column.offsets)
    lengths = np.diff(offsets)
    if len(lengths) and (lengths == width).all():
        return flat.reshape(-1, width)
    out = np.zeros((len(lengths), width), np.int64)
    for i, (a, n) in enumerate(zip(offsets[:-1] - offsets[0], np.minimum(lengths, width), strict=True)):
        out[i, :n] = flat[a : a + n]
    return out


def exact(m: np.ndarray, other_top: float) -> np.ndarray:
    """As doubles where all sums stay whole in them, else as 64-bit integers."""
    top = float(np.abs(m).max(initial=0)) if m.size else 0.0
    return m.astype(np.float64) if max(top, other_top) ** 2 * max(m.shape[1], 1) < 2**53 else m


def ranked(row: np.ndarray, ids: np.ndarray, scores: np.ndarray, k: int) -> np.ndarray:
    """Places of each row's k largest scores, ties to smaller ids, row by row."""
    order = np.lexsort((ids, -scores, row))
    r = row[order]
    starts = np.flatnonzero(np.r_[True, r[1:] != r[:-1]]) if len(r) else np.zeros(0, np.int64)
    return order[np.arange(len(r)) - np.repeat(starts, np.diff(np.r_[starts, len(r)])) < k]


class Block:
    """The local score lists of some candidates. ``scored`` counts what was scored in full, ``read`` list entries."""

    def __init__(self, ids: np.ndarray, vectors: np.ndarray, lists: int):
        self.ids, self.vectors, self.scored, self.read = ids, vectors, 0, 0
        self.lists = []
        for s in np.array_split(np.arange(vectors.shape[1]), max(min(lists, vectors.shape[1]), 1)):
            part = vectors[:, s]
            length = np.sqrt((part.astype(np.float64) ** 2).sum(axis=1))
            order = np.argsort(-length, kind="stable")
            self.lists.append((s, order, length[order], np.ascontiguousarray(part[order].T)))

    def full(self, queries: np.ndarray, row: np.ndarray, at: np.ndarray) -> np.ndarray:
        """Scores of (query, candidate) pairs over all lists."""
        self.scored += len(row)
        return np.concatenate([np.zeros(0, queries.dtype), *(np.einsum("ij,ij->i", queries[row[a : a + PAIRS_AT_ONCE]], self.vectors[at[a : a + PAIRS_AT_ONCE]]) for a in range(0, len(row), PAIRS_AT_ONCE))])

    def heads(self, queries: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Phase one: query, candidate and full score of the best entries of each list's head."""
        n, rows, at = len(self.ids), [], []
        for s, order, _, columns in self.lists:
            depth = min(n, max(HEAD * k, n // 8))
            part = queries[:, s] @ columns[:, :depth]
            self.read += part.size
            few = min(k + 1, depth)
            near = np.argpartition(part, depth - few, axis=1)[:, depth - few :]
            rows.append(np.repeat(np.arange(len(queries)), few))
            at.append(order[near].ravel())
        return self.unique(queries, rows, at)

    def entries(self, queries: np.ndarray, cutoffs: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Phases two and three: the same of all entries that reach their share of the cutoff in some list."""
        rows, at, m = [], [], len(self.lists)
        for s, order, length, columns in self.lists:
            own = np.sqrt((queries[:, s].astype(np.float64) ** 2).sum(axis=1))
            least = np.where(cutoffs > 0, cutoffs / np.maximum(m * own, 1e-300), 0.0).min(initial=np.inf)
            depth = int(np.searchsorted(-length, -least * (1 - 1e-9), "right"))
            part = queries[:, s] @ columns[:, :depth]
            self.read += part.size
            row, near = np.nonzero(part * m >= cutoffs[:, None])
            rows.append(row)
            at.append(order[near])
        return self.unique(queries, rows, at)

    def unique(self, queries: np.ndarray, rows: list[np.ndarray], at: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        n = max(len(self.ids), 1)
        pairs = np.unique(np.concatenate(rows) * n + np.concatenate(at))
        row, near = pairs // n, pairs % n
        if len(pairs) * DENSE > len(queries) * n:  # so many that the product of the whole block costs less
            self.scored += len(queries) * n
            return row, near, (queries @ self.vectors.T)[row, near]
        return row, near, self.full(queries, row, near)


def top_k(vectors: DataFrame, is_query, k: int = 5, lists: int = 2, queries_at_once: int = QUERIES_AT_ONCE) -> DataFrame:
    """For each query row its k best other rows: query_id, rank (from 1), vec_id, score; all, if there are fewer.

    ``vectors`` is what ``quantised`` gives and ``is_query`` a condition on vec_id.
    Ties go to the smaller vec_id. Rows with a query's own vec_id are not its
    candidates. A vec_id that several query rows bear is one query, which ranks the
    scores of all its different vectors together; a candidate row that is there
    several times ranks as often. Equal vectors within a block are scored once and only
    their k + 1 smallest ids kept, which no answer can miss, so copies cost nothing.
    Shorter vectors count as ended by zeros. Scores must fit 64 bits. Queries are taken
    ``queries_at_once`` at a time, fewer if they are wide (that many vectors are
    broadcast), and each round's answers are written; candidates stay where they are read.
    """
    spark = vectors.sparkSession
    schema = "query_id long, vec_id long, score long"
    facts = vectors.agg(F.max(F.size("v")).alias("width"), F.count_if(is_query).alias("n"), F.max(F.array_max(F.transform("v", lambda c: F.abs(c)))).alias("top")).first()
    width, top = facts.width or 0, float(facts.top or 0)
    path = fresh_path(spark, "top-k")
    out = "query_id long, rank int, vec_id long, score long"
    rounds = -(-facts.n // max(1, min(queries_at_once, QUERY_BYTES // (8 * max(width, 1)))))
    by_query = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    for i in range(rounds):
        mine = vectors.filter(is_query & (F.pmod(F.xxhash64("vec_id"), F.lit(rounds)) == i)).dropDuplicates(["vec_id", "v"]).toArrow().combine_chunks()
        if not mine.num_rows:
            continue
        q_ids = mine.column("vec_id").to_numpy()
        queries = spark.sparkContext.broadcast((q_ids, np.concatenate([matrix(c, width) for c in mine.column("v").chunks])))
        heads = vectors.mapInArrow(tidy(_gathered(queries, None, width, top, k, lists)), schema)
        best = heads.groupBy("query_id", "vec_id").agg(F.max("score").alias("score")).withColumn("at", F.row_number().over(by_query))
        cut = {r.query_id: r.score for r in best.filter(F.col("at") == k).select("query_id", "score").collect()}
        cutoffs = spark.sparkContext.broadcast(np.array([cut.get(int(x), NO_CUTOFF) for x in q_ids], np.int64))
        found = vectors.mapInArrow(tidy(_gathered(queries, cutoffs, width, top, k, lists)), schema)
        found.withColumn("rank", F.row_number().over(by_query)).filter(F.col("rank") <= k).select("query_id", F.col("rank").cast("int").alias("rank"), "vec_id", "score").write.parquet(f"{path}/round={i}")
        queries.destroy()
        cutoffs.destroy()
    if not rounds:
        return spark.createDataFrame([], out)
    return spark.read.schema(f"{out}, round int").parquet(path).drop("round")


def _gathered(queries, cutoffs, width: int, top: float, k: int, lists: int):
    """Of each block of candidates its list heads (phase one), or with cutoffs all entries that can matter (phases two and three); the k best of a query."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        q_ids, q = queries.value
        q = exact(q, top)
        for batch in batches:
            for part in (batch.slice(i, BLOCK) for i in range(0, batch.num_rows, BLOCK)):
                ids, c = _distinct(np.asarray(part.column("vec_id")), matrix(part.column("v"), width), k)
                block, found = Block(ids, c.astype(q.dtype), lists), []
                for a in range(0, len(q_ids), TILE):
                    tile, own = q[a : a + TILE], q_ids[a : a + TILE]
                    least = np.full(len(own), NO_CUTOFF) if cutoffs is None else cutoffs.value[a : a + TILE]
                    row, at, score = block.heads(tile, k) if cutoffs is None else block.entries(tile, least)
                    fit = (ids[at] != own[row]) & (score >= least[row])
                    row, at, score = row[fit], at[fit], score[fit]
                    few = ranked(row, ids[at], score, k)
                    found.append((own[row[few]], ids[at[few]], score[few]))
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(x).astype(np.int64)) for x in zip(*found, strict=True)], names=["query_id", "vec_id", "score"])

    return run


def _distinct(ids: np.ndarray, c: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """Of equal vectors the k + 1 smallest ids, each k + 1 times at most."""
    order = np.argsort(ids, kind="stable")
    ids, c = ids[order], np.ascontiguousarray(c[order])
    if c.shape[1]:
        _, group = np.unique(c.view(np.dtype((np.void, c.dtype.itemsize * c.shape[1]))).ravel(), return_inverse=True)
    else:
        group = np.zeros(len(ids), np.int64)
    by_group = np.argsort(group, kind="stable")
    g, i = group[by_group], ids[by_group]
    fresh = np.r_[True, g[1:] != g[:-1]][: len(g)]
    new = fresh | np.r_[True, i[1:] != i[:-1]][: len(g)]
    starts, news = np.flatnonzero(fresh), np.flatnonzero(new)
    number = np.cumsum(new) - 1  # of the id, from the block's start on
    nth_id = number - np.repeat(number[starts], np.diff(np.r_[starts, len(g)]))
    nth_row = np.arange(len(g)) - np.repeat(news, np.diff(np.r_[news, len(g)]))
    keep = np.sort(by_group[(nth_id <= k) & (nth_row <= k)])
    return ids[keep], c[keep]
