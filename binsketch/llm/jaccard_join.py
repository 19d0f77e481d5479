"""Exact self-join of word-shingle sets at a Jaccard similarity of 0.8 or more.

Sets are ordered rare shingles first, and sets that link share a shingle of their
prefixes. The entries of an inverted list lie in blocks by size and by the shared
shingle's position in the set; a block pair whose sizes are too far apart, or
which leaves too little of either set behind its first position, is skipped as a
whole. In a long list, most sets are answers of its first one, which has least of
its own: each is compared with that one, and from those answers the rest follows,
since one minus the similarity is a metric: sets already connected need no
comparison, and sets whose distances to the first differ by more than 0.2 can't
link. Lists of shingles known to be frequent never meet in one task.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators.components import components
from .common import map_batches, parts_for, scratch, texts_of, tidy, written
from .shingles import fingerprint, mixed, shingle_sets

#: Lists up to this long are compared block by block; entries of a block; a frequent shingle's list is dealt out in parts of so many sets.
SHORT_LIST, BLOCK, PART = 32, 4, 8192
COMMON_LOCAL, COMMON_CHUNK, MOST_COMMON = 2, 2_000_000, 1 << 18
MOST_BROADCAST_IDS = 1_000_000
SPREAD, FAR = 128, 0.2001  # bins of a set; width of a distance band, a little over 0.2
#: A pair to compare (a, b), or an entry of a long list (hash, own, b, n, at).
PAIRS = "hash long, own int, a long, b long, n int, at int"


def least_overlap(n: np.ndarray) -> np.ndarray:
    """Shingles that a set of n must share with a linked one at least: ceil(0.8 n)."""
    return (4 * n + 4) // 5


def set_table(docs: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(id, n, f1, f2, spread) of each row, and (hash, n) of shingles that are common within some stretch of the corpus.

    The second only orders shingles; a stretch counts equal sets once.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[np.ndarray] = []
        seen: set[tuple[int, int]] = set()
        size = 0

        def common() -> pa.RecordBatch:
            values, n = np.unique(np.concatenate(held) if held else np.empty(0, np.uint64), return_counts=True)
            far = np.flatnonzero(n >= COMMON_LOCAL)
            return row_batch(values[far].view(np.int64), n[far], None, None, None)

        for batch in (b.slice(i, 512) for b in batches for i in range(0, b.num_rows, 512)):
            sets = shingle_sets(texts_of(batch, "text"))
            prints = [fingerprint(s) for s in sets]
            yield row_batch(batch.column("doc_id"), [len(s) for s in sets], [p[0] for p in prints], [p[1] for p in prints], [spread(s) for s in sets])
            for s, p in zip(sets, prints, strict=True):
                if p not in seen:
                    seen.add(p)
                    held.append(s)
                    size += len(s)
            if size >= COMMON_CHUNK:
                yield common()
                held, seen, size = [], set(), 0
        yield common()

    both = written(docs.select("doc_id", "text").mapInArrow(tidy(run), "id long, n long, f1 long, f2 long, spread binary"), "shingle-sets")
    return both.filter("f1 is not null"), both.filter("f1 is null").groupBy(F.col("id").alias("hash")).agg(F.sum("n").alias("n"))


def row_batch(ids, n, f1, f2, bins) -> pa.RecordBatch:
    size = len(ids)
    cols = [c if isinstance(c, pa.Array) else pa.array(c if c is not None else [None] * size, pa.int64()) for c in (ids, n, f1, f2)]
    return pa.RecordBatch.from_arrays([*cols, pa.array(bins if bins is not None else [None] * size, pa.binary())], names=["id", "n", "f1", "f2", "spread"])


def spread(s: np.ndarray) -> bytes:
    """How many shingles fall in each of SPREAD bins (255: or more): two sets share at most the sum of the lesser counts."""
    return np.minimum(np.bincount((s >> np.uint64(64 - SPREAD.bit_length() + 1)).astype(np.int64), minlength=SPREAD), 255).astype(np.uint8).tobytes()


def possible(pairs: DataFrame, sets: DataFrame) -> DataFrame:
    """Pairs that the bound by bins leaves; no link is lost, and most others go without their texts being read."""
    of = lambda c: sets.select(F.col("id").alias(c), F.col("n").alias(f"n_{c}"), F.col("spread").alias(f"s_{c}")).dropDuplicates([c, f"s_{c}"])
    both = pairs.select("a", "b").join(of("a"), "a").join(of("b"), "b")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            x, y = (np.frombuffer(b"".join(batch.column(c).to_pylist()), np.uint8).reshape(-1, SPREAD) for c in ("s_a", "s_b"))
            n_a, n_b = (batch.column(c).to_numpy() for c in ("n_a", "n_b"))
            most = np.minimum(x, y).sum(axis=1, dtype=np.int64)
            full = ((x == 255) & (y == 255)).any(axis=1)
            keep = full | (9 * most >= 4 * (n_a + n_b))
            yield batch.select(["a", "b"]).filter(pa.array(keep))

    return both.mapInArrow(tidy(run), "a long, b long").distinct()


def common_order(common: DataFrame) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The most common shingles (sorted), each one's place among them from rare to common, and how many sets have it at least;
    at most MOST_COMMON reach the driver."""
    rows = common.orderBy(F.desc("n"), "hash").limit(MOST_COMMON).toArrow()
    hashes = rows.column("hash").to_numpy().view(np.uint64)
    order = np.argsort(hashes)
    return hashes[order], (len(hashes) - np.arange(len(hashes)))[order], rows.column("n").to_numpy()[order]


def prefix(s: np.ndarray, common: np.ndarray, place: np.ndarray) -> tuple[np.ndarray, int]:
    """The first n - ceil(0.8 n) + 1 shingles: rare ones by hash, then common ones, the commonest last; and how many are rare."""
    p = len(s) - int(least_overlap(np.int64(len(s)))) + 1
    at = np.searchsorted(common, s)
    at[at == len(common)] = 0
    is_common = common[at] == s if len(common) else np.zeros(len(s), bool)
    rare = s[~is_common]
    own, rare = len(rare), rare[:p]
    if len(rare) < p:
        rest = np.flatnonzero(is_common)
        rare = np.r_[rare, s[rest[np.argsort(place[at[rest]], kind="stable")][: p - len(rare)]]]
    return rare, own


def postings(docs: DataFrame, order: tuple[np.ndarray, np.ndarray, np.ndarray]) -> DataFrame:
    """route, hash, own, n, id, at: one row per shingle of a prefix; own: how many rare shingles the set has; route: the hash,
    or for a frequent shingle one of several, by the id."""
    frequent = order[2] > PART
    shared = docs.sparkSession.sparkContext.broadcast((*order[:2], order[0][frequent], order[2][frequent] // PART + 1))

    def run(batch):
        common, place, often, parts = shared.value
        sets = shingle_sets(texts_of(batch))
        found = [prefix(s, common, place) if len(s) else (s, 0) for s in sets]
        keys, own = [k for k, _ in found], [o for _, o in found]
        sizes = np.array([len(k) for k in keys])
        ids = np.repeat(batch.column("doc_id").to_numpy(zero_copy_only=False).astype(np.int64), sizes)
        at = np.arange(sizes.sum()) - np.repeat(np.r_[0, np.cumsum(sizes)[:-1]], sizes)
        hashes = np.concatenate(keys)
        route = hashes.copy()
        hot = np.flatnonzero(np.isin(hashes, often)) if len(often) else []
        if len(hot):
            route[hot] = mixed(hashes[hot] + mixed(ids[hot].view(np.uint64)) % parts[np.searchsorted(often, hashes[hot])].astype(np.uint64))
        yield {"route": route.view(np.int64), "hash": hashes.view(np.int64), "own": np.repeat(own, sizes).astype(np.int32), "n": np.repeat([len(s) for s in sets], sizes).astype(np.int32), "id": ids, "at": at.astype(np.int32)}

    return map_batches(docs.filter("doc_id is not null"), run, "route long, hash long, own int, n int, id long, at int")


def may_link(n_a, at_a, n_b, at_b):
    """By size, and by what is left of both sets behind a shared place (it holds for a link's first shared shingle)."""
    least = -(-4 * (n_a + n_b) // 9)
    return (4 * np.maximum(n_a, n_b) <= 5 * np.minimum(n_a, n_b)) & (np.minimum(n_a - at_a, n_b - at_b) >= least)


def band(n: np.ndarray) -> np.ndarray:
    """Sizes that may link lie in one band or in neighbouring ones."""
    return np.floor(np.log(n) / np.log(1.25)).astype(np.int64)


def within(counts: np.ndarray) -> np.ndarray:
    """0, 1, .. for each of some counts, one after another."""
    return np.arange(counts.sum()) - np.repeat(np.cumsum(counts) - counts, counts)


def block_pairs(list_of: np.ndarray, n: np.ndarray, at: np.ndarray) -> tuple[np.ndarray, np.ndarray, int]:
    """Places (i, j) of entries of one list that may link, over many lists at once (``list_of`` ascends), and how many pairs were looked at.

    A list's entries are ordered by size band, then by position; BLOCK of a band are a block. Block pairs go
    as a whole if the sizes are too far apart or the first position of either leaves too little behind it.
    """
    order = np.lexsort((at, band(n), list_of))
    lists, n, at, bands = list_of[order], n[order].astype(np.int64), at[order].astype(np.int64), band(n[order])
    fresh = np.flatnonzero(np.r_[True, (lists[1:] != lists[:-1]) | (bands[1:] != bands[:-1])])
    sizes = np.diff(np.r_[fresh, len(lists)])
    per = -(-sizes // BLOCK)
    start = np.repeat(fresh, per) + within(per) * BLOCK
    end = np.minimum(start + BLOCK, np.repeat(fresh + sizes, per))
    low, high, first = np.minimum.reduceat(n, start), np.maximum.reduceat(n, start), at[start]
    owner = lists[start]
    partners = np.searchsorted(owner, owner, "right") - np.arange(len(owner))
    x = np.repeat(np.arange(len(owner)), partners)
    y = x + within(partners)
    keep = (4 * np.maximum(low[x], low[y]) <= 5 * np.minimum(high[x], high[y])) & (9 * first[x] <= 5 * high[x] - 4 * low[y]) & (9 * first[y] <= 5 * high[y] - 4 * low[x])
    x, y = x[keep], y[keep]
    width = end[y] - start[y]
    counts = (end[x] - start[x]) * width
    nth, width = within(counts), np.repeat(width, counts)
    i, j = np.repeat(start[x], counts) + nth // width, np.repeat(start[y], counts) + nth % width
    once = i < j
    i, j = i[once], j[once]
    ok = may_link(n[i], at[i], n[j], at[j])
    return order[i[ok]], order[j[ok]], len(i)


def listed_pairs(lists: DataFrame, order: tuple[np.ndarray, np.ndarray, np.ndarray]) -> DataFrame:
    """Pairs to compare, of lists up to SHORT_LIST; the entries of longer lists, and of frequent shingles' lists, as they are.

    Rows come sorted by hash; SHORT_LIST entries are held from batch to batch at most.
    """
    often = lists.sparkSession.sparkContext.broadcast(order[0][order[2] > PART].view(np.int64))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = ("hash", "own", "n", "id", "at")
        held, long = [np.empty(0, np.int64)] * len(names), None  # the last list so far, or the hash of a long one

        def told(h, own, n, ids, at) -> pa.RecordBatch:
            """Whole lists, or parts of long ones."""
            fresh = np.flatnonzero(np.r_[True, h[1:] != h[:-1]])
            sizes = np.diff(np.r_[fresh, len(h)])
            far = np.repeat((sizes > SHORT_LIST) | np.isin(h[fresh], often.value) | (h[fresh] == long if long is not None else False), sizes)
            near = np.flatnonzero(~far & np.repeat(sizes > 1, sizes))
            i, j, _ = block_pairs(h[near].view(np.uint64), n[near], at[near]) if len(near) else (near, near, 0)
            a, b = ids[near[i]], ids[near[j]]
            a, b = np.minimum(a, b)[a != b], np.maximum(a, b)[a != b]
            none, far = [None] * len(a), np.flatnonzero(far)
            cols = [*none, *h[far].tolist()], [*none, *own[far].tolist()], [*a.tolist(), *[None] * len(far)], np.r_[b, ids[far]], [*none, *n[far].tolist()], [*none, *at[far].tolist()]
            return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, (pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int32(), pa.int32()), strict=True)], names=[x.split()[0] for x in PAIRS.split(", ")])

        for batch in batches:
            cols = [np.r_[o, batch.column(c).to_numpy().astype(np.int64)] for o, c in zip(held, names, strict=True)]
            if not len(cols[0]):
                continue
            last = cols[0][-1]
            cut = int(np.flatnonzero(np.r_[True, cols[0][1:] != cols[0][:-1]])[-1])
            if len(cols[0]) - cut > SHORT_LIST or last == long:  # a long list isn't held
                yield told(*cols)
                held, long = [c[:0] for c in cols], last
            else:
                if cut:
                    yield told(*(c[:cut] for c in cols))
                held, long = [c[cut:] for c in cols], None
        if len(held[0]):
            yield told(*held)

    return lists.mapInArrow(tidy(run), PAIRS)


def some_docs(docs: DataFrame, ids: DataFrame, how: str) -> DataFrame:
    """Rows of docs whose id is in ``ids`` (left_semi) or not (left_anti); ids are broadcast up to a checked size, joined beyond it."""
    return docs.join(F.broadcast(ids) if ids.count() <= MOST_BROADCAST_IDS else ids, "doc_id", how)


def compared(docs: DataFrame, pairs: DataFrame) -> DataFrame:
    """a, b, shared, union of each pair, from the whole texts.

    Shingles are compared by 64-bit hashes: that a pair of sets of n shingles in all is counted
    wrongly has a chance of less than n^2 / 2^65 (3e-8 for a million shingles).
    """
    ids = written(pairs.select(F.col("a").alias("doc_id")).union(pairs.select("b")).distinct(), "compared-ids")
    texts = some_docs(docs.select("doc_id", "text"), ids, "left_semi")
    left = pairs.join(texts.select(F.col("doc_id").alias("b"), F.col("text").alias("text_b")), "b")
    both = left.join(texts.select(F.col("doc_id").alias("a"), F.col("text").alias("text_a")), "a")

    def run(batch):
        a_ids, last, sets_a = batch.column("a").to_pylist(), None, []
        texts_a = batch.column("text_a")
        for k, i in enumerate(a_ids):  # neighbours often have the same a
            if i != last:
                last, one = i, shingle_sets([texts_a[k].as_py() or ""])[0]
            sets_a.append(one)
        sets_b = shingle_sets(texts_of(batch, "text_b"))
        shared = [len(np.intersect1d(x, y, assume_unique=True)) for x, y in zip(sets_a, sets_b, strict=True)]
        yield {"a": batch.column("a"), "b": batch.column("b"), "shared": shared, "union": [len(x) + len(y) - s for x, y, s in zip(sets_a, sets_b, shared, strict=True)]}

    return written(map_batches(both.select("a", "b", "text_a", "text_b"), run, "a long, b long, shared long, `union` long"), "compared")


def links(found: DataFrame) -> DataFrame:
    return found.filter("100 * shared >= 80 * `union` and `union` > 0").select("a", "b")


def near_duplicates(docs: DataFrame) -> DataFrame:
    """One row per document: doc_id, n_shingles, component_id (smallest doc_id that it reaches by links).

    Texts without words, or null, have an empty set and stay alone. Documents of
    equal sets link and are one class, whose smallest id stands for it in the join,
    so that copies cost nothing. Rows with one doc_id count as one document
    with several texts. Other columns are ignored; an empty table gives no rows.
    """
    with scratch(docs.sparkSession) as temp:
        return temp.keep(written(_near_duplicates(docs.select("doc_id", "text")), "near-duplicates"))


def _near_duplicates(docs: DataFrame) -> DataFrame:
    sets, common = set_table(docs)
    classes = written(sets.filter("n > 0").groupBy("f1", "f2").agg(F.min("id").alias("rep"), F.count(F.lit(1)).alias("copies")), "classes")
    many = classes.filter("copies > 1").select("f1", "f2", "rep")
    copies = written(sets.join(many, ["f1", "f2"]).filter("id <> rep").select(F.col("id").alias("doc_id")).distinct(), "copies")
    ones = some_docs(docs, copies, "left_anti")
    order = common_order(common)
    lists = postings(ones, order).repartition(parts_for(ones, 2.0), "route").sortWithinPartitions("hash", "own", "n", "id")
    listed = written(listed_pairs(lists, order), "listed-pairs")
    entry = listed.filter("hash is not null").select("hash", "own", F.col("b").alias("id"), "n", "at")
    leader = entry.groupBy("hash").agg(F.min(F.struct("own", "n", "id")).alias("first")).select("hash", F.col("first.id").alias("a"))
    members = written(entry.join(leader, "hash").filter("a <> id").select("hash", "a", F.col("id").alias("b"), F.col("n").alias("n_b"), F.col("at").alias("at_b")), "list-entries")
    stars = members.select("a", "b").distinct()
    others = possible(listed.filter("hash is null").select("a", "b").distinct(), sets)
    found = compared(ones, written(stars.union(others).distinct(), "pairs"))
    edges = links(found)
    if stars.limit(1).count():
        rest = skipped_pairs(members, found, components(edges))
        edges = edges.union(links(compared(ones, written(possible(rest, sets), "pairs"))))
    parent = written(components(edges), "components")
    own = sets.join(classes.select("f1", "f2", "rep"), ["f1", "f2"], "left").select(F.col("id").alias("doc_id"), F.col("n").alias("n_shingles"), F.coalesce(F.when(F.col("n") > 0, F.col("rep")), "id").alias("rep"))
    own = written(own, "class-members")
    return own.join(parent, F.col("rep") == F.col("node"), "left").select("doc_id", "n_shingles", F.coalesce("component", "rep").alias("component_id"))


def skipped_pairs(members: DataFrame, found: DataFrame, parent: DataFrame) -> DataFrame:
    """Pairs of long lists that neither are connected yet nor are ruled out by their distances to the list's first set.

    Members meet by list, size band and distance band, each with its neighbouring bands, so that most of a list is skipped
    unseen and a long list is many keys.
    """
    parent = written(parent, "components")
    of = lambda c: parent.select(F.col("node").alias(c), F.col("component").alias(f"c_{c}"))
    member = members.join(found, ["a", "b"]).join(of("a"), "a", "left").join(of("b"), "b", "left")
    member = written(member.select("hash", F.coalesce("c_a", "a").alias("c_a"), F.coalesce("c_b", "b").alias("c"), F.col("b").alias("id"), F.col("n_b").alias("n"), F.col("at_b").alias("at"), (1 - F.col("shared") / F.col("union")).alias("d")), "list-members")
    mixed_lists = written(member.groupBy("hash").agg(F.min(F.least("c", "c_a")).alias("low"), F.max(F.greatest("c", "c_a")).alias("high")).filter("low < high").select("hash"), "mixed-lists")
    bands = {"s": F.floor(F.log("n") / F.log(F.lit(1.25))), "w": F.floor(F.col("d") / FAR)}
    open_rows = written(member.join(mixed_lists, "hash", "left_semi").withColumns(bands), "open-members")
    near = lambda c: F.explode(F.array(*[F.col(c) + k for k in (-1, 0, 1)])).alias(c)
    x, y = (open_rows.select("hash", "s", "w", *(F.col(c).alias(f"{c}_{e}") for c in ("id", "c", "n", "at", "d"))) for e in "xy")
    x = x.select("hash", near("s"), *x.columns[2:]).select("hash", "s", near("w"), *x.columns[3:])
    least = F.ceil(4 * (F.col("n_x") + F.col("n_y")) / 9)
    left = F.least(F.col("n_x") - F.col("at_x"), F.col("n_y") - F.col("at_y"))
    size = 4 * F.greatest("n_x", "n_y") <= 5 * F.least("n_x", "n_y")
    pairs = x.join(y, ["hash", "s", "w"]).filter((F.col("id_x") < F.col("id_y")) & (F.col("c_x") != F.col("c_y")) & (F.abs(F.col("d_x") - F.col("d_y")) <= 0.2 + 1e-9) & size & (left >= least))
    return written(pairs.select(F.col("id_x").alias("a"), F.col("id_y").alias("b")).distinct().join(found.select("a", "b"), ["a", "b"], "left_anti"), "skipped-pairs")
