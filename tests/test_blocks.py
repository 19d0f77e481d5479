"""Pairs by blocks of sets: the same as by joins, and no join or exchange of pairs."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from binsketch import registry
from binsketch.functions.permute import Affine, Digest
from binsketch.operators import blocks, codes, estimate, linear_sketch, lsh, sets, sketch, ways
from binsketch.session import ship

D, P = 1 << 24, Digest(1 << 24, 7)
COLUMNS = "n_mat int, n_both int, n_emp int, n_emp_i int, n_emp_j int, f1 long, f2 long, a long, dot long"


@pytest.fixture(scope="module")
def docs(spark):
    ship(spark)
    r = np.random.default_rng(11)
    bases = [r.integers(0, 500, r.integers(3, 400)).astype(str).tolist() for _ in range(12)]
    rows = [(n * 37 % 1009 - 300, " ".join(w for w in bases[n % 12] if r.random() > 0.03 * (n % 4))) for n in range(90)]
    return spark.createDataFrame([*rows, (2000, None), (2001, ""), (None, rows[0][1]), (rows[0][0], rows[1][1]), (2002, "one two")], "doc_id long, text string")


@pytest.mark.parametrize("block", [5, 1000])
def test_blocks_equal_joins(spark, docs, monkeypatch, block):
    monkeypatch.setattr(blocks, "FILE_SETS", 4)
    monkeypatch.setattr(blocks, "BLOCK_SETS", block)
    monkeypatch.setattr(blocks, "FOUND", 50)
    monkeypatch.setattr(blocks, "MEASURED", 7)
    own = blocks.packed(docs, "doc_id", "text", D, 3, P, 64, blocks.summed(Digest(1 << 28, 31), 32, Digest(1 << 28, 32)), elems=True)
    got = blocks.measured(own, 64, 4, 4, [blocks.counters(), blocks.exact(D), blocks.dots()], COLUMNS, "i4")
    sh = sets.word_sets(docs.filter("doc_id is not null"), "doc_id", "text", D, 3).distinct().cache()
    sk = sketch.bin_minima(sh, P, 64)
    near = lsh.near_pairs(lsh.build_index(sk, 4, 4, 16)).cache()
    want = estimate.pair_counters(sk, near, 64).join(estimate.pair_resemblance(sh, near), ["i", "j"]).join(linear_sketch.dots(linear_sketch.signed_sums(sh, Digest(1 << 28, 31), Digest(1 << 28, 32), 32), near), ["i", "j"])
    rows = sorted(map(tuple, got.collect()))
    assert len(rows) > 100 and rows == sorted(map(tuple, want.select(*got.columns).collect()))
    low = blocks.measured(own, 64, 4, 4, [blocks.counters(3)], "n_mat int", None)
    assert sorted(map(tuple, low.collect())) == sorted(map(tuple, estimate.pair_counters(codes.low_bits(sk, 2), near, 64, "code").select("i", "j", "n_mat").collect()))
    noisy = blocks.packed(docs, "doc_id", "text", D, 3, P, 64, blocks.noisy(8, 9))
    same = blocks.measured(noisy, 64, 4, 4, [blocks.equal_codes()], "n_mat int", "u1")
    filled = codes.noise(codes.low_bits(sk, 8), 64, 8, 9, portable=True)
    assert sorted(map(tuple, same.collect())) == sorted(map(tuple, estimate.pair_counters(filled, near, 64, "code").select("i", "j", "n_mat").collect()))


def test_tables_without_pairs(spark, docs):
    for some in (docs.limit(0), docs.filter("text is null")):
        own = blocks.packed(some, "doc_id", "text", D, 3, P, 64)
        assert blocks.measured(own, 64, 4, 4, [blocks.counters()], COLUMNS.split(", f1")[0]).count() == 0


@pytest.mark.parametrize("name", ["pair_counters_docs", "unbiased_estimates", "separable_estimates", "noise_estimates", "debiased_bits", "hypergeom_interval", "onehot_dot", "binsum_dot", "debiased_dot", "signed_dot"])
def test_pairs_pass_no_exchange(spark, sf, name):
    ship(spark)
    plan = registry.queries()[name](spark, sf).select(F.col("i"))._jdf.queryExecution().executedPlan().toString()
    assert "Join" not in plan and "Exchange" not in plan


@pytest.mark.parametrize("name", ["supp_similar", "part_similar", "cust_similar"])
def test_similar_sets_join_no_pairs(spark, sf, name):
    """What follows the pairs is the ranking's one exchange."""
    ship(spark)
    plan = registry.queries()[name](spark, sf)._jdf.queryExecution().executedPlan().toString()
    assert "Join" not in plan and plan.count("Exchange") == 1


@pytest.mark.parametrize("block", [60, 1000])
@pytest.mark.parametrize("min_r", [0.3, 0.8])
def test_alike_pairs_equal_joins(spark, docs, monkeypatch, block, min_r):
    """Every pair above the bound, copies too, whatever the blocks are."""
    monkeypatch.setattr(blocks, "FILE_SETS", 32)
    monkeypatch.setattr(blocks, "BLOCK_SETS", block)
    monkeypatch.setattr(blocks, "FOUND", 50)
    monkeypatch.setattr(blocks, "MEASURED", 7)
    more = docs.unionByName(docs.filter("doc_id is not null").selectExpr("doc_id + 5000 as doc_id", "text")).unionByName(docs.filter("doc_id is not null").limit(20).selectExpr("9000 - doc_id as doc_id", "text"))
    own = blocks.packed(more, "doc_id", "text", D, 3, P, 8, elems=True)
    got = blocks.measured(own, 8, 4, 4, [], "f1 long, f2 long, a long", find=blocks.alike(D, min_r))
    sh = sets.word_sets(more.filter("doc_id is not null"), "doc_id", "text", D, 3).distinct().cache()
    want = sorted(map(tuple, estimate.all_pairs(sh).filter(F.col("r_exact") >= min_r).select("i", "j", "f1", "f2", "a").collect()))
    assert len(want) > 50 and sorted(map(tuple, got.collect())) == want


@pytest.mark.parametrize("name, exchanges", [("exact_pairs_docs", 0), ("errors_by_m", 1), ("comparator_errors", 1)])
def test_true_pairs_pass_no_exchange(spark, sf, name, exchanges):
    """Sums alone are exchanged, pairs are not."""
    ship(spark)
    plan = registry.queries()[name](spark, sf)._jdf.queryExecution().executedPlan().toString()
    assert "Join" not in plan and plan.count("Exchange") == exchanges


def test_links_connect_as_pairs_do(spark, docs):
    """A task gives a forest: fewer links than pairs, the same components."""
    more = docs.unionByName(docs.filter("doc_id is not null").selectExpr("doc_id + 5000 as doc_id", "text"))
    own = blocks.packed(more, "doc_id", "text", D, 3, P, 64, elems=True)
    pairs = blocks.measured(own, 64, 4, 4, [], "a long", find=blocks.alike(D, 0.5)).cache()
    few = blocks.measured(own, 64, 4, 4, [blocks.counters()], "n_mat int", find=blocks.linked(blocks.alike(D, 0.5), lambda x, i, y, j, known: np.ones(len(i), bool))).cache()
    assert 0 < few.count() < pairs.count() / 2
    assert sorted(map(tuple, lsh.clusters(few).collect())) == sorted(map(tuple, lsh.clusters(pairs).collect()))


@pytest.mark.parametrize("size", [10, 1000])
def test_ways_equal_joins(spark, docs, monkeypatch, size):
    """Candidates of queries and pairs brought together, by way, are those of joined buckets, whatever the blocks are."""
    for module, name, n in ((blocks, "FILE_SETS", 8), (ways, "SETS", size), (ways, "QUERIES", size // 2)):
        monkeypatch.setattr(module, name, n)
    few = [Affine(D, 2 * (15_485_863 * (j + 1) % (1 << 22)) + 1, 32_452_843 * (j + 1) % D) for j in range(16)]
    settings = [(b, k, L) for b in (1, 4) for k in (4, 8) for L in (1, 2, 8)]
    grid = ways.Ways(settings, 64, len(few))
    own = blocks.packed(docs, "doc_id", "text", D, 3, P, 64, ways.classic_minima(few), elems=True)
    got = {grid.all[r.way]: r.candidates for r in ways.candidates(own, grid, "set_id % 3 = 0").collect() if r.used}
    pairs = blocks.measured(own, 64, 4, 4, [grid.shared()], "ways long", "i4", blocks.alike(D, 0.5)).collect()
    sh = sets.word_sets(docs.filter("doc_id is not null"), "doc_id", "text", D, 3).distinct().cache()
    at = ["b", "k", "tables", "table_no", "bucket"]
    want, hits = {}, {}
    for source, policy, sk, most in (("one permutation", "skip_band", sketch.bin_minima(sh, P, 64), 64), ("one permutation", "sentinel", sketch.bin_minima(sh, P, 64), 64), ("classic", "none", sketch.classic(sh, few), 16)):
        index = lsh.signatures_by(sk, spark.createDataFrame([s for s in settings if s[1] * s[2] <= most], "b int, k int, tables int"), "sentinel" if policy == "sentinel" else "skip_band")
        members = {}
        for r in index.collect():
            want.setdefault((source, policy, r.b, r.k, r.tables), set())
            members.setdefault(tuple(r[c] for c in at), []).append(r.set_id)
        for key, some in members.items():
            name = (source, policy, *key[:3])
            want[name] |= {(i, j) for i in some if i % 3 == 0 for j in some if i != j}
            hits.setdefault(name, set()).update((i, j) for i in some for j in some if i < j)
    assert got == {name: len(x) for name, x in want.items()} and sum(got.values()) > 1000
    assert len(pairs) > 50 and all({(r.i, r.j) in hits.get(w, ()) for r in pairs if r.ways >> n & 1} <= {True} for n, w in enumerate(grid.all))
    assert all(sum(r.ways >> n & 1 for r in pairs) == len({(r.i, r.j) for r in pairs} & hits.get(w, set())) for n, w in enumerate(grid.all))


def test_search_grid_joins_no_buckets(spark, sf):
    """Counts alone are joined and exchanged."""
    ship(spark)
    plan = registry.queries()["search_grid"](spark, sf)._jdf.queryExecution().optimizedPlan().toString()
    assert "bucket" not in plan and "MapInArrow" in plan
