"""Algebra of the sketches: forms that must agree, and edges."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from binsketch.functions import permute
from binsketch.functions.permute import Affine, Digest, Feistel, Hash64, Identity
from binsketch.operators import codes, estimate, lsh, sets, sketch

D = 1 << 12
P = Affine(D, 1140671485, 99)


@pytest.fixture(scope="module")
def rows(spark):
    r = np.random.default_rng(5)
    data = [(i, int(e)) for i in range(30) for e in r.choice(D, r.integers(1, 200))]
    return spark.createDataFrame(data + data[:50], "set_id long, elem long").cache()


def as_set(df):
    return set(map(tuple, df.collect()))


def test_merge_coarsen_and_stripes(rows):
    raw = sketch.bin_minima(rows, P, 256, reindex=False)
    assert as_set(sketch.coarsen(raw, D, 256, 32)) == as_set(sketch.bin_minima(rows, P, 32))
    a, b = rows.filter("elem % 2 = 0"), rows.filter("elem % 2 = 1")
    merged = sketch.merge(sketch.bin_minima(a, P, 64), sketch.bin_minima(b, P, 64))
    assert as_set(merged) == as_set(sketch.bin_minima(rows, P, 64))
    assert as_set(sketch.striped(rows, [P], 64)) == as_set(sketch.bin_minima(rows, P, 64))
    one_bin_each = as_set(sketch.striped(rows, [P, Digest(D, 3)], 2))
    assert one_bin_each == as_set(sketch.classic(rows, [P, Digest(D, 3)]))


def test_row_local_form_equals_long_form(rows, spark):
    wide = rows.groupBy("set_id").agg(F.collect_list("elem").alias("elems"))
    local = sketch.bin_minima_rows(wide, P, 64)
    assert as_set(sketch.long(local)) == as_set(sketch.bin_minima(rows, P, 64))
    assert "Exchange" not in sketch.bin_minima_rows(spark.range(3).select(F.col("id").alias("set_id"), F.array("id").alias("elems")), P, 64)._jdf.queryExecution().executedPlan().toString()
    empty = spark.createDataFrame([(1, []), (2, None)], "set_id long, elems array<long>")
    assert all(v is None for r in sketch.bin_minima_rows(empty, P, 64).collect() for v in r.offsets)
    back = sketch.wide(sketch.bin_minima(rows, P, 64), 64)
    assert as_set(sketch.long(back)) == as_set(sketch.bin_minima(rows, P, 64))


def test_permuters(spark):
    ids = spark.range(1 << 10).select(F.col("id").alias("x"))
    for p in (Feistel(10, 1), Feistel(11, 9), Affine(1 << 10, 5, 3)):
        assert ids.select(p.pos(F.col("x")).alias("p")).distinct().count() == 1 << 10
        assert permute.from_json(permute.to_json(p)) == p
    v = permute.permutation_vector(spark, 100, 4)
    assert v.select("pos").distinct().count() == 100
    assert permute.permutation_matrix(spark, 16, [1, 2]).count() == 32
    with pytest.raises(ValueError):
        Affine(1 << 10, 4, 0)
    with pytest.raises(ValueError):
        permute.permutation_vector(spark, 1 << 21, 1)


def test_whole_64_bit_universe(spark):
    rows = spark.createDataFrame([(1, -5), (1, 7), (2, -(1 << 63)), (2, (1 << 63) - 1)], "set_id long, elem long")
    got = sketch.bin_minima(rows, Hash64(3), 16)
    assert got.count() == got.select("set_id", "bin").distinct().count() and got.filter("bin < 0 or bin > 15").count() == 0
    with pytest.raises(ValueError):
        sketch.bin_minima(rows, Hash64(3), 12)


def test_codes(rows):
    sk = sketch.bin_minima(rows, P, 64)
    c8 = codes.low_bits(sk, 8)
    assert as_set(codes.low_bits(c8, 3)) == as_set(codes.low_bits(sk, 3))
    assert as_set(codes.from_binary(codes.to_binary(codes.low_bits(sk, 5), 64, 5), 64, 5)) == as_set(codes.low_bits(sk, 5))
    noisy = codes.noise(codes.low_bits(sk, 2), 64, 2, 7)
    assert noisy.count() == 64 * 30 and as_set(noisy) == as_set(codes.noise(codes.low_bits(sk, 2), 64, 2, 7))
    v = {r.set_id: r.features for r in codes.to_vectors(codes.low_bits(sk, 2), 64, 2).collect()}
    long = {(r.set_id, r.idx): r.val for r in codes.expand_long(codes.blank(codes.low_bits(sk, 2)), 2).collect()}
    assert {(i, int(j)): pytest.approx(x) for i, f in v.items() for j, x in zip(f.indices, f.values)} == long


def test_estimates_of_equal_disjoint_and_empty(spark):
    rows = spark.createDataFrame([(1, 3), (1, 9), (2, 3), (2, 9), (3, 4000)], "set_id long, elem long")
    pairs = spark.createDataFrame([(1, 2), (1, 3), (8, 9)], "i long, j long")
    sk = sketch.bin_minima(rows, Identity(D), 16)
    got = {(r.i, r.j): (r.u, r.s) for r in estimate.pair_counters(sk, pairs, 16).select("i", "j", estimate.unbiased(16).alias("u"), estimate.separable(16).alias("s")).collect()}
    assert got == {(1, 2): (1.0, 1.0), (1, 3): (0.0, 0.0), (8, 9): (None, None)}
    exact = {(r.i, r.j): r.r_exact for r in estimate.pair_resemblance(rows, pairs).collect()}
    assert exact == {(1, 2): 1.0, (1, 3): 0.0, (8, 9): None}


def test_all_pairs_with_prefixes_loses_none(rows):
    every = {(r.i, r.j) for r in estimate.all_pairs(rows).filter("r_exact >= 0.1").collect()}
    assert {(r.i, r.j) for r in estimate.all_pairs(rows, 0.1).collect()} == every


def test_search_policies(rows):
    sk = sketch.bin_minima(rows, P, 64)
    skip, kept = lsh.build_index(sk, 2, 4, 16), lsh.build_index(sk, 2, 4, 16, "sentinel")
    assert skip.count() <= kept.count()
    assert 0 <= lsh.skipped_share(skip, sk, 16).first().skipped <= 1
    wide = lsh.build_index(sk, 8, 16, 4, "sentinel")
    assert wide.count() == wide.select("table_no", "set_id").distinct().count()
    with pytest.raises(ValueError):
        lsh.build_index(sk, 2, 4, 16, "other")


def test_texts(spark):
    t = spark.createDataFrame([(1, None), (2, ""), (3, "One two"), (4, "Où est l'Île 42")], "id long, text string")
    got = {r.id: (r.w, r.s) for r in t.select("id", sets.tokens(F.col("text")).alias("w"), sets.shingles(sets.tokens(F.col("text")), 3).alias("s")).collect()}
    assert got[1] == ([], []) and got[2] == ([], []) and got[3] == (["one", "two"], [])
    assert got[4] == (["où", "est", "l", "île", "42"], ["où est l", "est l île", "l île 42"])


def test_components(spark):
    from binsketch.operators.components import components

    edges = [(5, 4), (4, 3), (3, 2), (2, 1), (9, 8), (8, 8), (7, 9), (20, 30)] + [(100, 100 + i) for i in range(50)]
    got = {r.node: r.component for r in components(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert {got[i] for i in range(1, 6)} == {1} and {got[i] for i in (7, 8, 9)} == {7} and got[30] == 20 and got[149] == 100
    assert components(spark.createDataFrame([], "a long, b long")).count() == 0


def test_pipeline_stage_is_saved(spark, tmp_path):
    from pyspark.ml import Pipeline, PipelineModel

    from binsketch.operators.ml import BinMinTransformer

    df = spark.createDataFrame([(1, [5, 6, 7]), (2, []), (3, None)], "set_id long, e array<long>")
    model = Pipeline(stages=[BinMinTransformer(inputCol="e", outputCol="v", k=16, b=2)]).fit(df)
    model.write().overwrite().save(str(tmp_path / "m"))
    a, b = model.transform(df).collect(), PipelineModel.load(str(tmp_path / "m")).transform(df).collect()
    assert a == b and a[1].v.numNonzeros() == 0


def components_of(df):
    """Sets of nodes that pairs connect."""
    at = {}
    for i, j in df.select("i", "j").collect():
        both = at.get(i, {i}) | at.get(j, {j})
        at.update(dict.fromkeys(both, both))
    return {frozenset(c) for c in at.values()}


def clusters_of(df):
    at = {}
    for r in df.collect():
        at.setdefault(r.cluster, set()).add(r.set_id)
    return {frozenset(c) for c in at.values()}


def test_clusters_do_not_depend_on_bucket_heads(spark):
    """Unrelated smallest sets, chains and copies in the buckets: as all verified pairs of a bucket connect."""
    r = np.random.default_rng(8)
    data = {1: set(range(1000, 1100)), 2: set(range(100)), 3: set(range(5, 105)), 4: set(range(40, 140)), 5: set(range(5, 105)), 6: set(range(2000, 2100)), 7: set(range(2020, 2110))}
    data |= {10 + i: set(range(50 * i, 50 * i + 140)) | set(r.integers(9000, 9900, 3).tolist()) for i in range(30)}
    index = [(0, 7, i) for i in range(1, 8)] + [(1, 9, i) for i in (1, 6, 7)] + [(2, i % 3, i) for i in range(10, 40)] + [(3, 0, i) for i in range(10, 40)]
    sets_ = spark.createDataFrame([(i, e) for i, x in data.items() for e in map(int, x)], "set_id long, elem long")
    index = spark.createDataFrame(index, "table_no int, bucket long, set_id long")
    want = estimate.pair_resemblance(sets_, lsh.near_pairs(index)).filter("r_exact >= 0.4")
    got = lsh.clusters(lsh.linked_pairs(index, sets_, 0.4))
    assert clusters_of(got) == components_of(want) and frozenset({6, 7}) in clusters_of(got)


def test_lsh_clusters_hold_all_verified_pairs(spark, sf):
    from binsketch.plans import search
    from binsketch.plans.base import doc_shingles
    from binsketch.session import ship

    ship(spark)
    sh = doc_shingles(spark, sf).cache()
    cluster = {r.set_id: r.cluster for r in search.lsh_clusters(spark, sf).collect()}
    pairs = estimate.pair_resemblance(sh, lsh.near_pairs(search.doc_index(spark, sf))).filter("r_exact >= 0.5").collect()
    assert pairs and all(cluster[r.i] == cluster[r.j] for r in pairs)


def test_sets_without_a_band_are_found(spark):
    """Copies and near copies of every size, down to one element."""
    from binsketch.functions.permute import Digest

    r = np.random.default_rng(3)
    data, n = {}, 0
    for f in (1, 2, 3, 5, 10, 20, 40, 80, 160):
        base = r.choice(D, f, replace=False).tolist()
        for drop in (0, 0, f // 5):
            data[n], n = base[drop:], n + 1
    sets_ = spark.createDataFrame([(i, int(e)) for i, x in data.items() for e in x], "set_id long, elem long")
    index = lsh.build_index(sketch.bin_minima(sets_, Digest(D, 7), 128), 4, 4, 32)
    assert index.filter("set_id < 12").count() == 0
    got = lsh.clusters(lsh.linked_pairs(index.unionByName(lsh.short_index(index, sets_, 32, 0.5)), sets_, 0.5))
    assert clusters_of(got) == components_of(estimate.all_pairs(sets_).filter("r_exact >= 0.5")) and len(clusters_of(got)) == 9


def test_lsh_clusters_hold_short_documents(spark, tmp_path):
    from binsketch.plans import search
    from binsketch.session import ship

    ship(spark)
    texts = ["one two three", "one two three", "a b c d e f g", "a b c d e f g", "x a b c d e f g", "alone in the world", None]
    spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    assert {(r.set_id, r.cluster) for r in search.lsh_clusters(spark, str(tmp_path)).collect()} == {(0, 0), (1, 0), (2, 2), (3, 2), (4, 2)}


def test_classic_hashes_each_element_once_a_batch(spark, monkeypatch):
    """Minima by batches equal those by columns, for numbers and names of sets, nulls and sets over several batches; no aggregate for each permutation."""
    from binsketch.functions.permute import Affine, Universal
    from binsketch.operators import sketch as operators

    rows = spark.createDataFrame([(i % 7, (i * i * 31 + i) % 90 if i % 11 else None) for i in range(400)] + [(9, None), (None, 4)], "set_id long, elem long").repartition(3)
    monkeypatch.setattr(operators, "ROWS", 16)
    for permuters in ([Digest(1 << 24, j) for j in range(5)], [Affine(1 << 24, 2 * j + 1, 77 * j) for j in range(9)], [Universal(1 << 24, 15 + j, j) for j in range(3)]):
        for sets_ in (rows, rows.selectExpr("concat('s', set_id) as set_id", "elem")):
            got, want = operators.classic(sets_, permuters), operators.classic_columns(sets_, permuters).filter("offset is not null")
            assert got.dtypes == want.dtypes and sorted(map(str, got.collect())) == sorted(map(str, want.collect()))
    assert "min(" not in got._jdf.queryExecution().executedPlan().toString()


def test_classic_minima_of_affine_permutations(spark):
    """High bits of 32-bit products are the positions; no element is looked up or divided, and minima are those of plain columns."""
    r = np.random.default_rng(3)
    for size in (1 << 10, 1 << 24, 1 << 30):
        many = [Affine(size, int(r.integers(0, size // 2)) * 2 + 1, int(r.integers(0, size))) for _ in range(37)]
        elems, starts = r.integers(0, size, 500), np.array([0, 1, 7, 300])
        want = np.stack([np.minimum.reduceat(p.numpy(elems), starts) for p in many], axis=1)
        assert np.array_equal(sketch.affine_minima(many, elems, starts), want)
    rows = [(i % 40, int(r.integers(0, 1 << 24))) for i in range(2000)] + [(3, None), (77, None)]
    df = spark.createDataFrame(rows, "set_id long, elem long")
    many = [Affine(1 << 24, 2 * j + 1, 7 * j) for j in range(1, 30)]
    got = sorted(map(tuple, sketch.classic(df, many).collect()))
    assert got == sorted(tuple(x) for x in sketch.classic_columns(df, many).filter("offset is not null").collect()) and len(got) == 40 * 29
