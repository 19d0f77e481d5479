"""Experiment grids: what a task rolls up equals the sketches, learners reach their optimum, measures their definitions."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from binsketch import registry
from binsketch.functions.permute import Feistel
from binsketch.operators import cells, codes, learn, lsh, sets, sketch
from binsketch.plans import grids, search
from binsketch.session import ship
from binsketch.sources.tables import table


@pytest.fixture(scope="module")
def words(spark, sf):
    ship(spark)
    return sets.word_sets(table(spark, sf, "documents"), "doc_id", "text", 1 << 24).distinct().cache()


def test_rolled_codes_are_those_of_smaller_sketches(words):
    top = cells.collected(codes.to_binary(codes.low_bits(sketch.bin_minima(words, Feistel(24, 1), 512), 8), 512, 8), 512)
    for k in (8, 64, 512):
        small = sketch.bin_minima(words, Feistel(24, 1), k).select("set_id", "bin", F.col("offset").bitwiseAND(F.lit(255)).alias("code")).collect()
        code, filled = top.at(k, True)
        place = {int(i): n for n, i in enumerate(top.ids)}
        assert filled.sum() == len(small)
        assert all(filled[place[r.set_id], r.bin] and code[place[r.set_id], r.bin] == r.code for r in small)


def test_classic_codes_are_row_local_minima(words):
    rows = words.groupBy("set_id").agg(F.collect_list("elem").alias("elems")).orderBy("set_id").limit(5)
    got = cells.collected(cells.classic_codes(rows, 16, 3), 16)
    r = np.random.default_rng(3)
    a, b = (r.integers(0, 1 << 63, 16, dtype=np.uint64) * np.uint64(2) + np.uint64(1), r.integers(0, 1 << 63, 16, dtype=np.uint64))
    for n, row in enumerate(rows.collect()):
        e = np.array(row.elems, np.int64).view(np.uint64)
        want = ((a[:, None] * e + b[:, None]) >> np.uint64(40)).min(axis=1) & np.uint64(255)
        assert got.ids[n] == row.set_id and (got.codes[n] == want).all() and got.filled[n].all()


def test_blank_and_noise_coding():
    code, filled = np.array([[5, 0, 200], [1, 2, 3]], np.uint8), np.array([[True, False, True], [False] * 3])
    x = cells.design(code, filled, 2)
    assert x.index.tolist() == [3 - 1, 8 + 3 - 0] and x.row.tolist() == [0, 0] and x.scale.tolist() == [1 / np.sqrt(2), 1]
    y = cells.design(code, filled, 2, np.random.default_rng(1))
    assert len(y.index) == 6 and (y.index // 4 == [0, 1, 2, 0, 1, 2]).all() and y.index[0] == 2 and np.allclose(y.scale, 1 / np.sqrt(3))


@pytest.mark.parametrize("solver", ["logistic", "svm"])
def test_learners_reach_the_optimum(solver, monkeypatch):
    monkeypatch.setattr(cells, "ROUNDS", 3000)
    monkeypatch.setattr(cells, "STILL", 0.0)
    r = np.random.default_rng(2)
    x = cells.design(r.integers(0, 4, (60, 8), dtype=np.uint8), np.ones((60, 8), bool), 2)
    y = np.where(r.random(60) < 0.5, 1.0, -1.0)
    w = cells.fit(x, y, 2.0, solver)
    margin = y * x.margins(w)
    slope = -1 / (1 + np.exp(margin)) if solver == "logistic" else -np.clip((1 - margin) / cells.SMOOTH, 0, 1)
    assert np.abs(w + 2.0 * x.back(slope * y)).max() < 1e-4  # the objective's gradient


def test_measures():
    score, y = np.array([3.0, 1.0, 1.0, -2.0, -1.0]), np.array([1.0, 1.0, -1.0, -1.0, 1.0])
    accuracy, balanced, auc, majority = cells.measures(score, y)
    wins = [1.0 if a > b else 0.5 if a == b else 0.0 for a in score[y > 0] for b in score[y < 0]]
    assert (accuracy, majority) == (0.6, 0.6) and balanced == pytest.approx((2 / 3 + 1 / 2) / 2) and auc == pytest.approx(np.mean(wins))


def test_area_in_ranges(spark):
    r = np.random.default_rng(1)
    rows = [(float(r.integers(0, 2)), float(round(r.normal(), 2))) for _ in range(600)]
    df = spark.createDataFrame(rows, "label double, m double")
    want = np.mean([1.0 if a > b else 0.5 if a == b else 0.0 for y, a in rows if y for z, b in rows if not z])
    for steps in (8, 4096):
        assert learn.auc(df, F.col("m"), steps).first().auc == pytest.approx(want)


def test_grid_runs_and_keeps_its_shape(spark, sf):
    ship(spark)
    t = grids.best_over_c(grids.grid(spark, sf, "lang", 0.5, [16, 256], (1, 8), (1.0, 10.0), 2)).collect()
    assert len(t) == 3 * 2 * 2 * 2 + 2 and {r.reps for r in t if r.method != "original"} == {2}
    of = {(r.method, r.solver, r.k, r.b): r for r in t}
    for s in ("logistic", "svm"):
        assert of["blank", s, 256, 8].auc > of["blank", s, 16, 1].auc
        assert of["blank", s, 256, 8].nonzeros < of["noise", s, 256, 8].nonzeros == 256


def test_signatures_of_many_settings(spark, words):
    sk = sketch.bin_minima(words, Feistel(24, 2), 32).cache()
    for policy in ("skip_band", "sentinel"):
        got = lsh.signatures_by(sk, spark.createDataFrame([(2, 4, 8), (1, 2, 4)], "b int, k int, tables int"), policy)
        for b, k, n in ((2, 4, 8), (1, 2, 4)):
            want = {tuple(r) for r in lsh.build_index(sk, b, k, n, policy).collect()}
            assert {(r.table_no, r.bucket, r.set_id) for r in got.filter(f"b = {b} and k = {k}").collect()} == want


def test_new_points_find_what_is_contained(spark, sf):
    ship(spark)
    found = {(r.query_id, r.set_id): r.contained for r in registry.queries()["stream_new_points"](spark, sf).collect()}
    truth = {(r.item_id, r.doc_id): r.contained for r in search.contamination_bench(spark, sf).collect()}
    assert truth and set(found) <= set(truth) and len(found) >= 0.9 * len(truth) and all(truth[k] == v for k, v in found.items())


@pytest.mark.parametrize("b", [1, 2, 4, 6, 8])
def test_dense_rows_equal_sparse_ones(b):
    """Bins that share a byte give the margins and gradients of single ones."""
    r = np.random.default_rng(b)
    code = r.integers(0, 256, (50, 24), dtype=np.uint8)
    x, y = cells.design(code, np.ones((50, 24), bool), b), cells.Dense(np.ascontiguousarray(code.T), b)
    w, g = r.normal(size=24 << b), r.normal(size=50)
    assert x.dims == y.dims and np.allclose(x.margins(w), y.margins(w)) and np.allclose(x.back(g), y.back(g))
    wide = cells.design(code, r.random((50, 24)) < 0.3, 8)
    assert np.array_equal(wide.masked(b).index, wide.index >> 8 << b | (wide.index & 255) & ((1 << b) - 1)) and wide.masked(b).dims == 24 << b


def test_cells_read_a_part_of_the_rows_at_a_time(spark, words, monkeypatch):
    """Stored codes give the designs of collected ones; nothing but labels is broadcast."""
    from binsketch.tables import written

    packed = codes.to_binary(codes.low_bits(sketch.bin_minima(words, Feistel(24, 1), 512), 8), 512, 8).select("set_id", "codes", "holes")
    top, part = cells.collected(packed, 512), cells.Stored.of(written(packed, "packed"), 512)
    monkeypatch.setattr(cells, "READ", 7)
    assert np.array_equal(part.ids(), top.ids)
    want, got = cells.design(*top.at(64, True), 8), cells.blank_design(part, 64, True, top.ids)
    order = np.lexsort((got.index, got.row))
    assert np.array_equal(got.index[order], want.index[np.lexsort((want.index, want.row))]) and np.allclose(got.scale, want.scale) and got.index.dtype == np.int32
    code, filled = top.at(64, True)
    drawn = cells.filled_columns(part, 64, True, top.ids, np.random.default_rng(1))
    assert drawn.dtype == np.uint8 and np.array_equal(drawn[filled], code[filled])
    sent = []
    context = type(spark.sparkContext)
    broadcast = context.broadcast
    monkeypatch.setattr(context, "broadcast", lambda self, value: sent.append(value) or broadcast(self, value))
    t = cells.run_cells(spark, {("binned", 0): part}, {int(i): float(i % 2) for i in top.ids}, lambda ids: ids % 3 == 0, [("blank", "logistic", 64, 4, 0), ("noise", "svm", 64, 4, 0)], [1.0])
    assert t.count() == 2 and sent and all(isinstance(v, dict) and len(v) == len(top.ids) for v in sent)


def test_packing_unpacks_few_rows_at_a_time(words, monkeypatch):
    c = codes.low_bits(sketch.bin_minima(words, Feistel(24, 1), 64), 8)
    want = sorted(map(tuple, codes.to_binary(c, 64, 8).collect()))
    monkeypatch.setattr(codes, "UNPACKED", 64 * 8 * 3)
    assert sorted(map(tuple, codes.to_binary(c, 64, 8).collect())) == want
    assert sorted(map(tuple, codes.from_binary(codes.to_binary(c, 64, 8), 64, 8).collect())) == sorted(map(tuple, c.collect()))


def test_grid_takes_all_labelled_rows(spark, tmp_path):
    """Every labelled document trains or is tested, however many there are."""
    ship(spark)
    docs = spark.range(25_000).select(F.col("id").alias("doc_id"), F.concat(F.lit("a w"), (F.col("id") % 2).cast("string"), F.lit(" x"), (F.col("id") % 7).cast("string")).alias("text"), F.lit("en").alias("lang"))
    docs.repartition(4).write.parquet(f"{tmp_path}/documents.parquet")
    docs.select("doc_id", (F.col("doc_id") % 2).alias("toxic"), F.lit(1).alias("quality")).write.parquet(f"{tmp_path}/labels.parquet")
    t = grids.grid(spark, str(tmp_path), "toxic", 0.5, [8, 16], (1, 8), (1.0,), 1, solvers=("logistic",)).collect()
    assert len(t) == 3 * 2 * 2 + 1 and all(r.n_train + r.n == 25_000 and min(r.n_train, r.n) > 10_000 for r in t)
    assert all(r.auc == 1 for r in t if r.method == "original")


@pytest.mark.parametrize("method", ["blank", "noise", "classic", "original"])
@pytest.mark.parametrize("held", [0, 1 << 26])
def test_parts_of_the_rows_fit_as_all_rows_do(words, method, held, monkeypatch):
    """Rows in parts, kept or read again in each round, give the weights of one matrix that holds all of them."""
    from binsketch.tables import written

    monkeypatch.setattr(cells, "HELD", held)
    monkeypatch.setattr(cells, "PART", 64 * 40)
    monkeypatch.setattr(cells, "READ", 16)
    arrays = written(words.groupBy("set_id").agg(F.collect_set("elem").alias("elems")), "arrays")
    packed = cells.classic_codes(arrays, 128, 3) if method == "classic" else codes.to_binary(codes.low_bits(sketch.bin_minima(words, Feistel(24, 1), 128), 8), 128, 8).select("set_id", "codes", "holes")
    own = written(packed, "packed")
    part = cells.files_of(arrays) if method == "original" else cells.Stored.of(own, 128)
    ids, train, probe, entries, at = cells.parts_of(part, method, 64, 1, lambda ids: ids % 3 == 0)
    top = cells.collected(own, 128)
    assert np.array_equal(ids, top.ids) and np.array_equal(np.sort(np.r_[train, probe]), np.arange(len(ids)))
    y = np.where(ids % 2, 1.0, -1.0)
    for b in (2, 8):
        a, z = at(b)
        code, filled = top.at(64, method != "classic")
        if method == "original":
            rows = {int(r.set_id): np.unique(r.elems) for r in arrays.collect()}
            values = np.unique(np.concatenate(list(rows.values())))
            sizes = np.array([len(rows[int(i)]) for i in ids])
            whole = cells.Design(np.concatenate([np.searchsorted(values, rows[int(i)]) for i in ids]), np.repeat(np.arange(len(ids)), sizes), 1 / np.sqrt(sizes), len(values))
        else:
            code = np.where(filled, code, np.random.default_rng([1, 64]).integers(0, 256, code.shape, dtype=np.uint8)) if method == "noise" else code
            whole = cells.design(code, np.ones_like(filled) if method == "noise" else filled, b)
        assert entries == pytest.approx(len(whole.index) / len(ids)) and len(list(a)) > 1
        number = np.full(len(ids), -1)
        number[train] = np.arange(len(train))
        some = number[whole.row] >= 0
        plain = cells.Design(whole.index[some], number[whole.row[some]], whole.scale[train], whole.dims)
        want = cells.fit(plain, y[train], 1.0, "logistic")
        assert np.allclose(cells.fit(a, y[train], 1.0, "logistic"), want, atol=1e-8)
        assert np.allclose(z.margins(want), whole.margins(want)[probe])
        assert (a.held is None) == (held == 0)
