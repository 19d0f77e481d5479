"""Jaccard join, suffix dedup, classifier, exact search, pipeline: against plain versions."""

import hashlib
import random
import re

import numpy as np
import pytest
from pyspark.sql import functions as F

from binsketch.llm import exact_topk, jaccard_join, quality, shingles, suffix_dedup
from binsketch.llm.shingles import shingle_sets
from binsketch.llm.suffix_order import common_prefixes, two_stage_order, words_at


def plain_sets(texts):
    lower = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
    out = {}
    for i, t in texts.items():
        w = re.findall("[^\x20\x09-\x0d]+", (t or "").translate(lower))
        out[i] = {tuple(w[k : k + 5]) for k in range(len(w) - 4)} if len(w) >= 5 else {tuple(w)} if w else set()
    return out


def plain_components(sets):
    parent = {i: i for i in sets}

    def root(x):
        while parent[x] != x:
            x = parent[x]
        return x

    ids = sorted(sets)
    for n, i in enumerate(ids):
        for j in ids[:n]:
            if sets[i] and sets[j] and 100 * len(sets[i] & sets[j]) >= 80 * len(sets[i] | sets[j]):
                a, b = sorted((root(i), root(j)))
                parent[b] = a
    return {i: root(i) for i in ids}


def near_texts(n, seed):
    """Groups of near copies around the threshold, chains among them, and unrelated texts with common lines."""
    r = random.Random(seed)
    word = lambda: f"w{r.randrange(400)}"
    common = " ".join(word() for _ in range(12))
    texts = []
    for _ in range(n):
        base = [word() for _ in range(r.randrange(5, 90))]
        for _ in range(r.choice([1, 1, 2, 30])):
            t = list(base)
            for _ in range(r.randrange(0, 4)):
                t[r.randrange(len(t))] = word()
            texts.append(" ".join(t) + (" " + common if r.random() < 0.4 else ""))
            base = t if r.random() < 0.3 else base
    r.shuffle(texts)
    return dict(enumerate(texts))


@pytest.mark.parametrize("short_list,part", [(2, 8192), (32, 8192), (32, 3), (2, 3)])
def test_join_is_exact(spark, monkeypatch, short_list, part):
    monkeypatch.setattr(jaccard_join, "SHORT_LIST", short_list)
    monkeypatch.setattr(jaccard_join, "PART", part)
    texts = near_texts(40, short_list)
    got = {r.doc_id: r for r in jaccard_join.near_duplicates(spark.createDataFrame(list(texts.items()), "doc_id long, text string")).collect()}
    sets = plain_sets(texts)
    want = plain_components(sets)
    assert {i: (r.n_shingles, r.component_id) for i, r in got.items()} == {i: (len(sets[i]), want[i]) for i in sets}
    assert len(set(want.values())) < len(want)


def test_blocks_are_skipped_by_position():
    """No pair that may link is lost, and most of the others are never looked at."""
    r = np.random.default_rng(3)
    sizes = r.integers(1, 33, 200)
    lists = np.repeat(np.arange(200), sizes)
    n = r.integers(5, 300, len(lists))
    at = (r.random(len(lists)) * (n - jaccard_join.least_overlap(n) + 1)).astype(np.int64)
    i, j, looked = jaccard_join.block_pairs(lists, n, at)
    want, every = set(), 0
    for k in range(200):
        own = np.flatnonzero(lists == k)
        for x, a in enumerate(own):
            for b in own[:x]:
                every += 1
                if jaccard_join.may_link(n[a], at[a], n[b], at[b]):
                    want.add((b, a))
    got = [(min(a, b), max(a, b)) for a, b in zip(i.tolist(), j.tolist(), strict=True)]
    assert len(got) == len(set(got)) and set(got) == want and want
    assert looked < every / 4
    # one size: position alone decides
    n[:], at[:] = 90, np.arange(len(lists)) % 19
    i, j, looked = jaccard_join.block_pairs(lists, n, at)
    assert 0 < len(i) < looked < every / 2


def test_join_edges(spark, edge, nothing):
    texts = {r.doc_id: r.text for r in edge.collect()}
    sets = plain_sets(texts)
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in jaccard_join.near_duplicates(edge).collect()}
    want = plain_components(sets)
    assert got == {i: (len(sets[i]), want[i]) for i in sets}
    assert jaccard_join.near_duplicates(nothing).count() == 0
    twice = jaccard_join.near_duplicates(edge.union(edge)).collect()
    assert len(twice) == 2 * len(texts) and {(r.doc_id, r.component_id) for r in twice} == {(i, c) for i, (_, c) in got.items()}
    assert [len(s) for s in shingle_sets(["", "a", "a b c d e f"])] == [0, 1, 2]


def test_long_texts_are_hashed_in_parts(monkeypatch):
    r = random.Random(5)
    texts = ["".join(r.choice("ab \n") for _ in range(n)) for n in (0, 1, 6, 7, 8, 40, 300, 301)] + ["x" * 100 + " " + "y" * 50, " " * 60, "one " * 30]
    want = shingle_sets(texts)
    monkeypatch.setattr(shingles, "AT_ONCE", 7)
    for a, b in zip(want, shingle_sets(texts), strict=True):
        assert a.tolist() == b.tolist()


@pytest.mark.parametrize("at_once", [1, 150, 1 << 19])
def test_long_texts_have_the_same_strings_in_parts(monkeypatch, at_once):
    monkeypatch.setattr(suffix_dedup, "AT_ONCE", at_once)
    r = np.random.default_rng(1)
    raw = [r.integers(97, 100, n).astype(np.uint8).tobytes() for n in (0, 99, 100, 101, 260, 700)]
    starts = []
    for where, blobs in suffix_dedup.pieces_of(raw):
        blob, start, count, far, key = suffix_dedup.anchors(blobs)
        for b, s, c, f, k in zip(blob, start, count, far, key, strict=True):
            i, at = where[b]
            starts += [(i, at + s + n) for n in range(c)]
            assert suffix_dedup.gram_hashes(np.frombuffer(raw[i], np.uint8))[at + s + f] == k
    assert sorted(starts) == [(i, s) for i, b in enumerate(raw) for s in range(len(b) - 99)]


@pytest.mark.parametrize("letters", [1, 2, 4, 200])
def test_two_stage_sorting(letters):
    r = np.random.default_rng(letters)
    for n in (1, 2, 3, 50, 400):
        text = r.integers(0, letters, n).astype(np.uint8)
        words = words_at(text, 104)
        order = two_stage_order(text, words, 104)
        b = text.tobytes()
        assert sorted(order.tolist()) == list(range(n))
        assert [b[i : i + 104] for i in order] == sorted(b[i : i + 104] for i in range(n))
        first = np.unique(r.integers(0, n, 5))
        last = np.minimum(first + r.integers(0, 9, len(first)), n - 1)
        wanted = {i for x, y in zip(first, last, strict=True) for i in range(x, y + 1)}
        some = two_stage_order(text, words, 104, first, last).tolist()
        assert len(set(some)) == len(some) and wanted <= set(some)
        assert [b[i : i + 104] for i in some] == sorted(b[i : i + 104] for i in some)
        shared = common_prefixes(order, text, words, 104)
        for k, (x, y) in enumerate(zip(order, order[1:], strict=False), 1):
            p, q = (b + b"\0" * 120)[x : x + 104], (b + b"\0" * 120)[y : y + 104]
            assert shared[k] == next((i for i in range(104) if p[i] != q[i]), 104)
        assert shared[0] == 0


def plain_removal(texts):
    seen, out = set(), {}
    for i in sorted(texts):
        b = (texts[i] or "").encode()
        gone = bytearray(len(b))
        for s in range(len(b) - 99):
            w = b[s : s + 100]
            if w in seen:
                gone[s : s + 100] = b"\1" * 100
            seen.add(w)
        kept = bytes(x for x, g in zip(b, gone, strict=True) if not g)
        out[i] = (len(b), sum(gone), sum(1 for k, g in enumerate(gone) if g and not (k and gone[k - 1])), hashlib.sha256(kept).hexdigest())
    return out


@pytest.mark.parametrize("hot", [1, 1024])
def test_removal_is_exact(spark, sf, edge, nothing, monkeypatch, hot):
    monkeypatch.setattr(suffix_dedup, "HOT_LEAST", hot)
    docs = edge.select("doc_id", "text").union(spark.read.parquet(f"{sf}/documents.parquet").selectExpr("doc_id + 100", "text"))
    got = {r.doc_id: (r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) for r in suffix_dedup.removal_digests(docs).collect()}
    assert got == plain_removal({r.doc_id: r.text for r in docs.collect()})
    assert suffix_dedup.removal_digests(nothing).count() == 0


def test_cleaned_texts(spark, edge, nothing):
    rows = {r.doc_id: r for r in suffix_dedup.cleaned(edge).collect()}
    assert suffix_dedup.cleaned(edge).columns == edge.columns
    want = plain_removal({r.doc_id: r.text for r in edge.collect()})
    for r in edge.collect():
        n, gone, *_ = want[r.doc_id]
        if gone and gone == n:
            assert r.doc_id not in rows
        elif not gone:
            assert rows[r.doc_id].text == r.text
        else:
            assert rows[r.doc_id].n_chars == len(rows[r.doc_id].text) < len(r.text)
    assert suffix_dedup.cleaned(nothing).count() == 0


def test_classifier_holds_out(spark):
    docs, labels = (spark.read.parquet(f"/root/testdata/sf0.01/{t}.parquet") for t in ("documents", "labels"))
    half = labels.filter(F.xxhash64("doc_id") % 2 == 0)
    rows = quality.classified(docs, half, ["doc_id"]).join(labels.subtract(half), "doc_id").collect()
    clean = [r for r in rows if r.quality == 1 and r.toxic == 0]
    assert sum(r.keep for r in clean) >= 0.95 * len(clean)
    poor = [r for r in rows if r.quality == 0]
    assert sum(not r.keep for r in poor) >= 0.7 * len(poor)


def test_classifier_edges(spark, edge, nothing):
    labels = spark.createDataFrame([(5, 1, 0), (7, None, 1), (8, 0, None), (None, 1, 0)], "doc_id long, quality int, toxic int")
    rows = quality.classified(edge, labels, ["doc_id", "text"]).collect()
    assert len(rows) == edge.count() and all(0 <= r.p_quality <= 1 and r.keep is not None for r in rows)
    clash = edge.withColumns({c: F.lit(c) for c in ("quality", "toxic", "p_quality", "_host", "_path", "host", "path", "c0", "label_id", "quality_shift", "_spans", "spans", "odd.name")})
    kept = quality.accepted(clash, labels)
    want = {r.doc_id for r in rows if r.keep}
    assert kept.columns == clash.columns and {r.doc_id for r in kept.collect()} == want and {r.p_quality for r in kept.collect()} <= {"p_quality"}
    assert quality.classified(clash, labels, clash.columns).columns[-5:] == ["quality_evidence", "toxic_evidence", "_p_quality", "p_toxic", "_keep"]
    assert suffix_dedup.cleaned(clash).columns == clash.columns and suffix_dedup.cleaned(clash).count() == suffix_dedup.cleaned(edge).count()
    assert quality.classified(nothing, labels, ["doc_id"]).count() == 0
    free = quality.classified(edge, labels.limit(0), ["doc_id"]).collect()
    assert len(free) == len(rows)


def test_sparse_sites_shrink(spark):
    rows = spark.createDataFrame([("big", "a", 3.0, -3.0)] * 400 + [("bad", "a", -3.0, 3.0)] * 300 + [("tiny", "a", -3.0, 3.0)], "host string, path string, quality_evidence double, toxic_evidence double")
    s = {r.host: r for r in quality.site_shifts(rows, "host", "path").collect()}
    assert s["bad"].quality_shift < s["tiny"].quality_shift < s["big"].quality_shift
    assert s["bad"].toxic_shift > s["big"].toxic_shift


def test_site_posteriors_equal_a_plain_computation(spark):
    r = np.random.default_rng(8)
    rows = [(str(r.choice(["a", "b", "c", "d"], p=[0.7, 0.2, 0.09, 0.01])), str(r.choice(["x", "y", "z"])), float(r.normal()), float(r.normal())) for _ in range(500)] + [(None, None, 1.0, -1.0)]
    df = spark.createDataFrame(rows, "source string, lang string, quality_evidence double, toxic_evidence double")
    shifts = quality.site_shifts(df, "source", "lang")
    got = {(x.host, x.path): (x.n, x.quality_shift, x.toxic_shift) for x in shifts.collect()}
    odds = lambda p: np.log(p / (1 - p))
    want = {}
    for head in (2, 3):
        p = [((x[0] or "", x[1] or ""), 1 / (1 + np.exp(-x[head]))) for x in rows]
        mean = np.mean([v for _, v in p])

        def groups(key):
            out = {}
            for k, v in p:  # noqa: B023
                out.setdefault(key(k), []).append(v)
            return out

        def strength(g):
            spread = sum(len(v) * (np.mean(v) - mean) ** 2 for v in g.values()) / len(rows)  # noqa: B023
            return np.clip(mean * (1 - mean) / spread - 1, 1, 10_000)  # noqa: B023

        hosts, paths = groups(lambda k: k[0]), groups(lambda k: k)
        for k, v in paths.items():
            h = hosts[k[0]]
            of_host = (sum(h) + strength(hosts) * mean) / (len(h) + strength(hosts))
            of_path = (sum(v) + strength(paths) * of_host) / (len(v) + strength(paths))
            want.setdefault(k, [len(v)]).append(odds(of_path) - odds(mean))
    assert set(got) == set(want)
    for k, v in want.items():
        assert got[k] == pytest.approx(tuple(v), abs=1e-9)
    for x in quality.judged(df, shifts, "source", "lang", 0.6, 0.4).collect():
        own = want[x.source or "", x.lang or ""]
        p, q = (1 / (1 + np.exp(-(e + o))) for e, o in zip((x.quality_evidence, x.toxic_evidence), own[1:], strict=True))
        assert (x.p_quality, x.p_toxic) == pytest.approx((p, q)) and x.keep == (p >= 0.6 and q < 0.4)


def test_sites_of_urls(spark):
    urls = {"http://www.A.example:80/x/y?q#f": ("a.example", "/x"), "https://u:p@b.example": ("b.example", ""), "//c.example/z": ("c.example", "/z"), None: ("", ""), "no url": ("", ""), "http://d.example/?x": ("d.example", "")}
    rows = quality.sites(spark.createDataFrame([(u,) for u in urls], "url string"), "url").collect()
    assert {r.url: (r.host, r.path) for r in rows} == urls


def plain_top(rows, k):
    v = {i: [int(np.floor(256 * float(x))) for x in e] for i, e in rows if e is not None and all(x is not None and np.isfinite(x) for x in e)}
    out = set()
    for q in v:
        if q % 50 == 0:
            score = sorted(((-sum(a * b for a, b in zip(v[q], v[c], strict=False)), c) for c in v if c != q))[:k]
            out |= {(q, n, c, -s) for n, (s, c) in enumerate(score, 1)}
    return out


@pytest.mark.parametrize("at_once,lists", [(16384, 2), (3, 1), (3, 5)])
def test_search_is_exact(spark, at_once, lists):
    r = np.random.default_rng(9)
    rows = [(i, [float(x) for x in r.normal(size=8)]) for i in range(400)]
    rows += [(i, rows[0][1]) for i in range(400, 450)] + [(450, None), (451, [1.0, None]), (452, [float("nan")] * 8), (453, []), (454, [0.5])]
    df = spark.createDataFrame([(*x, "clash") for x in rows], "vec_id long, embedding array<double>, v string")
    got = exact_topk.top_k(exact_topk.quantised(df), F.col("vec_id") % 50 == 0, 5, lists, at_once).collect()
    assert {tuple(x) for x in got} == plain_top(rows, 5)


def test_search_edges(spark):
    few = spark.createDataFrame([(0, [1.0]), (1, [1.0]), (2, [1.0])], "vec_id long, embedding array<double>")
    got = exact_topk.top_k(exact_topk.quantised(few), F.col("vec_id") % 50 == 0).collect()
    assert [tuple(r) for r in got] == [(0, 1, 1, 65536), (0, 2, 2, 65536)]
    assert exact_topk.top_k(exact_topk.quantised(few.limit(0)), F.col("vec_id") % 50 == 0).count() == 0
    assert exact_topk.top_k(exact_topk.quantised(few.filter("vec_id > 0")), F.col("vec_id") % 50 == 0).count() == 0


def test_search_scores_few_in_full():
    """Local lists, a cutoff, and full scores for what reaches it only."""
    r = np.random.default_rng(4)
    c = np.floor(256 * r.normal(size=(4000, 64)) * r.choice([0.2, 1.0], (4000, 1)))
    q, ids = np.floor(256 * r.normal(size=(50, 64))), np.arange(4000)
    want = np.sort(q @ c.T, axis=1)[:, -5:]
    first = exact_topk.Block(ids, c, 2)
    row, _, score = first.heads(q, 5)
    cutoffs = np.array([np.sort(score[row == i])[-5] for i in range(50)]).astype(np.int64)
    assert (cutoffs <= want[:, 0]).all() and first.scored <= 50 * 2 * 6
    second = exact_topk.Block(ids, c, 2)
    row, at, score = second.entries(q, cutoffs)
    assert [sorted(score[row == i])[-5:] for i in range(50)] == want.tolist()
    assert first.read < 50 * 4000 / 2 and second.scored < 50 * 4000 / 10 and second.read < 2 * 50 * 4000


def test_search_of_repeated_rows(spark):
    """Rows of one vec_id are one query; a candidate row that is there twice ranks twice."""
    rows = [(0, [1.0, 0.0]), (0, [0.0, 1.0]), (0, [1.0, 0.0]), (1, [2.0, 0.0]), (1, [2.0, 0.0]), (2, [0.0, 3.0]), *((3, [0.5, 0.5]) for _ in range(9)), (4, [0.5, 0.5])]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>")
    got = [tuple(r) for r in exact_topk.top_k(exact_topk.quantised(df), F.col("vec_id") % 50 == 0).orderBy("rank").collect()]
    one = 256 * 256
    assert got == [(0, 1, 2, 3 * one), (0, 2, 1, 2 * one), (0, 3, 1, 2 * one), (0, 4, 3, one // 2), (0, 5, 3, one // 2)]


def test_pipeline_stages(spark, sf):
    import corpus_pipeline
    from binsketch.llm.common import table, written

    docs = table(spark, sf, "documents")
    assert [n for n, _ in corpus_pipeline.STAGES] == ["quality", "near_duplicates", "repeated_passages", "packing"]
    for name, stage in corpus_pipeline.STAGES[:-1]:
        before, docs = docs, written(stage(spark, docs, sf), name)
        assert docs.columns == before.columns and 0 < docs.count() <= before.count()
        texts = {r.doc_id: r.text for r in before.collect()}
        after = {r.doc_id: r.text for r in docs.collect()}
        if name == "near_duplicates":
            assert set(after) == set(plain_components(plain_sets(texts)).values())
        if name == "repeated_passages":
            want = plain_removal(texts)
            assert {i for i in texts if want[i][1] < want[i][0] or not texts[i]} == set(after)
    packed = corpus_pipeline.STAGES[-1][1](spark, docs, sf)
    assert {r.doc_id for r in packed.select("doc_id").collect()} == {r.doc_id for r in docs.select("doc_id").collect()}


def test_stages_take_odd_rows(spark, sf, edge, nothing):
    """Nulls in any column, empty and long texts, ties, repeated rows and ids, extra columns with clashing names, an empty table."""
    import corpus_pipeline
    from binsketch.llm.common import written

    extra = {c: F.lit(c) for c in ("quality", "toxic", "p_quality", "keep_", "_host", "_path", "host", "path", "component_id", "copy_of", "sha", "spans", "_spans", "start", "end", "rep", "hash", "c0", "no", "terms")}
    odd = edge.union(edge.filter("doc_id in (5, 11)")).union(edge.filter("doc_id = 7").withColumn("doc_id", F.lit(None).cast("long"))).withColumns(extra)
    docs = written(odd, "odd")
    for name, stage in corpus_pipeline.STAGES:
        after = written(stage(spark, docs, sf), name)
        if name == "packing":
            assert after.filter("length <= 0").count() == 0 and {r.doc_id for r in after.collect()} == {r.doc_id for r in docs.collect()}
        else:
            assert after.columns == docs.columns and {tuple(r[c] for c in extra) for r in after.collect()} <= {tuple(extra)}
        assert stage(spark, docs.limit(0), sf).count() == 0
        if name != "quality":  # a few odd rows are no corpus to judge
            docs = after if name != "packing" else docs
    assert stage(spark, nothing, sf).count() == 0
