"""Token counts, token files, piece encoding, packing: against the libraries."""

import hashlib
import zlib

import numpy as np
import public_tokenizers as tokenizers_at
import pytest
import sentencepiece
from tokenizers import Tokenizer

from binsketch.llm import memo, packing, piece_codec, token_counts, token_files

BYTE, WORD, PIECE = (tokenizers_at.path(n) for n in ("byte_bpe_50k.json", "word_bpe_49k.json", "piece_bpe_32k.model"))


def library(path, text):
    t = Tokenizer.from_file(path)
    return t.encode(text or "", add_special_tokens=False).ids


def texts(df):
    return {r.doc_id: r.text for r in df.collect()}


@pytest.mark.parametrize("path", [BYTE, WORD])
def test_ids_are_the_librarys(spark, sf, edge, path):
    enc = memo.json_encoder(path)
    assert type(enc) is not memo.JsonEncoder
    some = [r.text for r in spark.read.parquet(f"{sf}/documents.parquet").collect()] + [r.text or "" for r in edge.collect()]
    want = [e.ids for e in Tokenizer.from_file(path).encode_batch(some, add_special_tokens=False)]
    assert [enc.ids(t).tolist() for t in some] == want


@pytest.mark.parametrize("path", [BYTE, WORD])
def test_each_token_is_reached_by_its_merges(path):
    """So that merging by rank gives what the listed merges give."""
    import json

    spec = json.load(open(path))
    order = {tuple(m.split(" ") if isinstance(m, str) else m): i for i, m in enumerate(spec["model"]["merges"])}
    special = {t["content"] for t in spec["added_tokens"]}
    for piece in spec["model"]["vocab"]:
        if piece in special:
            continue
        parts = list(piece.removesuffix("</w>")) if path == WORD else list(piece)
        if path == WORD and piece.endswith("</w>"):
            parts[-1] += "</w>"
        while len(parts) > 1:
            rank, k = min((order.get(p, 1 << 60), k) for k, p in enumerate(zip(parts, parts[1:], strict=False)))
            assert rank < 1 << 60, piece
            parts[k : k + 2] = [parts[k] + parts[k + 1]]


def test_plain_characters_are_split_alike():
    """Each character that the fast way takes is a letter, digit, space or sign for both pattern engines."""
    import regex
    from tokenizers import Regex, pre_tokenizers

    split = pre_tokenizers.Split(Regex(token_counts.SPLIT), "isolated")
    own = regex.compile(token_counts.SPLIT)
    for c in map(chr, [*range(0x250), *range(0x370, 0x480), *range(0x2010, 0x2060), *range(0x3040, 0x3100), *range(0x4E00, 0x9FA6, 7), *range(0xAC00, 0xD7A4, 11)]):
        if memo.PLAIN.fullmatch(c):
            probe = f"a1{c}b {c} 2{c}{c}.\n{c}"
            assert [p for p, _ in split.pre_tokenize_str(probe)] == own.findall(probe), hex(ord(c))


def test_counts(edge, nothing):
    for path in (BYTE, WORD):
        got = {r.doc_id: r for r in token_counts.token_counts(edge, path).collect()}
        for i, t in texts(edge).items():
            n = len(library(path, t))
            assert (got[i].n_tokens, got[i].n_bytes, got[i].over_limit) == (n, len((t or "").encode()), n > 1024)
    assert token_counts.token_counts(nothing, BYTE).count() == 0
    sp = sentencepiece.SentencePieceProcessor(model_file=PIECE)
    got = {r.doc_id: r.n_tokens for r in token_counts.token_counts(edge, PIECE).collect()}
    assert got == {i: len(sp.encode(t or "")) for i, t in texts(edge).items()}


def test_simple8b_round_trip():
    r = np.random.default_rng(1)
    for n in (0, 1, 127, 128, 129, 5000):
        for top in (1, 2, 60, 60_000, 1 << 31):
            ids = r.integers(0, top, n).astype("<u4")
            ids[r.random(n) < 0.3] = 0
            words, offsets = token_files.packed(ids)
            assert (token_files.unpacked(words) == ids).all() and len(offsets) == -(-n // 128)
    with pytest.raises(ValueError):
        token_files.packed(np.array([1 << 60], np.uint64))
    with pytest.raises(ValueError):
        token_files.opened(b"x" * 40)


def test_files_hold_all_ids(edge, nothing):
    files = token_files.write_token_files(edge, BYTE, file_ids=5000)
    got = {r.doc_id: r for r in token_files.read_token_files(files).collect()}
    start = 0
    for i, t in sorted(texts(edge).items()):
        ids = np.array([*library(BYTE, t), 0], "<u4")
        assert (got[i].start, got[i].n_tokens, got[i].ids_crc32) == (start, len(ids), zlib.crc32(ids.tobytes()))
        start += len(ids)
    first = min(files.collect(), key=lambda r: (r.part, r.seq))
    assert token_files.ids_of(bytes(first.blob), 0).tolist() == [0]
    assert token_files.token_digests(nothing, BYTE).count() == 0


def test_pieces(spark, sf, edge, nothing):
    sp = sentencepiece.SentencePieceProcessor(model_file=PIECE)
    docs = edge.select("doc_id", "text").union(spark.read.parquet(f"{sf}/documents.parquet").selectExpr("doc_id + 1000", "text"))
    got = {r.doc_id: r for r in piece_codec.piece_digests(docs, PIECE).collect()}
    for i, t in texts(docs).items():
        ids = sp.encode(t or "", add_bos=True, add_eos=True)
        assert (got[i].n_tokens, got[i].ids_sha256, got[i].decoded_sha256) == (len(ids), hashlib.sha256(np.array(ids, "<u4").tobytes()).hexdigest(), hashlib.sha256(sp.decode(ids).encode()).hexdigest()), t
        assert got[i].n_span_bytes == len((t or "").encode())
    assert piece_codec.piece_digests(nothing, PIECE).count() == 0
    again = piece_codec.piece_decode(piece_codec.piece_encode(edge, PIECE), PIECE)
    assert {r.doc_id: r.text for r in again.collect()} == {i: sp.decode(sp.encode(t or "", add_bos=True, add_eos=True)) for i, t in texts(edge).items()}


def test_piece_spans_are_the_librarys(edge):
    codec = piece_codec.piece_codec(PIECE)
    for t in [r.text for r in edge.collect()] + ["▁ a▁b ▁▁", " ▁"]:
        if not t:
            continue
        ids, begins, ends = codec.encode(t)
        pieces = codec.spans_of(t)
        assert ids.tolist() == [p.id for p in pieces]
        # the library gives all bytes of a character to the last of its byte pieces
        plain = [k for k, p in enumerate(pieces) if not p.piece.startswith("<0x")]
        assert [ends[k] for k in plain] == [pieces[k].end for k in plain]
        assert [begins[k] for k in plain if k == 0 or k - 1 in set(plain[:1]) or not pieces[k - 1].piece.startswith("<0x")] == [pieces[k].begin for k in plain if k == 0 or k - 1 in set(plain[:1]) or not pieces[k - 1].piece.startswith("<0x")]


def mapped_model(folder, trims):
    """The given model with the library's compiled character map in place of its empty one (nothing is trained)."""
    from sentencepiece import sentencepiece_model_pb2

    norm = sentencepiece.SentencePieceNormalizer(rule_name="nmt_nfkc")
    rules, spec = sentencepiece_model_pb2.ModelProto(), sentencepiece_model_pb2.ModelProto()
    rules.ParseFromString(norm.serialized_model_proto())
    spec.ParseFromString(open(PIECE, "rb").read())
    spec.normalizer_spec.precompiled_charsmap = rules.normalizer_spec.precompiled_charsmap
    spec.normalizer_spec.remove_extra_whitespaces = trims
    path = str(folder / f"mapped-{trims}.model")
    open(path, "wb").write(spec.SerializeToString())
    return path


@pytest.mark.parametrize("trims", [False, True])
def test_spans_through_a_compiled_map(spark, tmp_path, trims):
    path = mapped_model(tmp_path, trims)
    codec, lib = piece_codec.PieceCodec(path), sentencepiece.SentencePieceProcessor(model_file=path)
    assert len(codec.chars.units) and not codec.local
    rows = ["plain words", "ﬁne ＡＢＣ ①② and so on", "ｶﾞ ㍿ é Å", "tab\tnew\nline", "  two   spaces ", "½ cup ﬃ", "Ⅻ x"]
    got = {r.doc_id: r for r in piece_codec.piece_encode(spark.createDataFrame(list(enumerate(rows)), "doc_id long, text string"), path, begin=False, end=False).collect()}
    for i, t in enumerate(rows):
        pieces = lib.encode(t, return_type="proto").pieces
        assert got[i].ids == [p.id for p in pieces], t
        plain = [k for k, p in enumerate(pieces) if not p.piece.startswith("<0x")]
        assert [got[i].begins[k] for k in plain if k == 0 or k - 1 in plain] == [pieces[k].begin for k in plain if k == 0 or k - 1 in plain], t
        assert [got[i].ends[k] for k in plain] == [pieces[k].end for k in plain], t


def test_character_map_follows_the_library():
    try:
        norm = sentencepiece.SentencePieceNormalizer(rule_name="nmt_nfkc", add_dummy_prefix=False, escape_whitespaces=False, remove_extra_whitespaces=False)
    except Exception:
        pytest.skip("the library has no built-in rules")
    from sentencepiece import sentencepiece_model_pb2

    spec = sentencepiece_model_pb2.ModelProto()
    spec.ParseFromString(norm.serialized_model_proto())
    chars = piece_codec.CharMap(spec.normalizer_spec.precompiled_charsmap)
    for t in ("plain", "ﬁne ＡＢＣ ①②", "é é Å", "tab\tnew\nline", "㍿ ｶﾞ", ""):
        out, source = chars.normalise(t.encode())
        assert out.decode() == norm.normalize(t)
        assert len(source) == len(out) + 1 and source[-1] == len(t.encode()) and (np.diff(source) >= 0).all()


def test_packing(edge, nothing, spark):
    twice = edge.select("doc_id", "text")
    rows = packing.packed(twice, WORD, window=256, shard_tokens=20_000).collect()
    docs = {i: np.array([*library(WORD, t), 2], "<u4") for i, t in texts(edge).items()}
    by_doc, by_seq = {}, {}
    for r in rows:
        by_doc.setdefault(r.doc_id, []).append(r)
        by_seq.setdefault(r.sequence_id, []).append(r)
    for i, ids in docs.items():
        at = 0
        for r in sorted(by_doc[i], key=lambda r: r.start):
            assert r.start == at and r.doc_tokens == len(ids) and r.ids_crc32 == zlib.crc32(ids[at : at + r.length].tobytes())
            at += r.length
        assert at == len(ids)
    for s in by_seq.values():
        at = 0
        for r in sorted(s, key=lambda r: r.offset):
            assert r.offset == at
            at += r.length
        assert at <= 256
    assert packing.packed(nothing, WORD).count() == 0
    again = packing.packed(spark.createDataFrame([(1, "a b"), (1, "a b")], "doc_id long, text string"), WORD)
    assert again.count() == 2


def test_neighbours_share_words():
    docs = [np.array(d, np.uint16) for d in ([5, 6, 7, 8], [100, 101, 102], [5, 6, 9], [103, 104])]
    idf = np.ones(65536)
    index = packing.Index(docs, idf, 3.0)
    score = index.neighbours(0)
    assert score[2] > score[1] == score[3] == 0
    windows = list(packing.pack_shard(docs, index, 7))
    assert [d for d, *_ in windows[0]] == [0, 2]


def test_neighbours_are_scored_with_all_terms():
    docs = [np.array(d, np.uint16) for d in (range(100), range(60, 100), [*range(3), *range(200, 237)], [300])]
    idf = np.linspace(2, 1, 65536) * np.where(np.arange(65536) < 32, 1.5, 1)
    got = packing.Index(docs, idf, 60.0).neighbours(0)
    damp = packing.K1 * (1 - packing.B + packing.B * np.array([len(d) for d in docs]) / 60.0)
    want = [sum(idf[t] * (packing.K1 + 1) / (1 + damp[i]) for t in set(d) & set(docs[0])) for i, d in enumerate(docs)]
    assert got == pytest.approx(want, rel=1e-5) and got[1] > got[2] > got[3] == 0


def test_neighbours_come_from_the_whole_table(spark):
    """Each window is filled with the best unused documents, in whichever part of the table they lie."""
    r = np.random.default_rng(4)
    words = [f"{a}{b}{c}" for a in "bdfg" for b in "aeio" for c in ("lm", "nt", "rs", "x")]
    topics = [r.choice(words, 12, replace=False) for _ in range(40)]
    texts = [(100 * k + i, " ".join(r.choice(topics[i], 25))) for k in range(6) for i in range(40)]
    docs = spark.createDataFrame(texts, "doc_id long, text string").repartition(6).cache()
    window = 256
    ids = {i: np.array([*library(WORD, t), 2]) for i, t in texts}
    n, mean = len(ids), sum(map(len, ids.values())) / len(ids)
    df = {t: sum(t in set(d) for d in map(np.ndarray.tolist, ids.values())) for t in set(np.concatenate(list(ids.values())).tolist())}

    def bm25(seed, d):
        tf = dict(zip(*(x.tolist() for x in np.unique(ids[d], return_counts=True)), strict=True))
        damp = packing.K1 * (1 - packing.B + packing.B * len(ids[d]) / mean)
        return sum(np.log1p((n - df[t] + 0.5) / (df[t] + 0.5)) * tf[t] * (packing.K1 + 1) / (tf[t] + damp) for t in set(ids[seed].tolist()) & set(tf))

    rows = packing.packed(docs, WORD, window=window, shard_tokens=1000).collect()
    by_seq, left = {}, {i: len(d) for i, d in ids.items()}
    for x in rows:
        by_seq.setdefault(x.sequence_id, []).append(x)
    assert sorted(by_seq) == list(range(len(by_seq)))
    for s in sorted(by_seq):
        pieces = sorted(by_seq[s], key=lambda x: x.offset)
        seed = pieces[0].doc_id
        left[seed] -= pieces[0].length
        score = {d: bm25(seed, d) for d, m in left.items() if m and d != seed}
        for x in pieces[1:]:
            assert score[x.doc_id] >= max(score.values()) - 1e-3
            left[x.doc_id] -= x.length
            del score[x.doc_id]
        assert s == len(by_seq) - 1 or sum(x.length for x in pieces) == window
    assert not any(left.values())


def test_blocks_out_of_reach_are_not_scored():
    """Documents of other words are left out a block at a time, and lists are those of all scores."""
    r = np.random.default_rng(5)
    docs = [np.unique(r.integers(1000 * (i % 4), 1000 * (i % 4) + 300, 60)).astype(np.uint16) for i in range(1200)]
    docs += docs[:3]  # copies: ties go to smaller numbers
    n, sizes = len(docs), np.array([len(d) for d in docs])
    terms, ends, owner, place = np.concatenate(docs), np.r_[0, np.cumsum(sizes)], np.repeat(np.arange(n), sizes), np.arange(n)
    held = np.bincount(terms, minlength=65536)
    idf = np.log1p((n - held + 0.5) / (held + 0.5))
    counts = np.ones(len(terms), np.uint32)
    weight = packing.weights(terms, counts, owner, sizes, idf, sizes.mean())
    often = packing.frequent(held, n)
    column = packing.columns_of(often)
    rows = packing.matrix_of(terms, owner, weight, n, column, len(often))
    group = packing.groups(terms, owner, weight, n, packing.centres_of(rows), column)
    seeds = np.arange(40)[np.argsort(group[:40], kind="stable")]
    left = np.where(place % 7, sizes, 0)
    unused = np.flatnonzero(left)
    scorer, best = packing.Scorer(idf, sizes.mean()), [packing.Lists(len(seeds), 900)]
    for some in np.array_split(unused, 3):
        at = packing.runs(ends[some], sizes[some])
        blocks = list(scorer.blocks(some, group[some], terms[at], np.r_[0, np.cumsum(sizes[some])], counts[at], sizes[some]))
        asked = packing.runs(ends[seeds], sizes[seeds])
        scorer.look(best, blocks, seeds, terms[asked], np.r_[0, np.cumsum(sizes[seeds])], left)
    assert scorer.scored < len(seeds) * len(unused) / 2
    bounds = best[0].bounds()
    for i, seed in enumerate(seeds):
        score = np.array([weight[ends[d] : ends[d + 1]][np.isin(docs[d], docs[seed])].sum() if left[d] and d != seed else 0 for d in range(n)])
        want = np.argsort(-np.round(score, 4), kind="stable")
        want = want[: np.searchsorted(np.cumsum(left[want]), 900) + 1]
        got = best[0].docs[bounds[i] : bounds[i + 1]]
        assert len(got) == len(want) and score[got] == pytest.approx(score[want], abs=1e-3)
        assert left[got[:-1]].sum() < 900 <= left[got].sum()
    twin = np.flatnonzero(seeds == 1)[0]
    assert best[0].docs[bounds[twin]] == 1201  # its copy is the best of all


def test_texts_at_once_have_the_ids_of_each(edge):
    """Distinct chunks of a batch are merged in one call; ids are the library's."""
    words = np.random.default_rng(6).integers(0, 400, 3000)
    odd = [" a  b\n\t", "it's I'LL don't 12a-b..c", "3.5% (foo)", "a\x0bb", "\x01 a", "Ünï ÇA.", "İstanbul", " ".join(f"w{i}x{i % 7}. Ab{'c' * (i % 9)}" for i in words)]
    some = [t or "" for t in texts(edge).values()] + odd
    encoder = memo.json_encoder(WORD)
    for batch in (some, [""], [t for t in some if "<|" not in t and memo.PLAIN_LATIN.fullmatch(t)]):
        ids, sizes = encoder.many(batch)
        for t, got in zip(batch, np.split(ids, np.cumsum(sizes)[:-1]), strict=True):
            assert got.tolist() == library(WORD, t)


def test_likely_blocks_hold_nine_of_ten_neighbours(monkeypatch):
    """Recall against all scores where blocks are left out that are not likely to reach a list; near copies are found."""
    monkeypatch.setattr(packing, "FEW", 100)
    r = np.random.default_rng(7)
    p = 1 / np.arange(1, 401) ** 0.7
    bags = [1000 * (i % 4) + r.choice(400, int(r.lognormal(5, 0.8)) + 20, p=p / p.sum()) for i in range(6000)]
    bags += [np.r_[b[3:], 1000 * (i % 4)] for i, b in enumerate(bags[:200])]  # near copies
    found = [np.unique(b.astype(np.uint16), return_counts=True) for b in bags]
    n, lengths, sizes = len(bags), np.array([len(b) for b in bags]), np.array([len(t) for t, _ in found])
    terms, counts, owner, ends = np.concatenate([t for t, _ in found]), np.concatenate([c for _, c in found]), np.repeat(np.arange(n), sizes), np.r_[0, np.cumsum(sizes)]
    held = np.bincount(terms, minlength=65536)
    idf = np.log1p((n - held + 0.5) / (held + 0.5))
    weight = packing.weights(terms, counts, owner, lengths, idf, lengths.mean())
    often = packing.frequent(held, n)
    column = packing.columns_of(often)
    rows = packing.matrix_of(terms, owner, weight, n, column, len(often))
    group = packing.groups(terms, owner, weight, n, packing.centres_of(rows[:2048]), column)
    seeds = np.arange(400)[np.argsort(group[:400], kind="stable")]
    asked = packing.runs(ends[seeds], sizes[seeds])
    scorer, best = packing.Scorer(idf, lengths.mean(), packing.SPREAD), [packing.Lists(len(seeds), 5000)]
    blocks = list(scorer.blocks(np.arange(n), group, terms, ends, counts, lengths))
    scorer.look(best, blocks, seeds, terms[asked], np.r_[0, np.cumsum(sizes[seeds])], lengths, group[seeds], np.bincount(owner, weight, n)[seeds])
    assert scorer.scored < len(seeds) * n / 4
    full, bounds, recall, copies = np.zeros((n, 4000), np.float32), best[0].bounds(), [], []
    full[owner, terms] = weight
    for i, seed in enumerate(seeds):
        score = full[:, found[seed][0]].sum(axis=1)
        score[seed] = -1
        got = best[0].docs[bounds[i] : bounds[i + 1]]
        want = np.argsort(-score, kind="stable")[: min(10, len(got))]
        recall.append(np.isin(want, got).mean())
        if seed < 200:
            copies.append(seed + 6000 in got)
    assert np.mean(recall) >= 0.9 and np.mean(copies) >= 0.9


def test_rounds_leave_out_no_block_that_can_reach_a_list(spark, monkeypatch):
    """The scorer that op9 and the pipeline's packing give to tasks finds each seed's best documents, all of them, on parts of any size."""
    given, context = [], type(spark.sparkContext)
    broadcast = context.broadcast
    monkeypatch.setattr(context, "broadcast", lambda self, value: given.append(value) or broadcast(self, value))
    texts = [(i, " ".join(f"word{(i * 7 + j) % 50}" for j in range(40))) for i in range(30)]
    assert packing.packed(spark.createDataFrame(texts, "doc_id long, text string"), WORD, window=256, shard_tokens=1000).count() >= 30
    spread = next(v.spread for v in given if isinstance(v, packing.Scorer))
    monkeypatch.setattr(packing, "FEW", 100)
    r = np.random.default_rng(8)
    p = 1 / np.arange(1, 401) ** 0.7
    found = [np.unique((1000 * (i % 4) + r.choice(400, int(r.lognormal(5, 0.8)) + 20, p=p / p.sum())).astype(np.uint16), return_counts=True) for i in range(3000)]
    n, lengths, sizes = len(found), np.array([c.sum() for _, c in found]), np.array([len(t) for t, _ in found])
    terms, counts, owner, ends = np.concatenate([t for t, _ in found]), np.concatenate([c for _, c in found]), np.repeat(np.arange(n), sizes), np.r_[0, np.cumsum(sizes)]
    held = np.bincount(terms, minlength=65536)
    idf = np.log1p((n - held + 0.5) / (held + 0.5))
    weight = packing.weights(terms, counts, owner, lengths, idf, lengths.mean())
    often = packing.frequent(held, n)
    column = packing.columns_of(often)
    group = packing.groups(terms, owner, weight, n, packing.centres_of(packing.matrix_of(terms, owner, weight, n, column, len(often))[:2048]), column)
    seeds = np.arange(200)[np.argsort(group[:200], kind="stable")]
    scorer, best = packing.Scorer(idf, lengths.mean(), spread), [packing.Lists(len(seeds), 5000)]
    blocks = list(scorer.blocks(np.arange(n), group, terms, ends, counts, lengths))
    scorer.look(best, blocks, seeds, terms[packing.runs(ends[seeds], sizes[seeds])], np.r_[0, np.cumsum(sizes[seeds])], lengths, group[seeds], np.bincount(owner, weight, n)[seeds])
    full, bounds = np.zeros((n, 4000), np.float32), best[0].bounds()
    full[owner, terms] = weight
    for i, seed in enumerate(seeds):
        score = full[:, found[seed][0]].sum(axis=1)
        score[seed] = -1
        got = best[0].docs[bounds[i] : bounds[i + 1]]
        assert len(got) and score[got] == pytest.approx(np.sort(score)[::-1][: len(got)], abs=1e-2) and lengths[got].sum() >= 5000


def test_pipeline_packs_by_exact_bounds(spark, monkeypatch):
    """The pipeline's last stage gives its tasks a scorer that leaves out no block by likelihood."""
    import corpus_pipeline

    given, context = [], type(spark.sparkContext)
    broadcast = context.broadcast
    monkeypatch.setattr(context, "broadcast", lambda self, value: given.append(value) or broadcast(self, value))
    docs = spark.createDataFrame([(i, f"some words of text {i}") for i in range(5)], "doc_id long, text string")
    assert corpus_pipeline.packing(spark, docs, "").count() >= 5
    scorers = [v for v in given if isinstance(v, packing.Scorer)]
    assert scorers and all(s.spread is None for s in scorers)
