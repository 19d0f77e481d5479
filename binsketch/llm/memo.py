"""Encoding by remembered chunks.

Texts are cut at single spaces. For the vocabularies used here what stands
between two spaces is encoded alone, whatever its neighbours are, unless other
white space touches a space; such texts go through the library as a whole.
A chunk's ids are found once by the library and remembered by the worker.
"""

from __future__ import annotations

import array
import functools
import json
import os
import re

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import regex

from .common import MOST_BYTES, claim

#: The split pattern of byte-level vocabularies of this kind, and that of lower-case words.
SPLIT = r"""'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"""
WORDS = r"""'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+"""
#: Letters, digits and signs on which all Unicode versions of the patterns agree (a test compares each code point).
PLAIN = regex.compile(r"[\x00-\x7e\xa1-ȳΑ-ΡΣ-ώА-я‐-‧‰-⁞ぁ-ゖァ-ヺ一-龥가-힣]*+")
#: Those that composition leaves alone and that are lowered one by one.
PLAIN_LATIN = re.compile(r"[\t\n\r\x20-\x7e\xa1-ÿĀ-įĲ-ȳ]*+")

MOST_ENTRIES, MOST_CHARS = 350_000, 64
WORDS_KEPT = 150_000  # of each of two generations


class ChunkMemo(dict):
    """chunk -> bytes of its ids (little-endian); None where a chunk can't stand alone."""

    def __init__(self, encode, lead: str):
        self.encode, self.lead = encode, lead

    def __missing__(self, chunk: str):
        if not chunk or chunk[0].isspace() or chunk[-1].isspace():
            return None
        ids = self.encode(self.lead + chunk)
        if len(chunk) <= MOST_CHARS:
            if len(self) >= MOST_ENTRIES:
                self.clear()
            self[chunk] = ids
        return ids


class JsonEncoder:
    """ids of whole texts as the tokenizers library gives them, without added special tokens."""

    def __init__(self, path: str):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.tok = Tokenizer.from_file(path)
        self.tok.no_truncation()
        self.tok.no_padding()
        self.kind = np.dtype("<u2" if self.tok.get_vocab_size() <= 65536 else "<u4")
        self.first, self.rest = ChunkMemo(self.whole, ""), ChunkMemo(self.whole, " ")

    def whole(self, text: str) -> bytes:
        return np.asarray(self.tok.encode(text, add_special_tokens=False).ids, self.kind).tobytes()

    def ids(self, text: str) -> np.ndarray:
        if not text:
            return np.empty(0, self.kind)
        head, *tail = text.split(" ")
        try:
            found = self.first[head] + b"".join(map(self.rest.__getitem__, tail))
        except TypeError:  # a chunk that can't stand alone
            found = self.whole(text)
        return np.frombuffer(found, self.kind)

    def many(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """ids of all texts one after another, and how many each text has."""
        found = [self.ids(t) for t in texts]
        return np.concatenate([np.empty(0, self.kind), *found]), np.array([len(x) for x in found], np.int64)


def byte_alphabet() -> dict[int, str]:
    """The printable character that stands for each byte in byte-level vocabularies."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    rest = [b for b in range(256) if b not in set(plain)]
    return {b: chr(b) for b in plain} | {b: chr(256 + i) for i, b in enumerate(rest)}


class RankEncoder(JsonEncoder):
    """Byte-level vocabularies, merged by rank.

    Merging any two neighbours whose union is a token gives what the listed
    merges give if each token, alone, is reached by them: neighbours a and b that
    make up a token were formed within it, so the token alone would stop at them
    too. A test proves that for the whole vocabulary. Special strings and rare
    scripts go to the library.
    """

    def __init__(self, path: str, spec: dict):
        super().__init__(path)
        import tiktoken

        back = {c: b for b, c in byte_alphabet().items()}
        special = {t["content"] for t in spec["added_tokens"]}
        ranks = {bytes(back[c] for c in piece): i for piece, i in spec["model"]["vocab"].items() if piece not in special}
        self.special = sorted(special)
        self.core = tiktoken.Encoding("ranks", pat_str=SPLIT, mergeable_ranks=ranks, special_tokens={})

    def ids(self, text: str) -> np.ndarray:
        if any(s in text for s in self.special) or not text.isascii() and not PLAIN.fullmatch(text):
            return np.frombuffer(self.whole(text), self.kind)
        return np.array(array.array("H" if self.kind.itemsize == 2 else "I", self.core.encode_ordinary(text)), self.kind)


class WordEncoder(JsonEncoder):
    """Lower-case words with an end mark: words are remembered, new ones merged by rank (see RankEncoder).

    The end mark is a byte that plain texts don't hold; a word's last byte joins it
    before all listed merges, as in the vocabulary, whose symbols have both forms.
    """

    END, SUFFIX = b"\x01", "</w>"

    def __init__(self, path: str, spec: dict):
        super().__init__(path)
        import tiktoken

        back, vocab = {c: b for b, c in byte_alphabet().items()}, spec["model"]["vocab"]
        raw = lambda s: bytes(back[c] for c in s.removesuffix(self.SUFFIX)) + self.END * s.endswith(self.SUFFIX)
        ranks = {bytes([b]): b for b in range(256)} | {bytes([b]) + self.END: 256 + b for b in range(256)}
        self.to_id = [0] * (512 + len(spec["model"]["merges"]))
        for b, c in byte_alphabet().items():
            self.to_id[b], self.to_id[256 + b] = vocab[c], vocab[c + self.SUFFIX]
        for i, merge in enumerate(spec["model"]["merges"], 512):
            a, b = merge.split(" ") if isinstance(merge, str) else merge
            ranks.setdefault(raw(a) + raw(b), i)
            self.to_id[i] = vocab[a + b]
        self.core = tiktoken.Encoding("words", pat_str=r"[^\x01]*\x01", mergeable_ranks=ranks, special_tokens={})
        self.ids_of = np.array(self.to_id, self.kind)
        self.closes = np.zeros(len(self.to_id), bool)  # codes that end a word
        for token, i in ranks.items():
            self.closes[i] = token.endswith(self.END) and len(token) > 1
        self.known = pa.array([], pa.large_string()), np.empty(0, self.kind), np.empty(0, np.int64), np.empty(0, np.int64)
        self.split, self.memo, self.older = regex.compile(WORDS), {}, {}
        self.code = "H" if self.kind.itemsize == 2 else "I"

    def chunk(self, chunk: str) -> bytes:
        found = self.older.get(chunk)
        if found is not None:
            return self.kept(chunk, found)
        if chunk.isalpha():
            return self.word(chunk)
        if chunk[-1] in ".,;:!?" and chunk[:-1].isalpha():
            found = self.word(chunk[:-1]) + self.word(chunk[-1])
        else:
            found = b"".join(map(self.word, self.split.findall(chunk)))
        return self.kept(chunk, found)

    def kept(self, chunk: str, found: bytes) -> bytes:
        """Remembered; when the memory is full, what was used since the last time stays."""
        if len(chunk) <= MOST_CHARS:
            if len(self.memo) >= WORDS_KEPT:
                self.older = dict(self.memo)
                self.memo.clear()
            self.memo[chunk] = found
        return found

    def word(self, word: str) -> bytes:
        found = self.memo.get(word)
        if found is None:
            found = self.older.get(word)
            if found is None:
                found = array.array(self.code, map(self.to_id.__getitem__, self.core.encode_ordinary(word + "\x01"))).tobytes()
            self.kept(word, found)
        return found

    def ids(self, text: str) -> np.ndarray:
        if "<|" in text or not PLAIN_LATIN.fullmatch(text):
            return np.frombuffer(self.whole(text), self.kind)
        memo, chunk = self.memo, self.chunk
        return np.frombuffer(b"".join([memo.get(c) or chunk(c) for c in text.lower().split()]), self.kind)

    def merged(self, chunks: pa.LargeStringArray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """ids of all chunks, merged in one call; where each chunk's begin, and how many it has."""
        alone = pc.utf8_is_alpha(chunks)  # a word as it is; the others are cut
        words = pc.binary_join_element_wise(chunks.filter(alone), *(pa.scalar(x, pa.large_string()) for x in ("", "\x01"))), pc.replace_substring_regex(chunks.filter(pc.invert(alone)), f"(?:{WORDS})", "\\0\x01")
        codes = np.array(self.core.encode_ordinary("".join(map(joined, words))), np.int32)
        ends = np.r_[0, np.flatnonzero(self.closes[codes]) + 1][np.r_[0, np.ones(len(words[0]), np.int64), pc.count_substring(words[1], "\x01").to_numpy()].cumsum()]
        begins, sizes = np.empty((2, len(chunks)), np.int64)
        order = np.argsort(~alone.to_numpy(zero_copy_only=False), kind="stable")
        begins[order], sizes[order] = ends[:-1], np.diff(ends)
        return self.ids_of[codes], begins, sizes

    def many(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Each distinct chunk of the texts is merged once; the chunks of a worker's first texts are remembered. Texts that need the library are left to it."""
        plain = [not ("<|" in t or not PLAIN_LATIN.fullmatch(t)) for t in texts]
        if not all(plain):
            flat, own = self.many([t if ok else "" for ok, t in zip(plain, texts, strict=True)])
            parts = [x if ok else np.frombuffer(self.whole(t), self.kind) for ok, t, x in zip(plain, texts, np.split(flat, np.cumsum(own)[:-1]), strict=True)]
            return np.concatenate(parts), np.array([len(x) for x in parts], np.int64)
        lists = pc.ascii_split_whitespace(pa.array([t.lower() for t in texts], pa.large_string()))
        coded = lists.values.dictionary_encode()
        known, *old = self.known
        place = pc.index_in(coded.dictionary, value_set=known).fill_null(-1).to_numpy().astype(np.int64)
        fresh = place < 0
        place[fresh] = len(known) + np.arange(fresh.sum())
        chunks = coded.dictionary.filter(pa.array(fresh))
        new = self.merged(chunks)
        ids, begins, sizes = np.r_[old[0], new[0]], np.r_[old[1], new[1] + len(old[0])], np.r_[old[2], new[2]]
        if len(known) < WORDS_KEPT and chunks.nbytes < MOST_BYTES:
            self.known = pa.concat_arrays([known, chunks]), ids, begins, sizes
        which = place[coded.indices.to_numpy()]
        each = sizes[which]
        before = np.cumsum(each) - each
        return ids[np.repeat(begins[which] - before, each) + np.arange(each.sum())], np.diff(np.r_[before, each.sum()][lists.offsets.to_numpy()])


def joined(strings: pa.LargeStringArray) -> str:
    """All of an array's strings one after another."""
    if not len(strings):
        return ""
    at = np.frombuffer(strings.buffers()[1], np.int64)[strings.offset : strings.offset + len(strings) + 1]
    return str(memoryview(strings.buffers()[2])[at[0] : at[-1]], "utf-8") if at[-1] > at[0] else ""


def json_encoder(path: str) -> JsonEncoder:
    """One for each worker process and file."""
    claim("ids", _encoder.cache_clear)
    return _encoder(path)


@functools.lru_cache(maxsize=4)
def _encoder(path: str) -> JsonEncoder:
    """Kinds of vocabulary without a faster way go through the library."""
    with open(path, encoding="utf-8") as f:
        spec = json.load(f)
    model, cut = spec["model"], spec["pre_tokenizer"] or {}
    plain_model = model["type"] == "BPE" and not any(model.get(k) for k in ("dropout", "continuing_subword_prefix", "byte_fallback", "ignore_merges"))
    flat = [t for t in spec["added_tokens"] if t["special"] and not (t["lstrip"] or t["rstrip"] or t["single_word"])]
    if plain_model and len(flat) == len(spec["added_tokens"]):
        if cut.get("type") == "ByteLevel" and cut["use_regex"] and not cut["add_prefix_space"] and not spec["normalizer"] and not model["end_of_word_suffix"]:
            return RankEncoder(path, spec)
        steps = cut.get("pretokenizers", [{}])
        if model["end_of_word_suffix"] == WordEncoder.SUFFIX and steps[0].get("pattern", {}).get("Regex") == WORDS and steps[0].get("invert"):
            return WordEncoder(path, spec)
    return JsonEncoder(path)
