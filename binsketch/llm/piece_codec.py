"""Sentencepiece encoding that keeps byte offsets, and decoding.

The model file is read as a plain protocol message; its compiled character map
is a trie of longest prefixes to replacements, which ``CharMap`` walks, so that
each normalised byte knows the original bytes it came from. Between word marks
pieces never join, so each stretch (marks, then other characters) is encoded
alone, once per worker, with the lengths of its pieces in bytes.
"""

from __future__ import annotations

import functools
import hashlib
import re

import numpy as np
from pyspark.sql import DataFrame

from .common import map_batches, texts_of
from .memo import MOST_CHARS, MOST_ENTRIES

MARK = "▁"  # stands for a space in pieces
STRETCH = re.compile(f"{MARK}+[^{MARK}]*")


class CharMap:
    """Longest-prefix replacement by the compiled map (a double-array trie, then zero-ended strings)."""

    def __init__(self, blob: bytes):
        if blob:
            n = int.from_bytes(blob[:4], "little")
            self.units, self.strings = np.frombuffer(blob[4 : 4 + n], "<u4"), blob[4 + n :]
        else:
            self.units, self.strings = np.empty(0, "<u4"), b""

    def longest(self, data: bytes, at: int) -> tuple[int, bytes] | None:
        """Length of the longest key that starts at ``at``, and its replacement."""
        if not len(self.units):
            return None
        units, found = self.units, None
        node = self._jump(int(units[0]))
        for i in range(at, len(data)):
            node ^= data[i]
            unit = int(units[node])
            if unit & 0x800000FF != data[i]:
                break
            node ^= self._jump(unit)
            if unit >> 8 & 1:
                found = i + 1 - at, int(units[node]) & 0x7FFFFFFF
        if found is None:
            return None
        return found[0], self.strings[found[1] : self.strings.index(b"\0", found[1])]

    @staticmethod
    def _jump(unit: int) -> int:
        return unit >> 10 << ((unit & 0x200) >> 6)

    def normalise(self, data: bytes) -> tuple[bytes, np.ndarray]:
        """Replaced bytes, and for each of them (and the end) the original byte it came from."""
        if not len(self.units):
            return data, np.arange(len(data) + 1)
        out, source, at = bytearray(), [], 0
        while at < len(data):
            hit = self.longest(data, at)
            if hit is None:
                lead = data[at]
                step = 1 if lead < 0x80 else 2 if lead < 0xE0 else 3 if lead < 0xF0 else 4
                hit = step, data[at : at + step]
            out += hit[1]
            source += [at] * len(hit[1])
            at += hit[0]
        return bytes(out), np.array([*source, at])


class PieceCodec:
    """Encoder and decoder of one model file; ``memo`` maps a stretch to its ids and piece lengths."""

    def __init__(self, path: str):
        import sentencepiece
        from sentencepiece import sentencepiece_model_pb2

        self.lib = sentencepiece.SentencePieceProcessor(model_file=path)
        spec = sentencepiece_model_pb2.ModelProto()
        spec.ParseFromString(self.lib.serialized_model_proto())
        norm = spec.normalizer_spec
        self.chars, self.prefix = CharMap(norm.precompiled_charsmap), norm.add_dummy_prefix
        self.trims = norm.remove_extra_whitespaces
        split = not any(MARK in p.piece.lstrip(MARK) for p in spec.pieces) and not spec.trainer_spec.treat_whitespace_as_suffix
        self.local = split and spec.trainer_spec.model_type == 2 and norm.escape_whitespaces and self.prefix and not self.trims and not len(self.chars.units) and not any(p.type in (4, 5) for p in spec.pieces)
        self.pieces = [p.piece for p in spec.pieces]
        self.width = [1 if p.type == 6 else len(p.piece.encode()) - 2 * p.piece.count(MARK) for p in spec.pieces]
        self.unknown = self.lib.unk_id()
        self.kind = np.dtype("<u2" if len(self.pieces) <= 65536 else "<u4")
        self.memo: dict[str, tuple[bytes, bytes]] = {}

    def stretch(self, chunk: str) -> tuple[bytes, bytes]:
        """ids and lengths of what follows one mark; a leading space in it is one more mark."""
        ids = self.lib.encode(chunk) if chunk else [self.lib.piece_to_id(MARK)]
        lengths = [self.width[i] for i in ids]
        if self.unknown in ids:
            lengths = [s.end - s.begin + (k == 0) for k, s in enumerate(self.spans_of(chunk))]
        found = np.asarray(ids, self.kind).tobytes(), np.asarray(lengths, "<u4").tobytes()
        if len(chunk) <= MOST_CHARS:
            if len(self.memo) >= MOST_ENTRIES:
                self.memo.clear()
            self.memo[chunk] = found
        return found

    def spans_of(self, text: str):
        """The library's own spans, in bytes of the text."""
        return self.lib.encode(text, return_type="proto").pieces

    def encode(self, text: str) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """ids, and the byte offsets in the original text where pieces begin and end.

        The offsets are those of the text; the mark that the model puts before a
        text counts for no byte, each other mark for its space. Spaces that the
        normalisation drops at either end of the text belong to no piece.
        """
        if not text:
            return np.empty(0, self.kind), np.empty(0, np.int64), np.empty(0, np.int64)
        if not self.local or MARK in text:
            return self.general(text)
        if "  " in text or text[0] == " " or text[-1] == " ":  # runs of marks belong to what follows them
            chunks = [u[1:].replace(MARK, " ") for u in STRETCH.findall(MARK + text.replace(" ", MARK))]
        else:
            chunks = text.split(" ")
        memo, stretch = self.memo, self.stretch
        found = [memo.get(c) or stretch(c) for c in chunks]
        ids = np.frombuffer(b"".join([f[0] for f in found]), self.kind)
        ends = np.cumsum(np.frombuffer(b"".join([f[1] for f in found]), "<u4"), dtype=np.int64) - 1
        return ids, np.r_[0, ends[:-1]], ends

    def general(self, text: str) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Any model and text: the library's pieces over the mapped text, projected through the alignment."""
        proto = self.lib.encode(text, return_type="proto")
        ids = np.array([p.id for p in proto.pieces], self.kind)
        if not len(self.chars.units) and not self.trims:
            return ids, np.array([p.begin for p in proto.pieces], np.int64), np.array([p.end for p in proto.pieces], np.int64)
        mapped, source = self.chars.normalise(text.encode())
        return ids, *self.projected(proto.pieces, mapped, source)

    def projected(self, pieces, mapped: bytes, source: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Begins and ends of pieces in original bytes: walk the mapped bytes; spaces dropped at the ends belong to no piece."""
        begins, ends, at = [], [], 0
        for n, p in enumerate(pieces):
            surface, before = p.piece.replace(MARK, " ").encode(), at
            if self.pieces[p.id] != p.piece and p.id != self.unknown or p.piece.startswith("<0x"):
                surface = mapped[at : at + 1]
            if self.trims:
                while at < len(mapped) and mapped[at : at + 1] == b" " and (n == 0 or not surface.startswith(b" ") or mapped[at + 1 : at + 2] == b" "):
                    at += 1
            if n == 0 and self.prefix and surface.startswith(b" "):  # the mark before a text is no byte of it
                surface = surface[1:]
            begins.append(source[before if n else at])  # a run of spaces goes to the piece that follows it
            at = min(at + len(surface), len(mapped))
            ends.append(source[at])
        return np.array(begins, np.int64), np.array(ends, np.int64)

    def decode(self, ids: list[int]) -> str:
        return self.lib.decode(ids)


@functools.lru_cache(maxsize=4)
def piece_codec(path: str) -> PieceCodec:
    return PieceCodec(path)


def piece_encode(docs: DataFrame, path: str, id_col: str = "doc_id", text_col: str = "text", begin: bool = True, end: bool = True) -> DataFrame:
    """One row per document: id, ids array<int>, begins and ends array<long> (byte offsets of each piece in the original text; begin id 0 to 0, end id
    from the length to the length).

    Null or empty text gives the begin and end ids only. Repeated rows stay, other columns are ignored.
    """

    def run(batch):
        codec, ids, begins, ends = piece_codec(path), [], [], []
        for t in texts_of(batch, text_col):
            i, b, e = codec.encode(t)
            size = len(t.encode())
            ids.append([codec.lib.bos_id()] * begin + i.tolist() + [codec.lib.eos_id()] * end)
            begins.append([0] * begin + b.tolist() + [size] * end)
            ends.append([0] * begin + e.tolist() + [size] * end)
        yield {id_col: batch.column(id_col), "ids": ids, "begins": begins, "ends": ends}

    return map_batches(docs.select(id_col, text_col), run, f"{id_col} long, ids array<int>, begins array<long>, ends array<long>")


def piece_decode(coded: DataFrame, path: str, id_col: str = "doc_id", ids_col: str = "ids") -> DataFrame:
    """One row per document: id and the library's text of its ids (null ids: empty text)."""

    def run(batch):
        codec = piece_codec(path)
        yield {id_col: batch.column(id_col), "text": [codec.decode(list(i or [])) for i in batch.column(ids_col).to_pylist()]}

    return map_batches(coded.select(id_col, ids_col), run, f"{id_col} long, text string")


def piece_digests(docs: DataFrame, path: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Round trip in one pass, ids staying in the worker: id, n_tokens, ids_sha256, decoded_sha256, n_span_bytes.

    Ids are hashed with begin and end ids as little-endian unsigned 32-bit
    integers; the text is what decode gives for them; n_span_bytes is where the
    last piece ends. Null or empty text: two ids, empty text. Repeated rows stay.
    """

    def run(batch):
        codec, out = piece_codec(path), {k: [] for k in ("n_tokens", "ids_sha256", "decoded_sha256", "n_span_bytes")}
        bos, eos = codec.lib.bos_id(), codec.lib.eos_id()
        for t in texts_of(batch, text_col):
            ids, _, ends = codec.encode(t)
            full = np.empty(len(ids) + 2, "<u4")
            full[0], full[1:-1], full[-1] = bos, ids, eos
            out["n_tokens"].append(len(full))
            out["ids_sha256"].append(hashlib.sha256(full.tobytes()).hexdigest())
            out["decoded_sha256"].append(hashlib.sha256(codec.decode(full.tolist()).encode()).hexdigest())
            out["n_span_bytes"].append(int(ends[-1]) if len(ends) else 0)
        yield {id_col: batch.column(id_col)} | out

    return map_batches(docs.select(id_col, text_col), run, f"{id_col} long, n_tokens long, ids_sha256 string, decoded_sha256 string, n_span_bytes long")
