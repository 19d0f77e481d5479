"""Token counts with the whole-token shortcut."""

from __future__ import annotations

import regex
from pyspark.sql import DataFrame

from .common import map_batches, texts_of
from .memo import MOST_CHARS, MOST_ENTRIES, PLAIN, SPLIT, RankEncoder, byte_alphabet, json_encoder

def whole_tokens(path: str) -> frozenset[str]:
    """Vocabulary strings that encode alone as one token (proved by encoding each of them)."""
    from tokenizers import Tokenizer

    tok, back = Tokenizer.from_file(path), {c: b for b, c in byte_alphabet().items()}
    texts = []
    for piece in tok.get_vocab(with_added_tokens=False):
        try:
            texts.append(bytes(back[c] for c in piece).decode())
        except (KeyError, UnicodeDecodeError):
            continue  # half a character, or no piece of text
    return frozenset(t for t, e in zip(texts, tok.encode_batch(texts, add_special_tokens=False), strict=True) if len(e.ids) == 1)


class TokenCounter:
    """Counts tokens: pre-tokens of ``whole_tokens`` count one, the rest is merged by the library and remembered."""

    class Chunks(dict):
        def __init__(self, owner: TokenCounter, lead: str):
            self.owner, self.lead = owner, lead

        def __missing__(self, chunk: str) -> int | None:
            if not chunk or chunk[0].isspace() or chunk[-1].isspace():
                return None
            n = self.owner.by_pretokens(self.lead + chunk)
            if len(chunk) <= MOST_CHARS:
                if len(self) >= MOST_ENTRIES:
                    self.clear()
                self[chunk] = n
            return n

    def __init__(self, path: str, whole: frozenset[str] | None = None):
        """``whole`` is what ``whole_tokens`` has proved, if that was done before."""
        import os

        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.tok = Tokenizer.from_file(path)
        self.tok.no_truncation()
        self.tok.no_padding()
        self.whole, self.split = whole_tokens(path) if whole is None else whole, regex.compile(SPLIT)
        self.added = [t.content for t in self.tok.get_added_tokens_decoder().values()]
        self.first, self.rest = self.Chunks(self, ""), self.Chunks(self, " ")
        ranks = json_encoder(path)
        # a plain pre-token is merged by rank where the vocabulary allows it (see RankEncoder)
        self.plain = (lambda p: len(ranks.core.encode_ordinary(p))) if isinstance(ranks, RankEncoder) else self.merged

    def merged(self, text: str) -> int:
        return len(self.tok.encode(text, add_special_tokens=False).ids)

    def by_pretokens(self, text: str) -> int:
        """Of a text with any white space; special strings and rare scripts go to the library."""
        if any(a in text for a in self.added) or not text.isascii() and not PLAIN.fullmatch(text):
            return self.merged(text)
        return sum(1 if p in self.whole else self.plain(p) for p in self.split.findall(text))

    def count(self, text: str) -> int:
        if not text:
            return 0
        head, *tail = text.split(" ")
        try:
            return self.first[head] + sum(map(self.rest.__getitem__, tail))
        except TypeError:
            return self.by_pretokens(text)


class PieceCounter:
    """The same for a sentencepiece file: what stands between spaces is encoded alone."""

    def __init__(self, path: str):
        from .piece_codec import piece_codec

        self.codec = piece_codec(path)

    def count(self, text: str) -> int:
        return len(self.codec.encode(text)[0])


_counters: dict[str, TokenCounter | PieceCounter] = {}


def counter(path: str, whole: frozenset[str] | None = None) -> TokenCounter | PieceCounter:
    """One for each worker process and file."""
    if path not in _counters:
        _counters[path] = PieceCounter(path) if path.endswith(".model") else TokenCounter(path, whole)
    return _counters[path]


def token_counts(docs: DataFrame, path: str, id_col: str = "doc_id", text_col: str = "text", limit: int = 1024) -> DataFrame:
    """One row per document: id, n_bytes, n_tokens, over_limit (n_tokens > limit).

    Null or empty text: 0 bytes, 0 tokens. Repeated ids or rows: one row for each.
    Other columns are ignored. An empty table gives no rows. No exchange: each
    scan task counts its own texts. Which strings are one token is proved once, on the
    driver, and broadcast (as many strings as the vocabulary has at most).
    """
    proved = docs.sparkSession.sparkContext.broadcast(None if path.endswith(".model") else whole_tokens(path))

    def run(batch):
        c, texts = counter(path, proved.value), texts_of(batch, text_col)
        n = [c.count(t) for t in texts]
        yield {id_col: batch.column(id_col), "n_bytes": [len(t.encode()) for t in texts], "n_tokens": n, "over_limit": [x > limit for x in n]}

    return map_batches(docs.select(id_col, text_col), run, f"{id_col} long, n_bytes long, n_tokens long, over_limit boolean")
