"""Sets of word shingles as sorted 64-bit hashes, many texts at once."""

from __future__ import annotations

import functools

import numpy as np

from .common import claim

WIDTH = 5
U64 = np.uint64
AT_ONCE = 1 << 19  # bytes hashed together


def _table(seed: int, n: int) -> np.ndarray:
    return np.random.default_rng(seed).integers(0, 1 << 63, n, dtype=np.uint64) * U64(2) + U64(1)


BYTE = _table(20240101, 256)
BYTE[np.arange(65, 91)] = BYTE[np.arange(97, 123)]  # A-Z as a-z
PLACE = _table(20240102, WIDTH + 1)
SEPARATOR = np.zeros(256, bool)
SEPARATOR[[32, *range(9, 14)]] = True
BASE = U64(0x9E3779B97F4A7C15)


def mixed(x: np.ndarray) -> np.ndarray:
    """Every bit depends on all bits (a public 64-bit finaliser)."""
    x = (x ^ (x >> U64(30))) * U64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> U64(27))) * U64(0x94D049BB133111EB)
    return x ^ (x >> U64(31))


@functools.lru_cache(maxsize=1)
def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    base = np.full(n, BASE)
    base[0] = 1
    back = np.full(n, U64(pow(int(BASE), -1, 1 << 64)))
    back[0] = 1
    return np.cumprod(base), np.cumprod(back)


def _raw(joined: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Start, length and polynomial of each word of some bytes."""
    n = len(joined)
    up, down = _powers(1 << max(int(n).bit_length(), 20))
    edge = np.flatnonzero(np.diff(np.r_[True, SEPARATOR[joined], True].view(np.int8)))
    starts, ends = edge[0::2], edge[1::2]
    total = np.zeros(n + 1, np.uint64)
    np.cumsum(BYTE[joined] * up[:n], out=total[1:])
    return starts, ends - starts, (total[ends] - total[starts]) * down[starts]


def _words(raw: np.ndarray, size: np.ndarray) -> np.ndarray:
    return mixed(raw + size.astype(np.uint64))


def _grams(words: np.ndarray) -> np.ndarray:
    """Hash of the five words from each place on."""
    n = len(words) - WIDTH + 1
    return mixed(sum((words[k : n + k] * PLACE[k] for k in range(1, WIDTH)), words[:n] * PLACE[0])) if n > 0 else np.empty(0, U64)


def _set(words: np.ndarray, grams: np.ndarray) -> np.ndarray:
    if len(words) >= WIDTH:
        g = np.sort(grams)
        return g[np.r_[True, g[1:] != g[:-1]]]
    if len(words):
        short = np.concatenate([words * PLACE[: len(words)], PLACE[WIDTH:] * np.array([len(words)], np.uint64)])
        return mixed(short.sum(dtype=np.uint64, keepdims=True))
    return np.empty(0, U64)


def _sets(blobs: list[bytes]) -> list[np.ndarray]:
    starts, size, raw = _raw(np.frombuffer(b"\n".join(blobs) + b"\n", np.uint8))
    words = _words(raw, size)
    grams = _grams(words)
    first = np.r_[0, np.cumsum([len(b) + 1 for b in blobs])]
    bounds = np.searchsorted(starts, first)
    return [_set(words[a:b], grams[a : max(b - WIDTH + 1, a)]) for a, b in zip(bounds[:-1], bounds[1:], strict=True)]


def _long_set(blob: bytes) -> np.ndarray:
    """The set of one text in parts: beyond its words' hashes, the memory of AT_ONCE bytes. A word may span parts."""
    words, left = [], None  # left: polynomial and length of a word that may go on
    for i in range(0, len(blob), AT_ONCE):
        part = np.frombuffer(blob, np.uint8, min(AT_ONCE, len(blob) - i), i)
        starts, size, raw = _raw(part)
        if left is not None:
            if len(starts) and starts[0] == 0:
                raw[:1] = raw[:1] * U64(pow(int(BASE), left[1], 1 << 64)) + U64(left[0])
                size[0] += left[1]
            else:
                raw, size = np.r_[U64(left[0]), raw], np.r_[left[1], size]
        left = None
        if not SEPARATOR[part[-1]]:
            left, raw, size = (int(raw[-1]), int(size[-1])), raw[:-1], size[:-1]
        words.append(_words(raw, size))
    if left is not None:
        words.append(_words(np.array([left[0]], U64), np.array([left[1]])))
    own = np.concatenate(words)
    return _set(own, _grams(own))


def shingle_sets(texts: list[str]) -> list[np.ndarray]:
    """Of each text its distinct five-word shingles; fewer words: all of them as one; none: empty."""
    claim("shingles")
    out: list[np.ndarray] = []
    held: list[bytes] = []
    size = 0
    for t in texts:
        blob = t.encode()
        if len(blob) > AT_ONCE:
            out += [*(_sets(held) if held else []), _long_set(blob)]
            held, size = [], 0
            continue
        held.append(blob)
        size += len(blob) + 1
        if size >= AT_ONCE:
            out += _sets(held)
            held, size = [], 0
    return out + (_sets(held) if held else [])


def fingerprint(s: np.ndarray) -> tuple[int, int]:
    """128 bits that equal sets share, as two signed words."""
    both = np.array([s.sum(dtype=np.uint64), mixed(s ^ BASE).sum(dtype=np.uint64)], np.uint64)
    a, b = both.view(np.int64)
    return int(a), int(b)
