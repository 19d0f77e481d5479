"""Two-stage suffix sorting in numpy, to a fixed depth, and the common prefixes of neighbours.

Stage one sorts the suffixes that are smaller than their successors, word by
word. Stage two scans the buckets of first bytes upward: each suffix that is
placed puts its predecessor, if that one is larger than it, into the next place
of the predecessor's bucket. A bucket is taken as a whole, with further rounds
for runs of its own byte.
"""

from __future__ import annotations

import numpy as np

PAD = 8


def words_at(text: np.ndarray, depth: int) -> np.ndarray:
    """The eight bytes from each place on, as numbers that compare like the bytes; zeros follow the text."""
    room = np.concatenate([text, np.zeros(depth + PAD, np.uint8)])
    return np.lib.stride_tricks.as_strided(room, (len(text) + depth, 8), (1, 1)).copy().view(">u8").ravel().astype(np.uint64)


def smaller_than_next(text: np.ndarray) -> np.ndarray:
    """Whether each suffix is smaller than its successor; the last one is larger than nothing."""
    n = len(text)
    out = np.zeros(n, bool)
    if n < 2:
        return out
    change = np.flatnonzero(text[1:] != text[:-1])  # the last places of runs
    if not len(change):
        return out
    at = np.searchsorted(change, np.arange(change[-1] + 1))
    end = change[at]
    out[: change[-1] + 1] = text[end] < text[end + 1]
    return out


def direct_order(starts: np.ndarray, words: np.ndarray, depth: int) -> np.ndarray:
    """``starts`` by the bytes that follow them, ``depth`` at most.

    Only ties look at further words, and of them only groups in which a word differs are sorted again.
    """
    starts = starts[np.argsort(words[starts], kind="stable")]
    key = words[starts]
    same = np.r_[False, key[1:] == key[:-1]][: len(starts)]  # as the one before, so far
    tied = np.flatnonzero(same | np.r_[same[1:], False][: len(starts)])
    for at in range(8, depth, 8):
        if not len(tied):
            break
        own, head = starts[tied], ~same[tied]
        key, group = words[own + min(at, depth - 8)], np.cumsum(head) - 1
        open_ = np.zeros(group[-1] + 1, bool)
        open_[group[1:][(key[1:] != key[:-1]) & ~head[1:]]] = True
        some = np.flatnonzero(open_[group])
        if len(some):
            order = some[np.lexsort((key[some], group[some]))]
            starts[tied[some]] = own[order]
            g, k = group[order], key[order]
            same[tied[some]] = np.r_[False, (g[1:] == g[:-1]) & (k[1:] == k[:-1])]
        still = same[tied]
        tied = tied[still | np.r_[still[1:], False]]
    return starts


def two_stage_order(text: np.ndarray, words: np.ndarray, depth: int, first: np.ndarray | None = None, last: np.ndarray | None = None) -> np.ndarray:
    """All suffixes of ``text`` in order of their first ``depth`` bytes (more where that comes by itself).

    With ``first`` and ``last``, only suffixes from each first to its last place, and those from which these are
    induced: up to the next place whose suffix is smaller than its successor.
    """
    n = len(text)
    if not n:
        return np.empty(0, np.int64)
    small = smaller_than_next(text)
    starts, need = np.flatnonzero(small), np.ones(n, bool)
    if first is not None:
        end = np.r_[starts, n - 1][np.searchsorted(starts, last)]
        edge = np.zeros(n + 1, np.int32)
        np.add.at(edge, first, 1)
        np.add.at(edge, end + 1, -1)
        need = np.cumsum(edge[:-1]) > 0
        starts = starts[need[starts]]
    direct = direct_order(starts, words, depth)
    bounds = np.searchsorted(text[direct], np.arange(257))
    induced: list[list[np.ndarray]] = [[] for _ in range(256)]
    if need[-1]:
        induced[text[-1]].append(np.array([n - 1]))
    out = []

    def push(placed: np.ndarray, byte: int) -> np.ndarray:
        """Hand on the predecessors of placed suffixes; those of the same bucket come back."""
        before = placed[placed > 0] - 1
        before = before[~small[before] & need[before]]
        first = text[before]
        other = first != byte
        for_others, keys = before[other], first[other]
        order = np.argsort(keys, kind="stable")
        for_others, keys = for_others[order], keys[order]
        cuts = np.flatnonzero(np.r_[True, keys[1:] != keys[:-1]]) if len(keys) else np.empty(0, np.int64)
        for a, b in zip(cuts, np.r_[cuts[1:], len(keys)][: len(cuts)], strict=True):
            induced[keys[a]].append(for_others[a:b])
        return before[~other]

    for byte in np.unique(text):
        front = np.concatenate(induced[byte]) if induced[byte] else np.empty(0, np.int64)
        while len(front):
            out.append(front)
            front = push(front, byte)
        own = direct[bounds[byte] : bounds[byte + 1]]
        if len(own):
            out.append(own)
            push(own, byte)
    return np.concatenate([np.empty(0, np.int64), *out])


def common_prefixes(order: np.ndarray, text: np.ndarray, words: np.ndarray, depth: int) -> np.ndarray:
    """How many bytes each suffix shares with the one before it in the order, ``depth`` at most (the first: 0).

    Neighbours advance word by word as long as they agree; the byte in which they part
    is the highest one set in the difference of the words.
    """
    out = np.zeros(len(order), np.int64)
    left = np.arange(1, len(order))
    for at in range(0, depth, 8):
        differ = words[order[left] + at] ^ words[order[left - 1] + at]
        part = np.flatnonzero(differ)
        bits = np.frexp((differ[part] >> np.uint64(11)).astype(np.float64))[1] + 11  # exact: 53 bits are kept
        low = differ[part] >> np.uint64(11) == 0
        bits[low] = np.frexp(differ[part][low].astype(np.float64))[1]
        out[left[part]] = at + (64 - bits) // 8
        left = left[differ == 0]
    out[left] = depth
    return np.minimum(out, depth)
