"""Suffix arrays in numpy: Larsson-Sadakane refinement, Kasai common prefixes, merging by binary search."""

from __future__ import annotations

import numpy as np


def words_at(text: np.ndarray) -> np.ndarray:
    """Big-endian 8-byte word at every position; zeros after the end."""
    padded = np.concatenate([text, np.zeros(8, np.uint8)])
    out = np.zeros(len(text), np.uint64)
    for k in range(8):
        out |= padded[k : k + len(text)].astype(np.uint64) << np.uint64(56 - 8 * k)
    return out


def suffix_array(text: np.ndarray, depth: int | None = None) -> np.ndarray:
    """Positions in order of their suffixes; with ``depth``, only the first ``depth`` bytes are sure to be in order.

    A suffix's rank is the last place of its group.  Each round sorts only groups that are not yet single, by the
    rank of the suffix ``h`` further on, and doubles ``h``.  The first round sorts 8-byte words at once.
    """
    n = len(text)
    if n == 0:
        return np.zeros(0, np.int64)
    first = words_at(text)
    sa = np.argsort(first).astype(np.int64)
    ordered = first[sa]
    # a suffix that ends within its word sorts before longer ones with the same padded word
    short = np.minimum(n - sa, 8)
    if n:
        tail = np.flatnonzero(short < 8)
        for g in np.unique(ordered[tail]):
            lo, hi = np.searchsorted(ordered, g), np.searchsorted(ordered, g, side="right")
            sa[lo:hi] = sa[lo:hi][np.argsort(np.minimum(n - sa[lo:hi], 8), kind="stable")]
        short = np.minimum(n - sa, 8)
    new = np.concatenate([(ordered[1:] != ordered[:-1]) | (short[1:] != short[:-1]), [True]])
    ends = np.flatnonzero(new)
    rank = np.empty(n, np.int64)
    sizes = np.diff(np.concatenate([[-1], ends]))
    rank[sa] = np.repeat(ends, sizes)
    h = 8
    open_at = np.flatnonzero(np.repeat(sizes > 1, sizes))
    while len(open_at) and (depth is None or h < depth):
        own = sa[open_at]
        group = rank[own]
        later = np.where(own + h < n, rank[np.minimum(own + h, n - 1)], -1)
        both = (group << 32) | (later + 1)  # one number sorts faster than two; positions are below 2**31
        order = np.argsort(both)
        own, both = own[order], both[order]
        sa[open_at] = own
        new = np.concatenate([both[1:] != both[:-1], [True]])
        ends = np.flatnonzero(new)
        sizes = np.diff(np.concatenate([[-1], ends]))
        rank[own] = np.repeat(open_at[ends], sizes)
        open_at = open_at[np.repeat(sizes > 1, sizes)]
        h *= 2
    return sa


def common_prefixes(text: np.ndarray, sa: np.ndarray, limit: int, stride: int = 48) -> np.ndarray:
    """lcp[i]: common prefix of suffixes sa[i-1] and sa[i], up to ``limit``; lcp[0] = 0.  ``sa`` must be in full order.

    Kasai's order, in lanes: each lane runs through ``stride`` neighbouring positions and starts each comparison where the
    one before it less one leaves off; all lanes take a step at once, eight bytes a comparison.
    """
    n = len(sa)
    lcp = np.zeros(n, np.int64)
    if n < 2:
        return lcp
    word = np.concatenate([words_at(text), np.zeros(limit + 16, np.uint64)])
    rank = np.empty(n, np.int64)
    rank[sa] = np.arange(n)
    lanes = np.arange(0, n, stride)
    h = np.zeros(len(lanes), np.int64)
    for step in range(stride):
        i = lanes + step
        i = i[i < n]
        h = np.maximum(h[: len(i)] - 1, 0)
        r = rank[i]
        some = np.flatnonzero(r > 0)
        j = sa[r[some] - 1]
        h[r == 0] = 0
        at, other, here = some, j, i[some]
        room = n - np.maximum(other, here)
        while len(at):
            x = word[here + h[at]] ^ word[other + h[at]]
            same = (x == 0).astype(np.int64)
            for k in range(1, 8):  # leading bytes that agree
                same += x < np.uint64(1 << (64 - 8 * k))
            grown = np.minimum(h[at] + same, np.minimum(room, limit))
            go = (same == 8) & (grown < np.minimum(room, limit))
            h[at] = grown
            at, other, here, room = at[go], other[go], here[go], room[go]
        lcp[r] = h
    return lcp


def window_words(text: np.ndarray, at: np.ndarray, length: int) -> np.ndarray:
    """The ``length`` bytes at each position as big-endian words, in the order of their bytes."""
    word = np.concatenate([words_at(text), np.zeros(length + 8, np.uint64)])
    out = np.empty((len(at), -(-length // 8)), np.uint64)
    for k in range(out.shape[1]):
        out[:, k] = word[at + 8 * k]
    if length % 8:
        out[:, -1] >>= np.uint64(64 - 8 * (length % 8))
    return out


def _less(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    out, tied = np.zeros(len(a), bool), np.ones(len(a), bool)
    for k in range(a.shape[1]):
        out |= tied & (a[:, k] < b[:, k])
        tied &= a[:, k] == b[:, k]
    return out


def _lower(ordered: np.ndarray, probes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(first row of ``ordered`` that is not below each probe, whether it equals it), by binary search."""
    lo, hi = np.zeros(len(probes), np.int64), np.full(len(probes), len(ordered), np.int64)
    for _ in range(max(1, len(ordered)).bit_length()):
        live = lo < hi
        mid = (lo + hi) // 2
        below = np.zeros(len(probes), bool)
        below[live] = _less(ordered[mid[live]], probes[live])
        lo, hi = np.where(live & below, mid + 1, lo), np.where(live & ~below, mid, hi)
    found = np.minimum(lo, max(0, len(ordered) - 1))
    return lo, (lo < len(ordered)) & (ordered[found] == probes).all(1) if len(ordered) else np.zeros(len(probes), bool)


def locate(ordered: np.ndarray, probes: np.ndarray) -> np.ndarray:
    """Row of ``ordered`` (ascending rows) that equals each probe, or -1."""
    at, equal = _lower(ordered, probes)
    return np.where(equal, at, -1)


def merge_windows(words: np.ndarray, least: np.ndarray, more: np.ndarray, more_least: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Two ascending lists of distinct windows as one, with the smaller id of each; the longer list is searched for the shorter one's."""
    if len(words) < len(more):
        words, least, more, more_least = more, more_least, words, least
    at, equal = _lower(words, more)
    least = least.copy()
    least[at[equal]] = np.minimum(least[at[equal]], more_least[equal])
    at = at[~equal]
    return np.insert(words, at, more[~equal], axis=0), np.insert(least, at, more_least[~equal])
