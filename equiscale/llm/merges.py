"""A score-ordered agenda of adjacent symbol pairs, for one sequence (a heap) and for many short ones at once."""

from __future__ import annotations

import heapq

import numpy as np

NONE = np.iinfo(np.int32).max


class PairTable:
    """(left symbol, right symbol) -> (priority, merged symbol); the smallest priority merges first."""

    def __init__(self, left, right, priority, merged):
        keys = (np.asarray(left, np.uint64) << np.uint64(32)) | np.asarray(right, np.uint64)
        bits = max(6, int(len(keys) * 4).bit_length())
        self._shift, self._mask = np.uint64(64 - bits), (1 << bits) - 1
        self._keys = np.full(1 << bits, np.uint64(2**64 - 1))
        self._priority = np.full(1 << bits, NONE, np.int32)
        self._merged = np.zeros(1 << bits, np.int32)
        todo, slot = np.arange(len(keys)), self._slot(keys)
        while len(todo):
            free = self._keys[slot] == np.uint64(2**64 - 1)
            self._keys[slot[free]] = keys[todo[free]]
            won = self._keys[slot] == keys[todo]
            self._priority[slot[won]] = np.asarray(priority, np.int32)[todo[won]]
            self._merged[slot[won]] = np.asarray(merged, np.int32)[todo[won]]
            todo, slot = todo[~won], (slot[~won] + 1) & self._mask
        self.pairs = dict(zip(keys.tolist(), zip(np.asarray(priority).tolist(), np.asarray(merged).tolist())))

    def _slot(self, keys):
        return ((keys * np.uint64(0x9E3779B97F4A7C15)) >> self._shift).astype(np.int64)

    def find(self, left, right):
        """Priorities (NONE without a merge) and merged symbols of pairs; a negative symbol is padding."""
        keys = (left.astype(np.uint64) << np.uint64(32)) | (right.astype(np.uint64) & np.uint64(0xFFFFFFFF))
        flat = keys.ravel()
        slot = self._slot(flat)
        seen = self._keys[slot]
        odd = np.flatnonzero((seen != flat) & (seen != np.uint64(2**64 - 1)))
        while len(odd):
            slot[odd] = (slot[odd] + 1) & self._mask
            seen = self._keys[slot[odd]]
            odd = odd[(seen != flat[odd]) & (seen != np.uint64(2**64 - 1))]
        hit = (self._keys[slot] == flat) & (left.ravel() >= 0) & (right.ravel() >= 0)
        return np.where(hit, self._priority[slot], NONE).reshape(keys.shape), np.where(hit, self._merged[slot], -1).reshape(keys.shape)


def agenda(symbols: list[int], table: PairTable) -> list[int]:
    """Merges one sequence: the agenda holds every adjacent pair by (priority, place); outdated entries are skipped."""
    pairs, n = table.pairs, len(symbols)
    symbols, before, after = list(symbols), list(range(-1, n - 1)), list(range(1, n + 1))
    heap = []

    def offer(i: int, j: int) -> None:
        found = pairs.get((symbols[i] << 32) | symbols[j])
        if found is not None:
            heap.append((found[0], i, j, symbols[i], symbols[j], found[1])) if not ready else heapq.heappush(heap, (found[0], i, j, symbols[i], symbols[j], found[1]))

    ready = False
    for i in range(n - 1):
        offer(i, i + 1)
    heapq.heapify(heap)
    ready = True
    while heap:
        _, i, j, a, b, merged = heapq.heappop(heap)
        if symbols[i] != a or after[i] != j or j >= n or symbols[j] != b:
            continue
        symbols[i], symbols[j] = merged, -1
        after[i] = after[j]
        if after[i] < n:
            before[after[i]] = i
            offer(i, after[i])
        if before[i] >= 0:
            offer(before[i], i)
    out, i = [], 0
    while i < n:
        out.append(symbols[i])
        i = after[i]
    return out


def agenda_many(block: np.ndarray, table: PairTable) -> np.ndarray:
    """Merges every row of ``block`` (padded with -1) by the same order: each round takes each row's first agenda entry."""
    done = block.copy()
    width = block.shape[1]
    if width < 2:
        return done
    rows, now = np.arange(len(block)), np.concatenate([block, np.full((len(block), 1), -1, block.dtype)], axis=1)
    rank = np.concatenate([table.find(now[:, :-1], now[:, 1:])[0], np.full((len(block), 1), NONE, np.int32)], axis=1)
    places = np.arange(width)
    while len(rows):
        at = rank[:, :-1].argmin(1)
        r = np.arange(len(rows))
        live = rank[r, at] < NONE
        if not live.all():
            done[rows[~live]] = now[~live, :width]
            rows, now, rank, at = rows[live], now[live], rank[live], at[live]
            r = np.arange(len(rows))
            if not len(rows):
                break
        now[r, at] = table.find(now[r, at], now[r, at + 1])[1]
        take = places + (places > at[:, None])
        now[:, :width] = np.take_along_axis(now, take, 1)
        now[:, width] = -1
        rank[:, :width] = np.take_along_axis(rank, take, 1)
        rank[:, width] = NONE
        rank[r, at] = table.find(now[r, at], now[r, at + 1])[0]
        left = np.flatnonzero(at > 0)
        rank[left, at[left] - 1] = table.find(now[left, at[left] - 1], now[left, at[left]])[0]
    return done


class UnitCache:
    """Ids of text units in one flat array.  ``fill`` gets the new units of a batch; over ``limit`` units those used most stay, at most half, and the others go."""

    def __init__(self, fill, limit: int = 600_000):
        self._fill, self._limit = fill, limit
        self._at: dict[str, int] = {}
        self._flat, self._used = np.zeros(1 << 16, np.int32), 0
        self._start, self._len, self._hits = (np.zeros(1 << 12, np.int64) for _ in range(3))

    def _shrink(self) -> None:
        n = len(self._at)
        hits = self._hits[:n]
        least = max(2, int(np.partition(hits, n - self._limit // 2)[n - self._limit // 2]) + 1)  # at most half have more than the middle one
        keep = np.flatnonzero(hits >= least)
        start, lens = self._start[keep], self._len[keep]
        where = np.repeat(start - (np.cumsum(lens) - lens), lens) + np.arange(int(lens.sum()))
        kept = self._flat[where]
        units = list(self._at)
        self._at = {units[k]: i for i, k in enumerate(keep.tolist())}
        self._flat, self._used = np.zeros(max(1 << 16, 2 * len(kept)), np.int32), len(kept)
        self._flat[: len(kept)] = kept
        size = max(1 << 12, 2 * len(keep))
        self._start, self._len, self._hits = (np.zeros(size, np.int64) for _ in range(3))
        self._start[: len(keep)], self._len[: len(keep)], self._hits[: len(keep)] = np.cumsum(lens) - lens, lens, hits[keep] // 2

    def ids(self, units: list[str], codes: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
        """All ids in order, and the number of ids of each unit.  With ``codes`` the units are distinct and ``units[c]`` is meant for each code c."""
        if len(self._at) > self._limit:
            self._shrink()
        new = [u for u in (dict.fromkeys(units) if codes is None else units) if u not in self._at]
        if new:
            flat, lens = self._fill(new)
            n = len(self._at)
            while n + len(new) > len(self._start):
                self._start, self._len, self._hits = (np.concatenate([x, np.zeros_like(x)]) for x in (self._start, self._len, self._hits))
            while self._used + len(flat) > len(self._flat):
                self._flat = np.concatenate([self._flat, np.zeros_like(self._flat)])
            self._flat[self._used : self._used + len(flat)] = flat
            self._len[n : n + len(new)] = lens
            self._start[n : n + len(new)] = self._used + np.cumsum(lens) - lens
            self._used += len(flat)
            self._at.update(zip(new, range(n, n + len(new))))
        at = np.fromiter(map(self._at.__getitem__, units), np.int64, len(units))
        if codes is not None:
            at = at[codes]
        self._hits[: len(self._at)] += np.bincount(at, minlength=len(self._at))
        lens = self._len[at]
        total = int(lens.sum())
        where = np.repeat(self._start[at] - (np.cumsum(lens) - lens), lens) + np.arange(total)
        return self._flat[where], lens


def merge_words(flat: np.ndarray, size: np.ndarray, table: PairTable, longest: int = 48) -> tuple[np.ndarray, np.ndarray]:
    """Merged symbols of all words, flat, and how many each has.  ``flat`` holds the words' symbols, ``size`` their numbers."""
    n = len(size)
    start = np.cumsum(size) - size
    out_len = np.zeros(n, np.int64)
    parts: list[tuple[np.ndarray, np.ndarray]] = []
    low = 0
    for high in (4, 8, 12, 16, 24, 32, longest):
        pick = np.flatnonzero((size > low) & (size <= high))
        low = high
        if len(pick):
            cols = np.arange(high)
            inside = cols < size[pick][:, None]
            block = np.where(inside, flat[np.minimum(start[pick][:, None] + cols, len(flat) - 1)], -1)
            merged = agenda_many(block, table)
            keep = merged >= 0
            out_len[pick] = keep.sum(1)
            parts.append((pick, merged[keep]))
    for i in np.flatnonzero(size > longest).tolist():
        got = agenda(flat[start[i] : start[i] + size[i]].tolist(), table)
        out_len[i] = len(got)
        parts.append((np.array([i]), np.array(got, np.int64)))
    out = np.zeros(int(out_len.sum()), np.int64)
    begin = np.cumsum(out_len) - out_len
    for pick, values in parts:
        lens = out_len[pick]
        out[np.repeat(begin[pick] - (np.cumsum(lens) - lens), lens) + np.arange(len(values))] = values
    return out, out_len
