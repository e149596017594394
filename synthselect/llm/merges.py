"""Pair merging over many words at once, on flat numpy arrays.

All words' symbols lie in one array, with one rank per adjacent pair.  Each round takes the smallest
rank of every word (segmented minimum), merges all its occurrences from the left at the same time,
closes the gaps and ranks only the pairs that changed; words without a pair leave.  Taking them at the
same time equals taking them one by one as long as no merge makes a pair of smaller or equal rank;
words where that happens or would have, or whose pair shares its rank with other pairs, are done again one by one.
"""

from __future__ import annotations

import heapq

import numpy as np

NONE = np.iinfo(np.int64).max


class PairTable:
    """(left, right) -> (rank, symbol)."""

    def __init__(self, pairs: dict[tuple[int, int], tuple[int, int]]):
        self.pairs = pairs
        left = np.fromiter((a for a, _ in pairs), np.int64, len(pairs))
        right = np.fromiter((b for _, b in pairs), np.int64, len(pairs))
        rank = np.fromiter((r for r, _ in pairs.values()), np.int64, len(pairs))
        made = np.fromiter((s for _, s in pairs.values()), np.int64, len(pairs))
        self.base = int(max(right.max(initial=0), left.max(initial=0), made.max(initial=0))) + 1
        key = left * self.base + right
        order = np.argsort(key)
        self.key, self.rank, self.made = np.append(key[order], NONE), np.append(rank[order], NONE), np.append(made[order], -1)
        of, n = np.unique(np.unique(np.stack([rank, made]), axis=1)[0], return_counts=True)
        self.shared = set(of[n > 1].tolist())  # ranks that several symbols have
        self.has_shared = np.fromiter(self.shared, np.int64, len(self.shared))

    def look(self, left: np.ndarray, right: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        key = left * self.base + right
        at = np.searchsorted(self.key, key)
        hit = (self.key[at] == key) & (left >= 0) & (right >= 0) & (left < self.base) & (right < self.base)
        return np.where(hit, self.rank[at], NONE), np.where(hit, self.made[at], -1)


def merge_one(symbols: list[int], table: PairTable) -> list[int]:
    """One word, one merge at a time: smallest rank first, then the leftmost."""
    sym = list(symbols)
    n = len(sym)
    before, after = list(range(-1, n - 1)), [*range(1, n), -1]
    heap: list[tuple[int, int, int, int]] = []

    def push(i: int, j: int) -> None:
        if i >= 0 and j >= 0 and (hit := table.pairs.get((sym[i], sym[j]))):
            heapq.heappush(heap, (hit[0], i, sym[i], sym[j]))

    for i in range(n - 1):
        push(i, i + 1)
    while heap:
        _, i, a, b = heapq.heappop(heap)
        j = after[i] if sym[i] == a else -1
        if j < 0 or sym[j] != b:
            continue
        sym[i], sym[j] = table.pairs[a, b][1], -1
        after[i] = after[j]
        if after[j] >= 0:
            before[after[j]] = i
        push(before[i], i)
        push(i, after[i])
    return [s for s in sym if s != -1]


def merge_words(words: list[list[int]], table: PairTable) -> list[list[int]]:
    """Fully merged symbols of each word; symbols are non-negative."""
    done: list[list[int] | None] = [None] * len(words)
    again: list[int] = []
    ids = np.array([k for k, w in enumerate(words) if len(w) > 1], np.int64)
    for k, w in enumerate(words):
        if len(w) <= 1:
            done[k] = list(w)
    if not len(ids):
        return done  # type: ignore[return-value]
    size = np.array([len(words[k]) for k in ids], np.int64)
    sym = np.concatenate([np.asarray(words[k], np.int64) for k in ids])
    start = np.concatenate([[0], np.cumsum(size)[:-1]])
    rank, made = np.full(len(sym), NONE), np.full(len(sym), -1)
    r, m = table.look(sym[:-1], sym[1:])
    rank[:-1], made[:-1] = r, m
    rank[start + size - 1] = NONE  # the last symbol of a word has no pair
    floor, redo = np.full(len(ids), -1), np.zeros(len(ids), bool)
    while len(ids):
        low = np.minimum.reduceat(rank, start)
        # leave: no pair left, or to be done one by one
        bad = (low <= floor) | np.isin(low, table.has_shared)
        bad = bad & (low != NONE) | redo
        out = (low == NONE) | bad
        if out.any():
            for k in np.flatnonzero(out):
                if bad[k]:
                    again.append(int(ids[k]))
                else:
                    done[ids[k]] = sym[start[k] : start[k] + size[k]].tolist()
            keep = np.repeat(~out, size)
            sym, rank, made = sym[keep], rank[keep], made[keep]
            ids, size, low, floor, redo = ids[~out], size[~out], low[~out], floor[~out], redo[~out]
            start = np.concatenate([[0], np.cumsum(size)[:-1]]) if len(ids) else start[:0]
            if not len(ids):
                break
        hit = rank == np.repeat(low, size)
        at = np.flatnonzero(hit)
        # of hits side by side (a a a) take the first, third, ...; a word's last symbol is never a hit
        run = np.concatenate([[True], np.diff(at) != 1])
        odd = (np.arange(len(at)) - np.maximum.accumulate(np.where(run, np.arange(len(at)), 0))) & 1
        at = at[odd == 0]
        of = np.repeat(np.arange(len(ids)), size)
        # a merge whose right neighbour goes into the next merge: was the pair they would make to come first?
        side = at[:-1][np.diff(at) == 2]
        side = side[of[side] == of[side + 2]]
        if len(side):
            sooner, _ = table.look(made[side], sym[side + 2])
            redo[of[side[sooner <= low[of[side]]]]] = True
        sym[at] = made[at]
        gone = np.zeros(len(sym), bool)
        gone[at + 1] = True
        keep = ~gone
        place = np.cumsum(keep) - 1
        size = size - np.bincount(of[at], minlength=len(ids))
        sym, rank, made = sym[keep], rank[keep], made[keep]
        start = np.concatenate([[0], np.cumsum(size)[:-1]])
        at = place[at]
        changed = np.unique(np.concatenate([at, at[at > 0] - 1]))
        ends = np.zeros(len(sym), bool)
        ends[start + size - 1] = True
        changed = changed[~ends[changed]]
        rank[ends], made[ends] = NONE, -1
        rank[changed], made[changed] = table.look(sym[changed], sym[changed + 1])
        floor = low
    for k in again:
        done[k] = merge_one(words[k], table)
    return done  # type: ignore[return-value]
