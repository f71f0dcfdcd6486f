"""Byte-pair merges of many words at once.

Words stand in the rows of a matrix of symbols. A round merges the lowest-ranked pair of every row
that still has one, the leftmost first, as the library does word by word; symbols of a row are
linked to their neighbours, so nothing is moved. Words are dealt to matrices by length.
"""

from __future__ import annotations

import numpy as np

from unionlake.llm.hash_arrays import HashArray

NONE = np.int32(2**31 - 1)
#: Widths of the matrices: a word goes to the narrowest that holds it; longer words are left to the caller.
WIDTHS = (1, 2, 3, 4, 5, 6, 7, 8, 10, 12, 15, 19, 24, 32, 48, 64)


class Merges:
    """pairs: (left id, right id, merged id) by rank; ids of single symbols are below `single`."""

    def __init__(self, pairs: list[tuple[int, int, int]], single: int):
        left, right, to = np.array(pairs, np.int64).reshape(-1, 3).T
        self.first = np.full((single, single), NONE, np.int32)
        low = (left < single) & (right < single)
        self.first[left[low], right[low]] = np.flatnonzero(low)
        self.table = HashArray(((left << 32) | right).astype(np.uint64))
        self.ranks = np.append(self.table.order.astype(np.int32), NONE)  # the last place stands for pairs that never merge
        self.to = to.astype(np.int32)

    def rank(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        return self.ranks[self.table.rows(((left.astype(np.int64) << 32) | right).view(np.uint64))]

    def apply(self, symbols: np.ndarray, starts: np.ndarray, lengths: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Token ids of the words one after another, and how many each has; words longer than the widest matrix have none."""
        counts = np.zeros(len(lengths), np.int64)
        found: list[tuple[np.ndarray, np.ndarray]] = []
        least = 0
        for width in WIDTHS:
            rows = np.flatnonzero((lengths > least) & (lengths <= width))
            least = width
            if len(rows):
                ids, counts[rows] = self._matrix(symbols, starts[rows], lengths[rows], width)
                found.append((rows, ids))
        begins = np.cumsum(counts) - counts
        out = np.empty(int(counts.sum()), np.uint32)
        for rows, ids in found:
            n = counts[rows]
            out[np.repeat(begins[rows] - (np.cumsum(n) - n), n) + np.arange(len(ids))] = ids
        return out, counts

    def _matrix(self, symbols: np.ndarray, starts: np.ndarray, lengths: np.ndarray, width: int) -> tuple[np.ndarray, np.ndarray]:
        place = np.arange(width)
        inside = place < lengths[:, None]
        by_row = np.where(inside, symbols[np.minimum(starts[:, None] + place, len(symbols) - 1)], np.int32(-1))
        ranks = np.full(by_row.shape, NONE, np.int32)
        ranks[:, :-1] = np.where(inside[:, 1:], self.first[by_row[:, :-1], by_row[:, 1:]], NONE)
        symbol, rank = by_row.reshape(-1), ranks.reshape(-1)
        after = np.arange(1, len(symbol) + 1)
        before = after - 2
        row = np.arange(len(starts))
        while True:
            own = ranks[row]
            at = own.argmin(1)
            lowest = own[np.arange(len(row)), at]
            live = np.flatnonzero(lowest < NONE)
            if not len(live):
                kept = by_row >= 0
                return by_row[kept], kept.sum(1)
            row, lowest = row[live], lowest[live]
            begin = row * width
            left, merged = at[live] + begin, self.to[lowest]
            right = after[left]
            far = after[right]
            symbol[left], symbol[right] = merged, -1
            rank[left] = rank[right] = NONE
            after[left] = far
            more = np.flatnonzero(far < begin + lengths[row])
            a, far = left[more], far[more]
            before[far] = a
            near = before[left]
            less = np.flatnonzero(near >= begin)
            near = near[less]
            fresh = self.rank(np.concatenate((merged[more], symbol[near])), np.concatenate((symbol[far], merged[less])))
            rank[a], rank[near] = fresh[: len(a)], fresh[len(a) :]
