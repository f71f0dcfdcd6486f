"""Sorted hash arrays: a read-only map from 64-bit keys to rows, looked up for many keys at once."""

from __future__ import annotations

import numpy as np

#: An odd multiplier spreads keys over all 64 bits and can be undone, so distinct keys stay distinct.
SPREAD = np.uint64(0x9E3779B97F4A7C15)


class HashArray:
    """Keys sorted by their spread value; the top bits index where a value's neighbours begin."""

    def __init__(self, keys: np.ndarray):
        spread = keys.astype(np.uint64) * SPREAD
        self.order = np.argsort(spread, kind="stable")  # of the rows as given; users let go of it once values are in this order
        spread = spread[self.order]
        bits = max(1, len(keys).bit_length())
        self.shift = np.uint64(64 - bits)
        self.first = np.searchsorted(spread >> self.shift, np.arange((1 << bits) + 1, dtype=np.uint64)).astype(np.int32)
        self.longest = int(np.diff(self.first).max()) if len(keys) else 0
        self.padded = np.append(spread, np.uint64(0))  # a read at the end finds nothing wrong

    def sort(self, values: np.ndarray) -> np.ndarray:
        """Values of the keys as given, in the order of the rows."""
        return values[self.order]

    def __getstate__(self) -> dict:
        return self.__dict__ | {"order": None}

    def rows(self, keys: np.ndarray) -> np.ndarray:
        """The row of each key in the sorted order, -1 where it is absent."""
        size = len(self.padded) - 1
        if not size:
            return np.full(len(keys), -1, np.int32)
        want = keys * SPREAD
        at = self.first[want >> self.shift]
        hit = self.padded[at] == want
        hit &= at < size
        out = np.where(hit, at, np.int32(-1))
        todo = np.flatnonzero(~hit)
        for _ in range(1, self.longest):
            if not len(todo):
                break
            w = want[todo]
            nxt = at[todo] + 1
            inside = self.padded[np.minimum(nxt, size)] <= w
            inside &= nxt < size
            todo, nxt, w = todo[inside], nxt[inside], w[inside]
            at[todo] = nxt
            found = self.padded[nxt] == w
            out[todo[found]] = nxt[found]
            todo = todo[~found]
        return out
