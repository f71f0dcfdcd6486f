"""One-to-one problems of many pairs at once, as edges.

Most pairs of tables share no edge and most of the others few, so what a pair needs is found from
its edges alone: no pair has a matrix, and only parts of the graph in which edges compete are solved.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from functools import partial

import numpy as np
import pyarrow as pa

from unionlake.functions.vectors import MICRO
from unionlake.operators import kernels as K


@dataclass
class Edges:
    """Edges in order of pair, q and j. pair: number of the pair, below `size`; q, j: column of the query and of the set; most: the largest possible number of pairs of columns, by pair."""

    pair: np.ndarray
    q: np.ndarray
    j: np.ndarray
    sim: np.ndarray
    size: int
    most: np.ndarray

    def of(self, wanted: np.ndarray) -> Edges:
        """The edges of some pairs, numbered in their order (ascending)."""
        low, high = np.searchsorted(self.pair, wanted), np.searchsorted(self.pair, wanted, "right")
        n = high - low
        at = np.repeat(low - (np.cumsum(n) - n), n) + np.arange(n.sum())
        return Edges(np.repeat(np.arange(len(wanted)), n), self.q[at], self.j[at], self.sim[at], len(wanted), self.most[wanted])


def _ends(e: Edges) -> tuple[np.ndarray, np.ndarray, int, int]:
    """Numbers of the columns at both ends of each edge, and how many a pair may have."""
    n, p = int(e.q.max()) + 1, int(e.j.max()) + 1
    return e.pair * n + e.q, e.pair * p + e.j, n, p


def _sums(pair: np.ndarray, values: np.ndarray, size: int) -> np.ndarray:
    """Sums by pair, exact below 2^53."""
    return np.bincount(pair, values, size).astype(np.int64)


def _order(pair: np.ndarray, sim: np.ndarray) -> np.ndarray:
    """The order by pair and descending similarity, of equals by place: one sort of whole keys where these fit."""
    n, top = len(pair), int(sim.max(initial=0))
    bits = n.bit_length()
    if (int(pair.max(initial=0)) + 1) * (top + 1) << bits >= 1 << 62:
        return np.lexsort((-sim, pair))
    return np.sort((pair * (top + 1) + (top - sim) << bits) | np.arange(n)) & (1 << bits) - 1


def uppers(e: Edges) -> np.ndarray:
    """Of each pair the sum of its `most` best edges."""
    out = _sums(e.pair, e.sim, e.size)
    many = np.flatnonzero(np.bincount(e.pair, minlength=e.size) > e.most)
    if len(many):
        some = e.of(many)
        order = _order(some.pair, some.sim)
        start = np.searchsorted(some.pair, np.arange(some.size))
        best = order[np.arange(len(order)) - start[some.pair] < some.most[some.pair]]
        out[many] = _sums(some.pair[best], some.sim[best], some.size)
    return out


def lowers(e: Edges, tau: int, card: bool) -> np.ndarray:
    """`kernels.lower_bound` of each pair. Edges that are first at both ends are what greedy takes next."""
    t, total = np.zeros(e.size, np.int64), np.zeros(e.size, np.int64)
    if not len(e.pair):
        return total
    row, target, n, p = _ends(e)
    has_row, has_target = np.zeros(e.size * n, bool), np.zeros(e.size * p, bool)
    has_row[row], has_target[target] = True, True
    most = np.minimum(has_row.reshape(e.size, n).sum(1), has_target.reshape(e.size, p).sum(1))
    left = _order(e.pair, e.sim)
    at_row, at_target = np.empty(e.size * n, np.int64), np.empty(e.size * p, np.int64)
    while len(left):
        r, c, rank = row[left], target[left], np.arange(len(left))
        at_row[r[::-1]], at_target[c[::-1]] = rank[::-1], rank[::-1]  # the first edge of each column
        on = (at_row[r] == rank) & (at_target[c] == rank)
        t += np.bincount(e.pair[left[on]], minlength=e.size)
        total += _sums(e.pair[left[on]], e.sim[left[on]], e.size)
        has_row[r[on]], has_target[c[on]] = False, False
        left = left[has_row[r] & has_target[c]]
    return np.where(t == most, total, tau * t) if card else total


def _places(nodes: np.ndarray, part: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(place of each entry's node among those of its part, number of nodes by part); a node has one part."""
    ids, first, inverse = np.unique(nodes, return_index=True, return_inverse=True)
    own = part[first]
    order = np.argsort(own, kind="stable")
    count = np.bincount(own, minlength=int(part.max()) + 1)
    place = np.empty(len(ids), np.int64)
    place[order] = np.arange(len(ids)) - (np.cumsum(count) - count)[own[order]]
    return place[inverse], count


def scores(e: Edges, card: bool, elements: int = 1 << 18) -> np.ndarray:
    """The total of an optimal matching of each pair. An edge alone at both ends is in it; the rest falls into connected parts, those of one shape solved together."""
    if not len(e.pair):
        return np.zeros(e.size, np.int64)
    row, target, _, _ = _ends(e)
    _, row = np.unique(row, return_inverse=True)
    _, target = np.unique(target, return_inverse=True)
    alone = (np.bincount(row)[row] == 1) & (np.bincount(target)[target] == 1)
    out = _sums(e.pair[alone], e.sim[alone], e.size)
    at = np.flatnonzero(~alone)
    if not len(at):
        return out
    row, target, sim, pair = row[at], target[at], e.sim[at], e.pair[at]
    label = np.arange(int(row.max()) + 1)
    while True:  # the least row number that is reachable
        of_target = np.full(int(target.max()) + 1, len(label))
        np.minimum.at(of_target, target, label[row])
        new = label.copy()
        np.minimum.at(new, row, of_target[target])
        if np.array_equal(new, label):
            break
        label = new
    _, part = np.unique(label[row], return_inverse=True)
    (r, rows), (c, targets) = _places(row, part), _places(target, part)
    total = np.zeros(len(rows), np.int64)
    np.maximum.at(total, part, sim)  # of edges that all meet in one column, the best
    open_ = np.flatnonzero((rows > 1) & (targets > 1))
    shape = rows * (int(targets.max()) + 1) + targets
    order = np.argsort(part, kind="stable")
    ends = np.searchsorted(part[order], np.arange(len(rows) + 1))
    for one in np.unique(shape[open_]):
        same = open_[shape[open_] == one]
        n, p = int(rows[same[0]]), int(targets[same[0]])
        step = max(1, elements // (n * p))
        for low in range(0, len(same), step):
            some = same[low : low + step]
            size = ends[some + 1] - ends[some]
            edge = order[np.repeat(ends[some] - (np.cumsum(size) - size), size) + np.arange(size.sum())]
            m = np.full((len(some), n, p), K.NO_EDGE)
            m[np.repeat(np.arange(len(some)), size), r[edge], c[edge]] = sim[edge]
            total[some] = [K.assign_wide(x, card) for x in m] if K.one_by_one(n, p, len(same)) else K.assign_many(m, np.ones(p, np.int64), card)[1]
    of_part = np.empty(len(rows), np.int64)
    of_part[part] = pair
    return out + _sums(of_part, total, e.size)


@dataclass
class Block:
    """Some queries and some sets. first: place of the first query; open_: query x set, which pairs meet; pair i is (i // sets, i % sets)."""

    first: int
    set_ids: np.ndarray
    open_: np.ndarray
    edges: Edges


def blocks(batches: Iterator[pa.RecordBatch], ids: np.ndarray, stacked: np.ndarray, cuts: np.ndarray, threshold: int, few: int = 16, most: int = 1 << 20, vectors: int = 1 << 13) -> Iterator[Block]:
    """All pairs of queries (ids, vectors end to end, where each begins) and of sets (set_id, n, flat) in batches; with a fourth column, only the queries it lists meet a set.

    Few sets come first, so that rules have something to prune by before many pairs are solved.
    """
    widths = np.diff(cuts)
    for batch in batches:
        every, ns = (batch.column(i).to_numpy(zero_copy_only=False) for i in (0, 1))
        flat, ends, low = batch.column(2).flatten().to_numpy(zero_copy_only=False).reshape(-1, stacked.shape[1]), np.cumsum(ns), 0
        if batch.num_columns > 3:
            meets = batch.column(3)
            met = np.repeat(np.arange(len(every)), np.asarray(meets.value_lengths())), np.searchsorted(ids, meets.flatten().to_numpy(zero_copy_only=False))
        while low < len(ns):
            begin = ends[low] - ns[low]
            high = min(low + few, max(low + 1, int(np.searchsorted(ends, begin + vectors, "right"))), len(ns))
            few = min(2 * few, vectors)
            v, n, set_ids = flat[begin : ends[high - 1]], ns[low:high], every[low:high]
            of_vector, j = np.repeat(np.arange(high - low), n), np.arange(len(v)) - np.repeat(ends[low:high] - n - begin, n)
            if batch.num_columns > 3:
                a, b = np.searchsorted(met[0], (low, high))
                meet = np.zeros((len(ids), high - low), bool)
                meet[met[1][a:b], met[0][a:b] - low] = True
            first = 0
            while first < len(ids):
                last = max(first + 1, int(np.searchsorted(cuts, cuts[first] + most // max(1, len(v)), "right")) - 1)
                open_ = ids[first:last, None] != set_ids[None, :]
                if batch.num_columns > 3:
                    open_ &= meet[first:last]
                if open_.any():
                    sims = (stacked[cuts[first] : cuts[last]] @ v.T).ravel() * MICRO
                    at = np.flatnonzero(sims > threshold - 1)
                    sim = np.rint(sims[at]).astype(np.int64)
                    at, sim = at[sim >= threshold], sim[sim >= threshold]
                    a, b = np.divmod(at, len(v))
                    of_query = np.repeat(np.arange(last - first), widths[first:last])
                    pair = of_query[a] * (high - low) + of_vector[b]
                    keep = np.flatnonzero(open_.ravel()[pair])
                    keep = keep[_order(pair[keep], np.zeros(len(keep), np.int64))]
                    q = a[keep] - (cuts[first:last] - cuts[first])[of_query[a[keep]]]
                    limit = np.minimum(widths[first:last, None], n[None, :]).ravel()
                    yield Block(first, set_ids, open_, Edges(pair[keep], q, j[b[keep]], sim[keep], open_.size, limit))
                first = last
            low = high


def score_of(held: np.ndarray, most: int, card: bool) -> int:
    """The score of one pair; held: its edges, as q, j and similarity."""
    return int(scores(Edges(np.zeros(held.shape[1], np.int64), *held, 1, np.array([most])), card)[0])


#: Pairs of at most so many edges are solved together, before it is known which will be asked for.
SMALL = 64


class Scores:
    """Scores of the pairs of a block: those of `ahead` that are small together, others when asked for."""

    def __init__(self, e: Edges, ahead: np.ndarray, card: bool):
        self.e, self.card, self.counts = e, card, np.bincount(e.pair, minlength=e.size)
        self.known = np.where(self.counts > 0, -1, 0)
        some = ahead[(self.counts[ahead] > 0) & (self.counts[ahead] <= SMALL)]
        self.known[some] = scores(e.of(some), card)

    def of(self, pair: int) -> int:
        if self.known[pair] < 0:
            self.known[pair] = scores(self.e.of(np.array([pair])), self.card)[0]
        return int(self.known[pair])

    def later(self, pair: int):
        """A function that finds one score without holding the block: of the pair it holds one array."""
        if self.known[pair] >= 0:
            return int(self.known[pair]).__int__
        own = slice(*np.searchsorted(self.e.pair, (pair, pair + 1)).tolist())
        held = np.stack((self.e.q[own], self.e.j[own], self.e.sim[own]))
        return partial(score_of, held, int(self.e.most[pair]), self.card)


def see(keepers: list[K.Keeper], block: Block, tau: int, card: bool) -> None:
    """Shows the pairs of a block to the keepers of its queries, in order: as `Keeper.see` one by one, without a call for pairs the rule passes over."""
    e, (n, m) = block.edges, block.open_.shape
    own, k = keepers[block.first : block.first + n], keepers[0].top.k
    met = block.open_.sum(1).tolist()
    rule = own[0].rule
    for keeper, c in zip(own, met, strict=True):
        keeper.seen += c
        if rule != "none":
            keeper.bounded += c
    if rule == "listing":
        _see_listing(own, block, tau, card)
        return
    floors = np.array([x.top.least() if x.top.full() else 0 for x in own])
    if rule == "none":
        s = scores(e, card).reshape(n, m)
        ask = block.open_ & (s >= floors[:, None])
        for i in np.flatnonzero(ask.any(1)).tolist():
            at = np.flatnonzero(ask[i])
            if len(at) > k:
                at = at[np.lexsort((block.set_ids[at], -s[i, at]))[:k]]
            for x in at.tolist():
                own[i].top.offer(int(block.set_ids[x]), int(s[i, x]))
        for keeper, c in zip(own, met, strict=True):
            keeper.evals += c
        return
    ubs = uppers(e).reshape(n, m)
    ask = block.open_ & (ubs >= floors[:, None])
    found = Scores(e, np.flatnonzero(ask.ravel()), card)
    for i in np.flatnonzero(ask.any(1)).tolist():
        top = own[i].top
        for x in np.flatnonzero(ask[i]).tolist():
            if not top.full() or ubs[i, x] >= top.least():
                own[i].evals += 1
                top.offer(int(block.set_ids[x]), found.of(i * m + x))


def _see_listing(own: list[K.Keeper], block: Block, tau: int, card: bool) -> None:
    e, (n, m) = block.edges, block.open_.shape
    ubs = uppers(e).reshape(n, m)

    ask = block.open_ & (ubs >= np.array([x.listing.floor() for x in own])[:, None])
    ahead = np.flatnonzero(ask.ravel())
    lbs = np.full(n * m, -1)
    lbs[ahead] = lowers(e.of(ahead), tau, card)
    found = Scores(e, ahead, card)
    for i in np.flatnonzero(ask.any(1)).tolist():
        rule = own[i].listing
        at, x = np.flatnonzero(block.open_[i]), 0
        own_ubs = ubs[i, at]
        positive = np.flatnonzero(own_ubs > 0)
        while x < len(at):
            if rule.settled():
                following = int(np.searchsorted(positive, x))
                next_ = int(positive[following]) if following < len(positive) else len(at)
                rule.join(block.set_ids[at[x:next_]].tolist())
                x = next_
            elif (low := rule.floor()) and own_ubs[x] < low:
                left = np.flatnonzero(own_ubs[x:] >= low)[:1]
                x += int(left[0]) if len(left) else len(at)
            if x >= len(at):
                break
            pair = i * m + int(at[x])
            if lbs[pair] < 0:
                lbs[pair] = lowers(e.of(np.array([pair])), tau, card)[0]
            rule.see(int(block.set_ids[at[x]]), int(lbs[pair]), int(own_ubs[x]), found.later(pair))
            x += 1


class Held:
    """Pairs of a task that may still win: upper bound at or above the k-th best lower bound of their query. Of pairs without an edge the k of the smallest ids."""

    def __init__(self, n_queries: int, k: int, tau: int, card: bool):
        self.k, self.tau, self.card = k, tau, card
        self.lows = np.full((n_queries, k), 0)
        self.zeros: dict[int, np.ndarray] = {}
        self.seen = np.zeros(n_queries, np.int64)
        self.parts: list[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, Edges]] = []
        self.size = 0

    def see(self, block: Block) -> None:
        e, (n, m) = block.edges, block.open_.shape
        own = slice(block.first, block.first + n)
        self.seen[own] += block.open_.sum(1)
        ubs = uppers(e)
        with_edges = np.zeros(e.size, bool)
        with_edges[e.pair] = True
        at = np.flatnonzero(with_edges & (ubs >= np.repeat(self.lows[own, 0], m)))
        lbs = np.zeros(e.size, np.int64)
        lbs[at] = lowers(e.of(at), self.tau, self.card)
        for i in np.flatnonzero((lbs.reshape(n, m) > self.lows[own, :1]).any(1)).tolist():
            every = np.concatenate([self.lows[block.first + i], lbs[i * m : (i + 1) * m]])
            self.lows[block.first + i] = np.sort(every)[-self.k :]
        floors = self.lows[own, 0]
        at = at[ubs[at] >= np.repeat(floors, m)[at]]
        if len(at):
            part = e.of(at)
            self.parts.append((block.first + at // m, block.set_ids[at % m], lbs[at], ubs[at], part))
            self.size += len(part.pair)
        for i in np.flatnonzero(floors == 0).tolist():
            none = block.set_ids[np.flatnonzero(block.open_[i] & ~with_edges[i * m : (i + 1) * m])]
            self.zeros[block.first + i] = np.sort(np.concatenate([self.zeros.get(block.first + i, none[:0]), none]))[: self.k]

    def take(self) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, Edges]]:
        """(places of the queries, set ids, bounds, edges) of what is held and still may win; it is held no longer."""
        parts, self.parts, self.size = self.parts, [], 0
        for q, s, lb, ub, e in parts:
            on = np.flatnonzero(ub >= self.lows[q, 0])
            if len(on):
                yield q[on], s[on], lb[on], ub[on], e.of(on)

    def without_edges(self) -> tuple[np.ndarray, np.ndarray]:
        """(places of the queries, set ids) of the pairs that may fill an answer with zeros."""
        left = {q: s for q, s in self.zeros.items() if self.lows[q, 0] == 0}
        return np.repeat(np.array(list(left), np.int64), [len(s) for s in left.values()]), np.concatenate([np.zeros(0, np.int64), *left.values()])
