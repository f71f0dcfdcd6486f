"""Numpy kernels that run inside tasks: optimal assignments with capacities, bounds, pruning, clustering, graph."""

from __future__ import annotations

import heapq
from collections.abc import Callable, Iterable

import numpy as np

NO_EDGE = np.int64(-1)
FAR = np.int64(-(1 << 60))


def assign(sims: np.ndarray, caps: np.ndarray, max_cardinality: bool = True) -> tuple[int, int, np.ndarray]:
    """(pairs, total, target of each row or -1) of an optimal assignment of rows to targets with capacities.

    sims: int64, NO_EDGE where there is no edge. Augments along the most profitable path; after t
    steps the assignment is the heaviest of t pairs. With max_cardinality it goes on while a path
    exists, else only while a path gains.
    """
    n, p = sims.shape
    to = np.full(n, -1)
    edge = sims >= 0
    if not n or not p or not edge.any():
        return 0, 0, to
    w = np.where(edge, sims, FAR)
    # when everyone's favourite has room, that is optimal under either reading
    favourite = w.argmax(1)
    alive = edge.any(1)
    load = np.bincount(favourite[alive], minlength=p)
    if (load <= caps).all():
        to[alive] = favourite[alive]
        return int(alive.sum()), int(w[np.flatnonzero(alive), favourite[alive]].sum()), to
    used = np.zeros(p, np.int64)
    rows = np.arange(n)
    while True:
        gain = np.where((to < 0) & alive, 0, FAR)  # best gain of a path that ends by freeing this row
        via = np.full(n, -1)  # the row before it on that path
        matched = np.flatnonzero(to >= 0)
        for _ in range(n):
            through = gain[:, None] + w
            through[gain <= FAR // 2] = FAR
            reach, source = through.max(0), through.argmax(0)
            if not len(matched):
                break
            k = to[matched]
            new = np.where(reach[k] > FAR // 2, reach[k] - w[matched, k], FAR)
            better = (new > gain[matched]) & (source[k] != matched)
            if not better.any():
                break
            gain[matched[better]] = new[better]
            via[matched[better]] = source[k][better]
        open_ = np.where(used < caps, reach, FAR)
        k = int(open_.argmax())
        if open_[k] <= FAR // 2 or (not max_cardinality and open_[k] <= 0):
            break
        used[k] += 1
        row = int(source[k])
        while True:
            before = int(to[row])
            to[row] = k
            if before < 0:
                break
            k, row = before, int(via[row])
    on = rows[to >= 0]
    return len(on), int(sims[on, to[on]].sum()), to


def assign_many(sims: np.ndarray, caps: np.ndarray, max_cardinality: bool = True) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """`assign` of many problems of one shape at once: (pairs, totals, targets of the rows). sims: b x n x p; caps: b x p or p."""
    b, n, p = sims.shape
    to = np.full((b, n), -1)
    if not b or not n or not p:
        return np.zeros(b, np.int64), np.zeros(b, np.int64), to
    caps = np.broadcast_to(caps, (b, p))
    w = np.where(sims >= 0, sims, FAR)
    favourite, alive = w.argmax(2), (sims >= 0).any(2)
    load = np.zeros((b, p), np.int64)
    np.add.at(load, (np.nonzero(alive)[0], favourite[alive]), 1)
    easy = (load <= caps).all(1)
    to[easy] = np.where(alive, favourite, -1)[easy]
    left = np.flatnonzero(~easy)
    w_, alive_, caps_ = w[left], alive[left], caps[left]
    to_, used = to[left], np.zeros((len(left), p), np.int64)
    while len(left):
        at = np.arange(len(left))
        matched, k = to_ >= 0, np.maximum(to_, 0)
        held = np.take_along_axis(w_, k[:, :, None], 2)[:, :, 0]  # what a matched row weighs
        gain = np.where(~matched & alive_, 0, FAR)
        via = np.full(to_.shape, -1)
        for _ in range(n):
            through = np.where(gain[:, :, None] > FAR // 2, gain[:, :, None] + w_, FAR)
            source = through.argmax(1)
            reach = np.take_along_axis(through, source[:, None, :], 1)[:, 0, :]
            come, by = np.take_along_axis(reach, k, 1), np.take_along_axis(source, k, 1)
            new = np.where(matched & (come > FAR // 2), come - held, FAR)
            better = (new > gain) & (by != np.arange(n))
            if not better.any():
                break
            gain, via = np.where(better, new, gain), np.where(better, by, via)
        open_ = np.where(used < caps_, reach, FAR)
        k = open_.argmax(1)
        value = open_[at, k]
        on = value > FAR // 2 if max_cardinality else value > 0
        used[at[on], k[on]] += 1
        walk, k, row = at[on], k[on], source[at[on], k[on]]
        while len(walk):
            before = to_[walk, row]
            to_[walk, row] = k
            more = before >= 0
            walk, k, row = walk[more], before[more], via[walk[more], row[more]]
        if not on.all():
            to[left[~on]] = to_[~on]
            left, to_, used, w_, alive_, caps_ = left[on], to_[on], used[on], w_[on], alive_[on], caps_[on]
    chosen = np.take_along_axis(sims, np.maximum(to, 0)[:, :, None], 2)[:, :, 0]
    return (to >= 0).sum(1), np.where(to >= 0, chosen, 0).sum(1), to


def assign_wide(sims: np.ndarray, max_cardinality: bool = True) -> int:
    """The total of `assign` for one wide problem without capacities: rows are added along shortest paths at prices.

    A pair counts more than all weights together if pairs go first. Rows whose favourite nobody else
    wants are settled before any path is sought; a path ends at the first free target.
    """
    if not (sims >= 0).any():
        return 0
    if sims.shape[0] > sims.shape[1]:
        sims = sims.T
    n, p = sims.shape
    bonus = int(np.maximum(sims, 0).max(1).sum()) + 1 if max_cardinality else 0
    cost = np.where(sims >= 0, -(sims + bonus), 0)
    u, v = cost.min(1), np.zeros(p, np.int64)
    to, of = np.full(n, -1), np.full(p, -1)
    for i, k in enumerate(cost.argmin(1).tolist()):
        if of[k] < 0:
            of[k], to[i] = i, k
    for free in np.flatnonzero(to < 0).tolist():
        near, via = np.full(p, -FAR), np.full(p, -1)  # shortest way to each target, the row before it
        todo, rows, shown = np.ones(p, bool), [free], []
        low, i = 0, free
        while True:
            d = cost[i] - v + (low - u[i])
            better = todo & (d < near)
            near[better], via[better] = d[better], i
            reach = np.where(todo, near, -FAR)
            k = int(reach.argmin())
            low = int(reach[k])
            todo[k] = False
            if of[k] < 0:
                break
            shown.append(k)
            i = int(of[k])
            rows.append(i)
        u[free] += low
        if shown:
            by = low - near[shown]
            u[rows[1:]] += by
            v[shown] -= by
        while True:
            i = int(via[k])
            of[k] = i
            to[i], k = k, int(to[i])
            if i == free:
                break
    return int(np.maximum(sims[np.arange(n), to], 0).sum())


def match_many(sims: np.ndarray, max_cardinality: bool = True) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """`assign_many` without capacities, by `assign_wide`'s way for all problems in step: each adds the same row along a shortest path at its own prices."""
    b, n, p = sims.shape
    if n > p:
        t, total, of = match_many(np.ascontiguousarray(sims.transpose(0, 2, 1)), max_cardinality)
        to = np.full((b, n), -1)
        at, j = np.nonzero(of >= 0)
        to[at, of[at, j]] = j
        return t, total, to
    if not b or not n:
        return np.zeros(b, np.int64), np.zeros(b, np.int64), np.full((b, n), -1)
    edge = sims >= 0
    bonus = np.where(edge, sims, 0).max(2).sum(1) + 1 if max_cardinality else np.zeros(b, np.int64)
    cost = np.where(edge, -(sims + bonus[:, None, None]), 0)
    favourite = cost.argmin(2)
    u, v, at = np.take_along_axis(cost, favourite[:, :, None], 2)[:, :, 0], np.zeros((b, p), np.int64), np.arange(b)
    to, of = np.full((b, n), -1), np.full((b, p), -1)
    for i in range(n):
        k = favourite[:, i]
        on = np.flatnonzero(of[at, k] < 0)
        of[on, k[on]], to[on, i] = i, k[on]
    for free in range(n):
        own = np.flatnonzero(to[:, free] < 0)  # these problems have no target for the row yet
        near, via = np.full((len(own), p), -FAR), np.full((len(own), p), -1)
        todo, low, i = np.ones((len(own), p), bool), np.zeros(len(own), np.int64), np.full(len(own), free)
        while len(own):
            d = cost[own, i] - v[own] + (low - u[own, i])[:, None]
            better = todo & (d < near)
            near, via = np.where(better, d, near), np.where(better, i[:, None], via)
            reach = np.where(todo, near, -FAR)
            k, x = reach.argmin(1), np.arange(len(own))
            low = reach[x, k]
            todo[x, k] = False
            i = of[own, k]
            done = i < 0
            if done.any():
                walk, target = own[done], k[done]
                u[walk, free] += low[done]
                shown, column = np.nonzero(~todo[done] & (np.arange(p) != target[:, None]))
                by = low[done][shown] - near[done][shown, column]
                u[walk[shown], of[walk[shown], column]] += by
                v[walk[shown], column] -= by
                back = via[done]
                while len(walk):
                    row = back[np.arange(len(walk)), target]
                    of[walk, target] = row
                    before = to[walk, row].copy()
                    to[walk, row] = target
                    more = row != free
                    walk, target, back = walk[more], before[more], back[more]
                own, near, via, todo, low, i = (y[~done] for y in (own, near, via, todo, low, i))
    to[~np.take_along_axis(edge, to[:, :, None], 2)[:, :, 0]] = -1
    chosen = np.take_along_axis(sims, np.maximum(to, 0)[:, :, None], 2)[:, :, 0]
    return (to >= 0).sum(1), np.where(to >= 0, chosen, 0).sum(1), to


def one_by_one(n: int, p: int, problems: int) -> bool:
    """Whether problems of this shape are sooner solved by `assign_wide` each than together by `assign_many`."""
    return n * p > 256 or problems < 16


def upper_bounds(sims: np.ndarray, most: np.ndarray) -> np.ndarray:
    """Of each problem the sum of its `most` best edges. sims: b x n x p."""
    e = np.sort(np.maximum(sims, 0).reshape(len(sims), sims.shape[1] * sims.shape[2]), axis=1)[:, ::-1].cumsum(1)
    most = np.minimum(most, e.shape[1])
    return np.where(most > 0, np.take_along_axis(e, np.maximum(most - 1, 0)[:, None], 1)[:, 0], 0) if e.shape[1] else np.zeros(len(sims), np.int64)


def greedy_rows_many(sims: np.ndarray, caps: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """`greedy_rows` of many problems of one shape."""
    b, n, p = sims.shape
    left, at = np.broadcast_to(caps, (b, p)).copy(), np.arange(b)
    t, total = np.zeros(b, np.int64), np.zeros(b, np.int64)
    for i in range(n if p else 0):
        row = np.where(left > 0, sims[:, i], NO_EDGE)
        k = row.argmax(1)
        best = row[at, k]
        on = best >= 0
        left[at[on], k[on]] -= 1
        t, total = t + on, total + np.where(on, best, 0)
    return t, total


def greedy_edges_many(sims: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """`greedy_edges` of many problems of one shape."""
    b, n, p = sims.shape
    m, at = sims.copy(), np.arange(b)
    t, total = np.zeros(b, np.int64), np.zeros(b, np.int64)
    for _ in range(min(n, p)):
        k = m.reshape(b, n * p).argmax(1)
        best = m.reshape(b, n * p)[at, k]
        on = best >= 0
        t, total = t + on, total + np.where(on, best, 0)
        m[at, k // p] = NO_EDGE
        m[at, :, k % p] = NO_EDGE
    return t, total


def lower_bounds(greedy: tuple[np.ndarray, np.ndarray], sims: np.ndarray, caps: np.ndarray, tau: int, max_cardinality: bool) -> np.ndarray:
    """`lower_bound` of many problems of one shape."""
    t, total = greedy
    if not max_cardinality:
        return total
    edge = sims >= 0
    most = np.minimum(edge.any(2).sum(1), np.where(edge.any(1), caps, 0).sum(1))
    return np.where(t == most, total, tau * t)


def upper_bound(sims: np.ndarray, size: int) -> int:
    """Sum of the best min(rows, size) edges."""
    e = sims[sims >= 0]
    k = min(sims.shape[0], size)
    return int(np.sort(e)[::-1][:k].sum()) if len(e) else 0


def greedy_rows(sims: np.ndarray, caps: np.ndarray) -> tuple[int, int]:
    """(pairs, total): each row in order takes its best target that still has room."""
    left = caps.copy()
    t = total = 0
    for row in sims:
        row = np.where(left > 0, row, NO_EDGE)
        k = int(row.argmax()) if len(row) else 0
        if len(row) and row[k] >= 0:
            left[k] -= 1
            t, total = t + 1, total + int(row[k])
    return t, total


def greedy_edges(sims: np.ndarray) -> tuple[int, int]:
    """(pairs, total): edges in descending similarity, each row and target once."""
    q, j = np.nonzero(sims >= 0)
    order = np.lexsort((j, q, -sims[q, j]))
    rows, targets, t, total = set(), set(), 0, 0
    for i in order:
        if q[i] not in rows and j[i] not in targets:
            rows.add(q[i])
            targets.add(j[i])
            t, total = t + 1, total + int(sims[q[i], j[i]])
    return t, total


def lower_bound(greedy: tuple[int, int], sims: np.ndarray, caps: np.ndarray, tau: int, max_cardinality: bool) -> int:
    """A valid lower bound: what the greedy pairs weigh, if they reach the largest possible number of pairs; else that many thresholds."""
    t, total = greedy
    if not max_cardinality:
        return total
    edge = sims >= 0
    most = min(int(edge.any(1).sum()), int(caps[edge.any(0)].sum())) if edge.size else 0
    return total if t == most else tau * t


class DualEndedQueue:
    """Candidates by lower and by upper bound; removal marks a tombstone that leaves the heaps when it reaches a root."""

    def __init__(self):
        self.low, self.up, self.top, self.bounds = [], [], [], {}

    def __len__(self) -> int:
        return len(self.bounds)

    def push(self, item: int, lb: int, ub: int) -> None:
        self.bounds[item] = (lb, ub)
        heapq.heappush(self.low, (lb, item))
        heapq.heappush(self.up, (ub, item))
        heapq.heappush(self.top, (-ub, item))

    def _root(self, heap: list, key: Callable[[tuple[int, int]], int]) -> int | None:
        while heap and (heap[0][1] not in self.bounds or key(self.bounds[heap[0][1]]) != heap[0][0]):
            heapq.heappop(heap)
        return heap[0][1] if heap else None

    def min_lb(self) -> int | None:
        return self._root(self.low, lambda b: b[0])

    def min_ub(self) -> int | None:
        return self._root(self.up, lambda b: b[1])

    def max_ub(self) -> int | None:
        return self._root(self.top, lambda b: -b[1])

    def remove(self, item: int) -> None:
        del self.bounds[item]


class TopK:
    """The k best by (score descending, id ascending)."""

    def __init__(self, k: int):
        self.k, self.heap = k, []

    def full(self) -> bool:
        return len(self.heap) >= self.k

    def least(self) -> int:
        return self.heap[0][0]

    def offer(self, item: int, score: int) -> None:
        entry = (score, -item)
        if len(self.heap) < self.k:
            heapq.heappush(self.heap, entry)
        elif entry > self.heap[0]:
            heapq.heapreplace(self.heap, entry)

    def answer(self) -> list[tuple[int, int]]:
        return [(-i, s) for s, i in sorted(self.heap, reverse=True)]


Candidate = tuple[int, int, int]  # id, lower bound, upper bound


def base_prune(candidates: Iterable[Candidate], k: int, score: Callable[[int], int]) -> tuple[list[tuple[int, int]], int]:
    """(answer, exact evaluations), candidates in order of arrival."""
    top, evals = TopK(k), 0
    for item, _, ub in candidates:
        if not top.full() or ub >= top.least():
            evals += 1
            top.offer(item, score(item))
    return top.answer(), evals


class Listing:
    """The printed rule on arriving candidates: discard by the least upper bound, swap without comparing, else resolve by descending upper bound."""

    def __init__(self, k: int):
        self.k, self.queue, self.top, self.evals = k, DualEndedQueue(), TopK(k), 0
        self.done: set[int] = set()
        self.scores: dict[int, Callable[[], int]] = {}
        self.spare = 0  # pairs of bounds 0 beside the queue, which can no longer be scored
        self.zeros: list[int] = []  # a heap of others of bounds 0 beside the queue; while there are any, the queue has one

    def size(self) -> int:
        return len(self.queue) + self.spare + len(self.zeros)

    def floor(self) -> int:
        """What arrives with a lower upper bound is passed over."""
        return self.queue.bounds[self.queue.min_ub()][1] if self.size() >= self.k else 0

    def settled(self) -> bool:
        """Whether pairs of bounds 0 that follow one another only join the queue: the best of it, which is none of them, has been scored or will not be."""
        if self.size() < self.k or not self.top.full() or self.floor() != 0:
            return False
        best = self.queue.max_ub()
        return (self.top.least() > 0 or self.queue.bounds[best][1] > 0) and self._idle(best)

    def join(self, items: list[int]) -> None:
        """Takes pairs of bounds 0 while the rule is settled. They are scored at the end, if the k-th best is 0 until then."""
        if self.top.least() > 0:
            self.spare += len(items)
            return
        for item in items:
            heapq.heappush(self.zeros, item)

    def _idle(self, item: int) -> bool:
        return item in self.done or self.queue.bounds[item][1] < self.top.least()

    def _process(self, item: int) -> None:
        ub = self.queue.bounds[item][1]
        if item not in self.done and (not self.top.full() or ub >= self.top.least()):
            self.done.add(item)
            self.evals += 1
            self.top.offer(item, self.scores.pop(item)())

    def _push(self, item: int, lb: int, ub: int, score: Callable[[], int]) -> None:
        if not self.top.full() or ub >= self.top.least():  # else it is never asked for
            self.scores[item] = score
        self.queue.push(item, lb, ub)

    def _remove(self, item: int) -> None:
        self.scores.pop(item, None)
        self.queue.remove(item)

    def see(self, item: int, lb: int, ub: int, score: Callable[[], int]) -> None:
        queue = self.queue
        if self.size() < self.k:
            self._push(item, lb, ub, score)
            return
        weakest = queue.min_ub()
        if ub < queue.bounds[weakest][1]:
            return
        if lb > queue.bounds[queue.min_lb()][0]:
            if self.spare and queue.bounds[weakest] == (0, 0):
                self.spare -= 1
            elif self.zeros and self.zeros[0] < weakest:
                heapq.heappop(self.zeros)
            else:
                self._remove(weakest)
                if self.zeros:
                    self._push(heapq.heappop(self.zeros), 0, 0, lambda: 0)
        else:
            while len(queue) and ub >= queue.bounds[queue.min_lb()][0] and lb <= queue.bounds[queue.min_ub()][1]:
                best = queue.max_ub()
                self._process(best)
                if self.top.full() and ub <= self.top.least():
                    break
                self._remove(best)
        self._push(item, lb, ub, score)

    def finish(self) -> list[tuple[int, int]]:
        for item, _ in sorted(self.queue.bounds.items(), key=lambda x: (-x[1][1], x[0])):
            self._process(item)
        if self.zeros and self.top.least() == 0:
            self.evals += len(self.zeros)
            for item in heapq.nsmallest(self.k, self.zeros):
                self.top.offer(item, 0)
        return self.top.answer()


def enhanced_listing(candidates: Iterable[Candidate], k: int, score: Callable[[int], int]) -> tuple[list[tuple[int, int]], int]:
    """The printed rule, which may lose answers."""
    rule = Listing(k)
    for item, lb, ub in candidates:
        rule.see(item, lb, ub, lambda item=item: score(item))
    return rule.finish(), rule.evals


def enhanced_lossless(candidates: Iterable[Candidate], k: int, score: Callable[[int], int]) -> tuple[list[tuple[int, int]], int]:
    """The principle: who has k others above its upper bound is out; the rest by descending upper bound until none can enter."""
    rows = list(candidates)
    lows = sorted((lb for _, lb, _ in rows), reverse=True)
    theta = lows[k - 1] if len(lows) >= k else None
    top, evals = TopK(k), 0
    for item, _, ub in sorted(rows, key=lambda c: (-c[2], c[0])):
        if theta is not None and ub < theta or top.full() and ub < top.least():
            break
        evals += 1
        top.offer(item, score(item))
    return top.answer(), evals


PRUNES = {"base": base_prune, "listing": enhanced_listing, "lossless": enhanced_lossless}


def prune(kind: str, candidates: list[Candidate], k: int, score: Callable[[int], int]) -> tuple[list[tuple[int, int]], int]:
    """kind: none, base, listing or lossless."""
    if kind == "none":
        top = TopK(k)
        for item, _, _ in candidates:
            top.offer(item, score(item))
        return top.answer(), len(candidates)
    return PRUNES[kind](candidates, k, score)


class Problem:
    """The assignment of a query's columns to targets with capacities; by_rows: which greedy rule bounds it from below; only then are there capacities above one. Solved and bounded once at most."""

    def __init__(self, sims: np.ndarray, caps: np.ndarray, tau: int, card: bool, by_rows: bool):
        self.sims, self.caps, self.tau, self.card, self.by_rows = sims, caps, tau, card, by_rows
        self.known: dict[str, int] = {}

    def upper(self) -> int:
        return self._get("upper", lambda: upper_bound(self.sims, int(self.caps.sum())))

    def lower(self) -> int:
        return self._get("lower", lambda: lower_bound(greedy_rows(self.sims, self.caps) if self.by_rows else greedy_edges(self.sims), self.sims, self.caps, self.tau, self.card))

    def score(self) -> int:
        return self._get("score", lambda: assign_wide(self.sims, self.card) if not self.by_rows else assign(self.sims, self.caps, self.card)[1])

    def _get(self, what: str, find: Callable[[], int]) -> int:
        if what not in self.known:
            self.known[what] = find()
        return self.known[what]


def prepare(problems: list[Problem], what: str, elements: int = 1 << 18, wide: int = 1 << 12) -> None:
    """Finds `upper`, `lower` or `score` of many problems, those of one shape together; those of more than `wide` elements gain nothing by it."""
    shapes: dict[tuple[int, ...], list[Problem]] = {}
    for p in problems:
        if p.sims.size <= wide:
            shapes.setdefault(p.sims.shape, []).append(p)
    for (n, m), some in shapes.items():
        if what == "score" and not some[0].by_rows and one_by_one(n, m, len(some)):
            continue
        step = max(1, elements // max(1, n * m))
        for low in range(0, len(some), step):
            part = some[low : low + step]
            sims, caps = np.stack([p.sims for p in part]), np.stack([p.caps for p in part])
            if what == "upper":
                got = upper_bounds(sims, np.minimum(n, caps.sum(1)))
            elif what == "lower":
                got = lower_bounds(greedy_rows_many(sims, caps) if part[0].by_rows else greedy_edges_many(sims), sims, caps, part[0].tau, part[0].card)
            else:
                got = assign_many(sims, caps, part[0].card)[1]
            for p, x in zip(part, got.tolist(), strict=True):
                p.known[what] = x


class Keeper:
    """What one task keeps of one query's problems: the k best, as the rule none, base or listing finds them."""

    def __init__(self, rule: str, k: int):
        self.rule, self.seen, self.bounded, self.evals = rule, 0, 0, 0
        self.top, self.listing = TopK(k), Listing(k) if rule == "listing" else None

    def may_need(self, p: Problem) -> bool:
        """Whether `see` may ask for more than the upper bound, as far as is known now."""
        return self.rule in ("none", "listing") or not self.top.full() or p.upper() >= self.top.least()

    def see(self, item: int, p: Problem) -> None:
        self.seen += 1
        if self.rule != "none":
            self.bounded += 1
            ub = p.upper()
            if self.listing is not None:
                self.listing.see(item, p.lower(), ub, p.score)
                return
            if self.top.full() and ub < self.top.least():
                return
        self.evals += 1
        self.top.offer(item, p.score())

    def finish(self) -> list[tuple[int, int]]:
        if self.listing is None:
            return self.top.answer()
        answer, self.evals = self.listing.finish(), self.listing.evals
        return answer


class Survivors:
    """Problems of one query whose upper bound reaches the k-th best lower bound that the task has seen."""

    def __init__(self, k: int):
        self.seen, self.lows, self.held = 0, TopK(k), []

    def may_need(self, p: Problem) -> bool:
        return not self.lows.full() or p.upper() >= self.lows.least()

    def see(self, item: int, p: Problem) -> None:
        self.seen += 1
        ub = p.upper()
        if self.lows.full() and ub < self.lows.least():
            return
        lb = p.lower()
        self.lows.offer(item, lb)
        self.held.append((item, lb, ub, p))

    def take(self) -> list[tuple[int, int, int, Problem]]:
        """What is held and still survives; it is held no longer."""
        least = self.lows.least() if self.lows.full() else 0
        out, self.held = [h for h in self.held if h[2] >= least], []
        return out


def nearest(v: np.ndarray, c: np.ndarray) -> np.ndarray:
    """The nearest centroid of each vector in the Euclidean sense; of equals the first. Distances in whole 1e-9 units."""
    d = (c * c).sum(1)[None, :] - 2 * (v @ c.T)
    return np.rint(d * 1e9).argmin(1)


def lloyd(v: np.ndarray, k: int, rounds: int = 10) -> tuple[np.ndarray, np.ndarray]:
    """(centroids, assignment) of k-means seeded with the first k vectors; an empty cluster keeps its centroid."""
    c = v[:k].copy()
    for _ in range(rounds):
        own = nearest(v, c)
        new = c.copy()
        for i in np.unique(own):
            new[i] = v[own == i].mean(0)
        if np.array_equal(new, c):
            break
        c = new
    return c, nearest(v, c)


def merge_groups(centroids: np.ndarray, caps: list[int], size: int, rho_high: float) -> list[list[int]]:
    """Single-link merging of one-centroid groups while groups / size >= rho_high; of equal pairs the first. Similarities in micro-units."""
    groups = [[i] for i in range(len(caps))]
    sims = np.rint(centroids @ centroids.T * 1e6)
    sims[np.tril_indices(len(sims))] = -np.inf  # a pair of groups once, the first of equals first
    while len(groups) > 1 and len(groups) / size >= rho_high:
        a, b = divmod(int(sims.argmax()), len(groups))
        groups[a] = sorted(groups[a] + groups[b])
        both = np.maximum(np.maximum(sims[a], sims[:, a]), np.maximum(sims[b], sims[:, b]))
        sims[a, a + 1 :], sims[:a, a] = both[a + 1 :], both[:a]
        del groups[b]
        sims = np.delete(np.delete(sims, b, 0), b, 1)
    return groups


class ProximityGraph:
    """A layered proximity graph (navigable small world with a hierarchy) by inner product."""

    def __init__(self, vectors: np.ndarray, links: int = 16, beam: int = 200):
        self.v, self.links = np.asarray(vectors, np.float64), links
        self.layers: list[dict[int, list[int]]] = []
        self.entry = -1
        for i in range(len(self.v)):
            self._insert(i, beam)

    def _level(self, i: int) -> int:
        """Geometric levels from a hash of the place, so building again gives the same graph."""
        h = ((i + 1) * 0x9E3779B97F4A7C15 & (1 << 64) - 1) >> 11
        level, share = 0, 1 << 53
        while h < share // self.links and level < 16:
            level, share = level + 1, share // self.links
        return level

    def _search(self, q: np.ndarray, layer: dict[int, list[int]], starts: list[int], beam: int) -> list[tuple[float, int]]:
        sims = self.v[starts] @ q
        seen = set(starts)
        todo = [(-s, i) for s, i in zip(sims.tolist(), starts, strict=True)]
        heapq.heapify(todo)
        best = [(s, i) for s, i in zip(sims.tolist(), starts, strict=True)]
        heapq.heapify(best)
        while todo:
            s, i = heapq.heappop(todo)
            if len(best) >= beam and -s < best[0][0]:
                break
            near = [j for j in layer.get(i, ()) if j not in seen]
            if not near:
                continue
            seen.update(near)
            for t, j in zip((self.v[near] @ q).tolist(), near, strict=True):
                if len(best) < beam:
                    heapq.heappush(best, (t, j))
                    heapq.heappush(todo, (-t, j))
                elif t > best[0][0]:
                    heapq.heapreplace(best, (t, j))
                    heapq.heappush(todo, (-t, j))
        return sorted(best, key=lambda x: (-x[0], x[1]))

    def _insert(self, i: int, beam: int) -> None:
        level, q = self._level(i), self.v[i]
        starts = [self.entry] if self.entry >= 0 else []
        for k in range(len(self.layers) - 1, -1, -1):
            layer = self.layers[k]
            if starts:
                found = self._search(q, layer, starts, beam if k <= level else 1)
                starts = [j for _, j in found]
                if k <= level:
                    most = self.links * (2 if k == 0 else 1)
                    layer[i] = starts[: self.links]
                    for j in layer[i]:
                        layer[j].append(i)
                        if len(layer[j]) > most:
                            s = self.v[layer[j]] @ self.v[j]
                            layer[j] = [layer[j][x] for x in np.argsort(-s, kind="stable")[:most]]
        while len(self.layers) <= level:
            self.layers.append({i: []})
            self.entry = i
        for k in range(level + 1):
            self.layers[k].setdefault(i, [])

    def top(self, q: np.ndarray, k: int, beam: int | None = None) -> list[tuple[int, float]]:
        if self.entry < 0:
            return []
        starts = [self.entry]
        for layer in self.layers[:0:-1]:
            starts = [self._search(q, layer, starts, 1)[0][1]]
        found = self._search(q, self.layers[0], starts, max(k, beam or 2 * k, 64))
        return [(i, s) for s, i in found[:k]]

    def top_many(self, queries: np.ndarray, k: int, beam: int | None = None, most: int = 1 << 24) -> list[list[tuple[int, float]]]:
        """`top` of many queries (a row each), which walk the lowest layer in step: a round takes the best open node of each query, and one product finds the similarities to their links."""
        if self.entry < 0:
            return [[] for _ in queries]
        width = max(k, beam or 2 * k, 64)
        nearest = np.full((len(self.v), max((len(x) for x in self.layers[0].values()), default=0) or 1), -1, np.int64)
        for i, x in self.layers[0].items():
            nearest[i, : len(x)] = x
        out = []
        for low in range(0, len(queries), step := max(1, most // len(self.v))):
            some = np.ascontiguousarray(queries[low : low + step])
            at = np.arange(len(some))
            starts = [[self.entry] for _ in some]
            for layer in self.layers[:0:-1]:
                starts = [[self._search(q, layer, x, 1)[0][1]] for q, x in zip(some, starts, strict=True)]
            start = np.array(starts)[:, 0]
            seen = np.zeros((len(some), len(self.v)), bool)
            seen[at, start] = True
            # of each query the best nodes in order, and which of them are open
            nodes, sims, open_ = np.full((len(some), width), -1), np.full((len(some), width), -np.inf), np.zeros((len(some), width), bool)
            nodes[:, 0], sims[:, 0], open_[:, 0] = start, np.einsum("ij,ij->i", self.v[start], some), True
            left = at
            while len(left):
                best = open_[left].argmax(1)
                open_[left, best] = False
                links = nearest[nodes[left, best]]
                new = (links >= 0) & ~seen[left[:, None], links]
                a, b = np.nonzero(new)
                seen[left[a], links[a, b]] = True
                near = np.full(links.shape, -np.inf)
                near[a, b] = np.einsum("ij,ij->i", self.v[links[a, b]], some[left[a]])
                gained = near.max(1) > sims[left, -1]  # others stay as they are
                own = left[gained]
                every = np.concatenate([sims[own], near[gained]], 1)
                order = np.argsort(-every, axis=1, kind="stable")[:, :width]
                sims[own] = np.take_along_axis(every, order, 1)
                nodes[own] = np.take_along_axis(np.concatenate([nodes[own], links[gained]], 1), order, 1)
                open_[own] = np.take_along_axis(np.concatenate([open_[own], new[gained]], 1), order, 1) & np.isfinite(sims[own])
                left = left[open_[left].any(1)]
            for i in range(len(some)):
                found = sorted((x for x in zip(nodes[i].tolist(), sims[i].tolist(), strict=True) if x[1] > -np.inf), key=lambda x: (-x[1], x[0]))
                out.append(found[:k])
        return out

    def degrees(self) -> list[tuple[int, int, int]]:
        return [(k, i, len(n)) for k, layer in enumerate(self.layers) for i, n in layer.items()]
