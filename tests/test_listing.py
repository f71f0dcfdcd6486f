"""Pairs without an edge join the printed rule together, with the answer and the work of one by one."""

from __future__ import annotations

import numpy as np

from unionlake.operators import kernels as K


def test_pairs_without_an_edge_join_together():
    rng = np.random.default_rng(1)
    together = 0
    for _ in range(1500):
        k, share = int(rng.integers(1, 6)), rng.random()
        plain, fast = K.Listing(k), K.Listing(k)
        for i in rng.permutation(200)[: int(rng.integers(1, 60))].tolist():
            lb, score, ub = (0, 0, 0) if rng.random() < share else sorted(rng.integers(1, 12, 3).tolist())
            plain.see(i, lb, ub, lambda x=score: x)
            if ub == 0 and fast.settled():
                together += fast.top.least() == 0
                fast.join([i])
            else:
                fast.see(i, lb, ub, lambda x=score: x)
        assert (plain.finish(), plain.evals) == (fast.finish(), fast.evals)
    assert together > 1000  # also while a score of 0 is among the k best


def test_scores_that_are_never_asked_for_are_not_held():
    rng, held, queued = np.random.default_rng(2), 0, 0
    for _ in range(200):
        rule, asked = K.Listing(3), set()

        def score(i, x, asked=asked):
            assert i not in asked  # once at most
            asked.add(i)
            return x

        for i in range(300):
            lb, x, ub = sorted(rng.integers(1, 1000, 3).tolist())
            rule.see(i, lb, ub, lambda i=i, x=x: score(i, x))
            assert not asked & set(rule.scores)
        held, queued = held + len(rule.scores), queued + len(rule.queue)
        rule.finish()
        assert rule.evals == len(asked)
    assert held < queued
