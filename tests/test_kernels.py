from __future__ import annotations

import itertools

import numpy as np
from hypothesis import given, settings
from hypothesis import strategies as st

from unionlake.operators import kernels as K


def brute(s, caps):
    best_card, best_weight = (0, 0), 0
    n, p = s.shape
    for c in itertools.product(*[[-1] + [k for k in range(p) if s[i, k] >= 0] for i in range(n)]):
        if all(c.count(k) <= caps[k] for k in range(p)):
            t = sum(x >= 0 for x in c)
            w = sum(int(s[i, x]) for i, x in enumerate(c) if x >= 0)
            best_card, best_weight = max(best_card, (t, w)), max(best_weight, w)
    return best_card, best_weight


graphs = st.integers(1, 4).flatmap(lambda n: st.integers(1, 4).flatmap(lambda p: st.tuples(st.lists(st.lists(st.one_of(st.just(-1), st.integers(1, 30)), min_size=p, max_size=p), min_size=n, max_size=n), st.lists(st.integers(1, 3), min_size=p, max_size=p))))


@settings(max_examples=200, deadline=None)
@given(graphs)
def test_assign_is_optimal_and_bounds_hold(g):
    s, caps = np.array(g[0], np.int64), np.array(g[1], np.int64)
    (t, card), weight = brute(s, caps)
    assert K.assign(s, caps, True)[:2] == (t, card)
    assert K.assign(s, caps, False)[1] == weight
    assert card <= weight <= K.upper_bound(s, int(caps.sum()))
    tau = int(s[s >= 0].min()) if (s >= 0).any() else 1
    assert K.lower_bound(K.greedy_rows(s, caps), s, caps, tau, True) <= card
    assert K.lower_bound(K.greedy_rows(s, caps), s, caps, tau, False) <= weight
    one = np.ones_like(caps)
    (_, card1), weight1 = brute(s, one)
    assert K.lower_bound(K.greedy_edges(s), s, one, tau, True) <= card1
    assert K.lower_bound(K.greedy_edges(s), s, one, tau, False) <= weight1


def test_cardinality_before_weight():
    s = np.array([[900, 300], [300, -1]])
    assert K.assign(s, np.ones(2, np.int64), True)[:2] == (2, 600)
    assert K.assign(s, np.ones(2, np.int64), False)[1] == 900
    assert K.lower_bound(K.greedy_edges(s), s, np.ones(2, np.int64), 300, True) == 300  # greedy weighs 900 > 600


def test_pruning_fixture():
    cases = {"discard": [(0, 1, 10, 1.5), (1, 4, 5, 4.5)], "swap": [(0, 1, 10, 9), (1, 2, 11, 3)], "tie": [(0, 2, 2, 2), (1, 2, 2, 2)]}
    want = {"discard": (1, 0, 1), "swap": (0, 1, 0), "tie": (0, 0, 0)}
    for name, rows in cases.items():
        got = tuple(K.prune(kind, [r[:3] for r in rows], 1, lambda i, rows=rows: rows[i][3])[0][0][0] for kind in ("base", "listing", "lossless"))
        assert got == want[name], name


@settings(max_examples=100, deadline=None)
@given(st.lists(st.tuples(st.integers(0, 50), st.integers(0, 20), st.integers(0, 20)), max_size=40), st.integers(1, 6))
def test_lossless_prunes_agree(rows, k):
    cands = [(i, s - min(s, a), s + b) for i, (s, a, b) in enumerate(rows)]
    score = lambda i: rows[i][0]
    none, n_all = K.prune("none", cands, k, score)
    for kind in ("base", "lossless"):
        got, evals = K.prune(kind, cands, k, score)
        assert got == none and evals <= n_all


@settings(max_examples=100, deadline=None)
@given(st.lists(st.tuples(st.sampled_from(["push", "remove", "min_lb", "min_ub", "max_ub"]), st.integers(0, 9), st.integers(0, 9))))
def test_dual_ended_queue(ops):
    q, model = K.DualEndedQueue(), {}
    for i, (op, a, b) in enumerate(ops):
        if op == "push":
            q.push(i, a, a + b)
            model[i] = (a, a + b)
        elif op == "remove" and model:
            x = sorted(model)[a % len(model)]
            q.remove(x)
            del model[x]
        elif op == "min_lb":
            assert q.min_lb() == min(model, key=lambda x: (model[x][0], x), default=None)
        elif op == "min_ub":
            assert q.min_ub() == min(model, key=lambda x: (model[x][1], x), default=None)
        elif op == "max_ub":
            assert q.max_ub() == min(model, key=lambda x: (-model[x][1], x), default=None)
        assert len(q) == len(model)


def test_merging_stops_below_the_threshold_or_at_one_group():
    rng = np.random.default_rng(0)
    c = rng.normal(size=(6, 8))
    groups = K.merge_groups(c, [1] * 6, 6, 0.5)
    assert sorted(x for g in groups for x in g) == list(range(6)) and len(groups) / 6 < 0.5
    assert K.merge_groups(c[:1], [1], 1, 0.8) == [[0]]


def test_graph_finds_neighbours():
    rng = np.random.default_rng(1)
    v = rng.normal(size=(300, 16))
    g = K.ProximityGraph(v)
    hits = [len({i for i, _ in g.top(q, 10)} & set(np.argsort(-(v @ q))[:10])) for q in v[:30]]
    assert sum(hits) / 300 >= 0.9
    assert K.ProximityGraph(v).degrees() == g.degrees()


def test_many_problems_at_once_as_one_by_one():
    pick = np.random.default_rng(5)
    for n, p in itertools.product((1, 2, 4, 7), (1, 3, 6)):
        for spread in (6, 10**6):
            sims = np.where(pick.random((60, n, p)) < 0.6, pick.integers(0, spread, (60, n, p)), -1)
            caps = pick.integers(1, 4, (60, p))
            for card in (True, False):
                t, u, to = K.assign_many(sims, caps, card)
                assert [(int(x), int(y), z.tolist()) for x, y, z in zip(t, u, to)] == [(a, b, c.tolist()) for a, b, c in (K.assign(s, x, card) for s, x in zip(sims, caps))]
                rows, edges = K.greedy_rows_many(sims, caps), K.greedy_edges_many(sims)
                assert K.lower_bounds(rows, sims, caps, 3, card).tolist() == [K.lower_bound(K.greedy_rows(s, x), s, x, 3, card) for s, x in zip(sims, caps)]
                assert K.lower_bounds(edges, sims, np.ones(p, np.int64), 3, card).tolist() == [K.lower_bound(K.greedy_edges(s), s, np.ones(p, np.int64), 3, card) for s in sims]
            assert K.upper_bounds(sims, np.full(60, min(n, 2))).tolist() == [K.upper_bound(s, 2) for s in sims]
