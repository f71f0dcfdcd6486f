"""The k best sets by bounds, held against solving every pair."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pytest

from unionlake.operators import bounded
from unionlake.operators import kernels as K

DIM = 8


def lake(rng, n_sets: int, widest: int, copies: int = 0) -> dict[int, np.ndarray]:
    out = {}
    for i in range(n_sets):
        v = rng.normal(size=(int(rng.integers(1, widest + 1)), DIM))
        out[3 * i] = v / np.linalg.norm(v, axis=1, keepdims=True)
    for i in range(copies):  # equal scores, and sets without an edge
        out[3 * i + 1], out[3 * i + 2] = out[3 * i].copy(), np.zeros((2, DIM))
    return out


def batches(sets: dict[int, np.ndarray], ids: dict[int, list[int]] | None = None, size: int = 40):
    keys = list(sets)
    for low in range(0, len(keys), size):
        own = keys[low : low + size]
        columns = [pa.array(own, pa.int64()), pa.array([len(sets[i]) for i in own], pa.int32()), pa.array([sets[i].ravel().tolist() for i in own], pa.list_(pa.float64()))]
        if ids is not None:
            columns.append(pa.array([ids[i] for i in own], pa.list_(pa.int64())))
        yield pa.RecordBatch.from_arrays(columns, ["set_id", "n", "flat", "ids"][: len(columns)])


def brute(sets, queries, k, tau, card, ids=None, include_self=False):
    out = set()
    for q, v in queries.items():
        rows = []
        for s, w in sets.items():
            if (s != q or include_self) and (ids is None or q in ids[s]):
                sims = np.rint(v @ w.T * 1_000_000).astype(np.int64)
                rows.append((-K.assign(np.where(sims >= tau, sims, K.NO_EDGE), np.ones(len(w), np.int64), card)[1], s))
        out |= {(q, s, -u) for u, s in sorted(rows)[:k]}
    return out


def found(*how, **more):
    return {row for b in bounded.top_k(*how, **more) for row in zip(*(c.to_pylist() for c in b.columns), strict=True)}


@pytest.mark.parametrize("card", [True, False])
@pytest.mark.parametrize("tau", [0, 300_000, 900_000])
@pytest.mark.parametrize("widest", [4, 24])
def test_the_k_best_by_bounds_are_those_of_all_pairs(card, tau, widest):
    rng = np.random.default_rng(widest + tau)
    sets = lake(rng, 40, widest, 12)
    queries = {i: v for i, v in sets.items() if i % 9 == 0}
    for k in (1, 7):
        assert found(batches(sets), queries, k, tau, card) == brute(sets, queries, k, tau, card)
    assert found(batches(sets), queries, 5, tau, card, include_self=True) == brute(sets, queries, 5, tau, card, include_self=True)


def test_a_query_meets_only_sets_that_list_it():
    rng = np.random.default_rng(3)
    sets = lake(rng, 60, 6)
    queries = {i: v for i, v in sets.items() if i % 9 == 0}
    ids = {s: [q for q in queries if (s + q) % 4 == 0] for s in sets}
    assert found(batches(sets, ids), queries, 5, 300_000, True) == brute(sets, queries, 5, 300_000, True, ids)


def test_few_pairs_are_solved(monkeypatch):
    rng = np.random.default_rng(5)
    sets = lake(rng, 800, 6)
    queries = {i: v for i, v in sets.items() if i % 60 == 0}
    solved, solve = [], bounded.solve
    monkeypatch.setattr(bounded, "solve", lambda a, *how: (solved.append(len(a)), solve(a, *how))[1])
    assert found(batches(sets, size=200), queries, 5, 500_000, True) == brute(sets, queries, 5, 500_000, True)
    assert sum(solved) < len(sets) * len(queries) / 4


def test_both_answers_are_found_without_solving_all_pairs(spark, monkeypatch):
    from unionlake.plans import relational_queries as rq

    def solved_all(*_):
        raise AssertionError("every pair is solved")

    monkeypatch.setattr(rq.mt, "unionability", solved_all)
    monkeypatch.setattr(rq.se, "best_exact", solved_all)
    sf = "/root/testdata/sf0.01"
    exact, quantized = rq._two(spark, sf)
    monkeypatch.undo()
    assert set(map(tuple, exact.collect())) == set(map(tuple, rq.mt.ranked(rq.mt.unionability(rq.sq.sets_of(spark, sf), rq.sq.queries_of(spark, sf), rq.sq.TAU), rq.sq.TOP).collect()))
    assert set(map(tuple, quantized.collect())) == set(map(tuple, rq.sq.REGISTRY["quantized_search"](spark, sf).collect()))
