"""Matchings of many problems in step, and their check where they are found."""

from __future__ import annotations

import numpy as np
import pytest

from unionlake.operators import kernels as K
from unionlake.operators import matching as mt
from unionlake.plans import search_queries as sq

SF = "/root/testdata/sf0.01"


@pytest.mark.parametrize("shape", [(1, 1), (1, 5), (5, 1), (3, 7), (7, 3), (6, 6)])
@pytest.mark.parametrize("card", [True, False])
def test_problems_in_step_are_solved_as_one_by_one(shape, card):
    rng = np.random.default_rng(shape[0] * 10 + shape[1])
    sims = rng.integers(-6, 9, (60, *shape))  # many ties, some without an edge
    sims[sims < 0] = K.NO_EDGE
    t, u, to = K.match_many(sims, card)
    for x in range(len(sims)):
        want = K.assign(sims[x], np.ones(shape[1], np.int64), card)
        on = np.flatnonzero(to[x] >= 0)
        assert u[x] == want[1] and (not card or t[x] == want[0])
        assert len(on) == t[x] == len(set(to[x, on])) and (sims[x, on, to[x, on]] >= 0).all()


def rows(df):
    return {tuple(r) for r in df.select("query_id", "set_id", "t", "u6", "valid").collect()}


def test_matchings_are_checked_without_a_row_per_edge(spark, monkeypatch):
    sets, queries = sq.sets_of(spark, SF), sq.queries_of(spark, SF)
    m = mt.best_matching(sets, queries, sq.TAU)
    total = m.groupBy("query_id", "set_id").agg({"sim6": "sum"}).withColumnRenamed("sum(sim6)", "u6")
    want = rows(mt.is_matching(m, sq.edges_tau(spark, SF)).join(total, ["query_id", "set_id"]))

    def no_edges(*_):
        raise AssertionError("all edges become rows")

    monkeypatch.setattr(sq, "edges_tau", no_edges)
    assert rows(sq.REGISTRY["best_matching_check"](spark, SF)) == want


@pytest.mark.parametrize("wrong", ["target twice", "column twice", "no edge"])
def test_wrong_matchings_are_found(spark, wrong):
    def pairs(sims, card):
        b, n, p = sims.shape
        at, x = np.arange(b), np.zeros(b, np.int64)
        if wrong == "no edge":
            i, j = np.divmod(sims.reshape(b, n * p).argmin(1), p)
            return at, i, j
        other = x + 1
        return np.repeat(at, 2), np.stack([x, x if wrong == "column twice" else other], 1).ravel(), np.stack([x, x if wrong == "target twice" else other], 1).ravel()

    sets = spark.createDataFrame([(1, 2, [1.0, 0.0, 0.8, 0.6])], "set_id bigint, n int, flat array<double>")
    queries = {7: np.array([[1.0, 0.0], [0.6, 0.8]])}
    tau = 0.7 if wrong == "no edge" else 0.1
    good = mt.checked_matchings(sets, queries, tau).first()
    assert (good["t"], good["u6"], good["valid"]) == (2, 1_960_000, True)
    real, mt.pairs_of = mt.pairs_of, pairs
    try:
        assert [r["valid"] for r in mt.checked_matchings(sets, queries, tau).collect()] == [False]
    finally:
        mt.pairs_of = real
