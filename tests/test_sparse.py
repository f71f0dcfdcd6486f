"""Pairs bounded and solved from their edges, many at once, are as pairs one by one; a vector is normalized in one pass."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from unionlake.functions.vectors import normalize
from unionlake.operators import kernels as K
from unionlake.operators import search as se
from unionlake.operators import sparse as S
from unionlake.sources import lakes

SF = "/root/testdata/sf0.001"


def edges_of(matrices: list[np.ndarray]) -> S.Edges:
    at = [np.nonzero(m >= 0) for m in matrices]
    pair = np.repeat(np.arange(len(matrices)), [len(q) for q, _ in at])
    return S.Edges(pair, *[np.concatenate([x[i] for x in at]) for i in (0, 1)], np.concatenate([m[m >= 0] for m in matrices]), len(matrices), np.array([min(m.shape) for m in matrices]))


@pytest.mark.parametrize("card", [True, False])
def test_edges_give_what_matrices_give(card):
    pick = np.random.default_rng(1)
    matrices = [np.where(pick.random((n, p)) < pick.choice([0.1, 0.3, 0.8]), pick.integers(1, pick.choice([5, 40, 10**6]), (n, p)), -1) for n, p in pick.integers(1, 9, (300, 2))]
    problems, e = [K.Problem(m, np.ones(m.shape[1], np.int64), 1, card, False) for m in matrices], edges_of(matrices)
    assert S.uppers(e).tolist() == [p.upper() for p in problems]
    assert S.lowers(e, 1, card).tolist() == [p.lower() for p in problems]
    want = [p.score() for p in problems]
    assert S.scores(e, card).tolist() == want == [K.assign_wide(m, card) for m in matrices]


@pytest.mark.parametrize("rule", ["none", "base", "listing"])
def test_blocks_change_no_answer_and_no_count(rule):
    pick, tau, dim, n = np.random.default_rng(4), 100_000, 6, 200
    for k in (1, 2, 5):
        queries = [np.abs(pick.normal(size=(int(w), dim))) * (pick.random((1, dim)) < 0.3) for w in pick.integers(1, 4, 5)]
        ns, set_ids = pick.integers(1, 4, n), pick.permutation(n)
        flat = np.abs(pick.normal(size=(int(ns.sum()), dim))) * np.repeat(pick.random((n, dim)) < 0.25, ns, axis=0)
        sets = pa.RecordBatch.from_arrays([pa.array(set_ids), pa.array(ns.astype(np.int32)), pa.ListArray.from_arrays(pa.array(np.r_[0, np.cumsum(ns * dim)], pa.int32()), pa.array(flat.ravel()))], ["set_id", "n", "flat"])
        got, want = [K.Keeper(rule, k) for _ in queries], [K.Keeper(rule, k) for _ in queries]
        for block in S.blocks(iter([sets.slice(0, 150), sets.slice(150)]), np.arange(5), np.concatenate(queries), np.cumsum([0, *map(len, queries)]), tau, few=7):
            S.see(got, block, tau, True)
        for s, v in zip(set_ids.tolist(), np.split(flat, np.cumsum(ns)[:-1]), strict=True):
            for q, keeper in enumerate(want):
                m = np.rint(queries[q] @ v.T * 1e6).astype(np.int64)
                if q != s:
                    keeper.see(s, K.Problem(np.where(m >= tau, m, -1), np.ones(len(v), np.int64), tau, True, False))
        assert [(x.finish(), x.seen, x.bounded, x.evals) for x in got] == [(x.finish(), x.seen, x.bounded, x.evals) for x in want]


def test_a_vector_is_normalized_in_one_pass(spark):
    df = spark.createDataFrame([([3.0, 4.0],), ([0.0, 0.0],), (None,)], "v array<double>")
    out = df.select(normalize(F.col("v")).alias("v"))
    assert [r["v"] for r in out.collect()] == [[0.6, 0.8], [0.0, 0.0], None]
    assert out._jdf.queryExecution().optimizedPlan().toString().count("aggregate(") == 1  # the norm is not found anew for each element


def test_probe_is_one_product_a_task(spark):
    pick = np.random.default_rng(6)
    queries, c = {i: pick.integers(-2, 3, (3, 4)).astype(float) for i in (1, 7)}, pick.integers(-2, 3, (9, 4)).astype(float)  # many ties
    probe = se.probe_flat(spark, queries, c, 3)
    assert "Join" not in probe._jdf.queryExecution().executedPlan().toString()
    want = {(i, j, x, s) for i, q in queries.items() for j, v in enumerate(q) for s, x in sorted(((int(v @ m) * 10**6, x) for x, m in enumerate(c)), key=lambda y: (-y[0], y[1]))[:3]}
    assert {(r["query_id"], r["q"], r["c"], r["sim6"]) for r in probe.collect()} == want
    assert se.probe_flat(spark, queries, c, 20).count() == 2 * 3 * 9


def test_a_planted_lake_is_spread(spark):
    assert lakes.planted_lake(spark, SF, 2).rdd.getNumPartitions() > 1  # its one file is one split


def test_single_problems_take_the_shorter_way(monkeypatch):
    pick, asked = np.random.default_rng(2), []
    m = np.where(pick.random((30, 40)) < 0.6, pick.integers(1, 9, (30, 40)), -1)
    want = K.assign(m, np.ones(40, np.int64))[1]
    monkeypatch.setattr(K, "assign", lambda *_: asked.append("assign"))
    monkeypatch.setattr(K, "assign_many", lambda *_: asked.append("assign_many"))
    p = K.Problem(m, np.ones(40, np.int64), 1, True, False)
    K.prepare([p], "score")
    assert p.score() == want == S.scores(edges_of([m]), True)[0] and not asked
    assert K.assign_wide(np.full((3, 0), -1)) == K.assign_wide(np.full((2, 2), -1)) == 0


def test_groups_merge_as_by_hand():
    c = np.array([[1.0, 0.0], [0.9, 0.1], [0.0, 1.0], [0.0, 0.9], [0.5, 0.5]])
    assert K.merge_groups(c, [1] * 5, 5, 0.9) == [[0, 1], [2], [3], [4]]
    assert K.merge_groups(c, [1] * 5, 5, 0.5) == [[0, 1, 4], [2, 3]]
