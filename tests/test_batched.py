"""Many pairs solved at once give what SQL-like brute force gives; nothing is grouped by pair."""

from __future__ import annotations

import numpy as np

from unionlake.operators import index as ix
from unionlake.operators import kernels as K
from unionlake.operators import matching as mt
from unionlake.operators import search as se
from unionlake.plans import relational_queries as rq
from unionlake.plans import search_queries as sq

SF = "/root/testdata/sf0.001"


def plan_of(df) -> str:
    return df._jdf.queryExecution().executedPlan().toString()


def test_edges_and_nearest_columns(spark):
    pick = np.random.default_rng(3)
    v = pick.integers(-2, 3, (60, 4)).astype(float)  # many ties
    cols = spark.createDataFrame([(int(i // 3), int(i % 3), x.tolist()) for i, x in enumerate(v)] + [(50, 0, None), (51, 0, [1.0, None, 1.0, 1.0]), (52, 0, [1.0, 2.0]), (53, 0, [2.0, 1.0])], "set_id bigint, pos int, v array<double>")
    own = cols.where("set_id in (0, 5, 53)")
    got = {tuple(r) for r in mt.edges(own, cols, 1.0).collect()}
    want = {(a // 3, b // 3, a % 3, b % 3, int(v[a] @ v[b]) * 10**6) for a in range(60) if a // 3 in (0, 5) for b in range(60) if a // 3 != b // 3 and v[a] @ v[b] >= 1}
    assert got == want | {(53, 52, 0, 0, 4 * 10**6)}
    assert "BroadcastNestedLoopJoin" not in plan_of(mt.edges(own, cols, 1.0))
    queries = mt.collect_queries(cols.where("set_id in (0, 5)"))
    near = {tuple(r) for r in se.flat_column_candidates(cols.repartition(3), queries, 7).collect()}
    for a in (0, 1, 2, 15, 16, 17):
        best = sorted((-int(v[a] @ v[b]) * 10**6, b // 3, b % 3) for b in range(60))[:7]
        assert {(a // 3, a % 3, s, p, -x) for x, s, p in best} == {r for r in near if r[0] == a // 3 and r[1] == a % 3}


def test_no_group_is_one_pair(spark):
    cols, queries = sq.cols_of(spark, SF), sq.queries_of(spark, SF)
    exact = {(r["query_id"], r["set_id"]): (r["t"], r["u6"]) for r in mt.unionability(sq.sets_of(spark, SF), queries, sq.TAU).collect()}
    for name, of in (("cogroup_union", rq), ("udaf_unionability", rq), ("mwmto_card", sq), ("bounds_mwmto", sq)):
        plan = plan_of(of.REGISTRY[name](spark, SF))
        assert "hashpartitioning(query_id" not in plan, name
    got = {(r["query_id"], r["set_id"]): (r["t"], r["u6"]) for r in rq.REGISTRY["cogroup_union"](spark, SF).collect()}
    assert got == {k: x for k, x in exact.items() if x[0]}
    index = ix.build(cols, 64, centroids=sq.seeds(spark, SF)[:8])
    rows = {r["set_id"]: r for r in index.sets.collect()}
    for kind in ("mwmto", "score"):
        for r in se.bounds_scan(index, queries, sq.TAU, kind).collect():
            q = queries[r["query_id"]]
            c = se.Candidate(q, np.rint(q @ index.centroids.T * 1e6).astype(np.int64), rows[r["set_id"]], 64, 100_000, True)
            lb, ub = c.mwmto_bounds() if kind == "mwmto" else c.score_bounds()
            assert (r["lb6"], r["score6"], r["ub6"]) == (lb, c.mwmto()[1] if kind == "mwmto" else c.score(), ub)


def test_prepared_problems_change_no_count(spark):
    pick = np.random.default_rng(9)
    sims = [np.where(pick.random((n, p)) < 0.5, pick.integers(1, 40, (n, p)), -1) for n, p in pick.integers(1, 5, (80, 2))]
    for rule in ("none", "base", "listing"):
        plain, ready = K.Keeper(rule, 5), K.Keeper(rule, 5)
        problems = [K.Problem(s, np.ones(s.shape[1], np.int64), 1, True, False) for s in sims]
        for what in ("upper", "lower", "score"):
            K.prepare(problems, what)
        for i, s in enumerate(sims):
            plain.see(i, K.Problem(s, np.ones(s.shape[1], np.int64), 1, True, False))
            ready.see(i, problems[i])
        assert plain.finish() == ready.finish() and plain.evals == ready.evals


def test_examples_read_given_tables(spark):
    from unionlake.plans import workload_queries as wq

    for name, of, table in (("example_matching", sq, "embeddings"), ("pareto_front", wq, "part")):
        assert any(f.endswith(f"{table}.parquet") for f in of.REGISTRY[name](spark, SF).inputFiles()), name


def test_front_is_what_nothing_beats(spark):
    from unionlake.plans import workload_queries as wq

    pick = np.random.default_rng(2)
    points = [(i, int(r), int(m)) for i, (r, m) in enumerate(pick.integers(0, 12, (90, 2)))]
    got = {tuple(r) for r in wq.pareto_front(spark.createDataFrame(points, "i int, recall int, ms int")).collect()}
    assert got == {p for p in points if not any(q[1] >= p[1] and q[2] <= p[2] and q[1:] != p[1:] for q in points)}
