"""Searches over lakes in which most queries touch most sets: no row per pair, the same answers."""

from __future__ import annotations

import pickle

import numpy as np

from unionlake.operators import index as ix
from unionlake.operators import kernels as K
from unionlake.operators import search as se
from unionlake.plans import search_queries as sq
from unionlake.plans import workload_queries as wq

SF = "/root/testdata/sf0.001"


def test_touched_sets_without_a_row_per_pair(spark):
    probe, counts = sq._probe_counts(spark, SF)
    got = {(q, r["set_id"]) for r in se.met_by(probe, counts).collect() for q in r["ids"]}
    assert got == {(r["query_id"], r["set_id"]) for r in se.touched(probe, counts).collect()} and got
    assert "Join" not in se.met_by(probe, counts)._jdf.queryExecution().executedPlan().toString()
    assert se.met_by(probe.where("false"), counts).count() == 0


def test_every_twentieth_conversation_is_a_query(spark, monkeypatch):
    asked = []
    monkeypatch.setattr(wq, "compared", lambda spark, index, cols, sets, queries, *_: asked.append(set(queries)) or sets.limit(0))
    wq.REGISTRY["w_many_queries"](spark, SF)
    ids = {r["conv_id"] for r in wq.lakes.table(spark, SF, "conversations").select("conv_id").distinct().collect()}
    assert asked == [{i for i in ids if i % 20 == 0}] and asked[0]


def test_queries_walk_a_graph_in_step(spark, monkeypatch):
    v = np.random.default_rng(5).normal(size=(700, 8))
    g, queries = K.ProximityGraph(v, 6, 30), np.random.default_rng(6).normal(size=(40, 8))
    for k in (1, 10, 90):
        got = g.top_many(queries, k, most=10_000)
        assert [[i for i, _ in x] for x in got] == [[i for i, _ in g.top(q, k)] for q in queries]
    assert K.ProximityGraph(np.zeros((0, 8))).top_many(queries, 3) == [[]] * 40 and K.ProximityGraph(v[:1]).top_many(queries[:1], 3)[0][0][0] == 0
    shards = ix.build_sharded_graph(sq.cols_of(spark, SF), 2)
    queries = sq.queries_of(spark, SF)
    want, of_shards = set(), shards.toPandas()
    for i, q in queries.items():
        for j, x in enumerate(q):
            near = [(-round(s * 1e6), r.set_ids[n], r.poss[n]) for r in of_shards.itertuples() for n, s in pickle.loads(r.graph).top(x, 5)]
            want |= {(i, j, s, p, -u) for u, s, p in sorted(near)[:5]}
    monkeypatch.setattr(K.ProximityGraph, "top", None)
    assert {tuple(r)[:5] for r in se.column_candidates(shards, queries, 5).collect()} == want


def test_no_similarities_to_all_centroids_are_sent(spark):
    index, queries = sq.plain_index(spark, SF), sq.queries_of(spark, SF)
    sent, real = [], type(spark.sparkContext).broadcast
    try:
        type(spark.sparkContext).broadcast = lambda self, x: sent.append(x) or real(self, x)
        se._stages(index, queries, sq.PLAN)
    finally:
        type(spark.sparkContext).broadcast = real
    assert len(sent) == 1 and sent[0][0] is queries and sent[0][1] is index.centroids
