"""Refinement in the set layout against the windows, and stages that send numbers to a query and no vectors."""

from __future__ import annotations

from dataclasses import replace

import numpy as np
import pytest
from pyspark.sql import functions as F

from unionlake.functions.vectors import micro
from unionlake.operators import kernels as K
from unionlake.operators import search as se
from unionlake.plans import search_queries as sq

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def lake(spark):
    index, queries = sq.plain_index(spark, SF, adapt=True), sq.queries_of(spark, SF)
    index.sets, index.counts = index.sets.persist(), index.counts.persist()
    return index, queries


@pytest.mark.parametrize("phi_c", [1, 3, 16])
@pytest.mark.parametrize("phi_ref", [2, 1000])
def test_refinement_in_the_set_layout_gives_the_rows_of_the_windows(spark, lake, phi_c, phi_ref):
    index, queries = lake
    probe = se.probe_flat(spark, queries, index.centroids, phi_c)
    want = {tuple(r) for r in se.refine(probe, index.counts, phi_ref).collect()}
    assert want and {tuple(r) for r in se.refine(probe, index.counts, phi_ref, most=0).collect()} == want


def test_many_postings_make_no_row_each(spark):
    counts = spark.range(400).select((F.col("id") % 4).cast("int").alias("c"), "id", F.lit(1).cast("bigint").alias("n")).withColumnRenamed("id", "set_id")
    probe = spark.range(200).select((F.col("id") + 1000).alias("query_id"), F.lit(0).alias("q"), F.explode(F.array(*map(F.lit, range(4)))).alias("c")).withColumn("sim6", (F.col("query_id") - F.col("c")).cast("bigint"))
    got = se.refine(probe, counts, 3, most=1000)
    assert "Generate explode" not in got._jdf.queryExecution().toString().split("MapInArrow")[0] and "BroadcastHashJoin" not in got._jdf.queryExecution().executedPlan().toString()
    # the best centroid of a query is the first, so its sets come first
    assert {(r["set_id"], r["rank"], r["query_id"] - r["score6"]) for r in got.collect()} == {(0, 1, 0), (4, 2, 0), (8, 3, 0)}


@pytest.mark.parametrize("stages", [("refine", "filter", "score"), ("refine", "score"), ("refine", "filter"), ("refine",)])
@pytest.mark.parametrize("prune", ["none", "base", "listing", "lossless"])
def test_stages_send_no_vectors_to_a_query_and_follow_the_rule(lake, stages, prune):
    index, queries = lake
    plan = replace(sq.PLAN, stages=stages, prune=prune)
    ids = se.candidates(index, queries, plan)
    frame = se._stages(index, queries, plan)(ids)
    grouped = [x for x in frame._jdf.queryExecution().optimizedPlan().toString().split("\n") if "FlatMapGroupsInPandas" in x]
    assert grouped and not any("flat#" in x for x in grouped)
    got = {tuple(r) for r in frame.collect()}
    rows, tau = {r.set_id: r for r in index.sets.toPandas().itertuples()}, micro(plan.tau)
    of: dict[int, list[int]] = {}
    for r in ids.collect():
        of.setdefault(r["query_id"], []).append(r["set_id"])
    want = set()
    for q, sets in of.items():
        near = np.rint(queries[q] @ index.centroids.T * 1e6).astype(np.int64)
        seen = {i: se.Candidate(queries[q], near, rows[i], index.dim, tau, True) for i in sorted(sets)}

        def cut(stage, ids, k, bounds, score, q=q, seen=seen):
            answer, evals = K.prune(prune, [(i, *bounds(seen[i])) if prune != "none" else (i, 0, 0) for i in ids], k, lambda i: score(seen[i]))
            want.update((q, stage, rank, i, s, len(ids), len(ids) if prune != "none" else 0, evals) for rank, (i, s) in enumerate(answer, 1))
            return sorted(i for i, _ in answer)

        left = sorted(sets)
        if "filter" in stages:
            left = cut("filter", left, plan.phi_r, se.Candidate.mwmto_bounds, lambda c: c.mwmto()[1])
        if "score" in stages:
            cut("answer", left, plan.k, se.Candidate.score_bounds, se.Candidate.score)
        else:
            cut("answer", left, plan.k, se.Candidate.exact_bounds, se.Candidate.exact)
    assert got == want
