from __future__ import annotations

from dataclasses import replace

import duckdb
import numpy as np
import pandas as pd
import pytest

from unionlake.operators import index as ix
from unionlake.operators import matching as mt
from unionlake.operators import search as se
from unionlake.plans import search_queries as sq
from unionlake.sources import lakes

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def con():
    import os

    c = duckdb.connect()
    for f in os.listdir(SF):
        c.execute(f"CREATE VIEW {f[:-8]} AS SELECT * FROM '{SF}/{f}'")
    return c


def rows(df: pd.DataFrame) -> list:
    return sorted(tuple(None if pd.isna(x) else x for x in r) for r in df[sorted(df.columns)].itertuples(index=False))


@pytest.mark.parametrize("key", ["edges_tau", "unionability_card", "unionability_weight", "mwmto_card", "topk_exact_card", "refine_block", "filter_base", "filter_enhanced", "quantized_plus", "scan_enhanced_prune", "column_flat_search", "partition_index_check"])
def test_against_sql(spark, con, key):
    assert rows(sq.REGISTRY[key](spark, SF).toPandas()) == rows(con.execute(sq.SQL[key]).df())


def test_staged_variants(spark):
    index, q = sq.plain_index(spark, SF, adapt=True), sq.queries_of(spark, SF)
    index.sets, index.counts = index.sets.persist(), index.counts.persist()
    plans = [replace(sq.PLAN, prune=p) for p in ("none", "base", "lossless")]
    got = [rows(se.union_search(index, q, p).toPandas()) for p in plans]
    assert got[0] == got[1] == got[2]
    wide = replace(sq.PLAN, phi_c=sq.N_C, phi_ref=100, phi_r=100, stages=("refine", "filter"))
    exact = mt.top_k_exact(sq.sets_of(spark, SF), q, sq.TAU, sq.PLAN.k).toPandas()
    assert rows(se.union_search(index, q, wide).toPandas()) == rows(exact)  # every set reached, none cut


def test_partition_score_stays_below_unionability(spark):
    s = sq.REGISTRY["partition_score"](spark, SF).toPandas().merge(mt.unionability(sq.sets_of(spark, SF), sq.queries_of(spark, SF), sq.TAU, "max_weight").toPandas(), on=["query_id", "set_id"])
    assert len(s) and (s.score6 <= s.u6).all()


def test_block_refinement_is_the_heap_walk(spark):
    probe, counts = sq._probe_counts(spark, SF)
    p, c = probe.toPandas(), counts.toPandas()
    got = {(r.query_id, r.set_id): r.score6 for r in se.refine(probe, counts, 10_000).toPandas().itertuples()}
    by_c = {k: list(zip(g.set_id, g.n, strict=True)) for k, g in c.groupby("c")}
    score, used, done = {}, {}, set()
    for r in p.sort_values(["sim6", "q", "c"], ascending=[False, True, True]).itertuples():
        for s, n in by_c.get(r.c, ()):
            if s == r.query_id or (r.query_id, s, r.q) in done:
                continue
            done.add((r.query_id, s, r.q))
            if used.get((r.query_id, s, r.c), 0) < n:
                used[r.query_id, s, r.c] = used.get((r.query_id, s, r.c), 0) + 1
                score[r.query_id, s] = score.get((r.query_id, s), 0) + r.sim6
    assert got == score


def test_edge_cases(spark):
    one = [1.0] + [0.0] * 63
    two = [0.0, 1.0] + [0.0] * 62
    cols = spark.createDataFrame([(1, 0, one), (2, 0, one), (2, 1, one), (3, 0, two), (4, 0, [0.0] * 64), (5, 0, None), (6, 0, [1.0])], "set_id bigint, pos int, v array<double>")
    sets = lakes.vec_sets(cols)
    assert {r["set_id"] for r in lakes.bad_vectors(cols).collect()} == {5, 6}
    q = mt.collect_queries(cols.where("set_id = 1"))
    got = [(r["set_id"], r["score6"]) for r in mt.top_k_exact(sets, q, 1.0, 10).orderBy("rank").collect()]
    assert got == [(2, 1_000_000), (3, 0), (4, 0)]
    assert mt.top_k_scan(sets, q, 0.5, 10, "lossless")[0].count() == 3
    assert mt.top_k_exact(sets.where("false"), q, 0.5, 10).count() == 0
    with pytest.raises(ValueError):
        mt.collect_queries(cols.where("set_id < 5"), 10)
    with pytest.raises(ValueError):
        se.Plan(k=10, phi_r=5)
    part, groups, own = ix.partition(np.array([0, 0, 0, 0]), np.eye(4), np.eye(4), 0.35, 0.8)
    assert sorted(np.bincount(part)) and len(groups) == len(own) and all(g[0] < 0 for g in groups)
