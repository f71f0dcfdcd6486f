from __future__ import annotations

from unionlake.plans import workload_queries as wq
from unionlake.sources import lakes

SF = "/root/testdata/sf0.001"


def test_stream_equals_batch(spark):
    from unionlake.operators import index as ix
    from unionlake.plans import search_queries as sq

    got = {r["c"]: r["n"] for r in wq.REGISTRY["stream_ingest_counts"](spark, SF).collect()}
    want = {r["c"]: r["n"] for r in ix.inverted_vectors(sq.assigned(spark, SF)).groupBy("c").count().withColumnRenamed("count", "n").collect()}
    assert got == want


def test_relational_lake(spark):
    n = {r["set_id"]: r["count"] for r in lakes.relational_lake(spark, SF).groupBy("set_id").count().collect()}
    assert len(n) >= 150 and min(n.values()) >= 1 and max(n.values()) == 11


def test_relational_lake_encodes_every_row(spark):
    import hashlib
    from collections import Counter

    import numpy as np

    sf = "/root/testdata/sf0.01"
    e = lakes.table(spark, sf, "events").select("event_type", "value").toPandas()
    got = {r["set_id"]: r["v"] for r in lakes.relational_lake(spark, sf).where("set_id between 7000 and 7999 and set_id % 2 = 0 and pos = 4").collect()}
    assert len(got) == e.event_type.nunique() and e.event_type.value_counts().max() > 1000
    for rank, (_, rows) in enumerate(sorted(e.groupby("event_type"))):
        tokens: Counter = Counter()
        for x in rows.value:
            whole = str(int(abs(x)))
            tokens.update([f"n{len(whole)}", whole[0]])
        want = np.zeros(64)
        for token, tf in tokens.items():
            h = hashlib.md5(token.encode()).hexdigest()
            want[int(h[:8], 16) % 64] += (1 if int(h[8], 16) < 8 else -1) * round((1 + np.log(tf)) * 1e6)
        assert np.allclose(got[7000 + 2 * (rank + 1)], want / np.linalg.norm(want))


def test_filtered_search_takes_every_twentieth_document(spark):
    got = {r["query_id"] for r in wq.REGISTRY["filtered_search"](spark, SF).select("query_id").distinct().collect()}
    good = lakes.table(spark, SF, "labels").where("quality = 1 and toxic = 0 and doc_id % 20 = 0").select("doc_id")
    docs = lakes.table(spark, SF, "documents").where("trim(text) != ''")
    assert got == {r["doc_id"] for r in docs.join(good, "doc_id", "left_semi").select("doc_id").collect()} and got


def test_refinement_recall_rises_with_candidates(spark):
    r = [x["recall"] for x in wq._sweep(spark, SF, "phi_ref", [6, 24, 120], phi_c=32, stages=("refine",)).orderBy("phi_ref").collect()]
    assert r == sorted(r) and r[-1] > r[0]


def test_index_store_and_source(spark, tmp_path):
    import pytest

    from unionlake.operators import search as se
    from unionlake.plans import search_queries as sq
    from unionlake.sources import store

    index, q = sq.plain_index(spark, SF, adapt=True), sq.queries_of(spark, SF)
    folder = "file://" + str(tmp_path)
    store.save(index, folder, 1, buckets=4)
    m = store.save(index, folder, 2, buckets=4)
    assert m["sets"] == 84 and [r["version"] for r in store.versions(spark, folder).orderBy("version").collect()] == [1, 2]
    got = se.union_search(store.load(spark, folder), q, sq.PLAN).orderBy("query_id", "rank").collect()
    assert got == se.union_search(index, q, sq.PLAN).orderBy("query_id", "rank").collect()
    with pytest.raises(FileNotFoundError):
        store.load(spark, folder, 9)
    spark.dataSource.register(store.VecSetSource)
    sets = spark.read.format("vecset").load(f"{folder}/version=2/sets")
    assert sets.count() == 84
    spark.conf.set("spark.sql.python.filterPushdown.enabled", "true")
    for pushdown in ("false", "true"):
        sets = spark.read.format("vecset").option("pushdown", pushdown).load(f"{folder}/version=2/sets")
        assert sorted(r["set_id"] for r in sets.where("set_id >= 10 and set_id <= 12").collect()) == [10, 11, 12]
