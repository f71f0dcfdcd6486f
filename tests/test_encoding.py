"""Rows are encoded where they lie, to the same vectors as by counts of tokens."""

from __future__ import annotations

from pyspark.sql import functions as F

from unionlake.sources import lakes


def test_rows_are_encoded_as_by_counts_without_a_shuffle(spark):
    words = [["the", "the", "quick", "fox"], [], None, ["", "straße", None, "straße"], ["a"] * 50 + ["b"] * 7, [str(i % 90) for i in range(400)]]
    rows = spark.createDataFrame([(i // 2, i % 2, w) for i, w in enumerate(words)], "set_id bigint, pos int, tokens array<string>")
    got = lakes.encode(rows)
    assert "Exchange" not in got._jdf.queryExecution().executedPlan().toString()
    counts = rows.select("set_id", "pos", F.explode("tokens").alias("token")).groupBy("set_id", "pos", "token").agg(F.count("*").alias("tf"))
    want = lakes.encode_counts(rows.select("set_id", "pos"), counts)
    assert {tuple(r[:2]): list(r[2]) for r in got.collect()} == {tuple(r[:2]): list(r[2]) for r in want.collect()}


def test_only_wanted_documents_are_encoded(spark):
    sf = "/root/testdata/sf0.001"
    ids = spark.createDataFrame([(3,), (8,)], "set_id bigint")
    some, every = lakes.document_lake(spark, sf, ids), lakes.document_lake(spark, sf)
    assert sorted(map(str, some.collect())) == sorted(map(str, every.where("set_id in (3, 8)").collect()))
