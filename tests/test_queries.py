"""Queries are collected as columns of numbers, without an object per value on the driver."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame

from unionlake.operators import matching as mt


def test_queries_are_collected_without_rows(spark, monkeypatch):
    rows = [(7, 1, [3.0, 4.0]), (2, 0, [0.5, 1.5]), (7, 0, [1.0, 2.0]), (7, 2, [5.0, 6.0])]
    cols = spark.createDataFrame(rows, "set_id bigint, pos int, v array<double>").localCheckpoint()
    with monkeypatch.context() as m:
        m.setattr(type(cols), "collect", None)
        m.setattr(DataFrame, "collect", None)
        m.setattr(type(cols), "first", lambda self: (4,))
        got = mt.collect_queries(cols)
    assert list(got) == [2, 7] and got[2].tolist() == [[0.5, 1.5]] and got[7].tolist() == [[1.0, 2.0], [3.0, 4.0], [5.0, 6.0]]
    assert all(v.dtype == np.float64 and v.flags.c_contiguous for v in got.values())
    assert mt.collect_queries(cols.where("false")) == {}
    uneven = spark.createDataFrame([(1, 0, [1.0]), (2, 0, [1.0, 2.0])], "set_id bigint, pos int, v array<double>")
    assert {i: v.tolist() for i, v in mt.collect_queries(uneven).items()} == {1: [[1.0]], 2: [[1.0, 2.0]]}
