"""Offline index: centroids, assignment, inverted lists, dispersion, partitions and graphs."""

from __future__ import annotations

import math
import pickle
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from unionlake.operators import kernels as K


def default_centroids(n_vectors: int) -> int:
    return max(8, min(round(4 * math.sqrt(n_vectors)), n_vectors // 2))


def fit_centroids(cols: DataFrame, n_c: int, rounds: int = 10, digits: int = 6, seeds: np.ndarray | None = None, spherical: bool = False) -> np.ndarray:
    """Lloyd's k-means. Each round sends the centroids out and gets one sum per centroid and coordinate back.

    Seeds: the first n_c vectors by (set_id, pos). Coordinates are kept to `digits` places, so that
    the result does not depend on the order of addition. A cluster without vectors keeps its centroid.
    """
    spark = cols.sparkSession
    if seeds is None:
        seeds = np.array([r["v"] for r in cols.orderBy("set_id", "pos").limit(n_c).collect()], np.float64)
    c = np.round(seeds, digits)
    for _ in range(rounds):
        shared = spark.sparkContext.broadcast(c)

        def sums(batches, shared=shared):
            c = shared.value
            total, n = np.zeros_like(c), np.zeros(len(c), np.int64)
            for batch in batches:
                if batch.num_rows:
                    v = batch.column(0).flatten().to_numpy(zero_copy_only=False).reshape(batch.num_rows, -1)
                    own = K.nearest(v, c)
                    np.add.at(total, own, v)
                    n += np.bincount(own, minlength=len(c))
            on = np.flatnonzero(n)
            i, d = np.repeat(on, c.shape[1]), np.tile(np.arange(c.shape[1]), len(on))
            yield pa.RecordBatch.from_arrays([pa.array(i, pa.int32()), pa.array(d, pa.int32()), pa.array(total[on].ravel()), pa.array(np.repeat(n[on], c.shape[1]))], ["c", "d", "s", "n"])

        parts = cols.select("v").mapInArrow(sums, "c int, d int, s double, n bigint")
        got = parts.groupBy("c", "d").agg(F.sum("s").alias("s"), F.sum("n").alias("n")).toPandas()  # n_c * dim rows
        new = c.copy()
        new[got["c"], got["d"]] = np.round(got["s"] / got["n"], digits)
        if spherical:
            length = np.linalg.norm(new, axis=1, keepdims=True)
            new = np.where(length > 0, new / np.maximum(length, 1e-12), new)
        if np.array_equal(new, c):
            break
        c = new
    return c


def assign(cols: DataFrame, centroids: np.ndarray) -> DataFrame:
    """(set_id, pos, c, v): the nearest centroid of each vector."""
    shared = cols.sparkSession.sparkContext.broadcast(centroids)

    def run(batches):
        for batch in batches:
            v = batch.column(2).flatten().to_numpy(zero_copy_only=False).reshape(batch.num_rows, -1)
            own = K.nearest(v, shared.value) if batch.num_rows else np.zeros(0)
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(own.astype(np.int32)), batch.column(2)], ["set_id", "pos", "c", "v"])

    return cols.select("set_id", "pos", "v").mapInArrow(run, "set_id bigint, pos int, c int, v array<double>")


def inverted_vectors(assigned: DataFrame) -> DataFrame:
    return assigned.select("c", "set_id", "pos")


def inverted_counts(assigned: DataFrame) -> DataFrame:
    return assigned.groupBy("c", "set_id").agg(F.count("*").alias("n"))


def centroid_map(counts: DataFrame) -> DataFrame:
    """(set_id, w): map from centroid to how many of the set's vectors it has."""
    return counts.groupBy("set_id").agg(F.map_from_entries(F.array_sort(F.collect_list(F.struct("c", "n")))).alias("w"))


def dispersion(counts: DataFrame) -> DataFrame:
    """(set_id, n, n_cent, rho)."""
    s = counts.groupBy("set_id").agg(F.sum("n").alias("n"), F.count("*").alias("n_cent"))
    return s.withColumn("rho", F.col("n_cent") / F.col("n"))


def dispersion_class(stats: DataFrame, rho_low: float, rho_high: float) -> DataFrame:
    return stats.withColumn("class", F.when(F.col("rho") <= rho_low, "low").when(F.col("rho") >= rho_high, "high").otherwise("mid"))


def partitions_identity(assigned: DataFrame) -> DataFrame:
    """(set_id, k, c, cap): one partition per centroid of a set, numbered by centroid."""
    p = assigned.groupBy("set_id", "c").agg(F.count("*").alias("cap"))
    return p.withColumn("k", F.row_number().over(Window.partitionBy("set_id").orderBy("c")) - 1)


def partition(codes: np.ndarray, v: np.ndarray, centroids: np.ndarray, rho_low: float, rho_high: float, adapt: bool = True) -> tuple[np.ndarray, list[list[int]], np.ndarray]:
    """(partition of each vector, centroid ids of each partition, own centroids): own ones have ids -1, -2, ..."""
    own, place = np.unique(codes, return_inverse=True)
    rho = len(own) / len(codes)
    nothing = np.zeros((0, v.shape[1]))
    if adapt and rho <= rho_low:
        k = min(len(v), max(2, math.ceil(rho_low * len(v))))
        c, at = K.lloyd(v, k)
        used, at = np.unique(at, return_inverse=True)
        return at, [[-1 - i] for i in range(len(used))], c[used]
    if adapt and rho >= rho_high:
        groups = K.merge_groups(centroids[own], np.bincount(place).tolist(), len(codes), rho_high)
        to = np.empty(len(own), np.int64)
        for i, g in enumerate(groups):
            to[g] = i
        return to[place], [[int(own[x]) for x in g] for g in groups], nothing
    return place, [[int(c)] for c in own], nothing


@dataclass
class Index:
    """sets: (set_id, n, flat, part, groups, own); counts: (c, set_id, n)."""

    centroids: np.ndarray
    sets: DataFrame
    counts: DataFrame
    dim: int
    rho_low: float = 0.35
    rho_high: float = 0.80

    def graph(self, links: int = 16, beam: int = 200) -> K.ProximityGraph:
        return K.ProximityGraph(self.centroids, links, beam)


def build(cols: DataFrame, dim: int, n_c: int | None = None, rounds: int = 10, rho_low: float = 0.35, rho_high: float = 0.80, spherical: bool = False, adapt: bool = True, centroids: np.ndarray | None = None) -> Index:
    """One shuffle by set for the set layout, one aggregate for the counts; partitions need none."""
    if rho_low >= rho_high:
        raise ValueError("rho_low must be below rho_high")
    if centroids is None:
        centroids = fit_centroids(cols, n_c or default_centroids(cols.count()), rounds, spherical=spherical)
    assigned = assign(cols, centroids)
    packed = assigned.groupBy("set_id").agg(F.array_sort(F.collect_list(F.struct("pos", "c", "v"))).alias("s"))
    packed = packed.select("set_id", F.size("s").alias("n"), F.flatten(F.transform("s", lambda x: x["v"])).alias("flat"), F.transform("s", lambda x: x["c"]).alias("codes"))
    shared = cols.sparkSession.sparkContext.broadcast(centroids)

    def run(batches):
        for batch in batches:
            parts, groups, own = [], [], []
            for n, flat, codes in zip(*(batch.column(i).to_pylist() for i in (1, 2, 3)), strict=True):
                p, g, o = partition(np.array(codes), np.array(flat).reshape(n, dim), shared.value, rho_low, rho_high, adapt)
                parts.append(p.tolist())
                groups.append(g)
                own.append(o.ravel().tolist())
            columns = [pa.array(parts, pa.list_(pa.int32())), pa.array(groups, pa.list_(pa.list_(pa.int32()))), pa.array(own, pa.list_(pa.float64()))]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), batch.column(2), *columns], ["set_id", "n", "flat", "part", "groups", "own"])

    sets = packed.mapInArrow(run, "set_id bigint, n int, flat array<double>, part array<int>, groups array<array<int>>, own array<double>")
    return Index(centroids, sets, inverted_counts(assigned), dim, rho_low, rho_high)


def partitions(index: Index) -> DataFrame:
    """(set_id, k, g, s, cap): the partitions as rows."""
    rows = index.sets.select("set_id", F.posexplode("groups").alias("k", "g"), "part", "n")
    s = F.filter(F.sequence(F.lit(0), F.col("n") - 1), lambda i: F.element_at("part", i + 1) == F.col("k"))
    return rows.select("set_id", "k", "g", s.alias("s")).withColumn("cap", F.size("s"))


def build_sharded_graph(cols: DataFrame, shards: int, links: int = 16, beam: int = 64) -> DataFrame:
    """(shard, graph BINARY, set_ids, poss): a proximity graph over all column vectors of each shard."""

    def run(pdf):
        import pandas as pd

        pdf = pdf.sort_values(["set_id", "pos"])
        g = K.ProximityGraph(np.array(pdf["v"].tolist()), links, beam)
        return pd.DataFrame({"shard": [int(pdf["shard"].iloc[0])], "graph": [pickle.dumps(g)], "set_ids": [pdf["set_id"].tolist()], "poss": [pdf["pos"].tolist()]})

    keyed = cols.withColumn("shard", F.pmod(F.xxhash64("set_id"), F.lit(shards)).cast("int"))
    return keyed.groupBy("shard").applyInPandas(run, "shard int, graph binary, set_ids array<bigint>, poss array<int>")


def vq_error(assigned: DataFrame, centroids: np.ndarray) -> DataFrame:
    """One row: mean squared error in whole 1e-6, over all vectors."""
    spark = assigned.sparkSession
    c = spark.createDataFrame([(i, x.tolist()) for i, x in enumerate(centroids)], "c int, m array<double>")
    from unionlake.functions.vectors import l2sq

    e = assigned.join(F.broadcast(c), "c").select(F.round(l2sq(F.col("v"), F.col("m")) * 1e6).cast("bigint").alias("e6"))
    return e.agg(F.count("*").alias("n"), F.sum("e6").alias("sum_e6"), F.max("e6").alias("max_e6"))
