"""Staged search: probe centroids, refine by capacity-bounded credit, filter by many-to-one matching, score within partitions."""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from unionlake.functions.vectors import MICRO, micro, sim6
from unionlake.operators import credit as cr
from unionlake.operators import kernels as K
from unionlake.operators.index import Index
from unionlake.operators.matching import Queries, best_exact, best_of, by_length, by_width, rows_of, top_k_exact
from unionlake.sources.shared import written


@dataclass(frozen=True)
class Plan:
    """All parameters of a search. prune: none, base, listing or lossless. stages: which of refine, filter, score run;
    without refine all touched sets go on, without filter all refined ones, without score exact unionability ranks."""

    k: int = 10
    tau: float = 0.1
    phi_c: int = 8
    phi_ref: int = 100
    phi_r: int = 30
    prune: str = "base"
    semantics: str = "max_cardinality"
    on_full: str = "block"
    tau_in_refine: bool = False
    probe: str = "flat"
    stages: tuple[str, ...] = ("refine", "filter", "score")

    def __post_init__(self):
        if "refine" in self.stages and "filter" in self.stages and self.phi_r > self.phi_ref:
            raise ValueError("phi_r must not exceed phi_ref")
        if "filter" in self.stages and self.k > self.phi_r:
            raise ValueError("k must not exceed phi_r")


def query_frame(spark: SparkSession, queries: Queries) -> DataFrame:
    ids, qs, vectors = rows_of(queries)
    lists = pa.ListArray.from_arrays(pa.array(np.arange(len(ids) + 1) * vectors.shape[1], pa.int32()), pa.array(vectors.ravel(), pa.float64()))
    return spark.createDataFrame(pa.table([pa.array(ids, pa.int64()), pa.array(qs, pa.int32()), lists], ["query_id", "q", "vq"]), "query_id bigint, q int, vq array<double>")


def centroid_frame(spark: SparkSession, centroids: np.ndarray) -> DataFrame:
    return spark.createDataFrame([(i, c.tolist()) for i, c in enumerate(centroids)], "c int, m array<double>")


def probe_flat(spark: SparkSession, queries: Queries, centroids: np.ndarray, phi_c: int) -> DataFrame:
    """(query_id, q, c, sim6): the phi_c centroids of the largest inner product with each query column, ties by centroid.

    Centroids are small by their parameter and go to the query columns; a matrix product serves many of these.
    """
    shared, names = spark.sparkContext.broadcast(centroids), ["query_id", "q", "c", "sim6"]

    def run(batches, most: int = 1 << 20):
        m = shared.value
        step = max(1, most // max(1, len(m)))
        for batch in batches:
            every = batch.column(2).flatten().to_numpy(zero_copy_only=False).reshape(batch.num_rows, m.shape[1])
            for low in range(0, len(every), step):
                sims = np.rint(every[low : low + step] @ m.T * MICRO).astype(np.int64)
                keys = np.arange(len(m)) - sims * len(m)  # of equals the first
                at = np.argpartition(keys, phi_c - 1, axis=1)[:, :phi_c] if phi_c < len(m) else np.broadcast_to(np.arange(len(m)), sims.shape)
                ids, qs = (np.repeat(batch.column(i).to_numpy(zero_copy_only=False)[low : low + step], at.shape[1]) for i in (0, 1))
                yield pa.RecordBatch.from_arrays([pa.array(ids), pa.array(qs), pa.array(at.ravel().astype(np.int32)), pa.array(np.take_along_axis(sims, at, 1).ravel())], names)

    return query_frame(spark, queries).mapInArrow(run, "query_id bigint, q int, c int, sim6 bigint")


def probe_graph(spark: SparkSession, queries: Queries, graph: K.ProximityGraph, phi_c: int, beam: int | None = None) -> DataFrame:
    shared = spark.sparkContext.broadcast(graph)

    def run(frames):
        import pandas as pd

        for pdf in frames:
            rows = [(i, q, c, round(s * MICRO)) for i, q, v in zip(pdf["query_id"], pdf["q"], pdf["vq"], strict=True) for c, s in shared.value.top(np.array(v), phi_c, beam)]
            yield pd.DataFrame(rows, columns=["query_id", "q", "c", "sim6"])

    return query_frame(spark, queries).mapInPandas(run, "query_id bigint, q int, c int, sim6 bigint")


def postings(probe: DataFrame, counts: DataFrame) -> DataFrame:
    """(query_id, set_id, q, c, sim6, n) of every set on a probed list; the probe is small, so lists do not move."""
    return counts.join(F.broadcast(probe), "c").where("set_id != query_id")


def touched(probe: DataFrame, counts: DataFrame) -> DataFrame:
    return postings(probe, counts).select("query_id", "set_id").distinct()


def met_by(probe: DataFrame, counts: DataFrame) -> DataFrame:
    """(set_id, ids): the queries that probe a list of each set; `touched` in the set layout, without a row per pair."""
    got = probe.select("query_id", "c").distinct().toArrow()
    ids, place = np.unique(got.column("query_id").to_numpy(), return_inverse=True)
    c = got.column("c").to_numpy()
    probes = np.zeros((len(ids), int(c.max(initial=-1)) + 1), bool)
    probes[place, c] = True
    shared = probe.sparkSession.sparkContext.broadcast((ids, probes))

    def run(batches, most: int = 1 << 22):
        ids, probes = shared.value
        step = max(1, most // max(1, len(ids)))
        for every in batches:
            for low in range(0, every.num_rows, step):
                batch = every.slice(low, step)
                c = batch.column(1).flatten().to_numpy(zero_copy_only=False)
                order = np.argsort(c, kind="stable")
                at = np.repeat(np.arange(batch.num_rows), np.asarray(batch.column(1).value_lengths()))[order]
                begin = np.searchsorted(c[order], np.arange(probes.shape[1] + 1))  # where the sets of each centroid begin
                meets = np.zeros((batch.num_rows, len(ids)), bool)
                for c in np.flatnonzero(np.diff(begin)).tolist():
                    meets[np.ix_(at[begin[c] : begin[c + 1]], np.flatnonzero(probes[:, c]))] = True
                set_ids = batch.column(0).to_numpy(zero_copy_only=False)
                meets &= set_ids[:, None] != ids[None, :]
                ends = np.concatenate([[0], np.cumsum(meets.sum(1))])
                lists = pa.ListArray.from_arrays(pa.array(ends, pa.int32()), pa.array(ids[np.nonzero(meets)[1]], pa.int64()))
                on = pa.array(np.diff(ends) > 0)
                yield pa.RecordBatch.from_arrays([batch.column(0).filter(on), lists.filter(on)], ["set_id", "ids"])

    lists = counts.groupBy("set_id").agg(F.collect_list("c").alias("c"))
    return lists.mapInArrow(run, "set_id bigint, ids array<bigint>")


def tasks(spark: SparkSession) -> int:
    """So many tasks that all cores have work, however few bytes it takes."""
    return max(2 * spark.sparkContext.defaultParallelism, int(spark.conf.get("spark.sql.shuffle.partitions")))


def refine_in_sets(probe: DataFrame, counts: DataFrame, phi_ref: int) -> DataFrame:
    """`refine` by block in the set layout, without a row per posting: a task gives the phi_ref best of its sets for each query.

    A task of its own for each core and no more, since each gives so many rows.
    """
    spark, got = probe.sparkSession, probe.select("query_id", "q", "c", "sim6").toArrow()
    shared = spark.sparkContext.broadcast(tuple(x.to_numpy() for x in got.columns))
    lists = counts.repartition(spark.sparkContext.defaultParallelism, "set_id").groupBy("set_id")
    lists = lists.agg(F.collect_list(F.struct("c", "n")).alias("s")).select("set_id", F.col("s.c").alias("c"), F.col("s.n").alias("n"))
    return lists.sortWithinPartitions("set_id").mapInArrow(lambda batches: cr.best_sets(batches, cr.Probes(*shared.value), phi_ref), "query_id bigint, set_id bigint, score6 bigint")


def refine(probe: DataFrame, counts: DataFrame, phi_ref: int, on_full: str = "block", tau6: int | None = None, most: int = 10_000_000) -> DataFrame:
    """(query_id, set_id, score6, rank): the phi_ref best sets by credit.

    block: a query column spends its one try on the best probed centroid of the set, whether or
    not there is room. Only the order within a set matters, so this is two windows over one
    shuffle by (query, set), or if there are more than `most` postings, a scan of the sets.
    fallthrough: a column that finds no room tries its next centroid.
    """
    if tau6 is not None:
        probe = probe.where(F.col("sim6") >= tau6)
    order = Window.partitionBy("query_id").orderBy(F.col("score6").desc(), "set_id")
    if on_full == "block":
        sizes = counts.groupBy("c").agg(F.count("*").alias("lists")).join(probe.groupBy("c").agg(F.count("*").alias("columns")), "c")
        if (sizes.agg(F.sum(F.col("lists") * F.col("columns"))).first()[0] or 0) > most:
            return refine_in_sets(probe, counts, phi_ref).withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= phi_ref)
    post = postings(probe, counts).repartition("query_id", "set_id")
    if on_full == "block":
        first = Window.partitionBy("query_id", "set_id", "q").orderBy(F.col("sim6").desc(), "c")
        room = Window.partitionBy("query_id", "set_id", "c").orderBy(F.col("sim6").desc(), "q")
        hit = post.withColumn("r1", F.row_number().over(first)).where("r1 = 1").withColumn("r2", F.row_number().over(room)).where("r2 <= n")
        credit = hit.groupBy("query_id", "set_id").agg(F.sum("sim6").alias("score6"))
    elif on_full == "fallthrough":
        arrivals = F.sort_array(F.collect_list(F.struct((-F.col("sim6")).alias("s"), "q", "c", "n")))
        start = F.struct(F.lit(0).cast("bigint").alias("score"), F.array().cast("array<int>").alias("done"), F.array().cast("array<int>").alias("used"))

        def step(a, x):
            free = F.size(F.filter(a["used"], lambda u: u == x["c"])) < x["n"]
            take = free & ~F.array_contains(a["done"], x["q"])
            return F.when(take, F.struct((a["score"] - x["s"]).alias("score"), F.concat(a["done"], F.array(x["q"])).alias("done"), F.concat(a["used"], F.array(x["c"])).alias("used"))).otherwise(a)

        credit = post.groupBy("query_id", "set_id").agg(arrivals.alias("x")).select("query_id", "set_id", F.aggregate("x", start, step)["score"].alias("score6"))
    else:
        raise ValueError(f"unknown on_full {on_full!r}")
    return credit.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= phi_ref)


class Candidate:
    """One set as a query sees it: similarities to its partitions and vectors, bounds and scores on demand."""

    def __init__(self, q: np.ndarray, to_centroids: np.ndarray, row, dim: int, tau: int, card: bool):
        self.set_id, self.tau, self.card = int(row.set_id), tau, card
        self.q, self.v = q, np.asarray(row.flat, np.float64).reshape(-1, dim)
        self.part = np.asarray(row.part)
        own = np.asarray(row.own, np.float64).reshape(-1, dim)
        to_own = np.rint(q @ own.T * MICRO).astype(np.int64)
        columns = [np.max([to_centroids[:, c] if c >= 0 else to_own[:, -1 - c] for c in g], axis=0) for g in row.groups]
        sims = np.stack(columns, 1)
        self.sims = np.where(sims >= tau, sims, K.NO_EDGE)
        self.caps = np.bincount(self.part, minlength=len(row.groups)).astype(np.int64)
        self.tau, self.solved = tau, None
        self.kept: dict[str, list[K.Problem]] = {}

    def problems(self, what: str) -> list[K.Problem]:
        """mwmto: many-to-one matching; score: one-to-one in each partition; exact: one-to-one with all vectors."""
        if what not in self.kept:
            if what == "mwmto":
                self.kept[what] = [K.Problem(self.sims, self.caps, self.tau, self.card, True)]
            else:
                found = self.pieces() if what == "score" else [self._edges()]
                self.kept[what] = [K.Problem(m, np.ones(m.shape[1], np.int64), self.tau, self.card, False) for m in found]
        return self.kept[what]

    def mwmto(self) -> tuple[int, int, np.ndarray]:
        if self.solved is None:
            self.solved = K.assign(self.sims, self.caps, self.card)
        return self.solved

    def mwmto_bounds(self) -> tuple[int, int]:
        return self._bounds("mwmto")

    def _bounds(self, what: str) -> tuple[int, int]:
        every = self.problems(what)
        return sum(p.lower() for p in every), sum(p.upper() for p in every)

    def pieces(self) -> list[np.ndarray]:
        """Edge matrices of the query columns sent to each partition with its vectors."""
        to = self.mwmto()[2]
        out = []
        for k in np.unique(to[to >= 0]):
            s = np.rint(self.q[to == k] @ self.v[self.part == k].T * MICRO).astype(np.int64)
            out.append(np.where(s >= self.tau, s, K.NO_EDGE))
        return out

    def score(self) -> int:
        return sum(p.score() for p in self.problems("score"))

    def score_bounds(self) -> tuple[int, int]:
        return self._bounds("score")

    def exact(self) -> int:
        return sum(p.score() for p in self.problems("exact"))

    def exact_bounds(self) -> tuple[int, int]:
        return self._bounds("exact")

    def _edges(self) -> np.ndarray:
        s = np.rint(self.q @ self.v.T * MICRO).astype(np.int64)
        return np.where(s >= self.tau, s, K.NO_EDGE)


class Met(Candidate):
    """A candidate whose similarities were found together with those of other queries that meet the set. sims: to its partitions; near: to its vectors."""

    def __init__(self, set_id: int, sims: np.ndarray, caps: np.ndarray, part: np.ndarray, near: np.ndarray | None, tau: int, card: bool):
        self.set_id, self.sims, self.caps, self.part, self.near, self.tau, self.card = set_id, sims, caps, part, near, tau, card
        self.solved, self.kept = None, {}

    def pieces(self) -> list[np.ndarray]:
        to = self.mwmto()[2]
        return [self.near[np.ix_(to == k, self.part == k)] for k in np.unique(to[to >= 0])]

    def _edges(self) -> np.ndarray:
        return self.near


def meetings(batches: Iterator[pa.RecordBatch], queries: Queries, centroids: np.ndarray, tau: int, card: bool, near: bool, most: int = 1 << 18) -> Iterator[tuple[int, Met]]:
    """(query, candidate) of all pairs of rows (set_id, n, flat, part, groups, own, ids); the queries that meet a set share its products. near: whether vectors are compared too."""
    dim = centroids.shape[1]

    def cut(sims):
        sims = np.rint(sims * MICRO).astype(np.int64)
        sims[sims < tau] = K.NO_EDGE
        return sims

    for batch in batches:
        set_ids, ns = (batch.column(i).to_numpy(zero_copy_only=False) for i in (0, 1))
        flat, part, own, ids = (batch.column(i).flatten().to_numpy(zero_copy_only=False) for i in (2, 3, 5, 6))
        flat, own, groups = flat.reshape(-1, dim), own.reshape(-1, dim), batch.column(4)
        ends, owned, met = np.cumsum(ns), np.cumsum(np.asarray(batch.column(5).value_lengths()) // dim), np.cumsum(np.asarray(batch.column(6).value_lengths()))
        for i, set_id in enumerate(set_ids.tolist()):
            v, of = flat[ends[i] - ns[i] : ends[i]], part[ends[i] - ns[i] : ends[i]]
            g = groups[i].as_py()
            used = sorted({c for x in g for c in x if c >= 0})
            mine = own[owned[i - 1] if i else 0 : owned[i]]
            targets = np.concatenate([centroids[used], mine])
            place = {c: x for x, c in enumerate(used)} | {-1 - x: len(used) + x for x in range(len(mine))}
            columns = [[place[c] for c in x] for x in g]
            caps = np.bincount(of, minlength=len(g)).astype(np.int64)
            asks = np.sort(ids[met[i - 1] if i else 0 : met[i]])
            widths = np.array([len(queries[q]) for q in asks.tolist()], np.int64)
            rows, low = np.cumsum(widths), 0
            while low < len(asks):
                begin = rows[low] - widths[low]
                high = max(low + 1, int(np.searchsorted(rows, begin + most // max(1, len(v)), "right")))
                q = np.concatenate([queries[x] for x in asks[low:high].tolist()])
                to = cut(q @ targets.T)
                sims = to[:, [x[0] for x in columns]] if all(len(x) == 1 for x in columns) else np.stack([to[:, x].max(1) for x in columns], 1)
                vectors = cut(q @ v.T) if near else None
                for x, n, end in zip(asks[low:high].tolist(), widths[low:high].tolist(), (rows[low:high] - begin).tolist(), strict=True):
                    yield x, Met(set_id, sims[end - n : end], caps, of, vectors[end - n : end] if near else None, tau, card)
                low = high


def prepare(rows: list[Candidate], what: str, prune: str) -> None:
    """Finds together what a rule will ask of many candidates: their bounds, and unless few are scored (lossless) their scores."""
    if what == "score" or what == "mwmto" and prune != "lossless":
        shapes: dict[tuple[int, ...], list[Candidate]] = {}
        for c in rows:
            if c.solved is None and c.sims.size <= 1 << 12:
                shapes.setdefault(c.sims.shape, []).append(c)
        for (n, p), some in shapes.items():
            step = max(1, (1 << 18) // max(1, n * p))
            for low in range(0, len(some), step):
                part = some[low : low + step]
                t, u, to = K.assign_many(np.stack([c.sims for c in part]), np.stack([c.caps for c in part]), part[0].card)
                for c, *solved in zip(part, t.tolist(), u.tolist(), to, strict=True):
                    c.solved = tuple(solved)
    every = [p for c in rows for p in c.problems(what)]
    if prune != "none":
        K.prepare(every, "upper")
        K.prepare(every, "lower")
    if prune != "lossless" and what != "mwmto":
        K.prepare(every, "score")


def bounds_scan(index: Index, queries: Queries, tau: float, kind: str) -> DataFrame:
    """(query_id, set_id, lb6, score6, ub6) of every query and other set: mwmto, many-to-one matching, or score, the sum over partitions.

    Sets are scanned where they lie; the queries of one width meet a set together.
    """
    threshold, dim = micro(tau), index.dim
    near = [(ids, q, np.rint(q @ index.centroids.T * MICRO).astype(np.int64)) for ids, q in by_width(queries)]
    shared = index.sets.sparkSession.sparkContext.broadcast(near)

    def of_set(q, to_centroids, row, keep):
        part, own = np.asarray(row.part), np.asarray(row.own, np.float64).reshape(-1, dim)
        q, to_centroids = q[keep], to_centroids[keep]
        to_own = np.rint(q @ own.T * MICRO).astype(np.int64)
        sims = np.stack([np.max([to_centroids[:, :, c] if c >= 0 else to_own[:, :, -1 - c] for c in g], axis=0) for g in row.groups], 2)
        sims[sims < threshold] = K.NO_EDGE
        caps = np.bincount(part, minlength=len(row.groups)).astype(np.int64)
        _, u, to = K.assign_many(sims, caps, True)
        if kind == "mwmto":
            return K.lower_bounds(K.greedy_rows_many(sims, caps), sims, caps, threshold, True), u, K.upper_bounds(sims, np.full(len(q), min(q.shape[1], len(part))))
        v = np.asarray(row.flat, np.float64).reshape(-1, dim)
        lb, u, ub = (np.zeros(len(q), np.int64) for _ in range(3))
        for k in range(len(row.groups)):
            m = np.rint(q @ v[part == k].T * MICRO).astype(np.int64)
            m[(m < threshold) | (to != k)[:, :, None]] = K.NO_EDGE
            ones = np.ones(m.shape[2], np.int64)
            lb += K.lower_bounds(K.greedy_edges_many(m), m, ones, threshold, True)
            u += K.assign_many(m, ones, True)[1]
            ub += K.upper_bounds(m, np.minimum((to == k).sum(1), m.shape[2]))
        return lb, u, ub

    def run(frames):
        import pandas as pd

        for pdf in frames:
            for row in pdf.itertuples():
                for ids, q, to_centroids in shared.value:
                    keep = ids != row.set_id
                    if not keep.any():
                        continue
                    lb, u, ub = of_set(q, to_centroids, row, keep)
                    yield pd.DataFrame({"query_id": ids[keep], "set_id": row.set_id, "lb6": lb, "score6": u, "ub6": ub})

    return index.sets.select("set_id", "flat", "part", "groups", "own").mapInPandas(run, "query_id bigint, set_id bigint, lb6 bigint, score6 bigint, ub6 bigint")


RESULT = "query_id bigint, stage string, rank int, set_id bigint, score6 bigint, candidates bigint, bounds bigint, evaluations bigint"


JUDGED = "query_id bigint, set_id bigint, lb6 bigint, ub6 bigint, score6 bigint"


def _stages(index: Index, queries: Queries, plan: Plan) -> Callable[[DataFrame], DataFrame]:
    """A function of candidates (query_id, set_id) that gives RESULT rows.

    Bounds and scores of a stage are found where the sets lie, and only these numbers meet in one
    task per query, where the rule asks for them in its order and counts what it asks for.
    """
    shared = index.sets.sparkSession.sparkContext.broadcast((queries, index.centroids))
    tau, card, prune = micro(plan.tau), plan.semantics == "max_cardinality", plan.prune
    bounds = {"mwmto": Candidate.mwmto_bounds, "score": Candidate.score_bounds, "exact": Candidate.exact_bounds}
    scores = {"mwmto": lambda c: c.mwmto()[1], "score": Candidate.score, "exact": Candidate.exact}

    def judged(ids: DataFrame, what: str) -> DataFrame:
        def run(batches, size: int = 4096, most: int = 1 << 21):
            def given(some):
                prepare([c for _, c in some], what, "none" if prune == "none" else "base")
                rows = [(q, c.set_id, *(bounds[what](c) if prune != "none" else (0, 0)), scores[what](c)) for q, c in some]
                return pa.RecordBatch.from_arrays([pa.array(x, pa.int64()) for x in zip(*rows, strict=True)], [f.split()[0] for f in JUDGED.split(", ")])

            some, cells = [], 0
            for q, c in meetings(batches, *shared.value, tau, card, what != "mwmto"):
                some.append((q, c))
                cells += c.sims.size + (c.near.size if c.near is not None else 0)
                if len(some) >= size or cells > most:
                    yield given(some)
                    some, cells = [], 0
            if some:
                yield given(some)

        return _meeting(index, ids).select("set_id", "n", "flat", "part", "groups", "own", "ids").mapInArrow(run, JUDGED)

    def cut(found: DataFrame, stage: str, k: int) -> DataFrame:
        def run(pdf):
            import pandas as pd

            pdf, query_id = pdf.sort_values("set_id"), int(pdf["query_id"].iloc[0])
            ids, lbs, ubs, known = (pdf[c].tolist() for c in ("set_id", "lb6", "ub6", "score6"))
            answer, evals = K.prune(prune, list(zip(ids, lbs, ubs, strict=True)), k, dict(zip(ids, known, strict=True)).__getitem__)
            out = [(query_id, stage, rank, i, s, len(ids), len(ids) if prune != "none" else 0, evals) for rank, (i, s) in enumerate(answer, 1)]
            return pd.DataFrame(out, columns=[f.split()[0] for f in RESULT.split(", ")])

        return found.groupBy("query_id").applyInPandas(run, RESULT)

    def run(ids: DataFrame) -> DataFrame:
        kept = None
        if "filter" in plan.stages:
            kept = written(cut(judged(ids, "mwmto"), "filter", plan.phi_r), "filter")
            ids = kept.select("query_id", "set_id")
        last = cut(judged(ids, "score" if "score" in plan.stages else "exact"), "answer", plan.k)
        return last if kept is None else kept.unionByName(last)

    return run


def candidates(index: Index, queries: Queries, plan: Plan) -> DataFrame:
    """(query_id, set_id) that reach the filter."""
    spark = index.sets.sparkSession
    probe = probe_flat(spark, queries, index.centroids, plan.phi_c) if plan.probe == "flat" else probe_graph(spark, queries, index.graph(), plan.phi_c)
    if "refine" not in plan.stages:
        return touched(probe, index.counts)
    return refine(probe, index.counts, plan.phi_ref, plan.on_full, micro(plan.tau) if plan.tau_in_refine else None).select("query_id", "set_id")


def _with_work(answer: DataFrame, work: DataFrame, stage: str) -> DataFrame:
    """RESULT rows; work has a row per query."""
    names = [f.split()[0] for f in RESULT.split(", ")]
    return answer.join(F.broadcast(work), "query_id").withColumn("stage", F.lit(stage)).select(*names)


def _meeting(index: Index, ids: DataFrame) -> DataFrame:
    """The sets that a query is to meet, with the ids of those queries; vectors stay in the set layout. ids: (query_id, set_id), or (set_id, ids) as `met_by` gives."""
    if "ids" not in ids.columns:
        ids = ids.select("query_id", "set_id").where("query_id != set_id").repartition(tasks(index.sets.sparkSession), "set_id").groupBy("set_id").agg(F.collect_set("query_id").alias("ids"))
        return index.sets.repartition(tasks(index.sets.sparkSession), "set_id").join(ids, "set_id")
    return index.sets.join(ids, "set_id")


def filter_scan(index: Index, queries: Queries, ids: DataFrame, plan: Plan) -> DataFrame:
    """RESULT rows of the filter over any number of candidates (query_id, set_id): the phi_r best by many-to-one matching."""
    spark, dim, tau, card = index.sets.sparkSession, index.dim, micro(plan.tau), plan.semantics == "max_cardinality"
    to_centroids = {i: np.rint(q @ index.centroids.T * MICRO).astype(np.int64) for i, q in queries.items()}
    shared = spark.sparkContext.broadcast((queries, to_centroids))

    def pairs(batch):
        import pandas as pd

        rows = pd.DataFrame({c: batch.column(c).to_pylist() for c in ("set_id", "flat", "part", "groups", "own", "ids")})
        for r in rows.itertuples():
            for q in sorted(r.ids):
                c = Candidate(shared.value[0][q], shared.value[1][q], r, dim, tau, card)
                yield q, c.set_id, K.Problem(c.sims, c.caps, tau, card, True)

    rows = _meeting(index, ids).select("set_id", "flat", "part", "groups", "own", "ids")
    return _with_work(*best_of(rows, pairs, plan.phi_r, plan.prune, tau, card, True), "filter")


def staged(index: Index, queries: Queries, plan: Plan) -> DataFrame:
    """RESULT rows of each query: what the filter kept and the final answer, with work counts.

    A set meets all its queries in one row, so its vectors move once a stage and never to a query.
    """
    ids = candidates(index, queries, plan)
    if "refine" not in plan.stages:
        if "filter" not in plan.stages:
            return score_candidates(index, queries, ids, plan)
        kept = filter_scan(index, queries, ids, plan)
        rest = replace(plan, stages=("refine", *[s for s in plan.stages if s == "score"]))
        return kept.unionByName(_stages(index, queries, rest)(kept.select("query_id", "set_id")))
    return _stages(index, queries, plan)(ids)


def union_search(index: Index, queries: Queries, plan: Plan) -> DataFrame:
    """(query_id, rank, set_id, score6)."""
    return staged(index, queries, plan).where("stage = 'answer'").select("query_id", "rank", "set_id", "score6")


def union_search_plus(index: Index, queries: Queries, plan: Plan, variant: str = "lossless") -> DataFrame:
    return union_search(index, queries, replace(plan, prune=variant))


def column_candidates(shards: DataFrame, queries: Queries, k_prime: int) -> DataFrame:
    """(query_id, q, set_id, pos, sim6): the k' nearest columns of each query column, merged over the shards' graphs."""
    spark = shards.sparkSession
    shared = spark.sparkContext.broadcast(rows_of(queries))

    def run(frames, most: int = 1 << 10):
        import pickle

        import pandas as pd

        ids, qs, vq = shared.value
        for pdf in frames:
            for blob, set_ids, poss in zip(pdf["graph"], pdf["set_ids"], pdf["poss"], strict=True):
                g = pickle.loads(blob)
                for low in range(0, len(ids), most):
                    rows = [(i, q, set_ids[x], poss[x], round(s * MICRO)) for i, q, found in zip(ids[low : low + most].tolist(), qs[low : low + most].tolist(), g.top_many(vq[low : low + most], k_prime), strict=True) for x, s in found]
                    yield pd.DataFrame(rows, columns=["query_id", "q", "set_id", "pos", "sim6"])

    every = shards.mapInPandas(run, "query_id bigint, q int, set_id bigint, pos int, sim6 bigint")
    order = Window.partitionBy("query_id", "q").orderBy(F.col("sim6").desc(), "set_id", "pos")
    return every.withColumn("rn", F.row_number().over(order)).where(F.col("rn") <= k_prime).drop("rn")


def flat_column_candidates(cols: DataFrame, queries: Queries, k_prime: int) -> DataFrame:
    """The exact twin: all columns, k' kept per task before the shuffle. Ties by (set_id, pos)."""
    shared = cols.sparkSession.sparkContext.broadcast(rows_of(queries))

    def run(batches, most: int = 1 << 21):
        ids, qs, vq = shared.value
        best = None  # (similarity, set, place) of the k' best of each query column, rows x columns

        for batch in batches:
            found = by_length(*batch.columns).get(vq.shape[1]) if len(vq) else None
            step = max(k_prime, most // max(1, len(vq)))
            for low in range(0, len(found[0]) if found else 0, step):
                set_ids, pos, v = (x[low : low + step] for x in found)
                order = np.lexsort((pos, set_ids))
                set_ids, pos = set_ids[order], pos[order]
                sims = np.rint(v[order] @ vq.T * MICRO).astype(np.int64)
                # of equals the first: no two keys of a column are equal
                keys = np.arange(len(sims))[:, None] - sims * len(sims)
                at = np.argpartition(keys, k_prime - 1, axis=0)[:k_prime] if len(sims) > k_prime else np.broadcast_to(np.arange(len(sims))[:, None], sims.shape)
                new = (np.take_along_axis(sims, at, 0), set_ids[at], pos[at])
                if best is not None:
                    new = tuple(np.concatenate(x) for x in zip(best, new, strict=True))
                order = np.lexsort((new[2], new[1], -new[0]), axis=0)[:k_prime]
                best = tuple(np.take_along_axis(x, order, 0) for x in new)
        if best is not None:
            n = len(best[0])
            columns = (np.tile(ids, n), np.tile(qs, n), best[1].ravel(), best[2].ravel(), best[0].ravel())
            types = (pa.int64(), pa.int32(), pa.int64(), pa.int32(), pa.int64())
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, types, strict=True)], ["query_id", "q", "set_id", "pos", "sim6"])

    usable = F.col("v").isNotNull() & ~F.exists("v", lambda x: x.isNull() | F.isnan(x))
    pairs = cols.where(usable).select("set_id", "pos", "v").mapInArrow(run, "query_id bigint, q int, set_id bigint, pos int, sim6 bigint")
    order = Window.partitionBy("query_id", "q").orderBy(F.col("sim6").desc(), "set_id", "pos")
    return pairs.withColumn("rn", F.row_number().over(order)).where(F.col("rn") <= k_prime).drop("rn")


def score_candidates(index: Index, queries: Queries, ids: DataFrame, plan: Plan) -> DataFrame:
    """RESULT rows: exact unionability of any number of candidates, rows as `_meeting` takes them, pruned as the plan says, in the set layout: what both baselines share."""
    card = plan.semantics == "max_cardinality"
    rows = _meeting(index, ids).select("set_id", "n", "flat", "ids")
    return _with_work(*best_exact(rows, queries, plan.k, plan.prune, micro(plan.tau), card), "answer")


def quantized(index: Index, queries: Queries, plan: Plan) -> DataFrame:
    probe = probe_flat(index.sets.sparkSession, queries, index.centroids, plan.phi_c)
    return score_candidates(index, queries, met_by(probe, index.counts), plan)


def quantized_answer(sets: DataFrame, counts: DataFrame, centroids: np.ndarray, queries: Queries, plan: Plan) -> DataFrame:
    """(query_id, rank, set_id, score6) of `quantized` without its work counts: sets (set_id, n, flat) on a probed list, solved only if they may be among the k best."""
    met = met_by(probe_flat(sets.sparkSession, queries, centroids, plan.phi_c), counts)
    return top_k_exact(sets.join(met, "set_id"), queries, plan.tau, plan.k, plan.semantics)
