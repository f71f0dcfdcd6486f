"""Edges, matchings and unionability of queries against sets.

Queries are few and bounded, so their vectors travel as a broadcast; sets never move: each task
scans its sets in the set layout and gives small rows. SQL forms of the edge table serve where
rows per edge are wanted.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from functools import reduce
from itertools import islice

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from unionlake.functions.vectors import MICRO, micro, sim6
from unionlake.operators import bounded, sparse
from unionlake.operators import kernels as K
from unionlake.sources.shared import written

#: Most query vector components that may be broadcast; more queries go in blocks (`query_blocks`).
MOST_QUERY_VALUES = 64 << 20

Queries = dict[int, np.ndarray]


def collect_queries(cols: DataFrame, limit_values: int = MOST_QUERY_VALUES) -> Queries:
    """The vectors of each query set, ordered by pos, as n x d arrays. Raises beyond the bound."""
    size = cols.agg(F.sum(F.size("v"))).first()[0] or 0
    if size > limit_values:
        raise ValueError(f"{size} query values exceed the bound of {limit_values}; use query_blocks")
    got = cols.select("set_id", "pos", F.col("v").cast("array<double>").alias("v")).orderBy("set_id", "pos").toArrow()
    ids, v = got.column("set_id").to_numpy(), got.column("v").combine_chunks()
    ends = np.flatnonzero(np.diff(ids, append=ids[-1:] - 1)) + 1
    begins = np.concatenate([[0], ends])[: len(ends)].astype(np.int64)
    lengths = np.asarray(pc.list_value_length(v).to_numpy(zero_copy_only=False))
    if len(ids) and not v.null_count and (lengths == lengths[0]).all():
        flat = v.flatten().to_numpy(zero_copy_only=False).reshape(len(ids), -1)
        return {int(ids[a]): flat[a:b] for a, b in zip(begins.tolist(), ends.tolist(), strict=True)}
    return {int(ids[a]): np.array(v[a:b].to_pylist(), np.float64) for a, b in zip(begins.tolist(), ends.tolist(), strict=True)}


def query_blocks(cols: DataFrame, limit_values: int = MOST_QUERY_VALUES) -> Iterator[Queries]:
    """Blocks of queries that each stay within the bound; one scan of the sets serves a block."""
    size = cols.agg(F.sum(F.size("v"))).first()[0] or 0
    blocks = max(1, -(-2 * size // limit_values)) if size > limit_values else 1
    for b in range(blocks):
        yield collect_queries(cols.where(F.pmod(F.xxhash64("set_id"), F.lit(blocks)) == b), limit_values)


def similarities(q: np.ndarray, v: np.ndarray, tau: int) -> np.ndarray:
    """Micro-unit similarities, NO_EDGE below the threshold."""
    s = np.rint(q @ v.T * MICRO).astype(np.int64)
    return np.where(s >= tau, s, K.NO_EDGE)


def edges(query_cols: DataFrame, cols: DataFrame, tau: float, include_self: bool = False) -> DataFrame:
    """(query_id, set_id, q, j, sim6), one row per pair of columns at or above the threshold; vectors of unlike length or with nulls have none.

    Query columns go out in blocks of bounded size, and a matrix product finds the similarities of many columns at once.
    """
    usable = F.col("v").isNotNull() & ~F.exists("v", lambda x: x.isNull() | F.isnan(x))
    size = query_cols.agg(F.sum(F.size("v"))).first()[0] or 0
    blocks = max(1, -(-2 * size // MOST_QUERY_VALUES)) if size > MOST_QUERY_VALUES else 1
    every, threshold = query_cols.where(usable).select("set_id", "pos", F.col("v").cast("array<double>").alias("v")), micro(tau)
    names, types = ["query_id", "set_id", "q", "j", "sim6"], [pa.int64(), pa.int64(), pa.int32(), pa.int32(), pa.int64()]

    def block(b: int) -> DataFrame:
        got = every.where(F.pmod(F.xxhash64("set_id"), F.lit(blocks)) == b).toArrow()
        shared = cols.sparkSession.sparkContext.broadcast(by_length(got.column("set_id"), got.column("pos"), got.column("v")))

        def run(batches, most: int = 1 << 20):
            for batch in batches:
                for length, (set_ids, js, v) in by_length(*batch.columns).items():
                    ids, qs, vq = shared.value.get(length, (None, None, np.zeros((0, length))))
                    step = max(1, most // max(1, len(vq)))
                    for low in range(0, len(v) if len(vq) else 0, step):
                        sims = np.rint(v[low : low + step] @ vq.T * MICRO).astype(np.int64)
                        on = sims >= threshold
                        if not include_self:
                            on &= set_ids[low : low + step, None] != ids[None, :]
                        i, k = np.nonzero(on)
                        if len(i):
                            yield pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip((ids[k], set_ids[low + i], qs[k], js[low + i], sims[i, k]), types, strict=True)], names)

        return cols.where(usable).select("set_id", "pos", F.col("v").cast("array<double>").alias("v")).mapInArrow(run, "query_id bigint, set_id bigint, q int, j int, sim6 bigint")

    return reduce(DataFrame.unionByName, [block(b) for b in range(blocks)])


def by_length(set_ids, pos, v) -> dict[int, tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """length of vectors -> (set ids, places, vectors one a row), of Arrow columns without nulls."""
    set_ids, pos = (np.asarray(x.to_numpy() if isinstance(x, pa.ChunkedArray) else x.to_numpy(zero_copy_only=False)) for x in (set_ids, pos))
    v = v.combine_chunks() if isinstance(v, pa.ChunkedArray) else v
    lengths = np.asarray(pc.list_value_length(v).to_numpy(zero_copy_only=False))
    flat, ends = v.flatten().to_numpy(zero_copy_only=False), np.cumsum(lengths)
    out = {}
    for n in np.unique(lengths):
        at = np.flatnonzero(lengths == n)
        out[int(n)] = (set_ids[at], pos[at], flat[(ends[at] - n)[:, None] + np.arange(n)])
    return out


def is_matching(match: DataFrame, all_edges: DataFrame, capacity: int = 1) -> DataFrame:
    """(query_id, set_id, t, valid): every pair is an edge, no query column twice, no target more often than its capacity."""
    e = all_edges.dropDuplicates(["query_id", "set_id", "q", "j"]).select("query_id", "set_id", "q", "j", F.lit(1).alias("known"))
    m = match.join(e, ["query_id", "set_id", "q", "j"], "left")
    per = m.withColumn("nq", F.count("*").over(Window.partitionBy("query_id", "set_id", "q"))).withColumn("nj", F.count("*").over(Window.partitionBy("query_id", "set_id", "j")))
    ok = (F.max("nq") <= 1) & (F.max("nj") <= capacity) & F.bool_and(F.col("known").isNotNull())
    return per.groupBy("query_id", "set_id").agg(F.count("*").alias("t"), ok.alias("valid"))


def scan(sets: DataFrame, queries: Queries, tau: float, kernel: Callable[[int, int, np.ndarray], list[tuple]], schema: str, include_self: bool = False, raw: bool = False) -> DataFrame:
    """Applies kernel(query_id, set_id, similarities) to every pair; its tuples follow (query_id, set_id).

    With `raw` the threshold is not applied. One matrix product serves a batch of sets and all queries.
    """
    spark = sets.sparkSession
    names = ["query_id", "set_id", *[f.strip().split()[0] for f in schema.split(",")]]
    full = f"query_id bigint, set_id bigint, {schema}"
    kinds = {"bigint": pa.int64(), "int": pa.int32(), "double": pa.float64(), "boolean": pa.bool_()}
    types = [pa.int64(), pa.int64(), *[kinds[f.strip().split()[1]] for f in schema.split(",")]]
    ids = sorted(queries)
    dim = queries[ids[0]].shape[1] if ids else 1
    stacked = np.concatenate([queries[i] for i in ids]) if ids else np.zeros((0, dim))
    cuts = np.cumsum([0, *[len(queries[i]) for i in ids]])
    shared = spark.sparkContext.broadcast((ids, stacked, cuts))
    threshold = micro(tau)

    def run(batches):
        ids, stacked, cuts = shared.value
        for batch in batches:
            set_ids = batch.column(0).to_pylist()
            flat = batch.column(2).flatten().to_numpy(zero_copy_only=False).reshape(-1, dim)
            ends = np.cumsum(batch.column(1).to_numpy(zero_copy_only=False))
            out, size = [], 0
            for i, s in enumerate(set_ids):
                v = flat[ends[i - 1] if i else 0 : ends[i]]
                sims = np.rint(stacked @ v.T * MICRO).astype(np.int64)
                if not raw:
                    sims = np.where(sims >= threshold, sims, K.NO_EDGE)
                for k, q in enumerate(ids):
                    if q != s or include_self:
                        for row in kernel(q, s, sims[cuts[k] : cuts[k + 1]]):
                            out.append((q, s, *row))
                            size += 1
                if size > 50_000:
                    yield pa.RecordBatch.from_arrays([pa.array([o[c] for o in out], t) for c, t in enumerate(types)], names)
                    out, size = [], 0
            if out:
                yield pa.RecordBatch.from_arrays([pa.array([o[c] for o in out], t) for c, t in enumerate(types)], names)

    return sets.select("set_id", "n", "flat").mapInArrow(run, full)


def _ones(m: int) -> np.ndarray:
    return np.ones(m, np.int64)


def rows_of(queries: Queries) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(query ids, columns, vectors): a row per query column."""
    ids = sorted(queries)
    if not ids:
        return np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros((0, 0))
    ns = [len(queries[i]) for i in ids]
    return np.repeat(np.array(ids, np.int64), ns), np.concatenate([np.arange(n) for n in ns]), np.concatenate([queries[i] for i in ids])


def by_width(queries: Queries) -> list[tuple[np.ndarray, np.ndarray]]:
    """(ids, vectors query x column x place) of the queries with one number of columns."""
    widths: dict[int, list[int]] = {}
    for i in sorted(queries):
        widths.setdefault(len(queries[i]), []).append(i)
    return [(np.array(ids, np.int64), np.stack([queries[i] for i in ids])) for ids in widths.values()]


def pair_blocks(batch: pa.RecordBatch, groups: list[tuple[np.ndarray, np.ndarray]], threshold: int, include_self: bool, most: int = 1 << 18) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """(query ids, set ids, similarities pair x column x vector) of all pairs of queries and sets (set_id, n, flat) of a batch, pairs of one shape together."""
    set_ids, ns = (batch.column(i).to_numpy(zero_copy_only=False) for i in (0, 1))
    starts, values = np.cumsum(ns) - ns, batch.column(2).flatten().to_numpy(zero_copy_only=False)
    for ids, vectors in groups:
        g, nq, dim = vectors.shape
        flat = values.reshape(-1, dim)
        for p in np.unique(ns):
            of = np.flatnonzero(ns == p)
            few = max(1, most // max(1, nq * p))  # pairs at once
            for left in range(0, g, few):
                own, q = ids[left : left + few], vectors[left : left + few].reshape(-1, dim)
                step = max(1, few // len(own))
                for low in range(0, len(of), step):
                    at = of[low : low + step]
                    v = flat[(starts[at][:, None] + np.arange(p)).ravel()]
                    sims = np.rint(q @ v.T * MICRO).astype(np.int64).reshape(len(own), nq, len(at), p).transpose(2, 0, 1, 3).reshape(-1, nq, p)
                    sims[sims < threshold] = K.NO_EDGE
                    to_q, to_s = np.tile(own, len(at)), np.repeat(set_ids[at], len(own))
                    keep = slice(None) if include_self else to_q != to_s
                    yield to_q[keep], to_s[keep], sims[keep]


def scan_blocks(sets: DataFrame, queries: Queries, tau: float, kernel: Callable[[np.ndarray], tuple[np.ndarray, list[np.ndarray]]], schema: str, include_self: bool = False) -> DataFrame:
    """kernel(similarities of many pairs of one shape) gives (which pair, columns) of its rows; these follow (query_id, set_id)."""
    shared, threshold = sets.sparkSession.sparkContext.broadcast(by_width(queries)), micro(tau)
    fields = [f.strip().split() for f in f"query_id bigint, set_id bigint, {schema}".split(",")]
    kinds = {"bigint": pa.int64(), "int": pa.int32(), "boolean": pa.bool_()}

    def run(batches):
        for batch in batches:
            for qs, ss, sims in pair_blocks(batch, shared.value, threshold, include_self):
                if len(qs):
                    at, columns = kernel(sims)
                    yield pa.RecordBatch.from_arrays([pa.array(c, kinds[k]) for c, (_, k) in zip((qs[at], ss[at], *columns), fields, strict=True)], [n for n, _ in fields])

    return sets.select("set_id", "n", "flat").mapInArrow(run, f"query_id bigint, set_id bigint, {schema}")


def unionability(sets: DataFrame, queries: Queries, tau: float, semantics: str = "max_cardinality", include_self: bool = False) -> DataFrame:
    """(query_id, set_id, t, u6) for every pair; no edge gives 0, 0."""
    card = _card(semantics)

    def solve(sims):
        t, u, _ = K.match_many(sims, card)
        return np.arange(len(t)), [t, u]

    return scan_blocks(sets, queries, tau, solve, "t int, u6 bigint", include_self)


def _card(semantics: str) -> bool:
    if semantics not in ("max_cardinality", "max_weight"):
        raise ValueError(f"unknown semantics {semantics!r}")
    return semantics == "max_cardinality"


def best_matching(sets: DataFrame, queries: Queries, tau: float, semantics: str = "max_cardinality", include_self: bool = False) -> DataFrame:
    """(query_id, set_id, q, j, sim6): one optimal matching per pair."""
    card = _card(semantics)

    def solve(sims):
        at, i, j = pairs_of(sims, card)
        return at, [i, j, sims[at, i, j]]

    return scan_blocks(sets, queries, tau, solve, "q int, j int, sim6 bigint", include_self)


def pairs_of(sims: np.ndarray, card: bool) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(problem, query column, target) of an optimal matching of each problem."""
    to = K.match_many(sims, card)[2]
    at, i = np.nonzero(to >= 0)
    return at, i, to[at, i]


def checked_matchings(sets: DataFrame, queries: Queries, tau: float, semantics: str = "max_cardinality", include_self: bool = False) -> DataFrame:
    """(query_id, set_id, t, u6, valid) of the matchings that best_matching gives, of pairs with an edge, checked where they are found: `is_matching` without a row per edge."""
    card, threshold = _card(semantics), micro(tau)

    def solve(sims):
        at, i, j = pairs_of(sims, card)
        b, n, p = sims.shape
        sim = sims[at, i, j]
        bad = np.bincount(at, sim < threshold, b) > 0
        for place, width in ((i, n), (j, p)):  # a column twice
            bad |= (np.bincount(at * width + place, minlength=b * width).reshape(b, width) > 1).any(1)
        t = np.bincount(at, minlength=b)
        on = np.flatnonzero(t)
        return on, [t[on], np.bincount(at, sim, b).astype(np.int64)[on], ~bad[on]]

    return scan_blocks(sets, queries, tau, solve, "t bigint, u6 bigint, valid boolean", include_self)


def bounds_union(sets: DataFrame, queries: Queries, tau: float, semantics: str = "max_cardinality") -> DataFrame:
    """(query_id, set_id, lb6, ub6) of unionability."""
    card = _card(semantics)

    def bound(sims):
        lb = K.lower_bounds(K.greedy_edges_many(sims), sims, _ones(sims.shape[2]), micro(tau), card)
        return np.arange(len(lb)), [lb, K.upper_bounds(sims, np.full(len(sims), min(sims.shape[1:])))]

    return scan_blocks(sets, queries, tau, bound, "lb6 bigint, ub6 bigint")


def ranked(scores: DataFrame, k: int, score: str = "u6") -> DataFrame:
    """(query_id, rank, set_id, score6): the k best of each query, ties by set id. The window keeps k rows a task before it shuffles."""
    order = Window.partitionBy("query_id").orderBy(F.col(score).desc(), "set_id")
    top = scores.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k)
    return top.select("query_id", "rank", "set_id", F.col(score).alias("score6"))


def top_k_exact(sets: DataFrame, queries: Queries, tau: float, k: int, semantics: str = "max_cardinality", include_self: bool = False) -> DataFrame:
    """(query_id, rank, set_id, score6) over all sets (set_id, n, flat), or with a column `ids` over those that list a query; a task keeps the k best of each query and solves only pairs that may be among them."""
    card, threshold, shared = _card(semantics), micro(tau), sets.sparkSession.sparkContext.broadcast(queries)
    best = sets.select("set_id", "n", "flat", *[c for c in sets.columns if c == "ids"]).mapInArrow(lambda batches: bounded.top_k(batches, shared.value, k, threshold, card, include_self), "query_id bigint, set_id bigint, u6 bigint")
    return ranked(best, k)


KEPT = "query_id bigint, set_id bigint, score6 bigint, candidates bigint, bounds bigint, evaluations bigint"
PROBLEMS = "query_id bigint, set_id bigint, lb6 bigint, ub6 bigint, columns int, sims array<bigint>, caps array<bigint>, candidates bigint"
#: (query_id, set_id, problem) of the pairs in a batch of rows.
Pairs = Callable[[pa.RecordBatch], Iterator[tuple[int, int, K.Problem]]]


def _batches(rows: list[tuple], schema: str, size: int = 20_000) -> Iterator[pa.RecordBatch]:
    fields = [f.strip().split() for f in schema.split(",")]
    kinds = {"bigint": pa.int64(), "int": pa.int32(), "array<int>": pa.list_(pa.int32()), "array<bigint>": pa.list_(pa.int64())}
    for at in range(0, len(rows), size):
        part = rows[at : at + size]
        yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in part], kinds[k]) for i, (_, k) in enumerate(fields)], [n for n, _ in fields])


def _in_turn(batches: Iterator[pa.RecordBatch], pairs: Pairs, size: int = 4096) -> Iterator[list[tuple[int, int, K.Problem]]]:
    """The pairs of all batches in order, so many at a time; what is the same for many of one shape is then found together."""
    every = (x for batch in batches for x in pairs(batch))
    while some := list(islice(every, size)):
        yield some


def best_of(rows: DataFrame, pairs: Pairs, k: int, prune: str, tau: int, card: bool, by_rows: bool = False) -> tuple[DataFrame, DataFrame]:
    """(answer, work) of a scan: (query_id, rank, set_id, score6) and (query_id, candidates, bounds, evaluations).

    none, base, listing: a task keeps the k best of each query by its rule and gives only those.
    lossless: a task gives the problems whose upper bound reaches the k-th best lower bound it saw;
    of these the ones that reach the k-th best of all tasks are scored, best bounds first. Either
    way the scan runs once and small rows go on; what it found is written, and both results read it.
    """
    if prune not in ("none", "base", "listing", "lossless"):
        raise ValueError(f"unknown pruning {prune!r}")
    if prune != "lossless":

        def keep(batches):
            keepers: dict[int, K.Keeper] = {}
            for some in _in_turn(batches, pairs):
                if prune != "none":
                    K.prepare([p for _, _, p in some], "upper")
                for q, _, _ in some:
                    keepers.setdefault(q, K.Keeper(prune, k))
                K.prepare([p for q, _, p in some if keepers[q].may_need(p)], "lower" if prune == "listing" else "score")
                for q, s, p in some:
                    keepers[q].see(s, p)
            out: list[tuple] = []
            for q, keeper in keepers.items():
                out += [(q, s, u, 0, 0, 0) for s, u in keeper.finish()]
                out.append((q, None, None, keeper.seen, keeper.bounded, keeper.evals))
            yield from _batches(out, KEPT)

        kept = written(rows.mapInArrow(keep, KEPT), "kept")
        return _answer_and_work(kept, k)

    def survive(batches, most: int = 2_000):
        every: dict[int, K.Survivors] = {}

        def rows_of(q: int, held: list) -> list[tuple]:
            return [(q, s, lb, ub, p.sims.shape[1], p.sims.ravel().tolist(), p.caps.tolist(), 0) for s, lb, ub, p in held]

        for some in _in_turn(batches, pairs):
            K.prepare([p for _, _, p in some], "upper")
            for q, _, _ in some:
                every.setdefault(q, K.Survivors(k))
            K.prepare([p for q, _, p in some if every[q].may_need(p)], "lower")
            for q, s, p in some:
                own = every[q]
                own.see(s, p)
                if len(own.held) >= most:
                    yield from _batches(rows_of(q, own.take()), PROBLEMS)
        for q, own in every.items():
            yield from _batches([*rows_of(q, own.take()), (q, None, None, None, None, None, None, own.seen)], PROBLEMS)

    found = written(rows.mapInArrow(survive, PROBLEMS), "survivors")

    def solve(batches):
        tops: dict[int, tuple[K.TopK, list[int]]] = {}
        for batch in batches:
            for q, s, ub, p, sims, caps in zip(*(batch.column(c).to_pylist() for c in ("query_id", "set_id", "ub6", "columns", "sims", "caps")), strict=True):
                top, evals = tops.setdefault(q, (K.TopK(k), [0]))
                if not top.full() or ub >= top.least():
                    evals[0] += 1
                    top.offer(s, K.Problem(np.array(sims, np.int64).reshape(-1, p), np.array(caps, np.int64), tau, card, by_rows).score())
        yield from _batches(_kept_rows(tops), KEPT)

    return _answer_and_work(_solved(found, k, solve), k)


def _kept_rows(tops: dict[int, tuple[K.TopK, list[int]]]) -> list[tuple]:
    out: list[tuple] = []
    for q, (top, evals) in tops.items():
        out += [(q, s, u, 0, 0, 0) for s, u in top.answer()]
        out.append((q, None, None, 0, 0, evals[0]))
    return out


def _solved(found: DataFrame, k: int, solve: Callable) -> DataFrame:
    """KEPT rows of the problems that survive all tasks, which `solve` sees by query and best bound first."""
    real = found.where("set_id is not null")
    order = Window.partitionBy("query_id").orderBy(F.col("lb6").desc())
    least = real.select("query_id", "lb6").withColumn("rn", F.row_number().over(order)).where(F.col("rn") <= k)
    least = least.groupBy("query_id").agg(F.when(F.count("*") >= k, F.min("lb6")).otherwise(0).alias("theta"))  # a row per query
    left = real.join(F.broadcast(least), "query_id").where("ub6 >= theta").drop("theta", "candidates")
    # the problems of a query go to one task, best bound first, a row at a time; many problems to several
    n, queries = left.select(F.count("*"), F.count_distinct("query_id")).first()
    salt = F.pmod(F.xxhash64("set_id"), F.lit(max(1, n // (50_000 * max(1, queries)))))
    left = left.repartition("query_id", salt).sortWithinPartitions(F.col("query_id"), F.col("ub6").desc(), "set_id")
    seen = found.where("set_id is null").select("query_id", F.lit(None).cast("bigint").alias("set_id"), F.lit(None).cast("bigint").alias("score6"), "candidates", F.col("candidates").alias("bounds"), F.lit(0).cast("bigint").alias("evaluations"))
    return written(left.mapInArrow(solve, KEPT), "kept").unionByName(seen)


def _answer_and_work(kept: DataFrame, k: int) -> tuple[DataFrame, DataFrame]:
    work = kept.where("set_id is null").groupBy("query_id").agg(*[F.sum(c).alias(c) for c in ("candidates", "bounds", "evaluations")])
    return ranked(kept.where("set_id is not null"), k, "score6"), work


EDGES = "query_id bigint, set_id bigint, lb6 bigint, ub6 bigint, most int, qs array<int>, js array<int>, sims array<bigint>, candidates bigint"


def best_exact(rows: DataFrame, queries: Queries, k: int, prune: str, tau: int, card: bool) -> tuple[DataFrame, DataFrame]:
    """`best_of` for one-to-one matching, with rows (set_id, n, flat), or (set_id, n, flat, ids) if only the queries `ids` meet a set.

    A task finds the edges of many pairs by one matrix product and bounds and solves pairs from these.
    lossless: of the pairs without an edge a task gives the k of the smallest ids, since all score 0.
    """
    if prune not in ("none", "base", "listing", "lossless"):
        raise ValueError(f"unknown pruning {prune!r}")
    ids = np.array(sorted(queries), np.int64)
    stacked = np.concatenate([queries[i] for i in ids.tolist()]) if len(ids) else np.zeros((0, 1))
    cuts = np.cumsum([0, *[len(queries[i]) for i in ids.tolist()]])
    shared = rows.sparkSession.sparkContext.broadcast((ids, stacked, cuts))

    def keep(batches):
        ids = shared.value[0]
        keepers = [K.Keeper(prune, k) for _ in ids]
        for block in sparse.blocks(batches if len(ids) else (), *shared.value, tau):
            sparse.see(keepers, block, tau, card)
        out: list[tuple] = []
        for q, keeper in zip(ids.tolist(), keepers, strict=True):
            if keeper.seen:
                out += [(q, s, u, 0, 0, 0) for s, u in keeper.finish()]
                out.append((q, None, None, keeper.seen, keeper.bounded, keeper.evals))
        yield from _batches(out, KEPT)

    if prune != "lossless":
        return _answer_and_work(written(rows.mapInArrow(keep, KEPT), "kept"), k)
    names = [f.split()[0] for f in EDGES.split(", ")]

    def lists(sizes: np.ndarray, values: np.ndarray, kind: pa.DataType) -> pa.Array:
        return pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(sizes)]), pa.int32()), pa.array(values, kind))

    def survive(batches, most: int = 1 << 20):
        ids = shared.value[0]
        held = sparse.Held(len(ids), k, tau, card)

        def given():
            for q, s, lb, ub, e in held.take():
                n = np.bincount(e.pair, minlength=e.size)
                columns = [pa.array(x, pa.int64()) for x in (ids[q], s, lb, ub)]
                yield pa.RecordBatch.from_arrays([*columns, pa.array(e.most, pa.int32()), lists(n, e.q, pa.int32()), lists(n, e.j, pa.int32()), lists(n, e.sim, pa.int64()), pa.array(np.zeros(len(q)), pa.int64())], names)

        for block in sparse.blocks(batches if len(ids) else (), *shared.value, tau):
            held.see(block)
            if held.size > most:
                yield from given()
        yield from given()
        q, s = held.without_edges()
        yield from _batches([(a, b, 0, 0, 0, [], [], [], 0) for a, b in zip(ids[q].tolist(), s.tolist(), strict=True)], EDGES)
        yield from _batches([(q, *[None] * 7, n) for q, n in zip(ids.tolist(), held.seen.tolist(), strict=True) if n], EDGES)

    found = written(rows.mapInArrow(survive, EDGES), "survivors")

    def solve(batches):
        tops: dict[int, tuple[K.TopK, list[int]]] = {}
        for batch in batches:
            columns = [batch.column(c) for c in ("most", "qs", "js", "sims")]
            n = np.asarray(columns[1].value_lengths())
            most, qs, js, sims = columns[0].to_numpy(zero_copy_only=False), *[c.flatten().to_numpy(zero_copy_only=False).astype(np.int64) for c in columns[1:]]
            e = sparse.Edges(np.repeat(np.arange(len(n)), n), qs, js, sims, len(n), most)
            known = sparse.Scores(e, np.arange(len(n)), card)
            for i, (q, s, ub) in enumerate(zip(*(batch.column(c).to_pylist() for c in ("query_id", "set_id", "ub6")), strict=True)):
                top, evals = tops.setdefault(q, (K.TopK(k), [0]))
                if not top.full() or ub >= top.least():
                    evals[0] += 1
                    top.offer(s, known.of(i))
        yield from _batches(_kept_rows(tops), KEPT)

    return _answer_and_work(_solved(found, k, solve), k)


def top_k_scan(sets: DataFrame, queries: Queries, tau: float, k: int, prune: str, semantics: str = "max_cardinality") -> tuple[DataFrame, DataFrame]:
    """(answer, work) of a scan of all sets with pruning none, base, listing or lossless; the scan has run when this returns."""
    return best_exact(sets.select("set_id", "n", "flat"), queries, k, prune, micro(tau), _card(semantics))


def set_distance(sets: DataFrame, queries: Queries, kind: str) -> DataFrame:
    """(query_id, set_id, d6): Chamfer similarity (sum over query columns of the best similarity) or Hausdorff (the least of the best, both ways)."""

    def rows(q, s, m):
        if kind == "chamfer":
            return [(int(m.max(1).sum()),)]
        return [(int(min(m.max(1).min(), m.max(0).min())),)]

    return scan(sets, queries, 0.0, rows, "d6 bigint", raw=True)


def mean_pool(cols: DataFrame, dim: int) -> DataFrame:
    """(set_id, v): the mean vector of each set, coordinates in whole 1e-6 steps."""
    at = cols.select("set_id", F.posexplode("v").alias("i", "x")).groupBy("set_id", "i").agg(F.round(F.avg("x"), 6).alias("x"))
    return at.groupBy("set_id").agg(F.transform(F.array_sort(F.collect_list(F.struct("i", "x"))), lambda s: s["x"]).alias("v"))


def mean_pool_top_k(cols: DataFrame, queries: str, dim: int, k: int) -> DataFrame:
    """queries: the predicate of the sets that are queries."""
    pooled = mean_pool(cols, dim)
    q = pooled.where(queries).select(F.col("set_id").alias("query_id"), F.col("v").alias("vq"))
    pairs = pooled.join(F.broadcast(q), F.col("set_id") != F.col("query_id")).select("query_id", "set_id", sim6(F.col("vq"), F.col("v")).alias("u6"))
    return ranked(pairs, k)
