"""The experiment workloads on the given tables, measures over their results, and streams."""

from __future__ import annotations

import time
from collections.abc import Callable
from dataclasses import replace
from functools import reduce

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from unionlake.functions.vectors import micro
from unionlake.operators import index as ix
from unionlake.operators import matching as mt
from unionlake.operators import search as se
from unionlake.plans import search_queries as sq
from unionlake.plans.relational_queries import recall
from unionlake.sources import lakes
from unionlake.sources.shared import folder, size_of, written
from unionlake.streaming import jobs

REGISTRY: dict = {}
SQL: dict[str, str] = {}


def query(key: str, sql: str | None = None):
    def add(f):
        REGISTRY[key] = f
        if sql:
            SQL[key] = sql
        return f

    return add


# ---- lakes ------------------------------------------------------------------------------------

SIZES = """sz AS (SELECT 'vector' AS lake, set_id, count(*) AS n FROM vc GROUP BY ALL
 UNION ALL SELECT 'wide', vec_id // 30, count(*) FROM embeddings GROUP BY ALL UNION ALL SELECT 'label', label, count(*) FROM embeddings GROUP BY ALL
 UNION ALL SELECT 'conversation', conv_id, count(*) FROM conversations GROUP BY ALL UNION ALL SELECT 'event', user_id, count(DISTINCT event_type) FROM events GROUP BY ALL
 UNION ALL SELECT 'document', doc_id, len(list_filter(string_split(text, chr(10)), lambda x: trim(x) <> '')) FROM documents
 UNION ALL SELECT 'benchmark', item_id, len(list_filter(string_split(text, chr(10)), lambda x: trim(x) <> '')) FROM benchmark
 UNION ALL SELECT 'page', page_id, len(regexp_extract_all(html, '<p[^>]*>(.*?)</p>', 1)) FROM pages)"""


@query("lake_stats", sq.with_(sq.VC, SIZES) + " SELECT lake, count(*) AS tables, CAST(sum(n) AS BIGINT) AS columns, max(n) AS widest, count(*) FILTER (WHERE n > 15) AS wide FROM sz WHERE n > 0 GROUP BY 1")
def lake_stats(spark, sf):
    out = None
    for name in ("vector", "wide", "label", "conversation", "event", "document", "benchmark", "page"):
        n = lakes.LAKES[name][0](spark, sf).groupBy("set_id").agg(F.count("*").alias("n"))
        one = n.agg(F.count("*").alias("tables"), F.sum("n").alias("columns"), F.max("n").alias("widest"), F.count_if(F.col("n") > 15).alias("wide")).select(F.lit(name).alias("lake"), "*")
        out = one if out is None else out.unionByName(one)
    return out


query("relational_stats")(lambda s, d: lakes.relational_lake(s, d).groupBy("set_id").agg(F.count("*").alias("n")))

ENCODED = """tk AS (SELECT item_id AS set_id, CAST(pos - 1 AS INTEGER) AS pos, unnest(list_filter(regexp_split_to_array(lower(line), '[^a-z0-9\\x{80}-\\x{10FFFF}]+'), lambda w: w <> '')) AS token
  FROM (SELECT item_id, unnest(ls) AS line, unnest(range(1, len(ls) + 1)) AS pos FROM (SELECT item_id, list_filter(list_transform(string_split(text, chr(10)), lambda x: trim(x)), lambda x: x <> '') AS ls FROM benchmark))),
 tf AS (SELECT set_id, pos, token, count(*) AS tf FROM tk GROUP BY ALL),
 bw AS (SELECT set_id, pos, CAST(CAST('0x' || substr(md5(token), 1, 8) AS BIGINT) % 64 AS INTEGER) AS b, sum(CAST((CASE WHEN CAST('0x' || substr(md5(token), 9, 1) AS BIGINT) < 8 THEN 1 ELSE -1 END) * round((1 + ln(tf)) * 1000000) AS BIGINT)) AS w FROM tf GROUP BY ALL)"""
query("encode_columns", sq.with_(ENCODED) + " SELECT set_id, pos, b, CAST(round(w / sqrt(sum(CAST(w AS DOUBLE)*w) OVER (PARTITION BY set_id, pos)) * 1000) AS BIGINT) AS x3 FROM bw WHERE w <> 0")(
    lambda s, d: lakes.benchmark_lake(s, d).select("set_id", "pos", F.posexplode("v").alias("b", "x")).where("x != 0").select("set_id", "pos", "b", F.round(F.col("x") * 1000).cast("bigint").alias("x3"))
)
query("event_profile", "SELECT user_id AS set_id, CAST(hour(ts) AS INTEGER) AS h, event_type, CAST(sum(CAST(round(value * 1000000) AS BIGINT)) AS BIGINT) AS x6 FROM events GROUP BY ALL")(
    lambda s, d: lakes.table(s, d, "events").groupBy(F.col("user_id").alias("set_id"), F.hour("ts").alias("h"), "event_type").agg(F.sum(F.round(F.col("value") * 1e6).cast("bigint")).alias("x6"))
)

# ---- comparisons ------------------------------------------------------------------------------


def methods(index: ix.Index, cols: DataFrame, queries: mt.Queries, plan: se.Plan, k_prime: int | None = None, shards: int = 4) -> dict[str, DataFrame]:
    """RESULT rows (stage answer) of each method at one setting."""
    out = {
        "quantized": se.quantized(index, queries, replace(plan, prune="base")),
        "quantized+": se.quantized(index, queries, replace(plan, prune="lossless")),
        "staged": se.staged(index, queries, replace(plan, prune="base")),
        "staged+": se.staged(index, queries, replace(plan, prune="lossless")),
        "staged+ listing": se.staged(index, queries, replace(plan, prune="listing")),
    }
    if k_prime:
        graph = ix.build_sharded_graph(cols, shards)
        ids = se.column_candidates(graph, queries, k_prime)
        out["column graph"] = se.score_candidates(index, queries, ids, replace(plan, prune="base"))
        out["column graph+"] = se.score_candidates(index, queries, ids, replace(plan, prune="lossless"))
    return out


GRID_ROW = "method string, setting string, recall double, evaluations double, seconds double"


def measured(run: Callable[[], DataFrame], truth: DataFrame, n_queries: int) -> tuple[float, float, float]:
    """(recall, evaluations a query, seconds a query) of RESULT rows; the clock covers the whole call, with every scan it runs."""
    began = time.perf_counter()
    rows = written(run(), "measured")
    seconds = time.perf_counter() - began
    share = recall(truth, rows.where("stage = 'answer'")).agg(F.avg("recall")).first()[0] or 0.0
    work = rows.groupBy("query_id", "stage").agg(F.max("evaluations").alias("e")).groupBy("query_id").agg(F.sum("e").alias("e")).agg(F.avg("e")).first()[0] or 0.0
    return round(share, 4), round(float(work), 2), round(seconds / max(1, n_queries), 5)


def exact_answer(sets: DataFrame, queries: mt.Queries, plan: se.Plan) -> DataFrame:
    return mt.top_k_exact(sets, queries, plan.tau, plan.k, plan.semantics)


def compared(spark, index: ix.Index, cols: DataFrame, sets: DataFrame, queries: mt.Queries, plan: se.Plan, k_prime: int | None = None) -> DataFrame:
    """(method, recall, evaluations): means over queries; truth is the exact search."""
    truth = written(exact_answer(sets, queries, plan), "truth")
    rows = [(name, *measured(lambda f=frame: f, truth, len(queries))[:2]) for name, frame in methods(index, cols, queries, plan, k_prime).items()]
    return spark.createDataFrame(rows, "method string, recall double, evaluations double")


def planted(spark, sf, copies: int, n_queries: int | None = None, wide: bool = False):
    """(columns, sets, queries) of a planted lake. Queries: every set whose id divides by 20, or n_queries first copies in the order of a hash."""
    cols = lakes.planted_lake(spark, sf, copies, wide).persist()
    if n_queries is None:
        return cols, lakes.vec_sets(cols), mt.collect_queries(cols.where(sq.QUERIES))
    ids = [r["set_id"] for r in cols.where(F.col("set_id") % copies == 0).select("set_id").distinct().orderBy(F.md5(F.col("set_id").cast("string"))).limit(n_queries).collect()]
    return cols, lakes.vec_sets(cols), mt.collect_queries(cols.where(F.col("set_id").isin(ids)))


PLANTED = se.Plan(k=10, tau=0.3, phi_c=16, phi_ref=200, phi_r=60)


@query("w_small")
def w_small(spark, sf, copies: int = 10):
    """The small lake: k = 10, every method."""
    cols, sets, queries = planted(spark, sf, copies)
    index = ix.build(cols, 64, None, 4, spherical=True)
    index.sets, index.counts = index.sets.persist(), index.counts.persist()
    out = compared(spark, index, cols, sets, queries, PLANTED, 30)
    for frame in (cols, index.sets, index.counts):
        frame.unpersist()
    return out


@query("w_wide_lake")
def w_wide_lake(spark, sf, copies: int = 12):
    """A lake of tables with thirty columns, k = 10."""
    cols, sets, queries = planted(spark, sf, copies, wide=True)
    index = ix.build(cols, 64, None, 4, spherical=True)
    index.sets, index.counts = index.sets.persist(), index.counts.persist()
    out = compared(spark, index, cols, sets, queries, replace(PLANTED, phi_ref=100, phi_r=30))
    for frame in (cols, index.sets, index.counts):
        frame.unpersist()
    return out


def lake_search(spark, sf, name: str, where: str, plan: se.Plan, n_c: int | None = 64) -> DataFrame:
    build, dim = lakes.LAKES[name]
    cols = build(spark, sf).persist()
    sets = lakes.vec_sets(cols, dim).persist()
    queries = mt.collect_queries(cols.join(sets.where(where).select("set_id"), "set_id", "left_semi"))
    index = ix.build(cols, dim, n_c, 3)
    index.sets, index.counts = index.sets.persist(), index.counts.persist()
    out = compared(spark, index, cols, sets, queries, plan)
    for frame in (cols, sets, index.sets, index.counts):
        frame.unpersist()
    return out


query("w_many_queries")(lambda s, d: lake_search(s, d, "conversation", sq.QUERIES, se.Plan(k=10, tau=0.3, phi_c=8, phi_ref=50, phi_r=30)))
query("w_wide_queries")(lambda s, d: lake_search(s, d, "document", "n > 15", se.Plan(k=10, tau=0.3, phi_c=1, phi_ref=100, phi_r=30), 64))
query("w_pages")(lambda s, d: lake_search(s, d, "page", sq.QUERIES, se.Plan(k=50, tau=0.3, phi_c=16, phi_ref=500, phi_r=150)))


@query("benchmark_search")
def benchmark_search(spark, sf):
    """Benchmark items as queries against the lake of documents."""
    queries = mt.collect_queries(lakes.benchmark_lake(spark, sf))
    shifted = {-1 - i: v for i, v in queries.items()}  # item ids are not document ids
    return mt.top_k_scan(lakes.vec_sets(lakes.document_lake(spark, sf)), shifted, 0.3, 10, "lossless")[0]


@query("filtered_search")
def filtered_search(spark, sf):
    """Union search among documents of good quality that are not toxic, for each of them whose id divides by 20; the predicate goes before the ranking."""
    good = lakes.table(spark, sf, "labels").where("quality = 1 and toxic = 0").select(F.col("doc_id").alias("set_id"))
    cols = lakes.document_lake(spark, sf, good).persist()
    sets, out = lakes.vec_sets(cols), None
    for queries in mt.query_blocks(cols.where("set_id % 20 = 0")):
        one = mt.top_k_exact(sets, queries, 0.3, 10)
        out = one if out is None else out.unionByName(one)
    return out


@query("family_recall")
def family_recall(spark, sf):
    """Relational lake: the share of the ten best that come from the query's base table."""
    tables = lakes.relational_tables(spark, sf).persist()
    family = tables.select("set_id", "family").distinct()
    cols = lakes.encode_tables(tables).persist()
    firsts = [r["s"] for r in family.groupBy("family").agg(F.min("set_id").alias("s")).collect()]
    top = mt.top_k_scan(lakes.vec_sets(cols), mt.collect_queries(cols.where(F.col("set_id").isin(firsts))), 0.5, 10, "lossless")[0]
    both = top.join(family, "set_id").join(family.select(F.col("set_id").alias("query_id"), F.col("family").alias("own")), "query_id")
    return both.groupBy("own").agg(F.avg((F.col("family") == F.col("own")).cast("int")).alias("share"))


RULES = ("none", "base", "listing", "lossless")


def prune_rows(name: str, sets: DataFrame, queries: mt.Queries, tau: float, k: int) -> list[tuple]:
    """(lake, prune, evaluations, seconds, speedup over none, speedup over base, recall) of exact scans by rule, timed whole."""
    out, took, truth = [], {}, None
    for prune in RULES:
        began = time.perf_counter()
        answer, work = mt.top_k_scan(sets, queries, tau, k, prune)
        found = written(answer, "answer")
        took[prune] = (time.perf_counter() - began) / max(1, len(queries))
        truth = truth or found
        share = recall(truth, found).agg(F.avg("recall")).first()[0]
        evals = work.agg(F.avg("evaluations")).first()[0]
        out.append((name, prune, round(float(evals), 2), round(took[prune], 5), round(took["none"] / took[prune], 2), round(took["base"] / took[prune], 2) if "base" in took else None, round(float(share), 4)))
    return out


PRUNE_ROW = "lake string, prune string, evaluations double, seconds double, over_none double, over_base double, recall double"


@query("prune_compare")
def prune_compare(spark, sf):
    """Exact evaluations a query of a scan of all sets without pruning, with the base rule and with both enhanced ones."""
    cols, sets, queries = planted(spark, sf, 6)
    out = spark.createDataFrame(prune_rows("planted", sets, queries, 0.3, 10), PRUNE_ROW).select("prune", "evaluations")
    cols.unpersist()
    return out


@query("prune_lakes")
def prune_lakes(spark, sf):
    """Pruned scans on six lakes: small, large, wide, of conversations, of events and of pages; every set whose id divides by 20 is a query.

    Without pruning every pair is solved, which sets of hundreds of vectors, as documents are, do not allow.
    """
    rows = []
    for name, how in (("small", (4, False)), ("large", (12, False)), ("wide", (6, True))):
        cols, sets, queries = planted(spark, sf, how[0], wide=how[1])
        sets = sets.persist()
        sets.count()
        rows += prune_rows(name, sets, queries, 0.3, 10)
        for frame in (cols, sets):
            frame.unpersist()
    for name, k in (("conversation", 10), ("event", 10), ("page", 50)):
        build, dim = lakes.LAKES[name]
        cols = build(spark, sf).persist()
        sets = lakes.vec_sets(cols, dim).persist()
        rows += prune_rows(name, sets, mt.collect_queries(cols.where(sq.QUERIES)), 0.3, k)
        for frame in (cols, sets):
            frame.unpersist()
    return spark.createDataFrame(rows, PRUNE_ROW)


@query("scalability")
def scalability(spark, sf, sizes: tuple[int, ...] = (2, 5, 10, 20), ks: tuple[int, ...] = (5, 10, 15, 20, 25, 30), n_queries: int | None = None):
    """Exact evaluations and seconds a query of both rules, by lake size at k = 10 and by k on the largest lake."""
    rows = []
    for copies in sizes:
        cols, sets, queries = planted(spark, sf, copies, n_queries)
        sets = sets.persist()
        n = sets.count()
        for k in ks if copies == sizes[-1] else (10,):
            for prune in ("base", "lossless"):
                began = time.perf_counter()
                _, work = mt.top_k_scan(sets, queries, 0.3, k, prune)
                evals = work.agg(F.avg("evaluations")).first()[0]
                rows.append((n, k, prune, round(float(evals), 2), round((time.perf_counter() - began) / len(queries), 5)))
        for frame in (cols, sets):
            frame.unpersist()
    return spark.createDataFrame(rows, "sets bigint, k int, prune string, evaluations double, seconds double")


@query("storage_and_build")
def storage_and_build(spark, sf, copies: int = 10, shards: int = 8):
    """(method, part, bytes, seconds): what each index takes, as written, and how long each of its steps takes."""
    cols = lakes.planted_lake(spark, sf, copies).persist()
    n, rows = cols.count(), []

    def step(method: str, part: str, make: Callable[[], DataFrame]) -> DataFrame:
        path, began = folder(spark, "index"), time.perf_counter()
        make().write.parquet(path)
        rows.append((method, part, size_of(spark, path), round(time.perf_counter() - began, 3)))
        return spark.read.parquet(path)

    began = time.perf_counter()
    centroids = ix.fit_centroids(cols, ix.default_centroids(n), 4, spherical=True)
    fitted = round(time.perf_counter() - began, 3)
    for method in ("quantized", "staged"):
        rows.append((method, "centroids", centroids.astype("float32").nbytes, fitted))
        assigned = step(method, "codes", lambda: ix.assign(cols, centroids).select("set_id", "pos", "c"))
        step(method, "postings", lambda a=assigned: ix.inverted_counts(a))
    built = ix.build(cols, 64, centroids=centroids)
    step("staged", "partitions", lambda: built.sets.select("set_id", "n", "part", "groups", "own"))
    step("column graph", "graph", lambda: ix.build_sharded_graph(cols, shards))
    step("all", "vectors", lambda: cols.select("set_id", "pos", F.col("v").cast("array<float>").alias("v")))
    cols.unpersist()
    return spark.createDataFrame(rows, "method string, part string, bytes bigint, seconds double")


def grid_rows(index: ix.Index, cols: DataFrame, truth: DataFrame, queries: mt.Queries, plan: se.Plan, phi_cs: tuple[int, ...], phi_refs: tuple[int, ...], k_primes: tuple[int, ...], shards: int = 8) -> list[tuple]:
    """GRID_ROW rows over the parameter grid; phi_refs and k_primes in multiples of k."""
    n, rows = len(queries), []
    for phi_c in phi_cs:
        for name, prune in (("quantized", "base"), ("quantized+", "lossless")):
            rows.append((name, f"phi_c={phi_c}", *measured(lambda: se.quantized(index, queries, replace(plan, phi_c=phi_c, prune=prune)), truth, n)))
        for m in phi_refs:
            for name, prune in (("staged", "base"), ("staged+", "lossless")):
                at = replace(plan, phi_c=phi_c, phi_ref=m * plan.k, phi_r=min(plan.phi_r, m * plan.k), prune=prune)
                rows.append((name, f"phi_c={phi_c} phi_ref={m}k", *measured(lambda at=at: se.staged(index, queries, at), truth, n)))
    if k_primes:
        graph = written(ix.build_sharded_graph(cols, shards), "graph")
        for m in k_primes:
            for name, prune in (("column graph", "base"), ("column graph+", "lossless")):
                rows.append((name, f"k'={m}k", *measured(lambda: se.score_candidates(index, queries, se.column_candidates(graph, queries, m * plan.k), replace(plan, prune=prune)), truth, n)))
    return rows


@query("recall_latency_grid")
def recall_latency_grid(spark, sf, copies: int = 10, phi_cs: tuple[int, ...] = (4, 16), phi_refs: tuple[int, ...] = (5, 20), k_primes: tuple[int, ...] = (1, 10), n_queries: int | None = None):
    """Recall, evaluations and seconds a query of each method over the grid of parameters, on a planted lake."""
    cols, sets, queries = planted(spark, sf, copies, n_queries)
    index = ix.build(cols, 64, None, 4, spherical=True)
    index.sets, index.counts = index.sets.persist(), index.counts.persist()
    rows = grid_rows(index, cols, written(exact_answer(sets, queries, PLANTED), "truth"), queries, PLANTED, phi_cs, phi_refs, k_primes)
    for frame in (cols, index.sets, index.counts):
        frame.unpersist()
    return spark.createDataFrame(rows, GRID_ROW)


@query("pareto_measured")
def pareto_measured(spark, sf):
    """The points of the measured grid that no other point beats in recall and seconds."""
    grid = recall_latency_grid(spark, sf)
    ints = grid.select("method", "setting", F.round(F.col("recall") * 1000).cast("int").alias("recall"), F.round(F.col("seconds") * 1e6).cast("int").alias("ms"))
    return pareto_front(ints).withColumnRenamed("ms", "us")


def _sweep(spark, sf, field: str, values: list[int], **how) -> DataFrame:
    cols, sets, queries = planted(spark, sf, 6)
    index = ix.build(cols, 64, 128, 4, spherical=True)
    index.sets, index.counts = index.sets.persist(), index.counts.persist()
    base = replace(PLANTED, k=6, phi_ref=60, phi_r=18)
    out = _swept(spark, index, sets, queries, base, field, values, **how)
    for frame in (cols, index.sets, index.counts):
        frame.unpersist()
    return out


def _swept(spark, index, sets, queries, base: se.Plan, field: str, values: list[int], **how) -> DataFrame:
    """(field, recall): the recall of the staged search as one parameter moves."""
    truth = written(exact_answer(sets, queries, base), "truth")
    rows = [(v, recall(truth, se.union_search(index, queries, replace(base, **how, **{field: v}))).agg(F.avg("recall")).first()[0]) for v in values]
    return spark.createDataFrame(rows, f"{field} int, recall double")


@query("sweep_phi_ref_documents")
def sweep_phi_ref_documents(spark, sf):
    """The study of phi_ref on the lake of documents at phi_c = 1 with wide queries, and the quantized baseline beside it."""
    cols = lakes.document_lake(spark, sf).persist()
    sets = lakes.vec_sets(cols).persist()
    queries = mt.collect_queries(cols.join(sets.where("n > 15 and set_id % 20 = 0").select("set_id"), "set_id", "left_semi"))
    index = ix.build(cols, 64, None, 3)
    index.sets, index.counts = index.sets.persist(), index.counts.persist()
    base = se.Plan(k=10, tau=0.3, phi_c=1, phi_ref=50, phi_r=10)
    line = _swept(spark, index, sets, queries, base, "phi_ref", [10, 20, 50, 100, 200], stages=("refine",)).select(F.lit("staged").alias("method"), "phi_ref", "recall")
    truth = written(exact_answer(sets, queries, base), "truth")
    share = measured(lambda: se.quantized(index, queries, base), truth, len(queries))[0]
    for frame in (cols, sets, index.sets, index.counts):
        frame.unpersist()
    return line.unionByName(spark.createDataFrame([("quantized", None, share)], "method string, phi_ref int, recall double"))


query("sweep_phi_ref")(lambda s, d: _sweep(s, d, "phi_ref", [6, 12, 24, 60, 120], phi_c=32, stages=("refine",)))
query("sweep_phi_r")(lambda s, d: _sweep(s, d, "phi_r", [6, 9, 12, 18, 36], stages=("refine", "filter")))
query("sweep_phi_c")(lambda s, d: _sweep(s, d, "phi_c", [1, 2, 4, 8, 16], stages=("refine",)))
TAUS = [0.05, 0.1, 0.2, 0.3, 0.5]
SIMS = f"sa AS (SELECT {sq.SIM} AS sim6 FROM qs JOIN vc ON query_id <> set_id)"
query("sweep_tau", sq.with_(sq.VC, sq.QS, SIMS) + " SELECT CAST(tau6 AS BIGINT) AS tau6, count(*) FILTER (WHERE sim6 >= tau6) AS edges FROM sa, (SELECT unnest([50000,100000,200000,300000,500000]) AS tau6) GROUP BY 1")(lambda s, d: sweep_tau(s, d))


def sweep_tau(spark, sf):
    c = sq.cols_of(spark, sf)
    e = mt.edges(c.where(sq.QUERIES), c, TAUS[0]).agg(*[F.count_if(F.col("sim6") >= micro(x)).alias(str(micro(x))) for x in TAUS])
    return e.unpivot([], [F.col(str(micro(x))) for x in TAUS], "tau6", "edges").select(F.col("tau6").cast("bigint").alias("tau6"), "edges")


# ---- measures ---------------------------------------------------------------------------------

query("index_bytes_model", sq.with_(sq.VC, sq.CE, sq.AS, sq.IW) + """ SELECT 'raw' AS part, (SELECT 4*64*count(*) FROM vc) AS bytes UNION ALL SELECT 'codes', (SELECT 4*count(*) FROM vc)
 UNION ALL SELECT 'postings', (SELECT 20*count(*) FROM iw) UNION ALL SELECT 'centroids', (SELECT 4*64*count(*) FROM ce) UNION ALL SELECT 'column graph', (SELECT (4*64 + 2*16*8)*count(*) FROM vc)""")(lambda s, d: index_bytes(s, d))  # fmt: skip


def index_bytes(spark, sf):
    """Bytes by part from counts: 32-bit components, 32-bit codes, postings of 20 bytes, 32 links of 8 bytes at a graph's base."""
    n = sq.cols_of(spark, sf).agg(F.count("*").alias("n"))
    p = ix.inverted_counts(sq.assigned(spark, sf)).agg(F.count("*").alias("p"))
    parts = [("raw", F.col("n") * 256), ("codes", F.col("n") * 4), ("postings", F.col("p") * 20), ("centroids", F.lit(256 * sq.N_C).cast("bigint")), ("column graph", F.col("n") * 512)]
    both = n.crossJoin(p)  # one row each
    return both.select(F.explode(F.array(*[F.struct(F.lit(k).alias("part"), v.cast("bigint").alias("bytes")) for k, v in parts])).alias("x")).select("x.part", "x.bytes")


#: Parts as the points: large is good, and cheap.
PARTS = "g AS (SELECT p_brand AS method, p_partkey AS setting, p_size AS recall, CAST(round(p_retailprice * 100) AS BIGINT) AS ms FROM part), m AS (SELECT recall, min(ms) AS ms FROM g GROUP BY 1)"
query("pareto_front", f"WITH {PARTS} SELECT method, setting, recall, ms FROM g JOIN m a USING (recall, ms) WHERE NOT EXISTS (SELECT 1 FROM m b WHERE b.recall > a.recall AND b.ms <= a.ms)")(
    lambda s, d: pareto_front(lakes.table(s, d, "part").select(F.col("p_brand").alias("method"), F.col("p_partkey").alias("setting"), F.col("p_size").alias("recall"), F.round(F.col("p_retailprice") * 100).cast("bigint").alias("ms")))
)


def pareto_front(grid: DataFrame) -> DataFrame:
    """Rows that no other row beats: of each recall the least time, if it is below that of every higher recall (window over one row a recall)."""
    least = grid.groupBy("recall").agg(F.min("ms").alias("ms"))
    above = Window.orderBy(F.col("recall").desc()).rowsBetween(Window.unboundedPreceding, -1)
    front = least.withColumn("best", F.min("ms").over(above)).where(F.col("best").isNull() | (F.col("ms") < F.col("best"))).drop("best")
    return grid.join(F.broadcast(front), ["recall", "ms"]).select(*grid.columns)


# ---- streams ----------------------------------------------------------------------------------


@query("stream_ingest_counts", sq.with_(sq.VC, sq.CE, sq.AS) + " SELECT c, count(*) AS n FROM asg GROUP BY 1")
def stream_ingest_counts(spark, sf):
    stream = jobs.read_stream(spark, sf, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("v"))
    cols = stream.select(F.col("vec_id").alias("set_id"), F.lit(0).alias("pos"), "v")
    to = jobs.folder(spark, "postings")
    jobs.ingest(cols, sq.seeds(spark, sf), to)
    return spark.read.parquet(to).groupBy("c").agg(F.count("*").alias("n"))


@query("stream_standing_query", sq.with_(sq.VC, sq.QS, sq.ED, sq.dp("ed", True)) + " SELECT query_id, set_id, t, u6 FROM best WHERE u6 >= 500000")
def stream_standing_query(spark, sf):
    at = jobs.folder(spark, "sets")
    sq.sets_of(spark, sf).write.parquet(at)
    stream = spark.readStream.schema(spark.read.parquet(at).schema).parquet(at)
    return jobs.to_memory(jobs.standing_query(stream, sq.queries_of(spark, sf), sq.TAU, 500_000))


query("stream_drift")(lambda s, d: jobs.to_memory(jobs.drift(ix.assign(jobs.read_stream(s, d, "embeddings").select(F.col("vec_id").alias("set_id"), F.lit(0).alias("pos"), F.col("embedding").cast("array<double>").alias("v")), sq.seeds(s, d)), 10), "update"))


@query("stream_late", "SELECT date_trunc('day', ts) AS start, event_type, count(*) AS n FROM events GROUP BY 1, 2 HAVING date_trunc('day', min(ts)) + INTERVAL 1 DAY <= (SELECT max(ts) FROM events) - INTERVAL 1 HOUR")
def stream_late(spark, sf):
    """Daily counts in append mode. All events come first, then those before the last two days once more: these are late, and none may count.

    A day is put out once the watermark, an hour behind the latest event, has passed its end. A batch drops
    what was late for the batch before it, so one without rows stands between.
    """
    events = lakes.table(spark, sf, "events")
    last = events.agg((F.max("ts") - F.expr("interval 2 days")).alias("t")).first()["t"]
    stream = jobs.in_turn(spark, [events, events.where("false"), events.where(F.col("ts") < F.lit(last))], "events")
    return jobs.to_memory(jobs.late_counts(stream, "1 hour", "1 day")).select(F.col("w.start").cast("timestamp_ntz").alias("start"), "event_type", "n")


query("stream_dedup", "SELECT DISTINCT user_id, event_type FROM events")(
    lambda s, d: jobs.to_memory(jobs.deduplicated(jobs.read_stream(s, d, "events"), "90 days", ["user_id", "event_type"]).select("user_id", "event_type"))
)
query("stream_interval_join", "SELECT a.user_id, a.event_id AS first_id, b.event_id AS second_id FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type = 'purchase' AND b.ts BETWEEN a.ts AND a.ts + INTERVAL 1 HOUR")(
    lambda s, d: jobs.to_memory(jobs.interval_join(jobs.read_stream(s, d, "events"), jobs.read_stream(s, d, "events"), "click", "purchase", "1 hour"))
)
