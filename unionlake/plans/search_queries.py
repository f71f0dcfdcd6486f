"""Registered queries of the search methods, with DuckDB SQL where it can express them.

The SQL starts from the base tables each time. Optimal matchings are a recursive dynamic programme
over bit masks of used targets, which narrow queries (at most ten columns) allow.
"""

from __future__ import annotations

from dataclasses import replace
from functools import reduce

import numpy as np
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from unionlake.functions.vectors import micro, sim6
from unionlake.operators import index as ix
from unionlake.operators import kernels as K
from unionlake.operators import matching as mt
from unionlake.operators import search as se
from unionlake.sources import lakes

TAU, TOP, N_C = 0.1, 10, 32
#: Every set whose id divides by 20 is a query.
QUERIES = "set_id % 20 = 0"
PLAN = se.Plan(k=5, tau=TAU, phi_c=4, phi_ref=20, phi_r=10)


# ---- what the queries share -------------------------------------------------------------------


def cols_of(spark: SparkSession, sf: str) -> DataFrame:
    return lakes.vector_lake(spark, sf)


def sets_of(spark: SparkSession, sf: str) -> DataFrame:
    return lakes.vec_sets(cols_of(spark, sf))


def query_cols(spark: SparkSession, sf: str) -> DataFrame:
    return cols_of(spark, sf).where(QUERIES)


def queries_of(spark: SparkSession, sf: str) -> mt.Queries:
    return mt.collect_queries(query_cols(spark, sf))


def query_ids(spark: SparkSession, sf: str) -> DataFrame:
    """(query_id), as many rows as queries."""
    return sets_of(spark, sf).where(QUERIES).select(F.col("set_id").alias("query_id"))


def seeds(spark: SparkSession, sf: str) -> np.ndarray:
    rows = lakes.table(spark, sf, "embeddings").where(F.col("vec_id") < N_C).orderBy("vec_id").collect()
    return np.array([r["embedding"] for r in rows], np.float64)


def plain_index(spark: SparkSession, sf: str, adapt: bool = False, rho_low: float = 0.35, rho_high: float = 0.8) -> ix.Index:
    """Centroids are the first N_C vectors, without a round of k-means, so that SQL can follow."""
    cols, c = cols_of(spark, sf), seeds(spark, sf)
    return build_on(cols, c, adapt, rho_low, rho_high)


def build_on(cols: DataFrame, c: np.ndarray, adapt: bool, rho_low: float, rho_high: float, dim: int = 64) -> ix.Index:
    return ix.build(cols, dim, rho_low=rho_low, rho_high=rho_high, adapt=adapt, centroids=c)


VC = """vc AS (SELECT 5*(vec_id//30) + (CASE WHEN vec_id%30<2 THEN 0 WHEN vec_id%30<6 THEN 1 WHEN vec_id%30<12 THEN 2 WHEN vec_id%30<20 THEN 3 ELSE 4 END + vec_id//120) % 5 AS set_id,
 CAST(vec_id%30 - CASE WHEN vec_id%30<2 THEN 0 WHEN vec_id%30<6 THEN 2 WHEN vec_id%30<12 THEN 6 WHEN vec_id%30<20 THEN 12 ELSE 20 END AS INTEGER) AS pos,
 vec_id, CAST(embedding AS DOUBLE[]) AS v FROM embeddings)"""
MS = "ms AS (SELECT set_id, CAST(count(*) AS INTEGER) AS n FROM vc GROUP BY 1)"
QS = "qs AS (SELECT set_id AS query_id, pos AS q, v AS vq FROM vc WHERE set_id % 20 = 0)"
NQ = "nq AS (SELECT query_id, count(*) AS nq FROM qs GROUP BY 1)"
PR = "pr AS (SELECT query_id, nq, set_id, n FROM nq JOIN ms ON query_id <> set_id)"
SIM = "CAST(round(list_inner_product(vq, v) * 1000000) AS BIGINT)"
ED = f"ed AS (SELECT query_id, set_id, q, pos AS j, {SIM} AS sim6 FROM qs JOIN vc ON query_id <> set_id WHERE {SIM} >= {micro(TAU)})"
CE = f"ce AS (SELECT CAST(vec_id AS INTEGER) AS c, v AS m FROM vc WHERE vec_id < {N_C})"
AS = """asg AS (SELECT set_id, pos, v, arg_min(c, d*1000 + c) AS c FROM
 (SELECT set_id, pos, v, c, CAST(round((list_inner_product(m, m) - 2*list_inner_product(v, m)) * 1000000000) AS HUGEINT) AS d FROM vc, ce) GROUP BY set_id, pos, v)"""
IW = "iw AS (SELECT c, set_id, count(*) AS n FROM asg GROUP BY 1, 2)"
QC = "qc AS (SELECT query_id, q, c, CAST(round(list_inner_product(vq, m) * 1000000) AS BIGINT) AS sim6 FROM qs, ce)"
PB = f"pb AS (SELECT query_id, q, c, sim6 FROM qc QUALIFY row_number() OVER (PARTITION BY query_id, q ORDER BY sim6 DESC, c) <= {PLAN.phi_c})"
PO = "po AS (SELECT query_id, set_id, q, pb.c, sim6, n FROM pb JOIN iw ON pb.c = iw.c AND query_id <> set_id)"
BIG = 1_000_000_000


def refine_cte(where: str = "TRUE") -> str:
    return f"""r1 AS (SELECT * FROM po WHERE {where} QUALIFY row_number() OVER (PARTITION BY query_id, set_id, q ORDER BY sim6 DESC, c) = 1),
 r2 AS (SELECT * FROM r1 QUALIFY row_number() OVER (PARTITION BY query_id, set_id, c ORDER BY sim6 DESC, q) <= n),
 rf AS (SELECT query_id, set_id, CAST(sum(sim6) AS BIGINT) AS score6, CAST(row_number() OVER (PARTITION BY query_id ORDER BY sum(sim6) DESC, set_id) AS INTEGER) AS rank
  FROM r2 GROUP BY 1, 2 QUALIFY row_number() OVER (PARTITION BY query_id ORDER BY sum(sim6) DESC, set_id) <= {PLAN.phi_ref})"""


def dp(edges: str, card: bool, name: str = "best") -> str:
    """CTEs that end in `name`(query_id, set_id, t, u6): optimal matchings of the edges (query_id, set_id, q, j, sim6). t only with card."""
    w = f"sim6 + {BIG}" if card else "sim6"
    total = f"CAST(max(w) // {BIG} AS INTEGER) AS t, CAST(max(w) % {BIG} AS BIGINT) AS u6" if card else "CAST(NULL AS INTEGER) AS t, CAST(max(w) AS BIGINT) AS u6"
    return f"""e1 AS (SELECT query_id, set_id, q, j, {w} AS w FROM {edges} UNION ALL
  SELECT query_id, set_id, CAST(g.q AS INTEGER), -1, 0 FROM (SELECT DISTINCT query_id, set_id FROM {edges}), (SELECT unnest(range(10)) AS q) g),
 dp(query_id, set_id, q, mask, w) AS (SELECT DISTINCT query_id, set_id, -1, CAST(0 AS BIGINT), CAST(0 AS BIGINT) FROM e1 UNION ALL
  SELECT d.query_id, d.set_id, d.q + 1, d.mask | CASE WHEN e.j >= 0 THEN CAST(1 AS BIGINT) << e.j ELSE 0 END, max(d.w + e.w) FROM dp d
   JOIN e1 e ON e.query_id = d.query_id AND e.set_id = d.set_id AND e.q = d.q + 1 WHERE e.j < 0 OR (d.mask >> greatest(e.j, 0)) & 1 = 0
   GROUP BY d.query_id, d.set_id, d.q + 1, d.mask | CASE WHEN e.j >= 0 THEN CAST(1 AS BIGINT) << e.j ELSE 0 END),
 {name} AS (SELECT query_id, set_id, {total} FROM dp WHERE q = 9 GROUP BY 1, 2)"""


def top_sql(source: str, k: int, score: str = "u6") -> str:
    return f"SELECT query_id, CAST(row_number() OVER w AS INTEGER) AS rank, set_id, {score} AS score6 FROM {source} WINDOW w AS (PARTITION BY query_id ORDER BY {score} DESC, set_id) QUALIFY row_number() OVER w <= {k}"


def with_(*parts: str) -> str:
    return "WITH RECURSIVE " + ",\n".join(parts)


ALL_U = "allu AS (SELECT query_id, set_id, coalesce(t, 0) AS t, coalesce(u6, 0) AS u6 FROM pr LEFT JOIN best USING (query_id, set_id))"
# many-to-one: each partition (set, centroid) becomes as many slots as it owns vectors
SLOTS = """pt AS (SELECT set_id, c, n AS cap, sum(n) OVER (PARTITION BY set_id ORDER BY c) - n AS first FROM iw),
 em AS (SELECT query_id, set_id, q, CAST(first + s AS INTEGER) AS j, sim6 FROM (SELECT *, unnest(range(cap)) AS s FROM pt) JOIN qc USING (c) WHERE query_id <> set_id AND sim6 >= {tau})""".replace("{tau}", str(micro(TAU)))
PM = f"pm AS (SELECT query_id, set_id, q, c, cap, sim6 FROM pt JOIN qc USING (c) WHERE query_id <> set_id AND sim6 >= {micro(TAU)})"


REGISTRY: dict = {}
SQL: dict[str, str] = {}


def query(key: str, sql: str | None = None):
    def add(f):
        REGISTRY[key] = f
        if sql:
            SQL[key] = sql
        return f

    return add


# ---- core model -------------------------------------------------------------------------------


@query("repo_sets", with_(VC) + " SELECT set_id, CAST(count(*) AS INTEGER) AS n, CAST(round(sum(v[1]) * 1000) AS BIGINT) AS first_e3 FROM vc GROUP BY 1")
def repo_sets(spark, sf):
    firsts = F.transform(F.sequence(F.lit(0), F.col("n") - 1), lambda i: F.element_at("flat", (i * 64 + 1).cast("int")))
    return sets_of(spark, sf).select("set_id", "n", F.round(F.aggregate(firsts, F.lit(0.0), lambda a, x: a + x) * 1000).cast("bigint").alias("first_e3"))


@query("edges_tau", with_(VC, QS, ED) + " SELECT * FROM ed")
def edges_tau(spark, sf):
    c = cols_of(spark, sf)
    return mt.edges(c.where(QUERIES), c, TAU)


@query("match_valid", with_(VC, QS, ED, "mx AS (SELECT * FROM ed QUALIFY row_number() OVER (PARTITION BY query_id, set_id, q ORDER BY sim6 DESC, j) = 1)") + """
 SELECT query_id, set_id, count(*) AS t, count(*) = count(DISTINCT j) AS valid FROM mx GROUP BY 1, 2""")  # fmt: skip
def match_valid(spark, sf):
    e = edges_tau(spark, sf)
    best = e.withColumn("rn", F.row_number().over(Window.partitionBy("query_id", "set_id", "q").orderBy(F.col("sim6").desc(), "j"))).where("rn = 1").drop("rn")
    return mt.is_matching(best, e)


@query("m2o_valid", with_(VC, QS, CE, AS, IW, QC, "pt AS (SELECT set_id, c, n AS cap FROM iw)", PM, "mx AS (SELECT * FROM pm QUALIFY row_number() OVER (PARTITION BY query_id, set_id, q ORDER BY sim6 DESC, c) = 1)") + """,
 ld AS (SELECT query_id, set_id, c, count(*) AS load, max(cap) AS cap FROM mx GROUP BY 1, 2, 3) SELECT query_id, set_id, CAST(sum(load) AS BIGINT) AS t, bool_and(load <= cap) AS valid FROM ld GROUP BY 1, 2""")  # fmt: skip
def m2o_valid(spark, sf):
    best = partition_edges(spark, sf).withColumn("rn", F.row_number().over(Window.partitionBy("query_id", "set_id", "q").orderBy(F.col("sim6").desc(), "c"))).where("rn = 1")
    load = best.groupBy("query_id", "set_id", "c").agg(F.count("*").alias("load"), F.max("cap").alias("cap"))
    return load.groupBy("query_id", "set_id").agg(F.sum("load").alias("t"), F.bool_and(F.col("load") <= F.col("cap")).alias("valid"))


def assigned(spark, sf):
    return ix.assign(cols_of(spark, sf), seeds(spark, sf))


def partition_edges(spark, sf) -> DataFrame:
    """(query_id, set_id, q, c, cap, sim6) of query columns and one-centroid partitions at or above the threshold."""
    parts = ix.partitions_identity(assigned(spark, sf)).select("set_id", "c", "cap")
    sims = se.query_frame(spark, queries_of(spark, sf)).join(F.broadcast(se.centroid_frame(spark, seeds(spark, sf))), F.lit(True))
    sims = sims.select("query_id", "q", "c", sim6(F.col("vq"), F.col("m")).alias("sim6")).where(F.col("sim6") >= micro(TAU))
    return parts.join(F.broadcast(sims), "c").where("set_id != query_id").select("query_id", "set_id", "q", "c", "cap", "sim6")


def _u(semantics):
    return lambda spark, sf: mt.unionability(sets_of(spark, sf), queries_of(spark, sf), TAU, semantics)


@query("t_max", with_(VC, MS, QS, NQ, PR, ED, dp("ed", True), ALL_U) + " SELECT query_id, set_id, t FROM allu")
def t_max(spark, sf):
    return _u("max_cardinality")(spark, sf).select("query_id", "set_id", "t")


query("unionability_card", with_(VC, MS, QS, NQ, PR, ED, dp("ed", True), ALL_U) + " SELECT query_id, set_id, t, u6 FROM allu")(_u("max_cardinality"))
query("unionability_weight", with_(VC, MS, QS, NQ, PR, ED, dp("ed", False), ALL_U) + " SELECT query_id, set_id, u6 FROM allu")(lambda s, d: _u("max_weight")(s, d).select("query_id", "set_id", "u6"))


@query("best_matching")
def best_matching(spark, sf):
    return mt.best_matching(sets_of(spark, sf), queries_of(spark, sf), TAU)


@query("best_matching_check", with_(VC, QS, ED, dp("ed", True)) + " SELECT query_id, set_id, CAST(t AS BIGINT) AS t, u6, TRUE AS valid FROM best WHERE t > 0")
def best_matching_check(spark, sf):
    """Pairs, total and validity of the matchings that best_matching gives."""
    return mt.checked_matchings(sets_of(spark, sf), queries_of(spark, sf), TAU)


def _topk(semantics):
    return lambda spark, sf: mt.top_k_exact(sets_of(spark, sf), queries_of(spark, sf), TAU, TOP, semantics)


EXACT_CARD = with_(VC, MS, QS, NQ, PR, ED, dp("ed", True), ALL_U) + " " + top_sql("allu", TOP)
EXACT_WEIGHT = with_(VC, MS, QS, NQ, PR, ED, dp("ed", False), ALL_U) + " " + top_sql("allu", TOP)
query("topk_exact_card", EXACT_CARD)(_topk("max_cardinality"))
query("topk_exact_weight", EXACT_WEIGHT)(_topk("max_weight"))


@query("group_sim", with_(VC, QS, CE, AS, QC, "g AS (SELECT DISTINCT set_id, c FROM asg)") + " SELECT query_id, set_id, q, max(sim6) AS sim6 FROM g JOIN qc USING (c) WHERE query_id <> set_id GROUP BY 1, 2, 3")
def group_sim(spark, sf):
    """The similarity of query columns to each set's centroids taken as one group."""
    groups = assigned(spark, sf).select("set_id", "c").distinct()
    sims = se.probe_flat(spark, queries_of(spark, sf), seeds(spark, sf), N_C)
    return groups.join(F.broadcast(sims), "c").where("query_id != set_id").groupBy("query_id", "set_id", "q").agg(F.max("sim6").alias("sim6"))


def _mwmto(card: bool):
    def run(spark, sf):
        def solve(pdf):
            """All queries of a set at once, padded to the widest."""
            import pandas as pd

            ids, at = np.unique(pdf["query_id"].to_numpy(), return_inverse=True)
            cs, first, k = np.unique(pdf["c"].to_numpy(), return_index=True, return_inverse=True)
            m = np.full((len(ids), int(pdf["q"].max()) + 1, len(cs)), K.NO_EDGE)
            m[at, pdf["q"].to_numpy(), k] = pdf["sim6"].to_numpy()
            t, u, _ = K.assign_many(m, pdf["cap"].to_numpy()[first], card)
            return pd.DataFrame({"query_id": ids, "set_id": pdf["set_id"].iloc[0], "t": t, "u6": u})

        return partition_edges(spark, sf).groupBy("set_id").applyInPandas(solve, "query_id bigint, set_id bigint, t int, u6 bigint")

    return run


M2O = (VC, QS, CE, AS, IW, QC, SLOTS)
query("mwmto_card", with_(*M2O, dp("em", True)) + " SELECT query_id, set_id, t, u6 FROM best")(_mwmto(True))
query("mwmto_weight", with_(*M2O, dp("em", False)) + " SELECT query_id, set_id, u6 FROM best")(lambda s, d: _mwmto(False)(s, d).select("query_id", "set_id", "u6"))
query("m2o_t_max", with_(*M2O, dp("em", True)) + " SELECT query_id, set_id, t FROM best")(lambda s, d: _mwmto(True)(s, d).select("query_id", "set_id", "t"))

def _totals(kind: str, semantics: str, pairs: str) -> str:
    return f"SELECT '{kind}' AS kind, '{semantics}' AS semantics, count(*) AS pairs, CAST(sum(u6) AS BIGINT) AS u6 FROM ({pairs} SELECT * FROM best)"


@query("example_matching", " UNION ALL ".join(_totals(kind, semantics, with_(*of, dp(edges, card))) for kind, of, edges in (("one_to_one", (VC, QS, ED), "ed"), ("many_to_one", M2O, "em")) for semantics, card in (("max_cardinality", True), ("max_weight", False))))
def example_matching(spark, sf):
    """How many pairs of tables match, and the total of all matchings, by kind and reading."""
    out = []
    for semantics, card in (("max_cardinality", True), ("max_weight", False)):
        for kind, rows in (("one_to_one", _u(semantics)(spark, sf)), ("many_to_one", _mwmto(card)(spark, sf))):
            found = rows.where("u6 > 0").agg(F.count("*").alias("pairs"), F.sum("u6").alias("u6"))
            out.append(found.select(F.lit(kind).alias("kind"), F.lit(semantics).alias("semantics"), "pairs", "u6"))
    return reduce(DataFrame.unionByName, out)


@query("partition_score")
def partition_score(spark, sf):
    plan = replace(PLAN, phi_ref=1000, phi_r=1000, k=1000, prune="none", semantics="max_weight")
    return se.union_search(plain_index(spark, sf, adapt=True), queries_of(spark, sf), plan)


# ---- clustering and index ---------------------------------------------------------------------


def _lloyd_sql(rounds: int = 3) -> str:
    parts = [VC, f"k0 AS (SELECT CAST(vec_id AS INTEGER) AS c, list_transform(v, lambda x: round(x, 6)) AS m FROM vc WHERE vec_id < {N_C})"]
    for r in range(1, rounds + 1):
        parts.append(f"""a{r} AS (SELECT vec_id, v, arg_min(c, d*1000 + c) AS c FROM (SELECT vec_id, v, c, CAST(round((list_inner_product(m, m) - 2*list_inner_product(v, m)) * 1000000000) AS HUGEINT) AS d FROM vc, k{r - 1}) GROUP BY vec_id, v),
 u{r} AS (SELECT c, i, round(avg(x), 6) AS x FROM (SELECT c, unnest(v) AS x, unnest(range(64)) AS i FROM a{r}) GROUP BY 1, 2),
 k{r} AS (SELECT k.c, coalesce(n.m, k.m) AS m FROM k{r - 1} k LEFT JOIN (SELECT c, list(x ORDER BY i) AS m FROM u{r} GROUP BY 1) n USING (c))""")
    return with_(*parts) + f" SELECT c, CAST(i AS INTEGER) AS d, CAST(round(x * 1000000) AS BIGINT) AS x6 FROM (SELECT c, unnest(m) AS x, unnest(range(64)) AS i FROM k{rounds})"


@query("kmeans_lloyd", _lloyd_sql())
def kmeans_lloyd(spark, sf):
    c = ix.fit_centroids(cols_of(spark, sf), N_C, 3, seeds=seeds(spark, sf))
    return se.centroid_frame(spark, c).select("c", F.posexplode("m").alias("d", "x")).select("c", "d", F.round(F.col("x") * 1e6).cast("bigint").alias("x6"))


A = (VC, CE, AS)
query("assign_nearest", with_(*A) + " SELECT set_id, pos, c FROM asg")(lambda s, d: assigned(s, d).select("set_id", "pos", "c"))
query("vq_codes", with_(*A) + " SELECT set_id, string_agg(CAST(c AS VARCHAR), ',' ORDER BY pos) AS codes FROM asg GROUP BY 1")(
    lambda s, d: assigned(s, d).groupBy("set_id").agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("pos", "c"))), lambda x: x["c"].cast("string")), ",").alias("codes"))
)
query("vq_error", with_(*A, "er AS (SELECT CAST(round(list_sum(list_transform(list_zip(v, m), lambda p: (p[1]-p[2])*(p[1]-p[2]))) * 1000000) AS BIGINT) AS e6 FROM asg JOIN ce USING (c))") + " SELECT count(*) AS n, CAST(sum(e6) AS BIGINT) AS sum_e6, max(e6) AS max_e6 FROM er")(
    lambda s, d: ix.vq_error(assigned(s, d), seeds(s, d))
)
query("inv_vectors", with_(*A) + " SELECT c, set_id, pos FROM asg")(lambda s, d: ix.inverted_vectors(assigned(s, d)))
query("inv_counts", with_(*A, IW) + " SELECT * FROM iw")(lambda s, d: ix.inverted_counts(assigned(s, d)))
query("centroid_map", with_(*A, IW) + " SELECT set_id, string_agg(c || ':' || n, ',' ORDER BY c) AS w FROM iw GROUP BY 1")(
    lambda s, d: ix.centroid_map(ix.inverted_counts(assigned(s, d))).select("set_id", F.array_join(F.transform(F.array_sort(F.map_entries("w")), lambda x: F.concat(x["key"].cast("string"), F.lit(":"), x["value"].cast("string"))), ",").alias("w"))
)
ST = "st AS (SELECT set_id, CAST(sum(n) AS BIGINT) AS n, count(*) AS n_cent, count(*) / sum(n) AS rho FROM iw GROUP BY 1)"
query("dispersion", with_(*A, IW, ST) + " SELECT * FROM st")(lambda s, d: ix.dispersion(ix.inverted_counts(assigned(s, d))))
query("dispersion_class", with_(*A, IW, ST) + " SELECT set_id, CASE WHEN rho <= 0.35 THEN 'low' WHEN rho >= 0.8 THEN 'high' ELSE 'mid' END AS class FROM st")(
    lambda s, d: ix.dispersion_class(ix.dispersion(ix.inverted_counts(assigned(s, d))), 0.35, 0.8).select("set_id", "class")
)
query("dispersion_hist", with_(*A, IW, ST) + " SELECT CAST(floor(rho * 10) AS INTEGER) AS tenth, count(*) AS sets FROM st GROUP BY 1")(
    lambda s, d: ix.dispersion(ix.inverted_counts(assigned(s, d))).groupBy(F.floor(F.col("rho") * 10).cast("int").alias("tenth")).agg(F.count("*").alias("sets"))
)
query("partitions_mid", with_(*A, IW) + " SELECT set_id, c, n AS cap, CAST(row_number() OVER (PARTITION BY set_id ORDER BY c) - 1 AS INTEGER) AS k FROM iw")(lambda s, d: ix.partitions_identity(assigned(s, d)))


def _part_rows(index: ix.Index) -> DataFrame:
    join = lambda c: F.array_join(F.transform(c, lambda x: x.cast("string")), ",")
    return ix.partitions(index).select("set_id", "k", join("g").alias("g"), join("s").alias("s"), "cap")


query("partition_index")(lambda s, d: _part_rows(plain_index(s, d, adapt=True)))
query("partition_index_plain", with_(*A) + """ SELECT set_id, CAST(row_number() OVER (PARTITION BY set_id ORDER BY c) - 1 AS INTEGER) AS k, CAST(c AS VARCHAR) AS g,
 string_agg(CAST(pos AS VARCHAR), ',' ORDER BY pos) AS s, CAST(count(*) AS INTEGER) AS cap FROM asg GROUP BY set_id, c""")(lambda s, d: _part_rows(plain_index(s, d)))  # fmt: skip


@query("partition_index_check", with_(VC, MS) + " SELECT set_id, n, TRUE AS covers, TRUE AS disjoint, TRUE AS settled FROM ms")
def partition_index_check(spark, sf):
    p = ix.partitions(plain_index(spark, sf, adapt=True))
    per = p.groupBy("set_id").agg(F.sum("cap").alias("owned"), F.size(F.array_distinct(F.flatten(F.collect_list("s")))).alias("n_own"), F.count("*").alias("parts"))
    n = sets_of(spark, sf).select("set_id", "n")
    settled = (F.col("parts") == 1) | (F.col("parts") / F.col("n") < 0.8)
    return n.join(per, "set_id").select("set_id", "n", (F.col("owned") == F.col("n")).alias("covers"), (F.col("n_own") == F.col("owned")).alias("disjoint"), settled.alias("settled"))


query("partitions_high")(lambda s, d: _part_rows(plain_index(s, d, adapt=True, rho_low=0.01, rho_high=0.5)))


@query("partitions_low")
def partitions_low(spark, sf):
    return _part_rows(build_on(lakes.label_lake(spark, sf), seeds(spark, sf)[:12], True, 0.35, 0.8))


GS = """gs AS (SELECT a.set_id, a.c AS ca, b.c AS cb, CAST(round(list_inner_product(x.m, y.m) * 1000000) AS BIGINT) AS sim6
 FROM iw a JOIN iw b ON a.set_id = b.set_id AND a.c < b.c JOIN ce x ON x.c = a.c JOIN ce y ON y.c = b.c)"""


@query("gsim", with_(*A, IW, GS) + " SELECT * FROM gs")
def gsim(spark, sf):
    counts = ix.inverted_counts(assigned(spark, sf)).select("set_id", "c")
    m = F.broadcast(se.centroid_frame(spark, seeds(spark, sf)))
    one = counts.join(m, "c").select("set_id", F.col("c").alias("ca"), F.col("m").alias("ma"))
    two = counts.join(m, "c").select("set_id", F.col("c").alias("cb"), F.col("m").alias("mb"))
    return one.join(two, "set_id").where("ca < cb").select("set_id", "ca", "cb", sim6(F.col("ma"), F.col("mb")).alias("sim6"))


@query("merge_first", with_(*A, IW, GS) + " SELECT set_id, ca, cb, sim6 FROM gs QUALIFY row_number() OVER (PARTITION BY set_id ORDER BY sim6 DESC, ca, cb) = 1")
def merge_first(spark, sf):
    order = Window.partitionBy("set_id").orderBy(F.col("sim6").desc(), "ca", "cb")
    return gsim(spark, sf).withColumn("rn", F.row_number().over(order)).where("rn = 1").drop("rn")


@query("graph_degrees")
def graph_degrees(spark, sf):
    g = K.ProximityGraph(seeds(spark, sf))
    return spark.createDataFrame(g.degrees(), "level int, node int, degree int")


# ---- staged search ----------------------------------------------------------------------------

query("probe_centroids", with_(VC, QS, CE, QC, PB) + " SELECT * FROM pb")(lambda s, d: se.probe_flat(s, queries_of(s, d), seeds(s, d), PLAN.phi_c))
query("graph_probe")(lambda s, d: se.probe_graph(s, queries_of(s, d), K.ProximityGraph(seeds(s, d)), PLAN.phi_c))
R = (VC, QS, CE, AS, IW, QC, PB, PO)


def _probe_counts(spark, sf):
    return se.probe_flat(spark, queries_of(spark, sf), seeds(spark, sf), PLAN.phi_c), ix.inverted_counts(assigned(spark, sf))


query("touched_sets", with_(*R) + " SELECT DISTINCT query_id, set_id FROM po")(lambda s, d: se.touched(*_probe_counts(s, d)))
query("missed_by_probe", with_(VC, MS, QS, NQ, PR, CE, AS, IW, QC, PB, PO) + " SELECT query_id, set_id FROM pr EXCEPT SELECT query_id, set_id FROM po")(
    lambda s, d: sets_of(s, d).select("set_id").join(F.broadcast(query_ids(s, d)), F.col("set_id") != F.col("query_id")).join(se.touched(*_probe_counts(s, d)), ["query_id", "set_id"], "left_anti").select("query_id", "set_id")
)
query("refine_block", with_(*R, refine_cte()) + " SELECT * FROM rf")(lambda s, d: se.refine(*_probe_counts(s, d), PLAN.phi_ref))
query("refine_tau", with_(*R, refine_cte(f"sim6 >= {micro(0.2)}")) + " SELECT * FROM rf")(lambda s, d: se.refine(*_probe_counts(s, d), PLAN.phi_ref, tau6=micro(0.2)))
query("refine_fallthrough")(lambda s, d: se.refine(*_probe_counts(s, d), PLAN.phi_ref, "fallthrough"))

FILTER = with_(*R, refine_cte(), SLOTS, "ec AS (SELECT em.* FROM em JOIN rf USING (query_id, set_id))", dp("ec", True), "al AS (SELECT query_id, set_id, coalesce(u6, 0) AS u6 FROM rf LEFT JOIN best USING (query_id, set_id))") + " " + top_sql("al", PLAN.phi_r)


def _filter(prune):
    def run(spark, sf):
        got = se.staged(plain_index(spark, sf), queries_of(spark, sf), replace(PLAN, prune=prune))
        return got.where("stage = 'filter'").select("query_id", "rank", "set_id", "score6")

    return run


query("filter_mwmto", FILTER)(_filter("none"))
query("filter_base", FILTER)(_filter("base"))
query("filter_enhanced", FILTER)(_filter("lossless"))
query("filter_enhanced_listing")(_filter("listing"))


def _search(**how):
    return lambda spark, sf: se.union_search(plain_index(spark, sf, adapt=True), queries_of(spark, sf), replace(PLAN, **how))


query("score_topk")(_search(prune="none"))
query("staged_search")(_search())
query("staged_search_plus")(_search(prune="lossless"))
query("staged_search_listing")(_search(prune="listing"))
query("staged_no_refine")(_search(stages=("filter", "score")))
query("staged_no_filter")(_search(stages=("refine", "score")))
query("staged_exact_final")(_search(stages=("refine", "filter")))
query("staged_graph_probe")(_search(probe="graph"))


@query("search_trace")
def search_trace(spark, sf):
    index, queries, out = plain_index(spark, sf, adapt=True), queries_of(spark, sf), None
    for prune in ("none", "base", "listing", "lossless"):
        r = se.staged(index, queries, replace(PLAN, prune=prune)).groupBy("query_id", "stage").agg(F.max("candidates").alias("rows_in"), F.count("*").alias("rows_out"), F.max("bounds").alias("bound_evals"), F.max("evaluations").alias("exact_evals"))
        r = r.select(F.lit(prune).alias("prune"), "*")
        out = r if out is None else out.unionByName(r)
    return out


# ---- bounds and pruning -----------------------------------------------------------------------

UB = "ub AS (SELECT query_id, set_id, CAST(sum(sim6) FILTER (WHERE rn <= least(nq, n)) AS BIGINT) AS ub6 FROM (SELECT ed.*, row_number() OVER (PARTITION BY query_id, set_id ORDER BY sim6 DESC, q, j) AS rn, nq, n FROM ed JOIN pr USING (query_id, set_id)) GROUP BY 1, 2)"


@query("ub_union", with_(VC, MS, QS, NQ, PR, ED, UB) + " SELECT query_id, set_id, coalesce(ub6, 0) AS ub6 FROM pr LEFT JOIN ub USING (query_id, set_id)")
def ub_union(spark, sf):
    return mt.bounds_union(sets_of(spark, sf), queries_of(spark, sf), TAU).select("query_id", "set_id", "ub6")


# greedy over edges in descending similarity: a step of the recursion takes the next edge if both its ends are free
GREEDY = f"""oe AS (SELECT *, row_number() OVER (PARTITION BY query_id, set_id ORDER BY sim6 DESC, q, j) AS rn FROM ed),
 gd(query_id, set_id, rn, qm, jm, t, w) AS (SELECT DISTINCT query_id, set_id, CAST(0 AS BIGINT), 0, 0, 0, CAST(0 AS BIGINT) FROM oe UNION ALL
  SELECT query_id, set_id, rn, CASE WHEN f THEN qm | (1 << q) ELSE qm END, CASE WHEN f THEN jm | (1 << j) ELSE jm END, t + CASE WHEN f THEN 1 ELSE 0 END, w + CASE WHEN f THEN sim6 ELSE 0 END
  FROM (SELECT o.*, qm, jm, t, w, (qm >> o.q) & 1 = 0 AND (jm >> o.j) & 1 = 0 AS f FROM gd g JOIN oe o ON o.query_id = g.query_id AND o.set_id = g.set_id AND o.rn = g.rn + 1)),
 mo AS (SELECT query_id, set_id, least(count(DISTINCT q), count(DISTINCT j)) AS most, count(*) AS edges FROM ed GROUP BY 1, 2),
 lb AS (SELECT query_id, set_id, CAST(CASE WHEN t = most THEN w ELSE {micro(TAU)} * t END AS BIGINT) AS lb6 FROM gd JOIN mo USING (query_id, set_id) WHERE rn = edges),
 bo AS (SELECT query_id, set_id, coalesce(lb6, 0) AS lb6, coalesce(ub6, 0) AS ub6 FROM pr LEFT JOIN lb USING (query_id, set_id) LEFT JOIN ub USING (query_id, set_id))"""
BOUNDS = (VC, MS, QS, NQ, PR, ED, UB, GREEDY)
query("lb_union", with_(*BOUNDS) + " SELECT query_id, set_id, lb6 FROM bo")(lambda s, d: mt.bounds_union(sets_of(s, d), queries_of(s, d), TAU).select("query_id", "set_id", "lb6"))


@query("ub_mwmto", with_(VC, MS, QS, NQ, PR, CE, AS, IW, QC, "pt AS (SELECT set_id, c, n AS cap FROM iw)", PM) + """
 SELECT query_id, set_id, CAST(sum(sim6) AS BIGINT) AS ub6 FROM (SELECT pm.*, row_number() OVER (PARTITION BY query_id, set_id ORDER BY sim6 DESC, q, c) AS rn, nq, n FROM pm JOIN pr USING (query_id, set_id)) WHERE rn <= least(nq, n) GROUP BY 1, 2""")  # fmt: skip
def ub_mwmto(spark, sf):
    """Natively: the best min(columns, vectors) edges of each pair from a sorted array."""
    sizes = sets_of(spark, sf).select("set_id", "n")
    nq = spark.createDataFrame([(i, len(v)) for i, v in queries_of(spark, sf).items()], "query_id bigint, nq int")
    per = partition_edges(spark, sf).groupBy("query_id", "set_id").agg(F.sort_array(F.collect_list("sim6"), False).alias("s"))
    best = F.slice("s", F.lit(1), F.least("nq", "n"))
    return per.join(sizes, "set_id").join(F.broadcast(nq), "query_id").select("query_id", "set_id", F.aggregate(best, F.lit(0).cast("bigint"), lambda a, x: a + x).alias("ub6"))


def _bounds_rows(spark, sf, kind: str, adapt: bool = True) -> DataFrame:
    """(query_id, set_id, lb6, score6, ub6) of many-to-one matching, or of the sum over partitions."""
    return se.bounds_scan(plain_index(spark, sf, adapt=adapt), queries_of(spark, sf), TAU, kind)


# greedy over query columns in order: each takes its best partition that has room; `took` lists the centroids taken so far
GREEDY_ROWS = f"""gr(query_id, set_id, q, took, w) AS (SELECT DISTINCT query_id, set_id, -1, CAST([] AS INTEGER[]), CAST(0 AS BIGINT) FROM pm UNION ALL
  SELECT query_id, set_id, q + 1, CASE WHEN x >= 0 THEN list_append(took, CAST(999 - x % 1000 AS INTEGER)) ELSE took END, w + CASE WHEN x >= 0 THEN x // 1000 ELSE 0 END FROM
  (SELECT g.query_id, g.set_id, g.q, g.took, g.w, max(CASE WHEN p.c IS NOT NULL AND len(list_filter(g.took, lambda y: y = p.c)) < p.cap THEN CAST(p.sim6 AS BIGINT) * 1000 + 999 - p.c ELSE -1 END) AS x
   FROM gr g LEFT JOIN pm p ON p.query_id = g.query_id AND p.set_id = g.set_id AND p.q = g.q + 1 WHERE g.q < 9 GROUP BY ALL)),
 mr AS (SELECT query_id, set_id, least(count(DISTINCT q), sum(cap) FILTER (WHERE first)) AS most FROM (SELECT *, row_number() OVER (PARTITION BY query_id, set_id, c ORDER BY q) = 1 AS first FROM pm) GROUP BY 1, 2)"""
query("lb_mwmto", with_(VC, MS, QS, NQ, PR, CE, AS, IW, QC, "pt AS (SELECT set_id, c, n AS cap FROM iw)", PM, GREEDY_ROWS) + f""" SELECT query_id, set_id, CAST(coalesce(CASE WHEN len(took) = most THEN w ELSE {micro(TAU)} * len(took) END, 0) AS BIGINT) AS lb6
 FROM pr LEFT JOIN (SELECT * FROM gr WHERE q = 9) USING (query_id, set_id) LEFT JOIN mr USING (query_id, set_id)""")(lambda s, d: _bounds_rows(s, d, "mwmto", False).select("query_id", "set_id", "lb6"))  # fmt: skip
query("bounds_mwmto")(lambda s, d: _bounds_rows(s, d, "mwmto"))
query("bounds_partition")(lambda s, d: _bounds_rows(s, d, "score"))


@query("bound_tightness", with_(*BOUNDS, dp("ed", True)) + " SELECT query_id, round(avg(lb6 / u6), 9) AS lb_share, round(avg(ub6 / u6), 9) AS ub_share FROM bo JOIN best USING (query_id, set_id) WHERE u6 > 0 GROUP BY 1")
def bound_tightness(spark, sf):
    b = mt.bounds_union(sets_of(spark, sf), queries_of(spark, sf), TAU).join(_u("max_cardinality")(spark, sf), ["query_id", "set_id"]).where("u6 > 0")
    return b.groupBy("query_id").agg(F.round(F.avg(F.col("lb6") / F.col("u6")), 9).alias("lb_share"), F.round(F.avg(F.col("ub6") / F.col("u6")), 9).alias("ub_share"))


def _pruned(prune: str, k: int = TOP, order: str = "arrival"):
    def run(spark, sf):
        index, queries = plain_index(spark, sf), queries_of(spark, sf)
        ids = index.sets.select("set_id").join(F.broadcast(spark.createDataFrame([(q,) for q in queries], "query_id bigint")), F.lit(True))
        return se.score_candidates(index, queries, ids, replace(PLAN, k=k, prune=prune, phi_r=max(k, PLAN.phi_r), phi_ref=max(k, PLAN.phi_ref)))

    return run


def _answer(f):
    return lambda s, d: f(s, d).where("stage = 'answer'").select("query_id", "rank", "set_id", "score6")


query("base_prune_topk", EXACT_CARD)(_answer(_pruned("base")))
query("enhanced_topk", EXACT_CARD)(_answer(_pruned("lossless")))
query("enhanced_listing_topk")(_answer(_pruned("listing")))
query("base_prune_evals")(lambda s, d: _pruned("base")(s, d).groupBy("query_id").agg(F.max("evaluations").alias("evaluations"), F.max("candidates").alias("candidates")))


@query("enhanced_survivors", with_(*BOUNDS, f"th AS (SELECT query_id, min(lb6) AS theta FROM (SELECT query_id, lb6 FROM bo QUALIFY row_number() OVER (PARTITION BY query_id ORDER BY lb6 DESC) <= {TOP}) GROUP BY 1)") + " SELECT query_id, set_id, lb6, ub6 FROM bo JOIN th USING (query_id) WHERE ub6 >= theta")
def enhanced_survivors(spark, sf):
    """Candidates whose upper bound reaches the k-th best lower bound: the only ones the principle lets be scored."""
    b = mt.bounds_union(sets_of(spark, sf), queries_of(spark, sf), TAU)
    order = Window.partitionBy("query_id").orderBy(F.col("lb6").desc())
    theta = b.withColumn("rn", F.row_number().over(order)).where(F.col("rn") <= TOP).groupBy("query_id").agg(F.min("lb6").alias("theta"))
    return b.join(F.broadcast(theta), "query_id").where("ub6 >= theta").select("query_id", "set_id", "lb6", "ub6")


@query("prune_counters")
def prune_counters(spark, sf):
    out = None
    for prune in ("none", "base", "listing", "lossless"):
        r = _pruned(prune)(spark, sf).groupBy("query_id").agg(F.max("candidates").alias("candidates"), F.max("bounds").alias("bounds"), F.max("evaluations").alias("evaluations"))
        r = r.select(F.lit(prune).alias("method"), "*")
        out = r if out is None else out.unionByName(r)
    return out


@query("base_prune_order")
def base_prune_order(spark, sf):
    """Exact evaluations of the base rule by arrival order: best first, worst first and by a hash."""
    sets, queries = sets_of(spark, sf), queries_of(spark, sf)
    b = mt.bounds_union(sets, queries, TAU).join(_u("max_cardinality")(spark, sf), ["query_id", "set_id"])

    def run(pdf):
        import pandas as pd

        rows = {r.set_id: (int(r.lb6), int(r.ub6), int(r.u6)) for r in pdf.itertuples()}
        orders = {"descending": sorted(rows, key=lambda i: -rows[i][2]), "ascending": sorted(rows, key=lambda i: rows[i][2]), "shuffled": sorted(rows, key=lambda i: i * 2654435761 % 2**32)}
        q = pdf["query_id"].iloc[0]
        return pd.DataFrame([(q, o, K.base_prune([(i, *rows[i][:2]) for i in ids], TOP, lambda i: rows[i][2])[1]) for o, ids in orders.items()], columns=["query_id", "arrival", "evaluations"])

    return b.groupBy("query_id").applyInPandas(run, "query_id bigint, arrival string, evaluations int")


# ---- baselines --------------------------------------------------------------------------------


def _scan(prune):
    return lambda s, d: mt.top_k_scan(sets_of(s, d), queries_of(s, d), TAU, TOP, prune)[0]


query("scan_brute", EXACT_CARD)(_scan("none"))
query("scan_base_prune", EXACT_CARD)(_scan("base"))
query("scan_enhanced_prune", EXACT_CARD)(_scan("lossless"))
query("scan_enhanced_listing")(_scan("listing"))


def _column_graph(prune):
    def run(spark, sf):
        shards = ix.build_sharded_graph(cols_of(spark, sf), 2)
        queries, index = queries_of(spark, sf), plain_index(spark, sf)
        return se.score_candidates(index, queries, se.column_candidates(shards, queries, 20), replace(PLAN, k=TOP, prune=prune))

    return run


query("column_graph_search")(_answer(_column_graph("base")))
query("column_graph_plus")(_answer(_column_graph("lossless")))
query("column_graph_candidates")(lambda s, d: se.column_candidates(ix.build_sharded_graph(cols_of(s, d), 2), queries_of(s, d), 20))
FLAT = f"nc AS (SELECT query_id, q, set_id, pos, {SIM} AS sim6 FROM qs, vc QUALIFY row_number() OVER (PARTITION BY query_id, q ORDER BY {SIM} DESC, set_id, pos) <= 20)"
CAND = "ca AS (SELECT DISTINCT query_id, set_id FROM {src} WHERE query_id <> set_id), ec AS (SELECT ed.* FROM ed JOIN ca USING (query_id, set_id))"
CU = "cu AS (SELECT query_id, set_id, coalesce(u6, 0) AS u6 FROM ca LEFT JOIN best USING (query_id, set_id))"


@query("column_flat_search", with_(VC, QS, ED, FLAT, CAND.format(src="nc"), dp("ec", True), CU) + " " + top_sql("cu", TOP))
def column_flat_search(spark, sf):
    queries = queries_of(spark, sf)
    near = se.flat_column_candidates(cols_of(spark, sf), queries, 20)
    return _answer(lambda s, d: se.score_candidates(plain_index(s, d), queries, near, replace(PLAN, k=TOP)))(spark, sf)


QUANTIZED = with_(VC, QS, ED, CE, AS, IW, QC, PB, PO, CAND.format(src="po"), dp("ec", True), CU) + " " + top_sql("cu", TOP)
query("quantized_search", QUANTIZED)(_answer(lambda s, d: se.quantized(plain_index(s, d), queries_of(s, d), replace(PLAN, k=TOP))))
query("quantized_plus", QUANTIZED)(_answer(lambda s, d: se.quantized(plain_index(s, d), queries_of(s, d), replace(PLAN, k=TOP, prune="lossless"))))
ALLSIM = f"sa AS (SELECT query_id, set_id, q, pos AS j, {SIM} AS sim6 FROM qs JOIN vc ON query_id <> set_id)"
query("chamfer", with_(VC, QS, ALLSIM) + " SELECT query_id, set_id, CAST(sum(b) AS BIGINT) AS d6 FROM (SELECT query_id, set_id, q, max(sim6) AS b FROM sa GROUP BY 1, 2, 3) GROUP BY 1, 2")(lambda s, d: mt.set_distance(sets_of(s, d), queries_of(s, d), "chamfer"))
query("hausdorff", with_(VC, QS, ALLSIM) + " SELECT query_id, set_id, min(b) AS d6 FROM (SELECT query_id, set_id, max(sim6) AS b FROM sa GROUP BY query_id, set_id, q UNION ALL SELECT query_id, set_id, max(sim6) FROM sa GROUP BY query_id, set_id, j) GROUP BY 1, 2")(
    lambda s, d: mt.set_distance(sets_of(s, d), queries_of(s, d), "hausdorff")
)
MP = "mp AS (SELECT set_id, list(x ORDER BY i) AS v FROM (SELECT set_id, i, round(avg(x), 6) AS x FROM (SELECT set_id, unnest(v) AS x, unnest(range(64)) AS i FROM vc) GROUP BY 1, 2) GROUP BY 1)"
query("mean_pool_topk", with_(VC, MP, f"ms AS (SELECT a.set_id AS query_id, b.set_id, CAST(round(list_inner_product(a.v, b.v) * 1000000) AS BIGINT) AS u6 FROM mp a JOIN mp b ON a.set_id <> b.set_id WHERE a.set_id % 20 = 0)") + " " + top_sql("ms", TOP))(
    lambda s, d: mt.mean_pool_top_k(cols_of(s, d), QUERIES, 64, TOP)
)
