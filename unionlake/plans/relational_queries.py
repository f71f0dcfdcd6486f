"""Operators around the search: sources, joins, aggregations, windows, sets and scalar functions on the lakes, each with its SQL."""

from __future__ import annotations

from dataclasses import replace
from functools import reduce

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from unionlake.functions import vectors as vf
from unionlake.operators import index as ix
from unionlake.operators import matching as mt
from unionlake.operators import search as se
from unionlake.plans import search_queries as sq
from unionlake.sources import lakes
from unionlake.sources.shared import folder

REGISTRY: dict = {}
SQL: dict[str, str] = {}
W = sq.with_


def query(key: str, sql: str | None = None):
    def add(f):
        REGISTRY[key] = f
        if sql:
            SQL[key] = sql
        return f

    return add


def t(spark, sf, name) -> DataFrame:
    return lakes.table(spark, sf, name)


# ---- sources and sinks ------------------------------------------------------------------------


@query("scan_prune", "SELECT c_custkey, c_acctbal FROM customer WHERE c_acctbal > 9000")
def scan_prune(spark, sf):
    return t(spark, sf, "customer").where(F.col("c_acctbal") > 9000).select("c_custkey", "c_acctbal")


CATALOG = ["region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations"]


@query("scan_catalog", " UNION ALL ".join(f"SELECT '{n}' AS table_name, count(*) AS n_rows FROM {n}" for n in CATALOG))
def scan_catalog(spark, sf):
    out = None
    for n in CATALOG:
        one = t(spark, sf, n).agg(F.count("*").alias("n_rows")).select(F.lit(n).alias("table_name"), "n_rows")
        out = one if out is None else out.unionByName(one)
    return out


def _through(spark, df: DataFrame, fmt: str, schema: str, **options) -> DataFrame:
    """df written to the shared folder in a format and read back with its schema; bad rows are kept as nulls."""
    path = folder(spark, fmt)
    df.write.options(**options).format(fmt).save(path)
    return spark.read.schema(schema).options(**options).option("mode", "PERMISSIVE").format(fmt).load(path)


query("csv_roundtrip", "SELECT n_nationkey, n_name, n_regionkey FROM nation")(lambda s, d: _through(s, t(s, d, "nation"), "csv", "n_nationkey int, n_name string, n_regionkey int", header="true"))
query("json_roundtrip", "SELECT n_nationkey, n_name, n_regionkey FROM nation")(lambda s, d: _through(s, t(s, d, "nation"), "json", "n_nationkey int, n_name string, n_regionkey int"))
query("orc_roundtrip", "SELECT r_regionkey, r_name FROM region")(lambda s, d: _through(s, t(s, d, "region"), "orc", "r_regionkey int, r_name string"))
query("page_blocks", "SELECT page_id AS set_id, CAST(len(regexp_extract_all(html, '<p[^>]*>(.*?)</p>', 1)) AS BIGINT) AS blocks FROM pages WHERE len(regexp_extract_all(html, '<p[^>]*>(.*?)</p>', 1)) > 0")(
    lambda s, d: lakes.page_blocks(s, d).groupBy("set_id").agg(F.count("*").alias("blocks"))
)


@query("index_roundtrip", W(sq.VC, sq.CE, sq.AS, sq.IW) + " SELECT * FROM iw")
def index_roundtrip(spark, sf):
    """Postings written in ranges of c, sorted inside, and read back."""
    counts = ix.inverted_counts(sq.assigned(spark, sf)).withColumn("c_bucket", F.col("c") % 4)
    ordered = counts.repartitionByRange(4, "c_bucket", "c").sortWithinPartitions("c", "set_id")
    return _through(spark, ordered, "parquet", "c int, set_id bigint, n bigint, c_bucket int").select("c", "set_id", "n")


@query("sql_dot", W(sq.VC) + " SELECT a.vec_id, CAST(round(list_inner_product(a.v, b.v) * 1000000) AS BIGINT) AS sim6 FROM vc a, vc b WHERE b.vec_id = 0")
def sql_dot(spark, sf):
    vf.register(spark)
    e = t(spark, sf, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("v"))
    one = F.broadcast(e.where("vec_id = 0").select(F.col("v").alias("w")))
    return e.join(one, F.lit(True)).selectExpr("vec_id", "vec_sim6(v, w) AS sim6")


@query("sql_union_search", sq.EXACT_CARD)
def sql_union_search(spark, sf):
    """Union search from SQL: a table function takes the packed edges as a table argument, cut by query, with k and the threshold as parameters."""
    from pyspark.sql.functions import udtf

    from unionlake.operators import kernels as K

    @udtf(returnType="query_id bigint, rank int, set_id bigint, score6 bigint")
    class UnionSearch:
        def __init__(self):
            self.query_id, self.top = None, None

        def eval(self, row, k: int, tau: float):
            import numpy as np

            if self.top is None:
                self.query_id, self.top = row["query_id"], K.TopK(k)
            e = [x for x in row["e"] if x["sim6"] >= round(tau * 1e6)]
            m = np.full((max((x["q"] for x in e), default=-1) + 1, max((x["j"] for x in e), default=-1) + 1), K.NO_EDGE)
            for x in e:
                m[x["q"], x["j"]] = x["sim6"]
            self.top.offer(row["set_id"], K.assign(m, np.ones(m.shape[1], np.int64), True)[1])

        def terminate(self):
            if self.top is not None:
                for rank, (set_id, score) in enumerate(self.top.answer(), 1):
                    yield self.query_id, rank, set_id, score

    spark.udtf.register("union_search", UnionSearch)
    e = sq.edges_tau(spark, sf).groupBy("query_id", "set_id").agg(F.collect_list(F.struct("q", "j", "sim6")).alias("e"))
    pairs = sq.sets_of(spark, sf).select("set_id").join(F.broadcast(sq.query_ids(spark, sf)), F.col("set_id") != F.col("query_id"))
    empty = F.array().cast("array<struct<q:int,j:int,sim6:bigint>>")
    pairs.join(e, ["query_id", "set_id"], "left").select("query_id", "set_id", F.coalesce("e", empty).alias("e")).createOrReplaceTempView("packed_edges")
    return spark.sql("SELECT * FROM union_search(TABLE(packed_edges) PARTITION BY (query_id), :k, :tau)", args={"k": sq.TOP, "tau": sq.TAU})


# ---- filters ----------------------------------------------------------------------------------

query("filter_predicates", "SELECT p_partkey, p_name FROM part WHERE p_size BETWEEN 5 AND 20 AND p_brand IN ('Brand#11','Brand#22') OR p_type LIKE 'ECONOMY%' AND regexp_matches(p_name, '[aeiou]{2}') AND p_retailprice IS NOT NULL")(
    lambda s, d: t(s, d, "part").where((F.col("p_size").between(5, 20) & F.col("p_brand").isin("Brand#11", "Brand#22")) | (F.col("p_type").like("ECONOMY%") & F.col("p_name").rlike("[aeiou]{2}") & F.col("p_retailprice").isNotNull())).select("p_partkey", "p_name")
)
query("sets_without_edge", W(sq.VC, sq.MS, sq.QS, sq.NQ, sq.PR, sq.ED) + " SELECT query_id, set_id FROM pr WHERE NOT EXISTS (SELECT 1 FROM ed WHERE ed.query_id = pr.query_id AND ed.set_id = pr.set_id)")(
    lambda s, d: sq._u("max_cardinality")(s, d).select("query_id", "set_id").join(sq.edges_tau(s, d).select("query_id", "set_id"), ["query_id", "set_id"], "left_anti")
)
query("md5_sample", "SELECT vec_id FROM embeddings WHERE substr(md5(CAST(vec_id AS VARCHAR)), 1, 1) < '4'")(lambda s, d: t(s, d, "embeddings").where(F.substring(F.md5(F.col("vec_id").cast("string")), 1, 1) < "4").select("vec_id"))
LINES = "ln AS (SELECT doc_id AS set_id, CAST(len(list_filter(string_split(text, chr(10)), lambda x: trim(x) <> '')) AS BIGINT) AS n FROM documents)"


def _lines(s, d):
    n = F.size(F.filter(F.split("text", "\n"), lambda x: F.trim(x) != "")).cast("bigint")
    return t(s, d, "documents").select(F.col("doc_id").alias("set_id"), n.alias("n"))


query("wide_query_selection", W(LINES) + " SELECT * FROM ln WHERE n > 15")(lambda s, d: _lines(s, d).where("n > 15"))

# ---- joins ------------------------------------------------------------------------------------

query("cands_join_sets", W(sq.VC, sq.MS, sq.QS, sq.CE, sq.AS, sq.IW, sq.QC, sq.PB, sq.PO, sq.refine_cte()) + " SELECT query_id, set_id, n FROM rf JOIN ms USING (set_id)")(
    lambda s, d: sq.REGISTRY["refine_block"](s, d).select("query_id", "set_id").join(sq.sets_of(s, d).select("set_id", "n").hint("MERGE"), "set_id").select("query_id", "set_id", "n")
)
query("size_compatible", W(sq.VC, sq.MS, sq.QS, sq.NQ) + " SELECT query_id, set_id FROM nq JOIN ms ON n BETWEEN nq / 2.0 AND nq * 2 AND set_id <> query_id")(lambda s, d: size_compatible(s, d))


def size_compatible(spark, sf):
    """A range join by bins: both sides are filed under the power of two of their size, and a query looks in three bins."""
    sets = sq.sets_of(spark, sf).select("set_id", "n", F.floor(F.log2("n")).cast("int").alias("bin"))
    q = spark.createDataFrame([(i, len(v)) for i, v in sq.queries_of(spark, sf).items()], "query_id bigint, nq int")
    q = q.withColumn("bin", F.explode(F.array(*[F.floor(F.log2("nq")).cast("int") + i for i in (-1, 0, 1)])))
    return sets.join(F.broadcast(q), "bin").where((F.col("n") * 2 >= F.col("nq")) & (F.col("n") <= 2 * F.col("nq")) & (F.col("set_id") != F.col("query_id"))).select("query_id", "set_id")


def _two(s, d):
    """The exact answer and that of the quantized baseline; both scan the same sets for the same queries."""
    cols, queries = sq.cols_of(s, d), sq.queries_of(s, d)
    sets, c = lakes.vec_sets(cols), sq.seeds(s, d)
    exact = mt.top_k_exact(sets, queries, sq.TAU, sq.TOP)
    return exact, se.quantized_answer(sets, ix.inverted_counts(ix.assign(cols, c)), c, queries, replace(sq.PLAN, k=sq.TOP))


def _compare(s, d):
    a, b = _two(s, d)
    a, b = a.select("query_id", "set_id", F.col("rank").alias("rank_exact")), b.select("query_id", "set_id", F.col("rank").alias("rank_quantized"))
    return a.join(b, ["query_id", "set_id"], "full")


TWO = (sq.VC, sq.MS, sq.QS, sq.NQ, sq.PR, sq.ED, sq.dp("ed", True), sq.ALL_U, f"ex AS ({sq.top_sql('allu', sq.TOP)})", sq.CE, sq.AS, sq.IW, sq.QC, sq.PB, sq.PO, "ca AS (SELECT DISTINCT query_id, set_id FROM po WHERE query_id <> set_id)", "cu AS (SELECT * FROM allu JOIN ca USING (query_id, set_id))", f"qz AS ({sq.top_sql('cu', sq.TOP)})")
query("compare_answers", W(*TWO) + " SELECT query_id, set_id, ex.rank AS rank_exact, qz.rank AS rank_quantized FROM ex FULL JOIN qz USING (query_id, set_id)")(_compare)
query("answers_intersect", W(*TWO) + " SELECT query_id, set_id FROM ex INTERSECT SELECT query_id, set_id FROM qz")(lambda s, d: (lambda x: x[0].select("query_id", "set_id").intersect(x[1].select("query_id", "set_id")))(_two(s, d)))
query("answers_except", W(*TWO) + " SELECT query_id, set_id FROM ex EXCEPT SELECT query_id, set_id FROM qz")(lambda s, d: (lambda x: x[0].select("query_id", "set_id").exceptAll(x[1].select("query_id", "set_id")))(_two(s, d)))


def recall(truth: DataFrame, answer: DataFrame) -> DataFrame:
    """(query_id, recall): the share of the true sets that were returned."""
    hit = answer.select("query_id", "set_id", F.lit(1).alias("hit"))
    return truth.join(hit.hint("SHUFFLE_HASH"), ["query_id", "set_id"], "left").groupBy("query_id").agg((F.count("hit") / F.count("*")).alias("recall"))


query("recall_quantized", W(*TWO) + " SELECT query_id, count(qz.set_id) / count(*) AS recall FROM ex LEFT JOIN qz USING (query_id, set_id) GROUP BY 1")(lambda s, d: recall(*_two(s, d)))
query("recall_staged")(lambda s, d: recall(sq.REGISTRY["topk_exact_card"](s, d).where("rank <= 5"), sq.REGISTRY["staged_search"](s, d)))


@query("recall_tie", W(*TWO) + f", kt AS (SELECT query_id, min(score6) AS least FROM ex GROUP BY 1) SELECT query_id, count(*) FILTER (WHERE score6 >= least) / {sq.TOP} AS recall FROM qz JOIN kt USING (query_id) GROUP BY 1")
def recall_tie(spark, sf):
    ex, qz = _two(spark, sf)
    return qz.join(F.broadcast(ex.groupBy("query_id").agg(F.min("score6").alias("least"))), "query_id").groupBy("query_id").agg((F.count_if(F.col("score6") >= F.col("least")) / sq.TOP).alias("recall"))


@query("all_pairs_union", W(sq.VC, f"ed AS (SELECT a.set_id AS query_id, b.set_id, a.pos AS q, b.pos AS j, CAST(round(list_inner_product(a.v, b.v) * 1000000) AS BIGINT) AS sim6 FROM vc a JOIN vc b ON a.set_id < b.set_id WHERE CAST(round(list_inner_product(a.v, b.v) * 1000000) AS BIGINT) >= {vf.micro(0.25)})", sq.dp("ed", True)) + " SELECT * FROM best")
def all_pairs_union(spark, sf):
    """All pairs of sets with an edge at .25 or more, a block of sets as queries at a time."""
    c = sq.cols_of(spark, sf)
    sets = lakes.vec_sets(c)
    blocks = [mt.unionability(sets, queries, 0.25) for queries in mt.query_blocks(c)]
    return reduce(DataFrame.unionByName, blocks).where("query_id < set_id and t > 0")


VERSIONS = [("2024-01-01", 1), ("2024-01-09", 2), ("2024-01-20", 3)]


@query("asof_index_version", "SELECT event_id, CAST(max(v) AS INTEGER) AS version FROM events JOIN (VALUES (TIMESTAMP '2024-01-01',1),(TIMESTAMP '2024-01-09',2),(TIMESTAMP '2024-01-20',3)) x(since, v) ON since <= ts GROUP BY 1")
def asof_index_version(spark, sf):
    """The index version in force at each event; versions are a short list, so they are broadcast and the latest is an argmax."""
    v = spark.createDataFrame(VERSIONS, "since string, version int").select(F.col("since").cast("timestamp_ntz").alias("since"), "version")
    e = t(spark, sf, "events").join(F.broadcast(v), F.col("since") <= F.col("ts"))
    return e.groupBy("event_id").agg(F.max_by("version", "since").alias("version"))


query("explode_sets", W(sq.VC) + " SELECT set_id, pos, CAST(round(v[1] * 1000000) AS BIGINT) AS first6 FROM vc")(
    lambda s, d: sq.sets_of(s, d).select("set_id", F.explode(F.sequence(F.lit(0), F.col("n") - 1)).alias("pos"), "flat").select("set_id", F.col("pos").cast("int").alias("pos"), F.round(F.element_at("flat", (F.col("pos") * 64 + 1).cast("int")) * 1e6).cast("bigint").alias("first6"))
)


@query("salted_postings", W(sq.VC, sq.QS, sq.CE, sq.AS, sq.IW, sq.QC, sq.PB, sq.PO) + " SELECT query_id, set_id, q, c FROM po")
def salted_postings(spark, sf):
    """Postings joined by (centroid, salt): a hot list is spread over eight keys."""
    probe, counts = sq._probe_counts(spark, sf)
    left = counts.withColumn("salt", F.pmod("set_id", F.lit(8)).cast("int"))
    right = probe.withColumn("salt", F.explode(F.array(*[F.lit(i) for i in range(8)])))
    return left.join(right, ["c", "salt"]).where("set_id != query_id").select("query_id", "set_id", "q", "c")


@query("cogroup_union", sq.with_(sq.VC, sq.MS, sq.QS, sq.NQ, sq.PR, sq.ED, sq.dp("ed", True)) + " SELECT query_id, set_id, t, u6 FROM best")
def cogroup_union(spark, sf):
    """Edges of a set meet the set's own size without packing: a cogrouped map of edges and sets, all queries of a set at once."""
    import numpy as np

    from unionlake.operators import kernels as K

    def solve(left, right):
        import pandas as pd

        ids, at = np.unique(left["query_id"].to_numpy(), return_inverse=True)
        if not len(ids):
            return pd.DataFrame({"query_id": [], "set_id": [], "t": [], "u6": []})
        m = np.full((len(ids), int(left["q"].max()) + 1, int(right["n"].iloc[0])), K.NO_EDGE)
        m[at, left["q"].to_numpy(), left["j"].to_numpy()] = left["sim6"].to_numpy()
        n, u, _ = K.assign_many(m, np.ones(m.shape[2], np.int64), True)
        return pd.DataFrame({"query_id": ids, "set_id": left["set_id"].iloc[0], "t": n, "u6": u})

    e, sizes = sq.edges_tau(spark, sf), sq.cols_of(spark, sf).groupBy(F.col("set_id").alias("si")).agg((F.max("pos") + 1).alias("n"))
    return e.groupBy("set_id").cogroup(sizes.groupBy("si")).applyInPandas(solve, "query_id bigint, set_id bigint, t int, u6 bigint")


@query("udaf_unionability", sq.with_(sq.VC, sq.MS, sq.QS, sq.NQ, sq.PR, sq.ED, sq.dp("ed", False)) + " SELECT query_id, set_id, u6 FROM best")
def udaf_unionability(spark, sf):
    """An aggregate of the edges of a set: each query that has some and its unionability, flat."""
    import numpy as np

    from unionlake.operators import kernels as K

    @F.pandas_udf("array<bigint>", F.PandasUDFType.GROUPED_AGG)  # names its kind: annotations here are strings
    def score(query_id, q, j, s):
        ids, at = np.unique(query_id.to_numpy(), return_inverse=True)
        m = np.full((len(ids), int(q.max()) + 1, int(j.max()) + 1), K.NO_EDGE)
        m[at, q.to_numpy(), j.to_numpy()] = s.to_numpy()
        return np.stack((ids, K.assign_many(m, np.ones(m.shape[2], np.int64), False)[1]), 1).ravel().tolist()

    found = sq.edges_tau(spark, sf).groupBy("set_id").agg(score("query_id", "q", "j", "sim6").alias("x"))
    rows = found.select("set_id", "x", F.explode(F.sequence(F.lit(1), F.size("x"), F.lit(2))).alias("i"))
    return rows.select(F.element_at("x", F.col("i")).alias("query_id"), "set_id", F.element_at("x", F.col("i") + 1).alias("u6"))


# ---- aggregations and windows -----------------------------------------------------------------

FAM = "fam AS (SELECT 'orders' AS family, o_orderpriority AS kind, o_orderstatus AS state, o_totalprice AS x FROM orders)"


def _fam(s, d):
    return t(s, d, "orders").select(F.col("o_orderpriority").alias("kind"), F.col("o_orderstatus").alias("state"))


for name, how, sql in (("stats_rollup", "rollup", "ROLLUP (kind, state)"), ("stats_cube", "cube", "CUBE (kind, state)")):
    query(name, W(FAM) + f" SELECT kind, state, count(*) AS n, CAST(grouping(kind)*2 + grouping(state) AS BIGINT) AS level FROM fam GROUP BY {sql}")(
        lambda s, d, how=how: getattr(_fam(s, d), how)("kind", "state").agg(F.count("*").alias("n"), F.grouping_id().alias("level"))
    )
query("stats_grouping_sets", W(FAM) + " SELECT kind, state, count(*) AS n FROM fam GROUP BY GROUPING SETS ((kind), (state))")(
    lambda s, d: _fam(s, d).groupingSets([[F.col("kind")], [F.col("state")]], F.col("kind"), F.col("state")).agg(F.count("*").alias("n"))
)
query("report_pivot", W(FAM) + " SELECT kind, count(*) FILTER (WHERE state='F') AS f, count(*) FILTER (WHERE state='O') AS o, count(*) FILTER (WHERE state='P') AS p FROM fam GROUP BY 1")(
    lambda s, d: _fam(s, d).groupBy("kind").pivot("state", ["F", "O", "P"]).agg(F.count(F.lit(1))).select("kind", *[F.coalesce(x, F.lit(0)).alias(x.lower()) for x in "FOP"])
)
query("cells_unpivot", "SELECT n_nationkey AS id, 'n_name' AS col_name, n_name AS value FROM nation UNION ALL SELECT n_nationkey, 'n_regionkey', CAST(n_regionkey AS VARCHAR) FROM nation")(
    lambda s, d: t(s, d, "nation").select(F.col("n_nationkey").alias("id"), "n_name", F.col("n_regionkey").cast("string").alias("n_regionkey")).unpivot("id", ["n_name", "n_regionkey"], "col_name", "value")
)
query("hot_centroids", W(sq.VC, sq.CE, sq.AS, sq.IW) + " SELECT c, CAST(sum(n) AS BIGINT) AS n FROM iw GROUP BY 1 HAVING sum(n) > 15")(lambda s, d: ix.inverted_counts(sq.assigned(s, d)).groupBy("c").agg(F.sum("n").alias("n")).where("n > 15"))
query("sim_histogram", W(sq.VC, sq.QS, sq.ED) + " SELECT CAST(sim6 // 50000 AS INTEGER) AS bin, count(*) AS n FROM ed GROUP BY 1")(lambda s, d: sq.edges_tau(s, d).groupBy(F.floor(F.col("sim6") / 50000).cast("int").alias("bin")).agg(F.count("*").alias("n")))
query("profile_exact", "SELECT count(*) AS n, count(DISTINCT user_id) AS users, count(DISTINCT event_type) AS kinds, CAST(round(min(value)*1000) AS BIGINT) AS lo, CAST(round(max(value)*1000) AS BIGINT) AS hi FROM events")(
    lambda s, d: t(s, d, "events").agg(F.count("*").alias("n"), F.count_distinct("user_id").alias("users"), F.count_distinct("event_type").alias("kinds"), F.round(F.min("value") * 1000).cast("bigint").alias("lo"), F.round(F.max("value") * 1000).cast("bigint").alias("hi"))
)
query("profile_approx")(lambda s, d: t(s, d, "events").agg(F.approx_count_distinct("user_id").alias("users"), F.percentile_approx("value", [0.5, 0.95]).alias("quantiles"), F.hll_sketch_estimate(F.hll_sketch_agg("user_id")).alias("users_hll")))
query("rank_family", W("r AS (SELECT p_brand, p_partkey, p_size FROM part)") + " SELECT p_partkey, CAST(rank() OVER w AS INTEGER) AS r, CAST(dense_rank() OVER w AS INTEGER) AS dr, CAST(ntile(4) OVER (PARTITION BY p_brand ORDER BY p_size, p_partkey) AS INTEGER) AS quarter, CAST(round(percent_rank() OVER w * 1000000) AS BIGINT) AS pr6 FROM r WINDOW w AS (PARTITION BY p_brand ORDER BY p_size)")(lambda s, d: rank_family(s, d))


def rank_family(spark, sf):
    w = Window.partitionBy("p_brand").orderBy("p_size")
    return t(spark, sf, "part").select("p_partkey", F.rank().over(w).alias("r"), F.dense_rank().over(w).alias("dr"), F.ntile(4).over(Window.partitionBy("p_brand").orderBy("p_size", "p_partkey")).alias("quarter"), F.round(F.percent_rank().over(w) * 1e6).cast("bigint").alias("pr6"))




def by_rank():
    return Window.partitionBy("query_id").orderBy("rank")


EXT = (sq.VC, sq.MS, sq.QS, sq.NQ, sq.PR, sq.ED, sq.dp("ed", True), sq.ALL_U, f"ex AS ({sq.top_sql('allu', sq.TOP)})")
query("score_gap", W(*EXT) + " SELECT query_id, rank, score6 - lead(score6) OVER w AS gap, first_value(score6) OVER w AS best FROM ex WINDOW w AS (PARTITION BY query_id ORDER BY rank)")(
    lambda s, d: sq.REGISTRY["topk_exact_card"](s, d).select("query_id", "rank", (F.col("score6") - F.lead("score6").over(by_rank())).alias("gap"), F.first("score6").over(by_rank()).alias("best"))
)
query("running_sum", W(*EXT) + " SELECT query_id, rank, CAST(sum(score6) OVER (PARTITION BY query_id ORDER BY rank ROWS BETWEEN 2 PRECEDING AND CURRENT ROW) AS BIGINT) AS last3 FROM ex")(
    lambda s, d: sq.REGISTRY["topk_exact_card"](s, d).select("query_id", "rank", F.sum("score6").over(by_rank().rowsBetween(-2, 0)).alias("last3"))
)
query("cumulative_recall", W(*TWO) + " SELECT query_id, ex.rank, CAST(count(qz.set_id) OVER (PARTITION BY query_id ORDER BY ex.rank) AS BIGINT) AS found FROM ex LEFT JOIN qz USING (query_id, set_id)")(
    lambda s, d: (lambda x: x[0].join(x[1].select("query_id", "set_id", F.lit(1).alias("hit")), ["query_id", "set_id"], "left").select("query_id", "rank", F.count("hit").over(by_rank().rowsBetween(Window.unboundedPreceding, 0)).alias("found")))(_two(s, d))
)
query("topk_single", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 10")(lambda s, d: t(s, d, "orders").select("o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(10))
query("topk_page", "SELECT o_orderkey FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 10 OFFSET 10")(lambda s, d: t(s, d, "orders").orderBy(F.desc("o_totalprice"), "o_orderkey").offset(10).limit(10).select("o_orderkey"))
query("exact_copy_sets", "SELECT md5(text) AS content, count(*) AS n, min(doc_id) AS first_id FROM documents GROUP BY 1 HAVING count(*) > 1")(
    lambda s, d: t(s, d, "documents").groupBy(F.md5("text").alias("content")).agg(F.count("*").alias("n"), F.min("doc_id").alias("first_id")).where("n > 1")
)
query("materialize_union", "SELECT c_name AS name, c_nationkey AS nation, c_mktsegment AS segment FROM customer WHERE c_mktsegment = 'BUILDING' UNION ALL SELECT s_name, s_nationkey, NULL FROM supplier")(
    lambda s, d: t(s, d, "customer").where("c_mktsegment = 'BUILDING'").select(F.col("c_name").alias("name"), F.col("c_nationkey").alias("nation"), F.col("c_mktsegment").alias("segment")).unionByName(t(s, d, "supplier").select(F.col("s_name").alias("name"), F.col("s_nationkey").alias("nation")), allowMissingColumns=True)
)

# ---- scalar functions -------------------------------------------------------------------------

query("vector_functions", W(sq.VC) + " SELECT a.vec_id, CAST(round(list_inner_product(a.v,b.v)*1000000) AS BIGINT) AS dot6, CAST(round(list_distance(a.v,b.v)*1000000) AS BIGINT) AS l26, CAST(round(list_cosine_similarity(a.v,b.v)*1000000) AS BIGINT) AS cos6, CAST(list_position(a.v, list_max(a.v)) - 1 AS INTEGER) AS top FROM vc a, vc b WHERE b.vec_id = 1")(lambda s, d: vector_functions(s, d))


def vector_functions(spark, sf):
    e = t(spark, sf, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("v"))
    b = F.broadcast(e.where("vec_id = 1").select(F.col("v").alias("w")))
    six = lambda c: F.round(c * 1e6).cast("bigint")
    v, w = F.col("v"), F.col("w")
    return e.join(b, F.lit(True)).select("vec_id", six(vf.dot(v, w)).alias("dot6"), six(vf.l2(v, w)).alias("l26"), six(vf.cosine(v, w)).alias("cos6"), vf.argmax(v).alias("top"))


query("array_functions", "SELECT l_orderkey, CAST(len(list_distinct(list(l_partkey))) AS INTEGER) AS parts, list_max(list(l_quantity)) AS top, list_sort(list(l_linenumber))[1] AS first_line FROM lineitem GROUP BY 1")(
    lambda s, d: t(s, d, "lineitem").groupBy("l_orderkey").agg(F.size(F.array_distinct(F.collect_list("l_partkey"))).alias("parts"), F.array_max(F.collect_list("l_quantity")).alias("top"), F.element_at(F.array_sort(F.collect_list("l_linenumber")), 1).alias("first_line"))
)
query("map_functions", W(sq.VC, sq.CE, sq.AS, sq.IW) + " SELECT set_id, count(*) AS centroids, CAST(sum(n) AS BIGINT) AS vectors, count(*) FILTER (WHERE n > 1) AS crowded FROM iw GROUP BY 1")(
    lambda s, d: ix.centroid_map(ix.inverted_counts(sq.assigned(s, d))).select("set_id", F.size("w").cast("bigint").alias("centroids"), F.aggregate(F.map_values("w"), F.lit(0).cast("bigint"), lambda a, x: a + x).alias("vectors"), F.size(F.map_filter("w", lambda k, v: v > 1)).cast("bigint").alias("crowded"))
)
query("string_functions", "SELECT p_partkey, lower(p_name) AS low, md5(p_name) AS h, CAST(levenshtein(p_brand, 'Brand#13') AS INTEGER) AS far, substr(p_type, 1, 3) AS pre FROM part")(
    lambda s, d: t(s, d, "part").select("p_partkey", F.lower("p_name").alias("low"), F.md5("p_name").alias("h"), F.levenshtein("p_brand", F.lit("Brand#13")).alias("far"), F.substring("p_type", 1, 3).alias("pre"))
)
query("date_functions", "SELECT o_orderkey, CAST(year(o_orderdate) AS INTEGER) AS y, date_trunc('month', o_orderdate)::TIMESTAMP AS m, CAST(date_diff('day', TIMESTAMP '1992-01-01', o_orderdate) AS INTEGER) AS days FROM orders")(
    lambda s, d: t(s, d, "orders").select("o_orderkey", F.year("o_orderdate").alias("y"), F.date_trunc("month", "o_orderdate").cast("timestamp_ntz").alias("m"), F.datediff("o_orderdate", F.lit("1992-01-01").cast("date")).alias("days"))
)
query("json_props", "SELECT event_id, CAST(json_extract(props, '$.k') AS INTEGER) AS k FROM events")(lambda s, d: t(s, d, "events").select("event_id", F.from_json("props", "k int")["k"].alias("k")))
query("math_functions", "SELECT o_orderkey, CAST(round(ln(o_totalprice)*1000000) AS BIGINT) AS ln6, CAST(round(sqrt(o_totalprice)*1000000) AS BIGINT) AS sq6, o_orderkey % 7 AS m, (o_orderkey & 5) | 2 AS bits, greatest(o_totalprice, 1000.0) AS g FROM orders")(
    lambda s, d: t(s, d, "orders").select("o_orderkey", F.round(F.log("o_totalprice") * 1e6).cast("bigint").alias("ln6"), F.round(F.sqrt("o_totalprice") * 1e6).cast("bigint").alias("sq6"), F.pmod("o_orderkey", F.lit(7)).alias("m"), F.col("o_orderkey").bitwiseAND(F.lit(5)).bitwiseOR(F.lit(2)).alias("bits"), F.greatest("o_totalprice", F.lit(1000.0)).alias("g"))
)
query("null_functions", "SELECT d.doc_id, coalesce(l.quality, -1) AS q, nullif(l.toxic, 0) AS t, CASE WHEN l.quality = 1 THEN 'good' WHEN l.quality = 0 THEN 'bad' ELSE 'none' END AS word FROM documents d LEFT JOIN labels l USING (doc_id)")(
    lambda s, d: t(s, d, "documents").select("doc_id").join(t(s, d, "labels"), "doc_id", "left").select("doc_id", F.coalesce("quality", F.lit(-1)).alias("q"), F.nullif("toxic", F.lit(0)).alias("t"), F.when(F.col("quality") == 1, "good").when(F.col("quality") == 0, "bad").otherwise("none").alias("word"))
)
WIN = {
    "win_tumbling": ("SELECT date_trunc('day', ts) AS start, event_type, count(*) AS n FROM events GROUP BY 1, 2", "1 day", None),
    "win_sliding": ("SELECT start, event_type, count(*) AS n FROM (SELECT date_trunc('day', ts) - to_days(CAST(k AS INTEGER)) AS start, event_type FROM events, range(2) r(k)) GROUP BY 1, 2", "2 days", "1 day"),
}
for name, (sql, size, slide) in WIN.items():

    def _win(spark, sf, size=size, slide=slide):
        w = F.window(F.col("ts").cast("timestamp"), size, slide) if slide else F.window(F.col("ts").cast("timestamp"), size)
        return t(spark, sf, "events").groupBy(w.alias("w"), "event_type").agg(F.count("*").alias("n")).select(F.col("w.start").cast("timestamp_ntz").alias("start"), "event_type", "n")

    query(name, sql)(_win)
query("win_session", """SELECT user_id, min(ts) AS first_ts, count(*) AS n FROM (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS s FROM
 (SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) < INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS fresh FROM events)) GROUP BY user_id, s""")(
    lambda s, d: t(s, d, "events").withColumn("at", F.col("ts").cast("timestamp")).groupBy("user_id", F.session_window("at", "30 minutes").alias("w")).agg(F.count("*").alias("n"), F.min("ts").alias("first_ts")).select("user_id", "first_ts", "n")
)
