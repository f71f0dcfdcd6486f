"""Lakes of vector sets built from the given tables: `vec_cols(set_id, pos, v array<double>)`.

The set layout `vec_sets(set_id, n, flat array<double>)` holds a set's vectors end to end, because
matching needs all vectors of one set and no other row. Vectors that are null, of another length
than most or hold a null go to `bad_vectors` instead.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from unionlake.functions.vectors import normalize

DIM = 64


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _embeddings(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("v"), "label")


def vector_lake(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Blocks of 30 neighbouring vectors cut into sets of 2, 4, 6, 8 and 10.

    Numbers go round by one every four blocks, so that the ids divisible by 20 are of all widths.
    """
    o, block = F.col("vec_id") % 30, F.floor(F.col("vec_id") / 30)
    part = F.when(o < 2, 0).when(o < 6, 1).when(o < 12, 2).when(o < 20, 3).otherwise(4)
    begin = F.when(o < 2, 0).when(o < 6, 2).when(o < 12, 6).when(o < 20, 12).otherwise(20)
    e = _embeddings(spark, sf_dir)
    return e.select((5 * block + (part + F.floor(block / 4)) % 5).cast("bigint").alias("set_id"), (o - begin).cast("int").alias("pos"), "v")


def wide_lake(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = _embeddings(spark, sf_dir)
    return e.select(F.floor(F.col("vec_id") / 30).cast("bigint").alias("set_id"), (F.col("vec_id") % 30).cast("int").alias("pos"), "v")


def label_lake(spark: SparkSession, sf_dir: str) -> DataFrame:
    pos = F.row_number().over(Window.partitionBy("label").orderBy("vec_id")) - 1
    return _embeddings(spark, sf_dir).select(F.col("label").cast("bigint").alias("set_id"), pos.cast("int").alias("pos"), "v")


def planted_lake(spark: SparkSession, sf_dir: str, copies: int, wide: bool = False) -> DataFrame:
    """`copies` noisy copies of each set of the vector lake, or of the wide one; copy m of set s is set s * copies + m."""
    e = _embeddings(spark, sf_dir).select("vec_id", "v")
    n = e.count()
    if wide:
        base = wide_lake(spark, sf_dir).withColumn("vec_id", F.col("set_id") * 30 + F.col("pos"))
        last = F.lit(30)
    else:
        block = F.floor(F.col("set_id") / 5)
        part = F.pmod(F.col("set_id") % 5 - F.floor(block / 4), F.lit(5)).cast("int")
        base = vector_lake(spark, sf_dir).withColumn("vec_id", block * 30 + F.element_at(F.array(*map(F.lit, (0, 2, 6, 12, 20))), part + 1) + F.col("pos"))
        last = 2 * part + 2
    base = base.repartition(int(spark.conf.get("spark.sql.shuffle.partitions")), "set_id")  # the file is small, the copies are not
    last = F.least(last, F.lit(n) - (F.col("vec_id") - F.col("pos")))  # the last block may be cut short
    m = base.withColumn("size", last.cast("int")).withColumn("m", F.explode(F.sequence(F.lit(0), F.lit(copies - 1))))
    m = m.where(F.col("pos") < F.greatest(F.lit(1), F.col("size") - F.col("m") % 3))
    m = m.withColumn("other", (37 * F.col("vec_id") + 101 * F.col("m")) % n).withColumn("a", F.lit(0.1) * (F.col("m") % 6))
    joined = m.join(e.select(F.col("vec_id").alias("other"), F.col("v").alias("w")), "other")
    mixed = F.zip_with("v", "w", lambda x, y: x * (1 - F.col("a")) + y * F.col("a"))
    return joined.select((F.col("set_id") * copies + F.col("m")).alias("set_id"), "pos", normalize(mixed).alias("v"))


def encode(rows: DataFrame, dim: int = DIM) -> DataFrame:
    """(set_id, pos, v) from (set_id, pos, tokens), a row each: hashed tokens, weight 1 + ln of the count, unit length.

    A row needs no other, so nothing is shuffled; a token is hashed once a batch.
    """

    def run(batches):
        for batch in batches:
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), _encoded(batch.column(2), dim)], ["set_id", "pos", "v"])

    return rows.select("set_id", "pos", "tokens").mapInArrow(run, "set_id bigint, pos int, v array<double>")


def _encoded(lists: pa.Array, dim: int) -> pa.Array:
    """The unit vector of each list of tokens. Weights are whole micro-units and squares are added in order of place, as `encode_counts` does."""
    n, tokens = len(lists), lists.flatten()
    sizes = np.asarray(pc.fill_null(pc.list_value_length(lists), 0))
    row = np.repeat(np.arange(n), sizes)
    codes = pc.dictionary_encode(pc.fill_null(tokens, ""))
    words = codes.dictionary.to_pylist()
    hashes = [hashlib.md5(w.encode()).hexdigest() for w in words]
    bucket = np.array([int(h[:8], 16) % dim for h in hashes], np.int64)
    sign = np.array([0 if not w else 1 if h[8] < "8" else -1 for w, h in zip(words, hashes, strict=True)], np.int64)
    key, tf = np.unique(row * max(1, len(words)) + np.asarray(codes.indices), return_counts=True)
    at, word = np.divmod(key, max(1, len(words)))
    weight = sign[word] * np.floor((1 + np.log(tf)) * 1e6 + 0.5)
    v = np.bincount(at * dim + bucket[word], weight, n * dim).reshape(n, dim) + 0.0
    total = np.zeros(n)
    for i in range(dim):
        total += v[:, i] * v[:, i]
    v /= np.where(total > 0, np.sqrt(total), 1.0)[:, None]
    return pa.ListArray.from_arrays(pa.array(np.arange(n + 1) * dim, pa.int32()), pa.array(v.ravel()))


def encode_counts(columns: DataFrame, counts: DataFrame, dim: int = DIM) -> DataFrame:
    """encode() of the columns (set_id, pos) from the counts (set_id, pos, token, tf) of their tokens."""
    h = F.md5("token")
    bucket = (F.conv(F.substring(h, 1, 8), 16, 10).cast("bigint") % dim).cast("int")
    sign = F.when(F.conv(F.substring(h, 9, 1), 16, 10).cast("int") < 8, 1.0).otherwise(-1.0)
    # weights in whole micro-units, so that their sums do not depend on order
    weights = counts.where("token != ''").groupBy("set_id", "pos", bucket.alias("bucket")).agg(F.sum((sign * F.round((1 + F.log(F.col("tf").cast("double"))) * 1e6)).cast("bigint")).alias("w"))
    packed = weights.groupBy("set_id", "pos").agg(F.map_from_entries(F.collect_list(F.struct("bucket", "w"))).alias("at"))
    dense = F.transform(F.sequence(F.lit(0), F.lit(dim - 1)), lambda i: F.coalesce(F.element_at("at", i), F.lit(0)).cast("double"))
    rest = columns.join(packed, ["set_id", "pos"], "left").withColumn("raw", F.coalesce(dense, F.array_repeat(F.lit(0.0), dim)))
    return rest.select("set_id", "pos", normalize(F.col("raw")).alias("v"))


def _words(text: Column) -> Column:
    return F.filter(F.split(F.lower(text), "[^a-z0-9\\x{80}-\\x{10FFFF}]+"), lambda w: w != "")


def _lines(rows: DataFrame) -> DataFrame:
    """(set_id, pos, tokens) from (set_id, text): one vector per non-empty line."""
    lines = F.filter(F.transform(F.split("text", "\n"), lambda x: F.trim(x)), lambda x: x != "")
    return rows.select("set_id", F.posexplode(lines).alias("pos", "line")).select("set_id", "pos", _words(F.col("line")).alias("tokens"))


def document_lake(spark: SparkSession, sf_dir: str, ids: DataFrame | None = None) -> DataFrame:
    """All documents, or those whose id (set_id) is among `ids`; only these are encoded."""
    rows = table(spark, sf_dir, "documents").select(F.col("doc_id").alias("set_id"), "text")
    return encode(_lines(rows if ids is None else rows.join(ids, "set_id", "left_semi")))


def benchmark_lake(spark: SparkSession, sf_dir: str) -> DataFrame:
    return encode(_lines(table(spark, sf_dir, "benchmark").select(F.col("item_id").alias("set_id"), "text")))


def conversation_lake(spark: SparkSession, sf_dir: str) -> DataFrame:
    c = table(spark, sf_dir, "conversations")
    return encode(c.select(F.col("conv_id").alias("set_id"), F.col("turn").cast("int").alias("pos"), _words(F.col("text")).alias("tokens")))


def page_blocks(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(set_id, pos, block): the text after each paragraph tag up to its end, tags removed."""
    found = F.regexp_extract_all("html", F.lit("<p[^>]*>(.*?)</p>"), F.lit(1))
    rows = table(spark, sf_dir, "pages").select(F.col("page_id").alias("set_id"), F.posexplode(found).alias("pos", "block"))
    return rows.withColumn("block", F.trim(F.regexp_replace("block", "<[^>]*>", " ")))


def page_lake(spark: SparkSession, sf_dir: str) -> DataFrame:
    return encode(page_blocks(spark, sf_dir).select("set_id", "pos", _words(F.col("block")).alias("tokens")))


def event_lake(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One vector per event type and user: the sum of `value` by hour of day, in whole micro-units before scaling."""
    e = table(spark, sf_dir, "events").select("user_id", "event_type", F.hour("ts").alias("h"), F.round(F.col("value") * 1e6).cast("bigint").alias("x"))
    sums = e.groupBy("user_id", "event_type", "h").agg(F.sum("x").alias("x"))
    packed = sums.groupBy("user_id", "event_type").agg(F.map_from_entries(F.collect_list(F.struct("h", "x"))).alias("at"))
    dense = F.transform(F.sequence(F.lit(0), F.lit(23)), lambda i: F.coalesce(F.element_at("at", i), F.lit(0)).cast("double"))
    pos = F.row_number().over(Window.partitionBy("user_id").orderBy("event_type")) - 1
    return packed.select(F.col("user_id").alias("set_id"), pos.cast("int").alias("pos"), normalize(dense).alias("v"))


#: How the base tables are cut: slicing columns, key, and the columns of a slice in order.
SLICES = {
    "region": ([], "r_regionkey", ["r_regionkey", "r_name"]),
    "nation": (["n_regionkey"], "n_nationkey", ["n_nationkey", "n_name", "n_regionkey"]),
    "customer": (["c_mktsegment"], "c_custkey", ["c_custkey", "c_name", "c_nationkey", "c_acctbal", "c_mktsegment"]),
    "supplier": (["pmod(s_suppkey, 4)"], "s_suppkey", ["s_suppkey", "s_name", "s_nationkey", "s_acctbal"]),
    "part": (["p_brand"], "p_partkey", ["p_partkey", "p_name", "p_brand", "p_type", "p_size", "p_retailprice"]),
    "orders": (["o_orderpriority", "o_orderstatus"], "o_orderkey", ["o_orderkey", "o_custkey", "o_orderstatus", "o_totalprice", "o_orderdate", "o_orderpriority"]),
    "lineitem": (["year(l_shipdate)", "l_returnflag"], "l_orderkey", ["l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_returnflag", "l_linestatus", "l_shipdate"]),
    "events": (["event_type"], "event_id", ["event_id", "ts", "user_id", "event_type", "value", "props"]),
}


def relational_tables(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(set_id, family, pos, token, tf), the count of each token of a column: each base table cut across by a category, and each slice with all columns and without the first and the slicing ones."""
    out = None
    for number, (family, (by, key, columns)) in enumerate(SLICES.items()):
        t = table(spark, sf_dir, family)
        slice_id = F.concat_ws("|", *[F.expr(b).cast("string") for b in by]) if by else F.lit("all")
        t = t.withColumn("_slice", slice_id)
        kinds = dict(t.dtypes)

        def tokens(c: str, kinds: dict[str, str] = kinds) -> Column:
            if kinds[c] in ("int", "bigint", "double"):
                whole = F.abs(F.col(c)).cast("bigint").cast("string")
                return F.array(F.concat(F.lit("n"), F.length(whole).cast("string")), F.substring(whole, 1, 1))
            if kinds[c].startswith("timestamp"):
                return F.array(F.concat(F.lit("y"), F.year(c).cast("string")), F.concat(F.lit("m"), F.month(c).cast("string")))
            return _words(F.col(c))

        cells = F.array(*[F.struct(F.lit(i).alias("pos"), tokens(c).alias("tokens")) for i, c in enumerate(columns)])
        # every row counts; a column without tokens keeps a row with a null token
        long = t.select("_slice", F.explode(cells).alias("cell")).select("_slice", "cell.pos", F.explode_outer("cell.tokens").alias("token"))
        long = long.groupBy("_slice", "pos", "token").agg(F.count("token").alias("tf"))
        ranks = t.select("_slice").distinct().withColumn("rank", F.row_number().over(Window.orderBy("_slice")))  # as many rows as slices
        long = long.join(F.broadcast(ranks), "_slice")
        dropped = {0} | {columns.index(b) for b in by if b in columns}
        full = long.select((F.lit(number * 1000) + 2 * F.col("rank")).cast("bigint").alias("set_id"), F.lit(family).alias("family"), "pos", "token", "tf")
        part = long.where(~F.col("pos").isin([*dropped])).select((F.lit(number * 1000) + 2 * F.col("rank") + 1).cast("bigint").alias("set_id"), F.lit(family).alias("family"), "pos", "token", "tf")
        place = {c: i for i, c in enumerate(c for c in range(len(columns)) if c not in dropped)}
        part = part.withColumn("pos", F.element_at(F.array(*[F.lit(place.get(c, -1)) for c in range(len(columns))]), F.col("pos") + 1))
        both = full.unionByName(part)
        out = both if out is None else out.unionByName(both)
    return out


def encode_tables(tables: DataFrame) -> DataFrame:
    return encode_counts(tables.select("set_id", "pos").distinct(), tables.select("set_id", "pos", "token", "tf"))


def relational_lake(spark: SparkSession, sf_dir: str) -> DataFrame:
    return encode_tables(relational_tables(spark, sf_dir))


def well_formed(cols: DataFrame, dim: int) -> Column:
    return F.col("v").isNotNull() & (F.size("v") == dim) & ~F.exists("v", lambda x: x.isNull() | F.isnan(x))


def vec_sets(cols: DataFrame, dim: int = DIM) -> DataFrame:
    """Set layout: vectors in order of pos, end to end."""
    packed = cols.where(well_formed(cols, dim)).groupBy("set_id").agg(F.array_sort(F.collect_list(F.struct("pos", "v"))).alias("s"))
    return packed.select("set_id", F.size("s").alias("n"), F.flatten(F.transform("s", lambda x: x["v"])).alias("flat"))


def bad_vectors(cols: DataFrame, dim: int = DIM) -> DataFrame:
    return cols.where(~F.coalesce(well_formed(cols, dim), F.lit(False)))


LAKES = {
    "vector": (vector_lake, 64), "wide": (wide_lake, 64), "label": (label_lake, 64), "document": (document_lake, 64), "conversation": (conversation_lake, 64),
    "page": (page_lake, 64), "event": (event_lake, 24), "benchmark": (benchmark_lake, 64), "relational": (relational_lake, 64),
}
