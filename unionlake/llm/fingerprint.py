"""Canonical exact document fingerprints, with built-in column functions only.

Canonical text: compatibility composition (NFKC), full case folding, composition again, then each
run of white space as one blank and none at the ends. The fingerprint is 128 bits: two chained
xxhash64 digests of the canonical text. Equal fingerprints are only candidates: classes of equal
documents are confirmed by comparing the canonical bytes inside each bucket.

Defined results: a null text counts as empty; rows with a null id come last in descending order;
repeated rows keep one row each; an empty table gives an empty result; extra columns are ignored.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from unionlake.llm.common import checkpointed, range_bounds, range_bucket

#: White space to fold: what Unicode calls so, and the zero-width blank and byte order mark.
BLANKS = r"[\s\p{Z}\x{85}\x{1c}-\x{1f}\x{200b}\x{feff}]+"


def _compose(text: Column) -> Column:
    return F.java_method(F.lit("com.ibm.icu.text.Normalizer"), F.lit("compose"), text, F.lit(True))


def _fold(text: Column) -> Column:
    return F.java_method(F.lit("com.ibm.icu.lang.UCharacter"), F.lit("foldCase"), text, F.lit(True))


def canonical_text(text: Column) -> Column:
    """Texts of ASCII alone take the short way, which gives the same."""
    text = F.coalesce(text, F.lit(""))
    ascii_only = F.octet_length(text) == F.char_length(text)
    folded = F.when(ascii_only, F.lower(text)).otherwise(_compose(_fold(_compose(text))))
    return F.trim(F.regexp_replace(folded, BLANKS, " "))


def digest(canonical: Column) -> Column:
    """32 hex digits."""
    half = lambda h: F.lpad(F.lower(F.hex(h)), 16, "0")
    return F.concat(half(F.xxhash64(canonical)), half(F.xxhash64(F.lit(0x5EED), canonical)))


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, fingerprint) of every row."""
    return docs.select(F.col(id_col), digest(canonical_text(F.col(text_col))).alias("fingerprint"))


def exact_classes(
    spark: SparkSession,
    docs: DataFrame,
    id_col: str = "doc_id",
    text_col: str = "text",
    broadcast_ids: int = 2_000_000,
    rows_per_salt: int = 1_000,
    known: DataFrame | None = None,
) -> DataFrame:
    """(id, fingerprint, class_id) of each distinct (id, fingerprint); class_id: the smallest id of equal canonical bytes.

    known: (id, fingerprint) of all rows, if they are written already. Only documents whose fingerprint occurs more than once are compared. Their ids filter the text
    scan as a broadcast set of at most broadcast_ids longs, by a shuffled join beyond that. A bucket
    is spread over one salt per rows_per_salt rows, each with a copy of the bucket's first text, so
    no group of copies meets in one task.
    """
    light = known or checkpointed(spark, fingerprints(docs, id_col, text_col).select(F.col(id_col).alias("id"), "fingerprint"), "fingerprints")
    buckets = light.groupBy("fingerprint").agg(F.min("id").alias("first_id"), F.count("*").alias("n"))
    shared = buckets.where("n > 1 and first_id is not null")
    members = checkpointed(spark, light.where("id is not null").distinct().join(shared, "fingerprint"), "members")
    n = members.count()
    wanted = members.select("id", "fingerprint", "first_id", F.ceil(F.col("n") / rows_per_salt).alias("salts"))
    texts = docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text"))
    compared = texts.join(F.broadcast(wanted) if n <= broadcast_ids else wanted, "id")
    compared = compared.withColumn("canonical", canonical_text(F.col("text"))).where(digest(F.col("canonical")) == F.col("fingerprint"))
    first = compared.where("id = first_id").groupBy("fingerprint", "salts").agg(F.min("canonical").alias("first_text"))
    first = first.select("fingerprint", "first_text", F.explode(F.sequence(F.lit(0), F.col("salts").cast("int") - 1)).alias("salt"))
    salted = compared.withColumn("salt", F.pmod(F.xxhash64("id"), F.col("salts")).cast("int"))
    checked = salted.join(first, ["fingerprint", "salt"], "left")
    same = F.col("canonical") == F.col("first_text")
    agreed = checked.where(same).select("id", "fingerprint", F.col("first_id").alias("class_id")).distinct()
    # texts of one fingerprint whose bytes differ, which 128 bits make next to impossible: classes of their own
    odd = checked.where(~F.coalesce(same, F.lit(False))).select("id", "fingerprint", "canonical")
    own = odd.groupBy("fingerprint", "canonical").agg(F.min("id").alias("class_id"))
    odd = odd.join(own, ["fingerprint", "canonical"]).select("id", "fingerprint", "class_id").distinct()
    alone = light.distinct().join(members.select("id", "fingerprint"), ["id", "fingerprint"], "left_anti")
    alone = alone.select("id", "fingerprint", F.col("id").alias("class_id"))
    return alone.unionByName(agreed).unionByName(odd).withColumnRenamed("id", id_col)


def with_next_document(docs: DataFrame, carry: list[str], id_col: str = "doc_id", rows_per_bucket: int = 512, most_buckets: int = 16_384) -> DataFrame:
    """Each row with the `carry` columns of the next row in descending id, as next_<name>; after the last comes the first.

    Rows meet in buckets of neighbouring ids. The largest id of each lower bucket visits the bucket
    above it, so one shuffle is enough and no task holds the whole order.
    """
    n = docs.count()
    bounds = range_bounds(docs, id_col, min(most_buckets, math.ceil(n / rows_per_bucket)))
    rows = docs.withColumn("_bucket", range_bucket(F.col(id_col), bounds))
    heads = rows.where(F.col(id_col).isNotNull()).groupBy("_bucket").agg(F.max(id_col).alias("head")).orderBy("_bucket").collect()  # at most most_buckets rows
    above = F.col("_bucket")
    if len(heads) > 1:
        visits = [(heads[i]["head"], heads[(i + 1) % len(heads)]["_bucket"]) for i in range(len(heads))]
        small = docs.sparkSession.createDataFrame(visits, "_head bigint, _visits int")
        rows = rows.join(F.broadcast(small), F.col(id_col) == F.col("_head"), "left").drop("_head")
        both = F.when(F.col("_visits").isNull(), F.array(F.struct(above.alias("b"), F.lit(0).alias("guest")))).otherwise(
            F.array(F.struct(above.alias("b"), F.lit(0).alias("guest")), F.struct(F.col("_visits").alias("b"), F.lit(1).alias("guest")))
        )
        rows = rows.withColumn("_at", F.explode(both)).withColumn("_bucket", F.col("_at.b")).withColumn("_guest", F.col("_at.guest")).drop("_at", "_visits")
    else:
        rows = rows.withColumn("_guest", F.lit(0))
    order = Window.partitionBy("_bucket").orderBy("_guest", F.col(id_col).desc_nulls_last(), *carry)
    rows = rows.withColumn("_next", F.coalesce(F.lead(F.struct(*carry)).over(order), F.first(F.struct(*carry)).over(order)))
    return rows.where("_guest = 0").select("*", *[F.col(f"_next.{c}").alias(f"next_{c}") for c in carry]).drop("_next", "_bucket", "_guest")


def edited_report(spark: SparkSession, docs: DataFrame) -> DataFrame:
    """Fingerprints of all documents, and how they answer when the last third of a text is replaced."""
    base = docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text"))
    base = base.withColumn("fingerprint", digest(canonical_text(F.col("text"))))
    rows = with_next_document(base, ["text", "fingerprint"])
    n = F.char_length("text").cast("bigint")
    tail = F.floor(F.col("n_chars") / 3).cast("int")
    rows = rows.withColumn("n_chars", n).withColumn(
        "edited", F.concat(F.substring(F.col("text"), F.lit(1), F.col("n_chars").cast("int") - tail), F.substring(F.col("next_text"), F.lit(1), tail))
    )
    rows = rows.withColumn("edited_fingerprint", digest(canonical_text(F.col("edited"))))
    likeness = lambda other, text: F.when(  # noqa: E731  equal digests are confirmed by the bytes
        (F.col("fingerprint") == F.col(other)) & (canonical_text(F.col("text")) == canonical_text(F.col(text))), 1.0
    ).otherwise(0.0)
    rows = rows.select(
        "doc_id",
        "n_chars",
        F.sha2(F.encode("edited", "UTF-8"), 256).alias("edited_sha256"),
        "fingerprint",
        "edited_fingerprint",
        likeness("edited_fingerprint", "edited").alias("near_edited"),
        likeness("next_fingerprint", "next_text").alias("near_next"),
    )
    rows = checkpointed(spark, rows, "edited")
    known = rows.select(F.col("doc_id").alias("id"), "fingerprint")
    classes = exact_classes(spark, docs, known=known).select(F.col("doc_id").alias("_id"), F.col("fingerprint").alias("_fp"), "class_id")
    return rows.join(classes, F.col("doc_id").eqNullSafe(F.col("_id")) & (F.col("fingerprint") == F.col("_fp")), "left").drop("_id", "_fp")
