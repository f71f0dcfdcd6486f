"""SimHash near-duplicates by covering locality-sensitive hashing.

Fingerprints: a bit of a text's 64-bit fingerprint is set where more than half of its shingle
hashes have it set. Links: a nonzero vector of r + 1 bits is given to each bit place; table v keeps
the places whose vector has odd overlap with v. For any r places there is a v that is even with all
of them, so two fingerprints that differ in at most r places agree in some table's kept bits: no
pair within the radius is missed. Pairs are verified by the count of differing bits and emitted
from the first table only in which they meet.

A bucket with more than `bucket_rows` distinct fingerprints is cut again: the places that its table
leaves out are split into r + 1 runs, of which one is equal for any pair within the radius.

Defined results: null and blank texts have fingerprint zero and are linked like any other; repeated
rows give a row each; rows with a null id belong to their component but never name it (a component
of null ids alone has a null name); an empty table gives an empty result; extra columns are ignored.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from unionlake.llm.common import checkpointed, discard, light, portions

BITS = 64


def shingle_hashes(words: list[bytes], k: int, seed: int = 42) -> list[int]:
    """xxh64 of each run of k words joined by blanks; of all words if there are fewer; none of none."""
    if not words:
        return []
    digest = xxhash.xxh64_intdigest
    if len(words) <= k:
        return [digest(b" ".join(words), seed)]
    joined = b" ".join(words)
    lengths = np.fromiter(map(len, words), np.int64, len(words))
    ends = np.cumsum(lengths + 1) - 1
    starts = (ends - lengths).tolist()
    return [digest(joined[a:b], seed) for a, b in zip(starts, ends[k - 1 :].tolist(), strict=False)]


def majority(hashes: list[int]) -> int:
    if not hashes:
        return 0
    bits = np.unpackbits(np.array(hashes, ">u8").view(np.uint8).reshape(-1, 8), axis=1)
    return int.from_bytes(np.packbits(2 * bits.sum(0, dtype=np.int64) > len(hashes)).tobytes(), "big")


def words_of(text: str | None) -> list[bytes]:
    return (text or "").encode("utf-8", "replace").lower().split()


def fingerprints(docs: DataFrame, shingle: int = 3) -> DataFrame:
    """(doc_id, fp) with the fingerprint as a signed long."""

    def run(batches):
        for batch in (p for b in batches for p in portions(b, 1)):
            fps = [majority(shingle_hashes(words_of(t), shingle)) for t in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(np.array(fps, np.uint64).view(np.int64))], ["doc_id", "fp"])

    return docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), "text").mapInArrow(light(run), "doc_id bigint, fp bigint")


def masks(radius: int) -> list[int]:
    """One mask for each nonzero vector of radius + 1 bits."""
    full = (1 << (radius + 1)) - 1
    return [sum(1 << i for i in range(BITS) if ((1 + i % full) & v).bit_count() % 2) for v in range(1, full + 1)]


def _signed(x: int) -> int:
    return x - (1 << 64) if x >> 63 else x


def _runs(mask: int, parts: int) -> list[int]:
    """The places a mask leaves out, dealt to `parts` masks."""
    left = [i for i in range(BITS) if not mask >> i & 1]
    return [sum(1 << i for i in left[p::parts]) for p in range(parts)]


def links(fps: DataFrame, radius: int = 2, bucket_rows: int = 200) -> DataFrame:
    """(a, b), a < b: every pair of distinct fingerprints within the radius, once. fps: distinct `fp`."""
    tables = masks(radius)
    and_ = lambda c, m: c.bitwiseAND(F.lit(_signed(m)))
    keyed = fps.select("fp", F.posexplode(F.array(*[and_(F.col("fp"), m) for m in tables])).alias("v", "key"))
    sizes = keyed.groupBy("v", "key").agg(F.count("*").alias("n")).where("n > 1")
    # the two sides of a bucket; large buckets are cut once more
    crowded = keyed.join(sizes, ["v", "key"])
    v = F.col("v")
    finer = F.when(v == 0, F.array(*[and_(F.col("fp"), m) for m in _runs(tables[0], radius + 1)]))
    for t in range(1, len(tables)):
        finer = finer.when(v == t, F.array(*[and_(F.col("fp"), m) for m in _runs(tables[t], radius + 1)]))
    sub = F.when(F.col("n") <= bucket_rows, F.array(F.lit(0).cast("bigint"))).otherwise(finer)
    dealt = crowded.select("fp", "v", "key", F.when(F.col("n") <= bucket_rows, -1).otherwise(0).alias("cut"), F.posexplode(sub).alias("part", "sub"))
    left = dealt.withColumnRenamed("fp", "a")
    right = dealt.withColumnRenamed("fp", "b")
    apart = F.col("a").bitwiseXOR(F.col("b"))
    earlier: Column = F.lit(True)
    for t, m in enumerate(tables):  # no earlier table has the pair together
        earlier = earlier & ((F.col("v") <= t) | (and_(apart, m) != 0))
    first_part: Column = F.lit(True)
    for t, m in enumerate(tables):
        runs = _runs(m, radius + 1)
        for p in range(radius):
            first_part = first_part & ((F.col("cut") < 0) | (F.col("v") != t) | (F.col("part") <= p) | (and_(apart, runs[p]) != 0))
    near = (F.bit_count(apart) <= radius) & (F.col("a") < F.col("b"))
    return left.join(right, ["v", "key", "cut", "part", "sub"]).where(near & earlier & first_part).select("a", "b")


def components(spark: SparkSession, edges: DataFrame, names: DataFrame, rounds: int = 100, broadcast_nodes: int = 1_000_000, salts: int = 16) -> DataFrame:
    """(node, root): for each node of `edges` (a, b) the least name reachable. names: (node, name).

    Labels spread along edges and are then shortened through the label's own label, so rounds grow
    with the logarithm of a component's width; each round is written out. Many nodes share a label
    and a hub has many neighbours: up to broadcast_nodes nodes the labels are a broadcast, beyond
    that they are copied under `salts` salts and the nodes or edges dealt over these.
    """
    both = edges.select(F.col("a").alias("node"), F.col("b").alias("near")).unionByName(edges.select(F.col("b").alias("node"), F.col("a").alias("near"))).distinct()
    both = checkpointed(spark, both, "edges")
    nodes = both.select("node").distinct().join(names, "node")
    held = checkpointed(spark, nodes.select("node", "name", F.col("name").alias("root")), "roots")
    few = held.count() <= broadcast_nodes
    salt = F.pmod(F.xxhash64("node"), F.lit(salts)).cast("int")

    def looked_up(rows: DataFrame, table: DataFrame, key: str) -> DataFrame:
        if few:
            return rows.join(F.broadcast(table), key, "left")
        copies = table.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
        return rows.withColumn("salt", salt).join(copies, [key, "salt"], "left").drop("salt")

    for _ in range(rounds):
        state = held.select("node", "name", "root")
        heard = looked_up(both, state.select(F.col("node").alias("near"), "root"), "near").groupBy("node").agg(F.min("root").alias("heard"))
        step = checkpointed(spark, state.join(heard, "node", "left").select("node", "name", F.col("root").alias("old"), F.least("root", "heard").alias("root")), "heard")
        hops = step.where("root < name").groupBy(F.col("name").alias("root")).agg(F.min("root").alias("far"))
        new = looked_up(step, hops, "root").select("node", "name", "old", F.least("root", "far").alias("root"))
        new = checkpointed(spark, new, "roots")
        discard(spark, held, step)
        held = new
        if not new.where("not (root <=> old)").limit(1).count():
            discard(spark, both)
            return new.select("node", "root")
    raise RuntimeError(f"components did not settle in {rounds} rounds")


def link_components(spark: SparkSession, docs: DataFrame, shingle: int = 3, radius: int = 2, bucket_rows: int = 200) -> DataFrame:
    """(doc_id, fingerprint, component_id) of each row."""
    fps = checkpointed(spark, fingerprints(docs, shingle), "simhash")
    first = checkpointed(spark, fps.groupBy("fp").agg(F.min("doc_id").alias("name")), "distinct")
    edges = checkpointed(spark, links(first.select("fp"), radius, bucket_rows), "links")
    # a fingerprint of null ids alone has no name: it borrows one beyond all ids
    names = first.select(F.col("fp").alias("node"), F.coalesce("name", F.lit((1 << 63) - 1)).alias("name"))
    roots = components(spark, edges, names)
    class_of = first.join(roots.withColumnsRenamed({"node": "fp"}), "fp", "left").select("fp", F.coalesce("root", "name").alias("root"))
    class_of = class_of.select("fp", F.when(F.col("root") < (1 << 63) - 1, F.col("root")).alias("component_id"))
    return fps.join(class_of, "fp", "left").select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")
