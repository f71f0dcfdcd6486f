"""Near-duplicate removal on word shingles: SimHash candidates from covering tables, links proved by Jaccard similarity.

Equal texts are one class from the start. Two rounds find the links. The first is quick and finds
most: candidates come from the covering tables of whole-text fingerprints, and from fingerprints of
blocks (runs of words that end where a hash of two words says, so an edit changes the blocks it
touches and no others). Its groups and keys are bounded, so it may miss pairs.

The second round misses none. All texts order their distinct shingles alike, those common in a
sample last; of n shingles the first n - ceil(similarity n) + 1 are filed, and two texts of that
similarity share one of them (prefix filter). Pairs that the first round has connected need no
proof, so a group within one component ends there and large groups of copies cost nothing; the
others are compared if their sizes and the places of the shared shingle allow the similarity.

Every link of either round is proved by the exact Jaccard similarity of the distinct shingles.

Defined results: null texts and texts without words form one class of empty texts; repeated rows
with one id stay or go together; a row with a null id stays only if no row with an id is like it
(of several such rows all stay); the smallest id of a group stays; an empty table gives an empty
result; extra columns are kept.
"""

from __future__ import annotations

import math
from functools import reduce

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from unionlake.llm.common import checkpointed, discard, light, partitions_for, portions, unused
from unionlake.llm.covering import components, links, majority, shingle_hashes, words_of


def unpacked(hashes: np.ndarray) -> np.ndarray:
    return np.unpackbits(hashes.astype(">u8").view(np.uint8).reshape(-1, 8), axis=1)


def sketch(words: list[bytes], hashes: list[int], shingle: int, mean: int = 16, least: int = 6, chunk: int = 1 << 16) -> tuple[int, np.ndarray]:
    """The fingerprint of a text and those of its content-defined blocks; hashes: those of its shingles.

    Bits are counted a chunk of shingles at a time, for all blocks that lie in it together.
    """
    own = np.array(hashes, np.uint64)
    total = np.zeros(64, np.int64)
    begins, ends = np.zeros(0, np.int64), np.zeros(0, np.int64)
    if len(words) >= 2 * least:
        digests = np.fromiter(map(xxhash.xxh64_intdigest, words), np.uint64, len(words))
        pair = (digests[:-1] * np.uint64(0x9E3779B97F4A7C15) + digests[1:]) >> np.uint64(40)
        cuts = [0]
        for i in (np.flatnonzero(pair % np.uint64(mean) == 0) + 2).tolist():
            if i - cuts[-1] >= least:
                cuts.append(i)
        cuts.append(len(words))
        begins, stops = np.array(cuts[:-1]), np.array(cuts[1:])
        keep = (stops - begins >= least) & (begins < len(own))
        begins, ends = begins[keep], np.minimum(np.maximum(begins + 1, stops - shingle + 1), len(own))[keep]
    found = []
    for low in range(0, len(own), chunk):
        bits = unpacked(own[low : low + chunk])
        total += bits.sum(0, dtype=np.int64)
        inside = (begins >= low) & (ends <= low + chunk)
        a, e = begins[inside] - low, ends[inside] - low
        if len(a):
            sums = np.add.reduceat(np.concatenate((bits, np.zeros((1, 64), np.uint8))), np.stack((a, e), 1).ravel(), axis=0, dtype=np.int32)[::2]
            found.append(np.packbits(2 * sums > (e - a)[:, None], axis=1).view(">u8").ravel().astype(np.uint64))
        for x, y in zip(begins, ends, strict=True):
            if low <= x < low + chunk < y:  # lies in two chunks
                found.append(np.array([majority(hashes[x:y])], np.uint64))
    fp = int.from_bytes(np.packbits(2 * total > len(own)).tobytes(), "big")
    return fp, np.unique(np.concatenate(found)) if found else np.zeros(0, np.uint64)


def common_shingles(spark: SparkSession, rows: DataFrame, shingle: int, share: int = 8, most: int = 1 << 21) -> tuple[np.ndarray, np.ndarray]:
    """Shingle hashes in ascending order that 2 or more texts of a sample hold, and how many: they only decide which shingles are filed first.

    The sample is one text in `share` at any size, so the groups of shingles it does not know stay
    as small as they are while the table grows.
    """
    cut = min(share, partitions_for(rows, "text", 1 << 20))
    sample = rows.where(F.pmod(F.xxhash64("id"), F.lit(cut)) == 0).select("text")

    def run(batches):
        for batch in (p for b in batches for p in portions(b, 0)):
            parts = [np.unique(np.array(shingle_hashes(words_of(t), shingle), np.uint64)) for t in batch.column(0).to_pylist()]
            key, n = np.unique(np.concatenate(parts), return_counts=True)
            yield pa.RecordBatch.from_arrays([pa.array(key.view(np.int64)), pa.array(n)], ["key", "n"])

    counted = sample.mapInArrow(light(run), "key bigint, n bigint").groupBy("key").agg(F.sum("n").alias("n")).where("n >= 2")
    got = counted.orderBy(F.desc("n"), "key").limit(most).toArrow()  # at most `most` rows
    keys, n = got.column("key").to_numpy().view(np.uint64), got.column("n").to_numpy()
    order = np.argsort(keys)
    return keys[order], n[order]


def prefix(own: np.ndarray, similarity: float, common: np.ndarray, times: np.ndarray) -> np.ndarray:
    """Of a text's distinct shingle hashes those to file it under, first those that are not common, as signed longs."""
    if not len(own):
        return own.view(np.int64)
    if len(common):
        at = np.minimum(np.searchsorted(common, own), len(common) - 1)
        own = own[np.argsort(np.where(common[at] == own, times[at], 0), kind="stable")]
    return own[: len(own) - math.ceil(similarity * len(own) - 1e-9) + 1].view(np.int64)


def parities(own: np.ndarray) -> bytes:
    """A bit for each class of the distinct shingle hashes by their low bits: whether it holds an odd number. Of n hashes n to 2 n bits, a power of two."""
    bits = 1 << max(3, (len(own) - 1).bit_length() if len(own) else 0)
    return np.packbits(np.bincount((own & np.uint64(bits - 1)).astype(np.int64), minlength=bits) & 1, bitorder="little").tobytes()


def fewest_apart(one: bytes, two: bytes) -> int:
    """At least this many shingles are in one of two texts only, by their parities; the longer ones are folded to the length of the others."""
    if len(one) < len(two):
        one, two = two, one
    x, size = int.from_bytes(one, "little"), len(one)
    while size > len(two):
        size //= 2
        x = (x >> 8 * size) ^ (x & (1 << 8 * size) - 1)
    return (x ^ int.from_bytes(two, "little")).bit_count()


def sketches(spark: SparkSession, docs: DataFrame, shingle: int, keep: int, similarity: float) -> DataFrame:
    """(id, text_key, n, fp, blocks, keys, parity): shingles, fingerprint, smallest block fingerprints, filed shingles and parities of each row."""
    shared = spark.sparkContext.broadcast(common_shingles(spark, docs, shingle))

    def run(batches):
        for batch in (p for b in batches for p in portions(b, 2)):
            out = []
            for text in batch.column(2).to_pylist():
                w = words_of(text)
                h = shingle_hashes(w, shingle)
                fp, block = sketch(w, h, shingle)
                small = block[np.argsort(block * np.uint64(0x9E3779B97F4A7C15))[:keep]].view(np.int64)
                own = np.unique(np.array(h, np.uint64))
                out.append((len(own), fp - (1 << 64) if fp >> 63 else fp, small, prefix(own, similarity, *shared.value), parities(own)))
            columns = [pa.array([o[i] for o in out], t) for i, t in enumerate((pa.int64(), pa.int64(), pa.list_(pa.int64()), pa.list_(pa.int64()), pa.binary()))]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), *columns], ["id", "text_key", "n", "fp", "blocks", "keys", "parity"])

    return docs.mapInArrow(light(run), "id bigint, text_key string, n bigint, fp bigint, blocks array<bigint>, keys array<bigint>, parity binary")


def candidates(spark: SparkSession, reps: DataFrame, radius: int, crowd: int, similarity: float, far: int) -> DataFrame:
    """(a, b) of distinct texts, a < b, that may reach the similarity. reps: (id, n, fp, blocks), a row per text.

    Each kind of pair is written out before they meet: one plan over all of them fails in adaptive
    execution, where the sides of its unions end up with different numbers of partitions.
    """
    slim = reps.select("id", "n", "fp")
    near = checkpointed(spark, links(slim.select("fp").distinct(), radius), "near")
    of = slim.groupBy("fp").agg(F.min("id").alias("id"))
    # texts with one fingerprint pair with the first of them; linked fingerprints pair by their firsts
    same = slim.join(of.select("fp", F.col("id").alias("first")), "fp").where("id != first").select(F.col("first").alias("a"), F.col("id").alias("b"))
    whole = near.join(of.select(F.col("fp").alias("a"), F.col("id").alias("ia")), "a").join(of.select(F.col("fp").alias("b"), F.col("id").alias("ib")), "b")
    whole = whole.select(F.least("ia", "ib").alias("a"), F.greatest("ia", "ib").alias("b"))

    filed = reps.select("id", "n", "fp", "blocks", F.explode("blocks").alias("key"))
    sizes = filed.groupBy("key").agg(F.count("*").alias("size")).where("size > 1")
    filed = checkpointed(spark, filed.join(sizes, "key"), "filed")
    common = filed.where(F.col("size") > crowd)
    finer = common.select("id", "n", "fp", F.explode(F.filter("blocks", lambda x: x != F.col("key"))).alias("other"), "key")
    finer = finer.select("id", "n", "fp", F.xxhash64(F.least("key", "other"), F.greatest("key", "other")).alias("key")).distinct()
    finer_sizes = finer.groupBy("key").agg(F.count("*").alias("size")).where("size > 1")
    finer = checkpointed(spark, finer.join(finer_sizes, "key"), "finer")
    alike = lambda na, nb, fa, fb: (F.least(na, nb) >= similarity * F.greatest(na, nb)) & (F.bit_count(fa.bitwiseXOR(fb)) <= far)
    pieces = [same, whole]
    for rows in (filed, finer):
        small = rows.where(F.col("size") <= crowd)
        left, right = (small.select(F.col("id").alias(x), F.col("n").alias(f"n{x}"), F.col("fp").alias(f"f{x}"), "key") for x in "ab")
        pieces.append(left.join(right, "key").where((F.col("a") < F.col("b")) & alike(F.col("na"), F.col("nb"), F.col("fa"), F.col("fb"))).select("a", "b"))

    large = finer.where(F.col("size") > crowd).select("id", "n", "fp", "key")
    lone = common.where(F.size("blocks") == 1).select("id", "n", "fp", "key")  # nothing finer to file them under
    large = checkpointed(spark, large.unionByName(lone), "large")
    heads = large.groupBy("key").agg(F.min(F.struct("id", "n", "fp")).alias("head"))
    to_head = large.join(heads, "key").select(F.col("head.id").alias("a"), F.col("id").alias("b"), F.col("head.n").alias("na"), F.col("n").alias("nb"), F.col("head.fp").alias("fa"), F.col("fp").alias("fb"))
    # neighbours in fingerprint order, within parts of a group so that no group is one task
    salt = F.shiftright("fp", 56)
    order = Window.partitionBy("key", salt).orderBy("fp", "id")
    beside = [large.select(F.col("id").alias("b"), F.col("n").alias("nb"), F.col("fp").alias("fb"), *[F.lag(c, k).over(order).alias(to) for c, to in (("id", "a"), ("n", "na"), ("fp", "fa"))]) for k in (1, 2)]
    for more in (to_head, *beside):
        more = more.where((F.col("a") != F.col("b")) & alike(F.col("na"), F.col("nb"), F.col("fa"), F.col("fb")))
        pieces.append(more.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")))
    written = [checkpointed(spark, piece.where("a != b").distinct(), "pairs") for piece in pieces]
    discard(spark, near, filed, finer, large)
    out = checkpointed(spark, reduce(DataFrame.unionByName, written).distinct(), "candidates")
    discard(spark, *written)
    return out


def unconnected(spark: SparkSession, reps: DataFrame, similarity: float, block: int = 1024) -> DataFrame:
    """(a, b), a < b, of texts with different roots that may reach the similarity, none missed. reps: (id, n, keys, root), a row per text.

    Of a pair that reaches it, the first shared shingle in the common order passes the test of
    places. Groups are joined in blocks of about `block` rows, so that no group is one task.
    """
    filed = reps.select("id", "root", F.col("n").cast("int").alias("n"), F.posexplode("keys").alias("at", "key"))
    group = Window.partitionBy("key")
    filed = filed.select("*", F.min("root").over(group).alias("low"), F.max("root").over(group).alias("high"), F.count("*").over(group).alias("size"))
    parts = F.ceil(F.col("size") / block).cast("int")
    filed = filed.where("low < high").select("id", "root", "n", "at", "key", parts.alias("parts"))
    filed = checkpointed(spark, filed, "shared")
    left, right = (filed.select("key", "parts", *[F.col(c).alias(f"{c}_{x}") for c in ("id", "root", "n", "at")]) for x in "ab")
    left = left.withColumn("part", F.pmod(F.xxhash64("id_a"), F.col("parts")).cast("int")).drop("parts")
    right = right.withColumn("part", F.explode(F.sequence(F.lit(0), F.col("parts") - 1))).drop("parts")
    total = F.col("n_a") + F.col("n_b")
    most = F.least(F.col("n_a") - F.col("at_a"), F.col("n_b") - F.col("at_b"))
    may = (F.least("n_a", "n_b") >= similarity * F.greatest("n_a", "n_b") - 1e-9) & (most * (1 + similarity) >= similarity * total - 1e-9)
    pairs = left.join(right, ["key", "part"]).where((F.col("id_a") < F.col("id_b")) & (F.col("root_a") != F.col("root_b")) & may)
    out = checkpointed(spark, pairs.select(F.col("id_a").alias("a"), F.col("id_b").alias("b")).distinct(), "unconnected")
    discard(spark, filed)
    return out


def close(pairs: DataFrame, reps: DataFrame, similarity: float) -> DataFrame:
    """The pairs that may reach the similarity by their parities, none missed. reps: (id, n, parity).

    Of texts with n_a and n_b shingles at most (1 - s) / (1 + s) of n_a + n_b are in one only. A
    parity is about a fiftieth of its text, so the texts of all other pairs need not move.
    """
    both = pairs
    for x in "ab":
        both = both.join(reps.select(F.col("id").alias(x), F.col("n").alias(f"n{x}"), F.col("parity").alias(f"p{x}")), x)

    def run(batches):
        for batch in batches:
            total, one, two = (batch.column(i).to_pylist() for i in (2, 3, 4))
            keep = [fewest_apart(p, q) * (1 + similarity) <= (1 - similarity) * n + 1e-6 for n, p, q in zip(total, one, two, strict=True)]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1)], ["a", "b"]).filter(pa.array(keep, pa.bool_()))

    return both.select("a", "b", F.col("na") + F.col("nb"), "pa", "pb").mapInArrow(light(run), "a bigint, b bigint")


def verified(pairs: DataFrame, texts: DataFrame, shingle: int, similarity: float, broadcast_ids: int = 1_000_000) -> DataFrame:
    """The pairs whose distinct shingles have at least the Jaccard similarity. texts: (id, text).

    Only texts of a pair are shuffled: their ids filter the scan as a broadcast of at most
    broadcast_ids longs, by a join beyond that.
    """
    ids = pairs.select(F.explode(F.array("a", "b")).alias("id")).distinct()
    texts = texts.join(F.broadcast(ids) if ids.count() <= broadcast_ids else ids, "id", "left_semi").dropDuplicates(["id"])
    # the last join leaves the pairs of one `a` beside each other, whose shingles are then made once
    both = pairs.join(texts.select(F.col("id").alias("b"), F.col("text").alias("tb")), "b").join(texts.select(F.col("id").alias("a"), F.col("text").alias("ta")), "a")

    def run(batches):
        last, mine = None, frozenset()
        for batch in (p for b in batches for p in portions(b, 3)):
            keep = []
            for ta, tb in zip(batch.column(2).to_pylist(), batch.column(3).to_pylist(), strict=True):
                if ta != last:
                    last, mine = ta, frozenset(shingle_hashes(words_of(ta), shingle))
                other = frozenset(shingle_hashes(words_of(tb), shingle))
                common = len(mine & other)
                keep.append(common >= similarity * (len(mine) + len(other) - common))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1)], ["a", "b"]).filter(pa.array(keep, pa.bool_()))

    return both.select("a", "b", "ta", "tb").mapInArrow(light(run), "a bigint, b bigint")


def text_key() -> Column:
    """What texts of one class share: their words in lower case."""
    return F.sha2(F.coalesce(F.concat_ws(" ", F.split(F.trim(F.lower("text")), r"[\s]+")), F.lit("")), 256)


def near_groups(spark: SparkSession, docs: DataFrame, shingle: int = 5, similarity: float = 0.8, radius: int = 3, keep: int = 12, crowd: int = 24, far: int = 24) -> DataFrame:
    """(text_key, root): for each distinct text that is not its group's first, the smallest id of the group."""
    base = docs.select(F.col("doc_id").cast("bigint").alias("id"), text_key().alias("text_key"), "text")
    rows = base.where("id is not null")
    keys = checkpointed(spark, rows.groupBy("text_key").agg(F.min("id").alias("id")), "texts")
    # rows of small numbers are joined to the firsts, so texts stay where they are
    every = checkpointed(spark, sketches(spark, rows, shingle, keep, similarity), "every")
    reps = checkpointed(spark, every.join(keys.select("id", "text_key"), ["id", "text_key"], "left_semi").dropDuplicates(["id"]), "sketches")
    discard(spark, every)
    every = candidates(spark, reps, radius, crowd, similarity, far)
    pairs = checkpointed(spark, close(every, reps, similarity), "close")
    discard(spark, every)
    edges = checkpointed(spark, verified(pairs, rows.select("id", "text"), shingle, similarity), "links")
    roots = components(spark, edges, reps.select(F.col("id").alias("node"), F.col("id").alias("name")))
    discard(spark, pairs, edges)
    state = reps.select("id", "n", "keys").join(roots.withColumnRenamed("node", "id"), "id", "left").withColumn("root", F.coalesce("root", "id"))
    every = unconnected(spark, state, similarity)
    pairs = checkpointed(spark, close(every, reps, similarity), "close")
    discard(spark, every)
    more = checkpointed(spark, verified(pairs, rows.select("id", "text"), shingle, similarity), "more")
    discard(spark, pairs)
    # the new links join components: they are links of roots
    state = checkpointed(spark, state.select("id", "root"), "first")
    discard(spark, reps)
    of = [state.select(F.col("id").alias(x), F.col("root").alias(f"root_{x}")) for x in "ab"]
    edges = more.join(of[0], "a").join(of[1], "b").select(F.col("root_a").alias("a"), F.col("root_b").alias("b"))
    tops = components(spark, edges, state.where("id = root").select(F.col("id").alias("node"), F.col("id").alias("name")))
    roots = state.join(tops.select(F.col("node").alias("root"), F.col("root").alias("top")), "root", "left").select("id", F.coalesce("top", "root").alias("root"))
    return keys.join(roots, "id", "left").select("text_key", F.coalesce("root", "id").alias("root"))


def keep_first(spark: SparkSession, docs: DataFrame, **how) -> DataFrame:
    """The rows of docs, all columns, that are the first of their group."""
    groups = near_groups(spark, docs, **how)
    own = unused(docs, "group_key")
    firsts = groups.select(F.col("root").alias(own)).distinct()
    named = docs.join(firsts, F.col("doc_id") == F.col(own), "left_semi")
    nameless = docs.where("doc_id is null").withColumn(own, text_key()).join(groups.select(F.col("text_key").alias(own)), own, "left_anti").drop(own)
    return named.unionByName(nameless)
