"""Benchmark decontamination: a broadcast hash set of the benchmark's word windows, scanned over all texts.

Texts are words of lower-cased ASCII; a window is `width` consecutive words of an item, or a whole
item of fewer. A task maps words to small integers (0: not in any item), hashes only windows free
of 0 with a rolling polynomial, looks the hashes up in the sorted set and verifies hits word by word.

The set is broadcast only while its measured size allows. A larger benchmark is read in blocks of
items up to that size; each block scans all documents, and their hits are written and joined to them.

Defined results: null texts and null items have no words; an item without words never occurs;
items that repeat an item_id count as one; repeated documents give a row each; an empty benchmark
hits nothing; extra columns are ignored by `scan` and kept by `clean`.
"""

from __future__ import annotations

import hashlib
from collections import defaultdict
from collections.abc import Iterator
from functools import reduce
from itertools import chain, repeat

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from unionlake.llm.common import checkpointed, light, portions

#: Bytes that belong to no word become blanks and A-Z lower case; the rest are digits, a-z and UTF-8 beyond ASCII.
FOLD = bytes(b + 32 if 65 <= b <= 90 else b if 48 <= b <= 57 or 97 <= b <= 122 or b >= 128 else 32 for b in range(256))
SCHEMA = "doc_id bigint, n_words bigint, n_hit bigint, n_items bigint, items_sha256 string, contaminated boolean"


def words_of(text: str | None) -> list[bytes]:
    return (text or "").encode("utf-8", "replace").translate(FOLD).split()


class WindowSet:
    """The windows of some items, ready to be sought in texts."""

    MULTIPLIER = np.uint64(0x9E3779B97F4A7C15)

    def __init__(self, items: list[tuple[int, str | None]], width: int = 10):
        self.vocabulary: dict[bytes, int] = {}
        owners: dict[tuple[int, ...], set[int]] = defaultdict(set)
        for item, text in items:
            w = [self.vocabulary.setdefault(x, len(self.vocabulary) + 1) for x in words_of(text)]
            n = min(width, len(w))
            for i in range(len(w) - n + 1 if n else 0):
                owners[tuple(w[i : i + n])].add(item)
        self.owners = dict(owners)
        self.by_length = {n: np.unique(self._hash(np.array([w for w in self.owners if len(w) == n], np.uint64), n)) for n in {len(w) for w in self.owners}}

    def _hash(self, windows: np.ndarray, n: int) -> np.ndarray:
        h = np.zeros(len(windows), np.uint64)
        for k in range(n):
            h = (h + windows[:, k]) * self.MULTIPLIER
        return h

    def hits(self, words: list[bytes]) -> tuple[np.ndarray, set[int]]:
        """Which words lie in an occurring window, and whose windows occur."""
        found: set[int] = set()
        hit = np.zeros(len(words), bool)
        ids = np.fromiter(map(self.vocabulary.get, words, repeat(0)), np.uint64, len(words))
        if not ids.any():
            return hit, found
        unknown = np.concatenate(([0], np.cumsum(ids == 0)))
        for n, known in self.by_length.items():
            if len(ids) < n:
                continue
            at = np.flatnonzero(unknown[n:] == unknown[:-n])
            if not len(at):
                continue
            h = np.zeros(len(at), np.uint64)
            for k in range(n):
                h = (h + ids[at + k]) * self.MULTIPLIER
            near = np.searchsorted(known, h)
            near[near == len(known)] = 0
            for i in at[known[near] == h].tolist():
                owners = self.owners.get(tuple(ids[i : i + n].tolist()))
                if owners:
                    found |= owners
                    hit[i : i + n] = True
        return hit, found


def _blocks(benchmark: DataFrame, limit_bytes: int, item_col: str, text_col: str) -> Iterator[list[tuple[int, str]]]:
    """The items in blocks of at most limit_bytes of text each (a longer item alone), one after another; one empty block of none.

    The driver holds a block and a partition of the benchmark at a time.
    """
    rows = benchmark.select(F.col(item_col).cast("bigint").alias("item"), F.col(text_col).alias("text")).where("item is not null and text is not null").distinct()
    block, size, some = [], 0, False
    for r in rows.toLocalIterator():
        own = len(r["text"].encode("utf-8", "replace"))
        if block and size + own > limit_bytes:
            yield block
            block, size, some = [], 0, True
        block.append((r["item"], r["text"]))
        size += own
    if block or not some:
        yield block


def _hits(docs: DataFrame, block: list[tuple[int, str]], width: int, spark: SparkSession) -> DataFrame:
    """(doc_id, key, hit, items) of the rows of docs (doc_id, key, text) in which an item of the block occurs."""
    shared = spark.sparkContext.broadcast(WindowSet(block, width))

    def run(batches):
        seek = shared.value
        for batch in (p for b in batches for p in portions(b, 2)):
            got = [seek.hits(words_of(t)) for t in batch.column(2).to_pylist()]
            at = [i for i, (_, items) in enumerate(got) if items]
            columns = [pa.array(c, pa.list_(pa.int64())) for c in ([np.flatnonzero(got[i][0]) for i in at], [sorted(got[i][1]) for i in at])]
            yield pa.RecordBatch.from_arrays([*(batch.column(c).take(pa.array(at, pa.int64())) for c in (0, 1)), *columns], ["doc_id", "key", "hit", "items"])

    return docs.mapInArrow(light(run), "doc_id bigint, key bigint, hit array<bigint>, items array<bigint>")


def _counted(docs: DataFrame) -> DataFrame:
    """(doc_id, key, n_words) of the rows of docs (doc_id, key, text)."""

    def run(batches):
        for batch in (p for b in batches for p in portions(b, 2)):
            n = [len(words_of(t)) for t in batch.column(2).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(n, pa.int64())], ["doc_id", "key", "n_words"])

    return docs.mapInArrow(light(run), "doc_id bigint, key bigint, n_words bigint")


def scan(spark: SparkSession, docs: DataFrame, benchmark: DataFrame, width: int = 10, limit_bytes: int = 16 << 20, item_col: str = "item_id") -> DataFrame:
    """One row per document: words, words hit, items with occurring windows."""
    rows = docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), "text")
    blocks = _blocks(benchmark, limit_bytes, item_col, "text")
    block, more = next(blocks), next(blocks, None)
    if more is None:
        shared = spark.sparkContext.broadcast(WindowSet(block, width))

        def one(batches):
            seek = shared.value
            for batch in (p for b in batches for p in portions(b, 1)):
                out = []
                for text in batch.column(1).to_pylist():
                    w = words_of(text)
                    hit, items = seek.hits(w)
                    names = ",".join(sorted(map(str, items)))
                    out.append((len(w), int(hit.sum()), len(items), hashlib.sha256(names.encode()).hexdigest(), bool(items)))
                yield pa.RecordBatch.from_arrays([batch.column(0), *(pa.array(c) for c in zip(*out, strict=True))], [f.split()[0] for f in SCHEMA.split(", ")])

        return rows.mapInArrow(light(one), SCHEMA)

    # a block's hits are few and are written before the next block is read; equal rows have equal hits
    keyed = rows.select("doc_id", F.xxhash64("text").alias("key"), "text")
    parts = [checkpointed(spark, _hits(keyed, b, width, spark), "hits") for b in chain([block, more], blocks)]
    flat = lambda c: F.array_distinct(F.flatten(F.collect_list(c)))
    hits = reduce(DataFrame.unionByName, parts).groupBy(F.col("doc_id").alias("id"), F.col("key").alias("k")).agg(flat("hit").alias("hit"), flat("items").alias("items"))
    every = _counted(keyed).join(hits, F.col("doc_id").eqNullSafe(F.col("id")) & (F.col("key") == F.col("k")), "left")
    none = F.array().cast("array<bigint>")
    names = F.array_join(F.array_sort(F.transform(F.coalesce("items", none), lambda x: x.cast("string"))), ",")
    size = lambda c: F.coalesce(F.size(c), F.lit(0)).cast("bigint")
    sizes = [F.when(F.col("items").isNull(), 0).otherwise(size(c)).cast("bigint").alias(n) for c, n in (("hit", "n_hit"), ("items", "n_items"))]
    return every.select("doc_id", "n_words", *sizes, F.sha2(names, 256).alias("items_sha256"), F.col("items").isNotNull().alias("contaminated"))


def strip(text: str, sets: list[WindowSet]) -> str:
    """The text without the spans of hit words, again until nothing is hit."""
    raw = text.encode("utf-8", "replace")
    while True:
        folded = raw.translate(FOLD)
        w = folded.split()
        hit = np.zeros(len(w), bool)
        for s in sets:
            hit |= s.hits(w)[0]
        if not hit.any():
            return raw.decode()
        starts, at = [], 0
        for x in w:
            at = folded.index(x, at)
            starts.append((at, at + len(x)))
            at += len(x)
        out, last = [], 0
        i = 0
        while i < len(w):
            if hit[i]:
                j = i
                while j + 1 < len(w) and hit[j + 1]:
                    j += 1
                out.append(raw[last : starts[i][0]])
                last = starts[j][1]
                i = j
            i += 1
        raw = b"\n".join([*out, raw[last:]])


def clean(spark: SparkSession, docs: DataFrame, benchmark: DataFrame, action: str = "drop", width: int = 10, limit_bytes: int = 16 << 20, item_col: str = "item_id") -> DataFrame:
    """docs without contaminated rows (`drop`), or with hit spans cut out of their texts (`strip`)."""
    if action not in ("drop", "strip"):
        raise ValueError(f"unknown action {action!r}")
    schema = docs.schema
    names, at = docs.columns, docs.columns.index("text")
    nullable = T.StructType([T.StructField(f.name, f.dataType, True) for f in schema])
    for n, block in enumerate(_blocks(benchmark, limit_bytes, item_col, "text")):
        if n:
            docs = checkpointed(spark, docs, "clean")
        shared = spark.sparkContext.broadcast(WindowSet(block, width))

        def keep(batches, shared=shared):
            seek = shared.value
            for batch in (p for b in batches for p in portions(b, at)):
                texts = batch.column(at).to_pylist()
                dirty = [bool(seek.hits(words_of(t))[0].any()) for t in texts]
                if action == "drop":
                    yield batch.filter(pa.array([not d for d in dirty]))
                else:
                    new = pa.array([strip(t, [seek]) if d else t for t, d in zip(texts, dirty, strict=True)], batch.column(at).type)
                    yield pa.RecordBatch.from_arrays([new if i == at else batch.column(i) for i in range(len(names))], names=names)

        docs = docs.mapInArrow(light(keep), nullable)
    return docs
