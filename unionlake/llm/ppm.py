"""Language-model scoring by prediction by partial matching over byte contexts.

The trie holds, for contexts of 0 to `order` bytes, how often each byte followed in the training
texts. The probability of a byte comes from the longest known context; if the byte was never seen
there, an escape is coded and the next shorter context decides, without the bytes the longer one
already excludes. Each byte seen in a context gives half a count to the escape (method D). Because
the bytes after a context also follow every shorter one, what is excluded depends on the last
escaped context alone, and the trie becomes one table per order with a remainder per context, so
all places of a batch are scored at once.

Counting keeps nothing between blocks of text: each block's distinct runs and words go to Spark's
own aggregation, which combines them in a task and spills.

The base score of the contract, add-one word frequencies, is computed beside it: frequent words
from a bounded broadcast table, all others by a join, so that vocabulary may grow with the corpus.

The trie grows with the corpus too. While it fits it is a broadcast. Beyond that the most frequent
runs are a broadcast table of their probabilities, and every other run of the texts gets its own by
a join: all contexts of a run of two bytes or more end in the same bytes, so the full counts are cut
by those bytes into small tries, and no counted run is dropped.

Defined results: null texts count as empty (the end alone); rows with a null id are in training
(crc32 of the empty text is 0); repeated rows are scored and counted each; an empty table gives an
empty result; extra columns are ignored.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from unionlake.llm.common import checkpointed, id_remainder, light, portions
from unionlake.llm.hash_arrays import HashArray

END = b"\x00"  # ends a text, and stands before it as often as the order asks
BLOCK = 1 << 21


def stream(texts: list[bytes], order: int) -> tuple[np.ndarray, np.ndarray]:
    """The bytes of all texts, each between `order` ends and one, and where each begins."""
    pad = END * order
    joined = np.frombuffer(b"".join(pad + t + END for t in texts), np.uint8)
    sizes = np.fromiter(map(len, texts), np.int64, len(texts)) + order + 1
    return joined, np.cumsum(sizes) - sizes


def grams(joined: np.ndarray, begins: np.ndarray, order: int) -> tuple[np.ndarray, np.ndarray]:
    """The order + 1 bytes that end at each coded place, packed into a number, and the places."""
    key = np.zeros(len(joined) - order, np.uint64)
    for i in range(order + 1):
        key <<= np.uint64(8)
        key |= joined[i : i + len(key)]
    coded = np.ones(len(joined), bool)
    for i in range(order):
        coded[begins + i] = False
    places = np.flatnonzero(coded)
    return key[places - order], places


def lowered(texts: pa.Array) -> pa.Array:
    """A-Z in lower case; a null is empty."""
    return pc.ascii_lower(pc.fill_null(texts, ""))


def byte_strings(texts: pa.Array) -> list[bytes]:
    return texts.cast(pa.binary()).to_pylist()


def counts(docs: DataFrame, order: int, modulus: int = 7, held: int = 2) -> DataFrame:
    """(word, run, n): words (run null, the end left out) and byte runs (word null) of all training texts, in one pass."""

    def run(batches):
        for batch in batches:
            for part in portions(batch, 0, BLOCK):
                texts = lowered(part.column(0))
                seen = pc.ascii_split_whitespace(texts).flatten().value_counts()
                seen = seen.filter(pc.not_equal(seen.field(0), ""))
                yield pa.RecordBatch.from_arrays([seen.field(0), pa.nulls(len(seen), pa.int64()), seen.field(1)], ["word", "run", "n"])
                key, _ = grams(*stream(byte_strings(texts), order), order)
                key.sort()
                first = np.flatnonzero(np.concatenate(([True], key[1:] != key[:-1])))
                n = np.diff(np.append(first, len(key)))
                yield pa.RecordBatch.from_arrays([pa.nulls(len(n), pa.string()), pa.array(key[first].view(np.int64)), pa.array(n)], ["word", "run", "n"])

    train = docs.where(id_remainder("doc_id", modulus) != held).select("text")
    return train.mapInArrow(light(run), "word string, run bigint, n bigint").groupBy("word", "run").agg(F.sum("n").alias("n"))


def frequent(df: DataFrame, most: int) -> DataFrame:
    """The keys that occur often enough that at most `most` occur as often or more."""
    spread = sorted(((r["n"], r["keys"]) for r in df.groupBy("n").agg(F.count("*").alias("keys")).collect()), reverse=True)  # a row per distinct count
    total, least = 0, (spread[0][0] + 1) if spread else 1
    for n, k in spread:
        if total + k > most:
            break
        total, least = total + k, n
    return df.where(F.col("n") >= least)


class Trie:
    """tables: for each order from 0 up, the byte runs of order + 1 bytes and how often each occurs."""

    def __init__(self, tables: list[tuple[np.ndarray, np.ndarray]]):
        self.order = len(tables) - 1
        self.grams, self.n, self.contexts, self.total, self.kinds, self.rest, self.unseen = [], [], [], [], [], [], []
        lower: dict | None = None
        for k, (keys, ns) in enumerate(tables):
            order = np.argsort(keys)
            keys, ns = keys[order].astype(np.uint64), ns[order].astype(np.float64)
            context = keys >> np.uint64(8)
            first = np.flatnonzero(np.concatenate(([True], context[1:] != context[:-1]))) if len(keys) else np.zeros(0, np.int64)
            total = np.add.reduceat(ns, first) if len(keys) else np.zeros(0)
            kinds = np.diff(np.append(first, len(keys)))
            own = context[first] if len(keys) else keys
            if lower is None:  # below order 0 stand the bytes never seen, all alike
                rest, unseen = np.zeros(len(own)), 256 - kinds
            else:
                mask = np.uint64((1 << (8 * k)) - 1)
                beneath = lower["n"][np.searchsorted(lower["keys"], keys & mask)]
                seen = np.add.reduceat(beneath, first) if len(keys) else np.zeros(0)
                at = np.searchsorted(lower["own"], own & (mask >> np.uint64(8)))
                rest, unseen = lower["total"][at] - seen, lower["kinds"][at] - kinds
            g, c = HashArray(keys), HashArray(own)
            self.grams.append(g)
            if k == self.order:  # a run known at the top needs no more than its probability
                ns = np.log10((ns - 0.5) / np.repeat(total, kinds))
            self.n.append(ns[g.order].astype(np.float32))
            self.contexts.append(c)
            for name, values, kind in (("total", total, np.float32), ("kinds", kinds, np.uint16), ("rest", rest, np.float32), ("unseen", unseen, np.uint16)):
                getattr(self, name).append(values[c.order].astype(kind))
            lower = {"keys": keys, "n": ns, "own": own, "total": total, "kinds": kinds}

    def log10(self, key: np.ndarray) -> np.ndarray:
        """log10 of the probability of the last byte of each run of order + 1 bytes, given the bytes before it."""
        row = self.grams[self.order].rows(key)
        out = np.where(row >= 0, self.n[self.order][row] if len(self.n[self.order]) else 0.0, 0.0).astype(np.float64)
        todo = np.flatnonzero(row < 0)
        # of the last escaped context: what is left below it, and how many bytes are new there; -1 before any escape
        left, fresh = np.full(len(todo), -1.0), np.zeros(len(todo))
        for k in range(self.order, -1, -1):
            if not len(todo):
                return out
            g = key[todo] & np.uint64((1 << (8 * (k + 1))) - 1)
            c = self.contexts[k].rows(g >> np.uint64(8))
            row = self.grams[k].rows(g) if k < self.order else np.full(len(todo), -1)
            some = len(self.total[k]) > 0
            total = np.where(left < 0, self.total[k][c] if some else 0.0, left)
            kinds = np.where(left < 0, self.kinds[k][c] if some else 0.0, fresh)
            hit = row >= 0
            out[todo[hit]] += np.log10((self.n[k][row[hit]] - 0.5) / total[hit])
            esc = np.flatnonzero((c >= 0) & ~hit)
            if len(esc):
                sure = esc[kinds[esc] > 0]  # if no new byte is left here, the escape costs nothing
                out[todo[sure]] += np.log10(0.5 * kinds[sure] / total[sure])
                left[esc], fresh[esc] = self.rest[k][c[esc]], self.unseen[k][c[esc]]
            go = ~hit
            todo, left, fresh = todo[go], left[go], fresh[go]
        out[todo] -= np.log10(np.maximum(1.0, np.where(left < 0, 256.0, fresh)))
        return out

    def score(self, texts: list[bytes]) -> np.ndarray:
        """log10 probability of each text and its end."""
        joined, begins = stream(texts, self.order)
        key, places = grams(joined, begins, self.order)
        return np.add.reduceat(self.log10(key), np.searchsorted(places, begins + self.order)) if len(texts) else np.zeros(0)


class Head:
    """keys, logs: the most frequent byte runs of order + 1 bytes and the log10 of their probabilities."""

    def __init__(self, keys: np.ndarray, logs: np.ndarray, order: int):
        self.order, self.table = order, HashArray(keys)
        self.logs = np.append(logs[self.table.order], 0.0).astype(np.float32)  # the last place stands for runs not in the table

    def score(self, texts: list[bytes]) -> tuple[np.ndarray, pa.ListArray]:
        """log10 probability of the known runs of each text, and its other runs with their counts."""
        joined, begins = stream(texts, self.order)
        key, places = grams(joined, begins, self.order)
        starts = np.searchsorted(places, begins + self.order)
        row = self.table.rows(key)
        other = np.flatnonzero(row < 0)
        text, run = np.searchsorted(starts, other, "right") - 1, key[other]
        by = np.lexsort((run, text))
        text, run = text[by], run[by]
        first = np.flatnonzero(np.concatenate(([True], (text[1:] != text[:-1]) | (run[1:] != run[:-1])))) if len(run) else np.zeros(0, np.int64)
        pairs = listed(text[first], len(texts), {"key": pa.array(run[first].view(np.int64)), "n": pa.array(np.diff(np.append(first, len(run))))})
        return np.add.reduceat(self.logs[row].astype(np.float64), starts), pairs


def listed(owner: np.ndarray, owners: int, fields: dict[str, pa.Array]) -> pa.ListArray:
    """A list of structs for each owner; owner: ascending, whose each struct is."""
    offsets = np.searchsorted(owner, np.arange(owners + 1)).astype(np.int32)
    return pa.ListArray.from_arrays(pa.array(offsets), pa.StructArray.from_arrays(list(fields.values()), list(fields)))


def summed(keys: np.ndarray, ns: np.ndarray, size: int) -> tuple[np.ndarray, np.ndarray]:
    """The last `size` bytes of the runs, each once, and how often."""
    own, back = np.unique(keys & np.uint64((1 << (8 * size)) - 1), return_inverse=True)
    return own, np.bincount(back, ns, len(own))


def arrays(runs: DataFrame) -> tuple[np.ndarray, np.ndarray]:
    got = runs.select("run", "n").toArrow()
    return got.column("run").to_numpy().view(np.uint64), got.column("n").to_numpy()


def train(runs: DataFrame, order: int) -> Trie:
    """The trie from all byte runs (run, n) of order + 1 bytes."""
    keys, ns = arrays(runs)
    return Trie([summed(keys, ns, k + 1) for k in range(order)] + [(keys, ns)])


def train_head(runs: DataFrame, order: int, most_nodes: int) -> Head:
    """The probabilities of at most most_nodes frequent runs, from the full counts of their contexts."""
    context = F.shiftright("run", 8).alias("context")
    totals = runs.groupBy(context).agg(F.sum("n").alias("total"))
    got = frequent(runs, most_nodes).select("*", context).join(totals, "context").select("run", F.log10((F.col("n") - 0.5) / F.col("total")).alias("log")).toArrow()
    return Head(got.column("run").to_numpy().view(np.uint64), got.column("log").to_numpy(), order)


def run_logs(spark: SparkSession, runs: DataFrame, wanted: DataFrame, order: int, total: int, shard_rows: int = 1 << 17) -> DataFrame:
    """(key, log): log10 of the probability of each wanted run, from the full counts; total: how many runs are counted.

    Runs are cut by the last bytes of their contexts; what is shorter than those is small and a broadcast.
    """
    depth = min(order, 2 if total <= 1 << 26 else 3)
    short = [arrays(runs.groupBy(F.col("run").bitwiseAND(F.lit((1 << (8 * (k + 1))) - 1)).alias("run")).agg(F.sum("n").alias("n"))) for k in range(depth)]
    small = spark.sparkContext.broadcast(short)

    def shard(run: Column) -> Column:
        return F.pmod(F.xxhash64(F.shiftright(run, 8).bitwiseAND(F.lit((1 << (8 * depth)) - 1))), F.lit(-(-total // shard_rows))).cast("int").alias("shard")

    def solve(left: pa.Table, right: pa.Table) -> pa.Table:
        keys, ns = left.column("run").to_numpy().view(np.uint64), left.column("n").to_numpy()
        tables = [*small.value, *(summed(keys, ns, k + 1) for k in range(depth, order + 1))]
        asked = right.column("key").to_numpy()
        return pa.table({"key": asked, "log": Trie(tables).log10(asked.view(np.uint64))})

    counted, asked = runs.select("run", "n", shard(F.col("run"))), wanted.select("key", shard(F.col("key")))
    return counted.groupBy("shard").cogroup(asked.groupBy("shard")).applyInArrow(solve, "key bigint, log double")


def score(spark: SparkSession, docs: DataFrame, order: int = 5, head_words: int = 200_000, modulus: int = 7, held: int = 2, most_nodes: int = 1 << 21) -> DataFrame:
    """One row per document: the base score over words and the model's score over bytes."""
    if not 0 < order < 7:
        raise ValueError("order must be 1 to 6: a run of order + 1 bytes is kept in a signed long")
    docs = docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), "text")
    counted = checkpointed(spark, counts(docs, order, modulus, held), "counts")
    words = counted.where("word is not null").select("word", "n")
    totals = words.agg(F.sum("n").alias("n"), F.count("*").alias("kinds")).first()
    ends = docs.where(id_remainder("doc_id", modulus) != held).count()
    n_train, kinds = (totals["n"] or 0) + ends, totals["kinds"] + (ends > 0)
    got = frequent(words, head_words).toArrow().combine_chunks()  # at most head_words rows
    head = pa.array(got.column("word").to_pylist(), pa.string()), np.log10(got.column("n").to_numpy() + 1.0)
    runs = counted.where("run is not null").select("run", "n")
    n_runs = runs.count()
    whole = n_runs <= most_nodes
    shared = spark.sparkContext.broadcast((head, train(runs, order) if whole else train_head(runs, order, most_nodes)))
    end_log = math.log10(ends + 1)
    schema = "row_id bigint, doc_id bigint, held_out boolean, n_tokens bigint, n_known bigint, head_logs double, score double, tail array<struct<word:string,n:bigint>>, runs array<struct<key:bigint,n:bigint>>"

    def run(batches):
        from pyspark import TaskContext

        (known, logs), model = shared.value
        row_id = TaskContext.get().partitionId() << 36
        run_type = pa.list_(pa.struct([("key", pa.int64()), ("n", pa.int64())]))
        for batch in batches:
            for part in portions(batch, 2, BLOCK // 2):
                n, texts = part.num_rows, lowered(part.column(2))
                split = pc.ascii_split_whitespace(texts)
                coded = split.flatten().dictionary_encode()
                owner = np.repeat(np.arange(n), pc.list_value_length(split).to_numpy(zero_copy_only=False))
                at = coded.indices.to_numpy()
                real = pc.not_equal(coded.dictionary, "").to_numpy(zero_copy_only=False)[at]
                owner, at = owner[real], at[real]
                slot = pc.fill_null(pc.index_in(coded.dictionary, value_set=known), -1).to_numpy()[at]
                hit = slot >= 0
                n_words, n_known = np.bincount(owner, minlength=n) + 1, np.bincount(owner[hit], minlength=n) + (ends > 0)
                head_logs = np.bincount(owner[hit], logs[slot[hit]], n) + end_log
                pair, times = np.unique(owner[~hit] * max(1, len(coded.dictionary)) + at[~hit], return_counts=True)
                owned, word = np.divmod(pair, max(1, len(coded.dictionary)))
                tail = listed(owned, n, {"word": coded.dictionary.take(pa.array(word)), "n": pa.array(times)})
                scores, others = (model.score(byte_strings(texts)), pa.array([[]] * n, run_type)) if whole else model.score(byte_strings(texts))
                columns = [pa.array(np.arange(row_id, row_id + n)), part.column(0), part.column(1), *map(pa.array, (n_words, n_known, head_logs, scores)), tail, others]
                yield pa.RecordBatch.from_arrays(columns, ["row_id", "doc_id", "held_out", "n_tokens", "n_known", "head_logs", "score", "tail", "runs"])
                row_id += n

    scored = docs.select("doc_id", (id_remainder("doc_id", modulus) == held).alias("held_out"), "text").mapInArrow(light(run), schema)
    scored = checkpointed(spark, scored, "scored")
    shared.unpersist()
    tail = scored.select("row_id", F.inline("tail")).withColumnRenamed("n", "times")
    known = tail.join(words, "word").groupBy("row_id").agg(F.sum("times").alias("more"), F.sum(F.col("times") * F.log10(F.col("n") + 1.0)).alias("logs"))
    both = scored.drop("tail", "runs").join(known, "row_id", "left")
    if not whole:
        rare = scored.select("row_id", F.inline("runs")).withColumnRenamed("n", "times")
        logs = run_logs(spark, runs, rare.select("key").distinct(), order, n_runs)
        both = both.join(rare.join(logs, "key").groupBy("row_id").agg(F.sum(F.col("times") * F.col("log")).alias("rest")), "row_id", "left")
        both = both.withColumn("score", F.col("score") + F.coalesce("rest", F.lit(0.0)))
    logs = F.col("head_logs") + F.coalesce("logs", F.lit(0.0)) - F.col("n_tokens") * math.log10(n_train + kinds + 1)
    return both.select(
        "doc_id", "held_out", "n_tokens", (F.col("n_known") + F.coalesce("more", F.lit(0))).alias("n_known"),
        F.lit(n_train).cast("bigint").alias("train_tokens"), logs.alias("base_score"), "score",
    )
