"""Order-preserving packing of token streams into windows by dynamic programming.

Documents stand in id order within shards of neighbouring ids. A cut may stand at the end of a
document (free), of a sentence, of a clause, or at a stride of ids inside a clause, each dearer
than the last. The best cuts minimise padding plus the penalties of cuts inside documents:
best(j) = min over i with b_j - b_i <= size of best(i) + size - (b_j - b_i) + penalty(j), where the
minimum of best(i) + b_i over the sliding range comes from a monotone queue in constant time.

A shard's last window is cut at powers of two, which need no padding.

Defined results: a null text is the end id alone; null ids come first; rows that repeat an id are
each a document; an empty table has no pieces; extra columns are ignored.
"""

from __future__ import annotations

import zlib
from collections import deque

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from unionlake.llm.common import light, partitions_for, portions
from unionlake.llm.tokens import encoder, tokenizer_path, with_end

SENTENCE, CLAUSE, INSIDE = 4, 10, 24  # penalties, in padded ids
SCHEMA = "doc_id bigint, start bigint, length bigint, ids_crc32 bigint, doc_tokens bigint, sequence_id bigint, offset bigint"


def best_cuts(at: list[int], penalty: list[int], size: int) -> list[int]:
    """Indices of the chosen cuts among ascending positions `at`; the first and last are always chosen."""
    n = len(at)
    cost, back = [0] * n, [0] * n
    queue: deque[int] = deque()  # indices i with ascending key[i] = cost[i] + at[i]
    key = [0] * n
    key[0] = at[0]
    low = 0
    for j in range(1, n):
        k = key[j - 1]
        while queue and key[queue[-1]] >= k:
            queue.pop()
        queue.append(j - 1)
        least = at[j] - size
        while at[queue[0]] < least:
            queue.popleft()
        i = queue[0]
        cost[j] = c = key[i] + size - at[j] + penalty[j]
        back[j] = i
        key[j] = c + at[j]
    cuts, low = [n - 1], n - 1
    while low > 0:
        low = back[low]
        cuts.append(low)
    return cuts[::-1]


def candidates(ids: np.ndarray, doc_ends: np.ndarray, sentence: np.ndarray, clause: np.ndarray, stride: int) -> tuple[np.ndarray, np.ndarray]:
    """Positions where a cut may stand, and the penalty of each."""
    far = np.full(len(ids) + 1, 255, np.uint8)
    far[::stride] = INSIDE
    far[1:][clause[ids]] = CLAUSE
    far[1:][sentence[ids]] = SENTENCE
    far[doc_ends] = 0
    far[0] = 0
    at = np.flatnonzero(far < 255)
    return at, far[at]


def pack(spark: SparkSession, docs: DataFrame, size: int = 2048, end_id: int = 1, tokenizer: str | None = None, shard_bytes: int = 8 << 20, stride: int = 16, chunk: int = 1 << 19) -> DataFrame:
    """One row per piece. A task streams its shard and solves `chunk` ids at a time; the last window goes on into the next chunk."""
    path = tokenizer or tokenizer_path()
    rows = docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), F.col("text"))
    shards = partitions_for(rows, "text", shard_bytes)
    rows = rows.repartitionByRange(shards, "doc_id", F.xxhash64("text")) if shards > 1 else rows.coalesce(1)
    rows = rows.sortWithinPartitions("doc_id", "text")

    def solve(batches):
        from pyspark import TaskContext

        enc, sequence = encoder(path), TaskContext.get().partitionId() << 36
        vocab = enc.lib.get_vocab()
        sentence, clause = (np.zeros(max(vocab.values()) + 2, bool) for _ in range(2))
        for marks, to in ((".!?", sentence), (",;:", clause)):
            for token, i in vocab.items():
                if token.endswith("</w>") and token[:-4] and token[-5] in marks and not token[0].isalnum():
                    to[i] = True
        waiting: list[list] = []  # doc_id, the ids not packed yet, how many were packed before, ids of the document
        held = 0

        def windows(last: bool):
            """Packs what waits, but for the last window unless it is the last call."""
            nonlocal sequence, waiting, held
            ids = np.concatenate([w[1] for w in waiting])
            ends = np.cumsum([len(w[1]) for w in waiting])
            at, penalty = candidates(ids, ends, sentence, clause, stride)
            cuts = at[best_cuts(at.tolist(), penalty.tolist(), size)].tolist()
            if not last:
                cuts = cuts[:-1]
            else:  # the tail at powers of two
                tail, cuts = cuts[-1], cuts[:-1]
                while cuts[-1] < tail:
                    cuts.append(cuts[-1] + min(size, 1 << ((tail - cuts[-1]).bit_length() - 1)))
            out = []
            d, begin = 0, 0
            for a, b in zip(cuts, cuts[1:], strict=False):
                x = a
                while x < b:
                    e = int(ends[d])
                    y = min(b, e)
                    doc_id, own, before, n = waiting[d]
                    out.append((doc_id, before + x - begin, y - x, zlib.crc32(own[x - begin : y - begin]), n, sequence, x - a))
                    x = y
                    if x == e:
                        d, begin = d + 1, e
                sequence += 1
            stop = cuts[-1]
            rest = waiting[d:]
            if rest and stop > begin:
                doc_id, own, before, n = rest[0]
                rest[0] = [doc_id, own[stop - begin :], before + stop - begin, n]
            waiting, held = rest, len(ids) - stop
            return out

        def batch_of(out):
            return pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in zip(*out, strict=True)], [f.split()[0] for f in SCHEMA.split(", ")])

        for batch in batches:
            for part in portions(batch, 1):
                ids, bounds = with_end(*enc.encode(part.column(1)), end_id)
                for i, doc_id in enumerate(part.column(0).to_pylist()):
                    own = ids[bounds[i] : bounds[i + 1]]
                    waiting.append([doc_id, own, 0, len(own)])
                    held += len(own)
                    if held >= chunk and (out := windows(False)):
                        yield batch_of(out)
        if waiting and (out := windows(True)):
            yield batch_of(out)

    return rows.mapInArrow(light(solve), SCHEMA)
