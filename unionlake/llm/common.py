"""What several operators of this subpackage share: tables, shared folders, splits, ranges."""

from __future__ import annotations

import ctypes
import gc
import json
import math
import tempfile
import uuid
from collections.abc import Callable, Iterator
from weakref import WeakKeyDictionary

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_folder(spark: SparkSession, kind: str) -> str:
    """A new folder below the checkpoint folder that driver and executors share.

    The cluster names it in ``spark.checkpoint.dir``. Only a session in one JVM (tests) may do
    without that setting and gets a temporary folder of its own.
    """
    sc = spark.sparkContext
    base = sc.getConf().get("spark.checkpoint.dir") or sc.getCheckpointDir()
    if not base:
        if sc.master != "local" and not sc.master.startswith("local["):
            raise RuntimeError("spark.checkpoint.dir must name a folder that driver and executors share")
        base = "file://" + tempfile.mkdtemp(prefix="unionlake-")
    if not sc.getCheckpointDir():
        sc.setCheckpointDir(base)
    return f"{base.rstrip('/')}/{kind}-{uuid.uuid4().hex[:12]}"


def checkpointed(spark: SparkSession, df: DataFrame, kind: str) -> DataFrame:
    """df written once to the shared folder and read back: a cut of the lineage that survives lost executors."""
    path = shared_folder(spark, kind)
    df.write.parquet(path)
    out = spark.read.parquet(path)
    _FOLDERS[out] = path
    return out


_FOLDERS: WeakKeyDictionary[DataFrame, str] = WeakKeyDictionary()


def discard(spark: SparkSession, *frames: DataFrame) -> None:
    """Removes what `checkpointed` wrote for these frames, once all that was made from them is written."""
    for df in frames:
        path = spark._jvm.org.apache.hadoop.fs.Path(_FOLDERS.pop(df))
        path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)


def light(run: Callable) -> Callable:
    """`run` for mapInArrow; at a task's end its Python worker, which is kept for other tasks, gives unused memory back."""

    def task(batches):
        try:
            yield from run(batches)
        finally:
            give_back()

    return task


def give_back() -> None:
    gc.collect()
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)  # only some C libraries have it
    if trim:
        trim(0)


def portions(batch: pa.RecordBatch, column: int, size: int = 1 << 22) -> Iterator[pa.RecordBatch]:
    """The batch in slices of about `size` bytes of one text column, a row at least; none of no rows."""
    ends = np.cumsum(pc.fill_null(pc.binary_length(batch.column(column)), 0).to_numpy(zero_copy_only=False).astype(np.int64))
    low = 0
    while low < batch.num_rows:
        high = max(low + 1, int(np.searchsorted(ends, (ends[low - 1] if low else 0) + size, "right")))
        yield batch.slice(low, high - low)
        low = high


def unused(df: DataFrame, name: str) -> str:
    """A column name that df does not have, in any case of letters."""
    taken = {c.lower() for c in df.columns}
    while name.lower() in taken:
        name = "_" + name
    return name


def id_remainder(id_col: str, modulus: int) -> Column:
    """crc32 of the id written as text, modulo `modulus`; a null id counts as the empty text."""
    return F.crc32(F.coalesce(F.col(id_col).cast("string"), F.lit(""))) % modulus


def range_bounds(df: DataFrame, col: str, buckets: int) -> list[int]:
    """At most buckets - 1 ascending split values of a bigint column, from approximate quantiles."""
    if buckets < 2:
        return []
    shares = [i / buckets for i in range(1, buckets)]
    got = df.agg(F.percentile_approx(col, shares, max(10_000, 10 * buckets)).alias("b")).first()["b"]
    return sorted(set(got or []))


def range_bucket(col: Column, bounds: list[int], fan: int = 128) -> Column:
    """How many bounds are <= col, found over two levels of constant arrays; a null is 0."""
    if not bounds:
        return F.lit(0)

    def constant(values: list[int]) -> Column:
        return F.from_json(F.lit(json.dumps(values)), "array<bigint>")

    below = lambda values: F.size(F.filter(values, lambda b: b <= col))
    if len(bounds) <= fan:
        return F.when(col.isNull(), 0).otherwise(below(constant(bounds)))
    step = math.isqrt(len(bounds)) + 1
    coarse = below(constant(bounds[::step]))
    fine = below(F.slice(constant(bounds), (coarse - 1) * step + 1, F.lit(step)))
    return F.when(col.isNull() | (coarse == 0), 0).otherwise((coarse - 1) * step + fine)


def partitions_for(df: DataFrame, text_col: str, target_bytes: int, most: int = 100_000) -> int:
    """How many partitions of about target_bytes the texts fill."""
    total = df.agg(F.sum(F.octet_length(text_col)).alias("b")).first()["b"] or 0
    return int(min(most, max(1, math.ceil(total / target_bytes))))
