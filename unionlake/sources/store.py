"""An index on disk: partitioned postings, set layout, centroids and a manifest; and a read source for set layouts.

    version=3/sets       set_id, n, flat, part, groups, own (sorted by set_id inside files)
    version=3/counts     c_bucket=.../ c, set_id, n
    version=3/manifest   one JSON row: parameters, counts, checksum

A version without a manifest is unfinished and is never read.
"""

from __future__ import annotations

import json
import zlib
from collections.abc import Iterator

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, EqualTo, Filter, GreaterThanOrEqual, InputPartition, LessThanOrEqual

from unionlake.operators.index import Index


def save(index: Index, folder: str, version: int, buckets: int = 64) -> dict:
    """Writes a version; its manifest comes last."""
    at = f"{folder.rstrip('/')}/version={version}"
    spark = index.sets.sparkSession
    index.sets.repartitionByRange("set_id").sortWithinPartitions("set_id").write.parquet(f"{at}/sets")
    counts = index.counts.withColumn("c_bucket", F.col("c") % buckets)
    counts.repartition("c_bucket").sortWithinPartitions("c", "set_id").write.partitionBy("c_bucket").parquet(f"{at}/counts")
    spark.createDataFrame([(i, c.tolist()) for i, c in enumerate(index.centroids)], "c int, m array<double>").write.parquet(f"{at}/centroids")
    manifest = {
        "version": version, "dim": index.dim, "n_c": len(index.centroids), "rho_low": index.rho_low, "rho_high": index.rho_high, "buckets": buckets,
        "sets": spark.read.parquet(f"{at}/sets").count(), "postings": spark.read.parquet(f"{at}/counts").count(), "checksum": zlib.crc32(np.ascontiguousarray(index.centroids).tobytes()),
    }
    spark.createDataFrame([(json.dumps(manifest),)], "value string").coalesce(1).write.text(f"{at}/manifest")
    return manifest


def versions(spark: SparkSession, folder: str) -> DataFrame:
    """One row per finished version, with what its manifest says."""
    schema = "version int, dim int, n_c int, rho_low double, rho_high double, buckets int, sets bigint, postings bigint, checksum bigint"
    return spark.read.text(f"{folder.rstrip('/')}/version=*/manifest").select(F.from_json("value", schema).alias("m")).select("m.*")


def load(spark: SparkSession, folder: str, version: int | None = None) -> Index:
    """A version, or the latest; raises if its centroids are not those of the manifest."""
    found = versions(spark, folder)
    m = (found.where(F.col("version") == version) if version is not None else found.orderBy(F.desc("version"))).first()
    if m is None:
        raise FileNotFoundError(f"no finished version in {folder}")
    at = f"{folder.rstrip('/')}/version={m['version']}"
    c = np.array([r["m"] for r in spark.read.parquet(f"{at}/centroids").orderBy("c").collect()], np.float64)
    if zlib.crc32(np.ascontiguousarray(c).tobytes()) != m["checksum"]:
        raise ValueError("the centroids do not match the manifest")
    return Index(c, spark.read.parquet(f"{at}/sets"), spark.read.parquet(f"{at}/counts").select("c", "set_id", "n"), m["dim"], m["rho_low"], m["rho_high"])


class _File(InputPartition):
    def __init__(self, path: str):
        self.path = path


class VecSetReader(DataSourceReader):
    def __init__(self, path: str):
        self.path, self.low, self.high = path, None, None

    def partitions(self) -> list[_File]:
        import pyarrow.fs as pafs

        fs, root = pafs.FileSystem.from_uri(self.path) if "://" in self.path else (pafs.LocalFileSystem(), self.path)
        return [_File(f.path) for f in fs.get_file_info(pafs.FileSelector(root, recursive=True)) if f.path.endswith(".parquet")]

    def read(self, partition: _File) -> Iterator:
        import pyarrow.compute as pc
        import pyarrow.dataset as ds
        import pyarrow.fs as pafs

        fs = pafs.FileSystem.from_uri(self.path)[0] if "://" in self.path else pafs.LocalFileSystem()
        keep = None
        for ok, bound in ((lambda b: pc.field("set_id") >= b, self.low), (lambda b: pc.field("set_id") <= b, self.high)):
            if bound is not None:
                keep = ok(bound) if keep is None else keep & ok(bound)
        yield from ds.dataset(partition.path, filesystem=fs, format="parquet").to_batches(columns=["set_id", "n", "flat"], filter=keep)


class PushdownReader(VecSetReader):
    def pushFilters(self, filters: list[Filter]) -> Iterator[Filter]:
        """Bounds on set_id prune row groups; Spark still checks every filter."""
        for f in filters:
            if getattr(f, "attribute", None) == ("set_id",):
                if isinstance(f, EqualTo | GreaterThanOrEqual):
                    self.low = f.value if self.low is None else max(self.low, f.value)
                if isinstance(f, EqualTo | LessThanOrEqual):
                    self.high = f.value if self.high is None else min(self.high, f.value)
            yield f


class VecSetSource(DataSource):
    """spark.read.format("vecset").load(folder): (set_id, n, flat) of a set layout; register with spark.dataSource.register.

    Option pushdown=true takes bounds on set_id into the scan; it needs spark.sql.python.filterPushdown.enabled.
    """

    @classmethod
    def name(cls) -> str:
        return "vecset"

    def schema(self) -> str:
        return "set_id bigint, n int, flat array<double>"

    def reader(self, schema) -> VecSetReader:
        return (PushdownReader if self.options.get("pushdown") == "true" else VecSetReader)(self.options["path"])
