"""Folders that driver and executors share, for tables between steps."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def folder(spark: SparkSession, kind: str) -> str:
    """A new folder below the one that spark.checkpoint.dir names; only a session in one JVM may do without that setting."""
    sc = spark.sparkContext
    base = sc.getConf().get("spark.checkpoint.dir") or sc.getCheckpointDir()
    if not base:
        if sc.master != "local" and not sc.master.startswith("local["):
            raise RuntimeError("spark.checkpoint.dir must name a folder that driver and executors share")
        base = "file://" + tempfile.mkdtemp(prefix="unionlake-")
        sc.setCheckpointDir(base)
    return f"{base.rstrip('/')}/{kind}-{uuid.uuid4().hex[:10]}"


def written(df: DataFrame, kind: str) -> DataFrame:
    """df written once and read back."""
    spark = df.sparkSession
    path = folder(spark, kind)
    df.write.parquet(path)
    return spark.read.parquet(path)


def size_of(spark: SparkSession, path: str) -> int:
    """Bytes of all files below a folder."""
    p = spark._jvm.org.apache.hadoop.fs.Path(path)
    return p.getFileSystem(spark._jsc.hadoopConfiguration()).getContentSummary(p).getLength()
