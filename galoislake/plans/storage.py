"""Tables in the shared folder: lineage ends there, and they outlive any executor."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import Column, DataFrame, Observation, SparkSession
from pyspark.sql import functions as F


def shared_dir(spark: SparkSession) -> str:
    """The folder the cluster names for checkpoints; one of our own only on a single machine."""
    named = spark.sparkContext.getCheckpointDir() or spark.conf.get("spark.checkpoint.dir", None)
    if not named:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("spark.checkpoint.dir names no shared folder")
        named = tempfile.mkdtemp(prefix="galoislake-")
        spark.sparkContext.setCheckpointDir(named)
    return named.rstrip("/")


def new_path(spark: SparkSession, name: str) -> str:
    return f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"


def settle(df: DataFrame, name: str) -> DataFrame:
    """Write df as Parquet and read it back."""
    path = new_path(df.sparkSession, name)
    df.write.parquet(path)
    out = df.sparkSession.read.schema(df.schema).parquet(path)
    out._settled_path = path
    return out


def settle_counted(df: DataFrame, name: str, **sums: Column) -> tuple[DataFrame, dict[str, int]]:
    """settle(df), with its row count n and the given sums, taken while it is written."""
    seen = Observation()
    totals = [F.coalesce(F.sum(c), F.lit(0)).cast("long").alias(k) for k, c in sums.items()]
    out = settle(df.observe(seen, F.count(F.lit(1)).alias("n"), *totals), name)
    return out, seen.get


def forget(df: DataFrame | None) -> None:
    """Delete what settle() wrote, once nothing reads it any more."""
    path = getattr(df, "_settled_path", None)
    if path:
        p = df.sparkSession._jvm.org.apache.hadoop.fs.Path(path)
        p.getFileSystem(df.sparkSession._jsc.hadoopConfiguration()).delete(p, True)
