"""Tables in the folder that executors share, storage of descriptors, transfers."""

from __future__ import annotations

import tempfile
import time
import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, functions as F

_own_folder: list[str] = []
#: Paths of the tables parked inside each open park_only.
_parked: list[list[str]] = []


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_folder(spark: SparkSession) -> str:
    """spark.checkpoint.dir; where that is unset a folder of this process, which only a local master can share."""
    named = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if named:
        return named.rstrip("/")
    if not spark.sparkContext.master.startswith("local"):
        raise RuntimeError("spark.checkpoint.dir is unset: executors on other machines would not see each other's tables")
    if not _own_folder:
        _own_folder.append("file://" + tempfile.mkdtemp(prefix="shared-"))
    return _own_folder[0]


def new_folder(spark: SparkSession, label: str) -> str:
    """A path in the shared folder that nothing uses; an open park_only deletes it at its end."""
    path = f"{shared_folder(spark)}/{label}-{uuid.uuid4().hex}"
    if _parked:
        _parked[-1].append(path)
    return path


def park(df: DataFrame, label: str) -> DataFrame:
    """Write a table to the shared folder and read it: cuts lineage, survives lost executors."""
    path = new_folder(df.sparkSession, label)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def delete(spark: SparkSession, path: str) -> None:
    """Delete a file or folder of any file system that the session knows."""
    there = spark._jvm.org.apache.hadoop.fs.Path(path)
    there.getFileSystem(spark._jsc.hadoopConfiguration()).delete(there, True)


def park_only(spark: SparkSession, make: Callable[[], DataFrame], label: str) -> DataFrame:
    """Park what ``make`` gives and delete the tables that it parked on its way."""
    _parked.append([])
    try:
        out = park(make(), label)
        mine = _parked[-1].pop()
    finally:
        for path in _parked.pop():
            delete(spark, path)
    if _parked:
        _parked[-1].append(mine)
    return out


def write(df: DataFrame, path: str, partition_by: list[str] | None = None, max_records: int = 1_000_000, sort_by: list[str] | None = None, replication: int | None = None) -> None:
    """Descriptor or index tables as Parquet; ``replication`` is passed to the file system of the session."""
    if replication:
        df.sparkSession._jsc.hadoopConfiguration().set("dfs.replication", str(replication))
    if sort_by:
        df = df.repartitionByRange(*sort_by).sortWithinPartitions(*sort_by)
    writer = df.write.mode("overwrite").option("maxRecordsPerFile", max_records)
    (writer.partitionBy(*partition_by) if partition_by else writer).parquet(path)


def stage_in(spark: SparkSession, source: str, target: str) -> dict[str, float]:
    """Copy a table from the durable to the cluster's store; seconds and rows."""
    began = time.perf_counter()
    spark.read.parquet(source).write.mode("overwrite").parquet(target)
    return {"seconds": time.perf_counter() - began, "rows": spark.read.parquet(target).count()}


def size_of(spark: SparkSession, path: str) -> int:
    """Bytes below a path, from the file system that holds it."""
    p = spark._jvm.org.apache.hadoop.fs.Path(path)
    return p.getFileSystem(spark._jsc.hadoopConfiguration()).getContentSummary(p).getLength()


def elastic_conf(lo: int, hi: int) -> dict[str, str]:
    """Settings for a cluster that adds and removes executors."""
    return {"spark.dynamicAllocation.enabled": "true", "spark.dynamicAllocation.minExecutors": str(lo), "spark.dynamicAllocation.maxExecutors": str(hi), "spark.dynamicAllocation.shuffleTracking.enabled": "true"}


def check_vectors(df: DataFrame) -> int:
    """The dimension of column v; raises where rows differ or hold nulls."""
    row = df.agg(F.min(F.size("v")).alias("a"), F.max(F.size("v")).alias("b"), F.count_if(F.col("v").isNull()).alias("nulls")).first()
    if row.nulls or row.a != row.b:
        raise ValueError(f"descriptors of {row.a} to {row.b} entries, {row.nulls} nulls")
    return row.a or 0
