"""Shared storage for intermediate tables: lineage is cut by written tables, which survive lost executors."""

from __future__ import annotations

import atexit
import gc
import shutil
import tempfile
import uuid
from functools import cache
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession


@cache
def _local_dir() -> str:
    """A folder of this process, for local runs and tests where nothing is configured; it goes when the process ends."""
    base = tempfile.mkdtemp(prefix="headcount-")
    atexit.register(shutil.rmtree, base, ignore_errors=True)
    return Path(base).as_uri()


def shared_dir(spark: SparkSession) -> str:
    """A new folder in the storage that driver and executors share: the session's checkpoint folder."""
    base = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not base:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        base = _local_dir()
    return f"{base}/hc-{uuid.uuid4().hex}"


#: Bytes of a table per core below which it is dealt out: the least split Spark makes of a file.
LEAST_SPLIT = 4 << 20


def dealt(df: DataFrame) -> DataFrame:
    """``df`` as it is, or, where it has less than the least split a core, dealt evenly over the cores.

    A small table is often a single row group, which one task reads; all that follows without a shuffle would stay in that task.
    The shuffle is of 4 MB a core at most, and larger tables, whose splits keep the cores busy, have none."""
    cores = df.sparkSession.sparkContext.defaultParallelism
    size = int(str(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))
    return df.repartition(cores) if size < cores * LEAST_SPLIT else df


def stored(df: DataFrame, name: str = "t") -> DataFrame:
    """Write ``df`` to shared storage once and read it back."""
    path = f"{shared_dir(df.sparkSession)}-{name}"
    df.write.parquet(path)
    out = df.sparkSession.read.schema(df.schema).parquet(path)
    out._headcount_path = path
    return out


def dropped(*tables: DataFrame) -> None:
    """Delete tables that :func:`stored` has written, once everything that reads them has been written itself."""
    for t in tables:
        if path := getattr(t, "_headcount_path", None):
            target = t.sparkSession._jvm.org.apache.hadoop.fs.Path(path)
            target.getFileSystem(t.sparkSession._jsc.hadoopConfiguration()).delete(target, True)


def release(spark: SparkSession) -> None:
    """Let Spark's cleaner drop the shuffle files of finished steps now. It does so when the driver's heap is collected, which
    on a driver that holds little can be long after a step has ended and its files have filled the disks. Tables that Python still
    holds in cycles would keep theirs."""
    gc.collect()
    spark._jvm.System.gc()
