"""Materialising in iterative operators."""

from __future__ import annotations

import gc
import os
import tempfile

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def shared_folder(spark: SparkSession) -> str:
    """The folder that driver and executors share: ``spark.checkpoint.dir``.

    Where it is unset, a folder of this machine serves a session whose threads are all on this machine; on a cluster it is an error.
    """
    context = spark.sparkContext
    folder = context.getConf().get("spark.checkpoint.dir")
    if folder:
        return folder
    if not context.master.startswith("local") or context.master.startswith("local-cluster"):
        raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
    return os.path.join(tempfile.gettempdir(), "poiweave-checkpoints")


def cut(df: DataFrame) -> DataFrame:
    """Materialise ``df`` with ``checkpoint()`` in the shared folder and cut its lineage."""
    context = df.sparkSession.sparkContext
    if not context.getCheckpointDir():
        context.setCheckpointDir(shared_folder(df.sparkSession))
    return df.checkpoint(eager=True)


def cut_and_release(df: DataFrame) -> DataFrame:
    """:func:`cut`, after which shuffle files that nothing needs any more are let go. The caller must hold no reference to ``df``, so it passes the expression itself."""
    spark = df.sparkSession
    out = cut(df)
    del df
    release(spark)
    return out


def release(spark: SparkSession) -> None:
    """Have Spark delete the shuffle files of tables that are gone, which it does once both collectors, Python's and that of the driver's JVM, have dropped what refers to them. Left alone, the JVM waits until its heap is full."""
    gc.collect()
    spark.sparkContext._jvm.System.gc()


def small(df: DataFrame, rows: int | None, most: int = 1_000_000) -> DataFrame:
    """``df`` marked for broadcast if its counted rows are few; otherwise left to a shuffled join."""
    return F.broadcast(df) if rows is not None and rows <= most else df


def spread(df: DataFrame, *keys: str) -> DataFrame:
    """``df`` dealt by ``keys`` to as many partitions as the session shuffles to (or has cores), which adaptive execution does not merge: for groups that cost far more than their bytes."""
    spark = df.sparkSession
    return df.repartition(max(int(spark.conf.get("spark.sql.shuffle.partitions")), spark.sparkContext.defaultParallelism), *keys)
