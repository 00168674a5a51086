"""Session helpers shared by the training-data operators."""

from __future__ import annotations

import os
import tempfile

from pyspark.sql import Column, DataFrame, SparkSession
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


def remove(spark: SparkSession, path: str) -> None:
    """Delete a folder in whatever store it is."""
    jvm = spark.sparkContext._jvm
    place = jvm.org.apache.hadoop.fs.Path(path)
    place.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(place, True)


def cut(df: DataFrame) -> DataFrame:
    """Materialise ``df`` with ``checkpoint()`` in the shared folder and cut its lineage."""
    context = df.sparkSession.sparkContext
    if not context.getCheckpointDir():
        context.setCheckpointDir(shared_folder(df.sparkSession))
    return df.checkpoint(eager=True)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A given table, read by Spark so that any store Spark knows can hold it."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def held_out(doc_id: Column) -> Column:
    """Rows kept out of training: crc32 of the id's decimal text leaves no remainder mod 5 (a null id is held out)."""
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % 5 == 0, F.lit(True))


def bounded_sample(df: DataFrame, stratum: str, key: str, rows: int, max_strata: int = 1000) -> DataFrame:
    """About ``rows`` rows of each value of ``stratum``, chosen by a hash of ``key`` and the same in every run.

    The counts per stratum cover all rows; the share kept is ``rows / count``. A stratum with at most
    ``rows`` rows is kept whole. More than ``max_strata`` distinct values raise an error, so
    that what reaches the driver is bounded by ``rows * max_strata``.
    """
    counts = df.groupBy(stratum).count().limit(max_strata + 1).collect()
    if len(counts) > max_strata:
        raise ValueError(f"{stratum} has more than {max_strata} values")
    draw = F.pmod(F.xxhash64(F.lit(20_011), F.col(key)), F.lit(1 << 30)) / float(1 << 30)
    wanted = F.lit(False)
    for row in counts:
        if row[0] is not None:
            wanted = wanted | ((F.col(stratum) == F.lit(row[0])) & (draw < F.lit(min(1.0, rows / row["count"]))))
    return df.filter(wanted)


def label_share(labels: DataFrame, column: str) -> float | None:
    """Share of label 1 among all training labels; None if there are none."""
    return labels.filter(F.col(column).isin(0, 1) & F.col("doc_id").isNotNull() & ~held_out(F.col("doc_id"))).agg(F.avg(F.col(column).cast("double"))).first()[0]


def labelled_sample(documents: DataFrame, labels: DataFrame, column: str, per_label: int) -> DataFrame:
    """doc_id, __label, __text of a bounded sample of labelled training rows, the same in every run; texts are whole.

    Only rows that are not held out, with an id and a label of 0 or 1, count: at most about ``per_label`` of each label. A repeated id counts once.
    """
    known = labels.select("doc_id", F.col(column).cast("int").alias("__label")).filter(F.col("__label").isin(0, 1) & F.col("doc_id").isNotNull() & ~held_out(F.col("doc_id")))
    chosen = bounded_sample(known, "__label", "doc_id", per_label).groupBy("doc_id").agg(F.max("__label").alias("__label"))
    texts = documents.select("doc_id", F.coalesce("text", F.lit("")).alias("__text"))
    return texts.join(F.broadcast(chosen), "doc_id").groupBy("doc_id", "__label").agg(F.min("__text").alias("__text"))
