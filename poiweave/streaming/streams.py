"""Structured Streaming: windows, de-duplication, joins, and a stateful accumulator of region vectors.

Each function takes a streaming frame and returns one; :func:`drain` runs it to the end of what is there and returns a batch
frame, so that results can be compared with batch queries on the same rows.
"""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.session import shared_folder

EVENTS = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"
LATE = "1 day"


def _place(spark: SparkSession, kind: str) -> str:
    return f"{shared_folder(spark)}/{kind}-{uuid.uuid4().hex}"


def events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The event table as a stream of files."""
    return spark.readStream.schema(EVENTS).option("pathGlobFilter", "*.parquet").parquet(f"{sf_dir}/events.parquet*")


def drain(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Process all that is there and stop; the sink is a Parquet table in the shared folder.

    Every batch overwrites the folder of its own number, so a batch that is run again after a failure doubles nothing. With ``complete`` only the last batch is kept, the state of all keys; with ``update`` all updates are kept, so a key has one
    row for each batch that touched it.
    """
    spark = stream.sparkSession
    out = _place(spark, "sink")

    def write(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(out if mode == "complete" else f"{out}/batch={number}")

    q = stream.writeStream.outputMode(mode).foreachBatch(write).option("checkpointLocation", _place(spark, "progress")).trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.schema(stream.schema).parquet(out).select(*stream.columns)


def tumbling(stream: DataFrame, width: str = "1 hour") -> DataFrame:
    w = stream.withWatermark("ts", LATE).groupBy(F.window("ts", width), "event_type").agg(F.count(F.lit(1)).alias("n"), F.sum("value").alias("value"))
    return w.select(F.col("window.start").alias("start"), "event_type", "n", "value")


def sliding(stream: DataFrame, width: str = "2 hours", step: str = "1 hour") -> DataFrame:
    w = stream.withWatermark("ts", LATE).groupBy(F.window("ts", width, step)).agg(F.count(F.lit(1)).alias("n"), F.max("value").alias("top"))
    return w.select(F.col("window.start").alias("start"), "n", "top")


def sessions(stream: DataFrame, gap: str = "30 minutes") -> DataFrame:
    w = stream.withWatermark("ts", LATE).groupBy(F.session_window("ts", gap), "user_id").agg(F.count(F.lit(1)).alias("n"))
    return w.select("user_id", F.col("session_window.start").alias("start"), "n")


def distinct_events(stream: DataFrame) -> DataFrame:
    return stream.withWatermark("ts", LATE).dropDuplicatesWithinWatermark(["event_id"])


def with_static(stream: DataFrame, static: DataFrame, key: str) -> DataFrame:
    return stream.join(static, key)


def clicks_after_views(stream: DataFrame, first: str = "view", then: str = "click", within: str = "10 minutes") -> DataFrame:
    """Stream-stream join: a user's ``then`` events at most ``within`` after a ``first`` event."""
    a = stream.filter(F.col("event_type") == first).select(F.col("event_id").alias("first_id"), F.col("user_id").alias("u1"), F.col("ts").alias("t1")).withWatermark("t1", LATE)
    b = stream.filter(F.col("event_type") == then).select(F.col("event_id").alias("then_id"), F.col("user_id").alias("u2"), F.col("ts").alias("t2")).withWatermark("t2", LATE)
    return a.join(b, F.expr(f"u1 = u2 AND t2 >= t1 AND t2 <= t1 + INTERVAL {within}")).select("first_id", "then_id", F.col("u1").alias("user_id"))


def region_state(stream: DataFrame, d: int) -> DataFrame:
    """Running sums of open points' vectors by region: (zip_id, n, s) after each batch, from rows (zip_id, sign, h).

    ``sign`` is 1 for an opening and -1 for a closure, so the state is a monoid and any order of arrival gives the same end.
    """

    def update(key: tuple, rows: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        n, s = state.get if state.exists else (0, [0.0] * d)
        s = list(s)
        for pdf in rows:
            for sign, h in zip(pdf["sign"], pdf["h"], strict=True):
                n += int(sign)
                for i in range(d):
                    s[i] += float(sign) * float(h[i])
        state.update((n, s))
        yield pd.DataFrame({"zip_id": [key[0]], "n": [n], "s": [s]})

    return stream.groupBy("zip_id").applyInPandasWithState(update, "zip_id long, n long, s array<double>", "n long, s array<double>", "update", "NoTimeout")
