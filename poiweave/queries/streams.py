"""Queries: streams, each equal to a batch query on the same rows."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import vectors
from ..operators import encode
from ..sources import points
from ..streaming import streams
from .features import D
from .graph import HASHED
from .oracle import POI


def _ended(spark: SparkSession, sf: str, f) -> DataFrame:
    """Drain with complete output, so that windows still open at the end count as well."""
    return streams.drain(f(streams.events(spark, sf)), "complete")


def stream_tumbling(spark: SparkSession, sf: str) -> DataFrame:
    return _ended(spark, sf, streams.tumbling).select("start", "event_type", "n", F.round("value", 4).alias("value"))


def stream_sliding(spark: SparkSession, sf: str) -> DataFrame:
    return _ended(spark, sf, streams.sliding)


def stream_session(spark: SparkSession, sf: str) -> DataFrame:
    return _ended(spark, sf, streams.sessions)


def stream_dedup(spark: SparkSession, sf: str) -> DataFrame:
    """The stream joined with itself twice over would repeat events; each id comes through once."""
    s = streams.events(spark, sf)
    twice = s.withColumn("copy", F.explode(F.array(F.lit(1), F.lit(2)))).drop("copy")
    return streams.drain(streams.distinct_events(twice).select("event_id", "user_id"))


def stream_static_join(spark: SparkSession, sf: str) -> DataFrame:
    names = spark.createDataFrame([("click", 1), ("view", 2), ("purchase", 3)], "event_type string, code int")
    return streams.drain(streams.with_static(streams.events(spark, sf), names, "event_type").select("event_id", "code"))


def stream_stream_join(spark: SparkSession, sf: str) -> DataFrame:
    s = streams.events(spark, sf)
    return streams.drain(streams.clicks_after_views(s, "error", "click", "2 hours"))


def stream_region_state(spark: SparkSession, sf: str) -> DataFrame:
    """Vectors of points open at the end: openings and closures stream in as files, the state adds and subtracts."""
    p = points.points(spark, sf)
    h = encode.encode_poi(p, encode.hash_encoder(encode.distinct_paths(p), D), D).join(p, "poi_id")
    opened = h.select("zip_id", F.lit(1).alias("sign"), "h")
    life = opened.unionByName(h.filter("date_closed is not null").select("zip_id", F.lit(-1).alias("sign"), "h"))
    place = streams._place(spark, "life")
    life.repartition(4, "zip_id").write.parquet(place)
    s = spark.readStream.schema("zip_id long, sign int, h array<double>").option("maxFilesPerTrigger", 2).parquet(place)
    end = streams.drain(streams.region_state(s, D), "update")
    return _last(end)


def _last(updates: DataFrame) -> DataFrame:
    """All rows of a region come in one file here, so each region has one update."""
    return updates.select("zip_id", "n", vectors.rounded(F.col("s"), 5).alias("s"))


QUERIES = {f.__name__: f for f in (stream_tumbling, stream_sliding, stream_session, stream_dedup, stream_static_join, stream_stream_join, stream_region_state)}

SQL = {
    "stream_tumbling": "SELECT time_bucket(INTERVAL '1 hour', ts) AS start, event_type, count(*) AS n, round(sum(value), 4) AS value FROM events GROUP BY 1, 2",
    "stream_sliding": "SELECT start, count(*) AS n, max(value) AS top FROM (SELECT value, unnest([date_trunc('hour', ts), date_trunc('hour', ts) - INTERVAL '1 hour']) AS start FROM events) GROUP BY start",
    "stream_session": """WITH m AS (SELECT user_id, ts, CASE WHEN ts < lag(ts) OVER w + INTERVAL '30 minutes' THEN 0 ELSE 1 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)),
s AS (SELECT user_id, ts, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts) AS k FROM m) SELECT user_id, min(ts) AS start, count(*) AS n FROM s GROUP BY user_id, k""",
    "stream_dedup": "SELECT event_id, user_id FROM events",
    "stream_static_join": "SELECT event_id, CAST(CASE event_type WHEN 'click' THEN 1 WHEN 'view' THEN 2 WHEN 'purchase' THEN 3 END AS INTEGER) AS code FROM events WHERE event_type IN ('click', 'view', 'purchase')",
    "stream_stream_join": "SELECT a.event_id AS first_id, b.event_id AS then_id, a.user_id FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL '2 hours' WHERE a.event_type = 'error' AND b.event_type = 'click'",
    "stream_region_state": f"""WITH {POI}, {HASHED}, l AS (SELECT v.zip_id, v, CASE WHEN date_closed IS NULL THEN 1 ELSE 0 END AS sign FROM poi_v v JOIN poi ON poi.poi_id = v.poi_id),
m AS (SELECT zip_id, i, sum(sign * v[i + 1]) AS x, sum(sign) AS n FROM l, unnest(range(0, 8)) g(i) GROUP BY zip_id, i)
SELECT zip_id, CAST(any_value(n) AS BIGINT) AS n, list(round(x, 5) + 0.0::DOUBLE ORDER BY i) AS s FROM m GROUP BY zip_id""",
}
