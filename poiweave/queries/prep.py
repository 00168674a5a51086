"""Queries: data preparation."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import category
from ..operators import prep
from ..sources import points
from .oracle import CELL, POI, RAW

BOX = (30.0, -120.0, 40.0, -80.0)


def prep_select(spark: SparkSession, sf: str) -> DataFrame:
    return prep.select_states(points.points(spark, sf), [0, 2, 4], (30.05, -120.0, 30.6, -85.0)).select("poi_id", "state_id", F.round("lat", 6).alias("lat"), F.round("lon", 6).alias("lon"))


def prep_project(spark: SparkSession, sf: str) -> DataFrame:
    p = prep.project_poi(points.raw_points(spark, sf))
    return p.select("poi_id", F.round("lat", 6).alias("lat"), F.round("lon", 6).alias("lon"), "state", "postcode", "category", "date_created", "date_closed")


def prep_normalise(spark: SparkSession, sf: str) -> DataFrame:
    return prep.normalise_text(points.raw_points(spark, sf)).select("poi_id", "state", "postcode")


def prep_dedup(spark: SparkSession, sf: str) -> DataFrame:
    line = points.table(spark, sf, "lineitem").select("l_orderkey", "l_linenumber", "l_suppkey", "l_partkey", "l_shipdate", "l_extendedprice", "l_quantity", "l_linestatus")
    return prep.deduplicate(line, ["l_orderkey", "l_linenumber"], ["l_suppkey", "l_partkey", "l_shipdate", "l_extendedprice", "l_quantity", "l_linestatus"]).select("l_orderkey", "l_linenumber", "l_suppkey", "l_partkey")


def _validated(spark: SparkSession, sf: str, mode: str) -> DataFrame:
    raw = prep.repair_swapped_coordinates(points.raw_points(spark, sf), BOX).withColumn("zip_id", F.col("postcode").cast("long"))
    cells = points.zip_cells(spark, sf).select(F.col("zip_id").alias("region_id"), prep.square_polygon().alias("polygon"))
    return prep.validate_region(raw, cells, mode=mode)


def prep_zip_correct(spark: SparkSession, sf: str) -> DataFrame:
    return _validated(spark, sf, "correct").select("poi_id", "zip_id", "region_ok")


def prep_zip_flag_counts(spark: SparkSession, sf: str) -> DataFrame:
    return _validated(spark, sf, "flag").groupBy("region_ok").agg(F.count(F.lit(1)).alias("n"))


def prep_swap_repair(spark: SparkSession, sf: str) -> DataFrame:
    r = prep.repair_swapped_coordinates(points.raw_points(spark, sf), BOX)
    return r.select("poi_id", F.round("lat", 6).alias("lat"), F.round("lon", 6).alias("lon"), "swapped")


def category_levels(spark: SparkSession, sf: str) -> DataFrame:
    p = points.raw_points(spark, sf).withColumn("path", category.parse(F.col("category")))
    return p.select("poi_id", F.size("path").alias("depth"), *(category.level(F.col("path"), i).alias(f"c{i}") for i in range(1, 7)))


def category_rollup(spark: SparkSession, sf: str) -> DataFrame:
    p = points.points(spark, sf).withColumn("level", F.explode(F.sequence(F.lit(1), F.size("category_path"))))
    return p.groupBy("level", category.prefix(F.col("category_path"), F.col("level")).alias("prefix")).agg(F.count(F.lit(1)).alias("n"))


def snapshot_counts(spark: SparkSession, sf: str) -> DataFrame:
    days = ("1994-01-01", "1996-07-01", "1999-01-01")
    parts = [prep.snapshot(points.points(spark, sf), d).groupBy("state_id").agg(F.count(F.lit(1)).alias("n")).withColumn("as_of", F.lit(d)) for d in days]
    return parts[0].unionByName(parts[1]).unionByName(parts[2])


def turnover_monthly(spark: SparkSession, sf: str) -> DataFrame:
    return prep.turnover(points.points(spark, sf))


def category_top(spark: SparkSession, sf: str) -> DataFrame:
    return prep.category_frequency(points.points(spark, sf), 2).orderBy(F.desc("n"), "prefix").limit(10)


def sample_fixed(spark: SparkSession, sf: str) -> DataFrame:
    return prep.uniform_sample(points.points(spark, sf), 1000).select("poi_id", "state_id")


def dataset_stats(spark: SparkSession, sf: str) -> DataFrame:
    p = points.points(spark, sf)
    return prep.graph_statistics(p, p.select(F.col("poi_id").alias("src")).filter("false")).drop("edges")


def state_stats(spark: SparkSession, sf: str) -> DataFrame:
    return points.points(spark, sf).groupBy("state_id").agg(F.count(F.lit(1)).alias("nodes"), F.count_distinct("county_id").alias("counties"), F.count_distinct("zip_id").alias("zips"), F.count_distinct("locality_id").alias("localities"))


QUERIES = {f.__name__: f for f in (prep_select, prep_project, prep_normalise, prep_dedup, prep_zip_correct, prep_zip_flag_counts, prep_swap_repair, category_levels, category_rollup, snapshot_counts, turnover_monthly, category_top, sample_fixed, dataset_stats, state_stats)}

_FIXED = f"""{RAW},
fixed AS (SELECT poi_id, postcode, true_zip, swapped, CASE WHEN swapped THEN lon ELSE lat END AS lat, CASE WHEN swapped THEN lat ELSE lon END AS lon
  FROM (SELECT *, NOT (lat BETWEEN 30 AND 40 AND lon BETWEEN -120 AND -80) AND (lon BETWEEN 30 AND 40 AND lat BETWEEN -120 AND -80) AS swapped FROM raw)),
valid AS (SELECT poi_id, coalesce(c.zip_id, CAST(postcode AS BIGINT)) AS zip_id, coalesce(c.zip_id = CAST(postcode AS BIGINT), false) AS region_ok
  FROM fixed LEFT JOIN cell c ON lat >= lat0 AND lat < lat0 + 0.1::DOUBLE AND lon >= lon0 AND lon < lon0 + 0.1::DOUBLE)"""
_SNAP = " UNION ALL ".join(f"SELECT state_id, count(*) AS n, '{d}' AS as_of FROM poi WHERE date_created <= DATE '{d}' AND (date_closed IS NULL OR date_closed > DATE '{d}') GROUP BY state_id" for d in ("1994-01-01", "1996-07-01", "1999-01-01"))

SQL = {
    "prep_select": f"WITH {POI} SELECT poi_id, state_id, round(lat, 6) AS lat, round(lon, 6) AS lon FROM poi WHERE state_id IN (0, 2, 4) AND lat BETWEEN 30.05::DOUBLE AND 30.6::DOUBLE AND lon BETWEEN -120 AND -85",
    "prep_project": f"WITH {RAW} SELECT poi_id, round(lat, 6) AS lat, round(lon, 6) AS lon, state, postcode, category, date_created, date_closed FROM raw",
    "prep_normalise": f"WITH {RAW} SELECT poi_id, regexp_replace(upper(trim(state)), '\\s+', ' ', 'g') AS state, lpad(postcode, 5, '0') AS postcode FROM raw",
    "prep_dedup": f"WITH {POI} SELECT l_orderkey, l_linenumber, l_suppkey, l_partkey FROM line1",
    "prep_zip_correct": f"WITH {_FIXED} SELECT poi_id, zip_id, region_ok FROM valid",
    "prep_zip_flag_counts": f"WITH {_FIXED} SELECT region_ok, count(*) AS n FROM valid GROUP BY region_ok",
    "prep_swap_repair": f"WITH {_FIXED} SELECT poi_id, round(lat, 6) AS lat, round(lon, 6) AS lon, swapped FROM fixed",
    "category_levels": f"""WITH {RAW}, q AS (SELECT poi_id, list_transform(string_split(replace(replace(category, '[', ''), ']', ''), '->'), lambda x: trim(x)) AS path FROM raw)
SELECT poi_id, len(path) AS depth, path[1] AS c1, path[2] AS c2, path[3] AS c3, path[4] AS c4, path[5] AS c5, path[6] AS c6 FROM q""",
    "category_rollup": f"WITH {POI} SELECT level, array_to_string(list_slice(category_path, 1, level), '>') AS prefix, count(*) AS n FROM (SELECT category_path, unnest(range(1, len(category_path) + 1)) AS level FROM poi) GROUP BY 1, 2",
    "snapshot_counts": f"WITH {POI} {_SNAP}",
    "turnover_monthly": f"""WITH {POI}, e AS (SELECT date_created AS day, 1 AS o, 0 AS c FROM poi UNION ALL SELECT date_closed, 0, 1 FROM poi WHERE date_closed IS NOT NULL)
SELECT CAST(date_trunc('month', day) AS DATE) AS period, sum(o) AS opened, sum(c) AS closed FROM e GROUP BY 1""",
    "category_top": f"WITH {POI} SELECT array_to_string(list_slice(category_path, 1, 2), '>') AS prefix, count(*) AS n FROM poi GROUP BY 1 ORDER BY n DESC, prefix LIMIT 10",
    "sample_fixed": f"WITH {POI} SELECT poi_id, state_id FROM poi ORDER BY md5('1:' || poi_id), poi_id LIMIT 1000",
    "dataset_stats": f"WITH {POI} SELECT count(*) AS nodes, count(DISTINCT state_id) AS graphs, count(DISTINCT zip_id) AS zips, count(DISTINCT locality_id) AS localities FROM poi",
    "state_stats": f"WITH {POI} SELECT state_id, count(*) AS nodes, count(DISTINCT county_id) AS counties, count(DISTINCT zip_id) AS zips, count(DISTINCT locality_id) AS localities FROM poi GROUP BY state_id",
}
assert CELL in POI
