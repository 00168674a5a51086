"""SQL for the derived tables, for DuckDB."""

from __future__ import annotations

from ..sources.points import DENSITY, KEEP, TYPES

_KIND = "CASE p_type " + " ".join(f"WHEN '{x}' THEN {k}" for k, x in enumerate(TYPES)) + " END"


def pick(values: tuple[int, ...], index: str) -> str:
    return f"list_extract([{', '.join(map(str, values))}], CAST({index} AS BIGINT) + 1)"


CELL = """cell AS (
  SELECT s_suppkey AS zip_id, s_nationkey AS county_id, n_regionkey AS state_id, idx, w,
    30.0::DOUBLE + 0.1::DOUBLE * (idx // w) AS lat0, -120.0::DOUBLE + 8.0::DOUBLE * n_regionkey + 0.1::DOUBLE * (idx % w) AS lon0
  FROM (SELECT s_suppkey, s_nationkey, n_regionkey,
      row_number() OVER (PARTITION BY n_regionkey ORDER BY s_nationkey, s_suppkey) - 1 AS idx,
      CAST(ceil(sqrt(count(*) OVER (PARTITION BY n_regionkey))) AS BIGINT) AS w
    FROM supplier JOIN nation ON s_nationkey = n_nationkey))"""

PATH = """list_slice([p_type, split_part(p_name, ' ', 2), split_part(p_name, ' ', 1), p_brand,
    'size' || CAST(p_size // 10 AS VARCHAR), 'price' || CAST(CAST(floor(p_retailprice / 25) AS BIGINT) AS VARCHAR)], 1, 2 + p_partkey % 5)"""

POI = f"""{CELL},
line1 AS (SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY l_orderkey, l_linenumber
    ORDER BY l_suppkey, l_partkey, l_shipdate, l_extendedprice, l_quantity, l_linestatus) AS rn FROM lineitem) WHERE rn = 1),
poi0 AS (SELECT l_orderkey * 8 + l_linenumber AS poi_id, l_partkey, l_shipdate, l_linestatus, {_KIND} AS t, {PATH} AS category_path, cell.*
  FROM line1 JOIN part ON l_partkey = p_partkey JOIN cell ON l_suppkey = zip_id),
poi1 AS (SELECT *, ((poi_id * 7919 + 104729) % 9973 + 0.5::DOUBLE) / 9973 AS u, ((poi_id * 6101 + l_partkey * 31 + 1299709) % 9967 + 0.5::DOUBLE) / 9967 AS v,
    (t + zip_id) % 6 AS tt, (poi_id * 13 + 5) % 5 = 0 AS spread
  FROM poi0 WHERE (poi_id * 37 + 11) % 100 < {pick(KEEP, "(t * (1 + zip_id % 5) + zip_id) % 6")}),
poi AS (SELECT poi_id,
    lat0 + CASE WHEN spread THEN v ELSE 0.25::DOUBLE + 0.5::DOUBLE * (tt // 3) + (v - 0.5::DOUBLE) * 0.3::DOUBLE END * 0.1::DOUBLE AS lat,
    lon0 + CASE WHEN spread THEN u ELSE 0.2::DOUBLE + 0.3::DOUBLE * (tt % 3) + (u - 0.5::DOUBLE) * 0.3::DOUBLE END * 0.1::DOUBLE AS lon,
    state_id, county_id, zip_id, zip_id * 2 + poi_id % 2 AS locality_id, t, category_path,
    CAST(l_shipdate AS DATE) AS date_created,
    CASE WHEN l_linestatus = 'F' AND poi_id % 4 = 0 THEN CAST(l_shipdate AS DATE) + CAST(poi_id % 1500 AS INTEGER) END AS date_closed
  FROM poi1)"""

RAW = f"""{POI},
raw AS (SELECT poi_id,
    CASE WHEN (poi_id * 43 + 5) % 97 = 0 THEN lon ELSE lat END AS lat, CASE WHEN (poi_id * 43 + 5) % 97 = 0 THEN lat ELSE lon END AS lon,
    CASE poi_id % 3 WHEN 0 THEN upper('State ' || state_id) WHEN 1 THEN lower('State ' || state_id) ELSE '  State ' || state_id || ' ' END AS state,
    CAST(CASE WHEN (poi_id * 41 + 3) % 50 = 0 THEN (zip_id + 1) % (SELECT count(*) FROM cell) ELSE zip_id END AS VARCHAR) AS postcode,
    '[' || array_to_string(category_path, ' -> ') || ']' AS category, date_created, date_closed, zip_id AS true_zip
  FROM poi)"""

LABEL = f"""label AS (SELECT p.state_id, p.county_id, p.zip_id,
    sum({pick(DENSITY, "t")}) / (11.132::DOUBLE * 11.132::DOUBLE * cos(radians(max(lat0) + 0.05::DOUBLE))) AS density,
    100.0::DOUBLE + 30 * (p.county_id % 7) + 60 * avg(CASE WHEN t IN (1, 3) THEN 1.0::DOUBLE ELSE 0.0::DOUBLE END) + p.zip_id * 37 % 41 AS price
  FROM poi p JOIN cell ON cell.zip_id = p.zip_id GROUP BY p.state_id, p.county_id, p.zip_id)"""

VISIT = f"""visit AS (SELECT o_custkey AS visitor, row_number() OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey, l_linenumber, l_partkey) - 1 AS pos,
    {PATH} AS category_path
  FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN part ON l_partkey = p_partkey)"""


def prefixes(levels: int, source: str = "poi") -> str:
    """CTE ``prefix`` (category prefix text of each path of ``source``, with its depth)."""
    return f"""prefix AS (SELECT DISTINCT array_to_string(list_slice(category_path, 1, i), '>') AS prefix, i AS level
  FROM (SELECT DISTINCT category_path FROM {source}), unnest(range(1, {levels} + 1)) AS g(i) WHERE i <= len(category_path))"""


def dist(a: str, b: str) -> str:
    """Great-circle metres between two rows with lat and lon."""
    return f"""2 * 6371000.0::DOUBLE * asin(sqrt(least(1.0::DOUBLE, pow(sin(radians({b}.lat - {a}.lat) / 2), 2)
      + cos(radians({a}.lat)) * cos(radians({b}.lat)) * pow(sin(radians({b}.lon - {a}.lon) / 2), 2))))"""
