"""Points of interest derived from the given tables by integer rules (FIXTURES.md F1-F3, F5, F6).

Every rule is written once more as SQL in :mod:`poiweave.queries.oracle`; both sides share only the constants below.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

#: Fixed values of the derivation.
TYPES = ("ECONOMY", "LARGE", "MEDIUM", "PROMO", "SMALL", "STANDARD")
KEEP = (100, 70, 45, 25, 15, 10)
DENSITY = (5, 40, 15, 80, 2, 25)
SIDE, LAT0, LON0, STATE_STEP = 0.1, 30.0, -120.0, 8.0


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def pick(values: tuple[int, ...], index: Column) -> Column:
    return F.element_at(F.array(*map(F.lit, values)), (index + 1).cast("int"))


def zip_cells(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One square cell for every supplier, laid out row by row inside its state. The optimiser broadcasts it where its estimated size allows."""
    s = table(spark, sf_dir, "supplier").select("s_suppkey", "s_nationkey").join(table(spark, sf_dir, "nation").select("n_nationkey", "n_regionkey"), F.col("s_nationkey") == F.col("n_nationkey"))
    state = Window.partitionBy("n_regionkey")
    s = s.withColumn("idx", F.row_number().over(state.orderBy("s_nationkey", "s_suppkey")).cast("long") - 1).withColumn("w", F.ceil(F.sqrt(F.count(F.lit(1)).over(state))).cast("long"))
    lat0 = F.lit(LAT0) + F.lit(SIDE) * F.floor(F.col("idx") / F.col("w"))
    lon0 = F.lit(LON0) + F.lit(STATE_STEP) * F.col("n_regionkey") + F.lit(SIDE) * (F.col("idx") % F.col("w"))
    return s.select(F.col("s_suppkey").cast("long").alias("zip_id"), F.col("s_nationkey").cast("int").alias("county_id"), F.col("n_regionkey").cast("int").alias("state_id"), "idx", "w", lat0.alias("lat0"), lon0.alias("lon0"))


def polygons(cells: DataFrame) -> DataFrame:
    """``cells`` plus ``polygon``, the corners of each region's square in order, and ``area_km2``."""
    corner = lambda y, x: F.struct((F.col("lon0") + x).alias("lon"), (F.col("lat0") + y).alias("lat"))
    area = F.lit(11.132 * 11.132) * F.cos(F.radians(F.col("lat0") + SIDE / 2))
    return cells.withColumns({"polygon": F.array(corner(0.0, 0.0), corner(0.0, SIDE), corner(SIDE, SIDE), corner(SIDE, 0.0)), "area_km2": area})


def distinct_lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One line for each (order, line number): the first in a fixed order."""
    line = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_shipdate", "l_extendedprice", "l_quantity", "l_linestatus")
    order = Window.partitionBy("l_orderkey", "l_linenumber").orderBy("l_suppkey", "l_partkey", "l_shipdate", "l_extendedprice", "l_quantity", "l_linestatus")
    return line.withColumn("rn", F.row_number().over(order)).filter("rn = 1").drop("rn")


def category_path() -> Column:
    noun, adjective = F.element_at(F.split("p_name", " "), 2), F.element_at(F.split("p_name", " "), 1)
    size = F.concat(F.lit("size"), F.floor(F.col("p_size") / 10).cast("string"))
    price = F.concat(F.lit("price"), F.floor(F.col("p_retailprice") / 25).cast("string"))
    return F.slice(F.array("p_type", noun, adjective, "p_brand", size, price), 1, (F.lit(2) + F.col("p_partkey") % 5).cast("int"))


def points(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The ``poi`` table: columns of :data:`poiweave.schema.POI` plus u and v free."""
    cells = zip_cells(spark, sf_dir)
    part = table(spark, sf_dir, "part").select("p_partkey", "p_type", category_path().alias("category_path"))
    base = distinct_lines(spark, sf_dir).select((F.col("l_orderkey") * 8 + F.col("l_linenumber")).alias("poi_id"), "l_partkey", F.col("l_suppkey").alias("zip_id"), "l_shipdate", "l_linestatus")
    rows = base.join(part, F.col("l_partkey") == F.col("p_partkey")).join(cells, "zip_id")
    kind = F.array_position(F.array(*map(F.lit, TYPES)), F.col("p_type")).cast("int") - 1
    rows = rows.withColumn("t", kind)
    keep = pick(KEEP, (F.col("t") * (1 + F.col("zip_id") % 5) + F.col("zip_id")) % 6)
    rows = rows.filter((F.col("poi_id") * 37 + 11) % 100 < keep)
    u = ((F.col("poi_id") * 7919 + 104729) % 9973 + 0.5) / 9973
    v = ((F.col("poi_id") * 6101 + F.col("l_partkey") * 31 + 1299709) % 9967 + 0.5) / 9967
    tt = (F.col("t") + F.col("zip_id")) % 6
    spread = (F.col("poi_id") * 13 + 5) % 5 == 0
    x = F.when(spread, u).otherwise(F.lit(0.2) + F.lit(0.3) * (tt % 3) + (u - 0.5) * 0.3)
    y = F.when(spread, v).otherwise(F.lit(0.25) + F.lit(0.5) * F.floor(tt / 3) + (v - 0.5) * 0.3)
    created = F.to_date("l_shipdate")
    closed = F.when((F.col("l_linestatus") == "F") & (F.col("poi_id") % 4 == 0), F.date_add(created, (F.col("poi_id") % 1500).cast("int")))
    return rows.select(
        "poi_id",
        (F.col("lat0") + y * SIDE).alias("lat"),
        (F.col("lon0") + x * SIDE).alias("lon"),
        "state_id",
        "county_id",
        "zip_id",
        (F.col("zip_id") * 2 + F.col("poi_id") % 2).alias("locality_id"),
        "t",
        "category_path",
        created.alias("date_created"),
        closed.alias("date_closed"),
    )


def raw_points(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``poi`` with planted defects and text columns, as a catalogue would deliver it (F2)."""
    cells = zip_cells(spark, sf_dir)
    n = cells.agg(F.count(F.lit(1)).alias("n_zip"))
    p = points(spark, sf_dir).crossJoin(F.broadcast(n))
    wrong = (F.col("poi_id") * 41 + 3) % 50 == 0
    swapped = (F.col("poi_id") * 43 + 5) % 97 == 0
    declared = F.when(wrong, (F.col("zip_id") + 1) % F.col("n_zip")).otherwise(F.col("zip_id"))
    name = F.concat(F.lit("State "), F.col("state_id").cast("string"))
    state = F.when(F.col("poi_id") % 3 == 0, F.upper(name)).when(F.col("poi_id") % 3 == 1, F.lower(name)).otherwise(F.concat(F.lit("  "), name, F.lit(" ")))
    return p.select(
        "poi_id",
        F.when(swapped, F.col("lon")).otherwise(F.col("lat")).alias("lat"),
        F.when(swapped, F.col("lat")).otherwise(F.col("lon")).alias("lon"),
        state.alias("state"),
        declared.cast("string").alias("postcode"),
        F.concat(F.lit("["), F.array_join("category_path", " -> "), F.lit("]")).alias("category"),
        "date_created",
        "date_closed",
        F.col("zip_id").alias("true_zip"),
    )


def labels(poi: DataFrame, cells: DataFrame) -> DataFrame:
    """Planted labels of every region: ``density`` (partly explained by categories) and ``price`` (hardly)."""
    area = F.lit(11.132 * 11.132) * F.cos(F.radians(F.col("lat0") + SIDE / 2))
    sums = poi.groupBy("zip_id").agg(F.sum(pick(DENSITY, F.col("t"))).alias("people"), F.avg(F.when(F.col("t").isin(1, 3), 1.0).otherwise(0.0)).alias("share"))
    rows = sums.join(cells, "zip_id")
    price = F.lit(100.0) + 30 * (F.col("county_id") % 7) + 60 * F.col("share") + F.col("zip_id") * 37 % 41
    return rows.select("state_id", "county_id", "zip_id", (F.col("people") / area).alias("density"), price.alias("price"))


def customer_visits(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Ordered category visits (F6): customer, position from 0, category path."""
    orders = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", "o_orderdate")
    line = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey")
    part = table(spark, sf_dir, "part").select("p_partkey", category_path().alias("category_path"))
    rows = line.join(orders, F.col("l_orderkey") == F.col("o_orderkey")).join(part, F.col("l_partkey") == F.col("p_partkey"))
    order = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey", "l_linenumber", "l_partkey")
    return rows.select(F.col("o_custkey").alias("visitor"), (F.row_number().over(order) - 1).alias("pos"), "category_path")


def event_visits(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Two-level paths of events in time order (F6)."""
    e = table(spark, sf_dir, "events")
    band = F.concat(F.lit("k"), F.floor(F.get_json_object("props", "$.k").cast("int") / 20).cast("string"))
    order = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return e.select(F.col("user_id").alias("visitor"), (F.row_number().over(order) - 1).alias("pos"), F.array("event_type", band).alias("category_path"))
