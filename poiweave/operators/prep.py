"""Preparation of point tables: selection, cleaning, de-duplication, region validation, statistics."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import category, geo


def select_states(poi: DataFrame, states: Sequence[int], bbox: tuple[float, float, float, float] | None = None) -> DataFrame:
    """Rows of the wanted states, inside (lat, lon, lat, lon) bounds if given; both filters reach the scan."""
    out = poi.filter(F.col("state_id").isin(*states))
    return out if bbox is None else out.filter(F.col("lat").between(bbox[0], bbox[2]) & F.col("lon").between(bbox[1], bbox[3]))


def project_poi(raw: DataFrame) -> DataFrame:
    """Only the columns that the methods use."""
    return raw.select("poi_id", "lat", "lon", "state", "postcode", "category", "date_created", "date_closed")


def normalise_text(raw: DataFrame) -> DataFrame:
    """Upper-case trimmed states and five-digit postcodes."""
    return raw.withColumn("state", F.regexp_replace(F.upper(F.trim("state")), r"\s+", " ")).withColumn("postcode", F.lpad(F.regexp_replace("postcode", "[^0-9]", ""), 5, "0"))


def deduplicate(df: DataFrame, keys: Sequence[str], order: Sequence[str]) -> DataFrame:
    """The first row of each key in ``order``: deterministic, one shuffle."""
    place = Window.partitionBy(*keys).orderBy(*order)
    return df.withColumn("__rn", F.row_number().over(place)).filter("__rn = 1").drop("__rn")


def repair_swapped_coordinates(raw: DataFrame, bbox: tuple[float, float, float, float]) -> DataFrame:
    """Exchange latitude and longitude where only the exchanged pair lies in the box; ``swapped`` tells where."""
    lat, lon = F.col("lat"), F.col("lon")
    inside = lat.between(bbox[0], bbox[2]) & lon.between(bbox[1], bbox[3])
    other = lon.between(bbox[0], bbox[2]) & lat.between(bbox[1], bbox[3])
    wrong = ~inside & other
    return raw.select(*(c for c in raw.columns if c not in ("lat", "lon")), F.when(wrong, lon).otherwise(lat).alias("lat"), F.when(wrong, lat).otherwise(lon).alias("lon"), wrong.alias("swapped"))


def square_polygon(lat0: str = "lat0", lon0: str = "lon0", side: float = 0.1):
    corners = ((0, 0), (0, side), (side, side), (side, 0))
    return F.array(*(F.struct((F.col(lon0) + dx).alias("lon"), (F.col(lat0) + dy).alias("lat")) for dy, dx in corners))


def point_in_polygon(lat, lon, polygon):
    """Even-odd rule over the polygon's sides, half-open so that a shared side belongs to one polygon."""
    n = F.size(polygon)
    crossed = F.aggregate(
        F.sequence(F.lit(0), n - 1),
        F.lit(0),
        lambda s, i: s
        + F.when(
            ((polygon[i]["lat"] > lat) != (polygon[(i + 1) % n]["lat"] > lat))
            & (lon < (polygon[(i + 1) % n]["lon"] - polygon[i]["lon"]) * (lat - polygon[i]["lat"]) / (polygon[(i + 1) % n]["lat"] - polygon[i]["lat"]) + polygon[i]["lon"]),
            1,
        ).otherwise(0),
    )
    return crossed % 2 == 1


def validate_region(poi: DataFrame, cells: DataFrame, declared: str = "zip_id", mode: str = "correct", degrees: float = 0.1, rows: int | None = None) -> DataFrame:
    """Compare declared regions with polygons: ``correct`` replaces, ``flag`` only marks, ``drop`` removes wrong rows.

    ``cells`` has region_id, polygon. Cells are spread over the tiles that their bounds touch, so points meet only the cells of
    their tile (an equi-join, broadcast if ``rows`` of cells are few); the exact test follows.
    """
    from .session import small

    if mode not in ("correct", "flag", "drop"):
        raise ValueError(mode)
    box = cells.select("region_id", "polygon", *(f(F.col("polygon")[c]).alias(f"{n}_{c}") for c in ("lat", "lon") for n, f in (("lo", F.array_min), ("hi", F.array_max))))
    spread = box.withColumn("ty", F.explode(F.sequence(geo.tile(F.col("lo_lat"), degrees), geo.tile(F.col("hi_lat"), degrees)))).withColumn("tx", F.explode(F.sequence(geo.tile(F.col("lo_lon"), degrees), geo.tile(F.col("hi_lon"), degrees))))
    spread = spread.select("region_id", "polygon", "tx", "ty", "lo_lat", "hi_lat", "lo_lon", "hi_lon")
    tiled = poi.withColumns({"tx": geo.tile(F.col("lon"), degrees), "ty": geo.tile(F.col("lat"), degrees)})
    inside = (F.col("lat") >= F.col("lo_lat")) & (F.col("lat") <= F.col("hi_lat")) & (F.col("lon") >= F.col("lo_lon")) & (F.col("lon") <= F.col("hi_lon")) & point_in_polygon(F.col("lat"), F.col("lon"), F.col("polygon"))
    a, b = tiled.alias("a"), small(spread, rows).alias("b")
    met = a.join(b, (F.col("a.tx") == F.col("b.tx")) & (F.col("a.ty") == F.col("b.ty")) & inside, "left")
    ok = F.col("region_id") == F.col(f"a.{declared}")
    plain = [F.col(f"a.{c}") for c in poi.columns]
    if mode == "flag":
        return met.select(*plain, F.coalesce(ok, F.lit(False)).alias("region_ok"))
    if mode == "drop":
        return met.filter(ok).select(*plain)
    return met.select(*(F.coalesce("region_id", f"a.{c}").alias(c) if c == declared else F.col(f"a.{c}") for c in poi.columns), F.coalesce(ok, F.lit(False)).alias("region_ok"))


def snapshot(poi: DataFrame, as_of: str) -> DataFrame:
    """Points that are open on a date."""
    day = F.to_date(F.lit(as_of))
    return poi.filter((F.col("date_created") <= day) & (F.col("date_closed").isNull() | (F.col("date_closed") > day)))


def turnover(poi: DataFrame, grain: str = "month") -> DataFrame:
    """Openings and closures of each period."""
    events = poi.select(F.explode(F.array(F.struct(F.col("date_created").alias("day"), F.lit(1).alias("opened"), F.lit(0).alias("closed")), F.struct(F.col("date_closed").alias("day"), F.lit(0).alias("opened"), F.lit(1).alias("closed")))).alias("e")).select("e.*")
    return events.filter("day is not null").groupBy(F.to_date(F.date_trunc(grain, "day")).alias("period")).agg(F.sum("opened").alias("opened"), F.sum("closed").alias("closed"))


def category_frequency(poi: DataFrame, level: int) -> DataFrame:
    return poi.filter(F.size("category_path") >= level).groupBy(category.prefix(F.col("category_path"), level).alias("prefix")).agg(F.count(F.lit(1)).alias("n"))


def uniform_sample(poi: DataFrame, n: int, seed: int = 1) -> DataFrame:
    """Exactly ``n`` rows (or all) in the order of a seeded hash of the id; the same in every run."""
    mixed = F.md5(F.concat_ws(":", F.lit(str(seed)), F.col("poi_id").cast("string")))
    return poi.orderBy(mixed, "poi_id").limit(n)


def graph_statistics(poi: DataFrame, edges: DataFrame) -> DataFrame:
    """One row: nodes, edges, graphs, regions, localities."""
    p = poi.agg(F.count(F.lit(1)).alias("nodes"), F.count_distinct("state_id").alias("graphs"), F.count_distinct("zip_id").alias("zips"), F.count_distinct("locality_id").alias("localities"))
    return p.crossJoin(edges.agg(F.count(F.lit(1)).alias("edges")))
