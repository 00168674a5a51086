"""Reading and writing the engine's tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .. import schema


def load_poi(spark: SparkSession, path: str) -> DataFrame:
    """Points by their declared schema; nothing is inferred."""
    return spark.read.schema(schema.POI).parquet(path)


def save_partitioned(df: DataFrame, path: str, by: tuple[str, ...] = ("state_id",)) -> None:
    """Parquet in folders by key: later readers prune them."""
    df.write.mode("overwrite").partitionBy(*by).parquet(path)


def save_graph(df: DataFrame, name: str, buckets: int = 16) -> None:
    """An adjacency table bucketed and sorted by its join key, so that hops need no exchange of it."""
    df.write.mode("overwrite").bucketBy(buckets, "src").sortBy("src").saveAsTable(name)


def export_csv(df: DataFrame, path: str) -> None:
    flat = [F.to_json(c).alias(c) if t.startswith(("array", "map", "struct")) else F.col(c) for c, t in df.dtypes]
    df.select(*flat).write.mode("overwrite").option("header", True).csv(path)


def export_json(df: DataFrame, path: str) -> None:
    df.write.mode("overwrite").json(path)


def geojson(polygons: DataFrame, key: str) -> DataFrame:
    """One line of GeoJSON text for each row with ``polygon`` (array of lon, lat)."""
    ring = F.concat(F.col("polygon"), F.slice("polygon", 1, 1))
    return polygons.select(key, F.to_json(F.struct(F.lit("Polygon").alias("type"), F.array(F.transform(ring, lambda p: F.array(p["lon"], p["lat"]))).alias("coordinates"))).alias("geometry"))


def file_stream(spark: SparkSession, path: str, fields: str, files_per_trigger: int = 1) -> DataFrame:
    return spark.readStream.schema(fields).option("maxFilesPerTrigger", files_per_trigger).parquet(path)


def to_noop(df: DataFrame) -> None:
    df.write.format("noop").mode("overwrite").save()
