"""Declared schemas of the engine's tables."""

from __future__ import annotations

from pyspark.sql import types as T

POI = T.StructType(
    [
        T.StructField("poi_id", T.LongType()),
        T.StructField("lat", T.DoubleType()),
        T.StructField("lon", T.DoubleType()),
        T.StructField("state_id", T.IntegerType()),
        T.StructField("county_id", T.IntegerType()),
        T.StructField("zip_id", T.LongType()),
        T.StructField("locality_id", T.LongType()),
        T.StructField("t", T.IntegerType()),
        T.StructField("category_path", T.ArrayType(T.StringType())),
        T.StructField("date_created", T.DateType()),
        T.StructField("date_closed", T.DateType()),
    ]
)
CELL = "zip_id long, county_id int, state_id int, idx long, w long, lat0 double, lon0 double"
EDGE = "state_id int, src long, dst long, dist_m double"
RUN_LOG = "method string, state_id int, r double, seed int, seconds double, rmse double, mae double, r2 double"
