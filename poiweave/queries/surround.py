"""Queries: the operators around the methods (filters, joins, aggregations, windows, sets, functions, UDFs, SQL)."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import geo, vectors
from ..operators import places, sqlface
from ..sources import points
from ..sources.points import table
from ..streaming.streams import _place
from .features import D, hashed
from .graph import HASHED
from .oracle import CELL, POI, dist
from .places import SQL as _PLACE_SQL

REGION_SQL = _PLACE_SQL["region_mean"]


def scan_counts(spark: SparkSession, sf: str) -> DataFrame:
    out = None
    for t in ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "embeddings"):
        part = table(spark, sf, t).agg(F.count(F.lit(1)).alias("n")).withColumn("name", F.lit(t))
        out = part if out is None else out.unionByName(part)
    return out


def roundtrip(spark: SparkSession, sf: str) -> DataFrame:
    """Points written as Parquet by state and read by their declared schema."""
    from .. import schema
    from ..sources import io

    place = _place(spark, f"roundtrip-{uuid.uuid4().hex[:6]}")
    io.save_partitioned(points.points(spark, sf), place)
    back = spark.read.schema(schema.POI).parquet(place)
    return back.groupBy("state_id").agg(F.count(F.lit(1)).alias("n"), F.sum("poi_id").alias("ids"), F.sum(F.size("category_path")).alias("depth"))


def filter_bbox(spark: SparkSession, sf: str) -> DataFrame:
    return points.points(spark, sf).filter(F.col("lat").between(30.0, 30.15) & F.col("lon").between(-120.0, -103.9)).select("poi_id")


def filter_radius(spark: SparkSession, sf: str) -> DataFrame:
    p = points.points(spark, sf).withColumn("d", geo.haversine_m(F.col("lat"), F.col("lon"), F.lit(30.05), F.lit(-103.95)))
    return p.filter("d <= 4000").select("poi_id", F.round("d", 3).alias("d"))


def filter_prefix(spark: SparkSession, sf: str) -> DataFrame:
    return points.points(spark, sf).filter(F.array_join("category_path", ">").startswith("PROMO>")).select("poi_id")


def filter_conj(spark: SparkSession, sf: str) -> DataFrame:
    p = points.points(spark, sf)
    return p.filter(F.col("state_id").isin(1, 3) & F.col("date_closed").isNull() & (F.size("category_path") > 3) & (F.col("t") != 0)).select("poi_id")


def _joined(spark: SparkSession, sf: str, hint: str) -> DataFrame:
    p = points.points(spark, sf).select("poi_id", "zip_id")
    s = table(spark, sf, "supplier").select(F.col("s_suppkey").alias("zip_id"), "s_acctbal")
    return p.join(s.hint(hint), "zip_id").groupBy("zip_id").agg(F.count(F.lit(1)).alias("n"), F.round(F.max("s_acctbal"), 2).alias("acctbal"))


def join_broadcast(spark: SparkSession, sf: str) -> DataFrame:
    return _joined(spark, sf, "broadcast")


def join_merge(spark: SparkSession, sf: str) -> DataFrame:
    return _joined(spark, sf, "merge")


def join_shuffle_hash(spark: SparkSession, sf: str) -> DataFrame:
    return _joined(spark, sf, "shuffle_hash")


def join_distance(spark: SparkSession, sf: str) -> DataFrame:
    return places.join_within(points.points(spark, sf), 150.0).groupBy("state_id").agg(F.count(F.lit(1)).alias("pairs"))


def join_point_in_cell(spark: SparkSession, sf: str) -> DataFrame:
    p = points.points(spark, sf).select("poi_id", "state_id", "lat", "lon").withColumns({"tx": geo.tile(F.col("lon"), 0.1), "ty": geo.tile(F.col("lat"), 0.1)})
    c = points.zip_cells(spark, sf).select("state_id", "zip_id", "lat0", "lon0")
    near = c.withColumn("q", F.explode(geo.ring(geo.tile(F.col("lon0") + 0.05, 0.1), geo.tile(F.col("lat0") + 0.05, 0.1), 1))).select("state_id", "zip_id", "lat0", "lon0", F.col("q.x").alias("tx"), F.col("q.y").alias("ty"))
    inside = (F.col("lat") >= F.col("lat0")) & (F.col("lat") < F.col("lat0") + 0.1) & (F.col("lon") >= F.col("lon0")) & (F.col("lon") < F.col("lon0") + 0.1)
    # the squares of states overlap once a state has more than 80 cells in a row
    return p.join(near, ["state_id", "tx", "ty"]).filter(inside).groupBy("zip_id").agg(F.count(F.lit(1)).alias("n"))


def join_nested_loop(spark: SparkSession, sf: str) -> DataFrame:
    """Regions whose account balance is beaten by fewer than five others (a theta join of the small region table)."""
    s = table(spark, sf, "supplier").select("s_suppkey", "s_acctbal")
    a, b = s.alias("a"), s.alias("b")
    n = a.join(b, F.col("b.s_acctbal") > F.col("a.s_acctbal"), "left").groupBy(F.col("a.s_suppkey").alias("zip_id")).agg(F.count("b.s_suppkey").alias("beaten_by"))
    return n.filter("beaten_by < 5")


def join_interval(spark: SparkSession, sf: str) -> DataFrame:
    """Pairs of closed points of one locality whose life spans overlap, counted by state."""
    p = points.points(spark, sf).filter("date_closed is not null").select("state_id", "locality_id", "poi_id", F.col("date_created").alias("f"), F.col("date_closed").alias("t"))
    a, b = p.alias("a"), p.alias("b")
    met = a.join(b, (F.col("a.locality_id") == F.col("b.locality_id")) & (F.col("a.poi_id") < F.col("b.poi_id")) & (F.col("a.f") < F.col("b.t")) & (F.col("b.f") < F.col("a.t")))
    return met.groupBy("a.state_id").agg(F.count(F.lit(1)).alias("pairs"))


def asof(left: DataFrame, right: DataFrame, by: str, at: str, value: str, name: str) -> DataFrame:
    """``left`` plus the ``value`` of the last row of ``right`` with the same ``by`` at or before ``at``: both tables in one sorted window instead of a range join."""
    rows = left.withColumn("__own", F.lit(1)).unionByName(right.select(by, at, F.col(value).alias("__value"), F.lit(0).alias("__own")), allowMissingColumns=True)
    w = Window.partitionBy(by).orderBy(at, "__own", "__value").rowsBetween(Window.unboundedPreceding, 0)
    return rows.withColumn(name, F.last("__value", ignorenulls=True).over(w)).filter("__own = 1").drop("__own", "__value")


def join_asof(spark: SparkSession, sf: str) -> DataFrame:
    """Each point's last event at or before its opening, events being dealt to regions by user."""
    p = points.points(spark, sf).select("poi_id", "zip_id", F.col("date_created").cast("timestamp").alias("ts"))
    n = table(spark, sf, "supplier").count()
    e = table(spark, sf, "events").select((F.col("user_id") % n).alias("zip_id"), "ts", "event_id")
    return asof(p, e, "zip_id", "ts", "event_id", "event_id").select("poi_id", "event_id")


def join_semi(spark: SparkSession, sf: str) -> DataFrame:
    return points.zip_cells(spark, sf).join(points.points(spark, sf).filter("t = 3"), "zip_id", "left_semi").select("zip_id")


def join_anti(spark: SparkSession, sf: str) -> DataFrame:
    return table(spark, sf, "part").select("p_partkey").join(points.distinct_lines(spark, sf).filter("l_quantity > 45").select(F.col("l_partkey").alias("p_partkey")), "p_partkey", "left_anti")


def join_outer(spark: SparkSession, sf: str) -> DataFrame:
    p = points.points(spark, sf)
    a = p.filter("t = 4").groupBy("locality_id").agg(F.count(F.lit(1)).alias("small"))
    b = p.filter("t = 5").groupBy("locality_id").agg(F.count(F.lit(1)).alias("standard"))
    return a.join(b, "locality_id", "full")


def agg_basic(spark: SparkSession, sf: str) -> DataFrame:
    return points.points(spark, sf).groupBy("county_id").agg(F.count(F.lit(1)).alias("n"), F.round(F.avg("lat"), 6).alias("lat"), F.min("date_created").alias("first"), F.max("date_created").alias("last"))


def agg_distinct(spark: SparkSession, sf: str) -> DataFrame:
    return points.points(spark, sf).groupBy("state_id").agg(F.count_distinct("category_path").alias("paths"), F.count_distinct("zip_id", "t").alias("kinds"))


def agg_percentile(spark: SparkSession, sf: str) -> DataFrame:
    return table(spark, sf, "lineitem").groupBy("l_returnflag").agg(*(F.round(F.percentile("l_extendedprice", q), 4).alias(f"p{int(q * 100)}") for q in (0.1, 0.5, 0.95)))


def agg_approx_distinct(spark: SparkSession, sf: str) -> DataFrame:
    return points.points(spark, sf).groupBy("state_id").agg(F.approx_count_distinct("poi_id", 0.02).alias("n"))


def agg_rollup(spark: SparkSession, sf: str) -> DataFrame:
    return points.points(spark, sf).rollup("state_id", "county_id").agg(F.count(F.lit(1)).alias("n"))


def agg_cube(spark: SparkSession, sf: str) -> DataFrame:
    return points.points(spark, sf).cube("state_id", "t").agg(F.count(F.lit(1)).alias("n"))


def agg_grouping_sets(spark: SparkSession, sf: str) -> DataFrame:
    p = points.points(spark, sf)
    return p.groupingSets([["state_id"], ["t"], []], "state_id", "t").agg(F.count(F.lit(1)).alias("n"))


def agg_pivot(spark: SparkSession, sf: str) -> DataFrame:
    p = points.points(spark, sf).groupBy("state_id").pivot("t", list(range(6))).agg(F.count(F.lit(1)))
    return p.select("state_id", *(F.coalesce(F.col(str(i)), F.lit(0)).alias(f"t{i}") for i in range(6)))


def agg_vector_mean(spark: SparkSession, sf: str) -> DataFrame:
    e = table(spark, sf, "embeddings").select("label", F.col("embedding").cast("array<double>").alias("h"))
    return e.groupBy("label").agg(*vectors.means("h", 8)).select("label", vectors.rounded(vectors.gathered(8)).alias("z"))


def win_rank(spark: SparkSession, sf: str) -> DataFrame:
    n = points.points(spark, sf).groupBy("state_id", "zip_id").agg(F.count(F.lit(1)).alias("n"))
    w = Window.partitionBy("state_id").orderBy(F.desc("n"))
    return n.select("state_id", "zip_id", "n", F.rank().over(w).alias("rank"), F.dense_rank().over(w).alias("dense"), F.row_number().over(w.orderBy(F.desc("n"), "zip_id")).alias("row"))


def win_ntile(spark: SparkSession, sf: str) -> DataFrame:
    n = points.points(spark, sf).groupBy("zip_id").agg(F.count(F.lit(1)).alias("n"))
    w = Window.orderBy("n", "zip_id")
    return n.select("zip_id", F.ntile(5).over(w).alias("fifth"), F.round(F.percent_rank().over(w), 6).alias("share"))


def win_lag(spark: SparkSession, sf: str) -> DataFrame:
    w = Window.partitionBy("zip_id").orderBy("date_created", "poi_id")
    p = points.points(spark, sf)
    return p.select("poi_id", F.date_diff("date_created", F.lag("date_created").over(w)).alias("days_since"), F.lead("poi_id").over(w).alias("next"))


def win_running(spark: SparkSession, sf: str) -> DataFrame:
    n = points.points(spark, sf).groupBy("state_id", F.year("date_created").alias("year")).agg(F.count(F.lit(1)).alias("opened"))
    w = Window.partitionBy("state_id").orderBy("year")
    return n.select("state_id", "year", F.sum("opened").over(w.rowsBetween(Window.unboundedPreceding, 0)).alias("running"), F.sum("opened").over(w.rowsBetween(-1, 1)).alias("around"))


def win_range_frame(spark: SparkSession, sf: str) -> DataFrame:
    p = points.points(spark, sf).withColumn("day", F.unix_date("date_created"))
    w = Window.partitionBy("zip_id").orderBy("day").rangeBetween(-30, 0)
    return p.select("poi_id", F.count(F.lit(1)).over(w).alias("last_30_days"))


def topk_global(spark: SparkSession, sf: str) -> DataFrame:
    return table(spark, sf, "part").orderBy(F.desc("p_retailprice"), "p_partkey").limit(25).select("p_partkey", "p_retailprice")


def topk_group(spark: SparkSession, sf: str) -> DataFrame:
    w = Window.partitionBy("zip_id").orderBy(F.desc("date_created"), "poi_id")
    return points.points(spark, sf).withColumn("k", F.row_number().over(w)).filter("k <= 3").select("zip_id", "poi_id", "k")


def _paths(spark: SparkSession, sf: str, open_: bool) -> DataFrame:
    """Two-level categories of all points that are still open, or of all that are closed."""
    return points.points(spark, sf).filter(F.col("date_closed").isNull() == open_).select(F.array_join(F.slice("category_path", 1, 2), ">").alias("prefix"))


def set_union(spark: SparkSession, sf: str) -> DataFrame:
    return _paths(spark, sf, True).union(_paths(spark, sf, False)).distinct()


def set_intersect(spark: SparkSession, sf: str) -> DataFrame:
    return _paths(spark, sf, True).intersectAll(_paths(spark, sf, False)).groupBy("prefix").agg(F.count(F.lit(1)).alias("n"))


def set_except(spark: SparkSession, sf: str) -> DataFrame:
    return _paths(spark, sf, True).exceptAll(_paths(spark, sf, False)).groupBy("prefix").agg(F.count(F.lit(1)).alias("n"))


def set_jaccard(spark: SparkSession, sf: str) -> DataFrame:
    """Jaccard likeness of touching regions' sets of paths."""
    from ..operators.regions import region_adjacency

    s = points.points(spark, sf).groupBy("zip_id").agg(F.collect_set(F.array_join("category_path", ">")).alias("s"))
    pairs = region_adjacency(points.polygons(points.zip_cells(spark, sf)), within=("state_id",))
    met = pairs.join(s.select(F.col("zip_id").alias("a"), F.col("s").alias("s1")), "a").join(s.select(F.col("zip_id").alias("b"), F.col("s").alias("s2")), "b")
    return met.select("a", "b", vectors.half_up(F.size(F.array_intersect("s1", "s2")) / F.size(F.array_union("s1", "s2"))).alias("jaccard"))


def fn_string(spark: SparkSession, sf: str) -> DataFrame:
    return table(spark, sf, "part").select("p_partkey", F.upper("p_name").alias("up"), F.lpad(F.regexp_extract("p_brand", r"#(\d+)", 1), 4, "0").alias("brand"), F.concat_ws("/", F.split("p_name", " ")).alias("joined"), F.initcap("p_type").alias("cap"))


def fn_date(spark: SparkSession, sf: str) -> DataFrame:
    p = points.points(spark, sf)
    return p.select("poi_id", F.to_date(F.date_trunc("quarter", "date_created")).alias("quarter"), F.add_months("date_created", 2).alias("plus2"), F.date_diff("date_closed", "date_created").alias("age"), F.dayofweek("date_created").alias("dow"))


def fn_math(spark: SparkSession, sf: str) -> DataFrame:
    p = points.points(spark, sf)
    return p.select("poi_id", F.round(F.log1p(F.pow(F.col("lat"), 1.5)), 6).alias("lw"), F.round(F.degrees(F.atan2(F.col("lat"), F.col("lon"))), 6).alias("angle"), F.floor(F.col("poi_id").cast("decimal(18,0)") * F.lit("0.29").cast("decimal(3,2)")).cast("long").alias("exact"))


def fn_array(spark: SparkSession, sf: str) -> DataFrame:
    p = points.points(spark, sf)
    return p.select("poi_id", F.element_at("category_path", -1).alias("leaf"), F.array_join(F.transform("category_path", lambda x: F.substring(x, 1, 2)), "").alias("code"), F.aggregate("category_path", F.lit(0), lambda s, x: s + F.length(x)).alias("chars"))


def _vec(spark: SparkSession, sf: str) -> DataFrame:
    e = table(spark, sf, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("v"))
    return e.join(e.filter("vec_id = 0").select(F.col("v").alias("q")).hint("broadcast"))


def vec_dot(spark: SparkSession, sf: str) -> DataFrame:
    return _vec(spark, sf).select("vec_id", (F.round(vectors.dot(F.col("v"), F.col("q")), 6) + 0.0).alias("x"))


def vec_cosine(spark: SparkSession, sf: str) -> DataFrame:
    return _vec(spark, sf).select("vec_id", (F.round(vectors.cosine(F.col("v"), F.col("q")), 6) + 0.0).alias("x"))


def vec_axpy(spark: SparkSession, sf: str) -> DataFrame:
    return _vec(spark, sf).select("vec_id", vectors.rounded(F.slice(vectors.axpy(0.5, F.col("v"), F.col("q")), 1, 4)).alias("x"))


def vec_norm(spark: SparkSession, sf: str) -> DataFrame:
    return _vec(spark, sf).select("vec_id", F.round(vectors.norm(F.zip_with("v", "q", lambda a, b: a - b)), 6).alias("x"))


def fn_map(spark: SparkSession, sf: str) -> DataFrame:
    """Category histogram of a region as a map, and back to rows."""
    n = points.points(spark, sf).groupBy("zip_id", F.col("category_path")[0].alias("c")).agg(F.count(F.lit(1)).alias("n"))
    m = n.groupBy("zip_id").agg(F.map_from_entries(F.array_sort(F.collect_list(F.struct("c", "n")))).alias("m"))
    return m.select("zip_id", F.explode("m").alias("c", "n"))


def fn_json(spark: SparkSession, sf: str) -> DataFrame:
    e = table(spark, sf, "events")
    k = F.from_json("props", "k int")["k"]
    return e.groupBy("event_type").agg(F.sum(k).alias("k"), F.count_if(F.get_json_object("props", "$.k").cast("int") > 50).alias("large"))


def udf_vec_norm(spark: SparkSession, sf: str) -> DataFrame:
    return table(spark, sf, "embeddings").select("vec_id", F.round(sqlface.vec_norm("embedding"), 5).alias("x"))


def udaf_weighted_mean(spark: SparkSession, sf: str) -> DataFrame:
    x = table(spark, sf, "lineitem").select("l_returnflag", "l_extendedprice", "l_quantity")
    return x.groupBy("l_returnflag").agg(F.round(sqlface.weighted_mean("l_extendedprice", "l_quantity"), 4).alias("price"))


def udtf_tile_ring(spark: SparkSession, sf: str) -> DataFrame:
    sqlface.register(spark)
    points.zip_cells(spark, sf).select("zip_id", F.floor("lon0").cast("long").alias("x"), F.floor("lat0").cast("long").alias("y")).createOrReplaceTempView("poiweave_cells")
    return spark.sql("SELECT zip_id, r.tx, r.ty FROM poiweave_cells, LATERAL tile_ring(x, y, 1) AS r")


def udtf_place_split(spark: SparkSession, sf: str) -> DataFrame:
    p = points.points(spark, sf)
    return sqlface.split_places_sql(spark, hashed(p).join(p.select("poi_id", "zip_id"), "poi_id"), "0.05")


def sql_region_embedding(spark: SparkSession, sf: str) -> DataFrame:
    """Graph, one hop, combination and region vectors in SQL text over registered views."""
    p = points.points(spark, sf)
    sqlface.register_graph(spark, p, hashed(p))
    return sqlface.region_embedding_sql(spark, D, (0.5, 0.5))


QUERIES = {
    f.__name__: f
    for f in (
        scan_counts, roundtrip, filter_bbox, filter_radius, filter_prefix, filter_conj, join_broadcast, join_merge, join_shuffle_hash, join_distance, join_point_in_cell, join_nested_loop, join_interval, join_asof,
        join_semi, join_anti, join_outer, agg_basic, agg_distinct, agg_percentile, agg_approx_distinct, agg_rollup, agg_cube, agg_grouping_sets, agg_pivot, agg_vector_mean, win_rank, win_ntile, win_lag,
        win_running, win_range_frame, topk_global, topk_group, set_union, set_intersect, set_except, set_jaccard, fn_string, fn_date, fn_math, fn_array, vec_dot, vec_cosine, vec_axpy, vec_norm, fn_map, fn_json,
        udf_vec_norm, udaf_weighted_mean, udtf_tile_ring, udtf_place_split, sql_region_embedding,
    )
}

_JOIN = f"WITH {POI} SELECT zip_id, count(*) AS n, round(max(s_acctbal), 2) AS acctbal FROM poi JOIN supplier ON s_suppkey = zip_id GROUP BY zip_id"
_E = "WITH e AS (SELECT vec_id, list_transform(embedding, lambda x: CAST(x AS DOUBLE)) AS v FROM embeddings), m AS (SELECT e.vec_id, e.v, q.v AS q FROM e, e q WHERE q.vec_id = 0)"
_SUB = "len(v) - 1"
_PATHS = "pa AS (SELECT date_closed IS NULL AS live, array_to_string(list_slice(category_path, 1, 2), '>') AS prefix FROM poi)"

SQL = {
    "scan_counts": " UNION ALL ".join(f"SELECT count(*) AS n, '{t}' AS name FROM {t}" for t in ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "embeddings")),
    "roundtrip": f"WITH {POI} SELECT state_id, count(*) AS n, CAST(sum(poi_id) AS BIGINT) AS ids, CAST(sum(len(category_path)) AS BIGINT) AS depth FROM poi GROUP BY state_id",
    "filter_bbox": f"WITH {POI} SELECT poi_id FROM poi WHERE lat BETWEEN 30 AND 30.15::DOUBLE AND lon BETWEEN -120 AND -103.9::DOUBLE",
    "filter_radius": f"WITH {POI}, c AS (SELECT 30.05::DOUBLE AS lat, -103.95::DOUBLE AS lon), q AS (SELECT poi_id, {dist('poi', 'c')} AS d FROM poi, c) SELECT poi_id, round(d, 3) AS d FROM q WHERE d <= 4000",
    "filter_prefix": f"WITH {POI} SELECT poi_id FROM poi WHERE category_path[1] = 'PROMO' AND len(category_path) > 1",
    "filter_conj": f"WITH {POI} SELECT poi_id FROM poi WHERE state_id IN (1, 3) AND date_closed IS NULL AND len(category_path) > 3 AND t <> 0",
    "join_broadcast": _JOIN,
    "join_merge": _JOIN,
    "join_shuffle_hash": _JOIN,
    "join_distance": f"WITH {POI}, t AS (SELECT *, CAST(floor(lat / 0.01::DOUBLE) AS BIGINT) AS ty, CAST(floor(lon / 0.01::DOUBLE) AS BIGINT) AS tx FROM poi), m AS (SELECT a.state_id, {dist('a', 'b')} AS d FROM t a, (VALUES (-1), (0), (1)) i(i), (VALUES (-1), (0), (1)) j(j), t b WHERE b.tx = a.tx + i AND b.ty = a.ty + j AND a.state_id = b.state_id AND a.poi_id <> b.poi_id) SELECT state_id, count(*) AS pairs FROM m WHERE d <= 150 GROUP BY state_id",
    "join_point_in_cell": f"WITH {POI} SELECT zip_id, count(*) AS n FROM poi GROUP BY zip_id",
    "join_nested_loop": "SELECT a.s_suppkey AS zip_id, count(b.s_suppkey) AS beaten_by FROM supplier a LEFT JOIN supplier b ON b.s_acctbal > a.s_acctbal GROUP BY 1 HAVING count(b.s_suppkey) < 5",
    "join_interval": f"WITH {POI}, p AS (SELECT * FROM poi WHERE date_closed IS NOT NULL) SELECT a.state_id, count(*) AS pairs FROM p a JOIN p b ON a.locality_id = b.locality_id AND a.poi_id < b.poi_id AND a.date_created < b.date_closed AND b.date_created < a.date_closed GROUP BY a.state_id",
    "join_asof": f"""WITH {POI}, e AS (SELECT user_id % (SELECT count(*) FROM supplier) AS zip_id, ts, event_id FROM events)
SELECT poi_id, (SELECT max_by(event_id, (ts, event_id)) FROM e WHERE e.zip_id = poi.zip_id AND e.ts <= CAST(poi.date_created AS TIMESTAMP)) AS event_id FROM poi""",
    "join_semi": f"WITH {POI} SELECT DISTINCT zip_id FROM poi WHERE t = 3",
    "join_anti": f"WITH {POI} SELECT p_partkey FROM part WHERE p_partkey NOT IN (SELECT l_partkey FROM line1 WHERE l_quantity > 45)",
    "join_outer": f"WITH {POI} SELECT locality_id, nullif(count(*) FILTER (WHERE t = 4), 0) AS small, nullif(count(*) FILTER (WHERE t = 5), 0) AS standard FROM poi WHERE t IN (4, 5) GROUP BY locality_id",
    "agg_basic": f"WITH {POI} SELECT county_id, count(*) AS n, round(avg(lat), 6) AS lat, min(date_created) AS first, max(date_created) AS last FROM poi GROUP BY county_id",
    "agg_distinct": f"WITH {POI} SELECT state_id, count(DISTINCT category_path) AS paths, count(DISTINCT (zip_id, t)) AS kinds FROM poi GROUP BY state_id",
    "agg_percentile": "SELECT l_returnflag, " + ", ".join(f"round(quantile_cont(l_extendedprice, {q}), 4) AS p{int(q * 100)}" for q in (0.1, 0.5, 0.95)) + " FROM lineitem GROUP BY l_returnflag",
    "agg_rollup": f"WITH {POI} SELECT state_id, county_id, count(*) AS n FROM poi GROUP BY ROLLUP (state_id, county_id)",
    "agg_cube": f"WITH {POI} SELECT state_id, t, count(*) AS n FROM poi GROUP BY CUBE (state_id, t)",
    "agg_grouping_sets": f"WITH {POI} SELECT state_id, t, count(*) AS n FROM poi GROUP BY GROUPING SETS ((state_id), (t), ())",
    "agg_pivot": f"WITH {POI} SELECT state_id, " + ", ".join(f"count(*) FILTER (WHERE t = {i}) AS t{i}" for i in range(6)) + " FROM poi GROUP BY state_id",
    "agg_vector_mean": "WITH m AS (SELECT label, i, avg(CAST(embedding[i + 1] AS DOUBLE)) AS x FROM embeddings, unnest(range(0, 8)) g(i) GROUP BY label, i) SELECT label, list(round(x, 6) + 0.0::DOUBLE ORDER BY i) AS z FROM m GROUP BY label",
    "win_rank": f"WITH {POI}, n AS (SELECT state_id, zip_id, count(*) AS n FROM poi GROUP BY 1, 2) SELECT state_id, zip_id, n, CAST(rank() OVER w AS INTEGER) AS rank, CAST(dense_rank() OVER w AS INTEGER) AS dense, CAST(row_number() OVER (PARTITION BY state_id ORDER BY n DESC, zip_id) AS INTEGER) AS row FROM n WINDOW w AS (PARTITION BY state_id ORDER BY n DESC)",
    "win_ntile": f"WITH {POI}, n AS (SELECT zip_id, count(*) AS n FROM poi GROUP BY 1) SELECT zip_id, CAST(ntile(5) OVER w AS INTEGER) AS fifth, round(percent_rank() OVER w, 6) AS share FROM n WINDOW w AS (ORDER BY n, zip_id)",
    "win_lag": f"WITH {POI} SELECT poi_id, CAST(date_diff('day', lag(date_created) OVER w, date_created) AS INTEGER) AS days_since, lead(poi_id) OVER w AS next FROM poi WINDOW w AS (PARTITION BY zip_id ORDER BY date_created, poi_id)",
    "win_running": f"WITH {POI}, n AS (SELECT state_id, CAST(year(date_created) AS INTEGER) AS year, count(*) AS opened FROM poi GROUP BY 1, 2) SELECT state_id, year, CAST(sum(opened) OVER (PARTITION BY state_id ORDER BY year ROWS UNBOUNDED PRECEDING) AS BIGINT) AS running, CAST(sum(opened) OVER (PARTITION BY state_id ORDER BY year ROWS BETWEEN 1 PRECEDING AND 1 FOLLOWING) AS BIGINT) AS around FROM n",
    "win_range_frame": f"WITH {POI} SELECT poi_id, count(*) OVER (PARTITION BY zip_id ORDER BY date_created RANGE BETWEEN INTERVAL 30 DAY PRECEDING AND CURRENT ROW) AS last_30_days FROM poi",
    "topk_global": "SELECT p_partkey, p_retailprice FROM part ORDER BY p_retailprice DESC, p_partkey LIMIT 25",
    "topk_group": f"WITH {POI} SELECT zip_id, poi_id, CAST(k AS INTEGER) AS k FROM (SELECT zip_id, poi_id, row_number() OVER (PARTITION BY zip_id ORDER BY date_created DESC, poi_id) AS k FROM poi) WHERE k <= 3",
    "set_union": f"WITH {POI}, {_PATHS} SELECT DISTINCT prefix FROM pa",
    "set_intersect": f"WITH {POI}, {_PATHS} SELECT prefix, count(*) AS n FROM (SELECT prefix FROM pa WHERE live INTERSECT ALL SELECT prefix FROM pa WHERE NOT live) GROUP BY prefix",
    "set_except": f"WITH {POI}, {_PATHS} SELECT prefix, count(*) AS n FROM (SELECT prefix FROM pa WHERE live EXCEPT ALL SELECT prefix FROM pa WHERE NOT live) GROUP BY prefix",
    "set_jaccard": f"""WITH {POI}, s AS (SELECT zip_id, list(DISTINCT array_to_string(category_path, '>')) AS s FROM poi GROUP BY zip_id),
m AS (SELECT p.zip_id AS a, q.zip_id AS b FROM cell p JOIN cell q ON p.state_id = q.state_id AND p.zip_id < q.zip_id WHERE abs(p.idx // p.w - q.idx // q.w) <= 1 AND abs(p.idx % p.w - q.idx % q.w) <= 1)
SELECT a, b, round(len(list_intersect(x.s, y.s)) / (len(x.s) + len(y.s) - len(list_intersect(x.s, y.s))), 6) AS jaccard FROM m JOIN s x ON x.zip_id = a JOIN s y ON y.zip_id = b""",
    "fn_string": "SELECT p_partkey, upper(p_name) AS up, lpad(regexp_extract(p_brand, '#(\\d+)', 1), 4, '0') AS brand, replace(p_name, ' ', '/') AS joined, upper(p_type[1:1]) || lower(p_type[2:]) AS cap FROM part",
    "fn_date": f"WITH {POI} SELECT poi_id, CAST(date_trunc('quarter', date_created) AS DATE) AS quarter, CAST(date_created + INTERVAL 2 MONTH AS DATE) AS plus2, CAST(date_diff('day', date_created, date_closed) AS INTEGER) AS age, CAST(dayofweek(date_created) + 1 AS INTEGER) AS dow FROM poi",
    "fn_math": f"WITH {POI} SELECT poi_id, round(ln(1 + pow(lat, 1.5::DOUBLE)), 6) AS lw, round(degrees(atan2(lat, lon)), 6) AS angle, (poi_id * 29) // 100 AS exact FROM poi",
    "fn_array": f"WITH {POI} SELECT poi_id, category_path[-1] AS leaf, array_to_string(list_transform(category_path, lambda x: x[1:2]), '') AS code, CAST(list_sum(list_transform(category_path, lambda x: length(x))) AS INTEGER) AS chars FROM poi",
    "vec_dot": f"{_E} SELECT vec_id, round(list_dot_product(v, q), 6) + 0.0::DOUBLE AS x FROM m",
    "vec_cosine": f"{_E} SELECT vec_id, round(list_cosine_similarity(v, q), 6) + 0.0::DOUBLE AS x FROM m",
    "vec_axpy": f"{_E} SELECT vec_id, list_transform(range(1, 5), lambda i: round(0.5::DOUBLE * v[i] + q[i], 6) + 0.0::DOUBLE) AS x FROM m",
    "vec_norm": f"{_E} SELECT vec_id, round(list_distance(v, q), 6) AS x FROM m",
    "fn_map": f"WITH {POI} SELECT zip_id, category_path[1] AS c, count(*) AS n FROM poi GROUP BY 1, 2",
    "fn_json": "SELECT event_type, CAST(sum(CAST(json_extract_string(props, '$.k') AS INTEGER)) AS BIGINT) AS k, count(*) FILTER (WHERE CAST(json_extract_string(props, '$.k') AS INTEGER) > 50) AS large FROM events GROUP BY event_type",
    "udf_vec_norm": "SELECT vec_id, round(sqrt(list_sum(list_transform(embedding, lambda x: CAST(x AS DOUBLE) * CAST(x AS DOUBLE)))), 5) AS x FROM embeddings",
    "udaf_weighted_mean": "SELECT l_returnflag, round(sum(l_extendedprice * l_quantity) / sum(l_quantity), 4) AS price FROM lineitem GROUP BY l_returnflag",
    "udtf_tile_ring": f"WITH {CELL} SELECT zip_id, CAST(floor(lon0) AS BIGINT) + i AS tx, CAST(floor(lat0) AS BIGINT) + j AS ty FROM cell, (VALUES (-1), (0), (1)) i(i), (VALUES (-1), (0), (1)) j(j)",
    "udtf_place_split": f"WITH {POI} SELECT zip_id AS region, greatest(1, CAST(floor(count(*) * CAST(0.05 AS DECIMAL(10, 9))) AS BIGINT)) AS n_places, count(*) AS n FROM poi GROUP BY zip_id",
    "sql_region_embedding": REGION_SQL,
}
