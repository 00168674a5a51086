"""Queries: geometry and graphs."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import geo
from ..operators import delaunay, encode, graph
from ..sources import points
from .oracle import POI, dist

K = 5
#: Side of the square within which DuckDB looks for neighbours; the fifth neighbour of every derived point is nearer (a test checks it).
REACH = "0.05::DOUBLE"

KNN = f"""{POI},
tile AS (SELECT *, CAST(floor(lat / {REACH}) AS BIGINT) AS ty, CAST(floor(lon / {REACH}) AS BIGINT) AS tx FROM poi),
near AS (SELECT a.state_id, a.poi_id AS src, b.poi_id AS dst, {dist("a", "b")} AS dist_m
  FROM tile a, (VALUES (-1), (0), (1)) i(i), (VALUES (-1), (0), (1)) j(j), tile b
  WHERE b.tx = a.tx + i AND b.ty = a.ty + j AND a.state_id = b.state_id AND a.poi_id <> b.poi_id),
knn AS (SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY src ORDER BY dist_m, dst) AS rank FROM near) WHERE rank <= {K}),
edge AS (SELECT state_id, least(src, dst) AS src, greatest(src, dst) AS dst, min(dist_m) AS dist_m, count(*) AS times FROM knn GROUP BY 1, 2, 3)"""

SCALE = """scale AS (SELECT zip_id, count(*) AS n_r, 2 * 6371000.0::DOUBLE * asin(sqrt(least(1.0::DOUBLE, pow(sin(radians(max(lat) - min(lat)) / 2), 2)
    + cos(radians(min(lat))) * cos(radians(max(lat))) * pow(sin(radians(max(lon) - min(lon)) / 2), 2)))) AS scale FROM poi GROUP BY zip_id)"""

WEIGHT = f"""{KNN}, {SCALE},
raw_w AS (SELECT e.state_id, e.src, e.dst, e.dist_m, p.zip_id AS src_zip, q.zip_id AS dst_zip, p.zip_id = q.zip_id AS same_region,
    greatest(0.0::DOUBLE, ln(1 + pow(greatest(s.scale, t.scale), 1.5::DOUBLE)) - ln(1 + pow(e.dist_m, 1.5::DOUBLE))) * CASE WHEN p.zip_id = q.zip_id THEN 1.0::DOUBLE ELSE 0.4::DOUBLE END AS w_raw
  FROM edge e JOIN poi p ON p.poi_id = e.src JOIN poi q ON q.poi_id = e.dst JOIN scale s ON s.zip_id = p.zip_id JOIN scale t ON t.zip_id = q.zip_id),
bound AS (SELECT zip_id, min(w_raw) AS lo, max(w_raw) AS hi FROM (SELECT src_zip AS zip_id, w_raw FROM raw_w UNION ALL SELECT dst_zip, w_raw FROM raw_w WHERE src_zip <> dst_zip) GROUP BY zip_id),
weighted AS (SELECT r.*, (CASE WHEN a.hi > a.lo THEN (w_raw - a.lo) / (a.hi - a.lo) ELSE 1.0::DOUBLE END + CASE WHEN b.hi > b.lo THEN (w_raw - b.lo) / (b.hi - b.lo) ELSE 1.0::DOUBLE END) / 2 AS w
  FROM raw_w r JOIN bound a ON a.zip_id = src_zip JOIN bound b ON b.zip_id = dst_zip)"""


def adjacency_sql(source: str, weight: str = "w", how: str = "sym") -> str:
    """CTEs ``arc`` (both directions and loops), ``deg`` and ``a_hat`` from an edge table."""
    by = "sqrt(d.deg * e.deg)" if how == "sym" else "d.deg"
    return f"""arc AS (SELECT src, dst, {weight} AS w FROM {source} WHERE {weight} > 0 UNION ALL SELECT dst, src, {weight} FROM {source} WHERE {weight} > 0 UNION ALL SELECT poi_id, poi_id, 1.0::DOUBLE FROM poi),
deg AS (SELECT dst, sum(w) AS deg FROM arc GROUP BY dst),
a_hat AS (SELECT arc.dst, arc.src, arc.w / {by} AS w FROM arc JOIN deg d ON d.dst = arc.dst JOIN deg e ON e.dst = arc.src)"""


def knn_edges(spark: SparkSession, sf: str) -> tuple[DataFrame, DataFrame]:
    """Points and union edges."""
    p = points.points(spark, sf)
    return p, graph.knn_graph(p, K)


def weighted_edges(spark: SparkSession, sf: str, how: str = "minmax") -> tuple[DataFrame, DataFrame]:
    p, e = knn_edges(spark, sf)
    raw = graph.edge_weight(graph.with_regions(e, p), graph.region_scale(p))
    return p, graph.scale_weights(raw, how)


def dist_haversine(spark: SparkSession, sf: str) -> DataFrame:
    p = points.points(spark, sf).join(points.zip_cells(spark, sf).select("zip_id", "lat0", "lon0"), "zip_id")
    return p.select("poi_id", F.round(geo.haversine_m(F.col("lat"), F.col("lon"), F.col("lat0"), F.col("lon0")), 4).alias("dist_m"))


def dist_planar(spark: SparkSession, sf: str) -> DataFrame:
    x, y = geo.equirectangular(F.col("lat"), F.col("lon"), 30.0, -120.0)
    mx, my = geo.mercator(F.col("lat"), F.col("lon"))
    return points.points(spark, sf).select("poi_id", *(F.round(c, 3).alias(n) for n, c in (("x", x), ("y", y), ("mx", mx), ("my", my))))


def tile_counts(spark: SparkSession, sf: str) -> DataFrame:
    t = points.points(spark, sf).select(geo.tile(F.col("lon") + 180, 0.25).alias("tx"), geo.tile(F.col("lat") + 90, 0.25).alias("ty"))
    return t.groupBy("tx", "ty", geo.zorder(F.col("tx"), F.col("ty")).alias("z")).agg(F.count(F.lit(1)).alias("n"))


def knn_tiled(spark: SparkSession, sf: str) -> DataFrame:
    return graph.knn_tiled(points.points(spark, sf), K).select("src", "dst", "rank", F.round("dist_m", 4).alias("dist_m"))


def knn_brute(spark: SparkSession, sf: str) -> DataFrame:
    return graph.knn_brute(points.points(spark, sf), K).select("src", "dst", "rank", F.round("dist_m", 4).alias("dist_m"))


def knn_union(spark: SparkSession, sf: str) -> DataFrame:
    return knn_edges(spark, sf)[1].select("state_id", "src", "dst", F.round("dist_m", 4).alias("dist_m"))


def knn_mutual(spark: SparkSession, sf: str) -> DataFrame:
    return graph.knn_graph(points.points(spark, sf), K, how="mutual").select("state_id", "src", "dst", F.round("dist_m", 4).alias("dist_m"))


def delaunay_zip(spark: SparkSession, sf: str) -> DataFrame:
    return delaunay.delaunay_local(points.points(spark, sf), ["zip_id"])


def delaunay_state_edges(spark: SparkSession, sf: str) -> DataFrame:
    return delaunay.delaunay_graph(points.points(spark, sf)).select("state_id", "src", "dst", F.round("dist_m", 4).alias("dist_m"))


def coincident_points(spark: SparkSession, sf: str) -> DataFrame:
    snapped = (F.col("poi_id") * 47 + 9) % 400 == 0
    cells = points.zip_cells(spark, sf).select("zip_id", "lat0", "lon0")
    p = points.points(spark, sf).join(cells, "zip_id")
    p = p.withColumns({"lat": F.when(snapped, F.col("lat0") + 0.05).otherwise(F.col("lat")), "lon": F.when(snapped, F.col("lon0") + 0.05).otherwise(F.col("lon"))})
    return graph.coincident_points(p)


def region_scale(spark: SparkSession, sf: str) -> DataFrame:
    return graph.region_scale(points.points(spark, sf)).select("zip_id", "n_r", F.round("scale", 4).alias("scale"))


def region_scale_edges(spark: SparkSession, sf: str) -> DataFrame:
    p, e = knn_edges(spark, sf)
    e = graph.with_regions(e, p)
    parts = [graph.region_scale(p, e, how).select("zip_id", F.round("scale", 4).alias(how)) for how in ("max_edge", "mean_edge", "p95_edge")]
    return parts[0].join(parts[1], "zip_id").join(parts[2], "zip_id")


def edge_weight_raw(spark: SparkSession, sf: str) -> DataFrame:
    return weighted_edges(spark, sf)[1].select("src", "dst", "same_region", F.round("w_raw", 6).alias("w_raw"))


def edge_weight_scaled(spark: SparkSession, sf: str) -> DataFrame:
    return weighted_edges(spark, sf)[1].select("src", "dst", F.round("w", 6).alias("w"))


def graph_by_state(spark: SparkSession, sf: str) -> DataFrame:
    p, e = knn_edges(spark, sf)
    n = p.groupBy("state_id").agg(F.count(F.lit(1)).alias("nodes"))
    return n.join(e.groupBy("state_id").agg(F.count(F.lit(1)).alias("edges")), "state_id").withColumn("edges_per_node", F.round(F.col("edges") / F.col("nodes"), 6))


def sym_norm(spark: SparkSession, sf: str) -> DataFrame:
    p, e = weighted_edges(spark, sf)
    return graph.normalise_adjacency(e, p).select("dst", "src", F.round("w", 6).alias("w"))


def row_norm(spark: SparkSession, sf: str) -> DataFrame:
    p, e = weighted_edges(spark, sf)
    return graph.normalise_adjacency(e, p, "row").select("dst", "src", F.round("w", 6).alias("w"))


def graph_diag(spark: SparkSession, sf: str) -> DataFrame:
    d = graph.graph_diagnostics(weighted_edges(spark, sf)[1])
    return d.select("edges", *(F.round(c, 4).alias(c) for c in ("cross_share", "zero_share", "median_m", "p95_m")))


def degree_histogram(spark: SparkSession, sf: str) -> DataFrame:
    return graph.degree_histogram(knn_edges(spark, sf)[1])


def smoothing_score(spark: SparkSession, sf: str) -> DataFrame:
    p, e = knn_edges(spark, sf)
    h = encode.encode_poi(p, encode.hash_encoder(encode.distinct_paths(p)), 8)
    return graph.smoothing_score(e, h).select("edges", F.round("score", 6).alias("score"))


QUERIES = {f.__name__: f for f in (dist_haversine, dist_planar, tile_counts, knn_brute, knn_tiled, knn_union, knn_mutual, delaunay_zip, delaunay_state_edges, coincident_points, region_scale, region_scale_edges, edge_weight_raw, edge_weight_scaled, graph_by_state, sym_norm, row_norm, graph_diag, degree_histogram, smoothing_score)}

_KNN = f"WITH {KNN} SELECT src, dst, CAST(rank AS INTEGER) AS rank, round(dist_m, 4) AS dist_m FROM knn"
_BITS = " + ".join(f"((tx >> {k}) & 1) * {1 << (2 * k)} + ((ty >> {k}) & 1) * {1 << (2 * k + 1)}" for k in range(16))
_M = 6371000.0

#: Vector of each distinct path under the hashed encoder (d = 8), and of each point: CTEs path_v and poi_v.
HASHED = """path_v AS (SELECT path_key, list(x ORDER BY k) AS v FROM (
    SELECT path_key, k, sum(pow(0.5::DOUBLE, i - 1) * ((((h * (2654435 + 40503 * k) + 7919 * k) % 16777259) % 129) - 64) / 64) AS x
    FROM (SELECT path_key, i, CAST('0x' || substr(md5(array_to_string(list_slice(category_path, 1, i), '>')), 1, 6) AS BIGINT) AS h
      FROM (SELECT DISTINCT array_to_string(category_path, '>') AS path_key, category_path FROM poi), unnest(range(1, 7)) g(i) WHERE i <= len(category_path)),
      unnest(range(0, 8)) d(k) GROUP BY path_key, k) GROUP BY path_key),
poi_v AS (SELECT poi_id, state_id, county_id, zip_id, t, v FROM poi JOIN path_v ON path_key = array_to_string(category_path, '>'))"""

SQL = {
    "dist_haversine": f"WITH {POI}, c AS (SELECT zip_id, lat0 AS lat, lon0 AS lon FROM cell) SELECT poi_id, round({dist('poi', 'c')}, 4) AS dist_m FROM poi JOIN c ON c.zip_id = poi.zip_id",
    "dist_planar": f"WITH {POI} SELECT poi_id, round(radians(lon + 120) * cos(radians(30.0::DOUBLE)) * {_M}::DOUBLE, 3) AS x, round(radians(lat - 30) * {_M}::DOUBLE, 3) AS y, round(radians(lon) * {_M}::DOUBLE, 3) AS mx, round(ln(tan(pi() / 4 + radians(lat) / 2)) * {_M}::DOUBLE, 3) AS my FROM poi",
    "tile_counts": f"WITH {POI}, q AS (SELECT CAST(floor((lon + 180) / 0.25::DOUBLE) AS BIGINT) AS tx, CAST(floor((lat + 90) / 0.25::DOUBLE) AS BIGINT) AS ty FROM poi) SELECT tx, ty, {_BITS} AS z, count(*) AS n FROM q GROUP BY tx, ty",
    "knn_brute": _KNN,
    "knn_tiled": _KNN,
    "knn_union": f"WITH {KNN} SELECT state_id, src, dst, round(dist_m, 4) AS dist_m FROM edge",
    "knn_mutual": f"WITH {KNN} SELECT state_id, src, dst, round(dist_m, 4) AS dist_m FROM edge WHERE times = 2",
    # centres of circles through both ends lie on the bisector; each other point bounds them from one side, and an edge stands if the bounds leave room
    "delaunay_zip": f"""WITH {POI}, q AS (SELECT zip_id, poi_id, round_even(radians(lon + 120) * cos(radians(30.0::DOUBLE)) * {_M}::DOUBLE * 1024, 0) AS x, round_even(radians(lat - 30) * {_M}::DOUBLE * 1024, 0) AS y FROM poi),
pair AS (SELECT a.zip_id, a.poi_id AS src, b.poi_id AS dst, a.x AS ax, a.y AS ay, b.x - a.x AS ux, b.y - a.y AS uy FROM q a JOIN q b ON a.zip_id = b.zip_id AND a.poi_id < b.poi_id),
side AS (SELECT src, dst, pair.zip_id, ux * (c.y - ay) - uy * (c.x - ax) AS turn, (c.x - ax) * (c.x - ax - ux) + (c.y - ay) * (c.y - ay - uy) AS reach FROM pair JOIN q c ON c.zip_id = pair.zip_id AND c.poi_id <> src AND c.poi_id <> dst),
room AS (SELECT zip_id, src, dst, max(CASE WHEN turn < 0 THEN reach / turn END) AS low, min(CASE WHEN turn > 0 THEN reach / turn END) AS high, bool_or(turn = 0 AND reach < 0) AS blocked FROM side GROUP BY zip_id, src, dst)
SELECT zip_id, src, dst FROM room WHERE NOT blocked AND (low IS NULL OR high IS NULL OR low < high)""",
    "coincident_points": f"""WITH {POI}, s AS (SELECT poi_id, poi.state_id, CASE WHEN (poi_id * 47 + 9) % 400 = 0 THEN lat0 + 0.05::DOUBLE ELSE lat END AS lat, CASE WHEN (poi_id * 47 + 9) % 400 = 0 THEN lon0 + 0.05::DOUBLE ELSE lon END AS lon FROM poi JOIN cell ON cell.zip_id = poi.zip_id)
SELECT * FROM (SELECT state_id, poi_id, min(poi_id) OVER (PARTITION BY state_id, lat, lon) AS representative FROM s) WHERE representative <> poi_id""",
    "region_scale": f"WITH {POI}, {SCALE} SELECT zip_id, n_r, round(scale, 4) AS scale FROM scale",
    "region_scale_edges": f"""WITH {WEIGHT} SELECT z.zip_id, round(coalesce(max(dist_m), 0), 4) AS max_edge, round(coalesce(avg(dist_m), 0), 4) AS mean_edge, round(coalesce(quantile_cont(dist_m, 0.95), 0), 4) AS p95_edge
FROM (SELECT DISTINCT zip_id FROM poi) z LEFT JOIN weighted ON src_zip = z.zip_id AND same_region GROUP BY z.zip_id""",
    "edge_weight_raw": f"WITH {WEIGHT} SELECT src, dst, same_region, round(w_raw, 6) AS w_raw FROM weighted",
    "edge_weight_scaled": f"WITH {WEIGHT} SELECT src, dst, round(w, 6) AS w FROM weighted",
    "graph_by_state": f"WITH {KNN} SELECT p.state_id, nodes, edges, round(edges / nodes, 6) AS edges_per_node FROM (SELECT state_id, count(*) AS nodes FROM poi GROUP BY 1) p JOIN (SELECT state_id, count(*) AS edges FROM edge GROUP BY 1) e ON e.state_id = p.state_id",
    "sym_norm": f"WITH {WEIGHT}, {adjacency_sql('weighted')} SELECT dst, src, round(w, 6) AS w FROM a_hat",
    "row_norm": f"WITH {WEIGHT}, {adjacency_sql('weighted', how='row')} SELECT dst, src, round(w, 6) AS w FROM a_hat",
    "graph_diag": f"WITH {WEIGHT} SELECT count(*) AS edges, round(avg(CASE WHEN same_region THEN 0.0::DOUBLE ELSE 1.0::DOUBLE END), 4) AS cross_share, round(avg(CASE WHEN w = 0 THEN 1.0::DOUBLE ELSE 0.0::DOUBLE END), 4) AS zero_share, round(quantile_cont(dist_m, 0.5), 4) AS median_m, round(quantile_cont(dist_m, 0.95), 4) AS p95_m FROM weighted",
    "degree_histogram": f"WITH {KNN} SELECT degree, count(*) AS points FROM (SELECT p, count(*) AS degree FROM (SELECT src AS p FROM edge UNION ALL SELECT dst FROM edge) GROUP BY p) GROUP BY degree",
    "smoothing_score": f"WITH {KNN}, {HASHED} SELECT count(*) AS edges, round(avg(list_cosine_similarity(a.v, b.v)), 6) AS score FROM edge JOIN poi_v a ON a.poi_id = src JOIN poi_v b ON b.poi_id = dst",
}
