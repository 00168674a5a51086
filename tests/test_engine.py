from __future__ import annotations

import duckdb
import numpy as np
import pytest
from pyspark.sql import Window
from pyspark.sql import functions as F

from poiweave.functions import geo, vectors
from poiweave.operators import baselines, delaunay, encode, evaluate, graph, places, propagate, regions
from poiweave.operators.components import connected_components
from poiweave.operators.session import cut
from poiweave.plans.plan import Config, PlaceEngine, PlacePlan
from poiweave.queries import evaluation, features, surround
from poiweave.sources import points
from poiweave.streaming import streams

D = 8
ZIP = ["zip_id"]


@pytest.fixture(scope="module")
def poi(spark, sf):
    return cut(points.points(spark, sf))


@pytest.fixture(scope="module")
def edges(poi):
    return cut(graph.knn_graph(poi, 5))


@pytest.fixture(scope="module")
def a_hat(poi, edges):
    return cut(graph.normalise_adjacency(graph.unit_weights(edges), poi))


@pytest.fixture(scope="module")
def v(poi):
    return cut(encode.encode_poi(poi, encode.hash_encoder(encode.distinct_paths(poi), D), D))


@pytest.fixture(scope="module")
def h(poi, v, a_hat):
    return cut(propagate.propagate(v, a_hat, (0.5, 0.5), D).join(poi.select("poi_id", "state_id", "zip_id"), "poi_id"))


def frame(df, key="poi_id", column="h"):
    return {r[key]: np.array(r[column]) for r in df.collect()}


def same(a, b, tol=1e-9):
    assert a.keys() == b.keys()
    assert max(np.abs(a[k] - b[k]).max() for k in a) < tol


def test_tiled_neighbours_equal_brute_force(poi):
    for metric in ("haversine", "planar"):
        tiled = graph.knn_tiled(poi, 5, metric, degrees=0.05, most_points=8).select("src", "dst", "rank")
        brute = graph.knn_brute(poi, 5, metric).select("src", "dst", "rank")
        assert tiled.exceptAll(brute).isEmpty() and brute.exceptAll(tiled).isEmpty()


def test_strips_equal_all_pairs(spark, poi):
    lone = spark.createDataFrame([(0, -5, 31.9, -113.0), (9, -6, 10.0, 10.0), (9, -7, 10.0, 10.0), (7, -8, 1.0, 179.999), (7, -9, 1.0, -179.999)], "state_id int, poi_id long, lat double, lon double")
    p = poi.select("state_id", "poi_id", "lat", "lon").unionByName(lone)
    a, b = p.alias("a"), p.alias("b")
    for metric in ("haversine", "planar"):
        pairs = a.join(b, (F.col("a.state_id") == F.col("b.state_id")) & (F.col("a.poi_id") != F.col("b.poi_id")))
        far = geo.distance(metric, F.col("a.lat"), F.col("a.lon"), F.col("b.lat"), F.col("b.lon"))
        pairs = pairs.select(F.col("a.poi_id").alias("src"), F.col("b.poi_id").alias("dst"), far.alias("dist_m"))
        want = cut(pairs.withColumn("rank", F.row_number().over(Window.partitionBy("src").orderBy("dist_m", "dst"))).filter("rank <= 5").select("src", "dst", "rank"))
        for block in (3, 50, 4096):
            got = cut(graph.knn_brute(p, 5, metric, block).select("src", "dst", "rank"))
            assert got.exceptAll(want).isEmpty() and want.exceptAll(got).isEmpty()


def test_graphs_are_built_in_strips(poi, edges, monkeypatch):
    tiled = cut(graph.knn_graph(poi, 5, method="tiled").select("src", "dst"))
    assert tiled.exceptAll(edges.select("src", "dst")).isEmpty() and edges.select("src", "dst").exceptAll(tiled).isEmpty()
    monkeypatch.setattr(graph, "knn_tiled", None)  # the tiles' candidate pairs are what fills the disk
    assert graph.knn_graph(poi, 5).count() == edges.count()


def test_neighbours_of_tiny_states(spark):
    p = spark.createDataFrame([(1, 0, 1.0, 1.0), (2, 1, 1.0, 1.0), (3, 1, 1.0, 2.0)], "poi_id long, state_id int, lat double, lon double")
    got = {(r.src, r.dst) for r in graph.knn_tiled(p, 5).collect()}
    assert got == {(2, 3), (3, 2)}


def test_fifth_neighbour_is_within_the_oracles_reach(spark):
    p = points.points(spark, "/root/testdata/sf0.01")
    assert graph.knn_tiled(p, 5).agg(F.max("dist_m")).first()[0] < 0.05 * 111_000 * 0.8


def test_tiled_triangulation_equals_the_whole(poi):
    tiled = delaunay.delaunay_tiled(poi, tile_m=12_000.0, most_points=60).select("src", "dst")
    whole = delaunay.delaunay_local(poi, ["state_id"]).select("src", "dst")
    assert tiled.exceptAll(whole).isEmpty() and whole.exceptAll(tiled).isEmpty()


def test_triangulation_with_coincident_points(spark, poi):
    twin = poi.limit(5).withColumn("poi_id", F.col("poi_id") + 10_000_000)
    both = cut(poi.unionByName(twin))
    g = delaunay.delaunay_graph(both, tile_m=5_000.0)
    assert g.filter("dist_m = 0").count() == 5 and g.filter("src = dst").isEmpty()


def test_triangulation_holds_the_nearest_neighbours(poi):
    one = graph.knn_tiled(poi, 1, "planar").select(F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst")).distinct()
    d = delaunay.delaunay_local(poi, ["state_id"]).select("src", "dst")
    # the plane of the triangulation has one scale for all latitudes, so a few nearest pairs may differ
    assert one.join(d, ["src", "dst"], "left_anti").count() <= 0.01 * one.count()


def test_weights_lie_in_bounds_and_cross_edges_weigh_less(poi, edges):
    e = graph.with_regions(edges, poi)
    w = graph.scale_weights(graph.edge_weight(e, graph.region_scale(poi)))
    assert w.filter("w < 0 or w > 1 or w_raw < 0").isEmpty() and w.filter("not same_region").count() > 0
    s = graph.region_scale(poi).withColumn("scale", F.lit(5000.0))
    one = graph.edge_weight(e, s, cross=1.0).select("src", "dst", "same_region", F.col("w_raw").alias("full"))
    both = graph.edge_weight(e, s).join(one, ["src", "dst", "same_region"])
    assert both.filter(F.abs(F.col("w_raw") - F.col("full") * F.when(F.col("same_region"), 1.0).otherwise(0.4)) > 1e-9).isEmpty()
    for how in ("max", "none"):
        assert graph.scale_weights(graph.edge_weight(e, s), how).count() == edges.count()


def test_normalised_graph_keeps_root_degrees(poi, edges, a_hat):
    ends = edges.select(F.explode(F.array("src", "dst")).alias("p")).groupBy("p").count()
    root = poi.select("poi_id").join(ends.withColumnRenamed("p", "poi_id"), "poi_id", "left").select("poi_id", F.array(F.sqrt(1 + F.coalesce("count", F.lit(0)))).alias("h"))
    same(frame(propagate.hop(root, a_hat, 1)), frame(root), 1e-9)
    row = graph.normalise_adjacency(graph.unit_weights(edges), poi, "row").groupBy("dst").agg(F.sum("w").alias("w"))
    assert row.filter(F.abs(F.col("w") - 1) > 1e-9).isEmpty()


def test_propagation_is_linear_and_shrinks(v, a_hat):
    h1, h2 = (x for x in propagate.hops(v, a_hat, 2, D)[1:])
    twice = propagate.hop(v.withColumn("h", F.transform("h", lambda x: 2 * x)), a_hat, D)
    one = frame(h1)
    same(frame(twice), {k: 2 * x for k, x in one.items()})
    size = [np.sqrt(sum((x**2).sum() for x in frame(t).values())) for t in (v, h1, h2)]
    assert size[0] >= size[1] >= size[2]
    same(frame(propagate.combine([v, h1], (1.0, -0.5), D)), {k: a - 0.5 * one[k] for k, a in frame(v).items()})
    with pytest.raises(ValueError):
        propagate.propagate(v, a_hat, (0.0, 0.0), D)


def test_factored_propagation_is_the_same(poi, v, a_hat):
    table = encode.hash_encoder(encode.distinct_paths(poi), D)
    paths = poi.select("poi_id", F.array_join("category_path", ">").alias("path_key"))
    same(frame(propagate.propagate_factored(paths, table, a_hat, (0.5, 0.25, 0.75), D)), frame(propagate.propagate(v, a_hat, (0.5, 0.25, 0.75), D)))


def test_zero_hops_make_the_mean_baseline(poi, v, a_hat):
    table = encode.hash_encoder(encode.distinct_paths(poi), D)
    h0 = propagate.propagate(v, a_hat, (1.0, 0.0, 0.0), D).join(poi.select("poi_id", "zip_id"), "poi_id")
    same(frame(regions.region_mean(h0, ZIP, D), "zip_id", "z"), frame(baselines.mean_baseline(poi, table, ZIP, D), "zip_id", "z"))


def test_region_vector_does_not_depend_on_the_ratio(h):
    want = frame(regions.region_mean(h, ZIP, D), "zip_id", "z")
    for r in ("0.1", "0.02"):
        m = cut(places.bisect_places(h, ZIP, r))
        s = places.summarise_places(m, h, D).join(m.select("place_id", "zip_id").distinct(), "place_id")
        same(frame(regions.region_embedding(s, ZIP, D), "zip_id", "z"), want)


def test_engines_split_alike(h):
    task = {r.poi_id: r.place_id for r in places.bisect_places(h, ["state_id"], "0.01", engine="task").collect()}
    spread = {r.poi_id: r.place_id for r in places.bisect_places(h, ["state_id"], "0.01", engine="distributed").collect()}
    assert task == spread


@pytest.mark.parametrize("node_points", [10**9, 300])
def test_leaves_beyond_a_task_are_split_alike(h, monkeypatch, node_points):
    """Leaves of more than ``node_points`` points are split by all executors, smaller ones with what lies below them in a task: a state whose leaves all fit takes one round."""
    rounds = []
    expand_nodes = places._expand_nodes
    monkeypatch.setattr(places, "_expand_nodes", lambda *a: rounds.append(1) or expand_nodes(*a))
    rows = h.withColumn("weight", 1.0 + F.col("poi_id") % 3)
    for option in ({}, {"weight": "weight"}) if node_points > 300 else ({"weight": "weight"},):
        task = {r.poi_id: r.place_id for r in places.bisect_places(rows, ["state_id"], "0.004", engine="task", **option).collect()}
        rounds.clear()
        spread = {r.poi_id: r.place_id for r in places.bisect_places(rows, ["state_id"], "0.004", engine="distributed", node_points=node_points, **option).collect()}
        assert task == spread and (len(rounds) == 1) == (node_points > 300)


def test_auto_engine_routes_by_size(h):
    n = h.groupBy("zip_id").count().agg(F.max("count")).first()[0]
    got = places.bisect_places(h, ZIP, "0.02", task_points=n - 1)
    want = places.bisect_places(h, ZIP, "0.02", engine="task")
    assert got.select("poi_id", "place_id").exceptAll(want.select("poi_id", "place_id")).isEmpty()


def test_places_partition_points_and_lie_inside_their_members(h, poi):
    m = cut(places.bisect_places(h, ZIP, "0.1"))
    assert m.count() == h.count() == m.select("poi_id").distinct().count()
    s = places.summarise_places(m, h, D, poi)
    box = m.join(poi.select("poi_id", "lat", "lon"), "poi_id").groupBy("place_id").agg(F.min("lat").alias("a"), F.max("lat").alias("b"), F.min("lon").alias("c"), F.max("lon").alias("d"))
    assert s.join(box, "place_id").filter("lat < a - 1e-9 or lat > b + 1e-9 or lon < c - 1e-9 or lon > d + 1e-9").isEmpty()
    assert places.members_of(m).select(F.explode("poi_ids")).count() == m.count()


def test_density_engines_agree(poi, spark, sf):
    """Points projected to metres about their cell: vector reach and ground reach are nearly the same thing."""
    c = points.zip_cells(spark, sf).select("zip_id", "lat0", "lon0")
    x = F.radians(F.col("lon") - F.col("lon0")) * F.cos(F.radians(F.col("lat0") + 0.05)) * 6_371_000
    flat = poi.join(c, "zip_id").select("state_id", "zip_id", "poi_id", F.array(x, F.radians(F.col("lat") - F.col("lat0")) * 6_371_000).alias("h"))
    a = places.density_places(flat, ZIP, 400.0, 4).select("poi_id", "place_id", "is_core")
    b = places.density_places_spatial(poi, 400.0, 4, ZIP).select("poi_id", "place_id", "is_core")
    assert a.exceptAll(b).count() <= 0.02 * poi.count()
    assert places.density_places(flat, ZIP, 400.0, 4, noise="own").filter("place_id is null").isEmpty()


def test_components_against_union_find(spark):
    r = np.random.default_rng(0)
    pairs = [(int(a), int(b)) for a, b in r.integers(0, 300, (200, 2))] + [(k, k + 1) for k in range(1000, 1040)] + [(5000, k) for k in range(4000, 4100)]
    got = {x.node: x.root for x in connected_components(spark.createDataFrame(pairs, "a long, b long")).collect()}
    root = {}

    def find(i):
        while root.setdefault(i, i) != i:
            i = root[i]
        return i

    for a, b in pairs:
        if a != b:
            a, b = find(a), find(b)
            root[max(a, b)] = min(a, b)
    assert got == {n: find(n) for n in root}


def test_rollups_equal_direct_means(h, poi):
    rows = h.drop("state_id", "zip_id").join(poi.select("poi_id", "state_id", "county_id", "zip_id"), "poi_id")
    r = regions.rollup_embeddings(regions.region_mean(rows, ["state_id", "county_id", "zip_id"], D), ["state_id", "county_id", "zip_id"], D)
    same(frame(r.filter("county_id is null and state_id is not null"), "state_id", "z"), frame(regions.region_mean(rows, ["state_id"], D), "state_id", "z"))


def test_measures(spark):
    p = spark.createDataFrame([(0, 1.0, 1.0), (0, 2.0, 2.0), (1, 1.0, 2.0), (1, 3.0, 2.0), (2, 5.0, 4.0), (2, 5.0, 7.0)], "g int, y double, yhat double")
    s = {r.g: r for r in evaluate.score(p, ["g"]).collect()}
    assert (s[0].rmse, s[0].r2) == (0, 1) and s[1].r2 == 0 and s[2].r2 is None
    assert s[2].rmse >= s[2].mae


def test_splits_are_exact_and_repeatable(poi, spark, sf):
    y = points.labels(poi, points.zip_cells(spark, sf))
    s = cut(evaluate.split_runs(y))
    share = s.groupBy("state_id", "run").agg(F.sum(F.col("is_train").cast("int")).alias("k"), F.count(F.lit(1)).alias("n"))
    assert share.filter("k <> floor(n * 0.8)").isEmpty()
    assert s.exceptAll(evaluate.split_runs(y)).isEmpty()


def test_plan_rewrites():
    plan = PlacePlan.of(Config(alpha=(0.5, 0.0, 0.0))).rewrite()
    assert [s.kind for s in plan.steps] == ["source", "encode", "propagate", "aggregate"]
    plan = PlacePlan.of(Config(alpha=(0.5, 0.5, 0.0)), ("places",)).rewrite()
    assert [s.kind for s in plan.steps] == ["source", "graph", "encode", "propagate", "cluster", "aggregate"]
    assert plan.steps[3].get("alpha") == (0.5, 0.5)
    assert PlacePlan.of(Config(alpha=(0.5, 0.5), max_categories_in_reach=3)).rewrite().steps[3].get("form") == "factored"
    with pytest.raises(ValueError):
        PlacePlan.of(Config(alpha=(0.0,))).rewrite()


def test_rewritten_plan_gives_the_same_vectors(spark, sf, poi):
    engine = PlaceEngine(spark).with_points(poi)
    plain = engine.alpha(0.5, 0.5).frames("places")["regions"]
    short = engine.set(alpha=(0.5, 0.5, 0.0), max_categories_in_reach=1.0).frames("regions")["regions"]
    same(frame(plain, "zip_id", "z"), frame(short, "zip_id", "z"))
    assert "cluster" in engine.explain("places")


def test_filters_reach_the_scan_and_columns_are_pruned(spark, sf):
    plan = points.points(spark, sf)._jdf.queryExecution().executedPlan().toString()
    assert "l_tax" not in plan and "s_acctbal" not in plan
    few = spark.read.parquet(f"{sf}/supplier.parquet").filter("s_nationkey = 3").select("s_suppkey")._jdf.queryExecution().executedPlan().toString()
    assert "PushedFilters: [IsNotNull(s_nationkey), EqualTo(s_nationkey,3)]" in few


def test_empty_points(spark, sf, poi):
    none = poi.limit(0)
    assert graph.knn_tiled(none, 5).count() == 0
    assert delaunay.delaunay_tiled(none).count() == 0
    v = encode.encode_poi(none, encode.hash_encoder(encode.distinct_paths(none), D), D)
    assert v.count() == 0


def test_planted_districts_are_found_better_with_propagation(poi, edges, v, a_hat):
    share = []
    for alpha in ((1.0,), (0.25, 0.5, 0.5)):
        x = propagate.propagate(v, a_hat, alpha, D).join(poi.select("poi_id", "zip_id"), "poi_id")
        c = places.place_contiguity(edges, places.bisect_places(x, ZIP, "0.05")).agg(F.sum("n_inside"), F.sum("n_touching")).first()
        share.append(c[0] / c[1])
    assert share[1] > share[0]


def test_likeness_of_neighbours_rises_with_the_second_hop(v, a_hat, edges):
    levels = propagate.hops(v, a_hat, 2, D)
    score = [graph.smoothing_score(edges, propagate.combine(levels, (0.5, 0.25, a), D)).first().score for a in (0.0, 0.5, 1.0)]
    assert score == sorted(score)


def test_voronoi_cells_tile_the_square(poi, spark, sf):
    v = delaunay.voronoi_cells(poi, points.polygons(points.zip_cells(spark, sf))).groupBy("zip_id").agg(F.sum("area").alias("a"))
    assert v.filter(F.abs(F.col("a") - 0.01) > 1e-9).isEmpty()


def test_points_at_one_place_share_a_voronoi_cell(spark):
    square = [(0.0, 0.0), (0.0, 0.1), (0.1, 0.1), (0.1, 0.0)]
    p = spark.createDataFrame([(1, 1, 0.05, 0.02), (1, 2, 0.05, 0.08), (1, 3, 0.05, 0.08)], "zip_id long, poi_id long, lat double, lon double")
    r = spark.createDataFrame([(1, square)], "zip_id long, polygon array<struct<lon:double,lat:double>>")
    got = {c.poi_id: c for c in delaunay.voronoi_cells(p, r).collect()}
    assert [round(got[i].area, 9) for i in (1, 2, 3)] == [0.005, 0.0025, 0.0025] and got[2].polygon == got[3].polygon


def test_stream_state_handles_closures(spark):
    rows = [(1, 1, [1.0, 2.0]), (1, 1, [3.0, 4.0]), (1, -1, [1.0, 2.0]), (2, 1, [5.0, 5.0])]
    place = streams._place(spark, "life-test")
    spark.createDataFrame(rows, "zip_id long, sign int, h array<double>").repartition(1).write.parquet(place)
    s = spark.readStream.schema("zip_id long, sign int, h array<double>").parquet(place)
    got = {r.zip_id: (r.n, r.s) for r in streams.drain(streams.region_state(s, 2), "update").collect()}
    assert got == {1: (1, [3.0, 4.0]), 2: (1, [5.0, 5.0])}


def test_halves_are_rounded_as_in_sql(spark):
    rows = [0.0644375, -0.0644375, 0.0078125, -0.0078125, 0.0000005, 0.49999949999999997, 1.0, 0.0]
    df = spark.createDataFrame([(rows,)], "h array<double>")
    want = duckdb.connect().execute("select list_transform(?::DOUBLE[], lambda x: round(x, 6) + 0.0::DOUBLE)", [rows]).fetchall()[0][0]
    assert df.select(vectors.rounded(F.col("h"))).first()[0] == want


def test_vector_expressions_guard_zero(spark):
    z = spark.range(1).select(F.array(F.lit(0.0), F.lit(0.0)).alias("a"), F.array(F.lit(1.0), F.lit(0.0)).alias("b"))
    assert z.select(vectors.cosine(F.col("a"), F.col("b"))).first()[0] is None


def test_sequence_encoder_keeps_every_path(spark):
    visits = spark.createDataFrame([("x", k, ["a" if k % 3 else "b"]) for k in range(12)], "visitor string, pos long, category_path array<string>")
    paths = encode.distinct_paths(spark.range(5000).select(F.array(F.when(F.col("id") % 2 == 0, "a").otherwise("b"), F.col("id").cast("string")).alias("category_path")))
    got = encode.fit_sequence_encoder(visits, paths, levels=1, d=3)
    assert got.count() == got.select("path_key").distinct().count() == 5000
    assert got.filter(F.size("v") == 3).groupBy(F.substring("path_key", 1, 1)).agg(F.count_distinct("v").alias("n")).filter("n = 1").count() == 2
    assert got.filter(F.exists("v", lambda x: x != 0)).count() > 0


def test_compared_methods_have_the_protocol_dimension(spark, sf):
    assert {(r.method, r.d) for r in evaluation.align_dimension(spark, sf).collect()} == {(m, 30) for m in evaluation.METHODS}


def test_transfer_workload_runs_the_whole_protocol(spark, sf, monkeypatch):
    asked = []
    monkeypatch.setattr(evaluation, "method_features", lambda *a, epochs=evaluation.EPOCHS: asked.append((a[2:], epochs)) or {m: None for m in evaluation.METHODS})
    monkeypatch.setattr(evaluate, "fit_predict", lambda f, y, splits, *a: splits.select("state_id", F.lit(a[2]).alias("method"), "run", F.lit(1.0).alias("y"), F.lit(1.0).alias("yhat")))
    assert {r.runs for r in evaluation.w_transfer(spark, sf).collect()} == {evaluate.RUNS}
    assert asked == [(("density",), 100)]


@pytest.mark.parametrize("name", ["predict_rf", "predict_gbt"])
def test_tree_predictions_cover_all_runs(spark, sf, monkeypatch, name):
    monkeypatch.setattr(evaluation, "features", lambda *_: (None, None))
    monkeypatch.setattr(regions, "region_mean", lambda *_: spark.range(1))
    monkeypatch.setattr(evaluate, "fit_predict", lambda f, y, splits, *_: splits.filter("not is_train"))
    assert {r.run for r in getattr(evaluation, name)(spark, sf).select("run").distinct().collect()} == set(range(evaluate.RUNS))


def test_tuning_covers_both_targets_and_all_runs(spark, monkeypatch):
    y = spark.createDataFrame([(0, k, float(k), float(-k * k)) for k in range(10)], "state_id int, zip_id long, density double, price double")
    means = [y.select("zip_id", F.array(F.col("density") * m, F.sin("density")).alias("z")) for m in (1.0, 0.5, 0.2)]
    grid = evaluate.alpha_grid(spark, step=1.0)
    ten, default = (sorted((r.a0, r.a1, r.a2, round(r.rmse, 9)) for r in evaluate.tune(means, y, "price", grid, 2, *more).collect()) for more in ((evaluate.RUNS,), ()))
    assert ten == default
    monkeypatch.setattr(evaluation, "_hop_means", lambda *_: means)
    monkeypatch.setattr(evaluation, "_labels", lambda *_: y)
    monkeypatch.setattr(evaluate, "tune", lambda m, y, target, *_: spark.range(5).select((F.col("id") + 1).alias("place")))
    assert sorted((r.target, r.place) for r in evaluation.tune_settings(spark, "").collect()) == [(t, k) for t in ("density", "price") for k in (1, 2, 3)]


def test_members_below_a_place(spark):
    rows = [(k, p) for k, p in enumerate(("1|0", "1|01", "1|010", "1|1", "1|k1", "1|k10", "1|d1", "1|d10", "10|0", "1|"))]
    m = spark.createDataFrame(rows, "poi_id long, place_id string")
    below = lambda p: {r.place_id for r in places.members_of(m, p).collect()}
    assert below("1|0") == {"1|0", "1|01", "1|010"} and below("1|k1") == {"1|k1"} and below("1|d1") == {"1|d1"}
    assert below("1|") == {"1|", "1|0", "1|01", "1|010", "1|1"}


def test_points_nearer_than_the_grid_hang_on_one(spark):
    rows = [(k, 0, 30.0 + (k % 7) * 0.01 + (k // 7) * 0.003, -119.0 + (k * 13 % 11) * 0.01) for k in range(40)]
    rows += [(100, 0, rows[3][2] + 1e-11, rows[3][3]), (101, 0, rows[3][2], rows[3][3])]
    p = spark.createDataFrame(rows, "poi_id long, state_id int, lat double, lon double")
    g = delaunay.delaunay_graph(p, tile_m=2_000.0)
    assert {r.dst for r in g.filter("src = 3 and dst >= 100").collect()} == {100, 101}
    plain = delaunay.delaunay_local(p.filter("poi_id < 100"), ["state_id"])
    assert {(r.src, r.dst) for r in g.filter("dst < 100").collect()} == {(r.src, r.dst) for r in plain.collect()}


def test_contiguity_of_any_polygons(spark):
    ring = lambda *xy: [{"lon": float(x), "lat": float(y)} for x, y in xy]
    rows = [
        (1, ring((0, 0), (2, 0), (2, 2), (0, 2))),
        (2, ring((2, 0.5), (3, 0.5), (3, 1), (2, 1))),  # part of a side, no vertex in common
        (3, ring((2, 2), (3, 2), (3, 3))),  # one corner
        (4, ring((1, 2), (1.5, 3), (0.5, 3))),  # a corner on a side
        (5, ring((10, 0), (11, 0), (10, 1))),  # apart
        (6, ring((2.999, 1.5), (4, 1.5), (4, 1.6))),  # near nothing
    ]
    p = spark.createDataFrame(rows, "zip_id long, polygon array<struct<lon:double,lat:double>>")
    pairs = lambda how: {(r.a, r.b) for r in regions.region_adjacency(p, how).collect()}
    assert pairs("queen") == {(1, 2), (1, 3), (1, 4)} and pairs("rook") == {(1, 2)}


def test_overlapping_states_share_no_neighbours(spark):
    square = lambda x: [(x, 0.0), (x, 1.0), (x + 1.0, 1.0), (x + 1.0, 0.0)]
    rows = [(0, 1, square(0.0)), (0, 2, square(1.0)), (1, 3, square(1.0)), (1, 4, square(2.0))]
    p = spark.createDataFrame(rows, "state_id int, zip_id long, polygon array<struct<lon:double,lat:double>>")
    for how in ("queen", "rook"):
        assert {(r.a, r.b) for r in regions.region_adjacency(p, how, within=("state_id",)).collect()} == {(1, 2), (3, 4)}
        assert {(1, 3), (2, 4)} <= {(r.a, r.b) for r in regions.region_adjacency(p, how).collect()}


def test_points_meet_the_cells_of_their_own_state(spark, sf, poi, monkeypatch):
    monkeypatch.setattr(points, "STATE_STEP", 0.1)  # states overlap
    got = {r.zip_id: r.n for r in surround.join_point_in_cell(spark, sf).collect()}
    assert got == {r.zip_id: r["count"] for r in poi.groupBy("zip_id").count().collect()}


def test_jaccard_of_touching_regions_equals_sql(spark, sf):
    c = duckdb.connect()
    for t in ("supplier", "nation", "lineitem", "part"):
        c.execute(f"create view {t} as select * from '{sf}/{t}.parquet'")
    want = sorted(c.execute(surround.SQL["set_jaccard"]).fetchall())
    assert want and sorted(map(tuple, surround.set_jaccard(spark, sf).select("a", "b", "jaccard").collect())) == want


def test_engines_refuse_or_keep_every_option(h):
    with pytest.raises(ValueError, match="kmeans"):
        places.bisect_places(h, ["state_id"], "0.01", engine="distributed", init="kmeans++")
    assert places.bisect_places(h.limit(0), ["state_id"], "0.01", engine="distributed").count() == 0
    chosen = {}
    for priority in ("size", "sse"):
        engine = PlacePlan.of(Config(d=D, priority=priority, r="0.02", keys=("state_id",), levels=("state_id",), alpha=(1.0,)), ["places"])
        assert engine.config.priority == priority
        own = [sorted(r[0] for r in places.bisect_places(h, ["state_id"], "0.004", engine=e, priority=priority).groupBy("place_id").count().select("count").collect()) for e in ("task", "distributed")]
        assert own[0] == own[1]
        chosen[priority] = {(r.poi_id, r.place_id) for r in places.bisect_places(h, ZIP, "0.1", engine="task", priority=priority).collect()}
    assert chosen["size"] != chosen["sse"]


def test_condensed_places_equal_their_members(h):
    m = places.bisect_places(h, ZIP, "0.1")
    want = {r.place_id: r for r in places.summarise_places(m, h, D).collect()}
    got = {r.place_id: r for r in places.condensed_places(h, ZIP, "0.1").collect()}
    assert got.keys() == want.keys()
    assert all(got[k].n_poi == want[k].n_poi and abs(got[k].sse - want[k].sse) < 1e-9 and np.allclose(got[k].z, want[k].z) for k in want)


def test_measures_recomputed_by_sql_from_written_predictions(spark, sf, h):
    """Predictions go to Parquet; DuckDB scores them anew and lays the squared errors of places against their members."""
    import duckdb

    y = points.labels(points.points(spark, sf), points.zip_cells(spark, sf))
    pred = evaluate.fit_predict(regions.region_mean(h, ZIP, D), y, evaluate.split_runs(y), "density", "forest")
    folder = streams._place(spark, "predictions")
    pred.write.parquet(f"{folder}/pred")
    m = places.bisect_places(h, ZIP, "0.1")
    m.write.parquet(f"{folder}/members")
    h.select("poi_id", "h").write.parquet(f"{folder}/h")
    con = duckdb.connect()
    want = con.execute(f"SELECT state_id, run, sqrt(avg((y - yhat) * (y - yhat))), avg(abs(y - yhat)), CASE WHEN var_pop(y) > 1e-12 THEN 1 - sum((y - yhat) * (y - yhat)) / (var_pop(y) * count(*)) END FROM '{folder}/pred/*.parquet' GROUP BY 1, 2 ORDER BY 1, 2").fetchall()
    got = sorted((r.state_id, r.run, r.rmse, r.mae, r.r2) for r in evaluate.score(spark.read.parquet(f"{folder}/pred"), ["state_id", "run"]).collect())
    assert all(a[:2] == b[:2] and all((p is None and q is None) or abs(p - q) < 1e-9 for p, q in zip(a[2:], b[2:], strict=True)) for a, b in zip(got, want, strict=True))
    sse = dict(con.execute(f"WITH x AS (SELECT place_id, i, h[i + 1] AS v FROM '{folder}/members/*.parquet' JOIN '{folder}/h/*.parquet' USING (poi_id), unnest(range(0, {D})) g(i)), z AS (SELECT place_id, i, avg(v) AS c FROM x GROUP BY 1, 2) SELECT x.place_id, sum((v - c) * (v - c)) FROM x JOIN z ON z.place_id = x.place_id AND z.i = x.i GROUP BY 1").fetchall())
    assert all(abs(sse[r.place_id] - r.sse) < 1e-9 for r in places.condensed_places(h, ZIP, "0.1").collect())


def test_settings_are_chosen_without_the_test_regions(spark):
    """Changing labels of regions that a run tests changes nothing of what that run's training regions say."""
    rows = [(z, z % 2, float(z * 7 % 13), [float(z % 5), float(z % 3)]) for z in range(40)]
    means = [spark.createDataFrame([(z, [v * k for v in x]) for z, _, _, x in rows], "zip_id long, z array<double>") for k in (1, 2, 3)]
    y = spark.createDataFrame([r[:3] for r in rows], "zip_id long, state_id int, density double")
    tested = {r.zip_id for r in evaluate.split_runs(y, 1).filter("not is_train").collect()}
    z = y.withColumn("density", F.when(F.col("zip_id").isin(*tested), 1e6).otherwise(F.col("density")))
    grid = evaluate.alpha_grid(spark, step=0.5)
    a, b = (sorted((r.state_id, r.a0, r.a1, r.a2, r.rmse) for r in evaluate.tune(means, labels, "density", grid, 2, 1).collect()) for labels in (y, z))
    assert a == b and len(a) == 2 * 26


def test_a_batch_that_runs_again_doubles_nothing(spark, sf, monkeypatch):
    s = streams.events(spark, sf)
    seen = streams.drain(s.select("event_id"))
    n = seen.count()
    folder = seen.inputFiles()[0].split("/batch=")[0]
    seen.write.mode("overwrite").parquet(f"{folder}-again/batch=0")
    seen.write.mode("overwrite").parquet(f"{folder}-again/batch=0")
    assert n == spark.read.parquet(f"{folder}-again").count() == spark.read.parquet(f"{sf}/events.parquet").count()


@pytest.mark.parametrize("name", ["alpha_grid", "published_settings", "speedup"])
def test_settings_and_growth_are_those_of_the_given_points(spark, sf, name):
    """The tables of settings and of published seconds meet the given points, and equal the SQL."""
    import __spark_entry__ as entry

    own = entry.queries()[name](spark, sf)
    if name != "speedup":  # its sizes are materialised on the way
        assert any("lineitem" in f for f in own.inputFiles())
    duck = duckdb.connect()
    for t in ("region", "nation", "supplier", "part", "orders", "lineitem"):
        duck.execute(f"create view {t} as select * from '{sf}/{t}.parquet'")
    want = duck.execute(entry.oracle_sql()[name]).fetchdf()
    columns = sorted(want.columns)
    got = own.toPandas()
    assert sorted(got.columns) == columns and len(got) == len(want)
    assert len(got) == {"alpha_grid": 5 * 125, "published_settings": 5 * 14, "speedup": 4 * (3 + 5)}[name]
    plain = lambda df: sorted(tuple(round(v, 3) if isinstance(v, float) else str(v) for v in row) for row in df[columns].itertuples(index=False))
    assert plain(got) == plain(want)


def test_coded_hop_equals_propagation(spark, sf, poi, v, a_hat):
    p, table = features.coded_points(spark, sf)
    directed = graph.knn_brute(p).select("src", "dst")
    for alpha in ((0.5, 0.5), (0.0, 1.0)):
        got = propagate.propagate_coded(p.select("poi_id", "code"), directed.unionByName(directed), table, alpha, D)  # arcs given twice count once
        same(frame(got), frame(propagate.propagate(v, a_hat, alpha, D)))
    assert p.count() == poi.count() and not {"h", "category_path"} & set(p.columns)


def test_place_fragments_of_whole_places(spark, edges, poi, monkeypatch):
    members = poi.select("poi_id", "zip_id", F.concat_ws("|", "zip_id", F.col("category_path")[0]).alias("place_id"))
    got = {r["place_id"]: r["fragments"] for r in places.place_fragments(edges, members).collect()}
    place = {r["poi_id"]: r["place_id"] for r in members.collect()}
    root = {i: i for i in place}

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for a, b in edges.select("src", "dst").collect():
        if place[a] == place[b]:
            root[find(a)] = find(b)
    want = {}
    for i in place:
        want.setdefault(place[i], set()).add(find(i))
    assert got == {k: len(v) for k, v in want.items()} and max(got.values()) > 1
    monkeypatch.setattr(places, "connected_components", None)  # no rounds over all executors
    back = edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"))
    assert {r["place_id"]: r["fragments"] for r in places.place_fragments(edges.select("src", "dst").unionByName(back), members).collect()} == got


def test_links_of_a_place_cut_by_batches():
    import pandas as pd

    rows = pd.DataFrame({"place_id": list("aaaabbbbc"), "src": [1, 2, 3, 1, 7, 8, 11, 12, 1], "dst": [2, 3, 1, 9, 8, 7, 12, 13, 2]})
    for size in range(1, 10):
        out = pd.concat(places._count_links(rows[k : k + size] for k in range(0, 9, size)))
        assert dict(zip(out["place_id"], out["links"], strict=True)) == {"a": 3, "b": 3, "c": 1}


def test_recommended_regions_equal_plain_comparison(spark, monkeypatch):
    r = np.random.default_rng(5)
    z = np.round(r.normal(size=(300, 3)) * 2) / 2  # many ties, a few zero vectors
    rows = [(f"p{i:03d}", int(i % 11), x.tolist()) for i, x in enumerate(z)] + [("zero", 77, [0.0, 0.0, 0.0]), ("nowhere", None, [1.0, 0.0, 0.0])]
    p = spark.createDataFrame(rows, "place_id string, region_id long, z array<double>")
    q = p.filter("place_id like '%0'").select(F.col("place_id").alias("query_id"), "region_id", F.col("z").alias("q"))
    met = places._pairs_in_scope(p.select(F.col("region_id").alias("__r"), "place_id", "z"), q.select("query_id", F.col("region_id").alias("__qr"), "q"), "across")
    top = met.groupBy("query_id", F.col("__r").alias("region")).agg(F.max("cosine").alias("cosine"))
    want = top.withColumn("rank", F.row_number().over(Window.partitionBy("query_id").orderBy(F.desc_nulls_last("cosine"), "region")))
    monkeypatch.setattr(places, "_pairs_in_scope", None)  # pairs stay in their task
    for k, cells in ((3, 1 << 18), (20, 100)):
        monkeypatch.setattr(places, "CELLS", cells)
        got = places.recommend_regions(p, q, k)
        assert sorted(map(str, got.select("query_id", "region", "cosine", "rank").collect())) == sorted(map(str, want.filter(F.col("rank") <= k).select("query_id", "region", "cosine", "rank").collect()))


def test_places_of_places_and_recommendations_find_places_once(spark, sf, monkeypatch):
    from poiweave.queries import places as queries

    monkeypatch.setattr(places, "summarise_places", None)  # summed up in the task that finds them
    nested = queries.places_of_places(spark, sf)
    inner, outer = nested.select("zip_id", "place_id").distinct().count(), nested.select("outer_id").distinct().count()
    assert nested.count() == inner > outer
    top = queries.place_recommend(spark, sf)
    assert top.groupBy("query_id").count().select("count").distinct().collect() == [(3,)] or top.count() == 0


def test_triangulation_by_task_or_tiles_is_the_same(poi, monkeypatch):
    """States below the bound are triangulated whole, larger ones by tiles; a graph has both kinds."""
    sizes = sorted(r["count"] for r in poi.groupBy("state_id").count().collect())
    whole = {(r.state_id, r.src, r.dst) for r in delaunay.delaunay_graph(poi, "local").collect()}
    tiled = []
    own = delaunay.delaunay_tiled
    monkeypatch.setattr(delaunay, "delaunay_tiled", lambda p, tile_m: tiled.append(p.select("state_id").distinct().count()) or own(p, tile_m))
    for bound in (sizes[-1], sizes[1], 0):
        monkeypatch.setattr(delaunay, "TASK_POINTS", bound)
        assert {(r.state_id, r.src, r.dst) for r in delaunay.delaunay_graph(poi, "auto").collect()} == whole
    assert tiled == [sum(n > sizes[1] for n in sizes), len(sizes)]


def test_covisits_of_all_levels_come_from_one_pass(spark, sf, monkeypatch):
    visits = cut(points.customer_visits(spark, sf).filter("visitor < 60"))
    got = {(r.level, r.a, r.b, r.n) for r in encode.covisit_levels(visits, 4).collect()}
    assert got == {(level, r.a, r.b, r.n) for level in (1, 2, 3, 4) for r in encode.covisit_counts(visits, level).collect()}
    paths = cut(visits.select(F.array_join("category_path", ">").alias("path_key"), "category_path").distinct())
    monkeypatch.setattr(encode, "covisit_counts", None)
    seen = []
    monkeypatch.setattr(encode, "cut", lambda df: seen.append(df.columns) or cut(df))
    assert encode.fit_sequence_encoder(visits, paths, levels=3, d=6).count() == paths.count() and seen == [["level", "a", "b", "n"]]


def test_trained_baseline_in_blocks_and_single_precision(spark, monkeypatch):
    r = np.random.default_rng(2)
    rows = [(k % 2, k % 14, k, r.normal(size=4).tolist()) for k in range(300)]
    h = spark.createDataFrame(rows, "state_id int, zip_id long, poi_id long, h array<double>")
    touch = spark.createDataFrame([(s, z, z + 2) for s in (0, 1) for z in range(s, 12, 2)], "state_id int, a long, b long")
    whole, single = (frame(baselines.infomax_baseline(h, touch, 3, 20, kind=kind), "zip_id", "z") for kind in ("float64", "float32"))
    same(whole, single, 1e-3)
    x, region, other = r.normal(size=(90, 4)), np.sort(r.integers(0, 5, 90)), r.integers(0, 5, 90)
    order, mixed = r.permutation(90), r.permutation(90)
    found = []
    for size, at in ((1000, np.arange(90)), (7, np.arange(90)), (7, mixed)):  # in one block, in several, and with regions that do not ascend
        monkeypatch.setattr(baselines, "BLOCK", size)
        m = baselines.Infomax(x[at], region[at], np.eye(5, k=1) + np.eye(5, k=-1), 3, 1)
        moved = np.empty(90, int)
        moved[at] = np.arange(90)
        found.append(m.loss(moved[order][at], other[at]))
    for value, g in found[1:]:
        assert value == pytest.approx(found[0][0]) and all(np.allclose(g[k], found[0][1][k]) for k in g)


def test_encoder_and_cooccurrence_are_found_once(spark, sf, poi, edges, v, monkeypatch):
    """The reference method takes the vectors at hand; counts are materialised before they are read again."""
    monkeypatch.setattr(evaluation, "category_table", None)
    assert all(m.count() == poi.select("zip_id").distinct().count() for m in evaluation.reference_means(spark, sf, poi, D, v))
    seen = []
    monkeypatch.setattr(baselines, "cut", lambda df: seen.append(df.columns) or cut(df))
    assert baselines.cooccurrence_table(edges, poi, 4).count() > 0 and seen == [["a", "b", "n"]]


def counted(df):
    """``df`` and an accumulator of the rows that were computed for it."""
    seen = df.sparkSession.sparkContext.accumulator(0)

    def through(batches):
        for b in batches:
            seen.add(len(b))
            yield b

    return df.mapInPandas(through, df.schema), seen


def test_hops_read_the_graph_once(v, a_hat):
    arcs, seen = counted(a_hat)
    levels = propagate.hops(v, arcs, 3, D)
    assert seen.value == a_hat.count()
    for before, after in zip(levels, levels[1:], strict=False):
        same(frame(after), frame(propagate.hop(before, a_hat, D)))


def test_factored_propagation_reads_the_graph_once(poi, v, a_hat):
    arcs, seen = counted(a_hat)
    paths = poi.select("poi_id", F.array_join("category_path", ">").alias("path_key"))
    table = encode.hash_encoder(encode.distinct_paths(poi), D)
    for alpha in ((0.5, 0.25, 0.75), (0.0, 0.0, 1.0), (0.5,)):
        seen.value = 0
        got = frame(propagate.propagate_factored(paths, table, arcs, alpha, D))
        assert seen.value == (a_hat.count() if len(alpha) > 1 else 0)
        same(got, frame(propagate.propagate(v, a_hat, alpha, D)))


def test_neighbours_are_found_once_for_the_graph(spark, sf, monkeypatch):
    from poiweave.queries import graph as graph_queries

    counters = []

    def edges(*args):
        p, e = graph_queries.knn_edges(*args)
        e, seen = counted(e.select("src", "dst"))
        counters.append((e.count(), seen))
        seen.value = 0
        return p, e

    monkeypatch.setattr(features, "knn_edges", edges)
    p, _, a = features._knn_graph(spark, sf)
    n = counters[0][0]
    assert a.count() == 2 * n + p.count() and counters[0][1].value == n


def test_quantiles_are_exact(spark, monkeypatch):
    monkeypatch.setattr(graph, "SORTED", 20)
    monkeypatch.setattr(graph, "STEPS", 8)
    rng = np.random.default_rng(3)
    for x in (rng.lognormal(5, 3, 501), np.repeat([1.0, 2.0, 7.5], 200), np.array([4.0]), np.array([])):
        df = spark.createDataFrame([(float(a),) for a in x] + [(None,)], "dist_m double")
        got = graph.quantiles(df, "dist_m", (0.0, 0.5, 0.95, 1.0))
        assert got == [None] * 4 if not len(x) else np.allclose(got, np.quantile(x, (0.0, 0.5, 0.95, 1.0)), rtol=1e-12, atol=0)


def test_distributed_splitting_computes_the_features_once(h):
    rows, seen = counted(h)
    n = h.count()
    seen.value = 0
    m = places.bisect_places(rows, ["state_id"], "0.02", engine="distributed")
    assert m.count() == n and seen.value == n


def test_wide_vectors_hop_in_parts(v, a_hat, monkeypatch):
    kept = []
    monkeypatch.setattr(propagate, "WIDE", 3, raising=False)
    monkeypatch.setattr(propagate, "cut_and_release", lambda df: kept.append(cut(df)) or kept[-1], raising=False)
    levels = propagate.hops(v, a_hat, 1, D)
    assert [len(x.first()["h"]) for x in kept if "h" in x.columns] == [3, 3, 2, D]
    same(frame(levels[1]), frame(propagate.hop(v, a_hat, D)), 1e-12)
