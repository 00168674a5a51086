"""Queries: baselines, regressors, protocol, measures and the experiment workloads."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import vectors
from ..operators import baselines, delaunay, encode, evaluate, graph, places, propagate, regions
from ..operators.session import cut, cut_and_release
from ..plans.plan import Config, PlacePlan, adjacency, category_table
from ..sources import points
from .features import D, UNIT, _knn_graph, coded_points, hashed, hops_sql, mix_sql
from .graph import HASHED, KNN, knn_edges
from .oracle import LABEL, POI
from .places import ALPHA, ZIP, _z, features

#: Fixed values of the protocol for the compared methods: dimension of all vectors, epochs of the trained baseline.
WIDTH, EPOCHS = 30, 100
METHODS = ("mean", "cooc", "infomax", "pretrained", "reference")


def _labels(spark: SparkSession, sf: str) -> DataFrame:
    return points.labels(points.points(spark, sf), points.zip_cells(spark, sf))


def planted_labels(spark: SparkSession, sf: str) -> DataFrame:
    return _labels(spark, sf).select("state_id", "county_id", "zip_id", F.round("density", 6).alias("density"), F.round("price", 6).alias("price"))


def baseline_mean(spark: SparkSession, sf: str) -> DataFrame:
    p = points.points(spark, sf)
    return _z(baselines.mean_baseline(p, encode.hash_encoder(encode.distinct_paths(p), D), ZIP, D), "zip_id", "n_poi")


def cooc_counts(spark: SparkSession, sf: str) -> DataFrame:
    p, e = knn_edges(spark, sf)
    return baselines.cooccurrence_counts(e, p).select("a", "b", F.round("n", 5).alias("n"))


def cooc_ppmi(spark: SparkSession, sf: str) -> DataFrame:
    p, e = knn_edges(spark, sf)
    return encode.ppmi(baselines.cooccurrence_counts(e, p)).select("a", "b", F.round("ppmi", 6).alias("ppmi"))


def baseline_cooc(spark: SparkSession, sf: str) -> DataFrame:
    p, e = knn_edges(spark, sf)
    return baselines.cooccurrence_baseline(p, e, ZIP, 30)


def baseline_cooc_skipgram(spark: SparkSession, sf: str) -> DataFrame:
    p, e = knn_edges(spark, sf)
    return baselines.cooccurrence_baseline(p, e, ZIP, 30, method="w2v")


def attention_pool(spark: SparkSession, sf: str) -> DataFrame:
    """Softmax pooling with the first component as score."""
    p = points.points(spark, sf)
    rows = hashed(p).join(p.select("poi_id", "zip_id"), "poi_id").withColumn("score", F.col("h")[0] * 3)
    return _z(baselines.attention_pool(rows, ZIP, D), "zip_id")


def _infomax(spark: SparkSession, sf: str, epochs: int, d: int) -> DataFrame:
    p, table = coded_points(spark, sf)
    h = propagate.propagate_coded(p.select("poi_id", "code"), graph.knn_brute(p), table, (0.0, 1.0), D).join(p.select("poi_id", "state_id", "zip_id"), "poi_id")
    cells = points.zip_cells(spark, sf)
    touch = regions.region_adjacency(points.polygons(cells), within=("state_id",)).join(cells.select(F.col("zip_id").alias("a"), "state_id"), "a")
    return baselines.infomax_baseline(h, touch, d, epochs)


def baseline_infomax(spark: SparkSession, sf: str) -> DataFrame:
    return _infomax(spark, sf, 100, D).select("zip_id", "n_poi", "z")


def baseline_pretrained(spark: SparkSession, sf: str) -> DataFrame:
    return baselines.pretrained_baseline(points.zip_cells(spark, sf), points.table(spark, sf, "embeddings"), D)


def split_assign(spark: SparkSession, sf: str) -> DataFrame:
    return evaluate.split_runs(_labels(spark, sf))


def predict_mean(spark: SparkSession, sf: str) -> DataFrame:
    y = _labels(spark, sf)
    out = evaluate.constant_predictor(y, evaluate.split_runs(y), "density")
    return out.select("state_id", "run", "zip_id", F.round("y", 6).alias("y"), F.round("yhat", 6).alias("yhat"))


def score_mean_predictor(spark: SparkSession, sf: str) -> DataFrame:
    y = _labels(spark, sf)
    s = evaluate.score(evaluate.constant_predictor(y, evaluate.split_runs(y), "density"), ["state_id", "run"])
    return s.select("state_id", "run", "n", *(F.round(c, 5).alias(c) for c in ("rmse", "mae", "r2")))


def _line(spark: SparkSession, sf: str) -> DataFrame:
    """A fixed linear predictor of the price, for measures with SQL."""
    y = _labels(spark, sf)
    rows = evaluate.split_runs(y).filter("not is_train").join(y.select("zip_id", "county_id", F.col("price").alias("y")), "zip_id")
    return rows.withColumn("yhat", 130.0 + 30 * (F.col("county_id") % 7)).select("state_id", "run", "zip_id", "y", "yhat")


def score_linear(spark: SparkSession, sf: str) -> DataFrame:
    s = evaluate.score(_line(spark, sf), ["state_id", "run"])
    return s.select("state_id", "run", "n", *(F.round(c, 5).alias(c) for c in ("rmse", "mae", "r2")))


def score_runs(spark: SparkSession, sf: str) -> DataFrame:
    s = evaluate.summarise_runs(evaluate.score(_line(spark, sf), ["state_id", "run"]), ["state_id"])
    return s.select("state_id", "runs", *(F.round(f"{c}_{n}", 5).alias(f"{c}_{n}") for c in ("rmse", "mae", "r2") for n in ("mean", "sd")))


def error_map(spark: SparkSession, sf: str) -> DataFrame:
    return evaluate.error_by_region(_line(spark, sf)).withColumn("error", F.round("error", 6))


def error_breakdown(spark: SparkSession, sf: str) -> DataFrame:
    b = evaluate.error_breakdown(evaluate.error_by_region(_line(spark, sf)), points.points(spark, sf), points.polygons(points.zip_cells(spark, sf)))
    return b.select("state_id", "factor", "class", "regions", *(F.round(c, 5).alias(c) for c in ("error", "n_poi", "area_km2")))


def rank_methods(spark: SparkSession, sf: str) -> DataFrame:
    """Places of the two fixed predictors by mean error in each state."""
    y = _labels(spark, sf)
    a = evaluate.score(_line(spark, sf), ["state_id"]).withColumn("method", F.lit("line"))
    b = evaluate.score(evaluate.constant_predictor(y, evaluate.split_runs(y), "price"), ["state_id"]).withColumn("method", F.lit("mean"))
    r = evaluate.rank_methods(a.unionByName(b), ["state_id"])
    return r.select("state_id", "method", "place", F.round("rmse", 5).alias("rmse"))


def alpha_grid(spark: SparkSession, sf: str) -> DataFrame:
    """All settings for every state, with the hops and the spread vectors they cost there."""
    return evaluate.setting_cost(evaluate.alpha_grid(spark), points.points(spark, sf))


def published_settings(spark: SparkSession, sf: str) -> DataFrame:
    """The published settings at every given state: the places that their ratios give."""
    return evaluate.places_of_settings(evaluate.published_settings(spark), points.points(spark, sf))


def _hop_means(spark: SparkSession, sf: str) -> list[DataFrame]:
    p, v, a = _knn_graph(spark, sf)
    z = p.select("poi_id", "zip_id")
    return [cut(regions.region_mean(h.join(z, "poi_id"), ZIP, D)) for h in propagate.hops(v, a, 2, D)]


def alpha_region_combo(spark: SparkSession, sf: str) -> DataFrame:
    """Region vectors of all 125 settings from three sets of means."""
    g = evaluate.region_grid(_hop_means(spark, sf), evaluate.alpha_grid(spark), D)
    return g.select("zip_id", "a0", "a1", "a2", (F.round(F.col("z")[0] + F.col("z")[D - 1] * 2, 6) + 0.0).alias("probe"))


def tune_settings(spark: SparkSession, sf: str) -> DataFrame:
    """The three best settings of each state and target. Region vectors, and so the errors, are the same for every ratio r (``tune_ratio`` measures it)."""
    means, y, out = _hop_means(spark, sf), cut(_labels(spark, sf)), None
    for target in ("density", "price"):
        part = evaluate.tune(means, y, target, evaluate.alpha_grid(spark), D).filter("place <= 3").withColumn("target", F.lit(target))
        out = part if out is None else out.unionByName(part)
    return out


def tune_ratio(spark: SparkSession, sf: str) -> DataFrame:
    """state_id, target, r, rmse of ridge on the region vectors that places at each ratio give: errors agree to rounding, so any ratio is best."""
    h = cut(features(spark, sf)[1])
    y = cut(_labels(spark, sf))
    splits, tree = cut(evaluate.split_runs(y)), cut(places.place_hierarchy(h, ZIP, "0.1"))
    out = None
    for r in places.RATIOS:
        m = cut(places.cut_hierarchy(tree, ZIP, r).withColumn("place_id", places.place_id(ZIP)))
        z = cut(regions.region_embedding(places.summarise_places(m, h, D).join(m.select("place_id", "zip_id").distinct(), "place_id"), ZIP, D))
        for target in ("density", "price"):
            s = evaluate.score(evaluate.fit_predict(z, y, splits, target, "ridge"), ["state_id", "run"]).groupBy("state_id").agg(F.avg("rmse").alias("rmse"))
            part = s.select("state_id", F.lit(target).alias("target"), F.lit(r).alias("r"), F.round("rmse", 5).alias("rmse"))
            out = part if out is None else out.unionByName(part)
    return out


def speedup(spark: SparkSession, sf: str) -> DataFrame:
    """How many times longer the trained baselines take than the reference method: in the published states, and in the given ones by the growth of the published seconds over points."""
    rows = [("WY", 40165, "reference", 0.1, 2.41), ("WY", 40165, "reference", 0.05, 1.32), ("WY", 40165, "cooc", None, 34.52), ("WY", 40165, "infomax", None, 60.61), ("AL", 255000, "reference", 0.1, 14.61), ("AL", 255000, "reference", 0.05, 7.81), ("AL", 255000, "cooc", None, 72.12), ("AL", 255000, "infomax", None, 271.24), ("FL", 1350000, "reference", 0.1, 94.65), ("FL", 1350000, "reference", 0.05, 48.29), ("FL", 1350000, "cooc", None, 621.17), ("FL", 1350000, "infomax", None, 1293.84)]
    log = spark.createDataFrame(rows, "state string, points long, method string, r double, seconds double")
    sizes = points.points(spark, sf).groupBy(F.col("state_id").cast("string").alias("state")).agg(F.count(F.lit(1)).alias("points"))
    return evaluate.speedup_table(log.unionByName(cut(evaluate.seconds_at(log, sizes)))).withColumn("speedup", F.round("speedup", 4))


def growth_slopes(spark: SparkSession, sf: str) -> DataFrame:
    """Regression slope of log edges on log points over states; that of measured seconds is in ``w_efficiency``."""
    p, e = knn_edges(spark, sf)
    n = p.groupBy("state_id").agg(F.count(F.lit(1)).alias("points")).join(e.groupBy("state_id").agg(F.count(F.lit(1)).cast("double").alias("seconds")), "state_id")
    return evaluate.growth_slopes(n.withColumns({"method": F.lit("edges"), "r": F.lit(0.0)})).withColumn("slope", F.round("slope", 5))


def align_dimension(spark: SparkSession, sf: str) -> DataFrame:
    """Dimension of all methods' region vectors."""
    out = None
    for name, f in method_features(spark, sf, "density").items():
        part = f.groupBy(F.size("z").alias("d")).agg(F.count(F.lit(1)).alias("regions")).withColumn("method", F.lit(name))
        out = part if out is None else out.unionByName(part)
    return out


def reference_means(spark: SparkSession, sf: str, p: DataFrame, d: int = WIDTH, v: DataFrame | None = None) -> list[DataFrame]:
    """Region means of the reference method's hops: the encoder fitted to visits (``v``: the points' vectors, if at hand), spread over the weighted triangulation of every state."""
    config = Config(d=d, graph="delaunay", encoder="visits")
    v = cut_and_release(encode.encode_poi(p, cut_and_release(category_table(p, config, points.customer_visits(spark, sf))), d)) if v is None else v
    z = p.select("poi_id", "zip_id")
    return [cut(regions.region_mean(h.join(z, "poi_id"), ZIP, d)) for h in propagate.hops(v, adjacency(p, config), 2, d)]


def reference_features(spark: SparkSession, sf: str, p: DataFrame, y: DataFrame, target: str, d: int = WIDTH, v: DataFrame | None = None) -> DataFrame:
    """zip_id, z of the reference method with the coefficients that the training regions of each state choose for a target."""
    means = reference_means(spark, sf, p, d, v)
    best = cut(evaluate.tune(means, y, target, evaluate.alpha_grid(spark), d).filter("place = 1").select("state_id", "a0", "a1", "a2"))
    return evaluate.tuned_features(means, best, y, d)


def method_features(spark: SparkSession, sf: str, target: str, epochs: int = EPOCHS, d: int = WIDTH) -> dict[str, DataFrame]:
    """Region vectors (zip_id, z) of all methods at one dimension. The mean baseline and the trained one start from the same fitted encoder as the reference method."""
    p = cut_and_release(points.points(spark, sf))
    e = cut_and_release(graph.knn_graph(p))
    y = cut(points.labels(p, points.zip_cells(spark, sf)))
    table = cut_and_release(category_table(p, Config(d=d, encoder="visits"), points.customer_visits(spark, sf)))
    v = cut_and_release(encode.encode_poi(p, table, d))
    a = cut_and_release(graph.normalise_adjacency(graph.unit_weights(e), p))
    z = p.select("poi_id", "state_id", "zip_id")
    cells = cut(points.polygons(points.zip_cells(spark, sf)))
    touch = regions.region_adjacency(cells, within=("state_id",)).join(cells.select(F.col("zip_id").alias("a"), "state_id"), "a")
    out = {
        "mean": baselines.mean_baseline(p, table, ZIP, d),
        "cooc": baselines.cooccurrence_baseline(p, e, ZIP, d),
        "infomax": baselines.infomax_baseline(propagate.hops(v, a, 1, d)[1].join(z, "poi_id"), touch, d, epochs, kind="float32"),
        "pretrained": baselines.pretrained_baseline(cells, points.table(spark, sf, "embeddings"), d),
        "reference": reference_features(spark, sf, p, y, target, d, v),
    }
    return {k: cut_and_release(f.select("zip_id", "z")) for k, f in out.items()}


def predictions(spark: SparkSession, sf: str, target: str, models: tuple[str, ...], runs: int = evaluate.RUNS) -> DataFrame:
    """model, state_id, method, run, zip_id, y, yhat of all methods' features under the regressors."""
    y = cut(_labels(spark, sf))
    splits, out = cut(evaluate.split_runs(y, runs)), None
    for name, f in method_features(spark, sf, target).items():
        for model in models:
            part = evaluate.fit_predict(f, y, splits, target, model, name).withColumn("model", F.lit(model))
            out = part if out is None else out.unionByName(part)
    return out


def compare_methods(spark: SparkSession, sf: str, target: str, model: str, runs: int = evaluate.RUNS) -> DataFrame:
    """state_id, method, means and deviations of the measures over the runs."""
    scores = evaluate.score(cut(predictions(spark, sf, target, (model,), runs)), ["state_id", "method", "run"])
    return evaluate.rank_methods(evaluate.summarise_runs(scores, ["state_id", "method"]).withColumn("rmse", F.col("rmse_mean")), ["state_id"]).drop("rmse")


def w_density(spark: SparkSession, sf: str) -> DataFrame:
    """Population-density workload: five states, five methods, ten runs, forests of 100 trees (a task for each state and run)."""
    return compare_methods(spark, sf, "density", "forest")


def w_price(spark: SparkSession, sf: str) -> DataFrame:
    return compare_methods(spark, sf, "price", "forest")


def w_transfer(spark: SparkSession, sf: str) -> DataFrame:
    """Transfer workload: errors of all methods' features under forest, perceptron and boosted trees."""
    scores = evaluate.score(cut(predictions(spark, sf, "density", ("forest", "mlp", "xgb"))), ["state_id", "method", "model", "run"])
    return evaluate.summarise_runs(scores, ["state_id", "method", "model"])


def _reference_errors(spark: SparkSession, sf: str, target: str = "density") -> DataFrame:
    p = cut(points.points(spark, sf))
    y = cut(points.labels(p, points.zip_cells(spark, sf)))
    pred = evaluate.fit_predict(reference_features(spark, sf, p, y, target), y, evaluate.split_runs(y), target, "forest")
    return cut(evaluate.error_by_region(cut(pred)))


def w_error_map(spark: SparkSession, sf: str) -> DataFrame:
    """Error of every region under the reference method (mean over the runs that test it), with its class in the state and its outline."""
    shape = points.polygons(points.zip_cells(spark, sf)).select("zip_id", "area_km2", "polygon")
    return _reference_errors(spark, sf).join(shape, "zip_id")


def w_error_breakdown(spark: SparkSession, sf: str) -> DataFrame:
    """The reference method's errors by classes of point density and of area."""
    return evaluate.error_breakdown(_reference_errors(spark, sf), points.points(spark, sf), points.polygons(points.zip_cells(spark, sf)))


def w_efficiency(spark: SparkSession, sf: str) -> DataFrame:
    """method, r, states, points, seconds, slope, speedup: embedding generation over graphs of one, three and five states, the graph at hand.

    ``slope`` is the growth exponent of a method's seconds over points, ``speedup`` how many times longer it takes than the reference method at r = 0.1 on the same points.
    """
    p = cut(points.points(spark, sf))
    e = cut(graph.knn_graph(p))
    a = cut(graph.normalise_adjacency(graph.unit_weights(e), p))
    table = cut(category_table(p, Config(encoder="visits"), points.customer_visits(spark, sf)))
    cells = cut(points.polygons(points.zip_cells(spark, sf)))
    touch = cut(regions.region_adjacency(cells, within=("state_id",)).join(cells.select(F.col("zip_id").alias("a"), "state_id"), "a"))
    log = []
    for n in (1, 3, 5):
        own = cut(p.filter(F.col("state_id") < n))
        ids = own.select("poi_id", "state_id", "zip_id")
        arcs = cut(a.join(ids.select(F.col("poi_id").alias("dst")), "dst", "left_semi"))
        edges = cut(e.filter(F.col("state_id") < n))

        def reference(r: str, own=own, ids=ids, arcs=arcs) -> DataFrame:
            h = propagate.propagate(encode.encode_poi(own, table, WIDTH), arcs, ALPHA, WIDTH).join(ids, "poi_id")
            return regions.region_embedding(places.condensed_places(h, ZIP, r, sizes=own.groupBy("zip_id").agg(F.count(F.lit(1)).alias("n"))), ZIP, WIDTH)

        def infomax(own=own, ids=ids, arcs=arcs, n=n) -> DataFrame:
            return baselines.infomax_baseline(propagate.hop(encode.encode_poi(own, table, WIDTH), arcs, WIDTH).join(ids, "poi_id"), touch.filter(F.col("state_id") < n), WIDTH, EPOCHS, kind="float32")

        size = own.count()
        for method, r, build in (("reference", 0.1, lambda f=reference: f("0.1")), ("reference", 0.05, lambda f=reference: f("0.05")), ("cooc", None, lambda own=own, edges=edges: baselines.cooccurrence_baseline(own, edges, ZIP, WIDTH, method="w2v")), ("infomax", None, infomax)):
            log.append((method, r, n, size, evaluate.timed(method, build)[1]))
    rows = spark.createDataFrame(log, "method string, r double, states int, points long, seconds double")
    slopes = evaluate.growth_slopes(rows)
    base = rows.filter("method = 'reference' and r = 0.1").select("states", F.col("seconds").alias("own"))
    return rows.join(slopes, (rows["method"] == slopes["method"]) & rows["r"].eqNullSafe(slopes["r"])).drop(slopes["method"]).drop(slopes["r"]).join(base, "states").withColumn("speedup", F.col("seconds") / F.col("own")).drop("own")


def counters(spark: SparkSession, sf: str) -> DataFrame:
    """Rows that pass each stage of graph building and one hop, counted on the way."""
    p, points_seen = evaluate.observed(points.points(spark, sf), "points")
    p = cut(p)
    directed, arcs_seen = evaluate.observed(graph.knn_tiled(p, 5), "directed")
    edges, edges_seen = evaluate.observed(graph.symmetrise(cut(directed)), "edges")
    a, entries_seen = evaluate.observed(graph.normalise_adjacency(graph.unit_weights(cut(edges)), p), "entries")
    hop, hop_seen = evaluate.observed(propagate.hop(hashed(p), cut(a), D), "hop")
    cut(hop)
    rows = [(name, seen.get["rows"]) for name, seen in (("points", points_seen), ("directed edges", arcs_seen), ("edges", edges_seen), ("adjacency entries", entries_seen), ("spread vectors", hop_seen))]
    return spark.createDataFrame(rows, "stage string, rows long")


def predict_rf(spark: SparkSession, sf: str) -> DataFrame:
    y = cut(_labels(spark, sf))
    return evaluate.fit_predict(cut(regions.region_mean(features(spark, sf)[1], ZIP, D)), y, cut(evaluate.split_runs(y)), "density", "rf")


def predict_gbt(spark: SparkSession, sf: str) -> DataFrame:
    y = cut(_labels(spark, sf))
    return evaluate.fit_predict(cut(regions.region_mean(features(spark, sf)[1], ZIP, D)), y, cut(evaluate.split_runs(y)), "density", "gbt")


def _predict(spark: SparkSession, sf: str, model: str) -> DataFrame:
    y = _labels(spark, sf)
    return evaluate.fit_predict(regions.region_mean(features(spark, sf)[1], ZIP, D), y, evaluate.split_runs(y), "density", model)


def predict_ridge(spark: SparkSession, sf: str) -> DataFrame:
    return _predict(spark, sf, "ridge")


def predict_mlp(spark: SparkSession, sf: str) -> DataFrame:
    return _predict(spark, sf, "mlp")


def predict_xgb(spark: SparkSession, sf: str) -> DataFrame:
    return _predict(spark, sf, "xgb")


def expressiveness_gap(spark: SparkSession, sf: str) -> DataFrame:
    p, h = features(spark, sf)
    h = cut(h)
    m = places.bisect_places(h, ["state_id", "zip_id"], "0.1")
    z = places.summarise_places(m, h, D).join(m.select("place_id", "zip_id").distinct(), "place_id")
    return evaluate.expressiveness_gap(h.select("zip_id", "h"), z, _labels(spark, sf), "density")


def w_places(spark: SparkSession, sf: str) -> DataFrame:
    """Place identification: purity and inside-edge share of category-only and propagated places at two ratios."""
    p, e = knn_edges(spark, sf)
    p, e = cut(p), cut(e)
    v = cut(hashed(p))
    a = cut(graph.normalise_adjacency(graph.unit_weights(e), p))
    out = None
    for name, alpha, r in (("semantic", (1.0,), "0.1"), ("propagated", (0.25, 0.5, 0.5), "0.1"), ("propagated", (0.25, 0.5, 0.5), "0.05")):
        h = propagate.propagate(v, a, alpha, D).join(p.select("poi_id", "zip_id"), "poi_id")
        m = cut(places.bisect_places(h, ZIP, r))
        inside = places.place_contiguity(e, m).agg(F.sum("n_inside").alias("i"), F.sum("n_touching").alias("t"))
        pure = places.place_profile(m, p, 1).select("place_id", "purity").distinct().agg(F.avg("purity").alias("purity"), F.count(F.lit(1)).alias("n_places"))
        part = inside.crossJoin(pure).select(F.lit(name).alias("features"), F.lit(r).alias("r"), "n_places", "purity", (F.col("i") / F.col("t")).alias("inside_share"))
        out = part if out is None else out.unionByName(part)
    return out


def _place_settings(spark: SparkSession, sf: str) -> tuple[DataFrame, DataFrame, DataFrame]:
    """Points and edges of the region with most points, and its places under three settings: categories alone, spread with few large places, spread with many small ones."""
    p, e = knn_edges(spark, sf)
    p = cut(p)
    e = cut(graph.knn_graph(p))
    most = p.groupBy("zip_id").agg(F.count(F.lit(1)).alias("n")).orderBy(F.desc("n"), "zip_id").first()["zip_id"]
    own = cut(p.filter(F.col("zip_id") == most))
    v = cut(hashed(p))
    a = cut(graph.normalise_adjacency(graph.unit_weights(e), p))
    out = None
    for name, alpha, r in (("category only", (1.0,), "0.1"), ("spread, larger r", (0.25, 0.5, 0.5), "0.1"), ("spread, smaller r", (0.25, 0.5, 0.5), "0.05")):
        h = propagate.propagate(v, a, alpha, D).join(own.select("poi_id", "zip_id"), "poi_id")
        m = places.bisect_places(h, ZIP, r)
        n = m.groupBy("place_id").agg(F.count(F.lit(1)).alias("n_poi"))
        top = n.withColumn("rank", F.row_number().over(Window.orderBy(F.desc("n_poi"), "place_id"))).filter("rank <= 10")
        part = m.join(top, "place_id").select(F.lit(name).alias("setting"), "rank", "place_id", "n_poi", "poi_id")
        out = part if out is None else out.unionByName(part)
    return own, e, cut(out)


def w_place_map(spark: SparkSession, sf: str) -> DataFrame:
    """Place identification in one region: the ten largest places of each setting with the area of their points' Voronoi cells, commonest category, purity, parts and share of edges inside."""
    own, e, top = _place_settings(spark, sf)
    cells = cut(delaunay.voronoi_cells(own, points.polygons(points.zip_cells(spark, sf))).select("poi_id", "area"))
    area = top.join(cells, "poi_id", "left").groupBy("setting", "rank", "place_id", "n_poi").agg(F.sum("area").alias("area"))
    keyed = cut(top.select("poi_id", F.concat_ws("#", "setting", "place_id").alias("place_id")))
    best = places.place_profile(keyed, own, 1).groupBy("place_id").agg(F.max_by("label", F.struct("n", "label")).alias("category"), F.max("purity").alias("purity"))
    inside, parts = [], None
    for (name,) in top.select("setting").distinct().collect():  # three settings: a point has one place in each
        m = keyed.filter(F.col("place_id").startswith(name + "#"))
        inside.append(places.place_contiguity(e, m).select("place_id", "inside_share").join(places.place_fragments(e, m), "place_id", "full"))
    for part in inside:
        parts = part if parts is None else parts.unionByName(part)
    key = F.concat_ws("#", "setting", "place_id")
    out = area.withColumn("key", key).join(best.withColumnRenamed("place_id", "key"), "key", "left").join(parts.withColumnRenamed("place_id", "key"), "key", "left").drop("key")
    return out


def w_place_zoom(spark: SparkSession, sf: str) -> DataFrame:
    """The points in the densest ninth of that region, with their place's rank in each setting: one map, coloured three ways."""
    own, _, top = _place_settings(spark, sf)
    dense = delaunay.zoom(own, points.polygons(points.zip_cells(spark, sf)))
    return dense.select("poi_id", "lat", "lon").join(top.select("poi_id", "setting", "rank", "place_id"), "poi_id")


def w_homogenisation(spark: SparkSession, sf: str) -> DataFrame:
    """Likeness of neighbours as the second hop's coefficient grows."""
    p, v, a = _knn_graph(spark, sf)
    _, e = knn_edges(spark, sf)
    levels = propagate.hops(v, a, 2, D)
    e = cut(e)
    out = None
    for a2 in (0.0, 0.25, 0.5, 0.75, 1.0):
        part = graph.smoothing_score(e, propagate.combine(levels, (0.5, 0.25, a2), D)).withColumn("a2", F.lit(a2))
        out = part if out is None else out.unionByName(part)
    return out.select("a2", "edges", F.round("score", 6).alias("score"))


def w_embedding_clusters(spark: SparkSession, sf: str) -> DataFrame:
    """Bisecting on ready vectors, with each label as a region."""
    e = points.table(spark, sf, "embeddings").select(F.col("vec_id").alias("poi_id"), "label", F.col("embedding").cast("array<double>").alias("h"))
    return places.bisect_places(e, ["label"], "0.05").groupBy("label").agg(F.count_distinct("place_id").alias("n_places"), F.count(F.lit(1)).alias("n"))


def plan_regions(spark: SparkSession, sf: str) -> DataFrame:
    """The rewritten plan for region vectors: no clustering, one hop."""
    out = PlacePlan.of(Config(d=D, alpha=(0.5, 0.5, 0.0))).run(points.points(spark, sf))["regions"]
    return _z(out, "zip_id", "n_poi")


QUERIES = {
    f.__name__: f
    for f in (
        planted_labels, baseline_mean, cooc_counts, cooc_ppmi, baseline_cooc, baseline_cooc_skipgram, attention_pool, baseline_infomax, baseline_pretrained, split_assign, predict_mean, score_mean_predictor,
        score_linear, score_runs, error_map, error_breakdown, rank_methods, alpha_grid, published_settings, alpha_region_combo, tune_settings, tune_ratio, speedup, growth_slopes, align_dimension, w_density, w_price,
        w_transfer, w_error_map, w_error_breakdown, w_efficiency, counters, w_place_map, w_place_zoom, predict_rf, predict_gbt, predict_ridge, predict_mlp, predict_xgb, expressiveness_gap, w_places, w_homogenisation, w_embedding_clusters, plan_regions,
    )
}

_SPLIT = f"""{POI}, {LABEL},
split AS (SELECT state_id, run, zip_id, place <= floor(n * 0.8::DOUBLE + 1e-9) AS is_train FROM (
  SELECT state_id, run, zip_id, row_number() OVER (PARTITION BY state_id, run ORDER BY md5(run || ':' || zip_id), zip_id) AS place, count(*) OVER (PARTITION BY state_id, run) AS n
  FROM label, (SELECT CAST(unnest(range(0, 10)) AS INTEGER) AS run)))"""
_SCORE = "count(*) AS n, {r}sqrt(avg((y - yhat) * (y - yhat))){e} AS rmse, {r}avg(abs(y - yhat)){e} AS mae, {r}CASE WHEN var_pop(y) > 1e-12 THEN 1 - sum((y - yhat) * (y - yhat)) / (var_pop(y) * count(*)) END{e} AS r2"
_ROUNDED = _SCORE.format(r="round(", e=", 5)")
_PLAIN = _SCORE.format(r="", e="")
_CONST = "pred AS (SELECT state_id, run, zip_id, y, yhat FROM (SELECT s.state_id, s.run, s.zip_id, is_train, l.{t} AS y, avg(CASE WHEN is_train THEN l.{t} END) OVER (PARTITION BY s.state_id, s.run) AS yhat FROM split s JOIN label l ON l.zip_id = s.zip_id) WHERE NOT is_train)"
_LINE = "line AS (SELECT s.state_id, s.run, s.zip_id, l.price AS y, 130.0::DOUBLE + 30 * (l.county_id % 7) AS yhat FROM split s JOIN label l ON l.zip_id = s.zip_id WHERE NOT is_train)"
_ERR = "err AS (SELECT state_id, zip_id, avg(abs(y - yhat)) AS error FROM line GROUP BY state_id, zip_id)"
_COOC = f"""{KNN}, cat AS (SELECT poi_id, array_to_string(list_slice(category_path, 1, 2), '>') AS c FROM poi),
co AS (SELECT a, b, sum(w) AS n FROM (SELECT x.c AS a, y.c AS b, 1 / (1 + dist_m / 1000) AS w FROM edge JOIN cat x ON x.poi_id = src JOIN cat y ON y.poi_id = dst
  UNION ALL SELECT y.c, x.c, 1 / (1 + dist_m / 1000) FROM edge JOIN cat x ON x.poi_id = src JOIN cat y ON y.poi_id = dst) GROUP BY a, b)"""
_GRID = "grid AS (SELECT a.x AS a0, b.x AS a1, c.x AS a2 FROM (SELECT unnest([0.0::DOUBLE, 0.25::DOUBLE, 0.5::DOUBLE, 0.75::DOUBLE, 1.0::DOUBLE]) AS x) a, (SELECT unnest([0.0::DOUBLE, 0.25::DOUBLE, 0.5::DOUBLE, 0.75::DOUBLE, 1.0::DOUBLE]) AS x) b, (SELECT unnest([0.0::DOUBLE, 0.25::DOUBLE, 0.5::DOUBLE, 0.75::DOUBLE, 1.0::DOUBLE]) AS x) c)"
_VEC = "list(round(x, 6) + 0.0::DOUBLE ORDER BY i)"
_SET = ", ".join(f"('{s}', '{task}', '{r}', {', '.join(f'{x}::DOUBLE' for x in a)})" for s, r, density, price in evaluate.PUBLISHED for task, a in (("density", density), ("price", price)))
_SPEED = {"WY": (2.41, 1.32, 34.52, 60.61), "AL": (14.61, 7.81, 72.12, 271.24), "FL": (94.65, 48.29, 621.17, 1293.84)}
_SPEED_POINTS = {"WY": 40165, "AL": 255000, "FL": 1350000}
_SPEED_ROWS = ", ".join(f"('{s}', {_SPEED_POINTS[s]}, '{m}', {r}, {x}::DOUBLE)" for s, (a, b, c, i) in _SPEED.items() for m, r, x in (("reference", "0.1::DOUBLE", a), ("reference", "0.05::DOUBLE", b), ("cooc", "NULL", c), ("infomax", "NULL", i)))
_MEANS = ", ".join(f"m{k} AS (SELECT zip_id, i, avg(x) AS x FROM h{k} JOIN poi ON poi.poi_id = h{k}.poi_id GROUP BY zip_id, i)" for k in range(3))
_PROBE = " + ".join(f"a{k} * (z{k}_0 + 2 * z{k}_7)" for k in range(3))
_WIDE = ", ".join(f"w{k} AS (SELECT zip_id, sum(CASE WHEN i = 0 THEN x END) AS z{k}_0, sum(CASE WHEN i = 7 THEN x END) AS z{k}_7 FROM m{k} GROUP BY zip_id)" for k in range(3))

SQL = {
    "counters": f"""WITH {KNN} SELECT 'points' AS stage, count(*) AS rows FROM poi UNION ALL SELECT 'directed edges', count(*) FROM knn UNION ALL SELECT 'edges', count(*) FROM edge
UNION ALL SELECT 'adjacency entries', (SELECT 2 * count(*) FROM edge) + (SELECT count(*) FROM poi) UNION ALL SELECT 'spread vectors', count(*) FROM poi""",
    "planted_labels": f"WITH {POI}, {LABEL} SELECT state_id, county_id, zip_id, round(density, 6) AS density, round(price, 6) AS price FROM label",
    "baseline_mean": f"WITH {POI}, {HASHED}, m AS (SELECT zip_id, i, avg(v[i + 1]) AS x, count(*) AS n FROM poi_v, unnest(range(0, 8)) g(i) GROUP BY zip_id, i) SELECT zip_id, any_value(n) AS n_poi, {_VEC} AS z FROM m GROUP BY zip_id",
    "cooc_counts": f"WITH {_COOC} SELECT a, b, round(n, 5) AS n FROM co",
    "cooc_ppmi": f"WITH {_COOC}, m AS (SELECT a, sum(n) AS na FROM co GROUP BY a) SELECT co.a, co.b, round(greatest(0.0::DOUBLE, ln(n * (SELECT sum(n) FROM co) / (x.na * y.na))), 6) AS ppmi FROM co JOIN m x ON x.a = co.a JOIN m y ON y.a = co.b",
    "attention_pool": f"WITH {POI}, {HASHED}, m AS (SELECT zip_id, i, sum(exp(3 * v[1]) * v[i + 1]) / sum(exp(3 * v[1])) AS x FROM poi_v, unnest(range(0, 8)) g(i) GROUP BY zip_id, i) SELECT zip_id, {_VEC} AS z FROM m GROUP BY zip_id",
    "split_assign": f"WITH {_SPLIT} SELECT state_id, run, zip_id, is_train FROM split",
    "predict_mean": f"WITH {_SPLIT}, {_CONST.format(t='density')} SELECT state_id, run, zip_id, round(y, 6) AS y, round(yhat, 6) AS yhat FROM pred",
    "score_mean_predictor": f"WITH {_SPLIT}, {_CONST.format(t='density')} SELECT state_id, run, {_ROUNDED} FROM pred GROUP BY state_id, run",
    "score_linear": f"WITH {_SPLIT}, {_LINE} SELECT state_id, run, {_ROUNDED} FROM line GROUP BY state_id, run",
    "score_runs": f"WITH {_SPLIT}, {_LINE}, s AS (SELECT state_id, run, {_PLAIN} FROM line GROUP BY state_id, run) SELECT state_id, count(*) AS runs, " + ", ".join(f"round({f}({c}), 5) AS {c}_{n}" for c in ("rmse", "mae", "r2") for n, f in (("mean", "avg"), ("sd", "stddev_samp"))) + " FROM s GROUP BY state_id",
    "error_map": f"WITH {_SPLIT}, {_LINE}, {_ERR} SELECT state_id, zip_id, round(error, 6) AS error, CAST(ntile(4) OVER (PARTITION BY state_id ORDER BY error, zip_id) AS INTEGER) AS class FROM err",
    "error_breakdown": f"""WITH {_SPLIT}, {_LINE}, {_ERR}, n AS (SELECT zip_id, count(*) AS n_poi FROM poi GROUP BY zip_id),
a AS (SELECT zip_id, 11.132::DOUBLE * 11.132::DOUBLE * cos(radians(lat0 + 0.05::DOUBLE)) AS area_km2 FROM cell),
c AS (SELECT err.state_id, error, n_poi, area_km2, ntile(3) OVER (PARTITION BY err.state_id ORDER BY round(n_poi / area_km2, 9), err.zip_id) AS density, ntile(3) OVER (PARTITION BY err.state_id ORDER BY round(area_km2, 9), err.zip_id) AS area
  FROM err JOIN n ON n.zip_id = err.zip_id JOIN a ON a.zip_id = err.zip_id),
l AS (SELECT state_id, error, n_poi, area_km2, 'density' AS factor, density AS class FROM c UNION ALL SELECT state_id, error, n_poi, area_km2, 'area', area FROM c)
SELECT state_id, factor, CAST(class AS INTEGER) AS class, count(*) AS regions, round(avg(error), 5) AS error, round(avg(n_poi), 5) AS n_poi, round(avg(area_km2), 5) AS area_km2 FROM l GROUP BY state_id, factor, class""",
    "rank_methods": f"""WITH {_SPLIT}, {_LINE}, {_CONST.format(t='price')}, s AS (SELECT state_id, 'line' AS method, sqrt(avg((y - yhat) * (y - yhat))) AS rmse FROM line GROUP BY state_id UNION ALL SELECT state_id, 'mean', sqrt(avg((y - yhat) * (y - yhat))) FROM pred GROUP BY state_id)
SELECT state_id, method, CAST(rank() OVER (PARTITION BY state_id ORDER BY rmse NULLS LAST) AS INTEGER) AS place, round(rmse, 5) AS rmse FROM s""",
    "alpha_grid": f"WITH {POI}, {_GRID}, n AS (SELECT state_id, count(*) AS n FROM poi GROUP BY state_id), g AS (SELECT *, CAST(CASE WHEN a2 <> 0 THEN 2 WHEN a1 <> 0 THEN 1 ELSE 0 END AS INTEGER) AS hops FROM grid) SELECT state_id, a0, a1, a2, hops, n * hops AS n_spread FROM n, g",
    "published_settings": f"""WITH {POI}, n AS (SELECT state_id, zip_id, count(*) AS n FROM poi GROUP BY 1, 2)
SELECT state_id, state, task, r, a0, a1, a2, CAST(sum(n) AS BIGINT) AS n_poi, CAST(sum(greatest(1, CAST(floor(n * CAST(r AS DECIMAL(10, 9))) AS BIGINT))) AS BIGINT) AS n_places FROM n, (VALUES {_SET}) t(state, task, r, a0, a1, a2) GROUP BY ALL""",
    "alpha_region_combo": f"WITH {UNIT}, {hops_sql(2)}, {_MEANS}, {_WIDE}, {_GRID} SELECT w0.zip_id, a0, a1, a2, round({_PROBE}, 6) + 0.0::DOUBLE AS probe FROM w0 JOIN w1 ON w1.zip_id = w0.zip_id JOIN w2 ON w2.zip_id = w0.zip_id, grid",
    "speedup": f"""WITH {POI}, log AS (SELECT * FROM (VALUES {_SPEED_ROWS}) t(state, points, method, r, seconds)), n AS (SELECT CAST(state_id AS VARCHAR) AS state, count(*) AS points FROM poi GROUP BY 1),
law AS (SELECT method, r, regr_slope(ln(seconds), ln(points)) AS slope, regr_intercept(ln(seconds), ln(points)) AS start FROM log GROUP BY method, r),
every AS (SELECT state, method, r, seconds FROM log UNION ALL SELECT state, method, r, exp(start + slope * ln(points)) FROM n, law)
SELECT b.state, b.method, a.r AS ref_r, round(b.seconds / a.seconds, 4) AS speedup FROM every b JOIN every a ON a.state = b.state WHERE a.method = 'reference' AND b.method <> 'reference'""",
    "growth_slopes": f"WITH {KNN}, n AS (SELECT p.state_id, n, e FROM (SELECT state_id, count(*) AS n FROM poi GROUP BY 1) p JOIN (SELECT state_id, count(*) AS e FROM edge GROUP BY 1) q ON p.state_id = q.state_id) SELECT 'edges' AS method, 0.0::DOUBLE AS r, round(regr_slope(ln(e), ln(n)), 5) AS slope FROM n",
    "w_embedding_clusters": "SELECT label, greatest(1, CAST(floor(count(*) * CAST(0.05 AS DECIMAL(10, 9))) AS BIGINT)) AS n_places, count(*) AS n FROM embeddings GROUP BY label",
    "w_homogenisation": f"""WITH {UNIT}, {hops_sql(2)}, mix AS (SELECT a2, h0.poi_id, list(0.5::DOUBLE * h0.x + 0.25::DOUBLE * h1.x + a2 * h2.x ORDER BY h0.i) AS v
  FROM h0 JOIN h1 ON h1.poi_id = h0.poi_id AND h1.i = h0.i JOIN h2 ON h2.poi_id = h0.poi_id AND h2.i = h0.i, (SELECT unnest([0.0::DOUBLE, 0.25::DOUBLE, 0.5::DOUBLE, 0.75::DOUBLE, 1.0::DOUBLE]) AS a2) GROUP BY a2, h0.poi_id)
SELECT x.a2, count(*) AS edges, round(avg(list_cosine_similarity(x.v, y.v)), 6) AS score FROM edge JOIN mix x ON x.poi_id = src JOIN mix y ON y.poi_id = dst AND x.a2 = y.a2 GROUP BY x.a2""",
}
from .places import SQL as _PLACE_SQL  # noqa: E402

SQL["plan_regions"] = _PLACE_SQL["region_mean"]
assert vectors and mix_sql
