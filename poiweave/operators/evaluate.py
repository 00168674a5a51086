"""Evaluation protocol: repeated splits, regressors, measures, tuning, timing, ranking."""

from __future__ import annotations

import time
from collections.abc import Callable, Sequence

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Observation, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import vectors
from .learners import BULK, FITTERS
from .session import cut, spread

#: Fixed values of the protocol: repeats, training share; tuned settings by state (ratio, three coefficients for density, three for price).
RUNS, TRAIN = 10, 0.8
PUBLISHED = (
    ("WY", "0.1", (0.5, 0.5, 0.0), (0.5, 0.0, 0.0)),
    ("VT", "0.1", (0.0, 0.5, 0.0), (0.0, 0.25, 0.0)),
    ("AL", "0.1", (0.0, 0.0, 0.5), (0.0, 0.25, 0.0)),
    ("GA", "0.05", (0.5, 1.0, 0.0), (0.5, 1.0, 0.0)),
    ("NY", "0.02", (0.25, 0.0, 0.0), (0.75, 0.0, 0.0)),
    ("FL", "0.05", (0.0, 0.5, 1.0), (0.0, 0.5, 0.0)),
    ("CA", "0.05", (0.0, 0.5, 1.0), (1.0, 0.5, 1.0)),
)


def split_runs(labels: DataFrame, runs: int = RUNS, train: float = TRAIN) -> DataFrame:
    """state_id, run, zip_id, is_train: in every run the first ``train`` of a state's regions in the order of a hash, exactly."""
    rows = labels.select("state_id", "zip_id").withColumn("run", F.explode(F.sequence(F.lit(0), F.lit(runs - 1))))
    w = Window.partitionBy("state_id", "run")
    place = F.row_number().over(w.orderBy(F.md5(F.concat_ws(":", "run", "zip_id")), "zip_id"))
    return rows.withColumn("is_train", place <= F.floor(F.count(F.lit(1)).over(w) * train + 1e-9)).select("state_id", "run", "zip_id", "is_train")


def constant_predictor(labels: DataFrame, splits: DataFrame, target: str) -> DataFrame:
    """state_id, run, zip_id, y, yhat: the training mean for every test region."""
    rows = splits.join(labels.select("zip_id", F.col(target).alias("y")), "zip_id")
    mean = F.avg(F.when(F.col("is_train"), F.col("y"))).over(Window.partitionBy("state_id", "run"))
    return rows.withColumn("yhat", mean).filter("not is_train").select("state_id", "run", "zip_id", "y", "yhat")


def fit_predict(features: DataFrame, labels: DataFrame, splits: DataFrame, target: str, model: str = "rf", method: str = "reference", seed: int = 1) -> DataFrame:
    """state_id, method, run, zip_id, y, yhat on the test regions. ``rf`` is Spark's forest with 100 trees and ``gbt`` its boosted trees; ``ridge``,
    ``forest`` (100 trees), ``mlp`` and ``xgb`` run in NumPy, a task for each (state, run).
    """
    rows = splits.join(features.select("zip_id", "z"), "zip_id").join(labels.select("zip_id", F.col(target).alias("y")), "zip_id")
    if model in ("rf", "gbt"):
        return _spark_trees(rows, model, method, seed)
    fit = BULK.get(model, FITTERS[model])

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("zip_id")
        x, y, train = np.stack(pdf["z"].to_list()), pdf["y"].to_numpy(), pdf["is_train"].to_numpy()
        test = pdf[~train]
        yhat = fit(x[train], y[train])(x[~train]) if train.sum() > 1 and len(test) else np.full(len(test), y[train].mean() if train.any() else 0.0)
        return pd.DataFrame({"state_id": test["state_id"], "method": method, "run": test["run"], "zip_id": test["zip_id"], "y": test["y"], "yhat": yhat})

    return spread(rows, "state_id", "run").groupBy("state_id", "run").applyInPandas(run, "state_id int, method string, run int, zip_id long, y double, yhat double")


def _spark_trees(rows: DataFrame, model: str, method: str, seed: int) -> DataFrame:
    """One model for each state and run, fitted one after another from a table that is written once: a state and run is a bounded piece of work, and Spark trains it on all executors."""
    from pyspark.ml.functions import array_to_vector
    from pyspark.ml.regression import GBTRegressor, RandomForestRegressor

    rows = cut(rows).withColumn("features", array_to_vector("z"))
    out = None
    for state, run in sorted((r[0], r[1]) for r in rows.select("state_id", "run").distinct().collect()):
        own = rows.filter((F.col("state_id") == state) & (F.col("run") == run))
        kind = RandomForestRegressor(labelCol="y", numTrees=100, seed=seed) if model == "rf" else GBTRegressor(labelCol="y", maxIter=30, maxDepth=3, seed=seed)
        pred = kind.fit(own.filter("is_train")).transform(own.filter("not is_train"))
        pred = pred.select("state_id", F.lit(method).alias("method"), "run", "zip_id", "y", F.col("prediction").alias("yhat"))
        out = pred if out is None else out.unionByName(pred)
    return out


def score(predictions: DataFrame, by: Sequence[str]) -> DataFrame:
    """by, rmse, mae, r2, n. r2 = 1 - SSE / SST about the test mean; null if the test labels do not vary."""
    gap = F.col("y") - F.col("yhat")
    rows = predictions.groupBy(*by).agg(F.count(F.lit(1)).alias("n"), F.sqrt(F.avg(gap * gap)).alias("rmse"), F.avg(F.abs(gap)).alias("mae"), F.sum(gap * gap).alias("sse"), F.var_pop("y").alias("v"))
    return rows.select(*by, "rmse", "mae", F.when(F.col("v") > 1e-12, 1 - F.col("sse") / (F.col("v") * F.col("n"))).alias("r2"), "n")


def summarise_runs(scores: DataFrame, by: Sequence[str]) -> DataFrame:
    """Mean and sample standard deviation of each measure over the runs."""
    return scores.groupBy(*by).agg(*(f(c).alias(f"{c}_{n}") for c in ("rmse", "mae", "r2") for n, f in (("mean", F.avg), ("sd", F.stddev_samp))), F.count(F.lit(1)).alias("runs"))


def error_by_region(predictions: DataFrame, bins: int = 4) -> DataFrame:
    """zip_id, error (mean absolute over runs) and its rank class inside the state."""
    e = predictions.groupBy("state_id", "zip_id").agg(F.avg(F.abs(F.col("y") - F.col("yhat"))).alias("error"))
    return e.withColumn("class", F.ntile(bins).over(Window.partitionBy("state_id").orderBy("error", "zip_id")))


def error_breakdown(errors: DataFrame, poi: DataFrame, regions: DataFrame, bins: int = 3) -> DataFrame:
    """Mean error by classes of point density (points by area) and of area: the printed explanations of where errors lie. ``regions`` has zip_id, area_km2."""
    n = poi.groupBy("zip_id").agg(F.count(F.lit(1)).alias("n_poi"))
    rows = errors.join(n, "zip_id").join(regions.select("zip_id", "area_km2"), "zip_id").withColumn("density", F.col("n_poi") / F.col("area_km2"))
    classes = lambda c: F.ntile(bins).over(Window.partitionBy("state_id").orderBy(F.round(c, 9), "zip_id"))
    rows = rows.withColumns({"density": classes("density"), "area": classes("area_km2")})
    long = rows.select("state_id", "error", "n_poi", "area_km2", F.explode(F.array(*(F.struct(F.lit(c).alias("factor"), F.col(c).alias("class")) for c in ("density", "area")))).alias("c"))
    return long.groupBy("state_id", F.col("c.factor").alias("factor"), F.col("c.class").alias("class")).agg(F.avg("error").alias("error"), F.avg("n_poi").alias("n_poi"), F.avg("area_km2").alias("area_km2"), F.count(F.lit(1)).alias("regions"))


def rank_methods(scores: DataFrame, by: Sequence[str], measure: str = "rmse", higher_is_better: bool = False) -> DataFrame:
    order = F.desc_nulls_last(measure) if higher_is_better else F.asc_nulls_last(measure)
    return scores.withColumn("place", F.rank().over(Window.partitionBy(*by).orderBy(order)))


def alpha_grid(spark: SparkSession, step: float = 0.25, low: float = 0.0, high: float = 1.0, k: int = 2) -> DataFrame:
    """All coefficient vectors a0..ak on the grid."""
    n = round((high - low) / step)
    axis = spark.range(n + 1).select((F.col("id") * step + low).alias("x"))
    out = axis.withColumnRenamed("x", "a0")
    for i in range(1, k + 1):
        out = out.crossJoin(axis.withColumnRenamed("x", f"a{i}"))
    return out


def setting_cost(grid: DataFrame, poi: DataFrame) -> DataFrame:
    """state_id, a0, a1, a2, hops, n_spread: the hops that each setting of ``grid`` needs, and the vectors they spread over a state's points."""
    hops = F.when(F.col("a2") != 0, 2).when(F.col("a1") != 0, 1).otherwise(0)
    n = poi.groupBy("state_id").agg(F.count(F.lit(1)).alias("n"))
    return n.crossJoin(F.broadcast(grid)).select("state_id", "a0", "a1", "a2", hops.alias("hops"), (F.col("n") * hops).alias("n_spread"))


def places_of_settings(settings: DataFrame, poi: DataFrame) -> DataFrame:
    """state_id and ``settings``' columns with the points of each state and the places that the setting's ratio gives its regions."""
    n = poi.groupBy("state_id", "zip_id").agg(F.count(F.lit(1)).alias("n"))
    k = F.greatest(F.lit(1), F.floor(F.col("n").cast("decimal(18,0)") * F.col("r").cast("decimal(10,9)")))
    return n.crossJoin(F.broadcast(settings)).groupBy("state_id", *settings.columns).agg(F.sum("n").alias("n_poi"), F.sum(k.cast("long")).alias("n_places"))


def seconds_at(log: DataFrame, sizes: DataFrame) -> DataFrame:
    """``log``'s columns for other states (``sizes``: state, points): every method's power law of seconds over points, fitted to ``log``, at their size."""
    law = log.groupBy("method", "r").agg(F.regr_slope(F.log("seconds"), F.log("points")).alias("slope"), F.regr_intercept(F.log("seconds"), F.log("points")).alias("start"))
    return sizes.crossJoin(law).select("state", "points", "method", "r", F.exp(F.col("start") + F.col("slope") * F.log("points")).alias("seconds"))


def published_settings(spark: SparkSession) -> DataFrame:
    rows = [(s, task, r, *map(float, a)) for s, r, density, price in PUBLISHED for task, a in (("density", density), ("price", price))]
    return spark.createDataFrame(rows, "state string, task string, r string, a0 double, a1 double, a2 double")


def region_grid(means: Sequence[DataFrame], grid: DataFrame, d: int) -> DataFrame:
    """zip_id, a0, a1, a2, z of every setting: region means are linear in the hops, so means of H0, H1, H2 serve the whole grid."""
    rows = means[0].select("zip_id", F.col("z").alias("z0"))
    for k, m in enumerate(means[1:], 1):
        rows = rows.join(m.select("zip_id", F.col("z").alias(f"z{k}")), "zip_id")
    rows = rows.crossJoin(F.broadcast(grid))
    z = F.array(*(sum((F.col(f"a{k}") * F.col(f"z{k}")[i] for k in range(len(means))), F.lit(0.0)) for i in range(d)))
    return rows.select("zip_id", *(f"a{k}" for k in range(len(means))), z.alias("z"))


def tune(means: Sequence[DataFrame], labels: DataFrame, target: str, grid: DataFrame, d: int, runs: int = RUNS) -> DataFrame:
    """state_id, a0, a1, a2, rmse of all settings but the zero vector, best first inside a state (place 1).

    A setting is judged on the training regions of every run alone, by leaving each of them out of a ridge regression in turn (in closed form), so the test regions have no say. The
    grid is walked inside a task, which holds the region means of one state and run: the 125 settings are never written out.
    """
    settings = sorted((r["a0"], r["a1"], r["a2"]) for r in grid.collect() if r["a0"] or r["a1"] or r["a2"])
    n_hops, rows = len(means), means[0].select("zip_id", F.col("z").alias("z0"))
    for k, m in enumerate(means[1:], 1):
        rows = rows.join(m.select("zip_id", F.col("z").alias(f"z{k}")), "zip_id")
    joined = split_runs(labels, runs).filter("is_train").join(labels.select("zip_id", F.col(target).alias("y")), "zip_id").join(rows, "zip_id")

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("zip_id")
        y = pdf["y"].to_numpy()
        hops = [np.stack(pdf[f"z{k}"].to_list()) for k in range(n_hops)]
        out = [(int(pdf["state_id"].iloc[0]), int(pdf["run"].iloc[0]), *a, _left_out_error(sum(w * z for w, z in zip(a, hops, strict=True)), y)) for a in settings]
        return pd.DataFrame(out, columns=["state_id", "run", "a0", "a1", "a2", "rmse"])

    out = spread(joined, "state_id", "run").groupBy("state_id", "run").applyInPandas(run, "state_id int, run int, a0 double, a1 double, a2 double, rmse double")
    out = out.groupBy("state_id", "a0", "a1", "a2").agg(F.avg("rmse").alias("rmse"))
    return out.withColumn("place", F.row_number().over(Window.partitionBy("state_id").orderBy(F.round("rmse", 9), "a0", "a1", "a2")))


def _left_out_error(x: np.ndarray, y: np.ndarray, penalty: float = 1.0) -> float:
    """Root mean square of the errors of ridge predictions for rows left out one at a time."""
    if len(y) < 3:
        return 0.0
    z = np.column_stack([(x - x.mean(axis=0)) / (x.std(axis=0) + 1e-9), np.ones(len(y))])
    ridge = penalty * np.eye(z.shape[1])
    ridge[-1, -1] = 0.0
    half = np.linalg.solve(z.T @ z + ridge, z.T)  # z @ half is the hat matrix, of which only the diagonal and its product with y are needed
    return float(np.sqrt((((y - z @ (half @ y)) / np.maximum(1 - np.einsum("ij,ji->i", z, half), 1e-6)) ** 2).mean()))


def tuned_features(means: Sequence[DataFrame], best: DataFrame, labels: DataFrame, d: int) -> DataFrame:
    """zip_id, z: each region's vector under the best coefficients of its state (``best``: state_id, a0, a1, a2)."""
    rows = labels.select("zip_id", "state_id").join(best, "state_id")
    for k, m in enumerate(means):
        rows = rows.join(m.select("zip_id", F.col("z").alias(f"z{k}")), "zip_id")
    return rows.select("zip_id", F.array(*(sum((F.col(f"a{k}") * F.col(f"z{k}")[i] for k in range(len(means))), F.lit(0.0)) for i in range(d))).alias("z"))


def expressiveness_gap(h: DataFrame, places: DataFrame, labels: DataFrame, target: str) -> DataFrame:
    """Error of one ridge model fitted on all point vectors and of one on weighted place vectors, both scored on the regions' means."""
    y = labels.select("state_id", "zip_id", F.col(target).alias("y"))
    full = h.join(y, "zip_id").select("state_id", "zip_id", "y", F.col("h").alias("z"), F.lit(1.0).alias("w"), F.lit("points").alias("on"))
    few = places.join(y, "zip_id").select("state_id", "zip_id", "y", "z", F.col("n_poi").cast("double").alias("w"), F.lit("places").alias("on"))

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        x, w, t = np.stack(pdf["z"].to_list()), pdf["w"].to_numpy(), pdf["y"].to_numpy()
        x1 = np.column_stack([x, np.ones(len(x))])
        beta = np.linalg.solve((x1 * w[:, None]).T @ x1 + 1e-6 * w.sum() * np.eye(x1.shape[1]), (x1 * w[:, None]).T @ t)
        grouped = pd.DataFrame(x1 * w[:, None]).assign(zip=pdf["zip_id"].to_numpy(), w=w).groupby("zip").sum()
        truth = pdf.groupby("zip_id")["y"].first()
        pred = grouped.drop(columns="w").to_numpy() / grouped["w"].to_numpy()[:, None] @ beta
        return pd.DataFrame({"state_id": [pdf["state_id"].iloc[0]], "on": [pdf["on"].iloc[0]], "rows": [len(pdf)], "rmse": [float(np.sqrt(((pred - truth.to_numpy()) ** 2).mean()))]})

    return full.unionByName(few).groupBy("state_id", "on").applyInPandas(run, "state_id int, on string, rows long, rmse double")


def timed(name: str, build: Callable[[], DataFrame]) -> tuple[DataFrame, float]:
    """Seconds to compute a frame into a sink that keeps nothing."""
    began = time.perf_counter()
    df = build()
    df.write.format("noop").mode("overwrite").save()
    return df, time.perf_counter() - began


def observed(df: DataFrame, name: str) -> tuple[DataFrame, Observation]:
    """``df`` with a counter of its rows, read from the second result once an action has run: rows are counted as they pass, without a pass of their own."""
    seen = Observation(name)
    return df.observe(seen, F.count(F.lit(1)).alias("rows")), seen


def speedup_table(log: DataFrame) -> DataFrame:
    """method, r, slope of log seconds over log points, and speed-up of the reference over the method by state. Needs state, points, method, r, seconds."""
    ref = log.filter("method = 'reference'").select("state", F.col("r").alias("ref_r"), F.col("seconds").alias("ref_seconds"))
    return log.filter("method <> 'reference'").join(ref, "state").select("state", "method", "ref_r", (F.col("seconds") / F.col("ref_seconds")).alias("speedup"))


def growth_slopes(log: DataFrame) -> DataFrame:
    return log.groupBy("method", "r").agg(F.regr_slope(F.log("seconds"), F.log("points")).alias("slope"))


def mean_absolute_dimension(features: DataFrame) -> DataFrame:
    """Dimension and length of feature vectors: a check that all methods have the same ``d``."""
    return features.select(F.size("z").alias("d"), vectors.norm(F.col("z")).alias("norm")).groupBy("d").agg(F.count(F.lit(1)).alias("regions"), F.avg("norm").alias("norm"))
