"""Places: bisecting clustering of regions, its hierarchy, summaries, profiles and similarity."""

from __future__ import annotations

from collections.abc import Sequence
from decimal import Decimal

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions import category, geo, vectors
from .components import connected_components, least_labels
from .kmeans import bisect, dbscan, expand, leading_direction, lloyd, split_ranks
from .session import cut, cut_and_release, release, small, spread

#: Regions with more points than this are split by the distributed engine.
TASK_POINTS = 200_000
RATIOS = ("0.1", "0.05", "0.02")


def budget_of(n: int, r: str | Decimal) -> int:
    """Places of a region with ``n`` points: floor of the exact product, at least one."""
    return max(1, int(n * Decimal(str(r))))


def place_budget(n: Column, r: str) -> Column:
    ratio = Decimal(r)
    if not 0 < ratio <= 1:
        raise ValueError("the ratio must be in (0, 1]")
    return F.greatest(F.lit(1), F.floor(n.cast("decimal(18,0)") * F.lit(ratio).cast("decimal(10,9)"))).cast("long")


def _types(df: DataFrame, keys: Sequence[str]) -> str:
    return ", ".join(f"{k} {df.schema[k].dataType.simpleString()}" for k in keys)


def _matrix(column: pd.Series) -> np.ndarray:
    return np.stack(column.to_list()).astype(float)


def place_hierarchy(h: DataFrame, keys: Sequence[str], r: str = "0.1", priority: str = "size", init: str = "principal", max_iter: int = 300, tol: float = 1e-8, seed: int = 1, weight: str | None = None) -> DataFrame:
    """keys, poi_id, path, ranks: each point's leaf in its region's split tree and the split order of the leaf's ancestors.

    One task for a region. Cutting the tree at fewer splits (:func:`cut_hierarchy`) gives every smaller ratio. Equal vectors are never
    parted, so a region may have fewer leaves than its budget; a region with one point is one place.
    """
    keys = list(keys)

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        w = pdf["__w"].to_numpy(float)
        tree = bisect(pdf["poi_id"].to_numpy(), _matrix(pdf["h"]), budget_of(len(pdf), r), w, priority, init, max_iter, tol, seed)
        ranks = split_ranks(tree)
        out = pdf[[*keys, "poi_id"]].copy()
        out["path"] = tree.leaf
        out["ranks"] = [ranks[p] for p in tree.leaf]
        return out

    rows = h.select(*keys, "poi_id", "h", (F.col(weight).cast("double") if weight else F.lit(1.0)).alias("__w"))
    return spread(rows, *keys).groupBy(*keys).applyInPandas(run, f"{_types(h, keys)}, poi_id {h.schema['poi_id'].dataType.simpleString()}, path string, ranks array<int>")


def cut_hierarchy(members: DataFrame, keys: Sequence[str], r: str) -> DataFrame:
    """Places of ratio ``r`` from a finer hierarchy: a point's path is cut before the first split that came too late."""
    n = F.count(F.lit(1)).over(Window.partitionBy(*keys))
    kept = F.size(F.filter("ranks", lambda x: x < F.col("__k")))
    return members.withColumn("__k", place_budget(n, r)).withColumn("path", F.substring("path", F.lit(1), kept)).drop("__k")


def place_id(keys: Sequence[str], path: str = "path") -> Column:
    """Region id and path: ancestry is string prefix."""
    return F.concat_ws("|", *(F.col(k).cast("string") for k in keys), F.col(path))


def bisect_places(h: DataFrame, keys: Sequence[str], r: str = "0.1", engine: str = "auto", task_points: int = TASK_POINTS, sizes: DataFrame | None = None, **options) -> DataFrame:
    """keys, poi_id, path, place_id. ``auto`` sends regions up to ``task_points`` points to one task each, larger ones to the distributed engine; ``sizes`` (keys,
    n) spares it counting them, which would compute ``h`` once more.

    Both engines take the options of :func:`place_hierarchy`; the distributed one raises an error for ``init='kmeans++'``, whose draws belong to one task.
    """
    keys = list(keys)
    if engine == "task":
        out = place_hierarchy(h, keys, r, **options)
    elif engine == "distributed":
        out = bisect_distributed(h, keys, r, **options)
    else:
        large, n_large = _large_regions(h, keys, task_points, sizes)
        if not n_large:
            out = place_hierarchy(h, keys, r, **options)
        else:
            large = small(large, n_large)
            out = place_hierarchy(h.join(large, keys, "left_anti"), keys, r, **options).drop("ranks")
            out = out.unionByName(bisect_distributed(h.join(large, keys, "left_semi"), keys, r, **options))
    return out.select(*keys, "poi_id", "path", place_id(keys).alias("place_id"))


def _large_regions(h: DataFrame, keys: list[str], task_points: int, sizes: DataFrame | None) -> tuple[DataFrame, int]:
    sizes = h.groupBy(*keys).agg(F.count(F.lit(1)).alias("n")) if sizes is None else sizes
    large = cut(sizes.filter(F.col("n") > task_points).select(*keys))
    return large, large.count()


def bisect_distributed(h: DataFrame, keys: Sequence[str], r: str = "0.1", priority: str = "size", init: str = "principal", max_iter: int = 300, tol: float = 1e-8, seed: int = 1, weight: str | None = None, node_points: int = TASK_POINTS) -> DataFrame:
    """The same splits for regions of any size, all regions and all active leaves at once.

    A child is never larger than its parent (nor is its error), so "largest first" splits exactly the k - 1 largest nodes of the full tree: in each round every
    leaf whose rank among all known nodes is below k is split. A leaf of up to ``node_points`` points is split in one task, together with all nodes below it that may be among
    those: none of the k - 1 largest is smaller than a k-th of its region. Larger leaves are split by Lloyd passes over all executors, each one aggregation, and leaves that have settled take
    no part in further ones.
    """
    if init not in ("principal", "farthest"):
        raise ValueError(f"the distributed engine has no start {init}")
    keys = list(keys)
    kind = h.schema["poi_id"].dataType.simpleString()
    node = [*keys, "path"]
    rows = cut_and_release(h.select(*keys, "poi_id", "h", (F.col(weight).cast("double") if weight else F.lit(1.0)).alias("w")).withColumn("path", F.lit("")))
    first = rows.select("h").first()
    if first is None:
        return rows.select(*keys, F.col("poi_id").cast(kind).alias("poi_id"), "path")
    d = len(first[0])

    def measured(members: DataFrame, by: list[str]) -> DataFrame:
        """Points of every node, and what it is ranked by: its weight, or its error about its mean."""
        if priority == "size":
            return members.groupBy(*by).agg(F.count(F.lit(1)).alias("n"), F.sum("w").alias("rank_by"))
        mean = members.groupBy(*by).agg(F.count(F.lit(1)).alias("n"), *(F.expr(f"sum(w * h[{i}]) / sum(w)").alias(f"__s{i}") for i in range(d))).select(*by, "n", vectors.gathered(d).alias("mean"))
        gap = F.aggregate(F.zip_with("h", "mean", lambda a, b: (a - b) * (a - b)), F.lit(0.0), lambda s, x: s + x)
        error = members.join(mean.drop("n"), by).groupBy(*by).agg(F.round(F.sum(F.col("w") * gap), 9).alias("rank_by"))
        return mean.drop("mean").join(error, by)

    nodes = measured(rows, node).withColumns({"split": F.lit(False), "dead": F.col("n") < 2})
    nodes = cut(nodes.withColumn("whole", F.col("rank_by")))
    whole = nodes.select(*keys, "whole")
    budget = cut(nodes.select(*keys, place_budget(F.col("n"), r).alias("k")))
    while True:
        rank = F.row_number().over(Window.partitionBy(*keys).orderBy(F.desc("rank_by"), "path"))
        asked = nodes.filter("not dead").withColumn("rank", rank).join(budget, keys).filter("rank < k and not split").select(*node, "n", "rank_by", "k", "whole")
        asked = cut(asked)
        if asked.isEmpty():
            return _keep_largest_splits(rows, nodes, budget, keys)
        # what a task splits below a leaf: nodes of a k-th of the region's weight, or of a part of the leaf's own error
        least = F.col("whole") / F.col("k") if priority == "size" else F.col("rank_by") / 16
        own = cut_and_release(_expand_nodes(rows.join(asked.filter(F.col("n") <= node_points).select(*node, least.alias("least")), node), node, kind, priority, init, max_iter, tol))
        placed = own.filter("poi_id is not null").select(*keys, "poi_id", "h", "w", "path")
        fresh = own.filter("poi_id is null").select(*node, "n", "rank_by", "split", "dead")
        large = asked.filter(F.col("n") > node_points).select(*node)
        if not large.isEmpty():
            active = cut(rows.join(F.broadcast(large), node))  # few: each holds more than node_points points
            sides = _split_nodes(active, node, d, init, max_iter, tol)  # node, c0, c1 of nodes that can be split
            sided = active.join(F.broadcast(sides), node).withColumn("side", _side())
            lead = sided.groupBy(*node).agg(F.min_by("side", "poi_id").alias("lead"))
            halves = cut_and_release(sided.join(F.broadcast(lead), node).select(*keys, "poi_id", "h", "w", F.concat("path", F.when(F.col("side") == F.col("lead"), "0").otherwise("1")).alias("path")))
            parents = sides.select(*node).withColumn("__done", F.lit(True))
            tried = asked.join(large, node, "left_semi").join(parents, node, "left").select(*node, "n", "rank_by", F.coalesce("__done", F.lit(False)).alias("split"), F.col("__done").isNull().alias("dead"))
            fresh = fresh.unionByName(tried).unionByName(measured(halves, node).withColumns({"split": F.lit(False), "dead": F.col("n") < 2}))
            placed = placed.unionByName(halves)
        nodes = cut(nodes.join(asked.select(*node), node, "left_anti").select(*node, "n", "rank_by", "split", "dead").unionByName(fresh).join(whole, keys))
        rest = rows.join(placed.select("poi_id", *keys), [*keys, "poi_id"], "left_anti")
        rows = cut(rest.select(*keys, "poi_id", "h", "w", "path").unionByName(placed))
        own = placed = rest = active = sided = halves = sides = lead = fresh = None  # tables of this round, written for it alone
        release(rows.sparkSession)


def _expand_nodes(active: DataFrame, node: list[str], kind: str, priority: str, init: str, max_iter: int, tol: float) -> DataFrame:
    """Splits of whole nodes (``active``: node, poi_id, h, w, least), a task each: members with their new path, and, with null members, the node and all below it."""
    keys = node[:-1]

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        path, ids = pdf["path"].iloc[0], pdf["poi_id"].to_numpy()
        leaf, nodes = expand(ids, _matrix(pdf["h"]), pdf["w"].to_numpy(float), float(pdf["least"].iloc[0]), priority, init, max_iter, tol)
        members = pdf[[*keys, "poi_id", "h", "w"]].assign(path=[path + p for p in leaf])
        below = pd.DataFrame({k: [pdf[k].iloc[0]] * len(nodes) for k in keys}).assign(path=[path + x[0] for x in nodes], h=None, n=[x[1] for x in nodes], rank_by=[x[2] for x in nodes], split=[x[3] for x in nodes], dead=[x[4] for x in nodes])
        return pd.concat([members.reindex(columns=columns), below.reindex(columns=columns)]).astype({"n": "Int64", "split": "boolean", "dead": "boolean"} | ({"poi_id": "Int64"} if ids.dtype.kind == "i" else {}))

    columns = [*keys, "path", "poi_id", "h", "w", "n", "rank_by", "split", "dead"]
    return spread(active, *node).groupBy(*node).applyInPandas(run, f"{_types(active, keys)}, path string, poi_id {kind}, h array<double>, w double, n long, rank_by double, split boolean, dead boolean")


def _keep_largest_splits(rows: DataFrame, nodes: DataFrame, budget: DataFrame, keys: list[str]) -> DataFrame:
    """Undo splits beyond the k - 1 largest nodes: a round may have split a few too many. Parents are larger than children, so what
    is kept is a tree from the root, and a leaf's place ends after as many steps as it has kept ancestors.
    """
    rank = F.row_number().over(Window.partitionBy(*keys).orderBy(F.desc("rank_by"), "path"))
    kept = nodes.filter("split").withColumn("rank", rank).join(budget, keys).filter("rank < k").select(*keys, F.col("path").alias("up"), F.lit(1).alias("hit"))
    leaves = nodes.filter("not split").select(*keys, "path")
    ups = leaves.filter("path <> ''").select(*keys, "path", F.explode(F.transform(F.sequence(F.lit(0), F.length("path") - 1), lambda i: F.substring("path", F.lit(1), i))).alias("up"))
    steps = ups.join(kept, [*keys, "up"], "left").groupBy(*keys, "path").agg(F.sum(F.coalesce("hit", F.lit(0))).cast("int").alias("steps"))
    ends = leaves.join(steps, [*keys, "path"], "left").select(*keys, "path", F.substring("path", F.lit(1), F.coalesce("steps", F.lit(0))).alias("end"))
    return rows.join(ends, [*keys, "path"]).select(*keys, "poi_id", F.col("end").alias("path"))


def _side() -> Column:
    gap = F.zip_with("c1", "c0", lambda a, b: a - b)
    middle = (vectors.dot(F.col("c1"), F.col("c1")) - vectors.dot(F.col("c0"), F.col("c0"))) / 2
    return F.when(vectors.dot(F.col("h"), gap) > middle, 1).otherwise(0)


def _split_nodes(active: DataFrame, node: list[str], d: int, init: str, max_iter: int, tol: float) -> DataFrame:
    """Centres of both halves of every node of ``active`` (node, poi_id, h, w)."""
    x, w = [F.col("h")[i] for i in range(d)], F.col("w")
    if init == "principal":
        pairs = [(i, j) for i in range(d) for j in range(i, d)]
        stats = active.groupBy(*node).agg(
            F.sum(w).alias("n"),
            F.array(*(F.sum(w * c) for c in x)).alias("s"),
            F.array(*(F.max(c) - F.min(c) for c in x)).alias("range"),
            F.array(*(F.sum(w * x[i] * x[j]) for i, j in pairs)).alias("p"),
        )

        def directions(batches):
            for pdf in batches:
                means, axes = [], []
                for n, s, p in zip(pdf["n"], pdf["s"], pdf["p"], strict=True):
                    mean, cov = np.array(s) / n, np.zeros((d, d))
                    for (i, j), v in zip(pairs, p, strict=True):
                        cov[i, j] = cov[j, i] = v / n - mean[i] * mean[j]
                    means.append(mean.tolist())
                    axes.append(leading_direction(cov).tolist())
                yield pdf[node].assign(mean=means, axis=axes)

        axes = stats.filter(F.array_max("range") > 1e-12).mapInPandas(directions, f"{_types(stats, node)}, mean array<double>, axis array<double>")
        first = active.join(axes, node).withColumn("side", F.when(vectors.dot(F.zip_with("h", "mean", lambda a, b: a - b), F.col("axis")) > 0, 1).otherwise(0))
    else:  # the point farthest from the mean, and the one farthest from that; the first by id among equals
        mean = active.groupBy(*node).agg(F.array(*(F.sum(w * c) / F.sum(w) for c in x)).alias("mean"))
        gap = lambda c: F.aggregate(F.zip_with("h", c, lambda a, b: (a - b) * (a - b)), F.lit(0.0), lambda s, v: s + v)
        far = lambda rows, c, name: rows.groupBy(*node).agg(F.max_by("h", F.struct(gap(c), -F.col("poi_id"))).alias(name), F.max(gap(c)).alias("reach")).filter("reach > 1e-24").drop("reach")
        one = cut(far(active.join(mean, node), "mean", "a"))
        two = far(active.join(one, node), "a", "b")
        first = active.join(one.join(two, node), node).withColumn("side", F.when(gap("b") < gap("a"), 1).otherwise(0))
    kind = ", ".join([_types(active, node), "c0 array<double>, c1 array<double>"])
    centres = {tuple(r[k] for k in node): (r["c0"], r["c1"]) for r in _centres(first, node, d).collect()}  # one row for each node beyond a task: few
    going = set(centres)
    for _ in range(max_iter):
        if not going:
            break
        now = F.broadcast(active.sparkSession.createDataFrame([(*k, *centres[k]) for k in sorted(going)], kind))
        fresh = {tuple(r[k] for k in node): (r["c0"], r["c1"]) for r in _centres(active.join(now, node).withColumn("side", _side()), node, d).collect()}
        for key in list(going):
            if key not in fresh:  # one side is empty: the node cannot be split
                del centres[key]
                going.remove(key)
                continue
            if ((np.array(fresh[key]) - np.array(centres[key])) ** 2).sum(axis=1).max() <= tol * tol:
                going.remove(key)
            centres[key] = fresh[key]
    return active.sparkSession.createDataFrame([(*k, *v) for k, v in centres.items()], kind)


def _centres(sided: DataFrame, node: list[str], d: int) -> DataFrame:
    weight = lambda s: F.sum(F.when(F.col("side") == s, F.col("w")))
    mean = lambda s: F.array(*(F.sum(F.when(F.col("side") == s, F.col("w") * F.col("h")[i])) / weight(s) for i in range(d)))
    return sided.groupBy(*node).agg(mean(0).alias("c0"), mean(1).alias("c1"), F.count_distinct("side").alias("__sides")).filter("__sides = 2").drop("__sides")


def lloyd_places(h: DataFrame, keys: Sequence[str], r: str = "0.1", max_iter: int = 300, tol: float = 1e-8) -> DataFrame:
    """Flat k-means of each region: the contrast to bisecting. Paths number the clusters."""
    keys = list(keys)

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("poi_id")
        label = lloyd(_matrix(pdf["h"]), budget_of(len(pdf), r), max_iter, tol)
        return pdf[[*keys, "poi_id"]].assign(path=[f"k{x}" for x in label])

    out = spread(h.select(*keys, "poi_id", "h"), *keys).groupBy(*keys).applyInPandas(run, f"{_types(h, keys)}, poi_id {h.schema['poi_id'].dataType.simpleString()}, path string")
    return out.select(*keys, "poi_id", "path", place_id(keys).alias("place_id"))


def density_places(h: DataFrame, keys: Sequence[str], eps: float, min_pts: int, noise: str | None = None) -> DataFrame:
    """keys, poi_id, place_id (null: noise), is_core, by Euclidean reach ``eps`` between vectors of one region (a task each).

    Core points have ``min_pts`` points within reach, themselves included; a border point joins its nearest core's place, ties by id.
    ``noise='own'`` makes every noise point a place of its own.
    """
    keys = list(keys)

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("poi_id").reset_index(drop=True)
        x, ids = _matrix(pdf["h"]), pdf["poi_id"].to_numpy()
        near = []
        for begin in range(0, len(x), 512):
            gap = ((x[begin : begin + 512, None, :] - x[None, :, :]) ** 2).sum(axis=2)
            near += [np.flatnonzero(row <= eps * eps) for row in gap]

        def nearest(i: int, cores: np.ndarray) -> int | None:
            if not len(cores):
                return None
            gap = ((x[cores] - x[i]) ** 2).sum(axis=1)
            return int(cores[np.lexsort((ids[cores], gap))[0]])

        label, core = dbscan(ids, near, nearest, min_pts)
        region = "|".join(str(pdf[k].iloc[0]) for k in keys)
        own = [f"{region}|d{v}" if v != -1 else (f"{region}|n{i}" if noise == "own" else None) for v, i in zip(label, ids, strict=True)]
        return pdf[[*keys, "poi_id"]].assign(place_id=own, is_core=core)

    return spread(h.select(*keys, "poi_id", "h"), *keys).groupBy(*keys).applyInPandas(run, f"{_types(h, keys)}, poi_id {h.schema['poi_id'].dataType.simpleString()}, place_id string, is_core boolean")


def join_within(poi: DataFrame, eps_m: float, degrees: float | None = None, keys: Sequence[str] = ("state_id",)) -> DataFrame:
    """(keys, a, b, dist_m) of all ordered pairs within ``eps_m`` metres, by tiles no narrower than the distance."""
    degrees = degrees or eps_m / 111_000 * 1.01 / np.cos(np.radians(60))  # wide enough up to 60 degrees of latitude
    base = poi.select(*keys, "poi_id", "lat", "lon").withColumns({"tx": geo.tile(F.col("lon"), degrees), "ty": geo.tile(F.col("lat"), degrees)})
    here = base.withColumn("near", F.explode(geo.ring(F.col("tx"), F.col("ty"), 1))).select(*keys, F.col("poi_id").alias("a"), F.col("lat").alias("lat1"), F.col("lon").alias("lon1"), F.col("near.x").alias("tx"), F.col("near.y").alias("ty"))
    there = base.select(*keys, F.col("poi_id").alias("b"), F.col("lat").alias("lat2"), F.col("lon").alias("lon2"), "tx", "ty")
    pairs = here.join(there, [*keys, "tx", "ty"]).withColumn("dist_m", geo.haversine_m(F.col("lat1"), F.col("lon1"), F.col("lat2"), F.col("lon2")))
    return pairs.filter((F.col("a") != F.col("b")) & (F.col("dist_m") <= eps_m)).select(*keys, "a", "b", "dist_m")


def density_places_spatial(poi: DataFrame, eps_m: float, min_pts: int, keys: Sequence[str] = ("state_id", "zip_id")) -> DataFrame:
    """Density places by distance on the ground for regions of any size: tile join, then components of core points."""
    pairs = cut(join_within(poi, eps_m, keys=keys))
    cores = pairs.groupBy("a").agg((F.count(F.lit(1)) + 1).alias("n")).filter(F.col("n") >= min_pts).select(F.col("a").alias("poi_id")) if min_pts > 1 else poi.select("poi_id")
    cores = cut(cores)
    links = pairs.join(cores.withColumnRenamed("poi_id", "a"), "a").join(cores.withColumnRenamed("poi_id", "b"), "b")
    parts = connected_components(links.select("a", "b"))
    of_core = cores.join(parts.withColumnRenamed("node", "poi_id"), "poi_id", "left").select("poi_id", F.coalesce("root", "poi_id").alias("root"), F.lit(True).alias("is_core"))
    border = pairs.join(of_core.select(F.col("poi_id").alias("b"), "root"), "b").join(of_core.select(F.col("poi_id").alias("a")), "a", "left_anti")
    border = border.groupBy(F.col("a").alias("poi_id")).agg(F.min_by("root", F.struct("dist_m", "b")).alias("root")).withColumn("is_core", F.lit(False))
    out = poi.select(*keys, "poi_id").join(of_core.unionByName(border), "poi_id", "left")
    return out.select(*keys, "poi_id", F.when(F.col("root").isNotNull(), F.concat_ws("|", *(F.col(k).cast("string") for k in keys), F.concat(F.lit("d"), F.col("root").cast("string")))).alias("place_id"), F.coalesce("is_core", F.lit(False)).alias("is_core"))


def summarise_places(members: DataFrame, h: DataFrame, d: int, poi: DataFrame | None = None) -> DataFrame:
    """place_id, n_poi, z (centroid), sse, and lat, lon if ``poi`` is given. The error comes from a second pass about the exact centroid."""
    rows = members.select("place_id", "poi_id").join(h.select("poi_id", "h"), "poi_id")
    z = rows.groupBy("place_id").agg(F.count(F.lit(1)).alias("n_poi"), *vectors.means("h", d)).select("place_id", "n_poi", vectors.gathered(d).alias("z"))
    gap = F.aggregate(F.zip_with("h", "z", lambda a, b: (a - b) * (a - b)), F.lit(0.0), lambda s, x: s + x)
    out = z.join(rows.join(z, "place_id").groupBy("place_id").agg(F.sum(gap).alias("sse")), "place_id")
    if poi is not None:
        spot = members.select("place_id", "poi_id").join(poi.select("poi_id", "lat", "lon"), "poi_id").groupBy("place_id").agg(F.avg("lat").alias("lat"), F.avg("lon").alias("lon"))
        out = out.join(spot, "place_id")
    return out


def condensed_places(h: DataFrame, keys: Sequence[str], r: str = "0.1", task_points: int = TASK_POINTS, sizes: DataFrame | None = None, **options) -> DataFrame:
    """keys, place_id, n_poi, z, sse: the places of :func:`bisect_places` without their members, summed up in the task that found them, so points move once.

    Regions beyond ``task_points`` go through the distributed engine and :func:`summarise_places`. ``sizes`` as there.
    """
    keys = list(keys)

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        x = _matrix(pdf["h"])
        tree = bisect(pdf["poi_id"].to_numpy(), x, budget_of(len(pdf), r), pdf["__w"].to_numpy(float), **kernel)
        paths, at, n = np.unique(tree.leaf.astype(str), return_inverse=True, return_counts=True)
        z = np.zeros((len(paths), x.shape[1]))
        np.add.at(z, at, x)
        z /= n[:, None]
        sse = np.bincount(at, weights=((x - z[at]) ** 2).sum(axis=1))
        out = pd.DataFrame({k: [pdf[k].iloc[0]] * len(paths) for k in keys})
        return out.assign(path=paths, n_poi=n, z=list(z), sse=sse)

    weight = options.get("weight")
    kernel = {k: v for k, v in options.items() if k != "weight"}
    large, n_large = _large_regions(h, keys, task_points, sizes)
    some = h.join(small(large, n_large), keys, "left_anti") if n_large else h
    rows = some.select(*keys, "poi_id", "h", (F.col(weight).cast("double") if weight else F.lit(1.0)).alias("__w"))
    out = spread(rows, *keys).groupBy(*keys).applyInPandas(run, f"{_types(h, keys)}, path string, n_poi long, z array<double>, sse double")
    out = out.select(*keys, place_id(keys).alias("place_id"), "n_poi", "z", "sse")
    if n_large:
        of_large = cut(h.join(small(large, n_large), keys, "left_semi"))
        m = cut(bisect_places(of_large, keys, r, "distributed", **options))
        d = len(of_large.first()["h"])
        out = out.unionByName(summarise_places(m, of_large, d).join(m.select(*keys, "place_id").distinct(), "place_id").select(*out.columns))
    return out


def clustering_sse(places: DataFrame, keys: Sequence[str]) -> DataFrame:
    return places.groupBy(*keys).agg(F.sum("sse").alias("sse"), F.count(F.lit(1)).alias("n_places"))


def members_of(members: DataFrame, place: str | None = None) -> DataFrame:
    """place_id and its sorted points; all places, or one and everything below it.

    Below a place of a split tree lie those whose path goes on with further splits; flat and density places have nothing below them.
    """
    rows = members
    if place is not None:
        region, _, path = place.rpartition("|")
        below = F.lit(False)
        if set(path) <= {"0", "1"}:
            below = F.col("place_id").startswith(place) & F.col("place_id").substr(F.lit(len(place) + 1), F.length("place_id")).rlike("^[01]*$")
        rows = members.filter((F.col("place_id") == place) | below)
    return rows.groupBy("place_id").agg(F.array_sort(F.collect_list("poi_id")).alias("poi_ids"))


def nest_places(places: DataFrame, keys: Sequence[str], r: str = "0.1", **options) -> DataFrame:
    """Places of places: cluster centroids again, each weighing as many points as it holds. Needs keys, place_id, n_poi, z."""
    rows = places.withColumn("poi_id", F.row_number().over(Window.partitionBy(*keys).orderBy("place_id")).cast("long")).withColumnRenamed("z", "h")
    outer = place_hierarchy(rows, keys, r, weight="n_poi", **options)
    out = rows.select(*keys, "poi_id", "place_id").join(outer, [*keys, "poi_id"])
    return out.select(*keys, "place_id", F.concat(F.lit("p|"), place_id(keys)).alias("outer_id"))


def condense_graph(edges: DataFrame, members: DataFrame) -> DataFrame:
    """(a, b, w): weights between places, summed over their points' edges; inner weight as a = b."""
    m = members.select("poi_id", "place_id")
    met = edges.join(m.select(F.col("poi_id").alias("src"), F.col("place_id").alias("p")), "src").join(m.select(F.col("poi_id").alias("dst"), F.col("place_id").alias("q")), "dst")
    return met.groupBy(F.least("p", "q").alias("a"), F.greatest("p", "q").alias("b")).agg(F.sum("w").alias("w"), F.count(F.lit(1)).alias("n_edges"))


def reduction_report(members: DataFrame, keys: Sequence[str], d: int) -> DataFrame:
    """Per region: points, places, factor, bytes of both matrices."""
    out = members.groupBy(*keys).agg(F.count(F.lit(1)).alias("n_poi"), F.count_distinct("place_id").alias("n_places"))
    return out.withColumns({"factor": F.col("n_poi") / F.col("n_places"), "bytes_full": F.col("n_poi") * 8 * d, "bytes_condensed": F.col("n_places") * 8 * d})


def with_coordinates(h: DataFrame, poi: DataFrame, weight: float, keys: Sequence[str] = ("zip_id",)) -> DataFrame:
    """Vectors with two further components: coordinates scaled to [0, 1] inside the region, times ``weight``."""
    w = Window.partitionBy(*keys)
    unit = lambda c: F.coalesce(F.try_divide(F.col(c) - F.min(c).over(w), F.max(c).over(w) - F.min(c).over(w)), F.lit(0.5)) * weight
    spots = poi.select("poi_id", F.array(unit("lat"), unit("lon")).alias("xy"))
    return h.join(spots, "poi_id").withColumn("h", F.concat("h", "xy")).drop("xy")


def _pairs_in_scope(p: DataFrame, q: DataFrame, scope: str) -> DataFrame:
    same = F.col("__r") == F.col("__qr")
    where = {"within": same & (F.col("place_id") != F.col("query_id")), "across": ~same, "all": F.col("place_id") != F.col("query_id")}[scope]
    return p.join(small(q, q.count(), 100_000), where).withColumn("cosine", vectors.cosine(F.col("z"), F.col("q")))


def similar_places(places: DataFrame, queries: DataFrame, k: int, scope: str = "across", region: str = "region_id", index: float | None = None) -> DataFrame:
    """query_id, place_id, cosine, rank. ``places``: region, place_id, z; ``queries``: query_id, region, q. ``within`` keeps the query's region,
    ``across`` leaves it out, ``all`` takes both. Without ``index`` all places are compared with the stated queries, which are broadcast if few. With it, a hashed index of random projections
    (eight tables) gives the places whose cosine is at least ``index``, most of them, and only those are compared.
    """
    p, q = places.select(F.col(region).alias("__r"), "place_id", "z"), queries.select("query_id", F.col(region).alias("__qr"), "q")
    met = _pairs_in_scope(p, q, scope) if index is None else _indexed_pairs(p, q, scope, index)
    rank = F.row_number().over(Window.partitionBy("query_id").orderBy(F.desc_nulls_last("cosine"), "place_id"))
    return met.withColumn("rank", rank).filter(F.col("rank") <= k).select("query_id", "place_id", "cosine", "rank")


def _indexed_pairs(p: DataFrame, q: DataFrame, scope: str, least: float) -> DataFrame:
    from pyspark.ml.feature import BucketedRandomProjectionLSH
    from pyspark.ml.functions import array_to_vector

    unit = lambda df, c: df.withColumn("__n", vectors.norm(F.col(c))).filter("__n > 0").withColumn("__u", array_to_vector(F.transform(c, lambda x: x / F.col("__n"))))
    reach = float(np.sqrt(max(0.0, 2 - 2 * least)))
    places, queries = unit(p, "z"), unit(q, "q")
    model = BucketedRandomProjectionLSH(inputCol="__u", outputCol="__h", bucketLength=2 * max(reach, 1e-3), numHashTables=8, seed=1).fit(places)
    met = model.approxSimilarityJoin(places, queries, reach + 1e-9, "gap").select(*(f"datasetA.{c}" for c in ("__r", "place_id", "z")), *(f"datasetB.{c}" for c in ("query_id", "__qr", "q")))
    same = F.col("__r") == F.col("__qr")
    where = {"within": same & (F.col("place_id") != F.col("query_id")), "across": ~same, "all": F.col("place_id") != F.col("query_id")}[scope]
    return met.filter(where).withColumn("cosine", vectors.cosine(F.col("z"), F.col("q")))


def recommend_regions(places: DataFrame, queries: DataFrame, k: int, region: str = "region_id") -> DataFrame:
    """query_id, region, cosine, rank: the regions whose best place is nearest to each query, its own left out.

    A task compares whole regions with a block of queries as matrices, so of all pairs only its ``k`` best regions of each query leave it. Products are added in the order of the
    components, as in :func:`vectors.cosine`.
    """
    kinds = {n: df.schema[c].dataType.simpleString() for n, df, c in (("query_id", queries, "query_id"), ("region", places, region))}
    cores, n_queries = places.sparkSession.sparkContext.defaultParallelism, queries.count()
    blocks, parts = max(1, -(-n_queries // QUERIES)), max(2 * cores, int(places.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    p = places.filter(F.col(region).isNotNull()).select(F.col(region).alias("__r"), "z").withColumn("part", F.pmod(F.xxhash64("__r"), F.lit(parts)))
    q = queries.filter(F.col(region).isNotNull()).select("query_id", F.col(region).alias("__qr"), "q").withColumn("block", F.pmod(F.xxhash64("query_id"), F.lit(blocks)))
    p = p.withColumn("block", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(blocks - 1).cast("long"))))
    q = q.withColumn("q_part", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(parts - 1).cast("long"))))
    met = spread(p, "part", "block").groupBy("part", "block").cogroup(spread(q, "q_part", "block").groupBy("q_part", "block"))
    top = met.applyInPandas(_nearest_regions(k), f"query_id {kinds['query_id']}, region {kinds['region']}, cosine double")
    rank = F.row_number().over(Window.partitionBy("query_id").orderBy(F.desc_nulls_last("cosine"), "region"))
    return top.withColumn("rank", rank).filter(F.col("rank") <= k)


#: Queries that a task compares with its regions' places at most, about.
QUERIES = 8_192
#: Cells of the matrices in which they meet.
CELLS = 1 << 18
#: Below all cosines: of a zero vector, of a region that is left out.
NO_COSINE, TAKEN = -2.0, -3.0


def _nearest_regions(k: int):
    def run(p: pd.DataFrame, q: pd.DataFrame) -> pd.DataFrame:
        if not len(p) or not len(q):
            return pd.DataFrame([], columns=["query_id", "region", "cosine"])
        p = p.sort_values("__r", kind="stable")
        names, first = np.unique(p["__r"].to_numpy(), return_index=True)
        z, x, own = _matrix(p["z"]), _matrix(q["q"]), q["__qr"].to_numpy()
        size_z, size_x = (np.sqrt(_products(m, m)) for m in (z, x))
        out = []
        step = max(1, CELLS // len(z))
        for n in range(0, len(x), step):
            some = x[n : n + step]
            size = size_x[n : n + step, None] * size_z[None, :]
            with np.errstate(divide="ignore", invalid="ignore"):
                c = np.where(size > 0, _products(some[:, None, :], z[None, :, :]) / size, NO_COSINE)
            best = np.maximum.reduceat(c, first, axis=1)
            best[own[n : n + step, None] == names[None, :]] = TAKEN
            row = np.arange(len(some))
            for _ in range(min(k, len(names))):
                at = best.argmax(axis=1)  # names are in order: ties go to the smaller
                top = best[row, at]
                left = top > TAKEN
                out.append((n + row[left], at[left], top[left]))
                best[row, at] = TAKEN
        row, at, best = (np.concatenate([o[i] for o in out]) for i in range(3))
        return pd.DataFrame({"query_id": pd.Series(q["query_id"].to_numpy()[row], dtype=q["query_id"].to_numpy().dtype), "region": names[at], "cosine": np.where(best > NO_COSINE, best, np.nan)})  # not a number becomes null

    return run


def _products(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Sums of products over the last axis, added one component after the other."""
    out = np.zeros(np.broadcast_shapes(a.shape[:-1], b.shape[:-1]))
    for i in range(a.shape[-1]):
        out += a[..., i] * b[..., i]
    return out


def place_profile(members: DataFrame, poi: DataFrame, level: int = 1) -> DataFrame:
    """place_id, label, n, share, entropy and purity of the place at one category level."""
    rows = members.select("place_id", "poi_id").join(poi.select("poi_id", category.level(F.col("category_path"), level).alias("label")), "poi_id").filter("label is not null")
    n = rows.groupBy("place_id", "label").agg(F.count(F.lit(1)).alias("n"))
    w = Window.partitionBy("place_id")
    n = n.withColumn("share", F.col("n") / F.sum("n").over(w))
    return n.withColumns({"entropy": F.sum(-F.col("share") * F.log("share")).over(w), "purity": F.max("share").over(w)})


def place_contiguity(edges: DataFrame, members: DataFrame) -> DataFrame:
    """place_id, n_inside, n_touching, inside_share: how many of the edges at a place's points stay inside it."""
    m = members.select("poi_id", "place_id")
    met = edges.join(m.select(F.col("poi_id").alias("src"), F.col("place_id").alias("p")), "src").join(m.select(F.col("poi_id").alias("dst"), F.col("place_id").alias("q")), "dst")
    ends = met.select(F.explode(F.array_distinct(F.array("p", "q"))).alias("place_id"), (F.col("p") == F.col("q")).alias("inside"))
    return ends.groupBy("place_id").agg(F.sum(F.col("inside").cast("long")).alias("n_inside"), F.count(F.lit(1)).alias("n_touching")).withColumn("inside_share", F.col("n_inside") / F.col("n_touching"))


def place_fragments(edges: DataFrame, members: DataFrame) -> DataFrame:
    """place_id, fragments: connected parts of a place under the edges inside it (once or more, in any direction).

    No part leaves its place, so a task finds those of whole places, which come to it in order: what a spanning forest of the inner edges links is taken off the number of points.
    """
    m = members.select("poi_id", "place_id")
    met = edges.select("src", "dst").join(m.select(F.col("poi_id").alias("src"), F.col("place_id").alias("p")), "src").join(m.select(F.col("poi_id").alias("dst"), F.col("place_id").alias("q")), "dst").filter("p = q")
    inner = met.select(F.col("p").alias("place_id"), "src", "dst").repartition("place_id").sortWithinPartitions("place_id")
    links = inner.mapInPandas(_count_links, "place_id string, links long")
    n = m.groupBy("place_id").agg(F.count(F.lit(1)).alias("n"))
    return n.join(links, "place_id", "left").select("place_id", (F.col("n") - F.coalesce("links", F.lit(0))).alias("fragments"))


def _count_links(batches):
    """Links of a spanning forest of every place's edges; a place that may go on in the next batch waits for it."""
    held: list[pd.DataFrame] = []
    for pdf in batches:
        if not len(pdf):
            continue
        last = pdf["place_id"].iloc[-1]
        if pdf["place_id"].iloc[0] != last:
            going = (pdf["place_id"] == last).to_numpy()
            yield _links(pd.concat([*held, pdf[~going]]))
            held, pdf = [], pdf[going]
        elif held and held[0]["place_id"].iloc[0] != last:
            yield _links(pd.concat(held))
            held = []
        held.append(pdf)
    if held:
        yield _links(pd.concat(held))


def _links(pdf: pd.DataFrame) -> pd.DataFrame:
    place, names = pd.factorize(pdf["place_id"])
    nodes, at = np.unique(np.concatenate([pdf["src"].to_numpy(), pdf["dst"].to_numpy()]), return_inverse=True)
    place = np.concatenate([place, place])
    own, at = np.unique(place * len(nodes) + at, return_inverse=True)
    root = least_labels(at[: len(pdf)], at[len(pdf) :], len(own))
    linked = np.bincount(own[root != np.arange(len(own))] // len(nodes), minlength=len(names))
    return pd.DataFrame({"place_id": names, "links": linked})
