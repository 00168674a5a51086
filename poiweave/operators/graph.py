"""Proximity graphs: exact k nearest neighbours, edge weights, normalised adjacency, diagnostics."""

from __future__ import annotations

from collections.abc import Sequence

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import geo, vectors
from .session import cut, cut_and_release, small, spread


def knn_brute(poi: DataFrame, k: int = 5, metric: str = "haversine", block: int = 4096) -> DataFrame:
    """Directed edges (state_id, src, dst, dist_m, rank) by plain comparison, without tiles: only points that latitude or longitude alone puts too far are left out.

    A state is cut by latitude into strips of about ``block`` points. A first look inside each strip bounds the distance of its points' k-th neighbours; the strips within that
    bound then meet it in one task, which finds the neighbours of all its points. So rows are shuffled once for each strip that asks for them, pairs never.
    """
    if metric not in ("haversine", "planar"):
        raise ValueError(f"unknown metric {metric}")
    state = Window.partitionBy("state_id")
    place, n = F.row_number().over(state.orderBy("lat", "poi_id")) - 1, F.count(F.lit(1)).over(state)
    strips = F.greatest(F.lit(1), F.floor(n / block))
    rows = cut(poi.select("state_id", "poi_id", "lat", "lon").withColumn("strip", F.floor(place * strips / n).cast("long")))
    reach = cut(spread(rows, "state_id", "strip").groupBy("state_id", "strip").applyInPandas(_strip_reach(k, metric), "state_id int, strip long, low double, high double, bottom double, top double"))
    count = reach.count()
    other = reach.select("state_id", F.col("strip").alias("other"), F.col("low").alias("o_low"), F.col("high").alias("o_high"))
    asked = reach.join(other, "state_id").filter("o_high >= bottom and o_low <= top").select("state_id", "strip", "other", "bottom", "top")
    met = rows.withColumnRenamed("strip", "other").join(small(asked, count, 100_000), ["state_id", "other"]).filter("lat >= bottom and lat <= top")
    met = met.select("state_id", "strip", "poi_id", "lat", "lon", (F.col("other") == F.col("strip")).alias("own"))
    found = spread(met, "state_id", "strip").groupBy("state_id", "strip").applyInPandas(_strip_neighbours(k, metric), "state_id int, src long, dst long, rank int, a double, b double, c double, d double")
    return found.select("state_id", "src", "dst", geo.distance(metric, F.col("a"), F.col("b"), F.col("c"), F.col("d")).alias("dist_m"), "rank")


#: Points of a strip that look for neighbours at once.
LOOK = 64


class _Strip:
    """Points in the order of their longitude, with a measure that grows with the distance: the squared chord of the unit sphere, or the squared angle on the plane."""

    def __init__(self, pdf: pd.DataFrame, metric: str):
        self.metric = metric
        pdf = pdf.sort_values(["lon", "poi_id"])
        self.ids, self.lat, self.lon = pdf["poi_id"].to_numpy(), pdf["lat"].to_numpy(), pdf["lon"].to_numpy()
        self.own = np.flatnonzero(pdf["own"].to_numpy()) if "own" in pdf else np.arange(len(pdf))
        self.y, self.x = np.radians(self.lat), np.radians(self.lon)
        self.unit = np.cos(self.y) * np.cos(self.x), np.cos(self.y) * np.sin(self.x), np.sin(self.y)
        self.flattest = max(float(np.cos(self.y).min()), 1e-9) if len(self.y) else 1.0

    def measure(self, i: np.ndarray, at: slice) -> np.ndarray:
        if self.metric == "haversine":
            out = sum((u[i][:, None] - u[at][None, :]) ** 2 for u in self.unit)
        else:
            middle = np.cos((self.y[i][:, None] + self.y[at][None, :]) / 2)
            out = ((self.x[at][None, :] - self.x[i][:, None]) * middle) ** 2 + (self.y[at][None, :] - self.y[i][:, None]) ** 2
        out[self.ids[i][:, None] == self.ids[at][None, :]] = np.inf
        return out

    def looks(self, k: int):
        """Own points, some at a time, each with the measure within which its ``k`` nearest lie (infinite if there are fewer)."""
        for n in range(0, len(self.own), LOOK):
            i = self.own[n : n + LOOK]
            m = self.measure(i, slice(max(0, i[0] - LOOK), i[-1] + 1 + LOOK))
            yield i, np.partition(m, k - 1, axis=1)[:, k - 1] if m.shape[1] >= k else np.full(len(i), np.inf)

    def angle(self, measure: float) -> float:
        """Radians within which a measure stays, with room for rounding."""
        return 4.0 if not np.isfinite(measure) else 2 * float(np.arcsin(min(1.0, np.sqrt(measure) / 2))) * (1 + 1e-9) + 1e-12 if self.metric == "haversine" else float(np.sqrt(measure)) * (1 + 1e-9) + 1e-12

    def window(self, i: np.ndarray, measure: float) -> slice:
        """The points whose longitude lets them be as near."""
        wide = np.sin(min(self.angle(measure) / 2, np.pi / 2)) / self.flattest if self.metric == "haversine" else self.angle(measure) / 2 / self.flattest
        if wide >= 1:
            return slice(0, len(self.ids))
        step = np.degrees(2 * np.arcsin(wide)) * (1 + 1e-9) + 1e-9
        low, high = self.lon[i[0]] - step, self.lon[i[-1]] + step
        if low < -180 or high > 180:  # the other side of the date line may be as near
            return slice(0, len(self.ids))
        return slice(int(np.searchsorted(self.lon, low, "left")), int(np.searchsorted(self.lon, high, "right")))

    def metres(self, i: np.ndarray, j: np.ndarray) -> np.ndarray:
        dy, dx = np.radians(self.lat[j] - self.lat[i]), np.radians(self.lon[j] - self.lon[i])
        if self.metric == "haversine":
            a = np.sin(dy / 2) ** 2 + np.cos(self.y[i]) * np.cos(self.y[j]) * np.sin(dx / 2) ** 2
            return 2 * geo.EARTH_M * np.arcsin(np.sqrt(np.minimum(1.0, a)))
        return geo.EARTH_M * np.sqrt((dx * np.cos(np.radians((self.lat[i] + self.lat[j]) / 2))) ** 2 + dy**2)


def _strip_reach(k: int, metric: str):
    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        s = _Strip(pdf, metric)
        far = np.degrees(s.angle(max(float(m.max()) for _, m in s.looks(k))))
        low, high = s.lat.min(), s.lat.max()
        return pd.DataFrame({"state_id": pdf["state_id"].iloc[:1], "strip": pdf["strip"].iloc[:1], "low": low, "high": high, "bottom": low - far, "top": high + far})

    return run


def _strip_neighbours(k: int, metric: str):
    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        s, out = _Strip(pdf, metric), []
        for i, bound in s.looks(k):
            at = s.window(i, float(bound.max()))
            m = s.measure(i, at)
            kth = np.partition(m, k - 1, axis=1)[:, k - 1] if m.shape[1] >= k else np.full(len(i), np.inf)
            row, column = np.nonzero((m <= (kth * (1 + 1e-7) + 1e-18)[:, None]) & np.isfinite(m))
            src, dst = i[row], column + at.start
            order = np.lexsort((s.ids[dst], s.metres(src, dst), row))
            row, src, dst = row[order], src[order], dst[order]
            rank = np.arange(len(row)) - np.searchsorted(row, row, "left") + 1
            keep = rank <= k
            out.append((src[keep], dst[keep], rank[keep]))
        src, dst, rank = (np.concatenate([o[n] for o in out]) if out else np.zeros(0, int) for n in range(3))
        return pd.DataFrame({"state_id": np.full(len(src), pdf["state_id"].iloc[0]), "src": s.ids[src], "dst": s.ids[dst], "rank": rank, "a": s.lat[src], "b": s.lon[src], "c": s.lat[dst], "d": s.lon[dst]})

    return run


#: Halvings of the first tile width in dense parts: 0.05 degrees become about ten metres.
FINEST = 9


def tile_levels(base: DataFrame, degrees: float, most_points: int) -> DataFrame:
    """``base`` (state_id, poi_id, lat, lon) plus ``level``: how often a point's tile is halved until it holds at most ``most_points``.

    Counts of all levels come from one aggregation; only crowded tiles are joined back, so a city gets small tiles and the country around keeps large ones.
    """
    tile = lambda c: F.floor(F.col(c) * F.pow(F.lit(2.0), F.col("at")) / degrees).cast("long")
    every = base.withColumn("at", F.explode(F.sequence(F.lit(0), F.lit(FINEST - 1)))).withColumns({"tx": tile("lon"), "ty": tile("lat")})
    full = cut(every.groupBy("state_id", "at", "tx", "ty").agg(F.count(F.lit(1)).alias("n")).filter(F.col("n") > most_points).drop("n"))
    crowded = every.join(small(full, full.count()), ["state_id", "at", "tx", "ty"], "left_semi").groupBy("poi_id").agg(F.count(F.lit(1)).cast("int").alias("level"))
    return base.join(crowded, "poi_id", "left").withColumn("level", F.coalesce("level", F.lit(0)))


def knn_tiled(poi: DataFrame, k: int = 5, metric: str = "haversine", degrees: float = 0.05, most_points: int = 16, most_rounds: int = 40) -> DataFrame:
    """The same edges by tiles. Each open point looks at its tile and the eight around it, of a width that suits its surroundings (:func:`tile_levels`); it is final
    once ``k`` points are no farther than the border of that area (taken at the area's highest latitude, where a
    degree of longitude is shortest). Only open points go to the next round, with tiles twice as
    wide; a point whose area holds its whole state is final. Of points at one place only the ``k + 1`` smallest ids can be anybody's neighbours, so others
    are not looked at: a mall of coincident points costs no more than its size.
    """
    base = cut(poi.select("state_id", "poi_id", "lat", "lon"))
    extent = base.groupBy("state_id").agg(F.min("lat").alias("b_lat"), F.max("lat").alias("t_lat"), F.min("lon").alias("l_lon"), F.max("lon").alias("r_lon"))
    extent = small(extent, extent.count(), 100_000)
    at_place = F.row_number().over(Window.partitionBy("state_id", "lat", "lon").orderBy("poi_id"))
    shown = cut(base.withColumn("__n", at_place).filter(F.col("__n") <= k + 1).drop("__n"))
    # hidden points take the level of those shown at their place
    level = tile_levels(shown, degrees, most_points).groupBy("state_id", "lat", "lon").agg(F.max("level").alias("level"))
    open_, done = cut(base.join(level, ["state_id", "lat", "lon"])), None
    for _ in range(most_rounds):
        levels = [r[0] for r in open_.select("level").distinct().collect()]  # at most FINEST and one more each round
        if not levels:
            return done if done is not None else _no_edges(base)
        size = F.lit(float(degrees)) / F.pow(F.lit(2.0), F.col("level"))
        tile = lambda c: F.floor(F.col(c) / size).cast("long")  # noqa: E731, B023
        here = open_.withColumns({"cx": tile("lon"), "cy": tile("lat")})
        here = here.withColumn("near", F.explode(geo.ring(F.col("cx"), F.col("cy"), 1))).select("*", F.col("near.x").alias("tx"), F.col("near.y").alias("ty")).drop("near")
        there = shown.withColumn("level", F.explode(F.array(*map(F.lit, levels)))).withColumns({"tx": tile("lon"), "ty": tile("lat")})
        there = there.select("state_id", "level", "tx", "ty", F.col("poi_id").alias("dst"), F.col("lat").alias("lat2"), F.col("lon").alias("lon2"))
        if done is not None:  # few points are left: only their tiles matter
            asked = cut(here.select("state_id", "level", "tx", "ty").distinct())
            there = there.join(small(asked, asked.count()), ["state_id", "level", "tx", "ty"], "left_semi")
        south, north = F.col("lat") - (F.col("cy") - 1) * size, (F.col("cy") + 2) * size - F.col("lat")
        west, east = F.col("lon") - (F.col("cx") - 1) * size, (F.col("cx") + 2) * size - F.col("lon")
        top = F.least(F.lit(89.0), F.greatest(F.abs((F.col("cy") - 1) * size), F.abs((F.col("cy") + 2) * size)))
        # the nearest point of a meridian at angle a is asin(sin(a) cos(lat)) away, of a parallel its latitude difference
        side = F.asin(F.sin(F.radians(F.least(west, east, F.lit(90.0)))) * F.cos(F.radians(top))) * geo.EARTH_M * (1.0 if metric == "haversine" else 0.999)
        here = here.withColumn("reach", F.least(side, F.radians(F.least(south, north)) * geo.EARTH_M)).join(extent, "state_id")
        whole = ((F.col("cy") - 1) * size <= F.col("b_lat")) & ((F.col("cy") + 2) * size > F.col("t_lat")) & ((F.col("cx") - 1) * size <= F.col("l_lon")) & ((F.col("cx") + 2) * size > F.col("r_lon"))
        here = here.withColumn("whole", whole).select("state_id", "poi_id", "lat", "lon", "level", "tx", "ty", "reach", "whole")
        pairs = here.join(there, ["state_id", "level", "tx", "ty"]).filter("poi_id <> dst").withColumn("dist_m", geo.distance(metric, F.col("lat"), F.col("lon"), F.col("lat2"), F.col("lon2")))
        near = pairs.filter((F.col("dist_m") <= F.col("reach")) | F.col("whole"))
        rank = F.row_number().over(Window.partitionBy("poi_id").orderBy("dist_m", "dst"))
        kept = cut(near.select("state_id", "poi_id", "dst", "dist_m", "whole").withColumn("rank", rank).filter(F.col("rank") <= k))
        settled = kept.filter((F.col("rank") == k) | F.col("whole")).select("poi_id").distinct()
        got = kept.join(settled, "poi_id", "left_semi").select("state_id", F.col("poi_id").alias("src"), "dst", "dist_m", "rank")
        done = got if done is None else done.unionByName(got)
        alone = here.filter("whole").select("poi_id").distinct()  # also those that have no neighbours at all
        open_ = cut(open_.join(settled, "poi_id", "left_anti").join(alone, "poi_id", "left_anti").withColumn("level", F.col("level") - 1))
    raise RuntimeError("neighbour search did not settle")


def _no_edges(base: DataFrame) -> DataFrame:
    return base.filter("false").select("state_id", F.col("poi_id").alias("src"), F.col("poi_id").alias("dst"), F.col("lat").alias("dist_m"), F.lit(1).alias("rank"))


def symmetrise(directed: DataFrame, how: str = "union") -> DataFrame:
    """Undirected edges (src < dst): ``union`` of both directions, or ``mutual`` ones only; ``directed`` leaves them."""
    if how == "directed":
        return directed
    pairs = directed.groupBy("state_id", F.least("src", "dst").alias("a"), F.greatest("src", "dst").alias("b")).agg(F.min("dist_m").alias("dist_m"), F.count(F.lit(1)).alias("times"))
    if how == "mutual":
        pairs = pairs.filter("times = 2")
    elif how != "union":
        raise ValueError(how)
    return pairs.select("state_id", F.col("a").alias("src"), F.col("b").alias("dst"), "dist_m")


def knn_graph(poi: DataFrame, k: int = 5, metric: str = "haversine", how: str = "union", method: str = "strips") -> DataFrame:
    """Undirected edges of the nearest neighbours, found in strips (:func:`knn_brute`) or by tiles (``tiled``)."""
    return symmetrise((knn_tiled if method == "tiled" else knn_brute)(poi, k, metric), how)


def coincident_points(poi: DataFrame) -> DataFrame:
    """Points that share a place with one of smaller id: poi_id, representative. A triangulation uses representatives only."""
    spot = Window.partitionBy("state_id", "lat", "lon")
    return poi.withColumn("representative", F.min("poi_id").over(spot)).filter("representative <> poi_id").select("state_id", "poi_id", "representative")


def with_regions(edges: DataFrame, poi: DataFrame) -> DataFrame:
    """Edges plus the regions of both ends."""
    r = poi.select("poi_id", "zip_id")
    out = edges.join(r.select(F.col("poi_id").alias("src"), F.col("zip_id").alias("src_zip")), "src").join(r.select(F.col("poi_id").alias("dst"), F.col("zip_id").alias("dst_zip")), "dst")
    return out.withColumn("same_region", F.col("src_zip") == F.col("dst_zip"))


def region_scale(poi: DataFrame, edges: DataFrame | None = None, how: str = "bbox_diagonal") -> DataFrame:
    """zip_id, scale, n_r: the length that distances of a region are measured against.

    ``bbox_diagonal`` bounds every distance inside the region; ``max_edge``, ``mean_edge`` and ``p95_edge`` come from its inner edges (regioned
    with :func:`with_regions`).
    """
    n = poi.groupBy("zip_id").agg(F.count(F.lit(1)).alias("n_r"), F.min("lat").alias("a"), F.max("lat").alias("b"), F.min("lon").alias("c"), F.max("lon").alias("d"))
    if how == "bbox_diagonal":
        return n.select("zip_id", geo.haversine_m(F.col("a"), F.col("c"), F.col("b"), F.col("d")).alias("scale"), "n_r")
    measure = {"max_edge": F.max("dist_m"), "mean_edge": F.avg("dist_m"), "p95_edge": F.percentile("dist_m", 0.95)}[how]
    inner = edges.filter("same_region").groupBy(F.col("src_zip").alias("zip_id")).agg(measure.alias("scale"))
    return n.select("zip_id", "n_r").join(inner, "zip_id", "left").select("zip_id", F.coalesce("scale", F.lit(0.0)).alias("scale"), "n_r")


def edge_weight(edges: DataFrame, scale: DataFrame, cross: float = 0.4, power: float = 1.5, cross_scale: str = "max", clip: bool = True, unit: float = 1.0) -> DataFrame:
    """Regioned edges plus ``w_raw``: log of (1 + L^power) / (1 + d^power), times ``cross`` for edges between regions.

    ``unit`` divides lengths (1: metres, 1000: kilometres). A cross edge is measured against the larger, mean or smaller scale of its regions.
    """
    s = scale.select("zip_id", "scale")
    out = edges.join(s.select(F.col("zip_id").alias("src_zip"), F.col("scale").alias("s1")), "src_zip").join(s.select(F.col("zip_id").alias("dst_zip"), F.col("scale").alias("s2")), "dst_zip")
    length = {"max": F.greatest("s1", "s2"), "min": F.least("s1", "s2"), "mean": (F.col("s1") + F.col("s2")) / 2}[cross_scale] / unit
    raw = F.log1p(F.pow(length, power)) - F.log1p(F.pow(F.col("dist_m") / unit, power))
    raw = F.greatest(raw, F.lit(0.0)) if clip else raw
    return out.withColumn("w_raw", raw * F.when(F.col("same_region"), 1.0).otherwise(cross)).drop("s1", "s2")


def scale_weights(edges: DataFrame, how: str = "minmax") -> DataFrame:
    """Weights in [0, 1] by each region's incident edges; a cross edge takes the mean of its two values. Column ``w``."""
    if how == "none":
        return edges.withColumn("w", F.col("w_raw"))
    ends = edges.select(F.explode(F.array_distinct(F.array("src_zip", "dst_zip"))).alias("zip_id"), "w_raw")
    bounds = ends.groupBy("zip_id").agg(F.min("w_raw").alias("lo"), F.max("w_raw").alias("hi"))
    out = edges
    for side in ("src", "dst"):
        out = out.join(bounds.select(F.col("zip_id").alias(f"{side}_zip"), F.col("lo").alias(f"{side}_lo"), F.col("hi").alias(f"{side}_hi")), f"{side}_zip")

    def one(side: str):
        lo, hi = F.col(f"{side}_lo") if how == "minmax" else F.lit(0.0), F.col(f"{side}_hi")
        return F.when(hi > lo, (F.col("w_raw") - lo) / (hi - lo)).otherwise(1.0)

    return out.withColumn("w", (one("src") + one("dst")) / 2).drop("src_lo", "src_hi", "dst_lo", "dst_hi")


def normalise_adjacency(edges: DataFrame, poi: DataFrame, how: str = "sym") -> DataFrame:
    """(dst, src, w): both directions and a loop at every point, divided by degrees (``sym``: by both roots, ``row``: by the target's)."""
    live = edges.filter("w > 0")
    both = live.select("src", "dst", "w").unionByName(live.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "w"))
    both = both.unionByName(poi.select(F.col("poi_id").alias("src"), F.col("poi_id").alias("dst"), F.lit(1.0).alias("w")))
    degree = both.groupBy("dst").agg(F.sum("w").alias("deg"))
    out = both.join(degree, "dst")
    if how == "row":
        return out.select("dst", "src", (F.col("w") / F.col("deg")).alias("w"))
    out = out.join(degree.select(F.col("dst").alias("src"), F.col("deg").alias("deg_src")), "src")
    return out.select("dst", "src", (F.col("w") / F.sqrt(F.col("deg") * F.col("deg_src"))).alias("w"))


def unit_weights(edges: DataFrame) -> DataFrame:
    return edges.withColumn("w", F.lit(1.0))


def degree_histogram(edges: DataFrame) -> DataFrame:
    ends = edges.select(F.explode(F.array("src", "dst")).alias("poi_id")).groupBy("poi_id").agg(F.count(F.lit(1)).alias("degree"))
    return ends.groupBy("degree").agg(F.count(F.lit(1)).alias("points"))


#: Values that are sorted on the driver to find a quantile among them, and the steps of a histogram that leads there.
SORTED, STEPS = 100_000, 4_096


def quantiles(values: DataFrame, column: str, shares: Sequence[float]) -> list[float | None]:
    """Exact quantiles of a column, interpolated between neighbours in order like ``F.percentile``, which would hold all distinct values in one task's memory.

    Histograms of ``STEPS`` equal steps narrow the range that holds a rank until few values, or one value many times, are left. ``values`` is read several times.
    """
    x = F.col(column).cast("double")
    values = values.filter(x.isNotNull()).select(x.alias("x"))
    n, low, high = values.agg(F.count(F.lit(1)), F.min("x"), F.max("x")).first()
    if not n:
        return [None for _ in shares]
    places = [share * (n - 1) for share in shares]
    wanted = sorted({int(np.floor(p)) for p in places} | {int(np.ceil(p)) for p in places})
    found, open_ = {}, [(low, high, 0, n, wanted)]  # ranks in [before, before + count) lie between low and high
    while open_:
        low, high, before, count, ranks = open_.pop()
        if low == high:
            found |= dict.fromkeys(ranks, low)
            continue
        inside = values.filter(F.col("x").between(low, high))
        if count <= SORTED:
            order = np.sort(np.array([r[0] for r in inside.collect()]))
            found |= {r: float(order[r - before]) for r in ranks}
            continue
        step = F.least(F.floor((F.col("x") - low) / (high - low) * STEPS), F.lit(STEPS - 1))
        for _, m, a, b in sorted(inside.groupBy(step.alias("step")).agg(F.count(F.lit(1)), F.min("x"), F.max("x")).collect()):
            if own := [r for r in ranks if before <= r < before + m]:
                open_.append((a, b, before, m, own))
            before += m
    return [found[int(np.floor(p))] + (found[int(np.ceil(p))] - found[int(np.floor(p))]) * (p - np.floor(p)) for p in places]


def graph_diagnostics(edges: DataFrame) -> DataFrame:
    """One row: edges, cross-region share, zero-weight share, length quantiles. The edges are written once."""
    edges = cut_and_release(edges.select("dist_m", "same_region", "w"))
    median, p95 = (F.lit(q).cast("double") for q in quantiles(edges, "dist_m", (0.5, 0.95)))
    return edges.agg(
        F.count(F.lit(1)).alias("edges"),
        F.avg(F.when(F.col("same_region"), 0.0).otherwise(1.0)).alias("cross_share"),
        F.avg(F.when(F.col("w") == 0, 1.0).otherwise(0.0)).alias("zero_share"),
    ).select("edges", "cross_share", "zero_share", median.alias("median_m"), p95.alias("p95_m"))


def smoothing_score(edges: DataFrame, h: DataFrame) -> DataFrame:
    """Mean cosine between neighbours' vectors: how alike propagation has made them."""
    x = h.select(F.col("poi_id").alias("src"), F.col("h").alias("h1")), h.select(F.col("poi_id").alias("dst"), F.col("h").alias("h2"))
    pairs = edges.join(x[0], "src").join(x[1], "dst")
    return pairs.agg(F.avg(vectors.cosine(F.col("h1"), F.col("h2"))).alias("score"), F.count(F.lit(1)).alias("edges"))
