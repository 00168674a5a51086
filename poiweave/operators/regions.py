"""Region vectors, roll-ups and region adjacency."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import vectors


def region_embedding(places: DataFrame, keys: Sequence[str], d: int, weights: str = "n_poi", top_places: int | None = None) -> DataFrame:
    """keys, n_places, n_poi, z: the mean of a region's places by size (``n_poi``) or unweighted (``none``); of its largest ``top_places`` only if given."""
    if top_places is not None:
        rank = F.row_number().over(Window.partitionBy(*keys).orderBy(F.desc("n_poi"), "place_id"))
        places = places.withColumn("__rn", rank).filter(F.col("__rn") <= top_places)
    w = F.col("n_poi").cast("double") if weights == "n_poi" else F.lit(1.0)
    sums = places.groupBy(*keys).agg(F.count(F.lit(1)).alias("n_places"), F.sum("n_poi").alias("n_poi"), F.sum(w).alias("__w"), *vectors.sums("z", d, w))
    return sums.select(*keys, "n_places", "n_poi", vectors.gathered(d, F.col("__w")).alias("z"))


def region_mean(h: DataFrame, keys: Sequence[str], d: int) -> DataFrame:
    """The same vector without clustering: with all places kept, the mean by size is the mean of the points."""
    return h.groupBy(*keys).agg(F.count(F.lit(1)).alias("n_poi"), *vectors.means("h", d)).select(*keys, "n_poi", vectors.gathered(d).alias("z"))


def region_matrix(places: DataFrame, keys: Sequence[str]) -> DataFrame:
    """All place vectors of a region in the order of their ids."""
    rows = places.groupBy(*keys).agg(F.array_sort(F.collect_list(F.struct("place_id", "z"))).alias("m"))
    return rows.select(*keys, F.col("m.place_id").alias("place_ids"), F.col("m.z").alias("matrix"))


def rollup_embeddings(rows: DataFrame, levels: Sequence[str], d: int, how: str = "rollup") -> DataFrame:
    """Vectors of all levels at once: sums and counts add up, so one ``rollup`` or ``cube`` aggregation serves all. Needs n_poi, z."""
    grouped = rows.rollup(*levels) if how == "rollup" else rows.cube(*levels)
    w = F.col("n_poi").cast("double")
    out = grouped.agg(F.grouping_id().alias("gid"), F.sum("n_poi").alias("n_poi"), F.sum(w).alias("__w"), *vectors.sums("z", d, w))
    return out.select(*levels, "gid", "n_poi", vectors.gathered(d, F.col("__w")).alias("z"))


def region_adjacency(regions: DataFrame, contiguity: str = "queen", level: str = "zip_id", tolerance: float = 1e-7, within: Sequence[str] = ()) -> DataFrame:
    """(a, b), a < b, of regions whose polygons touch: in a point (``queen``), or along a line (``rook``). ``regions`` has ``level``, polygon (lon, lat) and the columns
    ``within``, if any: only regions that agree in them are compared (states whose squares overlap share no neighbours).

    Sides of any two polygons meet in tiles as wide as a usual side; two sides touch where an end of one lies within ``tolerance`` degrees of the other or they cross, and
    share a line where both ends of the part that overlaps do. Vertices of neighbours need not agree.
    """
    ring = F.transform("polygon", lambda p, i: F.struct(p["lon"].alias("x1"), p["lat"].alias("y1"), F.element_at("polygon", (i + 1) % F.size("polygon") + 1)["lon"].alias("x2"), F.element_at("polygon", (i + 1) % F.size("polygon") + 1)["lat"].alias("y2")))
    sides = regions.select(*within, F.col(level).alias("id"), F.explode(ring).alias("s")).select(*within, "id", "s.*")
    usual = sides.agg(F.percentile_approx(F.greatest(F.abs(F.col("x2") - F.col("x1")), F.abs(F.col("y2") - F.col("y1"))), 0.5)).first()[0]
    width = max(usual or 0.0, 100 * tolerance)
    reach = lambda a, b: F.sequence(F.floor((F.least(a, b) - tolerance) / width), F.floor((F.greatest(a, b) + tolerance) / width))
    tiled = sides.withColumn("tx", F.explode(reach("x1", "x2"))).withColumn("ty", F.explode(reach("y1", "y2")))
    p = tiled.select(*within, "tx", "ty", F.col("id").alias("a"), *(F.col(c).alias(f"p{c}") for c in ("x1", "y1", "x2", "y2")))
    q = tiled.select(*within, "tx", "ty", F.col("id").alias("b"), *(F.col(c).alias(f"q{c}") for c in ("x1", "y1", "x2", "y2")))
    met = p.join(q, [*within, "tx", "ty"]).filter("a < b")
    for x in ("x", "y"):  # most pairs of a tile are apart: their bounds tell at once
        low, high = (lambda s, f=f: f(f"{s}{x}1", f"{s}{x}2") for f in (F.least, F.greatest))  # noqa: B023
        met = met.filter((low("p") <= high("q") + tolerance) & (low("q") <= high("p") + tolerance))

    def along(x: str, y: str, s: str) -> tuple:
        """Where the foot of a point falls on side ``s`` (0 to 1), and the point's squared distance from the side's line."""
        dx, dy = F.col(f"{s}x2") - F.col(f"{s}x1"), F.col(f"{s}y2") - F.col(f"{s}y1")
        ex, ey, size = F.col(x) - F.col(f"{s}x1"), F.col(y) - F.col(f"{s}y1"), dx * dx + dy * dy
        return (ex * dx + ey * dy) / size, F.pow(ex * dy - ey * dx, 2) / size, F.sqrt(size)

    def near(x: str, y: str, s: str):
        t, off, _ = along(x, y, s)
        inside = F.greatest(F.lit(0.0), F.least(F.lit(1.0), t))
        gx, gy = F.col(x) - F.col(f"{s}x1") - inside * (F.col(f"{s}x2") - F.col(f"{s}x1")), F.col(y) - F.col(f"{s}y1") - inside * (F.col(f"{s}y2") - F.col(f"{s}y1"))
        return gx * gx + gy * gy <= tolerance * tolerance

    def turn(s: str, x: str, y: str):
        return F.signum((F.col(f"{s}x2") - F.col(f"{s}x1")) * (F.col(y) - F.col(f"{s}y1")) - (F.col(f"{s}y2") - F.col(f"{s}y1")) * (F.col(x) - F.col(f"{s}x1")))

    crossing = (turn("p", "qx1", "qy1") * turn("p", "qx2", "qy2") < 0) & (turn("q", "px1", "py1") * turn("q", "px2", "py2") < 0)
    touch = near("px1", "py1", "q") | near("px2", "py2", "q") | near("qx1", "qy1", "p") | near("qx2", "qy2", "p") | crossing
    (t1, off1, size), (t2, off2, _) = along("px1", "py1", "q"), along("px2", "py2", "q")
    shared = (F.least(F.lit(1.0), F.greatest(t1, t2)) - F.greatest(F.lit(0.0), F.least(t1, t2))) * size
    line = (F.greatest(off1, off2) <= tolerance * tolerance) & (shared > 2 * tolerance)
    return met.filter(line if contiguity == "rook" else touch).select("a", "b").distinct()


def region_cross_edges(edges: DataFrame) -> DataFrame:
    """Regions joined by a graph edge, with the number and weight of such edges (edges need src_zip, dst_zip, w)."""
    cross = edges.filter("src_zip <> dst_zip")
    return cross.groupBy(F.least("src_zip", "dst_zip").alias("a"), F.greatest("src_zip", "dst_zip").alias("b")).agg(F.count(F.lit(1)).alias("n_edges"), F.sum("w").alias("w"))
