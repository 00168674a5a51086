"""Linear propagation of features over a normalised graph, and its factored form."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import vectors
from .session import cut, cut_and_release, small


def packed(a_hat: DataFrame) -> DataFrame:
    """src, dst, w: all arcs that leave a point in one row, with arrays of their targets and weights."""
    arcs = a_hat.groupBy("src").agg(F.collect_list(F.struct("dst", "w")).alias("arcs"))
    return arcs.select("src", F.col("arcs.dst").alias("dst"), F.col("arcs.w").alias("w"))


def _unpacked(met: DataFrame, *columns: str) -> DataFrame:
    """poi_id (the target), w and ``columns`` of every arc in the rows of :func:`packed`."""
    arc = F.explode(F.arrays_zip("dst", "w")).alias("arc")
    return met.select(arc, *columns).select(F.col("arc.dst").alias("poi_id"), F.col("arc.w").alias("w"), *columns)


def _summed(met: DataFrame, d: int) -> DataFrame:
    """poi_id, h: weighted sums of what every point has met (poi_id, w, h)."""
    return met.groupBy("poi_id").agg(*vectors.sums("h", d, F.col("w"))).select("poi_id", vectors.gathered(d).alias("h"))


def hop(h: DataFrame, a_hat: DataFrame, d: int) -> DataFrame:
    """One multiplication by the graph: a join and one aggregation of ``d`` scalar sums."""
    return _summed(a_hat.join(h.withColumnRenamed("poi_id", "src"), "src").select(F.col("dst").alias("poi_id"), "w", "h"), d)


def needed_hops(alpha: Sequence[float]) -> int:
    """The highest hop that a coefficient asks for; the ones beyond are never computed."""
    return max((k for k, a in enumerate(alpha) if a != 0), default=-1)


def hops(h0: DataFrame, a_hat: DataFrame, k: int, d: int, keep: bool = True) -> list[DataFrame]:
    """H0 to Hk. ``keep`` materialises each hop, so that several uses and later hops do not compute it again; the graph is then written once, a row for each
    point, and what a hop shuffles is deleted before the next.
    """
    out = [h0]
    arcs = cut_and_release(packed(a_hat)) if keep and k else None
    for _ in range(k):
        if keep:
            out.append(cut_and_release(_hop_in_parts(arcs, out[-1], d)))
        else:
            out.append(hop(out[-1], a_hat, d))
    return out


#: Components that one shuffle of a materialised hop carries: wide vectors would fill the disk, as each travels along all arcs of its point.
WIDE = 10


def _hop_in_parts(arcs: DataFrame, h: DataFrame, d: int) -> DataFrame:
    """One hop over the rows of :func:`packed`, some components after another; of several parts each is written and its shuffle deleted before the next."""

    def part(i: int) -> DataFrame:
        n = min(WIDE, d - i)
        own = h.select(F.col("poi_id").alias("src"), (F.slice("h", i + 1, n) if n < d else F.col("h")).alias("h"))
        return _summed(_unpacked(arcs.join(own, "src"), "h"), n)

    if d <= WIDE:
        return part(0)
    begins = range(0, d, WIDE)
    whole = None
    for i in begins:
        own = cut_and_release(part(i)).withColumnRenamed("h", f"__h{i}")
        whole = own if whole is None else whole.join(own, "poi_id")
    return whole.select("poi_id", F.concat(*(f"__h{i}" for i in begins)).alias("h"))


def combine(levels: Sequence[DataFrame], alpha: Sequence[float], d: int) -> DataFrame:
    """Sum of alpha_k times H_k. All coefficients zero is an error: every vector would vanish."""
    used = [(a, x) for a, x in zip(alpha, levels, strict=False) if a != 0]
    if not used:
        raise ValueError("all coefficients are zero")
    terms = [x.select("poi_id", *(F.col("h")[i].cast("double").alias(f"__c{i}") for i in range(d)), F.lit(float(a)).alias("__a")) for a, x in used]
    if len(terms) == 1:
        return terms[0].select("poi_id", F.array(*(F.col("__a") * F.col(f"__c{i}") for i in range(d))).alias("h"))
    rows = terms[0]
    for t in terms[1:]:
        rows = rows.unionByName(t)
    return rows.groupBy("poi_id").agg(*(F.sum(F.col("__a") * F.col(f"__c{i}")).alias(f"__s{i}") for i in range(d))).select("poi_id", vectors.gathered(d).alias("h"))


def propagate(h0: DataFrame, a_hat: DataFrame, alpha: Sequence[float], d: int, keep: bool = False) -> DataFrame:
    """The propagated features: only the hops that ``alpha`` needs are computed, none for alpha = (a,).

    From the highest hop down, each step spreads what has been gathered so far and adds ``alpha_k`` times the features themselves in the same aggregation, so K hops
    take K aggregations and none is needed to combine them. ``keep`` materialises each step.
    """
    k = needed_hops(alpha)
    if k < 0:
        raise ValueError("all coefficients are zero")
    out = h0.select("poi_id", F.transform(F.col("h").cast("array<double>"), lambda x: x * float(alpha[k])).alias("h"))
    for a in reversed(alpha[:k]):
        met = a_hat.join(out.withColumnRenamed("poi_id", "src"), "src").select(F.col("dst").alias("poi_id"), "w", "h")
        if a:
            met = met.unionByName(h0.select("poi_id", F.lit(float(a)).alias("w"), F.col("h").cast("array<double>").alias("h")))
        out = met.groupBy("poi_id").agg(*vectors.sums("h", d, F.col("w"))).select("poi_id", vectors.gathered(d).alias("h"))
        out = cut(out) if keep else out
    return out


def propagate_factored(paths: DataFrame, table: DataFrame, a_hat: DataFrame, alpha: Sequence[float], d: int) -> DataFrame:
    """The same result by spreading category weights: a point's sums by path travel in one row, and path vectors are multiplied in at the end.

    ``paths`` has poi_id, path_key; pays off while a point's surroundings hold fewer distinct paths than ``d``. As in :func:`propagate`, each step from the highest hop down
    spreads what has been gathered and adds the points' own paths. Paths go by numbers; a point's arcs meet once and are summed by path where they meet.
    """
    k = needed_hops(alpha)
    if k < 0:
        raise ValueError("all coefficients are zero")
    coded = cut(table.withColumn("code", F.monotonically_increasing_id()))
    vectors_of = small(coded.select("code", F.col("v").alias("h")), n := coded.count(), 200_000)
    own = paths.select("poi_id", "path_key").join(small(coded.select("path_key", "code"), n, 200_000), "path_key").select("poi_id", F.array("code").alias("codes"), F.array(F.lit(1.0)).alias("xs"))
    arcs = cut_and_release(packed(a_hat)) if k else None
    own = cut_and_release(own) if k else own
    weighted = lambda a: own.select("poi_id", F.lit(float(a)).alias("w"), "codes", "xs")
    met = weighted(alpha[k])
    for n, a in enumerate(reversed(alpha[:k])):
        level = cut_and_release(_by_path(met).groupBy("poi_id").agg(F.collect_list(F.struct("code", "x")).alias("e")).select("poi_id", F.col("e.code").alias("codes"), F.col("e.x").alias("xs"))) if n else met.select("poi_id", "codes", F.transform("xs", lambda x: x * float(alpha[k])).alias("xs"))
        met = _unpacked(arcs.join(level.withColumnRenamed("poi_id", "src"), "src"), "codes", "xs")
        met = met.unionByName(weighted(a)) if a else met
    return _summed(_by_path(met).withColumnRenamed("x", "w").join(vectors_of, "code"), d)


def _by_path(met: DataFrame) -> DataFrame:
    """poi_id, code, x: the weighted sums by path of what a point has met (poi_id, w, codes, xs); rows are shuffled before they are taken apart."""
    entry = F.explode(F.arrays_zip("codes", "xs")).alias("e")
    return met.repartition("poi_id").select("poi_id", "w", entry).groupBy("poi_id", F.col("e.codes").alias("code")).agg(F.sum(F.col("w") * F.col("e.xs")).alias("x"))


def propagate_coded(coded: DataFrame, directed: DataFrame, table: DataFrame, alpha: tuple[float, float], d: int) -> DataFrame:
    """poi_id, h: ``alpha[0]`` times the features plus ``alpha[1]`` times one hop over the unweighted union graph, where features come from a table.

    ``coded`` has poi_id, code; ``table`` code, v; ``directed`` src, dst in any directions, once or more. Rows that move hold a code and a weight, not a vector; degrees are counted where a
    point's arcs meet, and a point's own is divided out at the end, so neither edges nor the adjacency are written.
    """
    pairs = directed.select(F.col("src").alias("u"), F.col("dst").alias("v"))
    both = pairs.unionByName(pairs.select(F.col("v").alias("u"), F.col("u").alias("v"))).unionByName(coded.select(F.col("poi_id").alias("u"), F.col("poi_id").alias("v")))
    arcs = both.repartition("u").distinct().withColumn("deg", F.count(F.lit(1)).over(Window.partitionBy("u")))
    w = F.lit(float(alpha[1])) / F.sqrt("deg") + F.when(F.col("u") == F.col("v"), F.lit(float(alpha[0])) * F.sqrt("deg")).otherwise(0.0)
    sent = arcs.join(coded.select(F.col("poi_id").alias("u"), "code"), "u").select("v", "code", w.alias("w")).repartition("v")
    met = sent.join(small(table.select("code", F.col("v").alias("h")), table.count(), 200_000), "code")
    sums = met.groupBy("v").agg(F.count(F.lit(1)).alias("__n"), *vectors.sums("h", d, F.col("w")))
    return sums.select(F.col("v").alias("poi_id"), vectors.gathered(d, F.sqrt("__n")).alias("h"))
