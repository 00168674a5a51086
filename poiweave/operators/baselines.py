"""Baselines: mean of category vectors, spatial co-occurrence, hierarchical infomax, pretrained vectors."""

from __future__ import annotations

from collections.abc import Sequence

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions import category, vectors
from .encode import encode_poi, factorise, ppmi, reduce_dim
from .regions import region_mean
from .session import cut


def mean_baseline(poi: DataFrame, table: DataFrame, keys: Sequence[str], d: int) -> DataFrame:
    """Region vectors as means of category vectors."""
    return region_mean(poi.select("poi_id", *keys).join(encode_poi(poi, table, d), "poi_id"), keys, d)


def cooccurrence_counts(edges: DataFrame, poi: DataFrame, level: int = 2, reach_m: float = 1_000.0) -> DataFrame:
    """a, b, n: category pairs of graph neighbours, each neighbour weighing 1 / (1 + d / reach)."""
    c = poi.select("poi_id", category.prefix(F.col("category_path"), level).alias("c"))
    met = edges.join(c.select(F.col("poi_id").alias("src"), F.col("c").alias("x")), "src").join(c.select(F.col("poi_id").alias("dst"), F.col("c").alias("y")), "dst")
    w = 1 / (1 + F.col("dist_m") / reach_m)
    return met.select(F.explode(F.array(F.struct(F.col("x").alias("a"), F.col("y").alias("b")), F.struct(F.col("y").alias("a"), F.col("x").alias("b")))).alias("p"), w.alias("w")).groupBy("p.a", "p.b").agg(F.sum("w").alias("n"))


def cooccurrence_table(edges: DataFrame, poi: DataFrame, d: int, level: int = 2, method: str = "ppmi") -> DataFrame:
    """path_key, v for categories at ``level``: factorised co-occurrence, or skip-gram over "centre and neighbours" sentences."""
    if method == "w2v":
        from pyspark.ml.feature import Word2Vec
        from pyspark.ml.functions import vector_to_array

        c = poi.select("poi_id", category.prefix(F.col("category_path"), level).alias("c"))
        both = edges.select("src", "dst", "dist_m").unionByName(edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "dist_m"))
        near = both.join(c.withColumnRenamed("poi_id", "dst"), "dst").groupBy("src").agg(F.array_sort(F.collect_list(F.struct("dist_m", "dst", "c"))).alias("n"))
        sentences = near.join(c.select(F.col("poi_id").alias("src"), F.col("c").alias("centre")), "src").select(F.concat(F.array("centre"), F.col("n.c")).alias("words"))
        model = Word2Vec(vectorSize=d, minCount=1, seed=1, windowSize=5, inputCol="words", outputCol="v", maxIter=2).fit(sentences)
        return model.getVectors().select(F.col("word").alias("path_key"), vector_to_array("vector").alias("v"))
    names, v = factorise(ppmi(cut(cooccurrence_counts(edges, poi, level))), d)
    schema = T.StructType([T.StructField("path_key", T.StringType()), T.StructField("v", T.ArrayType(T.DoubleType()))])
    return poi.sparkSession.createDataFrame([(n, [float(x) for x in row]) for n, row in zip(names, v, strict=True)], schema)


def cooccurrence_baseline(poi: DataFrame, edges: DataFrame, keys: Sequence[str], d: int, level: int = 2, method: str = "ppmi") -> DataFrame:
    return mean_baseline(poi, cooccurrence_table(edges, poi, d, level, method), keys, d)


def attention_pool(rows: DataFrame, keys: Sequence[str], d: int, score: str = "score") -> DataFrame:
    """Softmax-weighted mean of ``h`` inside each group. One aggregation finds the largest score, so no exponent overflows."""
    top = rows.groupBy(*keys).agg(F.max(score).alias("__top"))
    w = F.exp(F.col(score) - F.col("__top"))
    sums = rows.join(top, list(keys)).withColumn("__e", w).groupBy(*keys).agg(F.sum("__e").alias("__w"), *vectors.sums("h", d, F.col("__e")))
    return sums.select(*keys, vectors.gathered(d, F.col("__w")).alias("z"))


def _by_group(rows: np.ndarray, group: np.ndarray, n: int) -> np.ndarray:
    """Sums of ``rows`` in each of ``n`` groups, added in row order (as ``np.add.at`` does, which is far slower on matrices)."""
    return np.stack([np.bincount(group, weights=c, minlength=n) for c in rows.T], axis=1)


#: Points of the trained baseline that pass at once: a few arrays of so many rows stay in the processor's cache.
BLOCK = 4_096
#: States are dealt to so many tasks for training, that few share one.
TASKS = 200


class Infomax:
    """Two-level mutual information model of one state in NumPy, with hand-written gradients.

    Points: one propagation step, a linear map and a leaky rectifier. Regions: attention over their points, then a step over touching
    regions. Point-region and region-state pairs are told from corrupted ones by bilinear scores.
    """

    SHAPES = ("W", "w", "A", "B", "R", "S")

    def __init__(self, x: np.ndarray, region: np.ndarray, adjacency: np.ndarray | tuple[int, np.ndarray, np.ndarray], d: int, seed: int):
        """``adjacency`` is a square matrix of zeros and ones, or the number of regions and the ends of all its ones."""
        r = np.random.default_rng(seed)
        m, a, b = adjacency if isinstance(adjacency, tuple) else (len(adjacency), *np.nonzero(adjacency))
        self.x, self.region, self.n_regions = x, region, m
        self.to, self.of = np.concatenate([a, np.arange(m)]), np.concatenate([b, np.arange(m)])
        self.share = (1.0 / np.bincount(self.to, minlength=m))[self.to]
        self.size = np.bincount(region, minlength=self.n_regions).astype(float)
        k = x.shape[1]
        self.p = {"W": r.normal(0, 1 / np.sqrt(k), (k, d)), "w": np.zeros(d), "A": r.normal(0, 1 / np.sqrt(d), (d, d)), "B": r.normal(0, 1 / np.sqrt(d), d), "R": np.eye(d) + r.normal(0, 0.05, (d, d)), "S": np.eye(d) + r.normal(0, 0.05, (d, d))}
        self.r = r

    def encode(self, x: np.ndarray) -> dict[str, np.ndarray]:
        p = self.p
        raw = x @ p["W"] + p["w"]
        h = np.where(raw > 0, raw, 0.25 * raw)
        t = np.tanh(h @ p["A"])
        return {"x": x, "raw": raw, "h": h, "t": t, "s": t @ p["B"]} | self._pool(h, t @ p["B"], self.region)

    def _spread(self, z: np.ndarray, back: bool = False) -> np.ndarray:
        """Each region's mean over itself and those it touches (``back``: the transpose)."""
        to, of = (self.of, self.to) if back else (self.to, self.of)
        return _by_group(self.share[:, None] * z[of], to, self.n_regions)

    def _pool(self, h: np.ndarray, s: np.ndarray, region: np.ndarray) -> dict[str, np.ndarray]:
        """Regions and state over points that lie in ``region``."""
        top = np.full(self.n_regions, -np.inf)
        np.maximum.at(top, region, s)
        e = np.exp(s - top[region])
        a = e / np.bincount(region, weights=e, minlength=self.n_regions)[region]
        pooled = _by_group(a[:, None] * h, region, self.n_regions)
        z = self._spread(pooled)
        return {"region": region, "a": a, "pooled": pooled, "z": z, "g": (self.size / self.size.sum()) @ z}

    def _add(self, out: np.ndarray, rows: np.ndarray, group: np.ndarray) -> None:
        """Adds ``rows`` to the rows of ``out`` that ``group`` names: by runs of one group if it ascends, else by one count over all cells."""
        if (group[1:] >= group[:-1]).all():
            starts = np.flatnonzero(np.diff(group, prepend=-1))
            out[group[starts]] += np.add.reduceat(rows, starts, axis=0)
        else:
            d = out.shape[1]
            out += np.bincount((group[:, None] * d + np.arange(d)).ravel(), weights=rows.ravel(), minlength=out.size).reshape(out.shape)

    def loss(self, order: np.ndarray, other: np.ndarray, grad: bool = True) -> tuple[float, dict[str, np.ndarray]]:
        """Mean logistic loss of true and corrupted pairs; ``order`` shuffles features, ``other`` pairs points with other regions.

        Shuffled features are the same rows in other regions, so what is computed row by row serves both. Points pass in blocks that stay in the processor's cache; only their hidden
        vectors are kept from one pass to the next.
        """
        p, n, m, region, kind = self.p, len(self.x), self.n_regions, self.region, self.x.dtype
        w, shift, a_, b_ = (p[k].astype(kind) for k in ("W", "w", "A", "B"))  # rows of points have the features' precision, sums and parameters double
        blocks = [slice(k, min(n, k + BLOCK)) for k in range(0, n, BLOCK)]
        h, t, s = np.empty((n, len(shift)), kind), np.empty((n, len(shift)), kind), np.empty(n)
        for b in blocks:
            raw = self.x[b] @ w
            raw += shift
            np.maximum(raw, 0.25 * raw, out=h[b])
            np.tanh(h[b] @ a_, out=t[b])
            s[b] = t[b] @ b_
        elsewhere = np.empty_like(region)
        elsewhere[order] = region
        pools = []
        for own in (region, elsewhere):
            top = np.full(m, -np.inf)
            np.maximum.at(top, own, s)
            e = np.exp(s - top[own])
            e /= np.bincount(own, weights=e, minlength=m)[own]
            pools.append((own, e.astype(kind), np.zeros((m, h.shape[1]))))
        for b in blocks:
            for own, a, pooled in pools:
                self._add(pooled, a[b, None] * h[b], own[b])
        z, cz = (self._spread(pooled) for _, _, pooled in pools)
        g = (self.size / self.size.sum()) @ z
        sig = lambda y: 1 / (1 + np.exp(-np.clip(y, -40, 40)))
        zr, sg = (z @ p["R"].T).astype(kind), p["S"] @ g  # rows: R z
        pos, neg, dzr = np.empty(n), np.empty(n), np.zeros(z.shape)
        for b in blocks:
            pos[b], neg[b] = (np.einsum("ij,ij->i", h[b], zr.take(own[b], axis=0)) for own in (region, other))
        gpos, gneg = sig(z @ sg), sig(cz @ sg)
        pos, neg = sig(pos), sig(neg)
        value = float(-np.log(pos + 1e-12).mean() - np.log(1 - neg + 1e-12).mean() - np.log(gpos + 1e-12).mean() - np.log(1 - gneg + 1e-12).mean())
        if not grad:
            return value, {}
        dpos, dneg, dgp, dgn = ((pos - 1) / n).astype(kind), (neg / n).astype(kind), (gpos - 1) / m, gneg / m
        for b in blocks:
            self._add(dzr, dpos[b, None] * h[b], region[b])
            self._add(dzr, dneg[b, None] * h[b], other[b])
        dz = dzr @ p["R"] + dgp[:, None] * sg
        dsg = z.T @ dgp + cz.T @ dgn
        dz += (self.size / self.size.sum())[:, None] * (p["S"].T @ dsg)[None, :]
        out = {"R": dzr.T @ z, "S": np.outer(dsg, g), **{k: np.zeros(p[k].shape) for k in ("B", "A", "W", "w")}}
        # a region's share in the softmax's gradient: the sum of a * da over its points is the product of its gradient and its pooled vector
        back = [(own, a, d.astype(kind), np.einsum("ij,ij->i", d, pooled).astype(kind)) for (own, a, pooled), d in zip(pools, (self._spread(dz, back=True), self._spread(dgn[:, None] * sg, back=True)), strict=True)]
        for b in blocks:
            dh = dpos[b, None] * zr.take(region[b], axis=0)
            dh += dneg[b, None] * zr.take(other[b], axis=0)
            ds = np.zeros(len(dh), kind)
            for own, a, d, mean in back:
                dpool = d.take(own[b], axis=0)
                ds += a[b] * (np.einsum("ij,ij->i", dpool, h[b]) - mean[own[b]])
                dpool *= a[b, None]
                dh += dpool
            dt = 1 - t[b] * t[b]
            dt *= ds[:, None]
            dt *= b_
            dh += dt @ a_.T
            slope = (h[b] > 0).astype(kind)
            slope *= 0.75
            slope += 0.25
            dh *= slope
            out["B"] += t[b].T @ ds
            out["A"] += h[b].T @ dt
            out["W"] += self.x[b].T @ dh
            out["w"] += dh.sum(axis=0)
        return value, out

    def fit(self, epochs: int, rate: float = 0.01) -> list[float]:
        m = {k: np.zeros_like(v) for k, v in self.p.items()}
        q = {k: np.zeros_like(v) for k, v in self.p.items()}
        losses = []
        for step in range(1, epochs + 1):
            order = self.r.permutation(len(self.x))
            other = (self.region + self.r.integers(1, max(2, self.n_regions), len(self.x))) % self.n_regions
            value, g = self.loss(order, other)
            losses.append(value)
            for k in self.p:
                m[k] = 0.9 * m[k] + 0.1 * g[k]
                q[k] = 0.999 * q[k] + 0.001 * g[k] ** 2
                self.p[k] = self.p[k] - rate * (m[k] / (1 - 0.9**step)) / (np.sqrt(q[k] / (1 - 0.999**step)) + 1e-8)
        return losses


def infomax_baseline(h1: DataFrame, adjacency: DataFrame, d: int, epochs: int = 100, seed: int = 1, kind: str = "float64") -> DataFrame:
    """state_id, zip_id, n_poi, z: one model for each state, a task each. ``h1`` has state_id, zip_id, poi_id, h after one propagation step.

    ``adjacency`` (state_id, a, b) lists touching regions. The trained baseline needs a state in one task, as its publication does. ``kind`` is the precision of the points' rows.
    """

    def run(pdf: pd.DataFrame, near: pd.DataFrame) -> pd.DataFrame:
        if not len(pdf):
            return pd.DataFrame({"state_id": [], "zip_id": [], "n_poi": [], "z": []})
        pdf = pdf.sort_values(["zip_id", "poi_id"])  # points of a region lie together
        zips = np.sort(pdf["zip_id"].unique())
        region = np.searchsorted(zips, pdf["zip_id"].to_numpy())
        near = near[near["a"].isin(zips) & near["b"].isin(zips)]
        a, b = (np.searchsorted(zips, near[c].to_numpy(np.int64)) for c in ("a", "b"))
        both = np.unique(np.concatenate([a * len(zips) + b, b * len(zips) + a]))
        model = Infomax(np.stack(pdf["h"].to_list()).astype(kind), region, (len(zips), both // len(zips), both % len(zips)), d, seed)
        model.fit(epochs)
        z = model.encode(model.x)["z"]
        return pd.DataFrame({"state_id": pdf["state_id"].iloc[0], "zip_id": zips, "n_poi": model.size.astype(int), "z": list(z)})

    rows = h1.select("state_id", "zip_id", "poi_id", "h").repartition(TASKS, "state_id").groupBy("state_id")
    return rows.cogroup(adjacency.repartition(TASKS, "state_id").groupBy("state_id")).applyInPandas(run, "state_id int, zip_id long, n_poi long, z array<double>")


def pretrained_baseline(zips: DataFrame, embeddings: DataFrame, d: int = 30, dims: tuple[int, int] = (0, 64)) -> DataFrame:
    """zip_id, n_poi, z: released vectors mapped to regions by ``vec_id`` modulo the number of regions, averaged over chosen ``dims``, reduced to ``d``."""
    n = zips.select("zip_id").distinct().count()
    width = dims[1] - dims[0]
    rows = embeddings.select((F.col("vec_id") % n).alias("zip_id"), F.slice("embedding", dims[0] + 1, width).cast("array<double>").alias("h"))
    means = region_mean(rows, ["zip_id"], width)
    reduced = reduce_dim(means.select(F.col("zip_id").alias("poi_id"), F.col("z").alias("h")), width, d)
    return means.select("zip_id", "n_poi").join(reduced.select(F.col("poi_id").alias("zip_id"), F.col("h").alias("z")), "zip_id")
