"""Category encoders: hashed, one-hot, co-visit factorisation, Word2Vec, external vectors, dimension reduction."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions import category, vectors
from .session import cut

#: A table of category prefixes is collected for factorisation only up to this many rows.
MAX_CATEGORIES = 4_000


def distinct_paths(poi: DataFrame) -> DataFrame:
    """path_key, category_path: one row for each path."""
    return poi.select(category.key(F.col("category_path")).alias("path_key"), "category_path").distinct()


def prefix_key(prefix):
    """A stable 24-bit integer of a prefix: the first six hex digits of its MD5."""
    return F.conv(F.substring(F.md5(prefix), 1, 6), 16, 10).cast("long")


def hash_encoder(paths: DataFrame, d: int = 8, decay: float = 0.5) -> DataFrame:
    """path_key, v: each prefix gives integers in [-64, 64] over 64 by modular arithmetic (a multiplier for each dimension); level i weighs ``decay**(i - 1)``.

    All values are dyadic for decay 1/2, so sums are exact in any order.
    """

    def part(k: int):
        term = lambda i: F.pow(F.lit(decay), i - 1) * (F.pmod(F.pmod(prefix_key(category.prefix(F.col("category_path"), i)) * (2_654_435 + 40_503 * k) + 7_919 * k, F.lit(16_777_259)), F.lit(129)) - 64) / 64
        return F.aggregate(F.sequence(F.lit(1), F.size("category_path")), F.lit(0.0), lambda s, i: s + term(i))

    return paths.select("path_key", F.array(*(part(k) for k in range(d))).alias("v"))


def onehot_encoder(poi: DataFrame, level: int = 1) -> DataFrame:
    """poi_id and one 0/1 column for each label at ``level``."""
    label = category.level(F.col("category_path"), level)
    return poi.select("poi_id", label.alias("label")).filter("label is not null").groupBy("poi_id").pivot("label").agg(F.count(F.lit(1))).na.fill(0)


def encode_poi(poi: DataFrame, table: DataFrame, d: int, missing: str = "parent") -> DataFrame:
    """poi_id, h: each point's path vector. A path absent from ``table`` takes its nearest known ancestor's vector (``parent``) or zeros.

    The table has a row for each distinct path and is broadcast by the optimiser when small.
    """
    zero = F.array(*([F.lit(0.0)] * d))
    keyed = poi.select("poi_id", "category_path")
    if missing == "zero":
        return keyed.withColumn("path_key", category.key(F.col("category_path"))).join(table, "path_key", "left").select("poi_id", F.coalesce("v", zero).alias("h"))
    paths = distinct_paths(poi).withColumn("level", F.explode(F.sequence(F.lit(1), F.size("category_path"))))
    paths = paths.withColumn("own", category.prefix(F.col("category_path"), F.col("level")))
    known = paths.join(table.withColumnRenamed("path_key", "own"), "own").groupBy("path_key").agg(F.max_by("v", "level").alias("v"))
    return keyed.withColumn("path_key", category.key(F.col("category_path"))).join(known, "path_key", "left").select("poi_id", F.coalesce("v", zero).alias("h"))


def covisit_counts(visits: DataFrame, level: int, window: int = 2) -> DataFrame:
    """a, b, n: ordered pairs of prefixes at ``level`` visited within ``window`` positions by one visitor.

    Neighbours come from shifted window functions, so no pairs beyond the window are ever formed.
    """
    rows = visits.filter(F.size("category_path") >= level).select("visitor", "pos", category.prefix(F.col("category_path"), level).alias("c"))
    order = Window.partitionBy("visitor").orderBy("pos")
    near = [F.struct(F.lag("c", s).over(order).alias("c"), F.lag("pos", s).over(order).alias("pos")) for s in range(1, window + 1)]
    pairs = rows.withColumn("near", F.array(*near)).select("c", "pos", F.explode("near").alias("x")).filter(F.col("x.c").isNotNull() & (F.col("pos") - F.col("x.pos") <= window))
    once = pairs.groupBy(F.col("c").alias("a"), F.col("x.c").alias("b")).agg(F.count(F.lit(1)).alias("n"))
    return once.unionByName(once.select(F.col("b").alias("a"), F.col("a").alias("b"), "n")).groupBy("a", "b").agg(F.sum("n").alias("n"))


def covisit_levels(visits: DataFrame, levels: int, window: int = 2) -> DataFrame:
    """level, a, b, n: :func:`covisit_counts` of all levels from 1 on, from one pass over the visits."""
    level = F.explode(F.sequence(F.lit(1), F.least(F.size("category_path"), F.lit(levels)))).alias("level")
    rows = visits.filter(F.size("category_path") > 0).select("visitor", "pos", "category_path", level).select("visitor", "level", "pos", category.prefix(F.col("category_path"), F.col("level")).alias("c"))
    order = Window.partitionBy("visitor", "level").orderBy("pos")
    near = [F.struct(F.lag("c", s).over(order).alias("c"), F.lag("pos", s).over(order).alias("pos")) for s in range(1, window + 1)]
    pairs = rows.withColumn("near", F.array(*near)).select("level", "c", "pos", F.explode("near").alias("x")).filter(F.col("x.c").isNotNull() & (F.col("pos") - F.col("x.pos") <= window))
    once = pairs.groupBy("level", F.col("c").alias("a"), F.col("x.c").alias("b")).agg(F.count(F.lit(1)).alias("n"))
    ends = F.explode(F.array(F.struct("a", "b"), F.struct(F.col("b").alias("a"), F.col("a").alias("b")))).alias("p")
    return once.select("level", "n", ends).groupBy("level", "p.a", "p.b").agg(F.sum("n").alias("n"))


def ppmi(counts: DataFrame) -> DataFrame:
    """a, b, ppmi: positive pointwise mutual information of co-occurrence counts (count column ``n``)."""
    left = counts.groupBy("a").agg(F.sum("n").alias("na"))
    right = counts.groupBy("b").agg(F.sum("n").alias("nb"))
    total = counts.agg(F.sum("n").alias("total"))
    out = counts.join(left, "a").join(right, "b").crossJoin(F.broadcast(total))
    return out.select("a", "b", F.greatest(F.lit(0.0), F.log(F.col("n") * F.col("total") / (F.col("na") * F.col("nb")))).alias("ppmi"))


def factorise(cells: DataFrame, d: int, most: int = MAX_CATEGORIES) -> tuple[list[str], np.ndarray]:
    """Names and d-vectors of a symmetric matrix (a, b, ppmi): leading eigenvectors by root eigenvalue, signs fixed."""
    names = sorted(r[0] for r in cells.select("a").distinct().limit(most + 1).collect())
    if len(names) > most:
        raise ValueError(f"more than {most} categories at one level")
    at = {n: i for i, n in enumerate(names)}
    m = np.zeros((len(names), len(names)))
    for a, b, x in cells.filter("ppmi > 0").toLocalIterator():
        m[at[a], at[b]] = x
    values, vecs = np.linalg.eigh((m + m.T) / 2)
    order = np.argsort(-values, kind="stable")[:d]
    out = np.zeros((len(names), d))
    for k, j in enumerate(order):
        v = vecs[:, j]
        out[:, k] = v * np.sign(v[np.argmax(np.abs(v))]) * np.sqrt(max(values[j], 0.0))
    return names, out


def fit_sequence_encoder(visits: DataFrame, paths: DataFrame, levels: int = 6, d: int = 30, window: int = 2, method: str = "ppmi", partitions: int = 1) -> DataFrame:
    """path_key, v: each level has its own block of d / levels dimensions; a path that ends earlier inherits its last block's zeros.

    ``ppmi`` factorises co-visits of every level, and every path joins the tables of its prefixes; ``w2v`` trains Word2Vec on the visit sequences of whole paths,
    in ``partitions`` parts whose vectors are averaged after each pass (one part gives the same vectors in every run).
    """
    spark = visits.sparkSession
    if method == "w2v":
        return _word2vec(visits.select("visitor", "pos", category.key(F.col("category_path")).alias("word")), d, window, partitions)
    block = d // levels
    out, parts = paths.select("path_key", "category_path"), []
    counts = cut(covisit_levels(visits, levels, window))
    for level in range(1, levels + 1):
        names, v = factorise(ppmi(counts.filter(F.col("level") == level)), block)
        known = spark.createDataFrame([(n, x.tolist()) for n, x in zip(names, v, strict=True)], f"p{level} string, v{level} array<double>")
        own = F.when(F.size("category_path") >= level, category.prefix(F.col("category_path"), level))
        out = out.withColumn(f"p{level}", own).join(known, f"p{level}", "left").drop(f"p{level}")
        parts.append(F.coalesce(f"v{level}", F.array(*([F.lit(0.0)] * block))))
    rest = [F.array(*([F.lit(0.0)] * (d - block * levels)))] if d > block * levels else []
    return out.select("path_key", F.concat(*parts, *rest).alias("v"))


def _word2vec(words: DataFrame, d: int, window: int, partitions: int) -> DataFrame:
    from pyspark.ml.feature import Word2Vec
    from pyspark.ml.functions import vector_to_array

    sentences = words.groupBy("visitor").agg(F.sort_array(F.collect_list(F.struct("pos", "word"))).alias("s")).select(F.col("s.word").alias("words"))
    model = Word2Vec(vectorSize=d, minCount=1, seed=1, windowSize=window, inputCol="words", outputCol="v", numPartitions=partitions, maxIter=max(2, partitions)).fit(sentences)
    return model.getVectors().select(F.col("word").alias("path_key"), vector_to_array("vector").alias("v"))


def load_vectors(df: DataFrame, key: str, column: str) -> DataFrame:
    """Any external vectors as (poi_id, h) of doubles."""
    return df.select(F.col(key).alias("poi_id"), F.col(column).cast("array<double>").alias("h"))


def moments(h: DataFrame, d: int) -> DataFrame:
    """i, j, n, si, sj, p: component sums and products for all i <= j.

    Scalar sums in generated code up to 16 dimensions; beyond that, where thousands of sums would not compile well, each partition
    multiplies its rows as a matrix and only those small matrices are summed.
    """
    pairs = [(i, j) for i in range(d) for j in range(i, d)]
    if d > 16:
        return _matrix_moments(h, d)
    row = h.agg(F.count(F.lit(1)).alias("n"), *(F.sum(F.col("h")[i]).alias(f"s{i}") for i in range(d)), *(F.sum(F.col("h")[i] * F.col("h")[j]).alias(f"p{i}_{j}") for i, j in pairs))
    cells = F.array(*(F.struct(F.lit(i).alias("i"), F.lit(j).alias("j"), F.col("n"), F.col(f"s{i}").alias("si"), F.col(f"s{j}").alias("sj"), F.col(f"p{i}_{j}").alias("p")) for i, j in pairs))
    return row.select(F.explode(cells).alias("x")).select("x.*")


def _matrix_moments(h: DataFrame, d: int) -> DataFrame:
    i, j = np.triu_indices(d)

    def local(batches):
        n, s, p = 0, np.zeros(d), np.zeros((d, d))
        for pdf in batches:
            if len(pdf):
                x = np.stack(pdf["h"].to_list()).astype(float)
                n, s, p = n + len(x), s + x.sum(axis=0), p + x.T @ x
        yield pd.DataFrame({"i": i.astype(np.int32), "j": j.astype(np.int32), "n": n, "si": s[i], "sj": s[j], "p": p[i, j]})

    rows = h.select("h").mapInPandas(local, "i int, j int, n long, si double, sj double, p double")
    return rows.groupBy("i", "j").agg(*(F.sum(c).alias(c) for c in ("n", "si", "sj", "p")))


def reduce_dim(h: DataFrame, d_in: int, d: int) -> DataFrame:
    """poi_id, h projected to the leading ``d`` principal axes; only the d_in x d_in moments reach the driver."""
    cov = np.zeros((d_in, d_in))
    mean = np.zeros(d_in)
    for i, j, n, si, sj, p in moments(h, d_in).collect():
        cov[i, j] = cov[j, i] = p / n - (si / n) * (sj / n)
        mean[i], mean[j] = si / n, sj / n
    values, vecs = np.linalg.eigh(cov)
    axes = [v * np.sign(v[np.argmax(np.abs(v))]) for v in vecs.T[np.argsort(-values, kind="stable")[:d]]]
    matrix = F.array(*(F.struct(F.lit(float(a @ mean)).alias("shift"), F.array(*map(F.lit, map(float, a))).alias("axis")) for a in axes))
    return h.select("poi_id", F.transform(matrix, lambda a: vectors.dot(F.col("h"), a["axis"]) - a["shift"]).alias("h"))


def fuse_features(a: DataFrame, b: DataFrame) -> DataFrame:
    """Concatenate two feature tables by point: more modalities for the same pipeline."""
    return a.select("poi_id", F.col("h").alias("ha")).join(b.select("poi_id", F.col("h").alias("hb")), "poi_id").select("poi_id", F.concat("ha", "hb").alias("h"))
