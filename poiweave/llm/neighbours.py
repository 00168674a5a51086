"""Approximate nearest neighbours with a forest of random-projection trees.

The trees are fitted on the driver to a bounded sample: a node splits its rows by the plane halfway between two random rows. Every
distinct vector is then indexed: it goes to one leaf of each tree. A query searches all trees through one priority
queue ordered by the squared distance to a node's cell (the sum of the squared margins on the wrong side), and takes leaves until they
hold a share of the rows. Queries meet the rows of their leaves in blocks: a leaf's queries are dealt to as many blocks as they need, and its rows go to
each; a block gives a query its nearest rows by the exact cosine, and the best of all leaves win.
Equal vectors are indexed once with their smallest ids, all that any query can need.
"""

from __future__ import annotations

import heapq
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .session import cut

TREES = 16
#: Rows visited for a query: this share of all (a leaf counts in each tree), at least LEAST. Vectors without any structure, such as
#: uniform ones in 64 dimensions, need about half for a recall of 0.95; clustered ones far less.
SHARE, LEAST = 0.65, 4_000
#: A leaf holds about 1 / LEAVES of the rows within these bounds, so a query visits about as many leaves at any size.
LEAVES, LEAF_BOUNDS = 256, (32, 32_768)
#: Queries that meet a leaf in one block, about.
BLOCK_QUERIES = 8_192
#: Bound of the sample that the trees are fitted to.
SAMPLE_ROWS = 32_768


@dataclass
class Tree:
    """Nodes in arrays; a leaf has child -1 and its share of the sample in ``rows``."""

    normal: np.ndarray
    offset: np.ndarray
    child: np.ndarray
    rows: np.ndarray

    def leaves(self, x: np.ndarray) -> np.ndarray:
        """The leaf of every unit vector."""
        node = np.zeros(len(x), np.int64)
        live = np.arange(len(x))
        while len(live):
            at = node[live]
            inner = self.child[at, 0] >= 0
            live, at = live[inner], at[inner]
            side = np.einsum("ij,ij->i", x[live], self.normal[at]) > self.offset[at]
            node[live] = self.child[at, side.astype(np.int64)]
        return node


def grow(x: np.ndarray, leaf: int, r: np.random.Generator) -> Tree:
    """One tree over the sample ``x``; rows that no plane parts stay in one leaf."""
    normal, offset, child, rows = [], [], [], []

    def add() -> int:
        normal.append(np.zeros(x.shape[1], np.float32))
        offset.append(0.0)
        child.append([-1, -1])
        rows.append(0)
        return len(rows) - 1

    open_ = [(add(), np.arange(len(x)))]
    while open_:
        node, own = open_.pop()
        rows[node] = len(own)
        if len(own) <= leaf:
            continue
        for _ in range(8):
            a, b = x[r.choice(own, 2, replace=False)]
            n = (a - b).astype(np.float32)
            n /= np.linalg.norm(n) + 1e-12
            value = x[own] @ n
            cut_at = float(n @ ((a + b) / 2))
            side = value > cut_at
            if 0.1 * len(own) <= side.sum() <= 0.9 * len(own):
                break
        else:
            cut_at = float(np.median(value))
            side = value > cut_at
            if not 0 < side.sum() < len(own):
                continue
        normal[node], offset[node] = n, cut_at
        child[node] = [add(), add()]
        open_ += [(child[node][0], own[~side]), (child[node][1], own[side])]
    return Tree(np.array(normal), np.array(offset, np.float64), np.array(child, np.int64), np.array(rows, np.float64))


@dataclass
class Forest:
    trees: list[Tree]
    scale: float  #: indexed rows for each sample row

    def probe(self, q: np.ndarray, search: float) -> list[tuple[int, int]]:
        """(tree, leaf) pairs for one unit vector: the queue holds the most promising nodes of all trees."""
        margins = [t.normal @ q - t.offset for t in self.trees]
        queue = [(0.0, k, 0) for k in range(len(self.trees))]
        out, held = [], 0.0
        while queue and held < search:
            far, k, node = heapq.heappop(queue)
            t = self.trees[k]
            while t.child[node, 0] >= 0:
                m = margins[k][node]
                heapq.heappush(queue, (far + float(m * m), k, int(t.child[node, int(m <= 0)])))
                node = int(t.child[node, int(m > 0)])
            out.append((k, node))
            held += t.rows[node] * self.scale
        return out


def fit_forest(sample: np.ndarray, total: int, trees: int = TREES, seed: int = 5) -> Forest:
    scale = max(1.0, total / max(1, len(sample)))
    leaf_rows = min(max(total // LEAVES, LEAF_BOUNDS[0]), LEAF_BOUNDS[1])
    return Forest([grow(sample, max(8, round(leaf_rows / scale)), np.random.default_rng((seed, k))) for k in range(trees)] if len(sample) else [], scale)


def usable(vectors: DataFrame) -> DataFrame:
    """vec_id and ``v`` (doubles) of the rows that take part: an id, and a finite, non-zero vector of the usual length."""
    v = F.col("v")
    rows = vectors.select(F.col("vec_id").cast("long").alias("vec_id"), F.col("embedding").cast("array<double>").alias("v")).filter(F.col("vec_id").isNotNull() & v.isNotNull())
    rows = rows.filter(F.forall(v, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf"))) & F.exists(v, lambda x: x != 0))
    usual = rows.groupBy(F.size(v).alias("n")).count().orderBy(F.desc("count"), "n").limit(1).collect()
    return rows.filter(F.size(v) == (usual[0]["n"] if usual else 0))


def _unit(raw: list[bytes], kind: str) -> np.ndarray:
    x = np.frombuffer(b"".join(raw), kind).astype(np.float64).reshape(len(raw), -1)
    big = np.abs(x).max(axis=1, keepdims=True)
    x = x / big
    return x / np.sqrt((x * x).sum(axis=1, keepdims=True))


def nearest(vectors: DataFrame, k: int = 5, every: int = 50, trees: int = TREES, share: float = SHARE, least: int = LEAST, block: int = BLOCK_QUERIES) -> DataFrame:
    """query_id, rank, vec_id, score: the ``k`` nearest other rows found for each row whose id is divisible by ``every``.

    Rows without an id, and null, empty, zero, non-finite or odd-length vectors take no part. A repeated id counts once (the
    smallest vector in array order). Ties go to the smaller id. With at most ``least / trees`` rows the result is exact.
    """
    kind = "<f4" if vectors.schema["embedding"].dataType.simpleString() == "array<float>" else "<f8"
    rows = usable(vectors)
    rows = rows.groupBy("vec_id").agg(F.min("v").alias("v"))
    by_vector = Window.partitionBy("v").orderBy("vec_id")
    distinct = rows.withColumn("__n", F.row_number().over(by_vector)).filter(F.col("__n") <= k + 1).groupBy("v").agg(F.array_sort(F.collect_list("vec_id")).alias("ids"))

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            v = b.column(0)
            flat = v.flatten().to_numpy(zero_copy_only=False).astype(kind)
            width = max(1, len(flat) // max(1, len(v)))
            raw = [flat[i : i + width].tobytes() for i in range(0, len(flat), width)]
            yield pa.RecordBatch.from_arrays([pa.array(raw, pa.binary()), b.column(1)], names=["raw", "ids"])

    indexed = cut(distinct.select("v", "ids").mapInArrow(pack, "raw binary, ids array<bigint>"))
    total = indexed.count()
    kept = min(1.0, SAMPLE_ROWS / max(1, total))
    search = max(least, share * total)
    drawn = indexed.filter(F.pmod(F.xxhash64(F.lit(11), "raw"), F.lit(1 << 30)) < int(kept * (1 << 30))).select("raw").limit(2 * SAMPLE_ROWS).collect()
    sample = _unit(sorted(bytes(r[0]) for r in drawn), kind).astype(np.float32) if drawn else np.empty((0, 1), np.float32)
    forest = fit_forest(sample, total, trees)

    def to_leaves(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for at in range(0, b.num_rows, 4096):
                part = b.slice(at, 4096)
                unit = _unit(part.column(0).to_pylist(), kind)
                for t, tree in enumerate(forest.trees):
                    yield pa.RecordBatch.from_arrays([pa.array(tree.leaves(unit.astype(np.float32)) * len(forest.trees) + t), *part.columns], names=["leaf", "raw", "ids"])

    def to_probes(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            raw = b.column(0).to_pylist()
            leaf, own, ids = [], [], []
            for x, i, unit in zip(raw, b.column(1).to_pylist(), _unit(raw, kind) if raw else [], strict=True):
                for t, node in forest.probe(unit.astype(np.float32), search):
                    leaf.append(node * len(forest.trees) + t)
                    own.append(x)
                    ids.append(i)
            yield pa.RecordBatch.from_arrays([pa.array(leaf, pa.int64()), pa.array(own, pa.binary()), pa.array(ids, pa.int64())], names=["leaf", "raw", "query_id"])

    def in_leaf(own: pd.DataFrame, asked: pd.DataFrame) -> pd.DataFrame:
        if not len(own) or not len(asked):
            return pd.DataFrame({"query_id": [], "vec_id": [], "score": []}).astype({"query_id": "int64", "vec_id": "int64", "score": "float64"})
        x, ids = _unit(own["raw"].tolist(), kind), own["ids"].tolist()
        out: list[tuple[int, int, float]] = []
        for begin in range(0, len(asked), 256):
            block = asked.iloc[begin : begin + 256]
            scores = np.einsum("ij,kj->ik", _unit(block["raw"].tolist(), kind), x)
            for q, row in zip(block["query_id"].tolist(), scores, strict=True):
                # all rows that tie with the last of the best may be needed
                near = np.flatnonzero(row >= np.partition(row, -min(len(row), k + 1))[-min(len(row), k + 1)])
                best = sorted(((-row[j], i) for j in near for i in ids[j] if i != q))[:k]
                out += [(q, i, -s) for s, i in best]
        return pd.DataFrame(out, columns=["query_id", "vec_id", "score"])

    queries = rows.filter(F.pmod("vec_id", F.lit(every)) == 0).select("v", F.array("vec_id").alias("ids")).mapInArrow(pack, "raw binary, ids array<bigint>").select("raw", F.col("ids")[0].alias("query_id"))
    probes = queries.mapInArrow(to_probes, "leaf long, raw binary, query_id long")
    # at most 2 * LEAVES leaves for each tree or so, whatever the size: a table that may be broadcast
    parts = cut(probes.groupBy("leaf").agg(F.ceil(F.count(F.lit(1)) / block).cast("int").alias("parts")))
    probes = probes.join(F.broadcast(parts), "leaf").withColumn("part", F.pmod(F.xxhash64(F.lit(13), "query_id"), F.col("parts")).cast("int")).drop("parts")
    leaves = indexed.mapInArrow(to_leaves, "leaf long, raw binary, ids array<bigint>")
    leaves = leaves.join(F.broadcast(parts), "leaf").withColumn("part", F.explode(F.sequence(F.lit(0), F.col("parts") - 1))).drop("parts")
    found = leaves.groupBy("leaf", "part").cogroup(probes.groupBy("leaf", "part")).applyInPandas(in_leaf, "query_id long, vec_id long, score double")
    best = found.groupBy("query_id", "vec_id").agg(F.max("score").alias("score"))
    rank = F.row_number().over(Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id"))
    return best.withColumn("rank", rank).filter(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
