"""NumPy kernels of clustering for one region: two-way splits, bisecting trees, flat k-means, density clusters."""

from __future__ import annotations

import heapq
import math
from dataclasses import dataclass, field

import numpy as np


def leading_direction(cov: np.ndarray, rounds: int = 64) -> np.ndarray:
    """Power iteration from a fixed start; the sign of the largest component is positive."""
    v = np.ones(len(cov)) + np.arange(len(cov)) / (7.0 * len(cov))
    for _ in range(rounds):
        w = cov @ v
        size = math.sqrt(w.dot(w))
        if size < 1e-300:
            return v / np.sqrt(v @ v)
        before, v = v, w / size
        if max(map(abs, (v - before).tolist())) < 1e-14:
            break
    return v * (1.0 if v[np.argmax(np.abs(v))] >= 0 else -1.0)


def _mean(x: np.ndarray, w: np.ndarray) -> np.ndarray:
    """Weighted mean of rows: ``np.average`` without its checks, which cost more than the sums of small regions."""
    return (x * w[:, None]).sum(axis=0) / w.sum()


def two_means(x: np.ndarray, w: np.ndarray, init: str, max_iter: int, tol: float, seed: int) -> np.ndarray | None:
    """Side (0 or 1) of every row, or None if the rows cannot be split."""
    if len(x) < 2 or np.ptp(x, axis=0).max() <= 1e-12:
        return None
    mean = _mean(x, w)
    c = x - mean
    if init == "principal":
        side = c @ leading_direction((c * w[:, None]).T @ c / w.sum()) > 0
    elif init == "farthest":
        a = int(np.argmax((c * c).sum(axis=1)))
        b = int(np.argmax(((x - x[a]) ** 2).sum(axis=1)))
        side = ((x - x[b]) ** 2).sum(axis=1) < ((x - x[a]) ** 2).sum(axis=1)
    elif init == "kmeans++":
        r = np.random.default_rng(seed)
        a = int(r.choice(len(x), p=w / w.sum()))
        far = ((x - x[a]) ** 2).sum(axis=1) * w
        b = int(r.choice(len(x), p=far / far.sum()))
        side = ((x - x[b]) ** 2).sum(axis=1) < ((x - x[a]) ** 2).sum(axis=1)
    else:
        raise ValueError(init)
    centres = None
    for _ in range(max_iter):
        if side.all() or not side.any():
            far = int(np.argmax((c * c).sum(axis=1)))
            side = side.copy()
            side[far] = not side[far]
        fresh = np.array([_mean(x[s], w[s]) for s in (~side, side)])
        if centres is not None and ((fresh - centres) ** 2).sum(axis=1).max() <= tol * tol:
            break
        centres = fresh
        gap = centres[1] - centres[0]
        side = x @ gap > (centres[1] @ centres[1] - centres[0] @ centres[0]) / 2
    return side.astype(np.int8) if side.any() and not side.all() else None


@dataclass
class SplitTree:
    """A tree of splits: every node's path ('' is the root), members, order of its split (from 1; 0: a leaf)."""

    paths: list[str] = field(default_factory=list)
    sizes: list[float] = field(default_factory=list)
    sse: list[float] = field(default_factory=list)
    rank: list[int] = field(default_factory=list)
    leaf: np.ndarray | None = None  #: path of every row's leaf


def bisect(ids: np.ndarray, x: np.ndarray, k: int, w: np.ndarray | None = None, priority: str = "size", init: str = "principal", max_iter: int = 300, tol: float = 1e-8, seed: int = 1) -> SplitTree:
    """Split the largest (or worst) leaf until there are ``k`` or none can be split; child 0 holds the smallest id."""
    w = np.ones(len(x)) if w is None else w
    tree = SplitTree(leaf=np.full(len(x), "", dtype=object))
    heap: list = []

    def add(path: str, rows: np.ndarray) -> None:
        own, weight = x[rows], w[rows]
        sse = float((weight * ((own - _mean(own, weight)) ** 2).sum(axis=1)).sum())
        size = float(weight.sum())
        tree.paths.append(path)
        tree.sizes.append(size)
        tree.sse.append(sse)
        tree.rank.append(0)
        tree.leaf[rows] = path
        # heap order: large first, then short and small paths
        heapq.heappush(heap, (-(size if priority == "size" else round(sse, 9)), path, len(tree.paths) - 1, rows))

    add("", np.argsort(ids, kind="stable"))
    leaves, splits = 1, 0
    while leaves < k and heap:
        _, path, node, rows = heapq.heappop(heap)
        side = two_means(x[rows], w[rows], init, max_iter, tol, hash_path(path, seed))
        if side is None:
            continue
        splits += 1
        leaves += 1
        tree.rank[node] = splits
        first = side[0]  # rows are in id order
        add(path + "0", rows[side == first])
        add(path + "1", rows[side != first])
    return tree


def expand(ids: np.ndarray, x: np.ndarray, w: np.ndarray, least: float, priority: str, init: str, max_iter: int, tol: float) -> tuple[np.ndarray, list[tuple[str, int, float, bool, bool]]]:
    """Split one node, and then every node below it that is ranked by at least ``least``: each row's path from the node down, and (path, n, rank_by, split, dead) of all nodes."""
    leaf, nodes = np.full(len(x), "", dtype=object), []
    open_ = [("", np.argsort(ids, kind="stable"))]
    while open_:
        path, rows = open_.pop()
        leaf[rows] = path
        rank_by = float(w[rows].sum())
        if priority != "size":
            mean = np.average(x[rows], axis=0, weights=w[rows])
            rank_by = round(float((w[rows] * ((x[rows] - mean) ** 2).sum(axis=1)).sum()), 9)
        tried = not path or rank_by >= least
        side = two_means(x[rows], w[rows], init, max_iter, tol, 1) if tried else None
        nodes.append((path, len(rows), rank_by, side is not None, len(rows) < 2 or (tried and side is None)))
        if side is not None:
            first = side[0]  # rows are in id order
            open_ += [(path + "0", rows[side == first]), (path + "1", rows[side != first])]
    return leaf, nodes


def hash_path(path: str, seed: int) -> int:
    out = seed
    for c in path:
        out = (out * 1_000_003 + ord(c)) % (1 << 31)
    return out


def split_ranks(tree: SplitTree) -> dict[str, list[int]]:
    """For each leaf path, the split order of its ancestors from the root down."""
    rank = dict(zip(tree.paths, tree.rank, strict=True))
    return {p: [rank[p[:i]] for i in range(len(p))] for p in set(tree.leaf.tolist())}


def lloyd(x: np.ndarray, k: int, max_iter: int = 300, tol: float = 1e-8) -> np.ndarray:
    """Flat k-means from farthest-first starts; labels by first member."""
    k = min(k, len(np.unique(x, axis=0)))
    at = [int(np.argmax(((x - x.mean(axis=0)) ** 2).sum(axis=1)))]
    far = ((x - x[at[0]]) ** 2).sum(axis=1)
    while len(at) < k:
        at.append(int(np.argmax(far)))
        far = np.minimum(far, ((x - x[at[-1]]) ** 2).sum(axis=1))
    centres = x[at].copy()
    label = np.zeros(len(x), np.int64)
    for _ in range(max_iter):
        label = np.argmin((x * x).sum(axis=1)[:, None] - 2 * x @ centres.T + (centres * centres).sum(axis=1)[None, :], axis=1)
        fresh = np.stack([x[label == j].mean(axis=0) if (label == j).any() else centres[j] for j in range(k)])
        moved = ((fresh - centres) ** 2).sum(axis=1).max()
        centres = fresh
        if moved <= tol * tol:
            break
    return label


def dbscan(ids: np.ndarray, near: list[np.ndarray], nearest_core, min_pts: int) -> tuple[np.ndarray, np.ndarray]:
    """Cluster (smallest core id, -1: noise) and core flag of every row. near: rows within reach, the row itself included."""
    core = np.array([len(n) >= min_pts for n in near])
    out = np.full(len(ids), -1, np.int64)
    for start in np.argsort(ids, kind="stable"):
        if not core[start] or out[start] != -1:
            continue
        stack = [start]
        out[start] = ids[start]
        while stack:
            for j in near[stack.pop()]:
                if core[j] and out[j] == -1:
                    out[j] = ids[start]
                    stack.append(j)
    for i in np.flatnonzero(~core):
        j = nearest_core(i, near[i][core[near[i]]])
        if j is not None:
            out[i] = out[j]
    return out, core
