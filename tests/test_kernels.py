from __future__ import annotations

import itertools
import random

import numpy as np
import pandas as pd
import pytest

from poiweave.operators.baselines import Infomax
from poiweave.operators import delaunay
from poiweave.operators.kmeans import bisect, lloyd, split_ranks, two_means
from poiweave.operators.learners import FITTERS
from poiweave.operators.places import budget_of
from poiweave.operators.triangulate import Triangulation, area, circle, circles, clip


def _brute_triangles(t, n):
    out = set()
    for a, b, c in itertools.combinations(range(n), 3):
        turn = t.orient(a, b, c)
        if turn:
            if turn < 0:
                b, c = c, b
            if not any(t.inside(a, b, c, d) for d in range(n) if d not in (a, b, c)):
                out.add(frozenset((a, b, c)))
    return out


def test_triangulation_against_empty_circles():
    r = random.Random(3)
    for _ in range(150):
        span = r.choice([3, 5, 50, 1000])
        pts = list({(r.randint(0, span), r.randint(0, span)) for _ in range(r.randint(1, 13))})
        ids = list(range(len(pts)))
        r.shuffle(ids)
        t = Triangulation(pts, ids)
        if not t.chain:
            assert {frozenset(x) for x in t.triangles()} == _brute_triangles(t, len(pts))


def test_triangulation_of_lattice_line_and_few_points():
    lattice = [(x, y) for x in range(10) for y in range(10)]
    t = Triangulation(lattice, list(range(100)))
    assert len(t.triangles()) == 162 and len(t.edges()) == 261 and len(t.hull()) == 36
    assert Triangulation([(k, 2 * k) for k in (3, 1, 2)], [0, 1, 2]).edges() == [(1, 2), (0, 2)]
    assert Triangulation([], []).edges() == [] and Triangulation([(1, 1)], [5]).edges() == []


def test_insertion_order_does_not_matter():
    pts = [(x, y) for x in range(6) for y in range(6)]
    want = {frozenset((pts[a], pts[b])) for a, b in Triangulation(pts, list(range(36))).edges()}
    r = random.Random(1)
    for _ in range(5):
        order = list(range(36))
        r.shuffle(order)
        own = [pts[i] for i in order]
        assert {frozenset((own[a], own[b])) for a, b in Triangulation(own, order).edges()} == want


def test_clip_and_circle():
    square = [(0.0, 0.0), (1.0, 0.0), (1.0, 1.0), (0.0, 1.0)]
    assert area(clip(square, 1, 0, 0.25)) == pytest.approx(0.25)
    assert clip(square, 1, 0, -1) == [] and area(square) == 1
    assert circle((0, 0), (2, 0), (0, 2)) == pytest.approx((1, 1, 2**0.5))


def test_two_blobs_are_found():
    r = np.random.default_rng(0)
    x = np.concatenate([r.normal(0, 1, (20, 3)), r.normal(20, 1, (20, 3))])
    for init in ("principal", "farthest", "kmeans++"):
        side = two_means(x, np.ones(40), init, 300, 1e-8, 1)
        assert len(set(side[:20])) == 1 and len(set(side[20:])) == 1 and side[0] != side[20]


def test_two_means_is_near_the_best_parting():
    r = np.random.default_rng(1)
    for _ in range(10):
        x = r.normal(size=(9, 2))

        def sse(mask, x=x):
            return sum(((x[m] - x[m].mean(axis=0)) ** 2).sum() for m in (mask, ~mask) if m.any())

        best = min(sse(np.array([(k >> i) & 1 for i in range(9)], bool)) for k in range(1, 256))
        assert best - 1e-9 <= sse(two_means(x, np.ones(9), "principal", 300, 1e-8, 1).astype(bool)) <= 2.5 * best


def test_bisect_special_cases_and_nesting():
    x = np.zeros((5, 2))
    assert set(bisect(np.arange(5), x, 3).leaf) == {""}
    r = np.random.default_rng(2)
    y = r.normal(size=(60, 3))
    tree = bisect(np.arange(60), y, 60)
    assert len(set(tree.leaf)) == 60
    ranks = split_ranks(tree)
    assert all(list(v) == sorted(v) and min(v) == 1 for v in ranks.values())
    for k in (1, 2, 7, 20):
        few = bisect(np.arange(60), y, k)
        cut = [p[: sum(q < k for q in ranks[p])] for p in tree.leaf]
        assert cut == list(few.leaf)
    sse = [sum(s for s, q in zip(t.sse, t.rank, strict=True) if q == 0) for t in (bisect(np.arange(60), y, k) for k in (1, 5, 20, 60))]
    assert sse == sorted(sse, reverse=True) and sse[-1] == pytest.approx(0)
    assert len(set(lloyd(y, 6))) == 6


def test_budget_is_exact():
    assert budget_of(100, "0.29") == 29 and budget_of(9, "0.1") == 1 and budget_of(10, "0.1") == 1 and budget_of(20, "0.1") == 2 and budget_of(1, "1") == 1


def test_learners_beat_the_mean():
    r = np.random.default_rng(0)
    x = r.normal(size=(200, 5))
    y = 2 * x[:, 0] + np.sin(2 * x[:, 1]) + 0.1 * r.normal(size=200)
    for fit in FITTERS.values():
        gap = fit(x[:160], y[:160])(x[160:]) - y[160:]
        assert np.sqrt((gap**2).mean()) < 0.6 * y.std()


def test_infomax_gradients_and_descent():
    r = np.random.default_rng(0)
    region = np.arange(40) % 4
    adj = np.eye(4, k=1) + np.eye(4, k=-1)
    x = r.normal(size=(40, 5)) + 3 * r.normal(size=(4, 5))[region]
    m = Infomax(x, region, adj, 3, 1)
    order, other = r.permutation(40), (region + 1) % 4
    _, g = m.loss(order, other)
    for k, p in m.p.items():
        at = tuple(0 for _ in p.shape)
        keep = p[at]
        p[at] = keep + 1e-6
        up, _ = m.loss(order, other, False)
        p[at] = keep - 1e-6
        down, _ = m.loss(order, other, False)
        p[at] = keep
        assert abs((up - down) / 2e-6 - g[k][at]) < 1e-5
    losses = m.fit(150)
    assert np.mean(losses[-10:]) < np.mean(losses[:10])


def test_far_points_on_one_circle_are_decided_in_integers():
    """Coordinates so large that the determinant in floating point has no sign to trust."""
    ring = [(a * 65 * 10**7, b * 65 * 10**7) for a, b in ((25, 60), (60, 25), (33, 56), (56, 33), (16, 63), (63, 16), (-25, 60), (-60, -25), (39, -52))]
    t = Triangulation(ring, list(range(len(ring))))
    assert {frozenset(x) for x in t.triangles()} == _brute_triangles(t, len(ring))
    moved = [(x + (k == 3), y) for k, (x, y) in enumerate(ring)]
    t = Triangulation(moved, list(range(len(ring))))
    assert {frozenset(x) for x in t.triangles()} == _brute_triangles(t, len(ring))


def test_circles_at_once_equal_single_ones():
    r = np.random.default_rng(4)
    x, y = r.random(30), r.random(30)
    rows = np.array([r.choice(30, 3, replace=False) for _ in range(50)])
    for k, (cx, cy, radius) in enumerate(zip(*circles(x, y, rows), strict=True)):
        assert (cx, cy, radius) == pytest.approx(circle(*((x[i], y[i]) for i in rows[k])))
    assert np.isinf(circles(np.array([0.0, 1, 2]), np.zeros(3), np.array([[0, 1, 2]]))[2][0])


def test_looked_up_points_are_the_first_of_all():
    """Points for doubtful triangles: outside the window, not brought before, inside the circle or beyond the side, nearest first."""
    r = np.random.default_rng(5)
    points = pd.DataFrame({"state_id": 0, "j": 0, "poi_id": r.permutation(400), "x": r.random(400) * 200, "y": r.random(400) * 200})
    doubts = pd.DataFrame({"state_id": 0, "ox": 0, "oy": 0, "src": [1, 2], "dst": [3, 4], "third": pd.array([5, None], "Int64"), "rings": 1, "cx": [90.0, 100.0], "cy": [90.0, 100.0], "ux": [None, 0.6], "uy": [None, 0.8], "r": [60.0, None], "have": [list(range(20)), None]})
    got = delaunay._look_kernel(10.0)(points, doubts)
    out = points[(points.x >= 70) | (points.y >= 70)]
    near = out.assign(far=np.hypot(out.x - 90, out.y - 90))
    near = near[(near.far <= 60) & ~near.poi_id.isin(range(20))].sort_values(["far", "poi_id"])
    beyond = out.assign(far=-(0.6 * (out.y - 100) - 0.8 * (out.x - 100)))
    beyond = beyond[beyond.far <= 0].sort_values(["far", "poi_id"])
    assert got[got.src == 1].poi_id.tolist() == near.poi_id.tolist()[: delaunay.BROUGHT]
    assert got[got.src == 2].poi_id.tolist() == beyond.poi_id.tolist()[: delaunay.BROUGHT]


def test_infomax_takes_touching_regions_as_pairs():
    r = np.random.default_rng(0)
    region, adj = np.arange(40) % 4, np.eye(4, k=1) + np.eye(4, k=-1)
    x = r.normal(size=(40, 5))
    plain, pairs = Infomax(x, region, adj, 3, 1), Infomax(x, region, (4, *np.nonzero(adj)), 3, 1)
    assert plain.fit(20) == pairs.fit(20)
    order = r.permutation(40)
    moved = Infomax(x[order], region, adj, 3, 1)
    moved.p = plain.p
    elsewhere = np.empty_like(region)
    elsewhere[order] = region
    v = plain.encode(x)
    assert np.allclose(plain._pool(v["h"], v["s"], elsewhere)["z"], moved.encode(x[order])["z"])  # shuffled features are the same rows in other regions
    mean = (adj + np.eye(4)) / (adj.sum(axis=1, keepdims=True) + 1)
    assert np.allclose(v["z"], mean @ v["pooled"]) and np.allclose(plain._spread(v["z"], back=True), mean.T @ v["z"])


def test_forest_grows_from_its_formula():
    r = np.random.default_rng(0)
    x, y, q = np.round(r.normal(size=(60, 7))), np.round(r.normal(size=60), 1), r.normal(size=(9, 7))

    def plain(least):  # trees node by node, gains by definition, in the same order of draws
        g, tried, total = np.random.default_rng(1), 2, np.zeros(len(q))
        for _ in range(5):
            open_ = [(g.integers(0, 60, 60), np.arange(len(q)))]
            while open_:
                own, at = open_.pop()
                best, t = (1e-12, None), y[own]
                if len(own) >= 2 * least and np.ptp(t):
                    columns = g.permutation(7)[:tried]
                    orders = [np.argsort(x[own, c], kind="stable") for c in columns]
                    for k in range(least, len(own) - least + 1):
                        for c, o in zip(columns, orders, strict=True):
                            v, s = x[own, c][o], t[o]
                            left = np.cumsum(s)[k - 1] if k < len(own) else 0
                            if k < len(own) and v[k] != v[k - 1]:
                                gain = left**2 / k + (t.sum() - left) ** 2 / (len(own) - k) - t.sum() ** 2 / len(own)
                                if gain > best[0]:
                                    best = (gain, c, (v[k - 1] + v[k]) / 2)
                if best[1] is None:
                    total[at] += t.mean()
                else:
                    low, side = x[own, best[1]] <= best[2], q[at, best[1]] <= best[2]
                    open_ += [(own[low], at[side]), (own[~low], at[~side])]
        return total / 5

    for least in (1, 3):
        assert np.allclose(FITTERS["forest"](x, y, trees=5, least=least)(q), plain(least))


def test_forest_of_a_state_takes_seconds():
    r = np.random.default_rng(0)
    x = r.normal(size=(960, 30))
    calls = []

    class Counted(np.ndarray):
        def __array_function__(self, function, types, args, kwargs):
            calls.append(function.__name__)
            return super().__array_function__(function, types, args, kwargs)

    FITTERS["forest"](x.view(Counted), x[:, 0] + r.normal(size=960), trees=1)
    assert "take_along_axis" not in calls and "ptp" not in calls  # helpers that cost more than the sums of small nodes


def test_forest_by_levels_grows_from_its_formula():
    """One column leaves no choice of features: the trees follow from the bootstrap rows alone."""
    from poiweave.operators.learners import level_forest

    r = np.random.default_rng(0)
    x, y, q = np.round(r.normal(size=(60, 1)), 1), np.round(r.normal(size=60), 1), r.normal(size=(9, 1))

    def plain(own, at, least, out):
        t, v = y[own], np.unique(x[own, 0])
        best = (1e-12, None)
        for cut in (v[1:] + v[:-1]) / 2 if len(own) >= 2 * least else ():
            a, b = t[x[own, 0] <= cut], t[x[own, 0] > cut]
            gain = len(a) * len(b) / len(t) * (a.mean() - b.mean()) ** 2
            if min(len(a), len(b)) >= least and gain > best[0] + 1e-12:
                best = (gain, cut)
        if best[1] is None:
            out[at] += t.mean()
        else:
            for low in (True, False):
                plain(own[(x[own, 0] <= best[1]) == low], at[(q[at, 0] <= best[1]) == low], least, out)

    for least in (1, 3):
        for at_once in (60, 180, 20_000):  # the draws come tree by tree, however many grow together
            g, want = np.random.default_rng(1), np.zeros(9)
            for _ in range(5):
                plain(g.integers(0, 60, 60), np.arange(9), least, want)
            assert np.allclose(level_forest(x, y, trees=5, least=least, at_once=at_once)(q), want / 5)


def test_forest_by_levels_is_pure_and_learns():
    from poiweave.operators.learners import BULK, level_forest

    r = np.random.default_rng(0)
    x = np.round(r.normal(size=(300, 9)), 1)
    x[:40] = x[40:80]  # equal rows with other targets share a leaf
    y = 2 * x[:, 0] + x[:, 1] * x[:, 2] + 0.1 * r.normal(size=300)
    drawn = np.unique(np.random.default_rng(1).integers(0, 300, 300))
    lone = drawn[drawn >= 80]
    assert np.allclose(level_forest(x, y, trees=1)(x[lone]), y[lone])
    a, b = (f(x[:240], y[:240])(x[240:]) for f in (BULK["forest"], FITTERS["forest"]))
    assert np.corrcoef(a, b)[0, 1] > 0.95 and np.sqrt(((a - y[240:]) ** 2).mean()) < 1.1 * np.sqrt(((b - y[240:]) ** 2).mean())
    assert np.array_equal(level_forest(x, y, trees=3)(x), level_forest(x, y, trees=3)(x)) and level_forest(x[:2], np.ones(2), trees=3)(x[:1])[0] == 1
