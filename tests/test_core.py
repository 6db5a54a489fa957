"""Geometry, trees, solvers and query structure against brute force, in memory."""

from __future__ import annotations

from fractions import Fraction
from itertools import combinations

import numpy as np
import pytest

from joinspace import baselines, coreset, diversity, hypergraph, kcenter, kmeans, local, measures, mixed, radius
from joinspace.region import Box, Region, centroid_shrink, fair_split, tight
from joinspace.spec import WORKLOADS
from joinspace.tree import flat_tree, sample_size


@pytest.fixture(scope="module")
def blobs():
    rng = np.random.default_rng(1)
    return np.concatenate([rng.normal(c, 1, (300, 3)) for c in ((0, 0, 0), (20, 0, 0), (0, 30, 0), (5, 5, 50))])


def test_structure():
    widths = {n: hypergraph.fhw(s) for n, s in WORKLOADS.items()}
    assert widths["w4t"] == Fraction(3, 2) and widths["w4"] == 2 and all(widths[n] == 1 for n in widths if n not in ("w4", "w4t"))
    assert hypergraph.edge_cover(WORKLOADS["w4t"].edges())[0] == Fraction(3, 2)
    for n, s in WORKLOADS.items():
        tree = hypergraph.join_tree(s)
        assert (tree is None) == (n in ("w4", "w4t"))
        if tree:
            assert tree.upward()[-1] == tree.root and hypergraph.connected_attributes(s.edges(), tree)


@pytest.mark.parametrize("hole", [((2, 2), (4, 4)), ((0, 0), (4, 8)), ((0, 3), (8, 4)), ((1, 0), (2, 8))])
def test_slabs(hole):
    r = Region(Box(np.zeros(2), np.full(2, 8.0)), Box(np.array(hole[0], float), np.array(hole[1], float)))
    grid = np.array([(x, y) for x in np.arange(0, 8, 0.5) for y in np.arange(0, 8, 0.5)])
    inside = np.stack([s.contains(grid) for s in r.slabs()]).sum(0)
    assert len(r.slabs()) <= 4 and (inside == r.contains(grid).astype(int)).all()


def test_midpoint_boxes():
    rng = np.random.default_rng(2)
    root = Box(np.zeros(2), np.full(2, 64.0))
    for _ in range(50):
        p = rng.integers(0, 64, (5, 2)).astype(float)
        b = tight(root, p.min(0), p.max(0))
        assert b.contains(p).all() and b.inside(root)
        for h in fair_split(Region(root, b)):
            assert h.hole is None or h.hole.inside(h.outer)


def test_shrink_balance(blobs):
    box = Box.around(blobs)
    (outer, _), (inner, _) = centroid_shrink(Region(box), blobs)
    share = inner.contains(blobs).mean()
    assert 1 / 3 - 1e-9 <= share <= 2 / 3 + 1e-9
    assert (inner.contains(blobs) ^ outer.contains(blobs)).all()

    def leaves(parts):
        for r, below in parts:
            yield from (leaves(below) if below else [r])

    for sub in (blobs, blobs[blobs[:, 2] > 10]):
        found = list(leaves(centroid_shrink(Region(box, inner.outer), sub[~inner.outer.contains(sub)])))
        hit = np.stack([r.contains(blobs) for r in found]).sum(0)
        assert (hit[~inner.outer.contains(blobs)] == 1).all() and (hit[inner.outer.contains(blobs)] == 0).all()


@pytest.mark.parametrize("shape", ["shrink", "exact", "halve", "quad", "median"])
def test_tree_partitions_and_sandwich(blobs, shape):
    tree = flat_tree(blobs, leaf_cap=8, shape=shape, draws=64, least_draws=8, eps=0.3)
    rng = np.random.default_rng(3)
    for _ in range(15):
        c, r = blobs[rng.integers(len(blobs))], float(rng.uniform(0.5, 25))
        d = np.linalg.norm(blobs - c, axis=1)
        n = tree.count(c, r)
        assert (d <= r).sum() <= n <= (d <= 1.3 * r * (1 + 1e-9)).sum()
    mark = tree.snapshot()
    left = len(blobs)
    for _ in range(5):
        left -= tree.deactivate(blobs[rng.integers(len(blobs))], 3.0)
        assert tree.active == left == sum(x.active for x in tree.frontier()) and tree.report()[1].sum() == left
        if left:
            rep = tree.representative()
            assert (np.abs(tree.report()[0] - rep).sum(1) == 0).any()
    tree.restore(mark)
    assert tree.active == len(blobs)


def test_tree_height_and_duplicates():
    p = np.repeat(np.array([[0.0, 0.0], [1e-9, 0.0], [5.0, 5.0]]), [700, 200, 100], axis=0)
    tree = flat_tree(p, leaf_cap=1, shape="exact").build()
    assert tree.stats.height < 60 and sum(x.active for x in tree.frontier()) == 1000
    tree = flat_tree(p, leaf_cap=10, draws=64)
    assert tree.count(np.array([0.0, 0.0]), 1.0) == 900


def test_sampling_is_uniform(blobs):
    tree = flat_tree(blobs, leaf_cap=50, draws=200)
    tree.deactivate(blobs[0], 4.0)
    got = tree.sample(6000)
    live = tree.report()[0]
    names = {tuple(x): i for i, x in enumerate(live)}
    seen = np.bincount([names[tuple(x)] for x in got], minlength=len(live))
    assert measures.uniformity(seen.astype(float), np.full(len(live), 6000 / len(live))) < 1.3
    assert sample_size(0.1, 1000) > sample_size(0.2, 1000)


def test_kth_difference():
    v = np.random.default_rng(4).integers(0, 60, 25).astype(float)
    d = sorted(abs(a - b) for a, b in combinations(v, 2))
    for z in (1, 5, 100, len(d)):
        assert radius.kth_difference(v, z) == pytest.approx(d[z - 1])


def test_cover_and_optimum():
    rng = np.random.default_rng(6)
    p = rng.uniform(0, 10, (24, 2))
    w = np.ones(24)
    _, best = local.exact(p, w, 3, "center")
    got = local.cover(p, 3, best)
    assert got is not None and local.cost(p, w, got, "center") <= 2 * best + 1e-9
    tree = flat_tree(p, leaf_cap=4, eps=0.2, draws=16)
    got = kcenter.cover(tree, 3, best)
    assert got is not None and local.cost(p, w, got, "center") <= 2.4 * best + 1e-9
    assert local.cost(p, w, local.cover_search(p, 3)[0], "center") <= 2 * best + 1e-9
    assert local.cost(p, w, local.farthest_first(p, 3), "center") <= 2 * best + 1e-9
    assert kcenter.sample_bound(tree, 3) <= best + 1e-9
    for objective in ("median", "means"):
        assert local.solver(objective)(p, w, 3)[1] <= 1.3 * local.exact(p, w, 3, objective)[1]


def test_kmeans_round_covers_half(blobs):
    tree = flat_tree(blobs, leaf_cap=100, eps=0.25)
    radii = kmeans.levels(8.0, tree.n)
    assert radii[-1] == float("inf") and radii[1] == 2 * radii[0]
    drawn, charge, facts = kmeans.one_round(tree, 4, 2, radii, kmeans.PRACTICAL, 1)
    gone = facts["covered"]
    assert 2 * gone >= facts["tau"] and sum(facts["counts"]) == gone and charge >= 0


def test_coresets(blobs):
    tree = flat_tree(blobs, leaf_cap=50, eps=0.1, draws=200)
    c = local.farthest_first(blobs, 4)
    w = np.ones(len(blobs))
    core = coreset.adaptive(tree, c, 0.3, 0.2)
    assert core.weights.sum() == len(blobs) and len(core.points) < len(blobs)
    sets = [blobs[np.random.default_rng(s).choice(len(blobs), 4)] for s in range(8)]
    assert measures.coreset_error(blobs, w, core.points, core.weights, sets, "means") < 0.2
    boxes = coreset.grid(c, local.cost(blobs, w, c, "center"), 1.0)
    literal = coreset.from_boxes(tree, boxes)
    assert literal.weights.sum() == len(blobs) and tree.active == len(blobs)


def test_line_and_categories():
    v, w = np.array([1.0, 2, 8, 9, 20]), np.array([1.0, 1, 2, 1, 3])
    best = min(
        sum(((w[s] * (v[s] - np.average(v[s], weights=w[s])) ** 2).sum()) for s in (slice(0, i), slice(i, j), slice(j, 5)))
        for i, j in combinations(range(1, 5), 2)
    )
    assert local.kmeans_1d(v, w, 3)[1] == pytest.approx(best)
    assert mixed.categorical_centers({"a": 5, "b": 7, "c": 1}, 2) == (["b", "a"], 1.0)


def test_diversity_values():
    square = np.array([[0.0, 0], [0, 1], [1, 0], [1, 1]])
    assert local.diversity(square, "edge") == 1 and local.diversity(square, "tree") == 3
    assert local.diversity(square, "cycle") == pytest.approx(4) and local.diversity(square, "matching") == 2
    assert local.diversity(square, "pseudoforest") == 4 and local.diversity(square, "clique") == pytest.approx(4 + 2 * 2**0.5)
    rng = np.random.default_rng(8)
    p = rng.uniform(0, 10, (12, 2))
    best = max(local.diversity(p[list(c)], "edge") for c in combinations(range(12), 4))
    assert local.diversity(local.farthest_first(p, 4), "edge") >= best / 2
    groups = np.array(["a"] * 6 + ["b"] * 6)
    at = local.fair_max_min(p, groups, {"a": 2, "b": 2})
    real = max(local.diversity(p[list(x + y)], "edge") for x in combinations(range(6), 2) for y in combinations(range(6, 12), 2))
    assert local.diversity(p[at], "edge") == pytest.approx(real)
    at = local.fair_max_sum(p, groups, {"a": 2, "b": 2})
    assert sorted(groups[at]) == ["a", "a", "b", "b"]


@pytest.mark.parametrize(("k", "most"), [(12, 30), (60, 40)])
def test_farthest_first_above_the_cap(k, most):
    """k points come back, each at least (1 - eps) times as far from those before as any tuple is."""
    p = np.random.default_rng(9).uniform(0, 100, (500, 2))
    got = diversity.farthest_first(None, k, 0.5, flat_tree(p, leaf_cap=100, eps=0.1), most=most)
    assert len(np.unique(got, axis=0)) == k
    for i in range(1, k):
        assert local.assign(got[i : i + 1], got[:i])[1][0] >= 0.5 * local.assign(p, got[:i])[1].max() - 1e-9


def test_complement_pieces():
    b = Box(np.zeros(2), np.full(2, 4.0))
    parts = baselines._minus(b, Box(np.array([1.0, 1]), np.array([2.0, 9])))
    grid = np.array([(x, y) for x in np.arange(0, 4, 0.25) for y in np.arange(0, 4, 0.25)])
    hole = Box(np.array([1.0, 1]), np.array([2.0, 9])).contains(grid)
    assert (np.stack([p.contains(grid) for p in parts]).sum(0) == (~hole).astype(int)).all()


@pytest.mark.parametrize("metric", ["l2", "l1", "linf"])
def test_assign_many_centres(metric, monkeypatch):
    """Blocks of points only meet centres that can be nearest to one of them; numbers and distances are those of the full comparison, ties included."""
    rng = np.random.default_rng(6)
    points, pairs = rng.random((20_000, 2)).round(3), []
    centres = points[rng.integers(0, len(points), 2000)]
    full = local.pairwise(points, centres, metric)
    plain = local.pairwise
    monkeypatch.setattr(local, "pairwise", lambda a, b, m: pairs.append(len(a) * len(b)) or plain(a, b, m))
    at, distance = local.assign(points, centres, metric)
    assert (at == full.argmin(1)).all() and (distance == full.min(1)).all()
    assert sum(pairs) < full.size / 10


def test_distances_of_short_and_long_tuples():
    rng = np.random.default_rng(7)
    for d in (1, 2, 5, 7, 9):
        a, b = rng.random((30, d)), rng.random((20, d))
        want = np.sqrt(((a[:, None, :] - b[None, :, :]) ** 2).sum(-1))
        assert (local.pairwise(a, b) == want).all() and (local.norm(a) == np.sqrt((a * a).sum(-1))).all()


def test_swap_keeps_its_result(monkeypatch):
    """What is left without a centre comes from the two least distances, not from all distances for each try; centres and cost are the same."""
    def plain(points, weights, centres, objective, seed=42, tries=60):
        rng, power = np.random.default_rng(seed), 1 if objective == "median" else 2
        d = local.pairwise(points, centres) ** power
        now = float((weights * d.min(1)).sum())
        for _ in range(tries):
            i = int(rng.choice(len(points), p=weights / weights.sum()))
            new = local.norm(points - points[i]) ** power
            best, at = now, -1
            for j in range(len(centres)):
                v = float((weights * np.minimum(new, np.delete(d, j, 1).min(1) if len(centres) > 1 else np.inf)).sum())
                if v < best * (1 - 1e-9):
                    best, at = v, j
            if at >= 0:
                centres = centres.copy()
                centres[at], now = points[i], best
                d[:, at] = new
        return centres, now

    rng = np.random.default_rng(8)
    points, weights = rng.random((3000, 2)), rng.random(3000)
    for k, objective in ((1, "means"), (2, "median"), (6, "means")):
        want = plain(points, weights, points[:k], objective)
        with monkeypatch.context() as m:
            m.setattr(np, "delete", None)
            got = local.swap(points, weights, points[:k], objective)
        assert (got[0] == want[0]).all() and got[1] == want[1]
        at, distance = local.assign(points, points[:k])
        full = local.pairwise(points, points[:k])
        assert (at == full.argmin(1)).all() and (distance == full.min(1)).all()


@pytest.mark.parametrize("listed", [2, 2_000_000])
def test_rank_is_found_in_few_counts(monkeypatch, listed):
    """Bisection took 60 counts of all pairs for each rank; differences are the same up to 1e-10."""
    rng = np.random.default_rng(8)
    pool = radius.Pool([np.round(rng.random(300) * 11, 2), rng.gamma(2, 5, 200_000)])
    monkeypatch.setattr(radius, "LISTED", min(listed, 50))
    small = radius.Pool([np.round(rng.random(60), 2), rng.random(80) ** 3])
    every = np.sort(np.concatenate([np.abs(v[:, None] - v[None, :])[np.triu_indices(len(v), 1)] for v in small.values]))
    for z in (1, 2, 50, len(every) // 2, len(every) - 1, len(every)):
        assert every[z - 1] * (1 - 1e-12) <= small.at_rank(z) <= every[z - 1] * (1 + 2e-10)
    if listed > 2:
        monkeypatch.setattr(radius, "LISTED", 20_000)
    plain, asked = radius.pairs_up_to, []
    monkeypatch.setattr(radius, "pairs_up_to", lambda v, x: asked.append(x) or plain(v, x))
    for z in (1000, pool.total // 7, pool.total // 2):
        asked.clear()
        d = pool.at_rank(z)
        assert len(asked) <= (2 * 60 if listed == 2 else 2 * 30)
        assert sum(plain(v, d) for v in pool.values) >= z > sum(plain(v, d * (1 - 1e-9)) for v in pool.values)
    v = pool.values[1]
    assert plain(v, 0.5) == int((np.searchsorted(v, v + 0.5, side="right") - np.arange(1, len(v) + 1)).sum())
