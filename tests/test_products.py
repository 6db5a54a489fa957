"""Tuples as pairs of two sides' rows against the same tuples in memory."""

from __future__ import annotations

import numpy as np
import pytest

from joinspace import baselines, coreset, local, products, resident
from joinspace.region import Box, Region
from joinspace.space import JoinSpace
from joinspace.spec import WORKLOADS
from joinspace.tree import flat_tree


def scaled(spark, sf, name):
    space = JoinSpace.bind(spark, sf, WORKLOADS[name])
    box = space.root_box()
    return JoinSpace.bind(spark, sf, WORKLOADS[name], scale={c: float(s) for c, s in zip(space.coords, box.hi - box.lo, strict=True)})


@pytest.mark.parametrize(("name", "block"), [("w9", 1 << 16), ("w9", 40), ("w2", 1 << 10), ("w6", 1 << 16)])
def test_same_as_in_memory(spark, sf, name, block, monkeypatch):
    """Costs, weights, farthest and nearest tuples do not depend on how the tuples are made, nor on blocks."""
    monkeypatch.setattr(products, "BLOCK", block)
    monkeypatch.setattr(products, "THIN", min(block // 4, 1 << 12))
    monkeypatch.setattr(products, "NEAR", 1 << 9)
    space = scaled(spark, sf, name)
    p, w = baselines.materialized(space)
    pairs = products.of(space)
    x, v = pairs.held()
    assert len(pairs) == len(x) >= len(p) and pairs.weights.sum() == v.sum() == w.sum()
    q, back = np.unique(x, axis=0, return_inverse=True)
    assert (q == p[np.lexsort(p.T[::-1])]).all() and (np.bincount(back.ravel(), v) == w[np.lexsort(p.T[::-1])]).all()
    assert (pairs[::7] == x[::7]).all() and (pairs[np.array([3, 0])] == x[[3, 0]]).all() and (pairs[5] == x[5]).all()
    rng = np.random.default_rng(4)
    for k in (1, 5, 60):
        c = p[rng.choice(len(p), k)] + (0.01 if k == 5 else 0)
        for objective in ("center", "median", "means"):
            for metric in ("l2", "l1", "linf"):
                assert local.cost(pairs, pairs.weights, c, objective, metric) == pytest.approx(local.cost(p, w, c, objective, metric))
        assert local.weight_near(pairs, pairs.weights, c, 0.2) == local.weight_near(p, w, c, 0.2)
    away = rng.random((9, p.shape[1]))
    assert local.assign(away, pairs)[1] == pytest.approx(local.assign(away, p)[1])
    assert (local.assign(p[:50], pairs)[1] == 0).all() and (local.snap(pairs, p[:4]) == p[:4]).all()
    own, flat = local.farthest_first(pairs, 5), local.farthest_first(x, 5)
    assert local.cost(x, v, own, "center") == pytest.approx(local.cost(x, v, flat, "center"))
    r = local.cost(x, v, flat, "center")
    assert local.cost(p, w, local.cover(pairs, 5, r), "center") <= 2 * r * (1 + 1e-9) and local.cover(pairs, 1, r / 9) is None


def test_solvers(spark, sf):
    """The solvers' sums over pairs are those over the tuples, and the centres are about as good."""
    space = scaled(spark, sf.replace("sf0.001", "sf0.01"), "w9")
    pairs = products.of(space)
    x, v = pairs.held()
    c = x[[0, 40, 200, 300]]
    (a, s), (b, t) = local._sums(pairs, None, c), local._sums(x, v, c)
    assert a == pytest.approx(b) and s == pytest.approx(t)
    for power, objective in ((1, "median"), (2, "means")):
        want = [local.cost(x, v, np.concatenate([c[:i], x[[77]], c[i + 1 :]]), objective) for i in range(4)]
        assert pairs.swapped(c, x[77], power) == pytest.approx(want)
        got, value = local.solver(objective)(pairs, pairs.weights, 4)
        assert value == pytest.approx(local.cost(x, v, got, objective)) and value <= 1.15 * local.solver(objective)(x, v, 4)[1]
        assert local.assign(got, x)[1].max() < 1e-9
    got = pairs.draw(40_000, np.random.default_rng(1))
    for h in Box.around(x).halves()[:2]:
        assert abs(h.contains(got).mean() - v[h.contains(x)].sum() / v.sum()) < 0.02


def test_trees_over_pairs(spark, sf):
    space = scaled(spark, sf.replace("sf0.001", "sf0.01"), "w9")
    pairs = products.of(space)
    x, v = pairs.held()
    t = flat_tree(pairs, pairs.weights, eps=1e-12, leaf_cap=64)
    d = np.linalg.norm(x - x[9], axis=1)
    assert t.n == v.sum() and t.count(x[9], 0.3) == v[d <= 0.3].sum() and t.deactivate(x[9], 0.3) == v[d <= 0.3].sum()
    assert t.reported() == t.report()[1].sum() == v[d > 0.3].sum()
    box = Box.around(x)
    r = Region(box, Box(box.lo, (box.lo + box.hi) / 2))
    n, reps = t.backend.count_and_represent_regions([r])
    assert n[0] == v[r.contains(x)].sum() and r.contains(reps[0]) and r.contains(t.backend.sample_regions([r], [200])[0]).all()


def test_large_joins_are_not_refused(spark, sf):
    """More distinct tuples than may be held: they come as pairs, if their sides fit, and are refused otherwise."""
    space = JoinSpace.bind(spark, sf, WORKLOADS["w9"])
    p, w = baselines.materialized(space)
    again, v = baselines.materialized(space, most=len(p) // 2)
    assert isinstance(again, products.Products) and v.sum() == w.sum()
    assert products.of(space, 10) is None and products.of(JoinSpace.bind(spark, sf, WORKLOADS["w11"])) is None


def test_points_of_boxes_lie_near_the_mean():
    """Of a box's least tuple every cost was off to one side: by 0.9 with rings of the w9 queries."""
    rng = np.random.default_rng(5)
    x = rng.random((6000, 2))
    t = flat_tree(x, leaf_cap=100)
    box = Box(np.array([0.1, 0.2]), np.array([0.7, 0.9]))
    inside = x[box.contains(x)]
    got = t.middle_of_box(box)
    assert (inside == got).all(1).any() and np.linalg.norm(got - inside.mean(0)) < 0.1
    t.deactivate(got, 0.2)
    again = t.middle_of_box(box)
    assert (inside == again).all(1).any() and np.linalg.norm(again - got) > 0.2
    core = coreset.from_boxes(t, coreset.grid(np.array([[0.5, 0.5]]), 0.5, 0.8))
    live = t.report()[0]
    for c in (np.zeros((1, 2)), np.ones((1, 2))):
        assert abs(local.cost(core.points, core.weights, c, "means") / local.cost(live, np.ones(len(live)), c, "means") - 1) < 0.15


def test_groups_keep_only_their_rows(spark, sf):
    """The orders of other customers stayed in each group's relations, which were then too large for a tree in memory."""
    space = JoinSpace.bind(spark, sf, WORKLOADS["w8"], cats=["segment"])
    part = space.group("segment", "BUILDING")
    small = part.reduced()
    box = space.root_box()
    assert small.size() == part.size() and list(small.count(box.halves()[:2])) == list(part.count(box.halves()[:2]))
    values = sum(f.count() * len(f.columns) for f in small.frames.values())
    assert values < sum(f.count() * len(f.columns) for f in part.frames.values()) / 2
    assert resident.of(part, values) is None and resident.of(small, values) is not None
    small.release()
