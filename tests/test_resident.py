"""Join spaces in memory against Spark's messages."""

from __future__ import annotations

import numpy as np
import pytest

from joinspace import baselines, diversity, mixed, radius, resident, tree
from joinspace.region import Box, Region
from joinspace.space import JoinSpace
from joinspace.spec import WORKLOADS
from joinspace.tree import SpaceBackend


@pytest.mark.parametrize("name", ["w9", "w6", "w11"])
def test_same_as_spark(spark, sf, name):
    space = JoinSpace.bind(spark, sf, WORKLOADS[name]).cached()
    near = resident.of(space)
    assert near is not None and near.size() == space.size()
    root, rng = space.root_box(), np.random.default_rng(3)
    ends = root.lo + np.sort(rng.random((12, 2, len(root.lo))), axis=1) * (root.hi - root.lo)
    boxes = [root, *[Box(a, z) for a, z in ends]]
    (n, reps), (m, seen) = space.count_and_represent(boxes), near.count_and_represent(boxes)
    assert list(n) == list(m)
    assert all((a is None and b is None) or (a == b).all() for a, b in zip(reps, seen, strict=True))
    box = next(b for b, c in sorted(zip(boxes, n, strict=True), key=lambda x: x[1]) if c)
    middle = (box.lo + box.hi) / 2
    for r in (Region(box), Region(box, Box(box.lo, middle))):
        (p, w), (q, v) = space.report_regions([r])[0], near.report_regions([r])[0]
        by = np.lexsort(p.T[::-1])
        order = np.lexsort(q.T[::-1])
        assert (p[by] == q[order]).all() and (w[by] == v[order]).all()
        assert space.reported_weight([r]) == near.reported_weight([r]) == w.sum()
        assert r.contains(near.sample_regions([r], [500])[0]).all() and len(near.sample_regions([r], [500])[0]) in (0, 500)


def test_draws_are_even(spark, sf):
    near = resident.of(JoinSpace.bind(spark, sf, WORKLOADS["w9"]))
    points, w = near.report_regions([Region(near.root_box())])[0]
    got = near.sample_regions([Region(near.root_box())], [20_000])[0]
    for box in near.root_box().halves()[:2]:
        for b in box.halves()[:2]:
            assert abs(b.contains(got).mean() - w[b.contains(points)].sum() / w.sum()) < 0.02


def test_large_relations_stay_with_spark(spark, sf):
    space = JoinSpace.bind(spark, sf, WORKLOADS["w9"])
    assert resident.of(space, 10) is None
    assert SpaceBackend(space, 10).space is space and SpaceBackend(space).space is not space


def test_materialized_is_limited_by_what_it_holds(spark, sf):
    """Copies of a tuple are one row: a join of many of them is not refused."""
    space = JoinSpace.bind(spark, sf, WORKLOADS["w11"])
    points, w = baselines.materialized(space)
    assert space.size() == w.sum() > len(points)
    again, v = baselines.materialized(space, most=len(points))
    assert len(again) == len(points) and v.sum() == w.sum()
    with pytest.raises(ValueError):
        baselines.materialized(space, most=len(points) - 1)


def test_walk_asks_centres_near_the_parent(monkeypatch):
    """Many centres: nodes only meet those within reach of their parent, and the count is the same."""
    rng = np.random.default_rng(2)
    points, centres = rng.random((4000, 2)), rng.random((300, 2))
    asked = []
    plain = tree.distance_bounds
    monkeypatch.setattr(tree, "distance_bounds", lambda box, c, metric: asked.append(len(c)) or plain(box, c, metric))
    t = tree.flat_tree(points, eps=1e-12, leaf_cap=20)
    d = np.sqrt(((points[:, None] - centres[None]) ** 2).sum(-1)).min(1)
    assert t.count(centres, 0.02) == (d <= 0.02).sum()
    assert sum(asked) < 0.2 * len(asked) * len(centres)
    assert t.deactivate(centres, 0.03) == (d <= 0.03).sum() and t.reported() == t.report()[1].sum() == (d > 0.03).sum()


def test_inner_boxes_start_from_kept_rows(spark, sf):
    """Boxes inside boxes: the rows looked at follow the enclosing box, counts and least tuples stay Spark's."""
    space = JoinSpace.bind(spark, sf, WORKLOADS["w6"]).cached()
    near, boxes, box = resident.of(space), [], space.root_box()
    for i in range(7):
        box = box.halves()[i % 2]
        boxes.append(box)
    (n, reps), (m, seen) = space.count_and_represent(boxes), near.count_and_represent(boxes)
    assert list(n) == list(m)
    assert all((a is None and b is None) or (a == b).all() for a, b in zip(reps, seen, strict=True))
    slot = near._around(boxes[-1])
    assert slot is not None and near.held_many[slot] < sum(map(len, near.w.values())) / 4
    assert near.root_box().same(space.root_box())


def test_reported_weight_is_summed_in_parts(spark, sf, monkeypatch):
    space = JoinSpace.bind(spark, sf, WORKLOADS["w6"])
    near = resident.of(space)
    monkeypatch.setattr(resident, "CHUNK", 500)
    parts = [len(x) for _, x, _ in near._picked(near.root_box(), resident.CHUNK)]
    most = near._weighted(near.root_box())[near.tree.root][1].max()
    assert len(parts) > 10 and max(parts) <= resident.CHUNK + most
    assert near.reported_weight([Region(near.root_box())]) == near.size() == space.size()


def test_classes_in_memory(spark, sf):
    """Class counts and reports of a tree pass messages in memory too, and agree with Spark's."""
    own = {"returnflag": ["R", "N"], "segment": ["BUILDING", "MACHINERY", "FURNITURE"]}
    space = mixed.classed(JoinSpace.bind(spark, sf, WORKLOADS["w7"], cats=list(own)), own)
    near, far = tree.ClassBackend(space), tree.ClassBackend(space, 10)
    assert isinstance(near.space, resident.ResidentSpace) and far.space is space
    box = near.root_box()
    inner = Box(box.lo + (box.hi - box.lo) / 4, box.lo + (box.hi - box.lo) / 2)
    regions = [Region(box), Region(inner), Region(box, inner)]
    assert near.count_classes(regions) == far.count_classes(regions)
    for (p, w, tags), (q, v, names) in zip(near.report_classes(regions[1:2]), far.report_classes(regions[1:2]), strict=True):
        assert sorted(zip(map(tuple, p), w, tags)) == sorted(zip(map(tuple, q), v, names))


def test_radius_pool_by_columns(spark, sf, monkeypatch):
    """Base values come as columns, not as Python rows."""
    space = JoinSpace.bind(spark, sf, WORKLOADS["w8"])
    rows = space.value_pool().collect()
    monkeypatch.setattr("pyspark.sql.classic.dataframe.DataFrame.toPandas", None)
    for c, v in zip(space.coords, radius.pool(space).values, strict=True):
        assert list(v) == sorted(r["value"] for r in rows if r["attr"] == c)


def test_least_tuples_follow_the_root(spark, sf):
    """Only rows that the root's least rows meet are put in order."""
    space = JoinSpace.bind(spark, sf, WORKLOADS["w1"]).cached()
    near, box = resident.of(space), space.root_box()
    rows = near._weighted(box)
    kept = near._under(rows, rows[near.tree.root][0][:1])
    assert all(len(kept[n]) < len(rows[n][0]) / 4 for n in near.names)
    boxes = [box, *box.halves()[:2]]
    for a, b in zip(space.representative(boxes), near.representative(boxes), strict=True):
        assert (a == b).all()


def repeated(spark, sf, folder) -> list[JoinSpace]:
    """w9, and w9 on customers five times and suppliers three times."""
    for name, times in (("customer", 5), ("supplier", 3), ("nation", 1)):
        f = spark.read.parquet(f"{sf}/{name}.parquet")
        f.crossJoin(spark.range(times).toDF("copy")).drop("copy").write.parquet(f"{folder}/{name}.parquet")
    return [JoinSpace.bind(spark, x, WORKLOADS["w9"]) for x in (sf, str(folder))]


def test_leaves_of_repeated_tuples(spark, sf, tmp_path):
    """Tables that repeat their rows make the same leaves, heavier: a tree opens no more nodes than on the tables themselves."""
    once, often = repeated(spark, sf, tmp_path)
    near, many = resident.of(once), resident.of(often)
    box = near.root_box()
    inner = Box(box.lo + (box.hi - box.lo) / 4, box.hi - (box.hi - box.lo) / 4)
    regions = [Region(box), Region(inner), Region(box, inner)]
    rows = [sum(len(x) for b in r.slabs() for _, x, _ in many._picked(b)) for r in regions]
    assert many.count_rows(regions) == rows and many.size() == 15 * near.size() > many.count_rows(regions)[0]
    a, b = (tree.lazy_tree(x, eps=0.1, leaf_cap=4, leaf_rows=True) for x in (once, often))
    centres = near.sample_regions([Region(box)], [40])[0]
    points, w = many.report_regions([Region(box)])[0]
    d = np.sqrt(((points[:, None] - centres[None]) ** 2).sum(-1)).min(1)
    assert w[d <= 300].sum() <= b.deactivate(centres, 300) <= w[d <= 330 * (1 + 1e-9)].sum()
    assert b.active == b.reported() == b.report()[1].sum()
    a.deactivate(centres, 300)
    assert a.stats.nodes > 10 and b.stats.nodes < 1.5 * a.stats.nodes


@pytest.mark.parametrize("kind", ["edge", "tree", "matching", "pseudoforest"])
def test_diversity_of_repeated_tuples(spark, sf, tmp_path, monkeypatch, kind):
    """Repeated rows open no more nodes, and the subset is as diverse as on the tables themselves, up to the method's factor."""
    trees, plain = [], tree.lazy_tree
    monkeypatch.setattr(diversity, "lazy_tree", lambda *a, **o: trees.append(plain(*a, **o)) or trees[-1])
    (x, a), (y, b) = (diversity.solve(s, 4, kind, leaf_cap=4) for s in repeated(spark, sf, tmp_path))
    points = resident.of(JoinSpace.bind(spark, sf, WORKLOADS["w9"])).report_regions([Region(trees[0].root.region.outer)])[0][0]
    assert all((points == p).all(1).any() for p in (*x, *y)) and len(x) == len(y) == 4
    assert b >= a / 3 and trees[1].n == 15 * trees[0].n
    assert trees[0].stats.nodes > 10 and trees[1].stats.nodes < 1.3 * trees[0].stats.nodes
