"""What the methods are compared with."""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import functions as F

from . import local, mixed, products
from .coreset import _grouped
from .kcenter import Solution
from .measures import nearest_class
from .region import Box
from .space import JoinSpace


def materialized(space: JoinSpace, most: int = 5_000_000) -> tuple[np.ndarray, np.ndarray] | tuple[products.Products, products.Weights]:
    """All tuples on the driver, equal ones summed. More than `most` are not held but made from two sides of the join whenever a solver goes
    through them; refused where the sides are too large for that, too, or there is only one relation."""
    if space.size() > most and (pairs := products.of(space)) is not None and len(pairs) > most:
        return pairs, pairs.weights
    rows = space.materialize().groupBy(*space.coords).agg(F.sum("w").cast("double").alias("w"))
    if space.size() > most and rows.count() > most:
        raise ValueError("the join is too large to materialise")
    held = rows.toArrow()
    return np.stack([held[c].to_numpy() for c in space.coords], 1), held["w"].to_numpy()


def materialize_then(space: JoinSpace, k: int, objective: str, solver=None, most: int = 5_000_000) -> Solution:
    """Join first, cluster then."""
    p, w = materialized(space, most)
    c, v = (solver or local.solver(objective))(p, w, k)
    return Solution(c, v, {"rows": len(p)})


def materialize_then_spark(space: JoinSpace, k: int, seed: int = 42) -> Solution:
    """Join first, then the k-means of Spark ML with weights; centres are not snapped."""
    from pyspark.ml.clustering import KMeans
    from pyspark.ml.feature import VectorAssembler

    rows = VectorAssembler(inputCols=space.coords, outputCol="x").transform(space.materialize().withColumn("w", F.col("w").cast("double")))
    model = KMeans(k=k, seed=seed, featuresCol="x", weightCol="w").fit(rows)
    return Solution(np.array(model.clusterCenters()), float(model.summary.trainingCost))


def hierarchical(space: JoinSpace, k: int, objective: str, eps: float = 0.5, seed: int = 42) -> Solution:
    """Relations are leaves of a balanced binary tree, in join-tree order. A node clusters its own coordinates to k centres:
    a leaf on its weighted rows, an inner node on the k * k products of its children's centres, weighted with the tuples
    nearest to each product. The root's k centres are the answer."""
    order = [n for n in reversed(space._need_tree().upward()) if space.owned[n][0]]
    solve, widest = local.solver(objective), 0

    def weights_of(names: list[str], centres: dict[str, np.ndarray]) -> dict[tuple, float]:
        """Join tuples by the nearest centre of each part, in one pass of messages."""
        classes: dict = {}
        for i, (part, c) in enumerate(centres.items()):
            mine = part.split("+")
            if len(mine) == 1:
                classes.setdefault(mine[0], {})[f"cls_{i}"] = nearest_class(space.owned[mine[0]][0], c)
        if len(classes) == len(centres):
            rows = space.count_classes(None, classes).collect()  # at most k * k rows
            return {tuple(r[f"cls_{i}"] - 1 for i in range(len(centres))): float(r["cnt"]) for r in rows}
        # a part over several relations is not separable: its classes are counted on weighted boxes of a sample
        tuples = space.sample([space.root_box()], [20_000], seed)[0]
        n = space.size()
        at = {c: i for i, c in enumerate(space.coords)}
        out: dict[tuple, float] = {}
        idx = [local.assign(tuples[:, [at[c] for m in part.split("+") for c in space.owned[m][0]]], c)[0] for part, c in centres.items()]
        for key, m in zip(*np.unique(np.stack(idx, 1), axis=0, return_counts=True), strict=True):
            out[tuple(int(v) for v in key)] = n * m / max(1, len(tuples))
        return out

    def node(names: list[str]) -> np.ndarray:
        nonlocal widest
        if len(names) == 1:
            mine = space.owned[names[0]][0]
            owner = names[0]
            rows = space.upward(None, extra={owner: {f"v_{c}": F.col(c) for c in mine}})
            total = rows.count()
            if total > 200_000:  # a leaf's rows by cells of its own box
                f = space.frames[owner].agg(*[F.min(c).alias(f"a{i}") for i, c in enumerate(mine)], *[F.max(c).alias(f"b{i}") for i, c in enumerate(mine)]).first()
                side = [max((f[f"b{i}"] - f[f"a{i}"]) / 4096, 1e-12) for i in range(len(mine))]
                cells = [F.floor(F.col(f"v_{c}") / side[i]).alias(f"g{i}") for i, c in enumerate(mine)]
                rows = rows.groupBy(*cells).agg(F.sum("cnt").alias("cnt"), *[F.min(f"v_{c}").alias(f"v_{c}") for c in mine])
            r = rows.toPandas()
            p, w = r[[f"v_{c}" for c in mine]].to_numpy(float), r["cnt"].to_numpy(float)
            p, w, _ = _grouped(p, w, np.empty((0, p.shape[1])), float(np.ptp(p, axis=0).max()) / 2000 + 1e-12, 0.0)
            return solve(p, w, k, seed=seed)[0] if len(p) > k else p
        half = (len(names) + 1) // 2
        left, right = names[:half], names[half:]
        a, b = node(left), node(right)
        counts = weights_of(names, {"+".join(left): a, "+".join(right): b})
        widest = max(widest, len(counts))
        pts = np.array([np.concatenate([a[i], b[j]]) for i, j in counts])
        w = np.array(list(counts.values()))
        return solve(pts, w, k, seed=seed)[0] if len(pts) > k else pts

    centres = node(order)
    names = [c for n in order for c in space.owned[n][0]]
    at = [names.index(c) for c in space.coords]
    return Solution(centres[:, at], float("nan"), {"widest": widest})


def complement_boxes(space: JoinSpace, k: int, side: float) -> Solution | None:
    """Cover by cubes of half-side `side`: the complement of their union is kept as disjoint boxes, the next centre is a
    representative of the first non-empty one. None if k cubes do not do."""
    free, centres, pieces = [space.root_box()], [], 0
    while True:
        counts, reps = space.count_and_represent(free) if free else (np.zeros(0), [])
        live = [(b, r) for b, n, r in zip(free, counts, reps, strict=True) if n]
        if not live:
            return Solution(np.array(centres), side, {"pieces": pieces})
        if len(centres) == k:
            return None
        c = live[0][1]
        centres.append(c)
        cube = Box(c - side, np.nextafter(c + side, np.inf))
        free = [q for b, _ in live for q in _minus(b, cube)]
        pieces = max(pieces, len(free))


def _minus(b: Box, cube: Box) -> list[Box]:
    from .region import Region

    if not b.meets(cube):
        return [b]
    inner = Box(np.maximum(b.lo, cube.lo), np.minimum(b.hi, cube.hi))
    return [] if inner.same(b) else Region(b, inner).slabs()


def complement_search(space: JoinSpace, k: int, steps: int = 8) -> Solution:
    lo, hi = 0.0, float((space.root_box().hi - space.root_box().lo).max())
    best = complement_boxes(space, k, hi)
    for _ in range(steps):
        mid = (lo + hi) / 2
        got = complement_boxes(space, k, mid)
        if got is not None:
            best, hi = got, mid
        else:
            lo = mid
    return Solution(best.centres, hi * math.sqrt(len(space.coords)), best.trace)


def grid_coreset(space: JoinSpace, k: int, per: str = "attribute", seed: int = 42) -> tuple[np.ndarray, np.ndarray]:
    """Product of each attribute's (or relation's) own k centres with exact weights: the nearest product cell is the product
    of nearest centres, so class numbers ride in the messages and one pass counts every cell."""
    classes: dict = {}
    tables: list[tuple[list[str], str, np.ndarray]] = []
    for n, (mine, _) in space.owned.items():
        parts = [[c] for c in mine] if per == "attribute" else ([mine] if mine else [])
        for part in parts:
            rows = space.upward(None, extra={n: {f"v_{c}": F.col(c) for c in part}}).toPandas() if len(part) > 1 else space.value_weights(part).toPandas()
            w = rows["cnt" if len(part) > 1 else "w"].to_numpy(float)
            if len(part) == 1:
                v = rows["value"].to_numpy(float)
                if len(v) > 2000:  # quantile-compressed domain
                    order = np.argsort(v)
                    bins = (np.cumsum(w[order]) / w.sum() * 1999).astype(int)
                    sums = np.bincount(bins, w[order], 2000)
                    mean = np.bincount(bins, w[order] * v[order], 2000) / np.maximum(sums, 1e-300)
                    v, w = mean[sums > 0], sums[sums > 0]
                c = local.kmeans_1d(v, w, k)[0][:, None]
            else:
                c = local.kmeans(rows[[f"v_{x}" for x in part]].to_numpy(float), w, k, seed)[0]
            name = f"cls_{len(tables)}"
            classes.setdefault(n, {})[name] = nearest_class(part, c)
            tables.append((part, name, c))
    rows = space.count_classes(None, classes).collect()  # at most k ** parts rows
    names = [c for part, _, _ in tables for c in part]
    at = [names.index(c) for c in space.coords]
    pts = np.array([np.concatenate([c[r[name] - 1] for _, name, c in tables])[at] for r in rows])
    return pts, np.array([float(r["cnt"]) for r in rows])


def grid(space: JoinSpace, k: int, objective: str = "means", per: str = "attribute", seed: int = 42) -> Solution:
    p, w = grid_coreset(space, k, per, seed)
    c, v = local.solver(objective)(p, w, k)
    return Solution(c, v, {"cells": len(p)})


def distance_seeding(space: JoinSpace, k: int, rounds: int = 4, seed: int = 42) -> Solution:
    """Stand-in for the k**4 method: candidates are drawn with probability by squared distance (rejection from uniform
    draws), weighted by the share of a uniform sample nearest to them, and clustered."""
    rng = np.random.default_rng(seed)
    n = space.size()
    pool = space.sample([space.root_box()], [4000], seed)[0]
    chosen = [pool[0]]
    for _ in range(rounds * k):
        d = local.assign(pool, np.array(chosen))[1] ** 2
        if d.max() <= 0:
            break
        take = pool[rng.random(len(pool)) * d.max() < d]
        if len(take):
            chosen.append(take[int(rng.integers(len(take)))])
    core = np.unique(np.array(chosen), axis=0)
    w = np.bincount(local.assign(pool, core)[0], minlength=len(core)) * (n / len(pool))
    live = w > 0
    c, v = local.kmeans(core[live], w[live], k, seed)
    return Solution(c, v, {"candidates": len(core)})


def uniform_sample(space: JoinSpace, k: int, objective: str, draws: int = 2000, seed: int = 42) -> Solution:
    n = space.size()
    pool = space.sample([space.root_box()], [draws], seed)[0]
    c, v = local.solver(objective)(pool, np.full(len(pool), n / len(pool)), k)
    return Solution(c, v)


def random_centres(space: JoinSpace, k: int, seed: int = 42) -> Solution:
    return Solution(space.sample([space.root_box()], [k], seed)[0], float("nan"))


def mixed_grid(space: JoinSpace, k: int, mismatch: float = 1.0, seed: int = 42) -> Solution:
    """Per-attribute grid over numeric and categorical attributes with exact weights."""
    cats = {a: mixed._typed(space, a, mixed.categorical_centers(w, k)[0]) for a, w in mixed.category_weights(space, k).items()}
    classes: dict = {}
    names: list[tuple[str, str, list]] = []
    for n, (mine, tags) in space.owned.items():
        for c in mine:
            rows = space.value_weights([c]).toPandas()
            v, w = rows["value"].to_numpy(float), rows["w"].to_numpy(float)
            if len(v) > 500:
                order = np.argsort(v)
                bins = (np.cumsum(w[order]) / w.sum() * 499).astype(int)
                sums = np.bincount(bins, w[order], 500)
                v, w = (np.bincount(bins, w[order] * v[order], 500) / np.maximum(sums, 1e-300))[sums > 0], sums[sums > 0]
            own = local.kmeans_1d(v, w, k)[0]
            classes.setdefault(n, {})[f"cls_{c}"] = nearest_class([c], own[:, None])
            names.append(("x", c, list(own)))
        for a in tags:
            classes.setdefault(n, {})[f"cls_{a}"] = mixed._class(a, cats[a])
            names.append(("c", a, cats[a]))
    rows = space.count_classes(None, classes).collect()  # at most k ** attributes
    x = np.array([[v[r[f"cls_{a}"] - 1] for kind, a, v in names if kind == "x"] for r in rows], float)
    tags = np.array([[v[r[f"cls_{a}"] - 1] for kind, a, v in names if kind == "c"] for r in rows], object)
    w = np.array([float(r["cnt"]) for r in rows])
    c, values, cost = mixed.weighted_solve(x, tags, w, k, mismatch, "means", seed)
    return Solution(c, cost, {"values": values, "cells": len(rows)})
