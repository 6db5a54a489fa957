"""Clustering of numeric and categorical attributes together: squared distance plus a constant for each mismatch."""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import functions as F

from . import kmeans, local
from .kcenter import Solution
from .space import JoinSpace
from .tree import ClassTree


def categorical_centers(weights: dict, k: int) -> tuple[list, float]:
    """Best k values for one attribute with unit mismatches: the heaviest; ties by value."""
    order = sorted(weights, key=lambda v: (-weights[v], str(v)))
    return order[:k], float(sum(weights[v] for v in order[k:]))


def mixed_distance(x: np.ndarray, cats: np.ndarray, centres: np.ndarray, values: list[tuple], mismatch: float = 1.0) -> np.ndarray:
    """Squared distance of every row to every centre."""
    d = ((x[:, None, :] - centres[None, :, :]) ** 2).sum(-1)
    for j in range(cats.shape[1]):
        d += mismatch * (cats[:, j][:, None] != np.array([v[j] for v in values], object)[None, :])
    return d


def weighted_solve(x: np.ndarray, cats: np.ndarray, w: np.ndarray, k: int, mismatch: float, objective: str = "means", seed: int = 42, rounds: int = 60) -> tuple[np.ndarray, list[tuple], float]:
    """Flat solver on weighted mixed points: seeding by distance, then single swaps."""
    k = min(k, len(x))
    rng = np.random.default_rng(seed)
    shape = (lambda d: d) if objective == "means" else np.sqrt

    def to(i: int) -> np.ndarray:
        return shape(mixed_distance(x, cats, x[i : i + 1], [tuple(cats[i])], mismatch)[:, 0])

    total = (lambda near: float(near.max())) if objective == "center" else (lambda near: float((w * near).sum()))
    chosen = [int(rng.choice(len(x), p=w / w.sum()))]
    d = [to(chosen[0])]
    while len(chosen) < k:
        near = np.min(d, axis=0)
        if objective == "center":
            i = int(near.argmax())
        else:
            p = w * near
            if p.sum() <= 0:
                break
            i = int(rng.choice(len(x), p=p / p.sum()))
        chosen.append(i)
        d.append(to(i))
    now = total(np.min(d, axis=0))
    for _ in range(rounds):
        i = int(rng.choice(len(x), p=w / w.sum()))
        new = to(i)
        options = [total(np.min([*(d[:j] + d[j + 1 :]), new], axis=0)) for j in range(len(d))]
        j = int(np.argmin(options))
        if options[j] < now * (1 - 1e-9):
            chosen[j], d[j], now = i, new, options[j]
    return x[chosen], [tuple(cats[i]) for i in chosen], now


def classed(space: JoinSpace, cat_centres: dict[str, list]) -> JoinSpace:
    """The space with each category replaced by the number of its centre, relations summed up again."""
    frames, owned, names = {}, {}, []
    for n, f in space.frames.items():
        mine, cats = space.owned[n]
        own = [f"cls_{a}" for a in cats if a in cat_centres]
        f = f.withColumns({f"cls_{a}": _class(a, cat_centres[a]) for a in cats if a in cat_centres}) if own else f
        keys = [c for c in f.columns if c.startswith("k_")] + mine + own
        frames[n] = f.groupBy(*keys).agg(F.sum("w").cast("decimal(38,0)").alias("w"))
        owned[n] = (mine, own)
        names += own
    return JoinSpace(space.spec, frames, space.coords, names, space.tree, space.scale, owned)


def grid_weights(space: JoinSpace, centres: np.ndarray, cat_centres: dict[str, list], low: float, eps: float, leaf_cap: int = 4096) -> tuple[np.ndarray, list[tuple], np.ndarray]:
    """Weights of the product of numeric centres and categorical ones, from one tree with class counters: growing balls take what is left
    around each centre in turn, by class vector, until nothing is left. Values go to their own centre, or else to the first one. A tuple goes to a centre
    within (1 + eps)^2 of its nearest one, or within (1 + eps) * low."""
    names = list(cat_centres)
    own = classed(space, cat_centres)
    order = [own.cats.index(f"cls_{a}") for a in names]
    tree = ClassTree(own, eps=eps, leaf_cap=leaf_cap)
    found: dict[tuple[int, tuple], int] = {}
    r, top = low, tree.root.region.outer.diameter * 2
    while tree.active:
        for i, c in enumerate(centres):
            for v, n in tree.deactivate_classes(c, r).items():
                found[i, v] = found.get((i, v), 0) + n
        if r > top:
            break
        r *= 1 + eps
    live = sorted((i, v) for (i, v), n in found.items() if n)
    values = [tuple(cat_centres[a][v[order[j]] - 1] for j, a in enumerate(names)) for _, v in live]
    return np.array([centres[i] for i, _ in live]), values, np.array([float(found[x]) for x in live])


def _class(attribute: str, values: list):
    out = F.lit(1)
    for i, v in enumerate(values):
        out = F.when(F.col(attribute).eqNullSafe(F.lit(v)), i + 1).otherwise(out)
    return out


def category_weights(space: JoinSpace, k: int | None = None) -> dict[str, dict]:
    """Per categorical attribute its values with weights, in one pass; only the k heaviest of each reach the driver if k is given."""
    from pyspark.sql import Window

    out: dict[str, dict] = {a: {} for a in space.cats}
    rows = space.value_weights(space.cats)
    if k is not None:
        order = Window.partitionBy("attr").orderBy(F.desc("w"), F.asc_nulls_first("value"))
        rows = rows.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k)
    for r in rows.collect():
        out[r["attr"]][r["value"]] = int(r["w"])
    return out


def solve(space: JoinSpace, k: int, eps: float = 0.5, objective: str = "means", mismatch: float = 1.0, seed: int = 42) -> Solution:
    """Numeric centres on the bag projection, the heaviest values per category, their product with weights, a flat solver."""
    numeric = JoinSpace(space.spec, space.frames, space.coords, [], space.tree, space.scale, space.owned)
    first = kmeans.solve(_without_cats(space), k, eps, 1 if objective == "median" else 2, seed=seed)
    own = {a: categorical_centers(w, k)[0] for a, w in category_weights(space, k).items()}
    typed = {a: _typed(space, a, v) for a, v in own.items()}
    low = max(first.trace.get("L", 1.0) / (9 * max(1, numeric.size())), 1e-6)
    x, values, w = grid_weights(space, first.centres, typed, low, eps)
    cats = np.array(values, dtype=object).reshape(len(values), -1)
    centres, picked, value = weighted_solve(x, cats, w, k, mismatch, objective, seed)
    return Solution(centres, value, {"values": picked, "grid": len(w), "weight": float(w.sum()), "numeric": first.estimate})


def _typed(space: JoinSpace, attribute: str, values: list) -> list:
    n = next(n for n, (_, cats) in space.owned.items() if attribute in cats)
    kind = dict(space.frames[n].dtypes)[attribute]
    return [None if v is None else int(v) for v in values] if kind in ("int", "bigint", "smallint") else values


def _without_cats(space: JoinSpace) -> JoinSpace:
    frames, owned = {}, {}
    for n, f in space.frames.items():
        names = [c for c in f.columns if c.startswith("k_")] + space.owned[n][0]
        frames[n] = f.groupBy(*names).agg(F.sum("w").cast("decimal(38,0)").alias("w"))
        owned[n] = (space.owned[n][0], [])
    return JoinSpace(space.spec, frames, space.coords, [], space.tree, space.scale, owned)


def one_hot_solve(space: JoinSpace, k: int, eps: float = 0.5, mismatch: float = 1.0, seed: int = 42) -> Solution:
    """Every value of every category becomes a numeric attribute of 0 or sqrt(mismatch / 2). Only for small domains."""
    frames, owned, coords = {}, {}, []
    for r in space.spec.relations:
        f, (mine, cats) = space.frames[r.name], space.owned[r.name]
        new = list(mine)
        for a in cats:
            for v in sorted((x[0] for x in f.select(a).distinct().limit(1001).collect()), key=lambda x: (x is None, str(x))):  # the category's domain
                c = f"{a}={v}"
                f = f.withColumn(c, F.when(F.col(a).eqNullSafe(F.lit(v)), math.sqrt(mismatch / 2)).otherwise(0.0))
                new.append(c)
        keep = [c for c in f.columns if c.startswith("k_")] + new
        frames[r.name] = f.groupBy(*[f"`{c}`" for c in keep]).agg(F.sum("w").cast("decimal(38,0)").alias("w"))
        frames[r.name] = frames[r.name].toDF(*[c.replace("=", "_is_").replace(" ", "_").replace("#", "").replace("-", "_") for c in frames[r.name].columns])
        clean = [c.replace("=", "_is_").replace(" ", "_").replace("#", "").replace("-", "_") for c in new]
        owned[r.name] = (clean, [])
        coords += clean
    wide = JoinSpace(space.spec, frames, coords, [], space.tree, space.scale, owned)
    found = kmeans.solve(wide, k, eps, 2, seed=seed)
    return Solution(found.centres, found.estimate, found.trace | {"coords": coords})


def assignment_cost(rows: np.ndarray, cats: np.ndarray, w: np.ndarray, centres: np.ndarray, values: list[tuple], mismatch: float = 1.0, objective: str = "means") -> float:
    d = mixed_distance(rows, cats, centres, values, mismatch).min(1)
    if objective == "center":
        return float(np.sqrt(d.max()))
    return float((w * (d if objective == "means" else np.sqrt(d))).sum())
