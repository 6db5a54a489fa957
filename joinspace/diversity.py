"""Farthest tuples, farthest-first traversal, and diverse subsets of a join space."""

from __future__ import annotations

import math

import numpy as np

from . import kcenter, local
from .tree import SpatialTree, lazy_tree

KINDS = ("edge", "tree", "cycle", "pseudoforest", "matching")


def farthest(space, chosen: np.ndarray, eps: float = 0.25, tree: SpatialTree | None = None, **options) -> tuple[np.ndarray, float]:
    """A tuple whose distance to `chosen` is at least (1 - eps) times the largest; the distance."""
    tree = tree or lazy_tree(space, eps=eps / 2, leaf_rows=True, **options)
    top = tree.root.region.outer.diameter

    def left(r: float) -> np.ndarray | None:
        tree.reset()
        tree.deactivate(chosen, r)
        out = tree.representative()
        tree.reset()
        return out

    best = left(0.0)
    if best is None:
        return chosen[0], 0.0
    step = 1 + eps / 4
    low = max(float(local.assign(best[None, :], chosen)[1][0]), top * 2.0**-40)
    lo, hi = 0, math.ceil(math.log(max(top / low, 1.0)) / math.log(step)) + 1
    while lo < hi:
        mid = (lo + hi) // 2
        got = left(low * step**mid)
        if got is not None:
            best, lo = got, mid + 1
        else:
            hi = mid
    return best, float(local.assign(best[None, :], chosen)[1][0])


def farthest_first_slow(space, k: int, eps: float = 0.25, tree: SpatialTree | None = None, **options) -> np.ndarray:
    """One farthest query for each step."""
    tree = tree or lazy_tree(space, eps=eps / 2, leaf_rows=True, **options)
    chosen = [tree.root.rep]
    while len(chosen) < k:
        x, d = farthest(space, np.array(chosen), eps, tree)
        if d == 0:
            break
        chosen.append(x)
    return np.array(chosen)


def farthest_first(space, k: int, eps: float = 0.5, tree: SpatialTree | None = None, most: int = 400, **options) -> np.ndarray:
    """k-center with more centres, about k / eps^d, then a flat traversal of them. Where that asks for over `most`
    centres, one farthest query for each step, with the same factor, takes their place."""
    tree = tree or lazy_tree(space, eps=eps / 5, leaf_rows=True, **options)
    d = len(tree.root.region.outer.lo)
    many = math.ceil(max(2 * k, k * eps**-d))
    if many > most:
        return farthest_first_slow(space, k, eps, tree)
    found = kcenter.refine(space, many, eps, tree)
    return local.farthest_first(found.centres, k)


def solve(space, k: int, kind: str, eps: float = 0.5, tree: SpatialTree | None = None, **options) -> tuple[np.ndarray, float]:
    points = farthest_first(space, k, eps, tree, **options)
    return points, local.diversity(points, kind)
