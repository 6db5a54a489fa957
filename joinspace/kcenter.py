"""k-center over a join space."""

from __future__ import annotations

import math
from dataclasses import dataclass, field

import numpy as np

from . import coreset, local, radius
from .tree import SpatialTree, lazy_tree


@dataclass
class Solution:
    centres: np.ndarray
    estimate: float  # an upper bound of the cost
    trace: dict = field(default_factory=dict)


def cover(tree: SpatialTree, k: int, r: float) -> np.ndarray | None:
    """Known radius: at most k representatives whose balls of 2r (up to 2(1 + eps)r) take everything; None on failure.
    It succeeds for every r at or over the optimum. Whatever the tree has expanded stays for the next radius."""
    tree.reset()
    out: list[np.ndarray] = []
    while tree.active:
        if len(out) == k:
            tree.reset()
            return None
        p = tree.representative()
        out.append(p)
        tree.deactivate(p, 2 * r)
    tree.reset()
    return np.array(out).reshape(-1, len(tree.root.region.outer.lo))


def sample_bound(tree: SpatialTree, k: int) -> float:
    """A lower bound of the optimum: of k + 1 tuples two share a centre, so half their least distance cannot be beaten."""
    s = tree.root.sample if tree.root.sample is not None else tree.root.points
    if s is None or not len(s):
        return 0.0
    p = local.farthest_first(s, k + 1)
    return local.diversity(p, "edge") / 2 if len(p) == k + 1 else 0.0


def search(space, k: int, eps: float = 0.25, tree: SpatialTree | None = None, how: str = "auto", **options) -> Solution:
    """Smallest radius found at which `cover` succeeds: by rank among base value differences (times sqrt(d)), or geometric."""
    tree = tree or lazy_tree(space, eps=eps / 2, **options)
    d = len(tree.root.region.outer.lo)
    if not tree.n:
        return Solution(np.empty((0, d)), 0.0)
    bound = sample_bound(tree, k)
    got = cover(tree, k, 0.0) if bound == 0 else None
    if got is not None:
        return Solution(got, 0.0, {"how": how, "radii": 1, **_facts(tree)})
    tried = 1
    pool = radius.pool(space) if how in ("auto", "pairs") else None
    how = "pairs" if pool is not None and pool.total else "geometric"
    best, r_best = None, None
    if how == "pairs":
        # the right rank's difference is at least bound / sqrt(d): below half the optimum no cover succeeds
        lo, hi = pool.rank_below(bound / 2 / math.sqrt(d)), pool.total
        failed = 0.0
        while lo < hi:
            # between a failure and a success the rank in the middle of the radii is asked; ranks whose radii differ by less than the slack are one
            mid = (lo + hi) // 2
            if failed and r_best is not None:
                if r_best <= failed * (1 + eps / 4):
                    break
                mid = min(max(pool.rank_below(math.sqrt(failed * r_best) / math.sqrt(d)), lo), hi - 1)
            r = math.sqrt(d) * pool.at_rank(mid)
            if r_best is not None and r >= r_best * (1 - 1e-12):  # another rank of a known radius
                hi = mid
                continue
            tried += 1
            got = cover(tree, k, r)
            if got is not None:
                best, r_best, hi = got, r, mid
            else:
                failed = max(failed, r)
                lo = max(mid + 1, pool.rank_below(r / math.sqrt(d) * (1 + 2e-9)))  # equal differences fail alike
                lo = min(lo, hi)
        if best is None:
            r_best = math.sqrt(d) * pool.at_rank(pool.total)
            best = cover(tree, k, r_best)
    if best is None:
        top = tree.root.region.outer.diameter
        low, high = max(top * 2.0**-40, sample_bound(tree, k)), top
        lo, hi = 0, math.ceil(math.log(high / low) / math.log(1 + eps))
        best, r_best = cover(tree, k, high), high
        while lo < hi:
            mid = (lo + hi) // 2
            tried += 1
            r = low * (1 + eps) ** mid
            got = cover(tree, k, r)
            if got is not None:
                best, r_best, hi = got, r, mid
            else:
                lo = mid + 1
    return Solution(best, 2 * (1 + tree.eps) * r_best, {"how": how, "radii": tried, "radius": r_best, **_facts(tree)})


def refine(space, k: int, eps: float = 0.25, tree: SpatialTree | None = None, how: str = "auto", **options) -> Solution:
    """A ladder of step (1 + eps / 5) below the first estimate, searched by bisection: factor 2 + eps."""
    tree = tree or lazy_tree(space, eps=eps / 5, **options)
    first = search(space, k, eps, tree, how)
    if first.estimate == 0:
        return first
    d = len(tree.root.region.outer.lo)
    step = 1 + eps / 5
    high = first.estimate / 2
    low = max(first.estimate / (2 * math.sqrt(d) + eps) / 2, sample_bound(tree, k) / 2)
    lo, hi = 0, math.ceil(math.log(high / low) / math.log(step))
    best, r_best, tried = first.centres, first.trace["radius"], 0
    while lo < hi:
        mid = (lo + hi) // 2
        r = low * step**mid
        if r >= r_best:
            hi = mid
            continue
        tried += 1
        got = cover(tree, k, r)
        if got is not None:
            best, r_best, hi = got, r, mid
        else:
            lo = mid + 1
    return Solution(best, 2 * (1 + tree.eps) * r_best, first.trace | {"ladder": tried, "radius": r_best, **_facts(tree)})


def coreset_solve(space, k: int, eps: float = 0.25, tree: SpatialTree | None = None, solver=None, how: str = "auto", **options) -> Solution:
    """Coreset of fineness eps times the radius around the first solution, then a flat solver on it."""
    tree = tree or lazy_tree(space, eps=eps / 5, **options)
    first = search(space, k, eps, tree, how)
    if first.estimate == 0:
        return first
    d = len(tree.root.region.outer.lo)
    fine = eps * first.estimate / (2 * math.sqrt(d)) / 2
    core = coreset.adaptive(tree, first.centres, base=fine, eps=0.0)
    centres, value = (solver or local.solver("center"))(core.points, core.weights, k)
    return Solution(centres, float(value + core.slack), first.trace | {"coreset": len(core.points), **_facts(tree)})


def solve(space, k: int, eps: float = 0.25, method: str = "coreset", **options) -> Solution:
    return {"first": search, "ladder": refine, "coreset": coreset_solve}[method](space, k, eps, **options)


def _facts(tree: SpatialTree) -> dict:
    s = tree.stats
    return {"n": tree.n, "jobs": s.jobs, "nodes": s.nodes, "height": s.height, "canonical": max(s.canonical, default=0)}
