"""Weighted points that stand for a join space."""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np

from . import local
from .region import Box, distance_bounds
from .tree import SpatialTree


@dataclass
class Coreset:
    points: np.ndarray
    weights: np.ndarray
    slack: float = 0.0  # largest distance of a tuple to its representative


def adaptive(tree: SpatialTree, centres: np.ndarray, base: float, eps: float) -> Coreset:
    """Descend until a node's diameter is at most max(base, eps * distance to the centres): every frontier node is a point."""
    points, weights, slack = [], [], 0.0
    front = [tree.root] if tree.root.active else []
    while front:
        missing, below = [], []
        for x in front:
            if not x.active:
                continue
            if x.points is not None:
                p, w, s = _grouped(x.points[x.live], x.weights[x.live], centres, base, eps)
                points.append(p)
                weights.append(w)
                slack = max(slack, s)
                continue
            size = x.region.outer.diameter
            near = float(distance_bounds(x.region.outer, centres)[0].min()) if len(centres) else 0.0
            if x.is_location or size <= max(base, eps * near):
                points.append(x.rep[None, :])
                weights.append(np.array([float(x.active)]))
                slack = max(slack, 0.0 if x.is_location else size)
            elif x.children is None:
                missing.append(x)
            else:
                below += x.children
        if missing:
            tree.expand(missing)
            below += missing
        front = below
    d = len(tree.root.region.outer.lo)
    return Coreset(np.concatenate(points), np.concatenate(weights), slack) if points else Coreset(np.empty((0, d)), np.empty(0))


def _grouped(points: np.ndarray, weights: np.ndarray, centres: np.ndarray, base: float, eps: float) -> tuple[np.ndarray, np.ndarray, float]:
    """Reported points by grid cells whose diameter follows their distance to the centres (in powers of two)."""
    if not len(points):
        return points, weights, 0.0
    d = points.shape[1]
    near = local.assign(points, centres)[1] if len(centres) else np.zeros(len(points))
    want = np.maximum(base, eps * near)
    level = np.floor(np.log2(np.maximum(want, 1e-300)))
    side = 2.0**level / math.sqrt(d)
    cell = np.floor(points / side[:, None])
    keys = np.concatenate([level[:, None], cell], 1)
    _, first, back = np.unique(keys, axis=0, return_index=True, return_inverse=True)
    reps = points[first]
    back = back.ravel()
    return reps, np.bincount(back, weights, len(reps)), float(np.linalg.norm(points - reps[back], axis=1).max())


def rings(centres: np.ndarray, estimate: float, n: int, power: int, eps: float) -> list[Box]:
    """Cells around each centre: cubes of exponentially growing rings, side in proportion to the ring."""
    d = centres.shape[1]
    base = max((estimate / max(1, n)) ** (1 / power), 1e-12)
    last = math.ceil(math.log2(max(2, n)) / power) + 2
    out = []
    for c in centres:
        for j in range(last + 1):
            reach = base * 2.0**j
            side = eps * reach / math.sqrt(d)
            steps = max(1, math.ceil(reach / side))
            for at in np.ndindex(*([2 * steps] * d)):
                lo = c + (np.array(at) - steps) * side
                if j and (np.abs(lo + side / 2 - c).max() < reach / 2 - side):
                    continue  # inside the ring before
                out.append(Box(lo, lo + side))
    return out


def grid(centres: np.ndarray, estimate: float, eps: float) -> list[Box]:
    """Cells of side eps * estimate / sqrt(d) around each centre."""
    d = centres.shape[1]
    side = eps * estimate / math.sqrt(d)
    steps = math.ceil(estimate / side) + 1
    out = []
    for c in centres:
        lo0 = np.floor(c / side) * side
        for at in np.ndindex(*([2 * steps + 1] * d)):
            lo = lo0 + (np.array(at) - steps) * side
            out.append(Box(lo, lo + side))
    return out


def from_boxes(tree: SpatialTree, boxes: list[Box], weights: str = "tree", draws: int = 64, seed: int = 42) -> Coreset:
    """Box by box: what it holds that earlier ones did not becomes one weighted point, near its mean: the least tuple lies in a corner, which moves
    all costs to one side. weights="sampled" estimates that
    part from a uniform sample of the box instead of asking the tree."""
    mark = tree.snapshot()
    points, w, before, slack = [], [], [], 0.0
    for i, b in enumerate(boxes):
        if not tree.active:
            break
        n = tree.count_box(b)
        if not n:
            continue
        rep = tree.middle_of_box(b)
        if weights == "sampled":
            inside = tree.backend.count_and_represent_regions([_clip(tree, b)])[0][0]
            got = tree.backend.sample_regions([_clip(tree, b)], [draws], seed + i)[0] if inside else np.empty((0, len(b.lo)))
            fresh = ~np.array([any(o.contains(x) for o in before) for x in got], bool) if len(got) else np.empty(0, bool)
            n_est = float(inside) * (fresh.mean() if len(fresh) else 0.0)
        else:
            n_est = float(n)
        tree.deactivate_box(b)
        before.append(b)
        if n_est > 0:
            points.append(rep)
            w.append(n_est)
            slack = max(slack, (1 + tree.eps) * b.diameter)
    tree.restore(mark)
    d = len(tree.root.region.outer.lo)
    return Coreset(np.array(points).reshape(-1, d), np.array(w), slack)


def _clip(tree: SpatialTree, b: Box):
    from .region import Region

    root = tree.root.region.outer
    lo, hi = np.maximum(b.lo, root.lo), np.minimum(b.hi, root.hi)
    return Region(Box(lo, np.maximum(lo, hi)))
