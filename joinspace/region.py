"""Boxes, boxes with a hole, and midpoint geometry. All boxes are half-open: lo <= x < hi."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np


@dataclass(frozen=True, eq=False)
class Box:
    lo: np.ndarray
    hi: np.ndarray

    def contains(self, x: np.ndarray) -> np.ndarray:
        return ((x >= self.lo) & (x < self.hi)).all(-1)

    def inside(self, other: Box) -> bool:
        return bool((self.lo >= other.lo).all() and (self.hi <= other.hi).all())

    def same(self, other: Box) -> bool:
        return bool((self.lo == other.lo).all() and (self.hi == other.hi).all())

    def meets(self, other: Box) -> bool:
        return bool((self.lo < other.hi).all() and (other.lo < self.hi).all())

    @property
    def diameter(self) -> float:
        return float(np.linalg.norm(self.hi - self.lo))

    def halves(self) -> tuple[Box, Box, int, float]:
        """Cut in the middle of the longest side."""
        axis = int(np.argmax(self.hi - self.lo))
        middle = float(self.lo[axis] + (self.hi[axis] - self.lo[axis]) / 2)
        low, high = self.hi.copy(), self.lo.copy()
        low[axis] = high[axis] = middle
        return Box(self.lo, low), Box(high, self.hi), axis, middle

    @staticmethod
    def around(points: np.ndarray) -> Box:
        """The least half-open box with these points."""
        return Box(points.min(0).astype(float), np.nextafter(points.max(0).astype(float), np.inf))

    @staticmethod
    def at(x: np.ndarray) -> Box:
        x = np.asarray(x, float)
        return Box(x, np.nextafter(x, np.inf))

    @property
    def is_point(self) -> bool:
        return bool((np.nextafter(self.lo, np.inf) >= self.hi).all())


def tight(box: Box, lo: np.ndarray, hi: np.ndarray, most: int = 4000) -> Box:
    """The smallest midpoint box below `box` that holds every point from lo to hi (inclusive)."""
    for _ in range(most):
        if box.is_point:
            break
        low, high, axis, middle = box.halves()
        if not box.lo[axis] < middle < box.hi[axis]:
            break
        if hi[axis] < middle:
            box = low
        elif lo[axis] >= middle:
            box = high
        else:
            break
    return box


@dataclass(frozen=True, eq=False)
class Region:
    """A box, or a box without an inner box."""

    outer: Box
    hole: Box | None = None

    def contains(self, x: np.ndarray) -> np.ndarray:
        inside = self.outer.contains(x)
        return inside & ~self.hole.contains(x) if self.hole is not None else inside

    def slabs(self) -> list[Box]:
        """At most 2d disjoint boxes whose union is the region."""
        if self.hole is None:
            return [self.outer]
        out, lo, hi = [], self.outer.lo.copy(), self.outer.hi.copy()
        for a in range(len(lo)):
            if lo[a] < self.hole.lo[a]:
                top = hi.copy()
                top[a] = self.hole.lo[a]
                out.append(Box(lo.copy(), top))
            if self.hole.hi[a] < hi[a]:
                bottom = lo.copy()
                bottom[a] = self.hole.hi[a]
                out.append(Box(bottom, hi.copy()))
            lo[a], hi[a] = self.hole.lo[a], self.hole.hi[a]
        return out

    @property
    def empty(self) -> bool:
        return self.hole is not None and self.hole.same(self.outer)


def norm(x: np.ndarray, metric: str = "l2") -> np.ndarray:
    if metric == "l2" and 0 < x.shape[-1] < 8:  # in the order of a sum over the axis, which is slow where the axis is short
        total = x[..., 0] * x[..., 0]
        for j in range(1, x.shape[-1]):
            total = total + x[..., j] * x[..., j]
        return np.sqrt(total)
    if metric == "l2":
        return np.sqrt((x * x).sum(-1))
    return np.abs(x).sum(-1) if metric == "l1" else np.abs(x).max(-1, initial=0)


def distance_bounds(box: Box, centres: np.ndarray, metric: str = "l2") -> tuple[np.ndarray, np.ndarray]:
    """Least and greatest distance of each centre to the box."""
    near = np.maximum(np.maximum(box.lo - centres, centres - box.hi), 0)
    far = np.maximum(np.abs(centres - box.lo), np.abs(box.hi - centres))
    return norm(near, metric), norm(far, metric)


def pairwise(a: np.ndarray, b: np.ndarray, metric: str = "l2") -> np.ndarray:
    if metric == "l2" and 0 < a.shape[1] < 8:  # the same sums, without an array of all differences
        total = np.zeros((len(a), len(b)))
        for j in range(a.shape[1]):
            d = a[:, j, None] - b[None, :, j]
            d *= d
            total += d
        return np.sqrt(total, out=total)
    return norm(a[:, None, :] - b[None, :, :], metric)


def fair_split(region: Region) -> list[Region]:
    """Halve the outer box; the hole, a midpoint box too, stays whole in one half. Empty parts are left out."""
    low, high, _, _ = region.outer.halves()
    parts = [Region(h, region.hole if region.hole is not None and region.hole.inside(h) else None) for h in (low, high)]
    return [p for p in parts if not p.empty]


def centroid_shrink(region: Region, points: np.ndarray) -> list:
    """Children of a shrink step from (sample) points of the region: nested lists [region, children] of a block.

    Majority halves are followed from tight box to tight box until at most two thirds of the points are left. Without a
    hole, or if it stays in the majority, two children come out. If the majority loses the hole, the block has
    further nodes: first outside and inside of the last tight box, then the half with the hole and the half without.
    """
    total, box, own = len(points), region.outer, points
    hole = region.hole
    while True:
        if (own == own[0]).all() and (hole is None or not hole.meets(box)):
            box = Box.at(own[0])
            break
        lo, hi = own.min(0), own.max(0)
        if hole is not None:
            lo, hi = np.minimum(lo, hole.lo), np.maximum(hi, np.nextafter(hole.hi, -np.inf))
        box = tight(box, lo, hi)
        if box.is_point:
            break
        low, high, axis, middle = box.halves()
        if not box.lo[axis] < middle < box.hi[axis]:
            break
        side = own[:, axis] < middle
        keep = low if side.sum() * 2 >= len(own) else high
        rest = high if keep is low else low
        mine = side if keep is low else ~side
        if hole is not None and not hole.inside(keep):
            inner = _shrink_free(keep, own[mine], total)
            block = [[Region(inner), []]] + ([[Region(keep, inner), []]] if not inner.same(keep) else [])
            kept = [Region(keep), block] if len(block) > 1 else [Region(keep), []]
            other = Region(rest, hole)
            below = [kept] + ([[other, []]] if not other.empty else [])
            if box.same(region.outer):
                return below
            return [[Region(region.outer, box), []], [Region(box, hole), below]]
        box, own = keep, own[mine]
        if 3 * len(own) <= 2 * total or not len(own):
            break
    parts = [Region(region.outer, box), Region(box, hole)]
    return [[p, []] for p in parts if not p.empty]


def _shrink_free(box: Box, points: np.ndarray, total: int) -> Box:
    own = points
    while 3 * len(own) > 2 * total:
        if (own == own[0]).all():
            return Box.at(own[0])
        box = tight(box, own.min(0), own.max(0))
        low, high, axis, middle = box.halves()
        if not box.lo[axis] < middle < box.hi[axis]:
            return box
        side = own[:, axis] < middle
        box, own = (low, own[side]) if side.sum() * 2 >= len(own) else (high, own[~side])
    return box
