"""Shrink trees: a hierarchy of boxes and holed boxes, expanded only where a query looks.

One tree serves two back ends: points in memory (flat), and a join space (lazy, by batched Spark jobs). A node alternates
halving and shrinking. Queries walk from the root; nodes whose children are missing are expanded together, one
level of the frontier at a time, so the number of jobs follows the depth and not the number of nodes.
"""

from __future__ import annotations

import math
from dataclasses import dataclass, field
from typing import Protocol

import numpy as np
from pyspark.sql import functions as F

from . import local, products, resident
from .region import Box, Region, centroid_shrink, distance_bounds, fair_split, norm


def sample_size(eps: float, n: int, relations: int = 1, c: float = 1.0) -> int:
    """Draws that make a sample represent all boxes up to eps: c / eps^2 * log2(n^(relations + 4))."""
    return max(1, math.ceil(c / eps**2 * (relations + 4) * math.log2(max(2, n))))


class Backend(Protocol):
    def root_box(self) -> Box: ...
    def size(self) -> int: ...
    def count_and_represent_regions(self, regions: list[Region]) -> tuple[np.ndarray, list]: ...
    def sample_regions(self, regions: list[Region], draws: list[int], seed: int) -> list[np.ndarray]: ...
    def report_regions(self, regions: list[Region]) -> list[tuple[np.ndarray, np.ndarray]]: ...
    def reported_weight(self, regions: list[Region]) -> int: ...
    def report_rows(self, regions: list[Region], totals: list[int], most: int) -> list[int]: ...


class FlatBackend:
    """Weighted points in memory."""

    def __init__(self, points: np.ndarray, weights: np.ndarray | None = None):
        self.points = np.atleast_2d(np.asarray(points, float))
        self.weights = np.ones(len(self.points)) if weights is None else np.asarray(weights, float)

    def root_box(self) -> Box:
        return Box.around(self.points)

    def size(self):
        return int(self.weights.sum())

    def count_and_represent_regions(self, regions):
        counts, reps = np.zeros(len(regions), object), []
        for i, r in enumerate(regions):
            inside = np.flatnonzero(r.contains(self.points))
            counts[i] = int(self.weights[inside].sum())
            reps.append(self.points[inside[0]] if len(inside) else None)
        return counts, reps

    def sample_regions(self, regions, draws, seed=42):
        out = []
        for i, (r, z) in enumerate(zip(regions, draws, strict=True)):
            inside = np.flatnonzero(r.contains(self.points))
            w = self.weights[inside]
            rng = np.random.Generator(np.random.Philox([seed, i]))
            out.append(self.points[rng.choice(inside, z, p=w / w.sum())] if len(inside) else self.points[:0])
        return out

    def report_regions(self, regions):
        return [(self.points[m], self.weights[m]) for m in (r.contains(self.points) for r in regions)]

    def reported_weight(self, regions):
        return sum(int(self.weights[r.contains(self.points)].sum()) for r in regions)

    def report_rows(self, regions, totals, most):
        return totals


class ProductBackend:
    """A join's tuples as pairs of rows of its two sides."""

    def __init__(self, points: products.Products):
        self.points = points

    def root_box(self):
        lo, hi = np.empty(self.points.shape[1]), np.empty(self.points.shape[1])
        for z, at in ((self.points.x, self.points.mine), (self.points.y, self.points.other)):
            lo[at], hi[at] = z.min(0), z.max(0)
        return Box(lo, np.nextafter(hi, np.inf))

    def size(self):
        return int(self.points.weights.sum())

    def count_and_represent_regions(self, regions):
        counts, reps = np.zeros(len(regions), object), [None] * len(regions)
        for i, r in enumerate(regions):
            for part in map(self.points.within, r.slabs()):
                counts[i] += int(part.weights.sum())
                if reps[i] is None and len(part):
                    reps[i] = part[0]
        return counts, reps

    def sample_regions(self, regions, draws, seed=42):
        out = []
        for i, (r, z) in enumerate(zip(regions, draws, strict=True)):
            rng = np.random.Generator(np.random.Philox([seed, i]))
            parts = [self.points.within(b) for b in r.slabs()]
            w = np.array([p.weights.sum() for p in parts])
            want = rng.multinomial(z, w / w.sum()) if w.sum() else []
            out.append(np.concatenate([self.points[:0], *[p.draw(int(m), rng) for p, m in zip(parts, want) if m]]))
        return out

    def report_regions(self, regions):
        out = []
        for r in regions:
            parts = [self.points.within(b).held() for b in r.slabs()]
            out.append((np.concatenate([self.points[:0], *[p for p, _ in parts]]), np.concatenate([np.empty(0), *[w for _, w in parts]])))
        return out

    def reported_weight(self, regions):
        return sum(int(self.points.within(b).weights.sum()) for r in regions for b in r.slabs())

    def report_rows(self, regions, totals, most):
        return totals


class SpaceBackend:
    """A join space; a region's count is its outer box's minus its hole's, representatives come with the same pass.
    Where its relations fit into memory, so do the messages, and no batch is a Spark job."""

    def __init__(self, space, resident_values: int | None = None):
        self.space = resident.of(space, resident_values) or space

    def root_box(self):
        return self.space.root_box()

    def size(self):
        return self.space.size()

    def count_and_represent_regions(self, regions):
        boxes: list[Box] = [r.outer for r in regions] + [r.hole for r in regions if r.hole is not None]
        counts, reps = self.space.count_and_represent(boxes) if boxes else (np.zeros(0, object), [])
        out, first, at = counts[: len(regions)].copy(), reps[: len(regions)], len(regions)
        again = []
        for i, r in enumerate(regions):
            if r.hole is not None:
                out[i] -= counts[at]
                at += 1
                if out[i] and r.hole.contains(first[i]):
                    again.append(i)
        if again:  # the least tuple of the outer box is in the hole
            for i, x in zip(again, self.space.represent_regions([regions[i] for i in again]), strict=True):
                first[i] = x
        return out, first

    def sample_regions(self, regions, draws, seed=42):
        return self.space.sample_regions(regions, draws, seed)

    def report_regions(self, regions):
        return self.space.report_regions(regions)

    def reported_weight(self, regions):
        """The weights of all reported tuples together: they are summed where they are made, none goes to the driver."""
        return self.space.reported_weight(regions)

    def report_rows(self, regions, totals, most):
        """How many rows a report of each region makes at most, as far as that can tell whether they are over `most`: rows stand for several
        tuples where base tuples repeat. Asked where it needs no job."""
        if not isinstance(self.space, resident.ResidentSpace):
            return totals
        ask = [i for i, n in enumerate(totals) if most < n <= most * self.space.heaviest]
        out = list(totals)
        for i, n in zip(ask, self.space.count_rows([regions[i] for i in ask]), strict=True):
            out[i] = n
        return out


@dataclass(eq=False)
class Node:
    region: Region
    total: int
    rep: np.ndarray | None
    depth: int
    shrink: bool
    parent: Node | None = None
    sample: np.ndarray | None = None
    children: list[Node] | None = None
    points: np.ndarray | None = None
    weights: np.ndarray | None = None
    live: np.ndarray | None = None
    active: int = 0
    block: list | None = None
    ident: int = 0
    stall: int = 0  # steps since a cut last separated anything
    near: tuple | None = None

    def __post_init__(self):
        self.active = self.total

    @property
    def is_location(self) -> bool:
        return self.region.hole is None and self.region.outer.is_point


@dataclass
class Stats:
    jobs: int = 0
    batches: int = 0
    nodes: int = 1
    height: int = 0
    canonical: list[int] = field(default_factory=list)
    drawn: int = 0
    reported: int = 0
    balance: list[float] = field(default_factory=list)


class SpatialTree:
    """eps: slack of ball and box queries. shape: "shrink" (halve, then shrink, by samples), "exact" (shrink on all points,
    flat back end only), "halve", "quad" or "median" (a cut at the sample's median). A node of at most leaf_cap tuples is reported,
    with leaf_rows one whose report makes at most leaf_cap rows, too."""

    def __init__(self, backend: Backend, eps: float = 0.25, seed: int = 42, leaf_cap: int = 20_000, shape: str = "shrink", draws: int = 2000, least_draws: int = 48, metric: str = "l2", always_draw: bool = False, leaf_rows: bool = False):
        self.backend, self.eps, self.seed, self.leaf_cap, self.shape = backend, eps, seed, leaf_cap, shape
        self.draws, self.least_draws, self.metric, self.always_draw, self.leaf_rows = draws, least_draws, metric, always_draw, leaf_rows
        self.stats = Stats()
        n = backend.size()
        self.n = n
        box = backend.root_box()
        self.root = Node(Region(box), n, None, 0, False)
        self.journal: list[tuple[Node, int, np.ndarray | None]] = []
        self.serial = 1
        if n:
            counts, reps = backend.count_and_represent_regions([self.root.region])
            self.root.rep = reps[0]
            if n > leaf_cap:
                self.root.sample = self._draw([self.root], min(20_000, 10 * draws))[0]

    # growing

    def _draw(self, nodes: list[Node], z: int) -> list[np.ndarray]:
        self.stats.jobs += 1
        self.stats.drawn += z * len(nodes)
        self.serial += 1
        return self.backend.sample_regions([x.region for x in nodes], [z] * len(nodes), self.seed + self.serial)

    def expand(self, nodes: list[Node]) -> None:
        """Children (or points) for all these nodes: at most one draw, one count and one report batch."""
        nodes = list(dict.fromkeys(x for x in nodes if x.children is None and x.points is None and x.total and not x.is_location))
        if not nodes:
            return
        self.stats.batches += 1
        rows = [x.total for x in nodes]
        if self.leaf_rows:
            rows = self.backend.report_rows([x.region for x in nodes], rows, self.leaf_cap)
        small = [x for x, n in zip(nodes, rows, strict=True) if n <= self.leaf_cap]
        if small:
            self.stats.jobs += 1
            for x, (p, w) in zip(small, self.backend.report_regions([x.region for x in small]), strict=True):
                x.points, x.weights, x.live = p, w, np.ones(len(p), bool)
                self.stats.reported += len(p)
                if not x.active:
                    x.live[:] = False
        large = [x for x, n in zip(nodes, rows, strict=True) if n > self.leaf_cap]
        if not large:
            return
        if self.shape == "exact":
            for x, (p, _) in zip(large, self.backend.report_regions([x.region for x in large]), strict=True):
                x.sample = p
        elif self.shape not in ("halve", "quad"):
            # where the inherited sample is thin, midpoint halving goes on as long as it separates; else draw anew
            thin = [x for x in large if x.block is None and (x.sample is None or len(x.sample) < self.least_draws) and (self.always_draw or x.stall >= 2)]
            if thin:
                for x, s in zip(thin, self._draw(thin, self.draws), strict=True):
                    x.sample = s
        made: list[Node] = []
        for x in large:
            parts = x.block if x.block else self._parts(x)
            x.children = []
            for region, block in parts:
                child = Node(region, 0, None, x.depth + 1, not x.shrink if not block else x.shrink, x)
                child.ident = self.serial = self.serial + 1
                child.block = block or None
                if x.sample is not None:
                    child.sample = x.sample[region.contains(x.sample)]
                x.children.append(child)
                made.append(child)
        self.stats.jobs += 1
        counts, reps = self.backend.count_and_represent_regions([c.region for c in made])
        for c, n, rep in zip(made, counts, reps, strict=True):
            c.total = c.active = int(n)
            c.rep = rep
        for x in large:
            x.children = [c for c in x.children if c.total]
            for c in x.children:
                c.stall = x.stall + 1 if len(x.children) == 1 else 0
            self.stats.nodes += len(x.children)
            if x.shrink and len(x.children) == 2 and any(c.region.hole is not None for c in x.children):
                self.stats.balance.append(max(c.total for c in x.children) / x.total)
            for c in x.children:
                self.stats.height = max(self.stats.height, c.depth)

    def _parts(self, x: Node) -> list:
        s = x.sample
        if self.shape == "quad":
            parts = [x.region]
            for _ in range(len(x.region.outer.lo)):
                parts = [q for p in parts for q in fair_split(p)]
            return [[p, []] for p in parts]
        if self.shape == "median" and s is not None and len(s) and not (s == s[0]).all():
            axis = int(np.argmax(s.max(0) - s.min(0)))
            cut = float(np.median(s[:, axis]))
            if cut <= s[:, axis].min():
                cut = float(np.min(s[s[:, axis] > cut, axis]))
            low, high = x.region.outer.hi.copy(), x.region.outer.lo.copy()
            low[axis] = high[axis] = cut
            return [[Region(Box(x.region.outer.lo, low)), []], [Region(Box(high, x.region.outer.hi)), []]]
        if s is not None and len(s) >= min(self.least_draws, x.total) and (s == s[0]).all() and self.shape != "median":
            point = Box.at(s[0])
            if x.region.hole is None:
                return [[Region(x.region.outer, point), []], [Region(point), []]]
        if self.shape in ("shrink", "exact") and x.shrink and s is not None and (len(s) >= self.least_draws or self.shape == "exact" and len(s)):
            parts = centroid_shrink(x.region, s)
            if len(parts) > 1:
                return parts
        region = x.region
        for _ in range(4000):  # halves without any point pass through
            parts = fair_split(region)
            if len(parts) > 1 or parts[0].hole is None:
                return [[p, []] for p in parts]
            region = parts[0]
        return [[p, []] for p in parts]

    def build(self) -> SpatialTree:
        """Expand everything."""
        front = [self.root]
        while front:
            self.expand(front)
            front = [c for x in front for c in (x.children or ()) if c.points is None]
            front = [c for c in front if not c.is_location]
        return self

    # queries

    def _walk(self, centres: np.ndarray, radius: float, box: Box | None = None):
        """Yields ("all", node), ("points", node, mask): what the query covers. Descends, expanding level by level."""
        reach = (1 + self.eps) * radius
        found, front = [], [(self.root, centres)] if self.root.active else []
        while front:
            missing, below = [], []
            for x, some in front:  # a node only meets the centres that its parent lies within reach of
                if not x.active:
                    continue
                if box is None:
                    near, far = distance_bounds(x.region.outer, some, self.metric)
                    if near.min() > radius:
                        continue
                    if x.region.hole is not None and self._in_hole(x.region, some[near <= radius], radius):
                        continue
                    inside = bool((far <= reach).any())
                    if not inside and len(some) > 1:
                        some = some[near <= reach]
                else:
                    if not box.meets(x.region.outer) or (x.region.hole is not None and Box(np.maximum(box.lo, x.region.outer.lo), np.minimum(box.hi, x.region.outer.hi)).inside(x.region.hole)):
                        continue
                    inside = x.region.outer.inside(box)
                if inside:
                    found.append((x, None))
                elif x.points is not None:
                    if box is None:
                        hit = self._nearest(x, centres, some) <= radius
                    else:
                        hit = box.contains(x.points)
                    if (hit & x.live).any():
                        found.append((x, hit & x.live))
                elif x.is_location:
                    p = x.region.outer.lo
                    if (norm(some - p, self.metric) <= radius).any() if box is None else bool(box.contains(p)):
                        found.append((x, None))
                elif x.children is None:
                    missing.append((x, some))
                else:
                    below += [(y, some) for y in x.children]
            if missing:
                self.expand([x for x, _ in missing])
                below += [(y, some) for x, some in missing for y in (x.children if x.children is not None else [x])]
            front = below
        self.stats.canonical.append(len(found))
        return found

    def _nearest(self, x: Node, centres: np.ndarray, some: np.ndarray) -> np.ndarray:
        """Distance of a leaf's points to the nearest centre, as far as it is within reach; kept while the same centres ask with other radii.
        Where few of them are within reach, those are asked."""
        if x.near is None or x.near[0] is not centres:
            if 8 * len(some) < len(centres):
                return local.assign(x.points, some, self.metric)[1]
            x.near = (centres, local.assign(x.points, centres, self.metric)[1])
        return x.near[1]

    @staticmethod
    def _in_hole(region: Region, centres: np.ndarray, radius: float) -> bool:
        for c in centres:
            ball = Box(np.maximum(c - radius, region.outer.lo), np.minimum(np.nextafter(c + radius, np.inf), region.outer.hi))
            if not ball.inside(region.hole):
                return False
        return True

    @staticmethod
    def _active(x: Node, hit: np.ndarray | None) -> int:
        return x.active if hit is None else int(round(float(x.weights[hit].sum())))

    def count(self, centres: np.ndarray, radius: float) -> int:
        """Active tuples within `radius` of a centre, at most those within (1 + eps) times that."""
        return sum(self._active(x, hit) for x, hit in self._walk(np.atleast_2d(np.asarray(centres, float)), radius))

    def deactivate(self, centres: np.ndarray, radius: float) -> int:
        """Count, and make them inactive. Several centres go in one walk."""
        return self._drop(self._walk(np.atleast_2d(np.asarray(centres, float)), radius))

    def count_box(self, box: Box) -> int:
        return sum(self._active(x, hit) for x, hit in self._walk(np.zeros((1, len(box.lo))), 0.0, box))

    def deactivate_box(self, box: Box) -> int:
        return self._drop(self._walk(np.zeros((1, len(box.lo))), 0.0, box))

    def represent_box(self, box: Box) -> np.ndarray | None:
        for x, hit in self._walk(np.zeros((1, len(box.lo))), 0.0, box):
            return x.points[np.flatnonzero(hit)[0]] if hit is not None else self._rep(x)
        return None

    def middle_of_box(self, box: Box) -> np.ndarray | None:
        """Of the active tuples that the walk meets in the box, the one nearest to the mean of what the box holds. A node that lies inside stands
        with its mean as far as its sample tells it."""
        some, means, weights = [], [], []
        for x, hit in self._walk(np.zeros((1, len(box.lo))), 0.0, box):
            if x.points is not None:
                own = x.live if hit is None else hit
                some.append(x.points[own])
                means.append(np.average(some[-1], axis=0, weights=x.weights[own]))
            else:
                some.append(self._rep(x)[None, :])
                inner = x.sample if x.sample is not None and x.active == x.total else some[-1]
                means.append(inner.mean(0) if len(inner) else some[-1][0])
                if inner is x.sample:
                    some.append(inner)
            weights.append(self._active(x, hit))
        if not some:
            return None
        p = np.concatenate(some)
        return p[norm(p - np.average(means, axis=0, weights=weights)).argmin()]

    def _drop(self, found: list) -> int:
        total = 0
        for x, hit in found:
            n = self._active(x, hit)
            self.journal.append((x, x.active, None if x.live is None else x.live.copy()))
            if hit is not None:
                x.live = x.live & ~hit
            elif x.live is not None:
                x.live = np.zeros_like(x.live)
            x.active -= n
            total += n
            up = x.parent
            while up is not None:
                self.journal.append((up, up.active, None))
                up.active -= n
                up = up.parent
        return total

    def _rep(self, x: Node) -> np.ndarray:
        while True:
            if x.points is not None:
                return x.points[np.flatnonzero(x.live)[0]]
            live = [c for c in x.children or () if c.active]
            # a node with inactive parts has children; an untouched one keeps its own representative
            if x.active == x.total or not live:
                return x.rep
            x = live[0]

    @property
    def active(self) -> int:
        return self.root.active

    def representative(self) -> np.ndarray | None:
        return self._rep(self.root) if self.root.active else None

    def frontier(self) -> list[Node]:
        """Active nodes without active children: together they hold every active tuple once."""
        out, todo = [], [self.root]
        while todo:
            x = todo.pop()
            if not x.active:
                continue
            if x.children is None or x.active == x.total and x.points is None:
                out.append(x)
            else:
                todo += x.children
        return out

    def report(self) -> tuple[np.ndarray, np.ndarray]:
        """All active tuples with weights."""
        points, weights, ask = [], [], []
        for x in self.frontier():
            if x.points is not None:
                points.append(x.points[x.live])
                weights.append(x.weights[x.live])
            else:
                ask.append(x)
        if ask:
            self.stats.jobs += 1
            for p, w in self.backend.report_regions([x.region for x in ask]):
                points.append(p)
                weights.append(w)
        d = len(self.root.region.outer.lo)
        return (np.concatenate(points), np.concatenate(weights)) if points else (np.empty((0, d)), np.empty(0))

    def reported(self) -> int:
        """The weight of all active tuples as `report` finds them, without holding them together."""
        front = self.frontier()
        held = sum(int(round(float(x.weights[x.live].sum()))) for x in front if x.points is not None)
        ask = [x.region for x in front if x.points is None]
        self.stats.jobs += bool(ask)
        return held + (self.backend.reported_weight(ask) if ask else 0)

    def sample(self, z: int, seed: int = 0) -> np.ndarray:
        """z uniform active tuples: a multinomial over the frontier, and one batch for nodes never opened."""
        front = self.frontier()
        if not front:
            return np.empty((0, len(self.root.region.outer.lo)))
        rng = np.random.Generator(np.random.Philox([self.seed, seed, 7]))
        p = np.array([float(x.active) for x in front])
        draws = rng.multinomial(z, p / p.sum())
        out, ask, want = [], [], []
        for x, n in zip(front, draws, strict=True):
            if not n:
                continue
            if x.points is not None:
                w = x.weights[x.live]
                out.append(x.points[x.live][rng.choice(len(w), n, p=w / w.sum())])
            else:  # fresh draws: those that shaped the tree are not used again
                ask.append(x)
                want.append(int(n))
        if ask:
            self.stats.jobs += 1
            out += self.backend.sample_regions([x.region for x in ask], want, self.seed + 1000 + seed)
        return np.concatenate(out)

    def snapshot(self) -> int:
        return len(self.journal)

    def restore(self, mark: int) -> None:
        while len(self.journal) > mark:
            x, active, live = self.journal.pop()
            x.active = active
            if live is not None:
                x.live = live
            elif x.points is not None:  # it was opened after the mark
                x.live = np.full(len(x.points), active > 0)

    def reset(self) -> None:
        self.restore(0)

    def nodes(self) -> list[Node]:
        out, todo = [], [self.root]
        while todo:
            x = todo.pop()
            out.append(x)
            todo += x.children or ()
        return out


class ClassBackend(SpaceBackend):
    """A join space whose categories are class numbers: counts and reports come by class vector too, in sparse form."""

    def _by_box(self, boxes: list[Box]) -> list[dict[tuple, int]]:
        if isinstance(self.space, resident.ResidentSpace):
            return self.space.count_classes(boxes)
        by = {n: {c: F.col(c) for c in cats} for n, (_, cats) in self.space.owned.items() if cats}
        per: list[dict[tuple, int]] = [{} for _ in boxes]
        for r in self.space.count_classes(boxes, by).collect():  # per box at most the product of the class numbers
            per[r["box_id"]][tuple(r[c] for c in self.space.cats)] = int(r["cnt"])
        return per

    def count_classes(self, regions: list[Region]) -> list[dict[tuple, int]]:
        per = self._by_box([r.outer for r in regions] + [r.hole for r in regions if r.hole is not None])
        out, at = per[: len(regions)], len(regions)
        for i, r in enumerate(regions):
            if r.hole is not None:
                for v, n in per[at].items():
                    out[i][v] -= n
                at += 1
        return [{v: n for v, n in x.items() if n} for x in out]

    def report_classes(self, regions: list[Region]) -> list[tuple[np.ndarray, np.ndarray, list[tuple]]]:
        """(points, weights, class vectors) of each region."""
        boxes = [(i, b) for i, r in enumerate(regions) for b in r.slabs()]
        if isinstance(self.space, resident.ResidentSpace):
            parts: list[list] = [[] for _ in regions]
            for i, b in boxes:
                parts[i].append(self.space.report_classes(b))
            empty = np.empty((0, len(self.space.coords))), np.empty(0), []
            return [(np.concatenate([p for p, _, _ in x]), np.concatenate([w for _, w, _ in x]), [t for _, _, ts in x for t in ts]) if x else empty for x in parts]
        rows = self.space.report([b for _, b in boxes]).withColumn("w", F.col("w").cast("double")).toPandas()
        owner = np.array([i for i, _ in boxes])[rows["box_id"].to_numpy(int)]
        points, w = rows[self.space.coords].to_numpy(float), rows["w"].to_numpy(float)
        tags = list(zip(*(rows[c].tolist() for c in self.space.cats), strict=True)) if self.space.cats else [()] * len(rows)
        return [(points[at], w[at], [tags[j] for j in at]) for at in (np.flatnonzero(owner == i) for i in range(len(regions)))]


class ClassTree(SpatialTree):
    """One tree in which every opened node has a counter of active tuples for each class vector that occurs in it."""

    def __init__(self, space, **options):
        super().__init__(ClassBackend(space), **options)
        self.counters: dict[Node, dict[tuple, int]] = {self.root: self.backend.count_classes([self.root.region])[0]} if self.n else {}
        self.tags: dict[Node, list[tuple]] = {}
        self.undo: list[tuple[Node, dict[tuple, int]]] = []

    def expand(self, nodes: list[Node]) -> None:
        nodes = list(dict.fromkeys(x for x in nodes if x.children is None and x.points is None and x.total and not x.is_location))
        super().expand(nodes)
        leaves = [x for x in nodes if x.points is not None]
        if leaves:  # their points again, by class
            for x, (p, w, tags) in zip(leaves, self.backend.report_classes([x.region for x in leaves]), strict=True):
                x.points, x.weights, x.live, x.near = p, w, np.full(len(p), x.active > 0), None
                self.tags[x] = tags
        made = [c for x in nodes for c in x.children or ()]
        if made:
            self.counters.update(zip(made, self.backend.count_classes([c.region for c in made]), strict=True))

    def classes(self, x: Node, hit: np.ndarray | None) -> dict[tuple, int]:
        if hit is None:
            return dict(self.counters[x])
        out: dict[tuple, int] = {}
        for i in np.flatnonzero(hit):
            out[self.tags[x][i]] = out.get(self.tags[x][i], 0) + int(round(x.weights[i]))
        return out

    def deactivate_classes(self, centres: np.ndarray, radius: float) -> dict[tuple, int]:
        """Active tuples by class vector that the balls take; they become inactive."""
        found = self._walk(np.atleast_2d(np.asarray(centres, float)), radius)
        total: dict[tuple, int] = {}
        for x, hit in found:
            own = self.classes(x, hit)
            for v, n in own.items():
                total[v] = total.get(v, 0) + n
            up: Node | None = x
            while up is not None:
                self.undo.append((up, dict(self.counters[up])))
                for v, n in own.items():
                    self.counters[up][v] -= n
                up = up.parent
        self._drop(found)
        return total

    def count_classes(self, centres: np.ndarray, radius: float) -> dict[tuple, int]:
        """The same without making them inactive."""
        total: dict[tuple, int] = {}
        for x, hit in self._walk(np.atleast_2d(np.asarray(centres, float)), radius):
            for v, n in self.classes(x, hit).items():
                total[v] = total.get(v, 0) + n
        return total

    def reset(self) -> None:
        super().reset()
        while self.undo:
            x, own = self.undo.pop()
            self.counters[x] = own


def flat_tree(points: np.ndarray, weights: np.ndarray | None = None, **options) -> SpatialTree:
    return SpatialTree(ProductBackend(points) if isinstance(points, products.Products) else FlatBackend(points, weights), **options)


def lazy_tree(space, **options) -> SpatialTree:
    return SpatialTree(SpaceBackend(space), **options)
