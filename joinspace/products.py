"""The tuples of a join that is too large to hold, as pairs of rows of two sides of its join tree.

One edge cuts the tree in two; each side is joined (on the executors) and grouped by the edge's attributes and its own coordinates. The join's tuples
are the pairs of rows that agree on those attributes, so the flat solvers can go through all of them, block by block, as often as they like: every tuple is
made in every pass, none is left out, and only the sides are in memory. A squared distance is the sum of the sides', which makes a block cheap.
Unlike rows of `baselines.materialized`, equal tuples that come by different attributes of the edge stay apart, each with its own weight.
"""

from __future__ import annotations

import os
from collections.abc import Callable, Iterator
from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass
from itertools import chain, islice

import numpy as np
from pyspark.sql import functions as F

from .hypergraph import JoinTree
from .region import Box, distance_bounds
from .spec import JoinSpec

#: Values (rows times columns) that both sides together may have, 8 bytes each.
MOST = 24_000_000
#: Tuples of a block; keys with fewer pairs than `THIN` share blocks.
BLOCK, THIN = 1 << 16, 1 << 12
#: From how many centres a block loses those that are nearest to none of its tuples, and up to how many pairs it is compared in full.
FEW, NEAR = 24, 1 << 17


def of(space, most: int | None = None) -> Products | None:
    """The pairs along the edge whose larger side is smallest; None without an edge, or where its sides have more than `most` values."""
    tree, best = space.tree, None
    if tree is None:
        return None
    each = {n: f.withColumn("w", F.lit(1).cast("decimal(38,0)")) for n, f in space.frames.items()}
    for edge in (n for n, p in tree.parent.items() if p is not None):
        sides = [_side(space, names, top) for names, top in _cut(tree, edge)]
        if not all(s.coords for s in sides):
            continue
        values = [s.with_frames({n: each[n] for n in s.frames}).size() * (len(s.coords) + len(tree.shared[edge]) + 1) for s in sides]
        if best is None or max(values) < best[0]:
            best = max(values), sum(values), sides, tree.shared[edge]
    if best is None or best[1] > (MOST if most is None else most):
        return None
    _, _, sides, shared = best
    held = []
    for s in sides:
        rows = _joined(s).groupBy(*[f"k_{a}" for a in shared], *s.coords).agg(F.sum("w").cast("double").alias("w")).toArrow()
        held.append((np.stack([rows[c].to_numpy() for c in s.coords], 1), rows["w"].to_numpy(), [np.asarray(rows[f"k_{a}"].to_numpy(zero_copy_only=False)) for a in shared]))
    (x, u, a), (y, v, b) = held
    key = np.zeros(len(x) + len(y), np.int64)
    for i, j in zip(a, b, strict=True):
        code = np.unique(np.concatenate([i, j]), return_inverse=True)[1].ravel()
        key = np.unique(key * (int(code.max(initial=0)) + 1) + code, return_inverse=True)[1].ravel()
    at = {c: i for i, c in enumerate(space.coords)}
    mine = [np.array([at[c] for c in s.coords]) for s in sides]
    by, to = (np.lexsort([*z.T[::-1], k]) for z, k in ((x, key[: len(x)]), (y, key[len(x) :])))
    return Products(x[by], u[by], key[: len(x)][by], y[to], v[to], key[len(x) :][to], *mine)


def _cut(tree: JoinTree, edge: str) -> list[tuple[list[str], str]]:
    """(relations, the uppermost of them) above and below an edge."""
    below, todo = [], [edge]
    while todo:
        below.append(todo.pop())
        todo += tree.children(below[-1])
    return [([n for n in tree.parent if n not in below], tree.root), (below, edge)]


def _side(space, names: list[str], top: str):
    tree = JoinTree(top, {n: None if n == top else p for n, p in space.tree.parent.items() if n in names}, {n: () if n == top else space.tree.shared[n] for n in names})
    spec = JoinSpec(space.spec.name, tuple(r for r in space.spec.relations if r.name in names))
    own = {n: (space.owned[n][0], []) for n in names}
    return type(space)(spec, {n: space.frames[n] for n in names}, [c for c in space.coords if any(c in v for v, _ in own.values())], [], tree, space.scale, own)


def _joined(side):
    """The side's tuples with their keys and multiplicities."""
    out = None
    for n in reversed(side.tree.upward()):
        f = side.frames[n]
        if out is None:
            out = f
            continue
        on, f = [f"k_{a}" for a in side.tree.shared[n]], f.withColumnRenamed("w", "w2")
        out = (out.join(f, on) if on else out.crossJoin(f)).withColumn("w", (F.col("w") * F.col("w2")).cast("decimal(38,0)")).drop("w2")
    return out


@dataclass(frozen=True, eq=False)
class Block:
    """All pairs of some left and some right rows; the pair (i, j) is tuple number first + i * stride + j."""

    x: np.ndarray
    u: np.ndarray
    y: np.ndarray
    v: np.ndarray
    mine: np.ndarray  # the coordinates of x, and those of y
    other: np.ndarray
    first: int
    stride: int

    def values(self, c: np.ndarray, metric: str) -> np.ndarray:
        """Distances to a centre, squared for l2."""
        a, b = _part(self.x, c[self.mine], metric), _part(self.y, c[self.other], metric)
        return np.maximum.outer(a, b) if metric == "linf" else np.add.outer(a, b)

    def least(self, centres: np.ndarray, metric: str) -> np.ndarray:
        out = self.values(centres[0], metric)
        for c in centres[1:]:
            np.minimum(out, self.values(c, metric), out=out)
        return out

    def sum(self, values: np.ndarray) -> float:
        return float(self.u @ (values @ self.v))

    def box(self) -> Box:
        lo, hi = np.empty(len(self.mine) + len(self.other)), np.empty(len(self.mine) + len(self.other))
        lo[self.mine], hi[self.mine], lo[self.other], hi[self.other] = self.x.min(0), self.x.max(0), self.y.min(0), self.y.max(0)
        return Box(lo, hi)

    def halves(self, axis: int) -> tuple[Block, Block]:
        """Cut at the median of a coordinate; numbers of tuples are lost."""
        left = axis in self.mine
        z, w = (self.x, self.u) if left else (self.y, self.v)
        half = len(z) // 2
        by = np.argpartition(z[:, int(np.flatnonzero((self.mine if left else self.other) == axis)[0])], half)
        parts = [(z[at], w[at]) for at in (by[:half], by[half:])]
        return tuple(Block(*p, self.y, self.v, self.mine, self.other, -1, 0) if left else Block(self.x, self.u, *p, self.mine, self.other, -1, 0) for p in parts)


def _part(x: np.ndarray, c: np.ndarray, metric: str) -> np.ndarray:
    d = np.abs(x - c)
    return (d * d).sum(1) if metric == "l2" else d.sum(1) if metric == "l1" else d.max(1, initial=0)


def _end(values, metric: str):
    return np.sqrt(values) if metric == "l2" else values


class Weights:
    """The tuples' weights: only their sum is asked for."""

    def __init__(self, total: float):
        self.total = total

    def sum(self) -> float:
        return self.total


class Products:
    """Rows of both sides in the order of their keys. A tuple has a number: by key, then left row, then right row; keys with few pairs come first."""

    def __init__(self, x, u, left, y, v, right, mine, other):
        self.mine, self.other = mine, other
        keep, also = np.isin(left, right), np.isin(right, left)
        x, u, left, y, v, right = x[keep], u[keep], left[keep], y[also], v[also], right[also]
        self.x, self.u, self.y, self.v = x, u, y, v
        self.left, self.right = (np.unique(k, return_inverse=True)[1].ravel() for k in (left, right))
        many = int(self.left.max(initial=-1)) + 1
        self.a, self.b = (np.searchsorted(k, np.arange(many + 1)) for k in (self.left, self.right))
        pairs = np.diff(self.a) * np.diff(self.b)
        self.order = np.argsort(pairs >= THIN, kind="stable")  # of the keys
        self.ends = np.cumsum(pairs[self.order])
        self.thin = int((pairs < THIN).sum())
        self.weight_right = np.add.reduceat(v, self.b[:-1]) if many else np.zeros(0)
        self.weights = Weights(float((u * self.weight_right[self.left]).sum()) if many else 0.0)

    @property
    def shape(self) -> tuple[int, int]:
        return len(self), len(self.mine) + len(self.other)

    def __len__(self) -> int:
        return int(self.ends[-1]) if len(self.ends) else 0

    def _rows(self, numbers: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Left and right rows of tuples."""
        at = np.searchsorted(self.ends, numbers, side="right")
        key = self.order[at]
        i, j = np.divmod(numbers - np.where(at > 0, self.ends[at - 1], 0), np.diff(self.b)[key])
        return self.a[key] + i, self.b[key] + j

    def _tuples(self, i: np.ndarray, j: np.ndarray) -> np.ndarray:
        out = np.empty((len(i), self.shape[1]))
        out[:, self.mine], out[:, self.other] = self.x[i], self.y[j]
        return out

    def __getitem__(self, at) -> np.ndarray:
        numbers = np.arange(*at.indices(len(self))) if isinstance(at, slice) else np.asarray(at, np.int64)
        out = self._tuples(*self._rows(np.atleast_1d(np.where(numbers < 0, numbers + len(self), numbers))))
        return out if numbers.ndim else out[0]

    def held(self) -> tuple[np.ndarray, np.ndarray]:
        """All tuples and weights; callers bound their number."""
        i, j = self._rows(np.arange(len(self)))
        return self._tuples(i, j), self.u[i] * self.v[j]

    def within(self, box: Box) -> Products:
        """The tuples in a box: rows drop out on their own side."""
        i, j = (((z >= box.lo[at]) & (z < box.hi[at])).all(1) for z, at in ((self.x, self.mine), (self.y, self.other)))
        return Products(self.x[i], self.u[i], self.left[i], self.y[j], self.v[j], self.right[j], self.mine, self.other)

    # passes

    def _thin(self) -> Iterator[Block]:
        """The keys with few pairs: a tuple is a left row, beside one right row without coordinates."""
        last = int(self.ends[self.thin - 1]) if self.thin else 0
        every, none = np.arange(self.shape[1]), np.zeros(0, int)
        for at in range(0, last, BLOCK):
            i, j = self._rows(np.arange(at, min(at + BLOCK, last)))
            yield Block(self._tuples(i, j), self.u[i] * self.v[j], np.empty((1, 0)), np.ones(1), every, none, at, 1)

    def _wide(self, block: int | None) -> Iterator[Block]:
        """The other keys, in blocks of about `block` pairs, or whole."""
        for at in range(self.thin, len(self.order)):
            k, base = self.order[at], int(self.ends[at - 1]) if at else 0
            a, z, b, y = self.a[k], self.a[k + 1], self.b[k], self.b[k + 1]
            wide = int(y - b) if block is None else min(int(y - b), max(256, block // 16))
            high = int(z - a) if block is None else max(1, block // wide)
            for i in range(0, z - a, high):
                for j in range(0, y - b, wide):
                    p, q = slice(a + i, min(a + i + high, z)), slice(b + j, min(b + j + wide, y))
                    yield Block(self.x[p], self.u[p], self.y[q], self.v[q], self.mine, self.other, base + i * int(y - b) + j, int(y - b))

    def _each(self, f: Callable[[Block], object], block: int | None = BLOCK) -> list:
        """f of every block, in their order, by threads: numpy lets go of the interpreter."""
        def blocks():
            yield from self._thin()
            yield from self._wide(block)

        threads = os.cpu_count() or 1
        out: list = []
        with ThreadPoolExecutor(threads) as pool:
            some: list[Block] = []
            for b in blocks():
                some.append(b)
                if len(some) == 64 * threads:  # so that no more blocks than these are made ahead
                    out += pool.map(f, some)
                    some = []
            out += pool.map(f, some)
        return out

    def _reduced(self, centres: np.ndarray, f: Callable[[Block, np.ndarray], float], metric: str) -> list[float]:
        """f of every block and its tuples' least values. Of many centres a block is asked those that can be nearest in its box."""
        if len(centres) < FEW:
            return self._each(lambda b: f(b, b.least(centres, metric)))

        def pruned(b: Block) -> list[float]:
            out, todo = [], [(b, centres)]
            while todo:
                b, some = todo.pop()
                box = b.box()
                near, far = distance_bounds(box, some, metric)
                some = some[near <= far.min() * (1 + 1e-9)]  # over rounding
                pairs, axis = len(b.u) * len(b.v), int(np.argmax(box.hi - box.lo))
                if len(some) > 4 and pairs * len(some) > NEAR and pairs > 64 and box.hi[axis] > box.lo[axis]:
                    todo += [(h, some) for h in b.halves(axis)]
                    continue
                for at in range(0, len(b.u), high := max(1, BLOCK // len(b.v))):
                    part = Block(b.x[at : at + high], b.u[at : at + high], b.y, b.v, b.mine, b.other, -1, 0)
                    out.append(f(part, part.least(some, metric)))
            return out

        return [v for part in self._each(pruned, 16 * BLOCK) for v in part]

    def cost(self, centres: np.ndarray, objective: str, metric: str = "l2") -> float:
        centres = np.asarray(centres, float)
        if objective == "center":
            return float(_end(max(self._reduced(centres, lambda b, d: float(d.max()), metric)), metric))
        power = (lambda d: _end(d, metric)) if objective == "median" else (lambda d: d if metric == "l2" else d * d)
        return float(sum(self._reduced(centres, lambda b, d: b.sum(power(d)), metric)))

    def weight_near(self, centres: np.ndarray, reach: float, metric: str = "l2") -> float:
        """The weight of the tuples within reach of a centre."""
        return float(sum(self._reduced(np.asarray(centres, float), lambda b, d: b.sum((_end(d, metric) <= reach).astype(float)), metric)))

    def farthest(self, centres: np.ndarray, metric: str = "l2") -> tuple[int, float]:
        """(number, distance) of a tuple farthest from the centres, the first of equals."""
        def one(b: Block) -> tuple[float, int]:
            d = b.least(centres, metric)
            i, j = np.unravel_index(int(d.argmax()), d.shape)
            return float(d[i, j]), -(b.first + int(i) * b.stride + int(j))

        value, at = max(self._each(one))
        return -at, float(_end(value, metric))

    def first_beyond(self, centres: np.ndarray, reach: float, metric: str = "l2") -> int | None:
        """The number of the first tuple out of reach of all centres."""
        def one(b: Block) -> int | None:
            i, j = np.nonzero(_end(b.least(centres, metric), metric) > reach)
            return int((b.first + i * b.stride + j).min()) if len(i) else None

        return min((x for x in self._each(one) if x is not None), default=None)

    def nearest(self, points: np.ndarray, metric: str = "l2") -> tuple[np.ndarray, np.ndarray]:
        """(number, distance) of the tuple nearest to each point: in each key that of the sides' nearest rows."""
        numbers, dist = np.empty(len(points), int), np.empty(len(points))
        base = np.empty(len(self.order), np.int64)
        base[self.order] = np.concatenate([[0], self.ends[:-1]])
        for n, c in enumerate(points):
            a, b = _part(self.x, c[self.mine], metric), _part(self.y, c[self.other], metric)
            s, t = np.minimum.reduceat(a, self.a[:-1]), np.minimum.reduceat(b, self.b[:-1])
            both = np.maximum(s, t) if metric == "linf" else s + t
            k = int(both.argmin())
            i, j = int(a[self.a[k] : self.a[k + 1]].argmin()), int(b[self.b[k] : self.b[k + 1]].argmin())
            numbers[n], dist[n] = base[k] + i * (self.b[k + 1] - self.b[k]) + j, _end(both[k], metric)
        return numbers, dist

    # draws

    def draw(self, z: int, rng: np.random.Generator) -> np.ndarray:
        """z tuples by weight."""
        if not len(self):
            return self[:0]
        ends = np.cumsum(self.u * self.weight_right[self.left])
        i = np.minimum(np.searchsorted(ends, rng.random(z) * ends[-1], side="right"), len(ends) - 1)
        ends, k = np.cumsum(self.v), self.left[i]
        before = np.where(self.b[k] > 0, ends[self.b[k] - 1], 0.0)
        j = np.searchsorted(ends, before + rng.random(z) * (ends[self.b[k + 1] - 1] - before), side="right")
        return self._tuples(i, np.clip(j, self.b[k], self.b[k + 1] - 1))

    def draw_far(self, centres: np.ndarray, power: int, rng: np.random.Generator) -> np.ndarray | None:
        """A tuple by weight times its distance to the centres to a power: first its block, then the pair."""
        def value(b: Block) -> np.ndarray:
            d = b.least(centres, "l2")
            return np.sqrt(d) if power == 1 else d

        p = np.array(self._each(lambda b: b.sum(value(b))))
        if p.sum() <= 0:
            return None
        want = int(rng.choice(len(p), p=p / p.sum()))
        b = next(islice(chain(self._thin(), self._wide(BLOCK)), want, None))
        each = (b.u[:, None] * value(b) * b.v[None, :]).ravel()
        i, j = np.divmod(int(rng.choice(len(each), p=each / each.sum())), len(b.v))
        return self[b.first + int(i) * b.stride + int(j)]

    # sums for the solvers

    def means(self, centres: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(weight, weighted sum of tuples) of those nearest to each centre, the first of equals."""
        def one(b: Block) -> tuple[np.ndarray, np.ndarray]:
            w, total = np.zeros(len(centres)), np.zeros((len(centres), self.shape[1]))
            least, at = b.values(centres[0], "l2"), np.zeros((len(b.u), len(b.v)), np.int16)
            for n, c in enumerate(centres[1:], 1):
                d = b.values(c, "l2")
                at[d < least] = n
                np.minimum(least, d, out=least)
            for n in range(len(centres)):
                own = (at == n).astype(float)
                rows, columns = b.u * (own @ b.v), b.v * (b.u @ own)
                w[n] = rows.sum()
                total[n, b.mine], total[n, b.other] = rows @ b.x, columns @ b.y
            return w, total

        parts = self._each(one)
        return sum(w for w, _ in parts), sum(t for _, t in parts)

    def swapped(self, centres: np.ndarray, new: np.ndarray, power: int) -> np.ndarray:
        """The cost with `new` in place of each centre."""
        def one(b: Block) -> np.ndarray:
            first, at = b.values(centres[0], "l2"), np.zeros((len(b.u), len(b.v)), np.int16)
            second = np.full_like(first, np.inf)
            for n, c in enumerate(centres[1:], 1):
                d = b.values(c, "l2")
                np.minimum(second, np.maximum(first, d), out=second)
                at[d < first] = n
                np.minimum(first, d, out=first)
            d = b.values(new, "l2")
            np.minimum(first, d, out=first)
            np.minimum(second, d, out=second)
            if power == 1:
                first, second = np.sqrt(first), np.sqrt(second)
            kept, more = b.sum(first), second - first
            return np.array([kept + b.sum(np.where(at == n, more, 0.0)) for n in range(len(centres))])

        return sum(self._each(one))
