"""A join space whose pre-aggregated relations fit into memory, for trees: they ask for many small batches of boxes, one after the other.

The messages are those of `space`, passed by arrays: a box's rows are a slice of each relation, multiplicities are summed by key. Nothing is joined,
sampled or left out beforehand; counts, representatives and reported tuples are the same as by Spark, draws are uniform too but use other random numbers.
A tree asks for boxes inside boxes that it asked for before, so the rows that take part in a box are kept (`HELD` row numbers at most, the oldest go
first) and a box inside it starts from them. Relations with more than `MOST` values stay with Spark.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import functions as F

from .region import Box, Region

#: Values (rows times columns) that all relations together may have, 8 bytes each.
MOST = 24_000_000
#: Row numbers that are kept of earlier boxes, 4 bytes each, and for how many boxes.
HELD = 16_000_000
HELD_BOXES = 4096
#: Tuples that a report without a result (`reported_weight`) makes at once.
CHUNK = 1_000_000


def of(space, most: int | None = None) -> ResidentSpace | None:
    """The space in memory, if its relations have at most `most` values and its counts are whole numbers in doubles."""
    if space.tree is None:
        return None
    room = MOST if most is None else most
    mine = [f for f in space.frames.values() if not f.storageLevel.useMemory]  # counted and then fetched: not made twice
    for f in mine:
        f.persist()
    try:
        for f in space.frames.values():
            room -= f.count() * len(f.columns)
            if room < 0:
                return None
        near = ResidentSpace(space)
    finally:
        for f in mine:
            f.unpersist()
    # with a key's number, that of a class vector fits into 63 bits
    return near if near.total < 2**52 and near.vectors < 2**31 else None


class ResidentSpace:
    def __init__(self, space):
        self.coords, self.tree = space.coords, space.tree
        self.at = {c: i for i, c in enumerate(self.coords)}
        self.order = space.rep_order()
        self.names = self.tree.upward()
        self.below = {n: self.tree.children(n) for n in self.names}
        self.mine: dict[str, list[int]] = {}
        self.x: dict[str, np.ndarray] = {}
        self.w: dict[str, np.ndarray] = {}
        self.tags: dict[str, list[tuple]] = {}  # per relation the values of its categories that occur together
        self.tag: dict[str, np.ndarray | None] = {}  # and their number in each row
        self.cats, self.order_of_cats = space.cats, []
        keys: dict[str, dict[str, np.ndarray]] = {}
        for n in self.names:
            own = space.owned[n][0]
            f = space.frames[n]
            cats = space.owned[n][1]
            rows = f.select(*[c for c in f.columns if c.startswith("k_")], *own, *cats, F.col("w").cast("double").alias("w")).toArrow()
            x = np.stack([rows[c].to_numpy() for c in own], 1) if own else np.empty((rows.num_rows, 0))
            by = np.lexsort(x.T[::-1]) if own else np.arange(rows.num_rows)  # least tuples first; a box is a slice of the first coordinate
            self.mine[n], self.x[n], self.w[n] = [self.at[c] for c in own], x[by], rows["w"].to_numpy()[by]
            keys[n] = {c: np.asarray(rows[c].to_numpy(zero_copy_only=False))[by] for c in rows.column_names if c.startswith("k_")}
            self.tags[n], self.tag[n] = [()], None
            if cats:
                code, values = pd.MultiIndex.from_frame(rows.select(cats).to_pandas()).factorize(use_na_sentinel=False)
                self.tags[n], self.tag[n] = [tuple(None if pd.isna(v) else v for v in x) for x in values], code[by]
            self.order_of_cats += cats
        self.radix = dict(zip(self.names, np.cumprod([1, *(len(self.tags[n]) for n in self.names)], dtype=object).tolist()))
        self.vectors = math.prod(len(x) for x in self.tags.values())
        self.up: dict[str, np.ndarray] = {}  # per relation the number of its key towards the parent
        self.down: dict[str, np.ndarray] = {}  # per relation the numbers of that key in the parent's rows
        self.many: dict[str, int] = {}
        for n in self.names:
            p = self.tree.parent[n]
            if p is None:
                self.up[n], self.many[n] = np.zeros(len(self.w[n]), np.int32), 1
                continue
            both = None
            for a in self.tree.shared[n]:
                code = pd.factorize(np.concatenate([keys[n][f"k_{a}"], keys[p][f"k_{a}"]]), use_na_sentinel=False)[0]
                both = code if both is None else pd.factorize(both * (int(code.max(initial=0)) + 1) + code)[0]
            both = np.zeros(len(self.w[n]) + len(self.w[p]), np.int32) if both is None else both.astype(np.int32)
            self.up[n], self.down[n], self.many[n] = both[: len(self.w[n])], both[len(self.w[n]) :], int(both.max(initial=0)) + 1
        self._sums = {n: np.zeros(m) for n, m in self.many.items()}
        self.held: dict[int, tuple[int, dict[str, np.ndarray]]] = {}  # by slot: the number of rows, and the rows
        self.held_lo, self.held_hi = (np.full((HELD_BOXES, len(self.coords)), v) for v in (np.inf, -np.inf))
        self.held_many, self.next_slot, self.held_rows = np.zeros(HELD_BOXES, int), 0, 0
        self._whole = Box(np.full(len(self.coords), -np.inf), np.full(len(self.coords), np.inf))
        if any(self.mine[n] and not len(x) for n, x in self.x.items()):
            self._box = Box(np.zeros(len(self.coords)), np.zeros(len(self.coords)))
        else:
            ends = {c: (v.min(), v.max()) for n, x in self.x.items() for c, v in zip(self.mine[n], x.T, strict=True)}
            self._box = Box(np.array([ends[c][0] for c in range(len(self.coords))]), np.nextafter(np.array([ends[c][1] for c in range(len(self.coords))]), np.inf))
        self.total = float(self._weighted(self._whole)[self.tree.root][1].sum())
        self.heaviest = math.prod(float(w.max(initial=1)) for w in self.w.values())  # no reported row weighs more, before equal ones are put together

    def root_box(self) -> Box:
        return self._box

    def size(self) -> int:
        return int(self.total)

    def _rows(self, n: str, box: Box, slot: int | None) -> np.ndarray:
        mine, x = self.mine[n], self.x[n]
        if slot is not None:
            at, lo, hi = self.held[slot][1][n], self.held_lo[slot], self.held_hi[slot]
            for j, c in enumerate(mine):
                if box.lo[c] > lo[c] or box.hi[c] < hi[c]:
                    v = x[at, j]
                    at = at[(v >= box.lo[c]) & (v < box.hi[c])]
            return at
        if not mine:
            return np.arange(len(x), dtype=np.int32)
        a, z = np.searchsorted(x[:, 0], [box.lo[mine[0]], box.hi[mine[0]]])
        at = np.arange(a, z, dtype=np.int32)
        for j, c in enumerate(mine[1:], 1):
            at = at[(x[at, j] >= box.lo[c]) & (x[at, j] < box.hi[c])]
        return at

    def _around(self, box: Box) -> int | None:
        """The kept box with the fewest rows that this one lies in."""
        at = np.flatnonzero((self.held_lo <= box.lo).all(1) & (self.held_hi >= box.hi).all(1))
        return int(at[self.held_many[at].argmin()]) if len(at) else None

    def _under(self, rows: dict[str, tuple[np.ndarray, np.ndarray]], top: np.ndarray) -> dict[str, np.ndarray]:
        """Of rows with partners below them those that some of the root's rows `top` meet."""
        kept: dict[str, np.ndarray] = {}
        for n in reversed(self.names):
            p = self.tree.parent[n]
            if p is None:
                kept[n] = top
                continue
            at, seen, want = rows[n][0], self._sums[n], self.down[n][kept[p]]
            seen[want] = 1
            kept[n] = at[seen[self.up[n][at]] > 0]
            seen[want] = 0
        return kept

    def _hold(self, box: Box, rows: dict[str, tuple[np.ndarray, np.ndarray]], slot: int | None) -> None:
        """Keeps the rows of some tuple in the box, if they are clearly fewer than those it was made from."""
        kept = self._under(rows, rows[self.tree.root][0])
        many = sum(map(len, kept.values()))
        whole = sum(map(len, self.w.values())) if slot is None else self.held_many[slot]
        if 5 * many > 4 * whole or many > HELD // 2:
            return
        here = self.next_slot
        while here in self.held or self.held and self.held_rows + many > HELD:
            old = next(iter(self.held))
            self.held_rows -= self.held.pop(old)[0]
            self.held_lo[old], self.held_hi[old] = np.inf, -np.inf
        self.held[here] = many, kept
        self.held_lo[here], self.held_hi[here], self.held_many[here] = box.lo, box.hi, many
        self.held_rows, self.next_slot = self.held_rows + many, (here + 1) % HELD_BOXES

    def _weighted(self, box: Box, hold: bool = False) -> dict[str, tuple[np.ndarray, np.ndarray]]:
        """Per relation its rows in the box that have partners below them, with the weight of the subtree."""
        out, slot = {}, self._around(box)
        for n in self.names:
            at = self._rows(n, box, slot)
            w = self.w[n][at]
            for c in self.below[n]:
                w = w * self._sums[c][self.down[c][at]]
            if self.below[n]:
                live = w > 0
                at, w = at[live], w[live]
            out[n] = at, w
            if self.tree.parent[n] is not None:
                np.add.at(self._sums[n], self.up[n][at], w)
        for n in self.names:  # zeros again
            self._sums[n][self.up[n][out[n][0]]] = 0
        if hold and len(out[self.tree.root][0]):
            self._hold(box, out, slot)
        return out

    def count_and_represent(self, boxes: list[Box], rep: bool = True) -> tuple[np.ndarray, list[np.ndarray | None]]:
        counts, reps = np.zeros(len(boxes), object), [None] * len(boxes)
        for i, box in enumerate(boxes):
            rows = self._weighted(box, hold=True)
            counts[i] = int(rows[self.tree.root][1].sum())
            if rep and counts[i]:
                reps[i] = self._least(rows)[self.order]
        return counts, reps

    def _least(self, rows: dict) -> np.ndarray:
        """The least tuple, in the order of `upward`'s messages."""
        sent: dict[str, np.ndarray] = {}
        top, own = rows[self.tree.root][0], self.x[self.tree.root]
        if own.shape[1]:  # rows are in order: only those with the first one's coordinates can be least, and what they meet
            top = top[: np.searchsorted(own[top, 0], own[top[0], 0], side="right")]
            top = top[(own[top] == own[top[0]]).all(1)]
        kept = self._under(rows, top)
        for n in self.names:
            at = kept[n]
            below = [sent[c][self.down[c][at]] for c in self.below[n]]
            x = np.concatenate([self.x[n][at], *below], 1)
            if below and x.shape[1]:  # own coordinates are in order, those below them need not be where they are equal
                by = np.lexsort(x.T[::-1])
                at, x = at[by], x[by]
            sent[n] = np.empty((self.many[n], x.shape[1]))
            sent[n][self.up[n][at[::-1]]] = x[::-1]  # the first row of a key is written last
        return sent[self.tree.root][0]

    def representative(self, boxes: list[Box]) -> list[np.ndarray | None]:
        return self.count_and_represent(boxes)[1]

    def represent_regions(self, regions: list[Region]) -> list[np.ndarray | None]:
        return [next((x for x in self.representative(r.slabs()) if x is not None), None) for r in regions]

    def _draw(self, box: Box, z: int, rng: np.random.Generator) -> np.ndarray:
        rows = self._weighted(box)
        out = np.empty((z, len(self.coords)))
        picked: dict[str, np.ndarray] = {}
        for n in reversed(self.names):
            at, w = rows[n]
            p = self.tree.parent[n]
            want = np.zeros(z, int) if p is None else self.down[n][picked[p]]
            by = np.argsort(self.up[n][at], kind="stable")
            at, ends = at[by], np.cumsum(w[by])
            key = self.up[n][at]
            first, last = np.searchsorted(key, want), np.searchsorted(key, want, side="right") - 1
            before = np.where(first > 0, ends[first - 1], 0.0)
            point = before + rng.random(z) * (ends[last] - before)
            picked[n] = at[np.clip(np.searchsorted(ends, point, side="right"), first, last)]
            out[:, self.mine[n]] = self.x[n][picked[n]]
        return out

    def sample_regions(self, regions: list[Region], draws: list[int], seed: int = 42) -> list[np.ndarray]:
        """Per region a multinomial over its slabs' counts, then draws in the slabs: every tuple is equally likely."""
        out = []
        for i, (r, z) in enumerate(zip(regions, draws, strict=True)):
            rng = np.random.Generator(np.random.Philox([seed, i]))
            slabs = r.slabs()
            counts = self.count_and_represent(slabs, rep=False)[0].astype(float)
            want = rng.multinomial(z, counts / counts.sum()) if counts.sum() else []
            out.append(np.concatenate([np.empty((0, len(self.coords))), *[self._draw(b, int(m), rng) for b, m in zip(slabs, want) if m]]))
        return out

    def report_regions(self, regions: list[Region]) -> list[tuple[np.ndarray, np.ndarray]]:
        """Distinct coordinate tuples and weights of each region; callers bound the counts."""
        out = []
        for r in regions:
            parts = [self._report(b) for b in r.slabs()]
            out.append((np.concatenate([p for p, _ in parts]), np.concatenate([w for _, w in parts])) if parts else (np.empty((0, len(self.coords))), np.empty(0)))
        return out

    def count_rows(self, regions: list[Region]) -> list[int]:
        """How many combinations of rows each region holds: what a report makes before equal tuples are put together."""
        return [sum(self._combinations(self._weighted(b)) for b in r.slabs()) for r in regions]

    def _combinations(self, rows: dict[str, tuple[np.ndarray, np.ndarray]]) -> int:
        many = np.zeros(0)
        for n in self.names:
            at = rows[n][0]
            many = np.ones(len(at))
            for c in self.below[n]:
                many *= self._sums[c][self.down[c][at]]
            np.add.at(self._sums[n], self.up[n][at], many)
        for n in self.names:  # zeros again
            self._sums[n][self.up[n][rows[n][0]]] = 0
        return int(many.sum())

    def reported_weight(self, regions: list[Region]) -> int:
        return sum(int(w.sum()) for r in regions for b in r.slabs() for _, _, w in self._picked(b, CHUNK))

    def _report(self, box: Box) -> tuple[np.ndarray, np.ndarray]:
        _, x, w = next(self._picked(box))
        if not len(x):
            return x, w
        by = np.lexsort(x.T[::-1])
        x, w = x[by], w[by]
        first = np.flatnonzero(np.concatenate([[True], (x[1:] != x[:-1]).any(1)]))
        return x[first], np.add.reduceat(w, first)

    def _by_key(self, n: str, at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        at = at[np.argsort(self.up[n][at], kind="stable")]
        return at, self.up[n][at]

    @staticmethod
    def _partners(key: np.ndarray, want: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(how many each wanted key has, their places) in sorted keys."""
        first, last = np.searchsorted(key, want), np.searchsorted(key, want, side="right")
        each = last - first
        return each, np.repeat(first, each) + np.arange(each.sum()) - np.repeat(np.cumsum(each) - each, each)

    def _picked(self, box: Box, most: float = np.inf) -> Iterator[tuple[dict[str, np.ndarray], np.ndarray, np.ndarray]]:
        """Each tuple's rows, coordinates and weight, equal ones not yet together; about `most` at once, or as many as one row of the root has."""
        rows, root = self._weighted(box), self.tree.root
        sorted_ = {n: self._by_key(n, rows[n][0]) for n in self.names if n != root}
        part = (np.cumsum(rows[root][1]) // most).astype(np.int64) if most < np.inf else np.zeros(len(rows[root][0]), np.int64)
        for some in np.split(rows[root][0], np.flatnonzero(np.diff(part)) + 1):
            picked: dict[str, np.ndarray] = {root: some}
            for n in reversed(self.names):
                if n == root:
                    continue
                at, key = sorted_[n]
                each, place = self._partners(key, self.down[n][picked[self.tree.parent[n]]])
                picked = {m: np.repeat(v, each) for m, v in picked.items()}
                picked[n] = at[place]
            total = len(picked[root])
            x, w = np.empty((total, len(self.coords))), np.ones(total)
            for n, at in picked.items():
                x[:, self.mine[n]] = self.x[n][at]
                w *= self.w[n][at]
            yield picked, x, w

    # classes

    def _classes(self, n: str, at: np.ndarray) -> np.ndarray:
        """What the rows' categories add to the number of a class vector."""
        return np.zeros(len(at), np.int64) if self.tag[n] is None else self.tag[n][at] * self.radix[n]

    def _vector(self, number: int) -> tuple:
        """The category values, in the space's order."""
        found = [v for n in self.names for v in self.tags[n][number // self.radix[n] % len(self.tags[n])]]
        of = dict(zip(self.order_of_cats, found, strict=True))
        return tuple(of[c] for c in self.cats)

    def count_classes(self, boxes: list[Box]) -> list[dict[tuple, int]]:
        """Per box the number of tuples of each class vector that occurs: messages have a row a key and classes below it."""
        out = []
        for box in boxes:
            rows = self._weighted(box)
            sent: dict[str, tuple[np.ndarray, np.ndarray, np.ndarray]] = {}
            for n in self.names:
                at = rows[n][0]
                w, vector = self.w[n][at], self._classes(n, at)
                for c in self.below[n]:
                    key, below, sums = sent[c]
                    each, place = self._partners(key, self.down[c][at])
                    at, w, vector = np.repeat(at, each), np.repeat(w, each) * sums[place], np.repeat(vector, each) + below[place]
                code, both = pd.factorize(self.up[n][at] * np.int64(self.vectors) + vector)
                sums, by = np.bincount(code, w, len(both)), np.argsort(both)
                sent[n] = both[by] // self.vectors, both[by] % self.vectors, sums[by]
            _, vector, sums = sent[self.tree.root]
            out.append({self._vector(v): int(k) for v, k in zip(vector.tolist(), sums.tolist(), strict=True)})
        return out

    def report_classes(self, box: Box) -> tuple[np.ndarray, np.ndarray, list[tuple]]:
        """(points, weights, class vectors) of a box."""
        picked, x, w = next(self._picked(box))
        vector = np.zeros(len(x), np.int64)
        for n, at in picked.items():
            vector += self._classes(n, at)
        if not len(x):
            return x, w, []
        by = np.lexsort([vector, *x.T[::-1]])
        x, w, vector = x[by], w[by], vector[by]
        first = np.flatnonzero(np.concatenate([[True], (x[1:] != x[:-1]).any(1) | (vector[1:] != vector[:-1])]))
        names = {v: self._vector(v) for v in set(vector[first].tolist())}
        return x[first], np.add.reduceat(w, first), [names[v] for v in vector[first].tolist()]
