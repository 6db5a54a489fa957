"""Radius candidates: differences of base values by rank, or a geometric ladder."""

from __future__ import annotations

import os
from concurrent.futures import ThreadPoolExecutor

import numpy as np
from pyspark.sql import functions as F

#: Values that one thread takes.
PART = 1 << 16
#: How far, as a share of it, a rank's difference may be overstated: well under what the search takes for equal.
FINE = 1e-10
#: Differences that are listed when the rank is known to be among them.
LISTED = 2_000_000


def pairs_up_to(values: np.ndarray, x: float) -> int:
    """Pairs i < j of sorted values with difference at most x."""
    def some(at: int) -> int:
        own = values[at : at + PART]
        return int((np.searchsorted(values[at:], own + x, side="right") - np.arange(1, len(own) + 1)).sum())

    if len(values) <= PART:
        return some(0)
    with ThreadPoolExecutor(os.cpu_count() or 1) as threads:
        return sum(threads.map(some, range(0, len(values), PART)))


def kth_difference(values: np.ndarray, z: int) -> float:
    """The z-th smallest (from 1) absolute difference of two entries, without listing the pairs."""
    v = np.sort(np.asarray(values, float))
    lo, hi = -1.0, float(v[-1] - v[0]) if len(v) else 0.0
    if pairs_up_to(v, 0.0) >= z:
        return 0.0
    for _ in range(200):
        mid = (lo + hi) / 2
        if mid <= lo or mid >= hi:
            break
        if pairs_up_to(v, mid) >= z:
            hi = mid
        else:
            lo = mid
    # hi is an upper end; the difference itself is the largest one not above it
    at = np.searchsorted(v, v + hi * (1 + 1e-12), side="right") - 1
    d = v[at] - v
    return float(d[d <= hi * (1 + 1e-9)].max())


class Pool:
    """Differences of all coordinates together, by rank."""

    def __init__(self, by_attribute: list[np.ndarray]):
        self.values = [np.unique(v) for v in by_attribute]
        self.total = sum(len(v) * (len(v) - 1) // 2 for v in self.values)

    def rank_below(self, x: float) -> int:
        """Number of differences below x."""
        return sum(pairs_up_to(v, x * (1 - 1e-9)) for v in self.values) if x > 0 else 0

    def _between(self, lo: float, hi: float) -> np.ndarray:
        """The differences over lo and up to hi."""
        out = []
        for v in self.values:
            first, last = np.searchsorted(v, v + lo, side="right"), np.searchsorted(v, v + hi, side="right")
            first = np.maximum(first, np.arange(1, len(v) + 1))
            each = last - first
            at = np.repeat(first - np.cumsum(each) + each, each) + np.arange(each.sum())
            out.append(v[at] - np.repeat(v, each))
        return np.concatenate(out)

    def at_rank(self, z: int) -> float:
        if z <= 0 or not self.total:
            return 0.0
        lo, hi = 0.0, max(float(v[-1] - v[0]) for v in self.values if len(v))
        below, above = 0, self.total  # numbers of differences up to both ends: z is over the one and not over the other

        def ask(x: float) -> None:
            nonlocal lo, hi, below, above
            if lo < x < hi:
                n = sum(pairs_up_to(v, x) for v in self.values)
                if n >= z:
                    hi, above = x, n
                else:
                    lo, below = x, n

        while hi - lo > FINE * hi and lo < (lo + hi) / 2 < hi:
            if above - below <= LISTED:  # so few that they are listed
                return min(hi, float(np.partition(self._between(lo, hi), z - below - 1)[z - below - 1]) * (1 + FINE / 100))
            wide = hi - lo
            x = lo + wide * (z - below) / max(1, above - below)  # numbers grow evenly over short ways: both sides of that are asked
            ask(x + wide / 64)
            ask(x - wide / 64)
            if hi - lo > wide / 8:  # or by steps
                ask((lo + hi) / 2)
        return hi


def pool(space, cells: int = 2_000_000) -> Pool | None:
    """Distinct base values by coordinate. Where there are more than `cells`, the values of each coordinate are rounded, on the executors, to the
    ends of `cells` equal steps, so that every difference is off by at most one step: the search's radius grows by at most
    2 * sqrt(d) steps, far below its own slack."""
    frame = space.value_pool()
    if frame.count() > cells:
        box = space.root_box()
        steps = {c: max(float(h - l) / cells * len(space.coords), 1e-300) for c, l, h in zip(space.coords, box.lo, box.hi, strict=True)}
        step = F.element_at(F.create_map(*[x for c, s in steps.items() for x in (F.lit(c), F.lit(s))]), F.col("attr"))
        frame = frame.select("attr", (F.round(F.col("value") / step) * step).alias("value")).distinct()
    rows = frame.toArrow()  # at most about `cells` rows
    attr = rows["attr"].combine_chunks().dictionary_encode() if rows.num_rows else None
    names, code = (attr.dictionary.to_pylist(), attr.indices.to_numpy()) if attr is not None else ([], np.empty(0, int))
    value = rows["value"].to_numpy()
    return Pool([value[code == names.index(c)] if c in names else value[:0] for c in space.coords])
