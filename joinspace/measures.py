"""Costs, ratios and counters."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import local
from .region import Box
from .space import JoinSpace


def squared_distances(coords: list[str], centres: np.ndarray, cats: list[str] | None = None, values: list[tuple] | None = None, mismatch: float = 1.0) -> Column:
    """Array of squared distances to each centre, as one expression; differing categories add `mismatch` each."""
    out = []
    for i, c in enumerate(centres):
        d = F.lit(0.0)
        for name, x in zip(coords, c, strict=True):
            d = d + (F.col(name) - F.lit(float(x))) * (F.col(name) - F.lit(float(x)))
        for j, name in enumerate(cats or ()):
            d = d + F.when(F.col(name).eqNullSafe(F.lit(values[i][j])), 0.0).otherwise(float(mismatch))
        out.append(d)
    return F.array(*out)


def nearest_class(coords: list[str], centres: np.ndarray) -> Column:
    """1-based number of the nearest centre, the first of equals."""
    d = squared_distances(coords, centres)
    return F.array_position(d, F.array_min(d)).cast("int")


def cost_frame(tuples: DataFrame, coords: list[str], centres: np.ndarray) -> DataFrame:
    """(n, center, median, means) of centres over materialised tuples with multiplicity w."""
    d = F.array_min(squared_distances(coords, centres))
    w = F.col("w").cast("double")
    return tuples.agg(F.sum("w").alias("n"), F.sqrt(F.max(d)).alias("center"), F.sum(w * F.sqrt(d)).alias("median"), F.sum(w * d).alias("means"))


def exact_cost(space: JoinSpace, centres: np.ndarray, objective: str) -> float:
    r = cost_frame(space.materialize(), space.coords, centres).first()
    return float(r[objective] or 0.0)


def cost_bracket(tree, centres: np.ndarray, power: int, levels: int = 24) -> tuple[float, float]:
    """Lower and upper bound of the cost without materialising: tuples by rings of growing radius."""
    top = tree.root.region.outer.diameter
    radii = [top * 2.0 ** (i - levels) for i in range(levels + 1)]
    mark = tree.snapshot()
    low = high = 0.0
    before = 0.0
    for r in radii:
        n = tree.deactivate(centres, r)
        low += n * before**power
        high += n * ((1 + tree.eps) * r) ** power
        before = r
        if not tree.active:
            break
    tree.restore(mark)
    return low, high


def ratio(value: float, optimum: float) -> float:
    return 1.0 if value == optimum else value / optimum if optimum else float("inf")


def blow_up(space: JoinSpace) -> tuple[int, int, float]:
    """(join size, base rows, quotient)"""
    n = space.size()
    base = sum(int(f.agg(F.sum("w")).first()[0] or 0) for f in space.frames.values())
    return n, base, n / max(1, base)


def sample_discrepancy(space: JoinSpace, sample: np.ndarray, boxes: list[Box]) -> float:
    """Largest difference between a box's share of the sample and of the join space."""
    counts, n = space.count(boxes).astype(float), space.size()
    shares = np.array([b.contains(sample).mean() for b in boxes])
    return float(np.abs(shares - counts / max(1, n)).max())


def uniformity(observed: np.ndarray, expected: np.ndarray) -> float:
    """Chi-square statistic divided by its degrees of freedom; about 1 for a uniform sample."""
    keep = expected > 0
    return float(((observed[keep] - expected[keep]) ** 2 / expected[keep]).sum() / max(1, keep.sum() - 1))


def coreset_error(points: np.ndarray, weights: np.ndarray, core: np.ndarray, core_weights: np.ndarray, centre_sets: list[np.ndarray], objective: str) -> float:
    """Largest relative cost error over centre sets."""
    worst = 0.0
    for c in centre_sets:
        real = local.cost(points, weights, c, objective)
        seen = local.cost(core, core_weights, c, objective)
        worst = max(worst, abs(seen - real) / real if real else 0.0)
    return worst
