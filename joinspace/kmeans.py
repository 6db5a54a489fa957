"""k-means and k-median over a join space: iterative sampling on a lazy tree, then a coreset and a flat solver."""

from __future__ import annotations

import math
from collections.abc import Callable
from dataclasses import dataclass

import numpy as np

from . import coreset, kcenter, local
from .kcenter import Solution, _facts
from .tree import SpatialTree, lazy_tree


@dataclass(frozen=True)
class Constants:
    """How many tuples a round draws, how many may be left to stop, and what share of a level makes it heavy (1 / (divide log n))."""

    name: str
    draw: Callable[[int, float], float]
    stop: Callable[[int, float], float]
    divide: float = 10


#: The analysed constants. With log n the binary logarithm of the join size.
LITERAL = Constants("literal", lambda k, log_n: 240 * k * log_n**2, lambda k, log_n: 480 * k * log_n**2)
#: A round needs one draw from each of k balls that hold 1 / (20 k log n) of what is active: so many draws miss one with probability
#: at most `MISS`. Half of the draws' number of tuples may be left for each.
MISS = 0.05
PRACTICAL = Constants("practical", lambda k, log_n: 20 * k * log_n * math.log(k / MISS), lambda k, log_n: 40 * k * log_n * math.log(k / MISS))
#: About 180 times fewer draws. No factor follows from the argument; for joins of billions of tuples on one machine only.
LIGHT = Constants("light", lambda k, log_n: 0.5 * k * log_n, lambda k, log_n: k * log_n**2)


def bracket(space, k: int, eps: float, tree: SpatialTree, power: int) -> tuple[float, float, float]:
    """(L, lower, upper) for the optimum from a refined k-center value L."""
    found = kcenter.refine(space, k, eps, tree)
    value = found.estimate
    low = (value / (2 + eps)) ** power if power == 1 else value**2 / 9
    return value, low, tree.n * value**power


def levels(value: float, n: int, first: float = 0.0) -> list[float]:
    """L / 4n, doubling 2 log n + 3 times, then everything. Radii below `first` are one level with it."""
    count = 2 * math.ceil(math.log2(max(2, n))) + 3
    radii = [value / (4 * n) * 2.0**j for j in range(count + 1)]
    return [r for r, after in zip(radii, [*radii[1:], math.inf], strict=True) if after > first] + [math.inf]


def one_round(tree: SpatialTree, k: int, power: int, radii: list[float], constants: Constants, seed: int, many: bool = True) -> tuple[np.ndarray, float, dict]:
    """Draw, cover by growing radii, keep the levels up to the last heavy one, roll the rest back."""
    log_n = math.log2(max(2, tree.n))
    before = tree.active
    z = max(k, math.ceil(constants.draw(k, log_n)))
    drawn = np.unique(tree.sample(z, seed), axis=0)
    threshold = before / (constants.divide * log_n)
    counts, marks = [], []
    top = tree.root.region.outer.diameter * 2
    for r in radii:
        reach = min(r, top)
        n = tree.deactivate(drawn, reach) if many else sum(tree.deactivate(x, reach) for x in drawn)
        counts.append(n)
        marks.append(tree.snapshot())
        if tree.active <= threshold:  # no later level can be heavy
            break
    heavy = max((j for j, n in enumerate(counts) if n > threshold), default=len(counts) - 1)
    tree.restore(marks[heavy])
    charge = sum(counts[j] * ((1 + tree.eps) * min(radii[j], top)) ** power for j in range(heavy + 1))
    return drawn, charge, {"tau": before, "beta": heavy, "covered": before - tree.active, "counts": counts[: heavy + 1], "radii": radii[: heavy + 1], "drawn": z}


def bicriteria(space, k: int, eps: float = 0.25, power: int = 2, tree: SpatialTree | None = None, constants: Constants = PRACTICAL, seed: int = 42, many: bool = True, **options) -> Solution:
    """More than k centres and an upper bound of their cost."""
    tree = tree or lazy_tree(space, eps=eps, leaf_rows=True, **options)
    d = len(tree.root.region.outer.lo)
    if not tree.n:
        return Solution(np.empty((0, d)), 0.0)
    value, low, high = bracket(space, k, eps, tree, power)
    tree.reset()
    if value == 0:
        return Solution(kcenter.cover(tree, k, 0.0), 0.0, {"rounds": [], **_facts(tree)})
    log_n = math.log2(max(2, tree.n))
    stop = constants.stop(k, log_n)
    # all tuples within `fine` cost at most eps^power times the lower bound together, so smaller radii need no levels of their own
    fine = eps * (low / tree.n) ** (1 / power)
    radii, found, total, rounds = levels(value, tree.n, fine), [], 0.0, []
    while tree.active > stop and len(rounds) < 10 * math.ceil(log_n):
        x, charge, facts = one_round(tree, k, power, radii, constants, seed + len(rounds), many)
        found.append(x)
        total += charge
        rounds.append(facts)
    if tree.active:
        found.append(tree.report()[0])
    tree.reset()
    centres = np.unique(np.concatenate(found), axis=0)
    return Solution(centres, total, {"rounds": rounds, "L": value, "low": low, "high": high, "constants": constants.name, **_facts(tree)})


def solve(space, k: int, eps: float = 0.25, power: int = 2, solver=None, constants: Constants = PRACTICAL, seed: int = 42, tree: SpatialTree | None = None, **options) -> Solution:
    """Bicriteria, coreset around it, flat solver: k centres from the join."""
    tree = tree or lazy_tree(space, eps=eps, leaf_rows=True, **options)
    first = bicriteria(space, k, eps, power, tree, constants, seed)
    if first.estimate == 0 and len(first.centres) <= k:
        return first
    base = eps * (max(first.estimate, first.trace["low"]) / tree.n) ** (1 / power)
    core = coreset.adaptive(tree, first.centres, base, eps)
    centres, value = (solver or local.solver("median" if power == 1 else "means"))(core.points, core.weights, k)
    # a tuple is at most `slack` from its point of the coreset: the triangle inequality makes the flat cost an upper bound of the cost
    value = (value ** (1 / power) + core.slack * tree.n ** (1 / power)) ** power
    return Solution(centres, value, first.trace | {"bicriteria": len(first.centres), "estimate": first.estimate, "coreset": len(core.points), "core": core, **_facts(tree)})
