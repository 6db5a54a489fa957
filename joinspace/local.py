"""Flat solvers on weighted points in memory: the last step of every method, and the references of the tests. Where the points are a join's
tuples that do not fit (`products.Products`), the solvers go through them block by block."""

from __future__ import annotations

from itertools import combinations

import numpy as np

from .products import Products
from .region import Box, distance_bounds, norm, pairwise

#: From how many centres and coordinate differences on the nearest centre is searched by blocks, and up to how many pairs a block is compared in full.
FEW, DIRECT, NEAR = 24, 1 << 18, 1 << 14


def assign(points: np.ndarray, centres: np.ndarray, metric: str = "l2", block: int = 1 << 22) -> tuple[np.ndarray, np.ndarray]:
    """(index, distance) of the nearest centre, the first of equals. Where points and centres are many, blocks of points first lose the centres
    that are nearest to none of them. Of a few points among centres that are a join's tuples, the nearest tuple of each."""
    if isinstance(centres, Products):
        return centres.nearest(points, metric)
    idx, dist = np.empty(len(points), int), np.empty(len(points))

    def each(rows: np.ndarray | slice, some: np.ndarray | None) -> None:
        d = pairwise(points[rows], centres if some is None else centres[some], metric)
        at = d.argmin(1)
        idx[rows], dist[rows] = at if some is None else some[at], d.min(1)

    if 0 < len(centres) < FEW:  # a row of distances for each centre: the least of a few is slow to take point by point
        for at in range(0, len(points), 1 << 15):
            d = pairwise(centres, points[at : at + (1 << 15)], metric)
            least, first = d[0], np.zeros(d.shape[1], int)
            for j in range(1, len(d)):
                first[d[j] < least] = j
                least = np.minimum(least, d[j])
            idx[at : at + (1 << 15)], dist[at : at + (1 << 15)] = first, least
        return idx, dist
    if len(points) * len(centres) * points.shape[1] <= DIRECT:
        step = max(1, block // max(1, len(centres) * points.shape[1]))
        for at in range(0, len(points), step):
            each(slice(at, at + step), None)
        return idx, dist
    todo = [(np.arange(len(points)), np.arange(len(centres)))]
    while todo:
        rows, some = todo.pop()
        x = points[rows]
        box = Box(x.min(0), x.max(0))
        near, far = distance_bounds(box, centres[some], metric)
        limit = far.min() * (1 + 1e-9)  # over rounding
        if np.isfinite(limit):
            some = some[near <= limit]
        if len(rows) > 1 and len(some) >= FEW and len(rows) * len(some) > NEAR and np.isfinite(limit) and not (box.lo == box.hi).all():
            axis = int(np.argmax(box.hi - box.lo))
            by, half = np.argpartition(x[:, axis], len(rows) // 2), len(rows) // 2
            todo += [(rows[by[:half]], some), (rows[by[half:]], some)]
            continue
        step = max(1, block // (len(some) * points.shape[1]))
        for at in range(0, len(rows), step):
            each(rows[at : at + step], some)
    return idx, dist


def cost(points: np.ndarray, weights: np.ndarray, centres: np.ndarray, objective: str, metric: str = "l2") -> float:
    if not len(points):
        return 0.0
    if isinstance(points, Products):
        return points.cost(centres, objective, metric)
    d = assign(points, centres, metric)[1]
    if objective == "center":
        return float(d.max())
    return float((weights * (d if objective == "median" else d * d)).sum())


def weight_near(points: np.ndarray, weights: np.ndarray, centres: np.ndarray, reach: float, metric: str = "l2") -> float:
    """The weight of the points within reach of a centre."""
    if isinstance(points, Products):
        return points.weight_near(centres, reach, metric)
    return float(weights[assign(points, centres, metric)[1] <= reach].sum())


def farthest_first(points: np.ndarray, k: int, metric: str = "l2", start: int = 0) -> np.ndarray:
    """Greedy traversal: each next point is farthest from those taken; ties go to the first. Radius at most twice the optimum."""
    if not len(points):
        return points[:0]
    if isinstance(points, Products):
        found = points[[start]]
        while len(found) < min(k, len(points)):
            i, far = points.farthest(found, metric)
            if far == 0:
                break
            found = np.concatenate([found, points[[i]]])
        return found
    chosen = [start]
    d = norm(points - points[start], metric)
    while len(chosen) < min(k, len(points)):
        i = int(d.argmax())
        if d[i] == 0:
            break
        chosen.append(i)
        d = np.minimum(d, norm(points - points[i], metric))
    return points[chosen]


def cover(points: np.ndarray, k: int, r: float, metric: str = "l2") -> np.ndarray | None:
    """At most k points whose balls of 2r hold all; None if greedy needs more, which proves r below the optimum."""
    if isinstance(points, Products):
        found, at = points[:0], 0 if len(points) else None
        while at is not None:
            if len(found) == k:
                return None
            found = np.concatenate([found, points[[at]]])
            at = points.first_beyond(found, 2 * r, metric)
        return found
    live, out = np.ones(len(points), bool), []
    while live.any():
        if len(out) == k:
            return None
        p = points[int(np.flatnonzero(live)[0])]
        out.append(p)
        live &= norm(points - p, metric) > 2 * r
    return np.array(out).reshape(-1, points.shape[1])


def cover_tree(tree, k: int, r: float) -> np.ndarray | None:
    """The same by ball queries on a tree: balls of between 2r and 2(1 + eps)r."""
    out: list[np.ndarray] = []
    mark = tree.snapshot()
    while tree.active:
        if len(out) == k:
            tree.restore(mark)
            return None
        out.append(tree.representative())
        tree.deactivate(out[-1], 2 * r)
    tree.restore(mark)
    return np.array(out)


def cover_search(points: np.ndarray, k: int, metric: str = "l2") -> tuple[np.ndarray, float]:
    """The least pairwise distance at which `cover` succeeds: within twice the optimum."""
    pts = np.unique(points, axis=0)
    radii = np.unique(np.concatenate([[0.0], pairwise(pts, pts, metric).ravel()]))
    lo, hi = 0, len(radii) - 1
    best = cover(pts, k, radii[hi], metric)
    while lo < hi:
        mid = (lo + hi) // 2
        got = cover(pts, k, radii[mid], metric)
        if got is not None:
            best, hi = got, mid
        else:
            lo = mid + 1
    return best if best is not None else farthest_first(pts, k, metric), 2 * float(radii[hi])


def exact(points: np.ndarray, weights: np.ndarray, k: int, objective: str, metric: str = "l2", most: int = 2_000_000) -> tuple[np.ndarray, float]:
    """The optimum over centres from the points, by enumeration."""
    pts, back = np.unique(points, axis=0, return_inverse=True)
    w = np.bincount(back.ravel(), weights, len(pts))
    k = min(k, len(pts))
    import math

    if math.comb(len(pts), k) > most:
        raise ValueError("too many subsets")
    d = pairwise(pts, pts, metric)
    value = d if objective in ("center", "median") else d * d
    best, arg = np.inf, None
    for c in combinations(range(len(pts)), k):
        near = value[list(c)].min(0)
        v = float(near.max()) if objective == "center" else float((w * near).sum())
        if v < best:
            best, arg = v, c
    return pts[list(arg)], best


def seeded(points: np.ndarray, weights: np.ndarray, k: int, power: int, seed: int) -> np.ndarray:
    """k points, each drawn by weight times distance to those before."""
    rng = np.random.default_rng(seed)
    if isinstance(points, Products):
        found = points.draw(1, rng)
        while len(found) < k and (x := points.draw_far(found, power, rng)) is not None:
            found = np.concatenate([found, x[None, :]])
        return found
    first = rng.choice(len(points), p=weights / weights.sum())
    chosen = [first]
    d = norm(points - points[first]) ** power
    while len(chosen) < k:
        p = weights * d
        if p.sum() <= 0:
            break
        i = int(rng.choice(len(points), p=p / p.sum()))
        chosen.append(i)
        d = np.minimum(d, norm(points - points[i]) ** power)
    return points[chosen]


def snap(points: np.ndarray, centres: np.ndarray) -> np.ndarray:
    """Each centre moves to the nearest input point."""
    if isinstance(points, Products):
        return points[points.nearest(centres)[0]]
    return points[pairwise(centres, points).argmin(1)]


def _sums(points: np.ndarray, weights: np.ndarray, centres: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(weight, weighted sum) of the points nearest to each centre."""
    if isinstance(points, Products):
        return points.means(centres)
    idx, _ = assign(points, centres)
    return np.bincount(idx, weights, len(centres)), np.stack([np.bincount(idx, weights * points[:, a], len(centres)) for a in range(points.shape[1])], 1)


def kmeans(points: np.ndarray, weights: np.ndarray, k: int, seed: int = 42, rounds: int = 30, tries: int = 4) -> tuple[np.ndarray, float]:
    best: tuple[np.ndarray, float] | None = None
    for t in range(tries):
        c = seeded(points, weights, k, 2, seed + t)
        for _ in range(rounds):
            w, new = _sums(points, weights, c)
            new = np.where(w[:, None] > 0, new / np.maximum(w, 1e-300)[:, None], c)
            if np.allclose(new, c):
                break
            c = new
        c = snap(points, c)
        v = cost(points, weights, c, "means")
        if best is None or v < best[1]:
            best = c, v
    return swap(points, weights, best[0], "means", seed)


def kmedian(points: np.ndarray, weights: np.ndarray, k: int, seed: int = 42) -> tuple[np.ndarray, float]:
    best = min(((c, cost(points, weights, c, "median")) for c in (seeded(points, weights, k, 1, seed + t) for t in range(4))), key=lambda x: x[1])
    return swap(points, weights, best[0], "median", seed)


def swap(points: np.ndarray, weights: np.ndarray, centres: np.ndarray, objective: str, seed: int = 42, tries: int = 60) -> tuple[np.ndarray, float]:
    """Single-swap local search over random candidates."""
    rng = np.random.default_rng(seed)
    power = 1 if objective == "median" else 2
    if isinstance(points, Products):
        now = points.cost(centres, objective)
        for _ in range(tries if len(points) > 1 else 0):
            new = points.draw(1, rng)[0]
            v = points.swapped(centres, new, power)
            if v.min() < now * (1 - 1e-9):
                centres = centres.copy()
                centres[int(v.argmin())], now = new, float(v.min())
        return centres, now
    d = pairwise(centres, points) ** power
    first, at_first, second = _two_least(d)
    now = float((weights * first).sum())
    for _ in range(tries if len(points) > 1 else 0):
        i = int(rng.choice(len(points), p=weights / weights.sum()))
        new = norm(points - points[i]) ** power
        best, at = now, -1
        for j in range(len(centres)):
            v = float((weights * np.minimum(new, np.where(at_first == j, second, first))).sum())
            if v < best * (1 - 1e-9):
                best, at = v, j
        if at >= 0:
            centres = centres.copy()
            centres[at], now = points[i], best
            d[at] = new
            first, at_first, second = _two_least(d)
    return centres, now


def _two_least(d: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Per column the least value, its row, and the least of the other rows (infinite if there are none)."""
    first, at, second = d[0], np.zeros(d.shape[1], int), np.full(d.shape[1], np.inf)
    for j in range(1, len(d)):
        second = np.minimum(second, np.maximum(first, d[j]))
        at[d[j] < first] = j
        first = np.minimum(first, d[j])
    return first.copy(), at, second


def solver(objective: str):
    def center(p, w, k, seed=42):
        c = farthest_first(p, k)
        return c, cost(p, w, c, "center")

    return {"center": center, "median": kmedian, "means": kmeans}[objective]


def kmeans_1d(values: np.ndarray, weights: np.ndarray, k: int) -> tuple[np.ndarray, float]:
    """Optimal weighted means on a line: dynamic programme over sorted distinct values with prefix sums."""
    v, back = np.unique(np.asarray(values, float), return_inverse=True)
    w = np.bincount(back, np.asarray(weights, float), len(v))
    k, n = min(k, len(v)), len(v)
    s0, s1, s2 = (np.concatenate([[0], np.cumsum(x)]) for x in (w, w * v, w * v * v))

    def spread(i: np.ndarray, j: int) -> np.ndarray:
        m = s0[j] - s0[i]
        return np.maximum(0, s2[j] - s2[i] - (s1[j] - s1[i]) ** 2 / np.where(m > 0, m, 1))

    table = np.full((k + 1, n + 1), np.inf)
    back_at = np.zeros((k + 1, n + 1), int)
    table[0, 0] = 0
    for c in range(1, k + 1):
        for j in range(c, n + 1):
            i = np.arange(c - 1, j)
            x = table[c - 1, i] + spread(i, j)
            best = int(x.argmin())
            table[c, j], back_at[c, j] = x[best], i[best]
    out, j = [], n
    for c in range(k, 0, -1):
        i = back_at[c, j]
        out.append((s1[j] - s1[i]) / max(s0[j] - s0[i], 1e-300))
        j = i
    return np.array(out[::-1]), float(table[k, n])


def bicriteria(points: np.ndarray, weights: np.ndarray, k: int, power: int = 2, seed: int = 42, draws: int | None = None) -> tuple[np.ndarray, float]:
    """Draw, assign every point to its nearest draw, drop the nearer half, repeat."""
    rng = np.random.default_rng(seed)
    draws = draws or 4 * k
    live, out, total = np.arange(len(points)), [], 0.0
    while len(live) > 2 * draws:
        w = weights[live]
        x = points[rng.choice(live, draws, p=w / w.sum())]
        d = assign(points[live], x)[1]
        order = np.argsort(d, kind="stable")
        cut = np.searchsorted(np.cumsum(w[order]), w.sum() / 2) + 1
        total += float((w[order[:cut]] * d[order[:cut]] ** power).sum())
        out.append(x)
        live = live[order[cut:]]
    out.append(points[live])
    return np.unique(np.concatenate(out), axis=0), total


# diversity values

def spanning_tree(points: np.ndarray) -> float:
    d = pairwise(points, points)
    inside, near, total = np.zeros(len(points), bool), np.full(len(points), np.inf), 0.0
    near[0] = 0
    for _ in range(len(points)):
        i = int(np.where(inside, np.inf, near).argmin())
        total += near[i]
        inside[i] = True
        near = np.minimum(near, d[i])
    return float(total)


def tour(points: np.ndarray) -> float:
    """Shortest closed tour: exact up to 12 points, beyond it nearest-neighbour with 2-opt."""
    n, d = len(points), pairwise(points, points)
    if n < 2:
        return 0.0
    if n <= 12:
        best = {(1 << j, j): d[0, j] for j in range(1, n)}
        for size in range(2, n):
            new: dict = {}
            for (s, j), v in best.items():
                if bin(s).count("1") == size - 1:
                    for i in range(1, n):
                        if not s >> i & 1:
                            key, x = (s | 1 << i, i), v + d[j, i]
                            if x < new.get(key, np.inf):
                                new[key] = x
            best |= new
        full = (1 << n) - 2
        return float(min(best[full, j] + d[j, 0] for j in range(1, n)))
    path, left = [0], set(range(1, n))
    while left:
        path.append(min(left, key=lambda j: d[path[-1], j]))
        left.discard(path[-1])
    better = True
    while better:
        better = False
        for i in range(n - 1):
            for j in range(i + 2, n - (i == 0)):
                a, b, c, e = path[i], path[i + 1], path[j], path[(j + 1) % n]
                if d[a, c] + d[b, e] < d[a, b] + d[c, e] - 1e-12:
                    path[i + 1 : j + 1] = path[i + 1 : j + 1][::-1]
                    better = True
    return float(sum(d[path[i], path[(i + 1) % n]] for i in range(n)))


def matching(points: np.ndarray) -> float:
    """Least perfect matching (even number of points): exact by subsets up to 16, beyond it greedy."""
    n, d = len(points), pairwise(points, points)
    if n % 2:
        raise ValueError("an even number of points")
    if n > 16:
        left, total = set(range(n)), 0.0
        while left:
            a, b = min(combinations(sorted(left), 2), key=lambda p: d[p])
            total += d[a, b]
            left -= {a, b}
        return float(total)
    best = {0: 0.0}
    for s in range(1, 1 << n):
        if bin(s).count("1") % 2 == 0:
            i = (s & -s).bit_length() - 1
            best[s] = min(d[i, j] + best[s ^ 1 << i ^ 1 << j] for j in range(i + 1, n) if s >> j & 1)
    return float(best[(1 << n) - 1])


def diversity(points: np.ndarray, kind: str) -> float:
    if len(points) < 2:
        return 0.0
    d = pairwise(points, points)
    np.fill_diagonal(d, np.inf)
    if kind == "edge":
        return float(d.min())
    if kind == "pseudoforest":
        return float(d.min(1).sum())
    if kind == "clique":
        np.fill_diagonal(d, 0)
        return float(d.sum() / 2)
    return {"tree": spanning_tree, "cycle": tour, "matching": matching}[kind](points)


# with quotas per group

def fair_max_min(points: np.ndarray, groups: np.ndarray, quotas: dict, most: int = 400_000) -> np.ndarray:
    """Indices that meet the quotas and keep apart as far as possible: for falling thresholds, an assignment by search."""
    d = pairwise(points, points)
    names = [g for g, q in quotas.items() if q]

    def attempt(r: float) -> list[int] | None:
        steps = 0

        def place(chosen: list[int], need: dict) -> list[int] | None:
            nonlocal steps
            steps += 1
            todo = [g for g in names if need[g]]
            if not todo:
                return chosen
            if steps > most // 200:
                return None
            options = {g: [i for i in np.flatnonzero(groups == g) if not chosen or (d[i, chosen] >= r).all() and i not in chosen] for g in todo}
            g = min(todo, key=lambda g: len(options[g]) - need[g])
            if len(options[g]) < need[g]:
                return None
            for i in options[g]:
                got = place([*chosen, int(i)], need | {g: need[g] - 1})
                if got:
                    return got
            return None

        return place([], dict(quotas))

    radii = np.unique(np.concatenate([[0.0], d[np.triu_indices(len(points), 1)]]))
    lo, hi, best = 0, len(radii) - 1, attempt(0.0)
    while lo <= hi:
        mid = (lo + hi) // 2
        got = attempt(float(radii[mid]))
        if got:
            best, lo = got, mid + 1
        else:
            hi = mid - 1
    if best is None:
        raise ValueError("quotas cannot be met")
    return np.array(best)


def fair_max_sum(points: np.ndarray, groups: np.ndarray, quotas: dict) -> np.ndarray:
    """Swaps inside a group while the sum of distances grows."""
    d = pairwise(points, points)
    chosen: list[int] = []
    for g, q in quotas.items():
        mine = np.flatnonzero(groups == g)
        if len(mine) < q:
            raise ValueError("quotas cannot be met")
        chosen += list(mine[np.argsort(-d[mine].sum(1), kind="stable")[:q]])
    better = True
    while better:
        better = False
        for at, i in enumerate(chosen):
            rest = [c for c in chosen if c != i]
            options = [j for j in np.flatnonzero(groups == groups[i]) if j not in chosen]
            if options:
                gain = d[np.ix_(options, rest)].sum(1) - d[i, rest].sum()
                if gain.max() > 1e-9:
                    chosen[at] = int(options[int(gain.argmax())])
                    better = True
    return np.array(chosen)
