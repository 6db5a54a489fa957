"""Diverse subsets with a quota for each value of one categorical attribute."""

from __future__ import annotations

import numpy as np

from . import diversity, local


def _groups(space, attribute: str, quotas: dict, k: int, eps: float, **options) -> tuple[list, list]:
    points, groups = [], []
    for g in sorted(quotas):
        if quotas[g]:
            part = space.group(attribute, g).reduced()
            p = diversity.farthest_first(part, k, eps, **options)
            part.release()
            points.append(p)
            groups += [g] * len(p)
    return points, groups


def remote_edge(space, attribute: str, quotas: dict, eps: float = 0.5, **options) -> tuple[np.ndarray, np.ndarray, float]:
    """k points of every group by farthest-first, then a flat solver with quotas: (points, groups, least distance)."""
    k = sum(quotas.values())
    points, groups = _groups(space, attribute, quotas, k, eps, **options)
    p, g = np.concatenate(points), np.array(groups)
    at = local.fair_max_min(p, g, quotas)
    return p[at], g[at], local.diversity(p[at], "edge")


def remote_clique(space, attribute: str, quotas: dict, eps: float = 0.5, **options) -> tuple[np.ndarray, np.ndarray, float]:
    """k_i points of group i and the k_i nearest tuples of each, then swaps: (points, groups, sum of distances)."""
    points, groups = [], []
    for g in sorted(quotas):
        q = quotas[g]
        if not q:
            continue
        part = space.group(attribute, g).reduced()
        own = diversity.farthest_first(part, q, eps, **options)
        near = [x for x, _ in part.nearest(own, q)]
        part.release()
        p = np.concatenate([own, *near])
        if q > 1:  # a tuple may be taken as often as the join has it; copies are only needed if distinct ones are short
            distinct = np.unique(p, axis=0)
            p = distinct if len(distinct) >= q else p
        points.append(p)
        groups += [g] * len(p)
    p, g = np.concatenate(points), np.array(groups)
    at = local.fair_max_sum(p, g, quotas)
    return p[at], g[at], local.diversity(p[at], "clique")
