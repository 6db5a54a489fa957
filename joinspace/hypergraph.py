"""Query structure on the driver: join trees, fractional edge covers, decompositions and their widths."""

from __future__ import annotations

from dataclasses import dataclass
from fractions import Fraction
from itertools import combinations, permutations

from .spec import JoinSpec


@dataclass
class JoinTree:
    root: str
    parent: dict[str, str | None]
    shared: dict[str, tuple[str, ...]]  # attributes a relation shares with its parent

    def children(self, name: str) -> list[str]:
        return [c for c, p in self.parent.items() if p == name]

    def upward(self) -> list[str]:
        """Leaves first, the root last."""
        out: list[str] = []

        def visit(name: str) -> None:
            for c in self.children(name):
                visit(c)
            out.append(name)

        visit(self.root)
        return out


def join_tree(spec: JoinSpec, root: str | None = None) -> JoinTree | None:
    """Ear removal: a relation whose shared attributes all lie in one other relation hangs below it. None: cyclic."""
    edges = dict(spec.edges())
    root = root or spec.relations[0].name
    left, parent = dict(edges), {}
    while len(left) > 1:
        for name in sorted(left, key=lambda n: (n == root, n)):
            if name == root:
                continue
            others = {o: e for o, e in left.items() if o != name}
            shared = left[name] & frozenset().union(*others.values())
            host = next((o for o in sorted(others, key=lambda o: (o != root, o)) if shared <= others[o]), None)
            if host is not None:
                parent[name] = host
                del left[name]
                break
        else:
            return None
    parent[next(iter(left))] = None
    tree = JoinTree(root, parent, {n: tuple(sorted(edges[n] & edges[p])) if p else () for n, p in parent.items()})
    return tree if connected_attributes(edges, tree) else None


def connected_attributes(edges: dict[str, frozenset[str]], tree: JoinTree) -> bool:
    """The relations that hold an attribute form one connected part of the tree."""
    for a in frozenset().union(*edges.values()) if edges else ():
        holders = [n for n in edges if a in edges[n]]
        tops = [n for n in holders if tree.parent[n] is None or a not in edges[tree.parent[n]]]
        if len(tops) != 1:
            return False
    return True


def edge_cover(edges: dict[str, frozenset[str]], attributes: frozenset[str] | None = None) -> tuple[Fraction, dict[str, Fraction]]:
    """Least total weight on relations so that each attribute has at least 1: exact, over the vertices of the polytope."""
    names = sorted(edges)
    need = sorted(attributes if attributes is not None else frozenset().union(*edges.values()))
    if not need:
        return Fraction(0), {}
    rows = [[Fraction(int(a in edges[n])) for n in names] + [Fraction(1)] for a in need]
    rows += [[Fraction(int(i == j)) for j in range(len(names))] + [Fraction(0)] for i in range(len(names))]
    best: tuple[Fraction, dict[str, Fraction]] | None = None
    for tight in combinations(range(len(rows)), len(names)):
        x = _solve([rows[i] for i in tight])
        if x is None or any(v < 0 for v in x):
            continue
        if all(sum(r[j] * x[j] for j in range(len(names))) >= r[-1] for r in rows[: len(need)]):
            total = sum(x)
            if best is None or total < best[0]:
                best = total, dict(zip(names, x, strict=True))
    if best is None:
        raise ValueError("an attribute is in no relation")
    return best


def _solve(rows: list[list[Fraction]]) -> list[Fraction] | None:
    m, n = [list(r) for r in rows], len(rows)
    for i in range(n):
        pivot = next((j for j in range(i, n) if m[j][i]), None)
        if pivot is None:
            return None
        m[i], m[pivot] = m[pivot], m[i]
        m[i] = [v / m[i][i] for v in m[i]]
        for j in range(n):
            if j != i and m[j][i]:
                f = m[j][i]
                m[j] = [a - f * b for a, b in zip(m[j], m[i], strict=True)]
    return [r[-1] for r in m]


def size_bound(spec: JoinSpec, sizes: dict[str, int], unique: set[str] | None = None) -> float:
    """Upper bound of the join's size from a fractional cover. Relations that are not `unique` on their keys hold
    further attributes of their own, which only they can cover."""
    edges = {n: e if unique is None or n in unique else e | {f"#{n}"} for n, e in spec.edges().items()}
    _, x = edge_cover(edges)
    out = 1.0
    for n, w in x.items():
        out *= float(sizes[n]) ** float(w)
    return out


@dataclass
class Decomposition:
    bags: list[frozenset[str]]
    parent: list[int | None]
    width: Fraction


def decompositions(edges: dict[str, frozenset[str]]):
    """One for each elimination order of the attributes."""
    attributes = sorted(frozenset().union(*edges.values()))
    for order in permutations(attributes):
        near = {a: set().union(*(e for e in edges.values() if a in e)) - {a} for a in attributes}
        bags = []
        for a in order:
            bags.append(frozenset(near[a] | {a}))
            for b in near[a]:
                near[b] |= near[a] - {b}
                near[b].discard(a)
        keep = [b for i, b in enumerate(bags) if not any(b < o or (b == o and j < i) for j, o in enumerate(bags))]
        yield keep


def decompose(edges: dict[str, frozenset[str]]) -> Decomposition:
    """Of least fractional width: each bag's width is the cover number of its attributes."""
    best: Decomposition | None = None
    seen: dict[frozenset[str], Fraction] = {}
    for bags in decompositions(edges):
        for b in bags:
            if b not in seen:
                seen[b] = edge_cover({n: e & b for n, e in edges.items() if e & b}, b)[0]
        width = max(seen[b] for b in bags)
        if best is None or (width, len(bags)) < (best.width, len(best.bags)):
            best = Decomposition(bags, _link(bags), width)
    assert best is not None
    return best


def _link(bags: list[frozenset[str]]) -> list[int | None]:
    """A tree of maximal overlap."""
    parent: list[int | None] = [None] * len(bags)
    inside = {0}
    while len(inside) < len(bags):
        i, j = max(((i, j) for i in range(len(bags)) if i not in inside for j in inside), key=lambda p: (len(bags[p[0]] & bags[p[1]]), -p[0], -p[1]))
        parent[i] = j
        inside.add(i)
    return parent


def fhw(spec: JoinSpec) -> Fraction:
    """Fractional hypertree width; 1 for acyclic queries."""
    return Fraction(1) if join_tree(spec) is not None else decompose(spec.edges()).width
