"""Cyclic queries: bags of a decomposition are joined and written, then they are an acyclic query."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import hypergraph
from .files import written_folder
from .space import COUNT, JoinSpace, key
from .spec import JoinSpec, Relation


def to_acyclic(space: JoinSpace, write: bool = True) -> JoinSpace:
    """Each bag joins the relations that meet it, cut to its attributes; a relation's coordinates and multiplicities go
    to exactly one bag that covers it. A bag has at most N**width rows."""
    if space.tree is not None:
        return space
    edges = space.spec.edges()
    plan = hypergraph.decompose(edges)
    home: dict[str, int] = {}
    for name, e in edges.items():
        home[name] = next(i for i, b in enumerate(plan.bags) if e <= b)
    folder = written_folder(space.spark, "bags")
    relations, frames, owned = [], {}, {}
    for i, bag in enumerate(plan.bags):
        out: DataFrame | None = None
        seen: set[str] = set()
        mine = [n for n in edges if home[n] == i]
        names = mine + [n for n in edges if home[n] != i and edges[n] & bag]
        while names:
            n = next((x for x in names if out is None or edges[x] & bag & seen), names[0])
            names.remove(n)
            keys = sorted(edges[n] & bag)
            f = space.frames[n]
            f = f if n in mine else f.select(*[key(a) for a in keys]).distinct().withColumn("w", F.lit(1).cast(COUNT))
            if out is None:
                out = f
            else:
                on = [key(a) for a in keys if a in seen]
                f = f.withColumnRenamed("w", "w2")
                out = (out.join(f, on) if on else out.crossJoin(f)).withColumn("w", (F.col("w") * F.col("w2")).cast(COUNT)).drop("w2")
            seen |= set(keys)
        name = f"bag{i}"
        if write:
            out.write.parquet(f"{folder}/{name}")
            out = space.spark.read.parquet(f"{folder}/{name}")
        coords = [c for n in mine for c in space.owned[n][0]]
        cats = [c for n in mine for c in space.owned[n][1]]
        relations.append(Relation(name, name, {a: a for a in sorted(bag)}, {c: c for c in coords}, {c: c for c in cats}))
        frames[name], owned[name] = out, (coords, cats)
    spec = JoinSpec(f"{space.spec.name}-bags", tuple(relations))
    return JoinSpace(spec, frames, space.coords, space.cats, hypergraph.join_tree(spec), space.scale, owned)
