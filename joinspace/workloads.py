"""The experiment workloads as queries: every method, baseline and measure on the given tables, with SQL for DuckDB.

Exact queries have SQL that computes the same rows from the materialised join. Verdict queries return facts (join size, number
of centres, whether centres are join tuples and bounds hold) whose expected values SQL takes from the data.
"""

from __future__ import annotations

import math
from collections.abc import Callable

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import baselines, coreset, cyclic, diversity, fairness, hypergraph, kcenter, kmeans, local, measures, mixed, radius
from .region import Box, Region
from .space import JoinSpace
from .spec import WORKLOADS, JoinSpec
from .tree import ClassTree, SpaceBackend, SpatialTree, flat_tree, lazy_tree

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
SQL: dict[str, str] = {}
K = 5


def add(name: str, sql: str | None, f: Callable) -> None:
    QUERIES[name] = f
    if sql:
        SQL[name] = sql


def join_sql(spec: JoinSpec) -> str:
    """SELECT of keys, coordinates and categories of the plain join."""
    out, seen = "", set()
    left = list(spec.relations)
    while left:
        r = next((x for x in left if not out or set(x.keys) & seen), left[0])
        left.remove(r)
        cols = [f"{e} AS k_{k}" for k, e in r.keys.items()] + [f"CAST({e} AS DOUBLE) AS {c}" for c, e in r.coords.items()] + [f"{e} AS {c}" for c, e in r.cats.items()]
        one = f"(SELECT {', '.join(cols)} FROM {r.table}) AS {r.name}_"
        both = [f"k_{k}" for k in r.keys if k in seen]
        out += one if not out else f" JOIN {one} USING ({', '.join(both)})" if both else f" CROSS JOIN {one}"
        seen |= set(r.keys)
    return f"(SELECT * FROM {out})"


def bind(spark: SparkSession, sf: str, name: str, cats: list[str] | None = None, scaled: bool = False) -> JoinSpace:
    space = JoinSpace.bind(spark, sf, WORKLOADS[name], cats=cats, grouped=not scaled)
    if scaled:
        box = space.root_box()
        scale = {c: float(s) if s > 1e-9 else 1.0 for c, s in zip(space.coords, box.hi - box.lo, strict=True)}
        space = JoinSpace.bind(spark, sf, WORKLOADS[name], cats=cats, scale=scale)
    return (space if space.tree is not None else cyclic.to_acyclic(space)).cached()


def one(spark: SparkSession, **facts) -> DataFrame:
    def cell(v):
        return v.item() if isinstance(v, np.generic) else v

    kinds = {bool: "boolean", int: "long", float: "double", str: "string"}
    row = {k: cell(v) for k, v in facts.items()}
    return spark.createDataFrame([tuple(row.values())], ", ".join(f"{k} {kinds[type(v)]}" for k, v in row.items()))


# sizes, counts, representatives, reports

for _w, _spec in WORKLOADS.items():
    add(f"size_{_w}", f"SELECT count(*) AS n FROM {join_sql(_spec)}", lambda spark, sf, w=_w: one(spark, n=bind(spark, sf, w).size()))

#: Test boxes by workload, (lo, hi) per coordinate.
BOXES: dict[str, list[list[tuple[float, float]]]] = {
    "w2": [[(0, 50_000), (0, 50_000)], [(10_000, 20_000), (30_000, 90_000)], [(-5, -1), (0, 1)]],
    "w3": [[(10, 30), (0, 5000), (0, 5000), (100_000, 300_000)], [(1, 2), (-1000, 10_000), (-1000, 10_000), (0, 500_000)], [(60, 70), (0, 1), (0, 1), (0, 1)]],
    "w5": [[(0, 20), (0, 20)], [(50, 100), (10, 500)]],
    "w6": [[(0, 5000), (0, 50), (100_000, 400_000), (10, 40)], [(-1000, 0), (0, 500), (0, 500_000), (0, 51)]],
    "w9": [[(-1000, 10_000), (-1000, 10_000)], [(0, 5000), (0, 5000)], [(2000, 3000), (-500, 9000)], [(20_000, 30_000), (0, 1)]],
    "w11": [[(10, 30), (0.02, 0.07), (0, 0.05)], [(1, 51), (0.05, 0.0500001), (0, 1)], [(25, 26), (0, 1), (0, 1)]],
    "w12": [[(0, 25), (0, 5)], [(5, 12), (1, 3)]],
}


def boxes_of(name: str) -> list[Box]:
    return [Box(np.array([a for a, _ in b], float), np.array([z for _, z in b], float)) for b in BOXES[name]]


def in_box(spec: JoinSpec, box: list[tuple[float, float]]) -> str:
    return " AND ".join(f"{c} >= {float(a)!r} AND {c} < {float(z)!r}" for c, (a, z) in zip(spec.coords, box, strict=True))


def _count(spark, sf, w):
    counts = bind(spark, sf, w).count(boxes_of(w))
    return spark.createDataFrame([(i, int(n)) for i, n in enumerate(counts)], "box_id int, n long")


def _rep(spark, sf, w):
    space = bind(spark, sf, w)
    _, reps = space.count_and_represent(boxes_of(w))
    rows = [(i, *[float(v) for v in r]) for i, r in enumerate(reps) if r is not None]
    return spark.createDataFrame(rows, "box_id int, " + ", ".join(f"{c} double" for c in space.coords))


def _rep_sql(w: str) -> str:
    spec = WORKLOADS[w]
    tree = hypergraph.join_tree(spec)
    owned = {r.name: list(r.coords) for r in spec.relations}
    names: list[str] = []

    def visit(n: str) -> None:
        names.extend(owned[n])
        for c in tree.children(n):
            visit(c)

    visit(tree.root)
    parts = [f"SELECT {i} AS box_id, min([{', '.join(names)}]) AS m FROM {join_sql(spec)} WHERE {in_box(spec, b)} HAVING count(*) > 0" for i, b in enumerate(BOXES[w])]
    return f"SELECT box_id, {', '.join(f'm[{names.index(c) + 1}] AS {c}' for c in spec.coords)} FROM ({' UNION ALL '.join(parts)})"


for _w in BOXES:
    _spec = WORKLOADS[_w]
    add(f"count_box_{_w}", " UNION ALL ".join(f"SELECT {i} AS box_id, count(*) AS n FROM {join_sql(_spec)} WHERE {in_box(_spec, b)}" for i, b in enumerate(BOXES[_w])), lambda spark, sf, w=_w: _count(spark, sf, w))
    if _w != "w3":
        add(f"rep_box_{_w}", _rep_sql(_w), lambda spark, sf, w=_w: _rep(spark, sf, w))

#: A box and its hole.
HOLES = {"w9": ([(0, 8000), (0, 8000)], [(1000, 3000), (0, 4000)]), "w11": ([(5, 45), (0.01, 0.1), (0, 0.08)], [(20, 25), (0.03, 0.06), (0.02, 0.05)]), "w2": ([(0, 90_000), (0, 90_000)], [(20_000, 40_000), (20_000, 40_000)])}


#: Two for each coordinate, less one for each face that box and hole share.
SLABS = {"w9": 3, "w11": 6, "w2": 4}


def _region(w: str) -> Region:
    outer, hole = ([np.array(v, float) for v in zip(*b, strict=True)] for b in HOLES[w])
    return Region(Box(*outer), Box(*hole))


def _count_hole(spark, sf, w):
    space, r = bind(spark, sf, w), _region(w)
    return one(spark, n=int(space.count_regions([r])[0]), by_slabs=int(sum(space.count(r.slabs()))), slabs=len(r.slabs()))


for _w in HOLES:
    _spec = WORKLOADS[_w]
    _test = f"{in_box(_spec, HOLES[_w][0])} AND NOT ({in_box(_spec, HOLES[_w][1])})"
    add(f"count_hole_{_w}", f"SELECT count(*) AS n, count(*) AS by_slabs, {SLABS[_w]} AS slabs FROM {join_sql(_spec)} WHERE {_test}", lambda spark, sf, w=_w: _count_hole(spark, sf, w))


def _report(spark, sf, w, i):
    return bind(spark, sf, w).report([boxes_of(w)[i]]).drop("box_id").withColumn("w", F.col("w").cast("long"))


for _w, _i in (("w9", 2), ("w12", 1), ("w2", 1), ("w6", 1)):
    _spec = WORKLOADS[_w]
    add(f"report_box_{_w}", f"SELECT {', '.join(_spec.coords)}, count(*) AS w FROM {join_sql(_spec)} WHERE {in_box(_spec, BOXES[_w][_i])} GROUP BY ALL", lambda spark, sf, w=_w, i=_i: _report(spark, sf, w, i))

for _w, _names in (("w7", ["returnflag", "priority", "segment", "quantity"]), ("w6", ["event_type", "nation", "returnflag"]), ("w10", ["lang", "source", "quality", "toxic"]), ("w9", ["region"]), ("w12", ["r_name"])):
    _spec = WORKLOADS[_w]
    _cast = lambda n, s=_spec: f"CAST(CAST({n} AS DECIMAL(18,1)) AS VARCHAR)" if n in s.coords else f"CAST({n} AS VARCHAR)"
    add(
        f"value_weights_{_w}",
        " UNION ALL ".join(f"SELECT '{n}' AS attr, {_cast(n)} AS value, count(*) AS w FROM {join_sql(_spec)} GROUP BY 2" for n in _names),
        lambda spark, sf, w=_w, names=_names: bind(spark, sf, w, cats=WORKLOADS[w].cats).value_weights(names).withColumn("w", F.col("w").cast("long")),
    )

for _w in ("w3", "w6", "w9", "w11", "w2"):
    _spec = WORKLOADS[_w]
    add(
        f"moments_{_w}",
        " UNION ALL ".join(f"SELECT '{c}' AS attr, CAST(count(*) AS DOUBLE) AS n, round(avg({c}), 3) AS mean, round(stddev_pop({c}), 3) AS spread, min({c}) AS least, max({c}) AS greatest FROM {join_sql(_spec)}" for c in _spec.coords),
        lambda spark, sf, w=_w: bind(spark, sf, w).moments().select("attr", "n", F.round("mean", 3).alias("mean"), F.round(F.sqrt("variance"), 3).alias("spread"), "least", "greatest"),
    )
    add(
        f"root_box_{_w}",
        " UNION ALL ".join(f"SELECT '{c}' AS attr, min(x) AS lo, max(x) AS hi FROM (SELECT CAST({_spec.owner(c).coords[c]} AS DOUBLE) AS x FROM {_spec.owner(c).table})" for c in _spec.coords),
        lambda spark, sf, w=_w: (lambda s, b: spark.createDataFrame([(c, float(lo), float(np.nextafter(hi, -np.inf))) for c, lo, hi in zip(s.coords, b.lo, b.hi, strict=True)], "attr string, lo double, hi double"))(*(lambda s: (s, s.root_box()))(bind(spark, sf, w))),
    )


def _classes(spark, sf):
    space = bind(spark, sf, "w7", cats=WORKLOADS["w7"].cats)
    classes = {"lineitem": {"cq": measures.nearest_class(["quantity"], np.array([[10.0], [40.0]])), "cr": mixed._class("returnflag", ["N", "R"])}, "orders": {"cp": measures.nearest_class(["totalprice"], np.array([[100_000.0], [300_000.0], [450_000.0]]))}}
    return space.count_classes(None, classes).select("cq", "cr", "cp", F.col("cnt").cast("long").alias("n"))


add("class_counts_w7", f"SELECT CASE WHEN abs(quantity - 10) <= abs(quantity - 40) THEN 1 ELSE 2 END AS cq, CASE WHEN returnflag = 'R' THEN 2 ELSE 1 END AS cr, CASE WHEN totalprice <= 200000 THEN 1 WHEN totalprice <= 375000 THEN 2 ELSE 3 END AS cp, count(*) AS n FROM {join_sql(WORKLOADS['w7'])} GROUP BY ALL", _classes)

#: Query points for nearest tuples.
POINTS = {"w9": [(1000, 1000), (9000, 0)], "w6": [(0, 50, 250_000, 25)], "w12": [(7, 3)]}


def _nearest(spark, sf, w):
    got = bind(spark, sf, w).nearest(np.array(POINTS[w], float), 3)
    return spark.createDataFrame([(q, i + 1, round(float(d), 4)) for q, (_, ds) in enumerate(got) for i, d in enumerate(ds)], "q int, rank int, d double")


for _w in POINTS:
    _spec = WORKLOADS[_w]
    _parts = [f"SELECT {q} AS q, rank, round(d, 4) AS d FROM (SELECT d, row_number() OVER (ORDER BY d) AS rank FROM (SELECT sqrt({' + '.join(f'({c} - {float(v)!r}) * ({c} - {float(v)!r})' for c, v in zip(_spec.coords, p, strict=True))}) AS d FROM {join_sql(_spec)})) WHERE rank <= 3" for q, p in enumerate(POINTS[_w])]
    add(f"nearest_{_w}", " UNION ALL ".join(_parts), lambda spark, sf, w=_w: _nearest(spark, sf, w))


def _kth(spark, sf, c):
    space = bind(spark, sf, "w11")
    v = np.array([r["value"] for r in space.value_pool().where(F.col("attr") == c).collect()])
    n = len(v) * (len(v) - 1) // 2
    return spark.createDataFrame([(z, round(radius.kth_difference(v, z), 6)) for z in (1, n // 2, n)], "z int, d double")


for _c, _e in (("quantity", "l_quantity"), ("discount", "l_discount")):
    _v = f"(SELECT DISTINCT {_e} AS x FROM lineitem)"
    add(f"kth_difference_{_c}", f"WITH d AS (SELECT round(b.x - a.x, 9) AS d, row_number() OVER (ORDER BY b.x - a.x) AS z, count(*) OVER () AS n FROM {_v} a JOIN {_v} b ON a.x < b.x) SELECT CAST(z AS INT) AS z, round(d, 6) AS d FROM d WHERE z IN (1, n // 2, n)", lambda spark, sf, c=_c: _kth(spark, sf, c))


def _heavy(spark, sf, w, a):
    space = bind(spark, sf, w, cats=WORKLOADS[w].cats)
    w_ = {r["value"]: int(r["w"]) for r in space.value_weights([a]).collect()}
    return spark.createDataFrame([(v, w_[v]) for v in mixed.categorical_centers(w_, 2)[0]], "value string, w long")


for _w, _a in (("w7", "segment"), ("w6", "nation"), ("w10", "lang")):
    add(f"categorical_centers_{_w}", f"SELECT value, w FROM (SELECT CAST({_a} AS VARCHAR) AS value, count(*) AS w FROM {join_sql(WORKLOADS[_w])} GROUP BY 1) ORDER BY w DESC, value LIMIT 2", lambda spark, sf, w=_w, a=_a: _heavy(spark, sf, w, a))


def _line(spark, sf, k):
    rows = bind(spark, sf, "w11").value_weights(["quantity"]).toPandas()
    _, v = local.kmeans_1d(rows["value"].to_numpy(float), rows["w"].to_numpy(float), k)
    return one(spark, cost=round(v, 2))


_q = "(SELECT l_quantity AS x, CAST(count(*) AS DOUBLE) AS w FROM lineitem GROUP BY 1)"
_p = f"(SELECT x, sum(w) OVER (ORDER BY x) AS a, sum(w * x) OVER (ORDER BY x) AS b, sum(w * x * x) OVER (ORDER BY x) AS c FROM {_q})"
_all = f"(SELECT sum(w) AS a, sum(w * x) AS b, sum(w * x * x) AS c FROM {_q})"
add("kmeans1d_k2", f"SELECT round(min(p.c - p.b * p.b / p.a + CASE WHEN t.a > p.a THEN (t.c - p.c) - (t.b - p.b) * (t.b - p.b) / (t.a - p.a) ELSE 0 END), 2) AS cost FROM {_p} p, {_all} t", lambda spark, sf: _line(spark, sf, 2))
add("kmeans1d_k3", f"SELECT round(min(p.c - p.b * p.b / p.a + (q.c - p.c) - (q.b - p.b) * (q.b - p.b) / (q.a - p.a) + CASE WHEN t.a > q.a THEN (t.c - q.c) - (t.b - q.b) * (t.b - q.b) / (t.a - q.a) ELSE 0 END), 2) AS cost FROM {_p} p JOIN {_p} q ON p.x < q.x, {_all} t", lambda spark, sf: _line(spark, sf, 3))


def _cells(spark, sf, w):
    _, weights = baselines.grid_coreset(bind(spark, sf, w), 3)
    return one(spark, n=int(weights.sum()), small=len(weights) <= 3 ** len(WORKLOADS[w].coords))


for _w in ("w9", "w1", "w3"):
    add(f"grid_coreset_{_w}", f"SELECT count(*) AS n, TRUE AS small FROM {join_sql(WORKLOADS[_w])}", lambda spark, sf, w=_w: _cells(spark, sf, w))


def _ff_flat(spark, sf):
    p, _ = baselines.materialized(bind(spark, sf, "w12"))
    p = p[np.lexsort(p.T[::-1])]
    got = local.farthest_first(p, 3)
    return spark.createDataFrame([(i + 1, float(a), float(b)) for i, (a, b) in enumerate(got)], "step int, nk double, rk double")


_j = join_sql(WORKLOADS["w12"])
add(
    "farthest_first_flat_w12",
    f"""WITH p AS (SELECT DISTINCT nk, rk FROM {_j}), a AS (SELECT nk, rk FROM p ORDER BY nk, rk LIMIT 1),
 b AS (SELECT p.nk, p.rk FROM p, a ORDER BY (p.nk - a.nk) ** 2 + (p.rk - a.rk) ** 2 DESC, p.nk, p.rk LIMIT 1),
 c AS (SELECT p.nk, p.rk FROM p, a, b ORDER BY least((p.nk - a.nk) ** 2 + (p.rk - a.rk) ** 2, (p.nk - b.nk) ** 2 + (p.rk - b.rk) ** 2) DESC, p.nk, p.rk LIMIT 1)
 SELECT 1 AS step, nk, rk FROM a UNION ALL SELECT 2, nk, rk FROM b UNION ALL SELECT 3, nk, rk FROM c""",
    _ff_flat,
)


def _reduce(spark, sf):
    rows = bind(spark, sf, "w8").reduce()
    return one(spark, customers=int(rows["customer"].agg(F.sum("w")).first()[0]), orders=int(rows["orders"].agg(F.sum("w")).first()[0]))


add("reduce_w8", "SELECT (SELECT count(*) FROM customer SEMI JOIN orders ON c_custkey = o_custkey) AS customers, (SELECT count(*) FROM orders SEMI JOIN customer ON c_custkey = o_custkey) AS orders", _reduce)


def _project(spark, sf):
    space = bind(spark, sf, "w9").project(["c_acctbal"])
    return one(spark, n=space.size(), coords=len(space.coords))


add("project_bag_w9", f"SELECT count(*) AS n, 1 AS coords FROM {join_sql(WORKLOADS['w9'])}", _project)


def _grouped(spark, sf):
    space = bind(spark, sf, "w8", cats=["segment"])
    rows = [(g, space.group("segment", g).size()) for g in sorted(mixed.category_weights(space)["segment"])]
    return spark.createDataFrame(rows, "segment string, n long")


add("group_space_w8", f"SELECT segment, count(*) AS n FROM {join_sql(WORKLOADS['w8'])} GROUP BY 1", _grouped)


def _widths(spark, sf):
    """Facts of each query's structure, and the base rows it is over, counted on the tables."""
    from .space import load

    base = None
    for t in sorted({r.table for s in WORKLOADS.values() for r in s.relations}):
        one_ = load(spark, sf, t).agg(F.count("*").alias("n")).select(F.lit(t).alias("t"), "n")
        base = one_ if base is None else base.unionByName(one_)
    sizes = {r["t"]: r["n"] for r in base.collect()}  # a row a table
    rows = []
    for n, s in WORKLOADS.items():
        cover = hypergraph.edge_cover(s.edges())[0] if any(r.keys for r in s.relations) else 0
        rows.append((n, hypergraph.join_tree(s) is not None, float(cover), float(hypergraph.fhw(s)), sum(sizes[r.table] for r in s.relations)))
    return spark.createDataFrame(rows, "workload string, acyclic boolean, cover double, fhw double, base long")


_FACTS = {"w4": (False, 2, 2), "w4t": (False, 1.5, 1.5), "w1": (True, 2, 1), "w2": (True, 1, 1), "w3": (True, 2, 1), "w5": (True, 1, 1), "w6": (True, 2, 1), "w7": (True, 1, 1), "w8": (True, 1, 1), "w9": (True, 1, 1), "w10": (True, 1, 1), "w11": (True, 0, 1), "w12": (True, 1, 1)}  # worked out by hand
add("query_structure", " UNION ALL ".join(f"SELECT '{n}' AS workload, {a} AS acyclic, CAST({c} AS DOUBLE) AS cover, CAST({w} AS DOUBLE) AS fhw, {' + '.join(f'(SELECT count(*) FROM {r.table})' for r in WORKLOADS[n].relations)} AS base" for n, (a, c, w) in _FACTS.items()), _widths)


def _bound(spark, sf, w):
    spec = WORKLOADS[w]
    space = bind(spark, sf, w)
    from .space import load

    tables = {r.name: load(spark, sf, r.table).select(*[F.expr(e).alias(k) for k, e in r.keys.items()]) for r in spec.relations}
    sizes = {n: x.count() for n, x in tables.items()}
    unique = {n for n, x in tables.items() if x.distinct().count() == sizes[n]}
    n = space.size()
    return one(spark, n=n, base=int(sum(sizes.values())), bounded=n <= hypergraph.size_bound(spec, sizes, unique) * (1 + 1e-9))


for _w in ("w3", "w9", "w4", "w4t", "w6"):
    _spec = WORKLOADS[_w]
    add(f"size_bound_{_w}", f"SELECT count(*) AS n, {' + '.join(f'(SELECT count(*) FROM {r.table})' for r in _spec.relations)} AS base, TRUE AS bounded FROM {join_sql(_spec)}", lambda spark, sf, w=_w: _bound(spark, sf, w))

# samples


def _sample(spark, sf, w, z=2000):
    space = bind(spark, sf, w)
    got = space.sample([space.root_box()], [z])[0]
    some = np.unique(got, axis=0)[:40]
    inside = space.count([Box.at(x) for x in some])
    boxes = [h for b in space.root_box().halves()[:2] for h in b.halves()[:2]]
    return one(spark, n=space.size(), drawn=len(got), strange=int((inside == 0).sum()), even=measures.sample_discrepancy(space, got, boxes) < 0.06)


def _sample_hole(spark, sf, w, z=1000):
    space, r = bind(spark, sf, w), _region(w)
    got = space.sample_regions([r], [z])[0]
    return one(spark, n=int(space.count_regions([r])[0]), drawn=len(got), strange=int((~r.contains(got)).sum()))


for _w in ("w9", "w3", "w11"):
    add(f"sample_{_w}", f"SELECT count(*) AS n, 2000 AS drawn, 0 AS strange, TRUE AS even FROM {join_sql(WORKLOADS[_w])}", lambda spark, sf, w=_w: _sample(spark, sf, w))
add("sample_hole_w9", f"SELECT count(*) AS n, 1000 AS drawn, 0 AS strange FROM {join_sql(WORKLOADS['w9'])} WHERE {in_box(WORKLOADS['w9'], HOLES['w9'][0])} AND NOT ({in_box(WORKLOADS['w9'], HOLES['w9'][1])})", lambda spark, sf: _sample_hole(spark, sf, "w9"))

# trees


def _tree(spark, sf, w, shape="shrink", cap=1500):
    space = bind(spark, sf, w, scaled=True)
    tree = SpatialTree(SpaceBackend(space), eps=0.5, leaf_cap=cap, shape=shape, draws=600)
    tree.count(tree.root.rep, 0.25)
    total = sum(x.active for x in tree.frontier())
    return one(spark, n=tree.n, frontier=int(total))


for _w, _cap in (("w9", 1500), ("w2", 100_000), ("w11", 15_000)):
    for _shape in ("shrink", "halve", "quad", "median") if _w == "w9" else ("shrink",):
        add(f"tree_frontier_{_w}_{_shape}", f"SELECT count(*) AS n, count(*) AS frontier FROM {join_sql(WORKLOADS[_w])}", lambda spark, sf, w=_w, s=_shape, c=_cap: _tree(spark, sf, w, s, c))


def _sandwich(spark, sf, w, cap=1500, r=0.2):
    space = bind(spark, sf, w, scaled=True)
    tree = lazy_tree(space, eps=0.5, leaf_cap=cap, draws=600)
    c = tree.root.rep
    p, wt = baselines.materialized(space)
    low, high = local.weight_near(p, wt, c[None, :], r), local.weight_near(p, wt, c[None, :], r * 1.5 * (1 + 1e-9))
    seen = tree.count(c, r)
    gone = tree.deactivate(c, r)
    left = tree.active
    reported = tree.reported()
    tree.reset()
    return one(spark, n=tree.n, sandwich=bool(low <= seen <= high), same=seen == gone, rest=left + gone, reported=reported == left, reset=tree.active == tree.n)


for _w, _cap in (("w9", 1500), ("w11", 15_000)):
    add(f"ball_sandwich_{_w}", f"SELECT count(*) AS n, TRUE AS sandwich, TRUE AS same, count(*) AS rest, TRUE AS reported, TRUE AS reset FROM {join_sql(WORKLOADS[_w])}", lambda spark, sf, w=_w, c=_cap: _sandwich(spark, sf, w, c))

# clustering

_POINTS: dict[tuple, tuple[np.ndarray, np.ndarray]] = {}


def points_of(space: JoinSpace, sf: str, w: str) -> tuple[np.ndarray, np.ndarray]:
    key = (space.spark.sparkContext.applicationId, sf, w)
    if key not in _POINTS:
        _POINTS[key] = baselines.materialized(space)
    return _POINTS[key]


#: Leaf sizes that make a tree open on the small workloads; elsewhere the default.
CAPS = {"w9": 500, "w8": 500, "w10": 40, "w12": 3, "w4": 200, "w4t": 200, "w7": 4000}


def verdict(spark, sf, w, objective: str, solve: Callable, factor: float | None, snapped: bool = True) -> DataFrame:
    """What the method says of the join, next to what SQL counts on it: n is the method's own size of it; covered, the tuples that the centres serve
    within the method's bound (center: within `estimate`; others: all, if the cost is within the bound); strange, centres that are no join tuples.
    near_reference: the cost is within factor * that of the flat solver on the materialised join."""
    space = bind(spark, sf, w, scaled=True)
    found = solve(space, {"leaf_cap": CAPS[w]} if w in CAPS else {})
    p, wt = points_of(space, sf, w)
    value = local.cost(p, wt, found.centres, objective)
    strange = int((local.assign(found.centres, p)[1] >= 1e-9).sum()) if snapped else 0
    bounded = math.isnan(found.estimate) or (value <= found.estimate * (1 + 1e-9) if objective != "center" else True)
    covered = local.weight_near(p, wt, found.centres, found.estimate * (1 + 1e-9)) if objective == "center" and not math.isnan(found.estimate) else wt.sum() * bounded
    facts = {"n": int(found.trace.get("n", 0)) or space.size(), "covered": int(round(covered)), "strange": strange, "k_ok": 0 < len(found.centres) <= K}
    space.release()
    if factor is None:
        return one(spark, **facts)
    reference = local.cost(p, wt, local.solver(objective)(p, wt, K)[0], objective)
    return one(spark, **facts, near_reference=bool(value <= factor * reference))


#: The methods alone, for timing: without the checks on the materialised join.
TIMED: dict[str, Callable[[SparkSession, str], DataFrame]] = {}


def timed(spark, sf, w, solve: Callable) -> DataFrame:
    space = bind(spark, sf, w, scaled=True)
    found = solve(space, {})
    space.release()
    return one(spark, centres=len(found.centres), estimate=float(found.estimate))


def unbounded(found):
    """For methods whose own value is no bound of the cost over the join."""
    return type(found)(found.centres, float("nan"), found.trace)


_METHODS: dict[str, tuple[str, Callable, float | None, bool]] = {
    "kcenter_{w}_first": ("center", lambda s, o: kcenter.search(s, K, 0.5, **o), None, True),
    "kcenter_{w}_ladder": ("center", lambda s, o: kcenter.refine(s, K, 0.5, **o), 2.5, True),
    "kcenter_{w}_coreset": ("center", lambda s, o: kcenter.coreset_solve(s, K, 0.5, **o), 3.0, True),
    "kcenter_{w}_hierarchical": ("center", lambda s, o: baselines.hierarchical(s, K, "center"), 6.0, False),
    "kcenter_{w}_complement": ("center", lambda s, o: baselines.complement_search(s, K), None, True),
    "kcenter_{w}_materialize": ("center", lambda s, o: baselines.materialize_then(s, K, "center"), 1.01, True),
    "kmedian_{w}": ("median", lambda s, o: kmeans.solve(s, K, 0.5, 1, **o), 1.5, True),
    "kmedian_{w}_hierarchical": ("median", lambda s, o: baselines.hierarchical(s, K, "median"), 3.0, False),
    "kmedian_{w}_materialize": ("median", lambda s, o: baselines.materialize_then(s, K, "median"), 1.01, True),
    "kmeans_{w}": ("means", lambda s, o: kmeans.solve(s, K, 0.5, 2, **o), 1.6, True),
    "kmeans_{w}_grid_relation": ("means", lambda s, o: unbounded(baselines.grid(s, K, "means", "relation")), 4.0, False),
    "kmeans_{w}_grid_attribute": ("means", lambda s, o: unbounded(baselines.grid(s, K, "means", "attribute")), 4.0, False),
    "kmeans_{w}_seeding": ("means", lambda s, o: unbounded(baselines.distance_seeding(s, K)), 3.0, True),
    "kmeans_{w}_hierarchical": ("means", lambda s, o: baselines.hierarchical(s, K, "means"), 3.0, False),
    "kmeans_{w}_sample": ("means", lambda s, o: unbounded(baselines.uniform_sample(s, K, "means")), 2.0, True),
    "kmeans_{w}_random": ("means", lambda s, o: baselines.random_centres(s, K), None, True),
    "kmeans_{w}_materialize": ("means", lambda s, o: baselines.materialize_then(s, K, "means"), 1.01, True),
    "kmeans_{w}_spark_ml": ("means", lambda s, o: baselines.materialize_then_spark(s, K), 1.6, False),
}


def _method(w: str, pattern: str) -> None:
    objective, solve, factor, snapped = _METHODS[pattern]
    TIMED[pattern.format(w=w)] = lambda spark, sf: timed(spark, sf, w, solve)
    near = "" if factor is None else ", TRUE AS near_reference"
    add(pattern.format(w=w), f"SELECT count(*) AS n, count(*) AS covered, 0 AS strange, TRUE AS k_ok{near} FROM {join_sql(WORKLOADS[w])}", lambda spark, sf: verdict(spark, sf, w, objective, solve, factor, snapped))


for _name in _METHODS:
    _method("w9", _name)
for _w in ("w1", "w6"):
    for _name in ("kcenter_{w}_coreset", "kmeans_{w}", "kmedian_{w}"):
        _method(_w, _name)
for _w in ("w2", "w5", "w11"):
    for _name in ("kcenter_{w}_ladder", "kmeans_{w}"):
        _method(_w, _name)
for _w in ("w4", "w4t"):
    for _name in ("kcenter_{w}_ladder", "kmeans_{w}", "kmedian_{w}"):
        _method(_w, _name)


def _explosive(spark, sf, solve, objective, eps):
    """Never materialised. n is the tree's; members are the centres found in the join by counting their boxes; covered is what balls around
    the centres hold, for centers within the estimate, else within the diameter; bound: the estimate is not below a lower bound of the cost by rings."""
    space = bind(spark, sf, "w3", scaled=True)
    tree = lazy_tree(space, eps=eps)
    found = solve(space, tree)
    inside = space.count([Box.at(x) for x in found.centres])
    tree.reset()
    reach = found.estimate if objective == "center" else tree.root.region.outer.diameter
    covered = tree.count(found.centres, reach)
    finite = 0 < found.estimate < math.inf and covered == tree.n
    if objective != "center":
        finite = finite and found.estimate >= measures.cost_bracket(tree, found.centres, 2 if objective == "means" else 1)[0] * (1 - 1e-9)
    space.release()
    return one(spark, n=tree.n, covered=int(covered), strange=int((inside == 0).sum()), k_ok=len(found.centres) <= K, finite=bool(finite))


_W3 = f"SELECT count(*) AS n, count(*) AS covered, 0 AS strange, TRUE AS k_ok, TRUE AS finite FROM {join_sql(WORKLOADS['w3'])}"
add("kcenter_w3_coreset", _W3, lambda spark, sf: _explosive(spark, sf, lambda s, tree: kcenter.coreset_solve(s, K, 0.9, tree, how="geometric"), "center", 0.2))
for _n, _p in (("kmeans", 2), ("kmedian", 1)):
    add(f"{_n}_w3", _W3, lambda spark, sf, p=_p: _explosive(spark, sf, lambda s, tree: kmeans.solve(s, K, 0.9, p, tree=tree, constants=kmeans.LIGHT), "means" if p == 2 else "median", 0.9))


def _exact(spark, sf, w, objective, k):
    """The method with an enumerating solver on a coreset of single tuples gives the optimum; SQL enumerates it."""
    space = bind(spark, sf, w)
    options = {"solver": lambda p, c, k, **_: local.exact(p, c, k, objective), "leaf_cap": CAPS[w]}
    found = kcenter.coreset_solve(space, k, 1e-6, **options) if objective == "center" else kmeans.solve(space, k, 1e-6, 1 if objective == "median" else 2, **options)
    p, wt = baselines.materialized(space)
    return one(spark, n=int(found.trace["n"]), cost=float(round(local.cost(p, wt, found.centres, objective), 4)))


def _exact_sql(w: str, objective: str, k: int) -> str:
    cs = WORKLOADS[w].coords
    far = lambda a, b: "sqrt(" + " + ".join(f"({a}.{c} - {b}.{c}) ** 2" for c in cs) + ")"
    value = f"least({', '.join(far('p', f'c{i}') for i in range(k))})"
    total = {"center": f"max({value})", "median": f"sum(p.w * {value})", "means": f"sum(p.w * {value} ** 2)"}[objective]
    sets = " JOIN ".join(["d c0", *[f"d c{i} ON c{i - 1}.i < c{i}.i" for i in range(1, k)]])
    return f"WITH d AS (SELECT *, row_number() OVER (ORDER BY {', '.join(cs)}) AS i FROM (SELECT {', '.join(cs)}, count(*) AS w FROM {join_sql(WORKLOADS[w])} GROUP BY ALL)) SELECT (SELECT CAST(sum(w) AS BIGINT) FROM d) AS n, round(min(v), 4) AS cost FROM (SELECT {total} AS v FROM {sets}, d p GROUP BY {', '.join(f'c{i}.i' for i in range(k))})"


for _w, _k in (("w12", 3), ("w10", 2)):
    for _o in ("center", "median", "means"):
        add(f"optimum_{_w}_{_o}", _exact_sql(_w, _o, _k), lambda spark, sf, w=_w, o=_o, k=_k: _exact(spark, sf, w, o, k))


def _ratios(spark, sf, k=3):
    """Cost of each method over the enumerated optimum on the smallest join, against its factor."""
    space = bind(spark, sf, "w12")
    p, wt = baselines.materialized(space)
    rows, o, eps = [], {"leaf_cap": 3}, 0.2
    best = {x: local.exact(p, wt, k, x)[1] for x in ("center", "median", "means")}
    d = len(space.coords)
    for name, objective, factor, solve in (
        ("first", "center", 2 * math.sqrt(d) + eps, lambda: kcenter.search(space, k, eps, **o)),
        ("ladder", "center", 2 + eps, lambda: kcenter.refine(space, k, eps, **o)),
        ("coreset", "center", (1 + eps) * 2, lambda: kcenter.coreset_solve(space, k, eps, **o)),
        ("hierarchical", "center", (1 + 0.5) * 2 * 2, lambda: baselines.hierarchical(space, k, "center")),
        ("bicriteria", "means", 84 + eps, lambda: kmeans.bicriteria(space, k, eps, 2, **o)),
        ("bicriteria", "median", 84 + eps, lambda: kmeans.bicriteria(space, k, eps, 1, **o)),
        ("coreset", "means", 4 + eps, lambda: kmeans.solve(space, k, eps, 2, **o)),
        ("coreset", "median", 2 + eps, lambda: kmeans.solve(space, k, eps, 1, **o)),
        ("hierarchical", "means", 4 + eps, lambda: baselines.hierarchical(space, k, "means")),
        ("hierarchical", "median", 2 + eps, lambda: baselines.hierarchical(space, k, "median")),
    ):
        value = local.cost(p, wt, solve().centres, objective)
        rows.append((name, objective, round(best[objective], 4), bool(measures.ratio(value, best[objective]) <= factor * (1 + 1e-9))))
    return spark.createDataFrame(rows, "method string, objective string, optimum double, within boolean")


_OF = {x: f"(SELECT cost FROM ({_exact_sql('w12', x, 3)}))" for x in ("center", "median", "means")}
add("ratios_w12", " UNION ALL ".join(f"SELECT '{m}' AS method, '{x}' AS objective, {_OF[x]} AS optimum, TRUE AS within" for m, x in (("first", "center"), ("ladder", "center"), ("coreset", "center"), ("hierarchical", "center"), ("bicriteria", "means"), ("bicriteria", "median"), ("coreset", "means"), ("coreset", "median"), ("hierarchical", "means"), ("hierarchical", "median"))), _ratios)


def _bicriteria(spark, sf, power):
    space = bind(spark, sf, "w9", scaled=True)
    found = kmeans.bicriteria(space, K, 0.5, power, leaf_cap=CAPS["w9"])
    p, w = points_of(space, sf, "w9")
    value = local.cost(p, w, found.centres, "means" if power == 2 else "median")
    thin = sum(2 * r["covered"] < r["tau"] for r in found.trace["rounds"])
    reference = local.cost(p, w, local.solver("means" if power == 2 else "median")(p, w, K)[0], "means" if power == 2 else "median")
    return one(spark, n=int(found.trace["n"]), cost_le_estimate=bool(value <= found.estimate + 1e-9 or not found.trace["rounds"]), within=bool(found.estimate <= 85 * reference), thin_rounds=int(thin), more=len(found.centres) >= K)


for _p, _n in ((2, "means"), (1, "median")):
    add(f"bicriteria_{_n}_w9", f"SELECT count(*) AS n, TRUE AS cost_le_estimate, TRUE AS within, 0 AS thin_rounds, TRUE AS more FROM {join_sql(WORKLOADS['w9'])}", lambda spark, sf, p=_p: _bicriteria(spark, sf, p))


def _cores(spark, sf, kind):
    space = bind(spark, sf, "w9", scaled=True)
    tree = lazy_tree(space, eps=0.25, leaf_cap=CAPS["w9"])
    first = kcenter.search(space, K, 0.5, tree)
    p, w = points_of(space, sf, "w9")
    if kind == "adaptive":
        core = coreset.adaptive(tree, first.centres, 0.02, 0.25)
    elif kind == "grid":
        core = coreset.from_boxes(tree, coreset.grid(first.centres, first.estimate, 0.5))
    else:
        value = local.cost(p, w, first.centres, "means")
        core = coreset.from_boxes(tree, coreset.rings(first.centres, value, tree.n, 2, 1.0), weights="sampled" if kind == "sampled" else "tree")
    rng = np.random.default_rng(1)
    sets = [p[rng.choice(len(p), K)] for _ in range(10)]
    error = measures.coreset_error(p, w, core.points, core.weights, sets, "means")
    exact = kind == "sampled" or abs(core.weights.sum() - w.sum()) < 0.5
    return one(spark, n=int(w.sum()), weights_ok=bool(exact), small=len(core.points) < len(p), error_ok=bool(error < 0.75))


for _kind in ("adaptive", "grid", "rings", "sampled"):
    add(f"coreset_{_kind}_w9", f"SELECT count(*) AS n, TRUE AS weights_ok, TRUE AS small, TRUE AS error_ok FROM {join_sql(WORKLOADS['w9'])}", lambda spark, sf, kind=_kind: _cores(spark, sf, kind))

# mixed attributes


def _mixed(spark, sf, w, how, objective="means"):
    """All categories. weight: what the product grid holds together; cost is within a factor of the best single-tuple swap solution on a sample-free
    reference only where the join is small enough to materialise with its categories."""
    cats = {"w7": ["returnflag", "priority", "segment"], "w10": ["lang", "source", "quality", "toxic"]}[w]
    space = bind(spark, sf, w, cats=cats, scaled=True)
    n = space.size()
    if how == "ours":
        found = mixed.solve(space, 3, 0.5, objective)
    elif how == "grid":
        found = baselines.mixed_grid(space, 3)
    else:
        found = mixed.one_hot_solve(space, 3)
    weight = found.trace.get("weight", float(n))
    rows = space.materialize().groupBy(*space.coords, *space.cats).agg(F.sum("w").cast("double").alias("w")).toPandas()
    x, tags, wt = rows[space.coords].to_numpy(float), rows[space.cats].to_numpy(object), rows["w"].to_numpy(float)
    centres, values = found.centres, found.trace.get("values")
    if values is None:  # one-hot centres: each category's value is the coordinate that is set
        names = found.trace["coords"]
        own = [c for c in names if c in space.coords]
        picked = [[(c.split("_is_", 1)[1], centre[names.index(c)]) for c in names if c.startswith(f"{a}_is_")] for centre in centres for a in space.cats]
        tags = np.array([[str(v).replace(" ", "_").replace("#", "").replace("-", "_") for v in r] for r in tags], object)
        values = [tuple(max(picked[i * len(space.cats) + j], key=lambda p: p[1])[0] for j in range(len(space.cats))) for i in range(len(centres))]
        centres = centres[:, [names.index(c) for c in own]]
    value = mixed.assignment_cost(x, tags, wt, centres, values, objective=objective)
    _, _, flat = mixed.weighted_solve(x, tags, wt, 3, 1.0, objective)
    space.release()
    return one(spark, n=n, k_ok=len(found.centres) <= 3, weight=int(round(weight)), near_flat=bool(value <= 3 * flat))


for _w in ("w7", "w10"):
    for _how in ("ours", "grid", "one_hot"):
        add(f"mixed_{_w}_{_how}", f"SELECT count(*) AS n, TRUE AS k_ok, count(*) AS weight, TRUE AS near_flat FROM {join_sql(WORKLOADS[_w])}", lambda spark, sf, w=_w, how=_how: _mixed(spark, sf, w, how))
for _o in ("median", "center"):
    add(f"mixed_w10_{_o}", f"SELECT count(*) AS n, TRUE AS k_ok, count(*) AS weight, TRUE AS near_flat FROM {join_sql(WORKLOADS['w10'])}", lambda spark, sf, o=_o: _mixed(spark, sf, "w10", "ours", o))


def _class_tree(spark, sf):
    """A tree with class counters: what a ball takes, and what is left, add up to the classes of the whole join."""
    own = {"returnflag": ["R", "N"], "segment": ["BUILDING", "MACHINERY", "FURNITURE"]}
    space = mixed.classed(bind(spark, sf, "w7", cats=list(own), scaled=True), own)
    tree = ClassTree(space, eps=0.5, leaf_cap=4000, draws=600)
    before = tree.count_classes(tree.root.rep, 0.3)
    taken = tree.deactivate_classes(tree.root.rep, 0.3)
    left: dict[tuple, int] = {}
    for x in tree.frontier():
        for v, n in tree.classes(x, x.live if x.points is not None else None).items():
            left[v] = left.get(v, 0) + n
    same = before == taken and tree.active == sum(left.values()) and tree.counters[tree.root] == {v: left.get(v, 0) for v in tree.counters[tree.root]}
    rows = [(int(v[space.cats.index("cls_returnflag")]), int(v[space.cats.index("cls_segment")]), taken.get(v, 0) + left.get(v, 0), bool(same and tree.stats.nodes > 1)) for v in {*taken, *left}]
    return spark.createDataFrame(rows, "cr int, cs int, n long, same boolean")


add("class_counts_tree_w7", f"SELECT CASE WHEN returnflag = 'N' THEN 2 ELSE 1 END AS cr, CASE segment WHEN 'MACHINERY' THEN 2 WHEN 'FURNITURE' THEN 3 ELSE 1 END AS cs, count(*) AS n, TRUE AS same FROM {join_sql(WORKLOADS['w7'])} GROUP BY 1, 2", _class_tree)

# diversity and fairness


def _diverse(spark, sf, kind, k=6):
    space = bind(spark, sf, "w9", scaled=True)
    got, value = diversity.solve(space, k, kind, leaf_cap=CAPS["w9"])
    p, w = points_of(space, sf, "w9")
    flat = local.diversity(local.farthest_first(p, k), kind)
    return one(spark, n=int(w.sum()), k=len(got), members=bool(local.assign(got, p)[1].max() < 1e-9), near_flat=bool(value >= flat / 3))


for _kind in diversity.KINDS:
    add(f"diversity_{_kind}_w9", f"SELECT count(*) AS n, 6 AS k, TRUE AS members, TRUE AS near_flat FROM {join_sql(WORKLOADS['w9'])}", lambda spark, sf, kind=_kind: _diverse(spark, sf, kind))


def _farthest(spark, sf, slow=False):
    space = bind(spark, sf, "w9", scaled=True)
    p, w = points_of(space, sf, "w9")
    if slow:
        got = diversity.farthest_first_slow(space, 5, 0.5, leaf_cap=CAPS["w9"])
        return one(spark, n=int(w.sum()), near=bool(local.diversity(got, "edge") >= 0.5 * local.diversity(local.farthest_first(p, 5), "edge")))
    chosen = p[:2]
    _, d = diversity.farthest(space, chosen, 0.5, leaf_cap=CAPS["w9"])
    return one(spark, n=int(w.sum()), near=bool(d >= 0.5 * local.cost(p, w, chosen, "center")))


for _slow, _n in ((False, "farthest_w9"), (True, "farthest_first_slow_w9")):
    add(_n, f"SELECT count(*) AS n, TRUE AS near FROM {join_sql(WORKLOADS['w9'])}", lambda spark, sf, slow=_slow: _farthest(spark, sf, slow))


def _fair(spark, sf, w, attribute, kind):
    space = bind(spark, sf, w, cats=[attribute], scaled=True)
    names = sorted(mixed.category_weights(space)[attribute])
    quotas = dict.fromkeys(names, 2)
    got, groups, value = (fairness.remote_edge if kind == "edge" else fairness.remote_clique)(space, attribute, quotas, 0.5)
    met = all(int((groups == g).sum()) == 2 for g in names)
    # the points of each group are tuples of that group
    strange = sum(int((space.group(attribute, g).count([Box.at(x) for x in got[groups == g]]) == 0).sum()) for g in names)
    return one(spark, n=space.size(), groups=len(names), k=len(got), met=bool(met), strange=strange, apart=bool(value > 0))


for _w, _a in (("w8", "segment"), ("w10", "lang")):
    for _kind in ("edge", "clique"):
        add(f"fair_{_kind}_{_w}", f"SELECT count(*) AS n, count(DISTINCT {_a}) AS groups, 2 * count(DISTINCT {_a}) AS k, TRUE AS met, 0 AS strange, TRUE AS apart FROM {join_sql(WORKLOADS[_w])}", lambda spark, sf, w=_w, a=_a, kind=_kind: _fair(spark, sf, w, a, kind))

# measures


def _cost(spark, sf):
    """Cost of three fixed centres over the materialised join."""
    r = measures.cost_frame(bind(spark, sf, "w9").materialize(), ["c_acctbal", "s_acctbal"], np.array([[0.0, 0.0], [5000.0, 5000.0], [9000.0, 1000.0]]))
    return r.select(F.col("n").cast("long").alias("n"), F.round("center", 3).alias("center"), F.round("median", 1).alias("median"), F.round(F.col("means") / 1e6, 2).alias("means"))


_d = "least(c_acctbal ** 2 + s_acctbal ** 2, (c_acctbal - 5000) ** 2 + (s_acctbal - 5000) ** 2, (c_acctbal - 9000) ** 2 + (s_acctbal - 1000) ** 2)"
add("cost_w9", f"SELECT count(*) AS n, round(sqrt(max({_d})), 3) AS center, round(sum(sqrt({_d})), 1) AS median, round(sum({_d}) / 1e6, 2) AS means FROM {join_sql(WORKLOADS['w9'])}", _cost)


def _bracket(spark, sf):
    space = bind(spark, sf, "w9", scaled=True)
    p, w = points_of(space, sf, "w9")
    c = p[:: max(1, len(p) // 5)][:5]
    low, high = measures.cost_bracket(lazy_tree(space, eps=0.25, leaf_cap=CAPS["w9"]), c, 2)
    value = local.cost(p, w, c, "means")
    return one(spark, n=int(w.sum()), inside=bool(low <= value <= high))


add("cost_bracket_w9", f"SELECT count(*) AS n, TRUE AS inside FROM {join_sql(WORKLOADS['w9'])}", _bracket)


# balls, box queries and traces with exact numbers

#: Centre and radius of a ball in the coordinates' own units.
BALLS = {"w9": ((4000.0, 3000.0), 2500.0), "w6": ((0.0, 50.0, 250_000.0, 25.0), 60_000.0)}
_NORMS = {"l2": lambda ds: "sqrt(" + " + ".join(f"({d}) ** 2" for d in ds) + ")", "l1": lambda ds: " + ".join(f"abs({d})" for d in ds), "linf": lambda ds: f"greatest({', '.join(f'abs({d})' for d in ds)})"}


def _ball(spark, sf, w, metric):
    """With next to no slack the sandwich closes: the tree's count is the number of tuples within the radius."""
    space, (c, r) = bind(spark, sf, w), BALLS[w]
    tree = lazy_tree(space, eps=1e-12, leaf_cap=CAPS.get(w, 60_000), draws=600, metric=metric)
    seen, gone = tree.count(np.array(c), r), tree.deactivate(np.array(c), r)
    out = one(spark, inside=int(seen), gone=int(gone), rest=int(tree.active), reported=tree.reported())
    space.release()
    return out


for _w, _metrics in (("w9", ("l2", "l1", "linf")), ("w6", ("l2",))):
    for _m in _metrics:
        _spec = WORKLOADS[_w]
        _d = _NORMS[_m]([f"{c} - {float(x)!r}" for c, x in zip(_spec.coords, BALLS[_w][0], strict=True)])
        _r = BALLS[_w][1]
        add(f"ball_{_m}_{_w}", f"SELECT count(*) FILTER (WHERE {_d} <= {_r}) AS inside, count(*) FILTER (WHERE {_d} <= {_r}) AS gone, count(*) FILTER (WHERE {_d} > {_r}) AS rest, count(*) FILTER (WHERE {_d} > {_r}) AS reported FROM {join_sql(_spec)}", lambda spark, sf, w=_w, m=_m: _ball(spark, sf, w, m))


def _tree_box(spark, sf):
    """Box queries of the lazy tree: count, deactivate, and what is left; a representative of the box lies in it."""
    space, box = bind(spark, sf, "w9"), boxes_of("w9")[1]
    tree = lazy_tree(space, eps=0.5, leaf_cap=CAPS["w9"], draws=600)
    seen, rep = tree.count_box(box), tree.represent_box(box)
    gone = tree.deactivate_box(box)
    out = one(spark, inside=int(seen), gone=int(gone), rest=int(tree.active), strange=int(rep is None or not box.contains(rep)))
    space.release()
    return out


_in = in_box(WORKLOADS["w9"], BOXES["w9"][1])
add("tree_after_deactivate_w9", f"SELECT count(*) FILTER (WHERE {_in}) AS inside, count(*) FILTER (WHERE {_in}) AS gone, count(*) FILTER (WHERE NOT ({_in})) AS rest, 0 AS strange FROM {join_sql(WORKLOADS['w9'])}", _tree_box)


def _blow(spark, sf, w):
    n, base, factor = measures.blow_up(bind(spark, sf, w))
    return one(spark, n=int(n), base=int(base), factor=float(round(factor, 6)))


for _w in ("w2", "w3", "w6", "w9"):
    _base = " + ".join(f"(SELECT count(*) FROM {r.table})" for r in WORKLOADS[_w].relations)
    add(f"blow_up_{_w}", f"SELECT count(*) AS n, {_base} AS base, round(count(*) / ({_base}), 6) AS factor FROM {join_sql(WORKLOADS[_w])}", lambda spark, sf, w=_w: _blow(spark, sf, w))


def _region_rep(spark, sf):
    space, r = bind(spark, sf, "w9"), _region("w9")
    x = space.represent_regions([r])[0]
    return one(spark, found=int(x is not None), strange=int(x is not None and (not r.contains(x) or space.count([Box.at(x)])[0] == 0)))


_in = f"{in_box(WORKLOADS['w9'], HOLES['w9'][0])} AND NOT ({in_box(WORKLOADS['w9'], HOLES['w9'][1])})"
add("rep_hole_w9", f"SELECT CAST(count(*) > 0 AS BIGINT) AS found, 0 AS strange FROM {join_sql(WORKLOADS['w9'])} WHERE {_in}", _region_rep)


def _cover_flat(spark, sf):
    """Known radius, on points and by ball queries on a tree over them: at a radius that must do, both serve every tuple within twice it (and the slack)."""
    space = bind(spark, sf, "w9", scaled=True)
    p, w = points_of(space, sf, "w9")
    r = local.cost(p, w, local.farthest_first(p, K), "center")  # at least the optimum of K centres
    a, b = local.cover(p, K, r), local.cover_tree(flat_tree(p, w, eps=0.2, leaf_cap=64), K, r)
    near = lambda c, reach: int(round(local.weight_near(p, w, c, reach * (1 + 1e-9))))
    return one(spark, flat=near(a, 2 * r), tree=near(b, 2 * 1.2 * r))


add("cover_flat_w9", f"SELECT count(*) AS flat, count(*) AS tree FROM {join_sql(WORKLOADS['w9'])}", _cover_flat)


def _seeds(spark, sf, seeds=5):
    """How many of several seeds give a tree whose ball count lies in its sandwich."""
    space = bind(spark, sf, "w9", scaled=True)
    p, w = points_of(space, sf, "w9")
    good = 0
    for seed in range(seeds):
        tree = lazy_tree(space, eps=0.5, leaf_cap=CAPS["w9"], draws=600, seed=seed)
        c = tree.root.rep[None, :]
        good += bool(local.weight_near(p, w, c, 0.2) <= tree.count(c, 0.2) <= local.weight_near(p, w, c, 0.3 * (1 + 1e-9)))
    space.release()
    return one(spark, seeds=seeds, good=int(good))


add("success_seeds_w9", "SELECT 5 AS seeds, 5 AS good", _seeds)


def _rounds(spark, sf, w):
    """Trace of the rounds: what was active, the last heavy level, and the tuples that each level took."""
    space = bind(spark, sf, w, scaled=True)
    found = kmeans.bicriteria(space, K, 0.5, 2, constants=kmeans.LIGHT, leaf_cap=CAPS[w])
    rows = [(i, int(r["tau"]), int(r["beta"]), j, float(x), int(n)) for i, r in enumerate(found.trace["rounds"]) for j, (x, n) in enumerate(zip(r["radii"], r["counts"], strict=True))]
    space.release()
    return spark.createDataFrame(rows, "round int, tau long, beta int, level int, radius double, cnt long")


add("trace_rounds_w9", None, lambda spark, sf: _rounds(spark, sf, "w9"))


def _tree_facts(spark, sf):
    """Height, nodes, canonical nodes of a ball, jobs, and the inner shares of the shrink steps of an opened tree."""
    space = bind(spark, sf, "w9", scaled=True)
    tree = lazy_tree(space, eps=0.25, leaf_cap=100, draws=600).build()
    tree.count(tree.root.rep, 0.25)
    s = tree.stats
    space.release()
    return one(spark, n=tree.n, nodes=s.nodes, height=s.height, canonical=max(s.canonical), jobs=s.jobs, drawn=s.drawn, shrinks=len(s.balance), largest_share=float(max(s.balance, default=0.0)))


add("trace_tree_w9", None, _tree_facts)
