"""Join spaces: the result of a join query that is only ever counted, sampled, reported or represented through boxes.

Every operation passes messages along the join tree, leaves first: rows outside a box drop out at their own relation,
multiplicities of the children's messages are multiplied, and one aggregation a tree edge sums them by the parent's keys.
A batch of boxes goes through together: box_id is one more key. The boxes are broadcast (a batch has at most `MAX_BOXES`).
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import hypergraph
from .region import Box, Region
from .spec import JoinSpec, Relation

MAX_BOXES = 512
COUNT = "decimal(38,0)"


def key(name: str) -> str:
    return f"k_{name}"


def load(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    if not table.startswith("("):
        return spark.read.parquet(f"{sf_dir}/{table}.parquet")
    import re

    text = table.strip("()")
    for t in set(re.findall(r"(?:FROM|JOIN)\s+(\w+)", text)):
        text = re.sub(rf"\b((?:FROM|JOIN)\s+){t}\b", rf"\1parquet.`{sf_dir}/{t}.parquet`", text)
    return spark.sql(text)


class JoinSpace:
    """A bound join query. frames: per relation its keys (k_), coordinates, categories and multiplicity w, pre-aggregated."""

    def __init__(self, spec: JoinSpec, frames: dict[str, DataFrame], coords: list[str], cats: list[str], tree: hypergraph.JoinTree | None, scale: dict[str, float] | None = None, owned: dict[str, tuple[list[str], list[str]]] | None = None):
        self.spec, self.frames, self.coords, self.cats, self.tree = spec, frames, coords, cats, tree
        self.scale = scale or {}
        self.owned = owned or {r.name: ([c for c in r.coords if c in coords], [c for c in r.cats if c in cats]) for r in spec.relations}
        self.passes = 0
        self.spans: dict[int, tuple[np.ndarray, np.ndarray]] = {}  # of the batch at work: the box around all its boxes

    @staticmethod
    def bind(spark: SparkSession, sf_dir: str, spec: JoinSpec, coords: list[str] | None = None, cats: list[str] | None = None, scale: dict[str, float] | None = None, grouped: bool = True) -> JoinSpace:
        """coords and cats: the attributes that stay; others are dropped, multiplicities are kept (bag projection).
        Without `grouped`, rows stay as they are, each with multiplicity 1: for a single look, as at the root box."""
        coords = spec.coords if coords is None else coords
        cats = [] if cats is None else cats
        tree = hypergraph.join_tree(spec)
        frames = {r.name: prepared(load(spark, sf_dir, r.table), r, coords, cats, scale or {}, grouped) for r in spec.relations}
        return JoinSpace(spec, frames, [c for c in spec.coords if c in coords], [c for c in spec.cats if c in cats], tree, scale)

    @property
    def spark(self) -> SparkSession:
        return next(iter(self.frames.values())).sparkSession

    def with_frames(self, frames: dict[str, DataFrame]) -> JoinSpace:
        return JoinSpace(self.spec, frames, self.coords, self.cats, self.tree, self.scale, self.owned)

    def cached(self) -> JoinSpace:
        """Pre-aggregated relations stay in executors' memory or disk; every batch scans them again. `release` frees them."""
        return self.with_frames({n: f.persist() for n, f in self.frames.items()})

    def release(self) -> None:
        for f in self.frames.values():
            f.unpersist()

    def group(self, attribute: str, value) -> JoinSpace:
        """The part where a categorical attribute has a value: a filter on its one relation."""
        name = next(n for n, (_, cats) in self.owned.items() if attribute in cats)
        return self.with_frames(self.frames | {name: self.frames[name].where(F.col(attribute) == value)})

    def project(self, coords: list[str], bag: bool = True, objective: str | None = None) -> JoinSpace:
        """Bag projection keeps multiplicities. Set projection is allowed only where they cannot matter."""
        if not bag and objective not in ("center", "edge"):
            raise ValueError("set semantics would change this objective")
        frames, owned = {}, {}
        for n, f in self.frames.items():
            mine = [c for c in self.owned[n][0] if c in coords]
            owned[n] = (mine, self.owned[n][1])
            names = [c for c in f.columns if c.startswith("k_")] + mine + self.owned[n][1]
            total = F.sum("w") if bag else F.lit(1).cast(COUNT)
            frames[n] = f.groupBy(*names).agg(total.cast(COUNT).alias("w"))
        return JoinSpace(self.spec, frames, [c for c in self.coords if c in coords], self.cats, self.tree, self.scale, owned)

    # plain join, for reference and cyclic queries

    def materialize(self) -> DataFrame:
        """All join tuples (coords, cats) with multiplicity w."""
        out, seen = None, set()
        order = [r.name for r in self.spec.relations]
        while order:
            name = next((n for n in order if out is None or {c for c in self.frames[n].columns if c.startswith("k_")} & seen), order[0])
            order.remove(name)
            f = self.frames[name]
            keys = {c for c in f.columns if c.startswith("k_")}
            if out is None:
                out = f
            else:
                f = f.withColumnRenamed("w", "w2")
                both = sorted(keys & seen)
                out = (out.join(f, both) if both else out.crossJoin(f)).withColumn("w", (F.col("w") * F.col("w2")).cast(COUNT)).drop("w2")
            seen |= keys
        return out.select(*self.coords, *self.cats, "w")

    # messages

    def _need_tree(self) -> hypergraph.JoinTree:
        if self.tree is None:
            raise ValueError("a cyclic query: turn it into an acyclic one first (cyclic.to_acyclic)")
        return self.tree

    def _boxed(self, name: str, boxes: DataFrame | None) -> DataFrame:
        """Rows of a relation inside each box, as far as its own coordinates tell."""
        f = self.frames[name]
        mine = self.owned[name][0]
        if boxes is None or not mine:
            return f
        at = {c: i for i, c in enumerate(self.coords)}
        test = F.lit(True)
        for c in mine:
            test = test & (F.col(c) >= F.col("lo")[at[c]]) & (F.col(c) < F.col("hi")[at[c]])
            if (ends := self.spans.get(id(boxes))) is not None:  # what no box of the batch can hold goes before the join
                f = f.where((F.col(c) >= F.lit(float(ends[0][at[c]]))) & (F.col(c) < F.lit(float(ends[1][at[c]]))))
        return f.join(F.broadcast(boxes), test).drop("lo", "hi")

    def upward(self, boxes: DataFrame | None, extra: dict[str, dict[str, Column]] | None = None, rep: bool = False, pairs: dict | None = None) -> DataFrame:
        """The root's message: sums of multiplicities by (box_id, carried columns), with a least tuple if `rep`.

        extra: per relation, columns that become keys of all messages above it (groups, classes).
        pairs: per coordinate an expression; then sums of it and of its square come along (moments).
        """
        tree = self._need_tree()
        self.passes += 1
        sent: dict[str, DataFrame] = {}
        carried: dict[str, list[str]] = {}
        for name in tree.upward():
            f = self._boxed(name, boxes)
            mine = list((extra or {}).get(name, {}).items())
            f = f.withColumns({c: e for c, e in mine}) if mine else f
            carry = [c for c, _ in mine]
            count = F.col("w")
            least = [F.array(*[F.col(c).cast("double") for c in self.owned[name][0]])] if rep else []
            for child in tree.children(name):
                m = sent[child]
                on = [key(a) for a in tree.shared[child]]
                if "box_id" in m.columns and "box_id" in f.columns:
                    on = [*on, "box_id"]
                m = m.withColumnsRenamed({"cnt": f"cnt_{child}", "rep": f"rep_{child}"})
                f = f.join(m, on) if on else f.crossJoin(m)
                count = (count * F.col(f"cnt_{child}")).cast(COUNT)
                least.append(F.col(f"rep_{child}"))
                carry += carried[child]
            parent_keys = [key(a) for a in tree.shared[name]]
            by = ([] if "box_id" not in f.columns else ["box_id"]) + parent_keys + carry
            sums = [F.sum(count).cast(COUNT).alias("cnt")]
            if rep:
                sums.append(F.min(F.concat(*least) if len(least) > 1 else least[0]).alias("rep"))
            sent[name] = f.groupBy(*by).agg(*sums)
            carried[name] = carry
        return sent[tree.root]

    def rep_order(self) -> list[int]:
        """Positions in a least tuple, by coordinate of the space."""
        names: list[str] = []

        def visit(name: str) -> None:
            names.extend(self.owned[name][0])
            for c in self._need_tree().children(name):
                visit(c)

        visit(self._need_tree().root)
        return [names.index(c) for c in self.coords]

    def box_frame(self, boxes: list[Box]) -> DataFrame:
        if len(boxes) > MAX_BOXES:
            raise ValueError("split the batch")
        rows = [(i, [float(v) for v in b.lo], [float(v) for v in b.hi]) for i, b in enumerate(boxes)]
        out = self.spark.createDataFrame(rows, "box_id int, lo array<double>, hi array<double>")
        if boxes:
            self.spans = {id(out): (np.min([b.lo for b in boxes], axis=0), np.max([b.hi for b in boxes], axis=0))}
        return out

    def _batches(self, boxes: list[Box]):
        for at in range(0, len(boxes), MAX_BOXES):
            yield at, self.box_frame(boxes[at : at + MAX_BOXES])

    def size(self) -> int:
        return int(self.upward(None).first()["cnt"] or 0)

    def count(self, boxes: list[Box]) -> np.ndarray:
        return self.count_and_represent(boxes, rep=False)[0]

    def count_and_represent(self, boxes: list[Box], rep: bool = True) -> tuple[np.ndarray, list[np.ndarray | None]]:
        """Counts and least tuples of a batch, in one pass."""
        counts, reps = np.zeros(len(boxes), object), [None] * len(boxes)
        order = self.rep_order()
        for at, frame in self._batches(boxes):
            for r in self.upward(frame, rep=rep).collect():  # one row a box
                counts[at + r["box_id"]] = int(r["cnt"])
                if rep:
                    reps[at + r["box_id"]] = np.array([r["rep"][i] for i in order])
        return counts, reps

    def representative(self, boxes: list[Box]) -> list[np.ndarray | None]:
        return self.count_and_represent(boxes)[1]

    def count_regions(self, regions: list[Region]) -> np.ndarray:
        """Outer minus hole: two boxes instead of 2d slabs, the same value."""
        boxes = [r.outer for r in regions] + [r.hole for r in regions if r.hole is not None]
        counts = self.count(boxes) if boxes else np.zeros(0, object)
        out, at = counts[: len(regions)].copy(), len(regions)
        for i, r in enumerate(regions):
            if r.hole is not None:
                out[i] -= counts[at]
                at += 1
        return out

    def represent_regions(self, regions: list[Region]) -> list[np.ndarray | None]:
        """A tuple from the first slab that has one."""
        boxes = [(i, s) for i, r in enumerate(regions) for s in r.slabs()]
        reps = self.representative([s for _, s in boxes]) if boxes else []
        out: list[np.ndarray | None] = [None] * len(regions)
        for (i, _), x in zip(boxes, reps, strict=True):
            if out[i] is None:
                out[i] = x
        return out

    def reduced(self) -> JoinSpace:
        """The same tuples over the rows that take part in some: a group's relations get as small as the group. Kept like `cached`."""
        return self.with_frames(self.reduce()).cached()

    # tuples

    def _on(self, a: DataFrame, b: DataFrame, child: str) -> list[str]:
        both = [key(x) for x in self._need_tree().shared[child]]
        return both + (["box_id"] if "box_id" in a.columns and "box_id" in b.columns else [])

    def reduce_up(self, boxes: DataFrame | None = None) -> dict[str, DataFrame]:
        """Rows with a partner in every relation below them: semijoins, leaves first."""
        tree = self._need_tree()
        rows = {n: self._boxed(n, boxes) for n in self.frames}
        for name in tree.upward():
            p = tree.parent[name]
            if p is not None and (on := self._on(rows[p], rows[name], name)):
                rows[p] = rows[p].join(rows[name].select(*on).distinct(), on, "left_semi")
        return rows

    def reduce(self, boxes: DataFrame | None = None) -> dict[str, DataFrame]:
        """Rows that take part in some tuple (of some box): semijoins up, then down."""
        tree, rows = self._need_tree(), self.reduce_up(boxes)
        for name in reversed(tree.upward()):
            p = tree.parent[name]
            if p is not None and (on := self._on(rows[name], rows[p], name)):
                rows[name] = rows[name].join(rows[p].select(*on).distinct(), on, "left_semi")
        return rows

    def report(self, boxes: list[Box]) -> DataFrame:
        """Tuples of each box: (box_id, coords, w), equal tuples summed up. Cost follows the output."""
        tree = self._need_tree()
        out = None
        for at, frame in self._batches(boxes):
            rows = self.reduce_up(frame)  # from the root down, every row then has a partner
            whole = None
            for name in reversed(tree.upward()):
                f = rows[name]
                if whole is None:
                    whole = f
                    continue
                f = f.withColumnRenamed("w", "w2")
                on = [c for c in f.columns if (c.startswith("k_") or c == "box_id") and c in whole.columns]
                whole = whole.join(f, on).withColumn("w", (F.col("w") * F.col("w2")).cast(COUNT)).drop("w2")
            part = whole.groupBy((F.col("box_id") + at).alias("box_id"), *self.coords, *self.cats).agg(F.sum("w").cast(COUNT).alias("w"))
            out = part if out is None else out.unionByName(part)
        return out

    def report_regions(self, regions: list[Region]) -> list[tuple[np.ndarray, np.ndarray]]:
        """Distinct coordinate tuples and weights of each region, on the driver; callers bound the counts."""
        boxes = [(i, s) for i, r in enumerate(regions) for s in r.slabs()]
        frame = self.report([s for _, s in boxes]).select("box_id", *self.coords, F.col("w").cast("double").alias("w")).toPandas()
        owner = np.array([i for i, _ in boxes])
        ids = owner[frame["box_id"].to_numpy(int)]
        points, w = frame[self.coords].to_numpy(float), frame["w"].to_numpy(float)
        return [(points[ids == i], w[ids == i]) for i in range(len(regions))]

    def reported_weight(self, regions: list[Region]) -> int:
        """The weights of the regions' reported tuples together, summed on the executors."""
        rows = self.report([s for r in regions for s in r.slabs()])
        return int(rows.agg(F.sum("w")).first()[0] or 0) if rows is not None else 0

    def _weighted(self, boxes: DataFrame) -> dict[str, DataFrame]:
        """Rows with the weight of the subtree below them, by box."""
        tree, out, sent = self._need_tree(), {}, {}
        self.passes += 1
        for name in tree.upward():
            f = self._boxed(name, boxes)
            if "box_id" not in f.columns:
                f = f.crossJoin(F.broadcast(boxes.select("box_id")))  # a batch has at most MAX_BOXES
            for child in tree.children(name):
                f = f.join(sent[child].withColumnRenamed("cnt", "c"), [key(a) for a in tree.shared[child]] + ["box_id"]).withColumn("w", (F.col("w") * F.col("c")).cast(COUNT)).drop("c")
            out[name] = f
            sent[name] = f.groupBy("box_id", *[key(a) for a in tree.shared[name]]).agg(F.sum("w").cast(COUNT).alias("cnt"))
        return out

    def sample(self, boxes: list[Box], draws: list[int], seed: int = 42, bucket_rows: int = 65_536) -> list[np.ndarray]:
        """draws[i] uniform tuples with replacement from box i, in time of the relations and the draws, not of their product.

        Rows are dealt to hash buckets of about `bucket_rows`. The root's draws are split over its buckets by a multinomial on the
        driver. Inside a bucket rows lie on [0, 1) one after the other, each as long as its share of the weight, a draw is a point, and one
        sorted merge gives every draw its row. Going down, a draw first picks a bucket of its key and then a row in the bucket,
        in the same way; rows of keys that no draw has are left out before sorting. Points are hashes of seed and draw: reruns agree.
        """
        out = [np.empty((0, len(self.coords))) for _ in boxes]
        if not boxes or not sum(draws):
            return out
        tree = self._need_tree()
        rng = np.random.Generator(np.random.Philox(seed))
        for at, frame in self._batches(boxes):
            some = [int(z) for z in draws[at : at + MAX_BOXES]]
            rows = self._weighted(frame)
            for n, f in rows.items():
                buckets = max(1, -(-self.frames[n].count() // bucket_rows))
                f = f.withColumn("row_id", F.xxhash64(*[c for c in f.columns if c not in ("w", "box_id")]))
                rows[n] = f.withColumn("bucket", F.pmod(F.xxhash64("row_id"), F.lit(buckets)).cast("int"))
            root = rows[tree.root]
            totals = root.groupBy("box_id", "bucket").agg(F.sum("w").cast("double").alias("t")).orderBy("box_id", "bucket").toPandas()  # a row a box and bucket
            asked = []
            for box, part in totals.groupby("box_id"):
                p = part["t"].to_numpy(float)
                got = rng.multinomial(some[box], p / p.sum())
                asked += [(int(box), int(b), int(n)) for b, n in zip(part["bucket"], got, strict=True) if n]
            if not asked:
                continue
            wanted = self.spark.createDataFrame(asked, "box_id int, bucket int, n int")
            first = wanted.select("box_id", "bucket", F.explode(F.sequence(F.lit(1), F.col("n"))).alias("j"))
            first = first.select("box_id", "bucket", F.xxhash64("box_id", "bucket", "j", F.lit(seed)).alias("draw"))
            picked = self._pick(first, root, ["box_id", "bucket"], tree.root, seed)
            for name in list(reversed(tree.upward()))[1:]:
                on = ["box_id"] + [key(a) for a in tree.shared[name]]
                f = rows[name]
                sums = f.groupBy(*on, "bucket").agg(F.sum("w").cast(COUNT).alias("w")).withColumn("row_id", F.col("bucket").cast("long"))
                picked = self._pick(picked, sums, on, f"{name}/bucket", seed)
                picked = self._pick(picked, f, [*on, "bucket"], name, seed)
            got = picked.select("box_id", *self.coords).toPandas()
            ids, points = got["box_id"].to_numpy(int), got[self.coords].to_numpy(float)
            for i in range(len(some)):
                out[at + i] = points[ids == i]
        return out

    @staticmethod
    def _pick(draws: DataFrame, rows: DataFrame, on: list[str], name: str, seed: int) -> DataFrame:
        """Each draw with one row of its group `on`, by weight: a merge of the rows' prefix shares with the draws' points."""
        old = [c for c in draws.columns if c not in on]
        old = [c for c in old if c != "bucket"]
        new = [c for c in rows.columns if c not in on and c not in ("w", "row_id") and c not in old]
        rows = rows.join(F.broadcast(draws.select(*on).distinct()), on, "left_semi")  # at most a row a draw, and draws are few
        group = Window.partitionBy(*on)
        before = F.coalesce(F.sum("w").over(group.orderBy("row_id").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0).cast(COUNT))
        rows = rows.withColumn("pos", before.cast("double") / F.sum("w").over(group).cast("double"))
        u = (F.pmod(F.xxhash64("draw", F.lit(name), F.lit(seed)), F.lit(2**52)).cast("double") + 0.5) / F.lit(float(2**52))
        payload, kept = F.struct(*new, F.lit(1).alias("_")), F.struct(*old)
        rows = rows.select(*on, "pos", F.lit(0).alias("kind"), payload.alias("row"))
        asked = draws.select(*on, u.alias("pos"), F.lit(1).alias("kind"), kept.alias("asked"))
        merged = rows.unionByName(asked, allowMissingColumns=True)
        along = group.orderBy("pos", "kind").rowsBetween(Window.unboundedPreceding, Window.currentRow)
        found = merged.withColumn("row", F.last("row", ignorenulls=True).over(along)).where("kind = 1")
        out = found.select(*on, *[F.col(f"asked.{c}").alias(c) for c in old], *[F.col(f"row.{c}").alias(c) for c in new])
        # as many rows as draws, which end on the driver anyway; going on from there, no step is computed twice
        return out.sparkSession.createDataFrame(out.toArrow())

    def sample_regions(self, regions: list[Region], draws: list[int], seed: int = 42) -> list[np.ndarray]:
        """Per region a multinomial over its slabs' counts, then draws in the slabs: every tuple is equally likely."""
        slabs = [(i, s) for i, r in enumerate(regions) for s in r.slabs()]
        plain = all(r.hole is None for r in regions)
        counts = np.ones(len(slabs)) if plain else self.count([s for _, s in slabs]).astype(float)
        rng = np.random.Generator(np.random.Philox(seed + 1))
        owner = np.array([i for i, _ in slabs])
        want = np.zeros(len(slabs), int)
        for i in range(len(regions)):
            mine = np.flatnonzero(owner == i)
            if counts[mine].sum() > 0:
                want[mine] = rng.multinomial(draws[i], counts[mine] / counts[mine].sum())
        live = np.flatnonzero(want)
        got = self.sample([slabs[j][1] for j in live], want[live].tolist(), seed)
        out = [[] for _ in regions]
        for j, x in zip(live, got, strict=True):
            out[owner[j]].append(x)
        return [np.concatenate(x) if x else np.empty((0, len(self.coords))) for x in out]

    # sums over the whole space

    def totals(self) -> dict[str, DataFrame]:
        """Per relation its rows that take part, with `total`: the number of join tuples each is in.

        One pass up multiplies the children's messages into each row; one pass down sends every child, by its keys, the weight of everything
        outside its subtree. Each relation meets its neighbours' messages once, so the work is that of the relations, for all attributes together.
        """
        tree = self._need_tree()
        self.passes += 2
        rows: dict[str, DataFrame] = {}
        sent: dict[str, DataFrame] = {}
        for name in tree.upward():
            f, inside = self.frames[name], F.col("w")
            for child in tree.children(name):
                m = sent[child].withColumnRenamed("cnt", f"cnt_{child}")
                on = [key(a) for a in tree.shared[child]]
                f = f.join(m, on) if on else f.crossJoin(m)  # without keys a message is one row
                inside = (inside * F.col(f"cnt_{child}")).cast(COUNT)
            rows[name] = f
            sent[name] = f.groupBy(*[key(a) for a in tree.shared[name]]).agg(F.sum(inside).cast(COUNT).alias("cnt"))
        rows[tree.root] = rows[tree.root].withColumn("outside", F.lit(1).cast(COUNT))
        for name in reversed(tree.upward()):
            children = tree.children(name)
            for child in children:
                others = (F.col("w") * F.col("outside")).cast(COUNT)
                for c in children:
                    if c != child:
                        others = (others * F.col(f"cnt_{c}")).cast(COUNT)
                on = [key(a) for a in tree.shared[child]]
                m = rows[name].groupBy(*on).agg(F.sum(others).cast(COUNT).alias("outside"))
                rows[child] = rows[child].join(m, on) if on else rows[child].crossJoin(m)
        out = {}
        for name, f in rows.items():
            total = (F.col("w") * F.col("outside")).cast(COUNT)
            for c in tree.children(name):
                total = (total * F.col(f"cnt_{c}")).cast(COUNT)
            out[name] = f.withColumn("total", total)
        return out

    def value_weights(self, names: list[str] | None = None) -> DataFrame:
        """(attr, value, w): number of join tuples with that value, for each attribute."""
        out, rows = None, self.totals()
        for n, (mine, cats) in self.owned.items():
            own = [a for a in [*mine, *cats] if a in (names or [*self.coords, *self.cats])]
            if own:
                each = F.explode(F.array(*[F.struct(F.lit(a).alias("attr"), F.col(a).cast("string").alias("value")) for a in own])).alias("x")
                one = rows[n].select(each, "total").groupBy("x.attr", "x.value").agg(F.sum("total").cast(COUNT).alias("w"))
                out = one if out is None else out.unionByName(one)
        return out

    def moments(self, names: list[str] | None = None) -> DataFrame:
        """(attr, n, mean, variance, least, greatest) over the join space: one aggregation a relation."""
        out, rows = None, self.totals()
        for n, (mine, _) in self.owned.items():
            own = [a for a in mine if a in (names or self.coords)]
            if own:
                w = F.col("total").cast("double")
                ends = [F.first(F.col(a)).alias(f"at_{a}") for a in own]  # any value near the data: sums about it do not cancel
                at = self.frames[n].agg(*ends).first()
                sums = [F.sum(w).alias("n")]
                for a in own:
                    x = F.col(a) - F.lit(float(at[f"at_{a}"] or 0.0))
                    sums += [F.sum(w * x).alias(f"s1_{a}"), F.sum(w * x * x).alias(f"s2_{a}"), F.min(a).alias(f"lo_{a}"), F.max(a).alias(f"hi_{a}")]
                one = rows[n].agg(*sums)
                shift = lambda a, at=at: F.lit(float(at[f"at_{a}"] or 0.0))
                mean = lambda a: F.col(f"s1_{a}") / F.col("n")
                each = [F.struct(F.lit(a).alias("attr"), F.col("n"), (shift(a) + mean(a)).alias("mean"), (F.col(f"s2_{a}") / F.col("n") - mean(a) * mean(a)).alias("variance"), F.col(f"lo_{a}").alias("least"), F.col(f"hi_{a}").alias("greatest")) for a in own]
                one = one.select(F.inline(F.array(*each)))
                out = one if out is None else out.unionByName(one)
        return out

    def root_box(self) -> Box:
        """From the base tables alone."""
        lo, hi = {}, {}
        for n, f in self.frames.items():
            mine = self.owned[n][0]
            if mine:
                r = f.agg(*[F.min(c).cast("double").alias(f"lo_{c}") for c in mine], *[F.max(c).cast("double").alias(f"hi_{c}") for c in mine]).first()
                for c in mine:
                    lo[c], hi[c] = r[f"lo_{c}"], r[f"hi_{c}"]
        if any(v is None for v in lo.values()):
            return Box(np.zeros(len(self.coords)), np.zeros(len(self.coords)))
        return Box(np.array([lo[c] for c in self.coords]), np.nextafter(np.array([hi[c] for c in self.coords]), np.inf))

    def value_pool(self) -> DataFrame:
        """(attr, value): distinct coordinate values of the base tables."""
        out = None
        for n, f in self.frames.items():
            for c in self.owned[n][0]:
                one = f.select(F.lit(c).alias("attr"), F.col(c).cast("double").alias("value")).distinct()
                out = one if out is None else out.unionByName(one)
        return out

    def count_classes(self, boxes: list[Box] | None, classes: dict[str, dict[str, Column]]) -> DataFrame:
        """Counts by (box_id, class columns). classes: per relation, columns over its own attributes; one pass for all."""
        if boxes is None:
            return self.upward(None, extra=classes)
        out = None
        for at, frame in self._batches(boxes):
            part = self.upward(frame, extra=classes).withColumn("box_id", F.col("box_id") + at)
            out = part if out is None else out.unionByName(part)
        return out

    def nearest(self, points: np.ndarray, j: int = 1) -> list[tuple[np.ndarray, np.ndarray]]:
        """The j nearest join tuples of each point, with distances. Squared distance is a sum over relations, so messages keep
        the j least partial sums of each key; equal sums rank by the tuple."""
        tree = self._need_tree()
        self.passes += 1
        rows = [(i, [float(v) for v in p]) for i, p in enumerate(np.atleast_2d(points))]
        asked = self.spark.createDataFrame(rows, "q int, p array<double>")
        at = {c: i for i, c in enumerate(self.coords)}
        sent: dict[str, DataFrame] = {}
        for name in tree.upward():
            mine = self.owned[name][0]
            f = self.frames[name].crossJoin(F.broadcast(asked))  # few points, given by the caller
            own = F.lit(0.0)
            for c in mine:
                own = own + (F.col(c) - F.col("p")[at[c]]) * (F.col(c) - F.col("p")[at[c]])
            tuple_ = F.struct(own.alias("d"), F.array(*[F.col(c).cast("double") for c in mine]).cast("array<double>").alias("x"))
            f = f.withColumn("best", F.array_repeat(tuple_, F.least(F.col("w"), F.lit(j)).cast("int")))
            for child in tree.children(name):
                f = f.join(sent[child].withColumnRenamed("best", "b2"), [key(a) for a in tree.shared[child]] + ["q"])
                both = F.flatten(F.transform("best", lambda a: F.transform("b2", lambda b: F.struct((a["d"] + b["d"]).alias("d"), F.concat(a["x"], b["x"]).alias("x")))))
                f = f.withColumn("best", F.slice(F.array_sort(both), 1, j)).drop("b2")
            # only j rows of a key are kept, by a rank that Spark limits before the shuffle too; no list is longer than j
            by = ["q", *[key(a) for a in tree.shared[name]]]
            slim = f.select(*by, F.explode("best").alias("t"))
            ranked = slim.withColumn("rank", F.row_number().over(Window.partitionBy(*by).orderBy("t"))).where(F.col("rank") <= j)
            sent[name] = ranked.groupBy(*by).agg(F.array_sort(F.collect_list("t")).alias("best"))
        order = self.rep_order()
        out: list = [(np.empty((0, len(self.coords))), np.empty(0))] * len(rows)
        for r in sent[tree.root].collect():
            out[r["q"]] = (np.array([[t["x"][i] for i in order] for t in r["best"]]), np.sqrt([t["d"] for t in r["best"]]))
        return out


def prepared(table: DataFrame, r: Relation, coords: list[str], cats: list[str], scale: dict[str, float], grouped: bool = True) -> DataFrame:
    if r.where:
        table = table.where(r.where)
    cols = [F.expr(e).alias(key(k)) for k, e in r.keys.items()]
    mine = [c for c in r.coords if c in coords]
    for c in mine:
        cols.append((F.expr(r.coords[c]).cast("double") / F.lit(float(scale.get(c, 1.0)))).alias(c))
    tags = [c for c in r.cats if c in cats]
    cols += [F.expr(r.cats[c]).alias(c) for c in tags]
    rows = table.select(*cols) if cols else table.select(F.lit(0).alias("one"))
    for k in r.keys:
        rows = rows.where(F.col(key(k)).isNotNull())
    for c in mine:
        rows = rows.where(F.col(c).isNotNull() & ~F.isnan(c))
    if not grouped:
        return rows.drop("one").withColumn("w", F.lit(1).cast(COUNT))
    return rows.groupBy(*[c for c in rows.columns if c != "one"]).agg(F.count("*").cast(COUNT).alias("w"))
