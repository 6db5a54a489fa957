"""Connected components by contraction; every table stays distributed."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import Scratch


def connected(edges: DataFrame, scratch: Scratch, name: str = "cc") -> DataFrame:
    """edges (a, b) -> (node, label): the least node reachable. Nodes without an edge do not appear.

    A round lets every vertex go to the first vertex among itself and its neighbours, and from there once more; edges whose ends meet vanish, so each
    round joins only the edges left over. First is the least in the first round, which ends stars around a least node at once, and the least by
    a hash that changes each round later, so no numbering of a chain takes more than logarithmically many rounds on average. The last
    vertex of a component is never gone to, so every round has fewer vertices and the loop ends. Edges with a null end are left out; loops and
    repeated edges change nothing; no edges give no rows; other columns are ignored.
    """
    ends = edges.where("a <> b").select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()
    left = scratch.store(ends, f"{name}-edges-0")
    labels, step = None, 0
    while not left.isEmpty():
        step += 1
        to = scratch.store(_steps(left, scratch, name, step), f"{name}-to-{step}")
        if labels is None:
            labels = to.select(F.col("v").alias("node"), F.col("to").alias("at"))
        else:
            labels = labels.join(to.withColumnRenamed("v", "at"), "at", "left").select("node", F.coalesce("to", "at").alias("at"))
        labels = scratch.store(labels, f"{name}-at-{step}")
        moved = left.join(to.select(F.col("v").alias("a"), F.col("to").alias("x")), "a").join(to.select(F.col("v").alias("b"), F.col("to").alias("y")), "b")
        moved = moved.where("x <> y").select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b")).distinct()
        left = scratch.store(moved, f"{name}-edges-{step}")
        scratch.drop(f"{name}-edges-{step - 1}", f"{name}-to-{step}", f"{name}-at-{step - 1}")
    if labels is None:
        labels = left.select(F.col("a").alias("node"), F.col("b").alias("at"))
    least = labels.groupBy("at").agg(F.min("node").alias("label"))
    found = scratch.store(labels.join(least, "at").select("node", "label"), f"{name}-labels")
    scratch.drop(f"{name}-edges-{step}", f"{name}-at-{step}", f"{name}-near")
    return found


def _steps(left: DataFrame, scratch: Scratch, name: str, step: int) -> DataFrame:
    """(v, to) for every vertex that has an edge: two moves to the first vertex among itself and its neighbours."""

    def order(vertex: Column) -> Column:
        return vertex if step == 1 else F.xxhash64(vertex, F.lit(step))

    def ranked(vertex: str) -> Column:
        return F.struct(order(F.col(vertex)).alias("order"), F.col(vertex).alias("vertex"))

    near = left.select(F.col("a").alias("v"), F.col("b").alias("w")).unionByName(left.select(F.col("b").alias("v"), F.col("a").alias("w")))
    near = near.groupBy("v").agg(F.min(ranked("w")).alias("best"))
    near = scratch.store(near.select("v", F.least(ranked("v"), F.col("best"))["vertex"].alias("to")), f"{name}-near")
    return near.join(near.select(F.col("v").alias("to"), F.col("to").alias("far")), "to").select("v", F.col("far").alias("to"))
