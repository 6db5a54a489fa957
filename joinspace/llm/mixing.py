"""Mixing sources to target weights: floor(rate) copies plus one hash-seeded Bernoulli copy.

Native. Sizes are summed per source before anything is joined; the table of sources has one row for each.
Rates never exceed `cap`, so no document is taken more often. The draw is a hash of seed and doc_id: reruns agree.

Defined cases: a null text has size 0; null is a source of its own, last in order; a null doc_id draws as the
string 'null'; rows that repeat a doc_id share its draw; sources of size 0 have target 0; sources that fill up at the same level
are taken in code-point order, with the same targets in any order; an empty table gives an empty mix; very long texts are counted whole;
columns of documents called like one of `ADDED` are replaced by `rates`, all others stay; `mix` keeps all but an own copy_no.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import Scratch, space_words

#: Fixed value: 52 random bits, 13 hexadecimal digits of an MD5.
DIGITS = 13
#: What `rates` adds.
ADDED = ("size", "source_size", "target", "copies")
WIDE = "decimal(38,0)"


def uniform(key: Column, seed: str = "mix") -> Column:
    """A number in [0, 1) from a hash."""
    digest = F.md5(F.concat(F.lit(f"{seed}:"), F.coalesce(key.cast("string"), F.lit("null"))))
    return F.conv(F.substring(digest, 1, DIGITS), 16, 10).cast("double") / F.lit(float(16**DIGITS))


def targets(sources: DataFrame, weights: tuple[int, ...] = (5, 2, 1), cap: int = 3) -> DataFrame:
    """sources (source, source_size) with weight and target.

    The targets share the total by weight, stop at cap * source_size, and the excess is shared again. That ends in
    target = min(cap * size, level * weight); sorted by size / weight, the first source below the level fixes it.
    """
    every = Window.partitionBy().orderBy(F.col("source").asc_nulls_last())
    turn = (F.row_number().over(every) - 1) % len(weights)
    weight = F.element_at(F.array(*[F.lit(w) for w in weights]), turn + 1).cast("long")
    # products of sizes and weights would leave 64 bits on large corpora
    own = sources.withColumn("weight", weight).withColumn("full", F.col("source_size").cast(WIDE) * cap)
    # exact order of full / weight: both scaled to the common multiple of the weights
    common = 1
    for w in weights:
        common *= w
    ratio = (F.col("full") * (F.lit(common) / F.col("weight")).cast("long")).cast(WIDE)
    order = Window.partitionBy().orderBy(ratio, F.col("source").asc_nulls_last())
    all_rows = order.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    before = order.rowsBetween(Window.unboundedPreceding, -1)
    own = own.withColumn("rest", (F.sum(F.col("source_size").cast(WIDE)).over(all_rows) - F.coalesce(F.sum("full").over(before), F.lit(0))).cast(WIDE))
    own = own.withColumn("heavy", F.sum("weight").over(all_rows) - F.coalesce(F.sum("weight").over(before), F.lit(0)))
    own = own.withColumn("below", F.col("full") * F.col("heavy") > F.col("rest") * F.col("weight"))
    level = F.first(F.when(F.col("below"), F.struct("rest", "heavy")), ignorenulls=True).over(all_rows)
    own = own.withColumn("level", level)
    shared = F.col("level.rest").cast("double") * F.col("weight").cast("double") / F.col("level.heavy").cast("double")
    first_below = F.min(F.when(F.col("below"), F.struct(ratio.alias("r"), F.col("source").isNull().alias("z"), F.col("source").alias("s")))).over(all_rows)
    own = own.withColumn("first", first_below)
    is_below = F.col("first").isNotNull() & (F.struct(ratio.alias("r"), F.col("source").isNull().alias("z"), F.col("source").alias("s")) >= F.col("first"))
    return own.select("source", "source_size", "weight", F.when(is_below, shared).otherwise(F.col("full").cast("double")).alias("target"))


def rates(documents: DataFrame, weights: tuple[int, ...] = (5, 2, 1), cap: int = 3, seed: str = "mix", broadcast_sources: int = 100_000) -> DataFrame:
    """documents plus size, source_size, target and copies."""
    kept = [c for c in documents.columns if c not in ADDED]
    sized = documents.select(*kept, space_words(F.col("text")).alias("size"))
    sums = sized.groupBy("source").agg(F.sum("size").alias("source_size"))
    scratch = Scratch(documents.sparkSession)
    table = scratch.store(targets(sums, weights, cap), "sources").select(F.col("source").alias("__js_source"), F.col("source_size"), F.col("target"))
    if table.count() <= broadcast_sources:
        table = F.broadcast(table)
    joined = sized.join(table, F.col("source").eqNullSafe(F.col("__js_source")), "left").drop("__js_source")
    rate = F.when(F.col("source_size") > 0, F.least(F.lit(float(cap)), F.col("target") / F.col("source_size"))).otherwise(F.lit(0.0))
    whole = F.floor(rate)
    return joined.withColumn("copies", whole + F.when(uniform(F.col("doc_id"), seed) < rate - whole, 1).otherwise(0))


def mix(documents: DataFrame, weights: tuple[int, ...] = (5, 2, 1), cap: int = 3, seed: str = "mix") -> DataFrame:
    """Each document `copies` times, with copy_no from 1 (it replaces a column of that name)."""
    packed = documents.select(F.struct("*").alias("row"), "doc_id", "text", "source")
    rated = rates(packed, weights, cap, seed).where(F.col("copies") > 0)
    turned = rated.select("row", F.explode(F.sequence(F.lit(1), F.col("copies").cast("int"))).alias("copy_no"))
    return turned.select(*[F.col("row")[c].alias(c) for c in documents.columns if c != "copy_no"], "copy_no")
