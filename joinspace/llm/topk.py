"""Exact top-k inner products over norm-sorted vectors with SVD-rotated partial sums.

Candidates are sorted by length into ranges, longest first, and a range into chunks of about `chunk_rows`. A query's floor is its k-th best
score among the `longest` longest candidates; by Cauchy-Schwarz it needs no range whose longest vector is shorter than floor / |query|, its
cutoff. Queries are sorted by cutoff into bands, and a band into blocks of about `block_rows`: a block meets exactly the chunks of the ranges
down to the smallest cutoff of its band, and all other pairs are dropped before anything is shuffled. A task takes one block against one
chunk, so both sides scale out; what is broadcast is the rotation, `longest` vectors, and at most `bounds` lengths a side.

In a task the chunk lies by descending length. The leading coordinates after rotation by the eigenvectors of the Gram matrix give a partial
inner product; Cauchy-Schwarz on the rest bounds the score. A candidate is dropped when that bound is below the query's k-th
best score so far; the walk ends once length times length is too small. What survives is scored in integers, so results and ties are exact.

Defined cases: vectors that are null or hold null or non-finite components take no part, nor do those with a component of 2**20 or more,
whose scores may leave 64 bits, nor rows with a null vec_id; vectors of unequal length are padded with zeros; equal scores rank by smaller
vec_id; fewer than k candidates give fewer rows; a repeated vec_id is never its own neighbour, each of its rows is a candidate, and
as a query it is its least vector (in the order of arrays); empty tables give no rows; extra columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import Scratch


#: Stands for a missing floor; below every score.
NO_FLOOR = -(2**63)


def whole(vectors: DataFrame, scale: int = 256) -> DataFrame:
    """(vec_id, v array<long>): floor(scale * x), rows that take part only."""
    x = F.col("embedding").cast("array<double>")
    bad = F.exists(x, lambda y: y.isNull() | F.isnan(y) | (F.abs(y) >= float(1 << 20)))
    own = vectors.select("vec_id", x.alias("embedding")).where(x.isNotNull() & F.col("vec_id").isNotNull()).where(~F.coalesce(bad, F.lit(True)))
    return own.select("vec_id", F.transform("embedding", lambda y: F.floor(y * scale)).alias("v"))


def gram(vectors: DataFrame, width: int) -> np.ndarray:
    """Sum of outer products; every task sends one matrix."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros((width, width))
        for batch in batches:
            m = _matrix(batch.column(0), width).astype(float)
            total += m.T @ m
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(width * width)), pa.array(total.ravel())], ["at", "x"])

    rows = vectors.select("v").mapInArrow(run, "at long, x double").groupBy("at").agg(F.sum("x").alias("x")).collect()  # width**2 rows
    out = np.zeros(width * width)
    for r in rows:
        out[r["at"]] = r["x"]
    return out.reshape(width, width)


def _matrix(column, width: int) -> np.ndarray:
    out = np.zeros((len(column), width), np.int64)
    lists = column.to_pylist() if isinstance(column, (pa.Array, pa.ChunkedArray)) else column
    for i, v in enumerate(lists):
        out[i, : len(v)] = v
    return out


class Chunk:
    """Candidates by descending length, with rotated heads and residual lengths."""

    def __init__(self, ids: np.ndarray, vectors: np.ndarray, turn: np.ndarray, head: int):
        length = np.linalg.norm(vectors.astype(float), axis=1)
        order = np.lexsort((ids, -length))
        self.ids, self.vectors, self.length = ids[order], vectors[order], length[order]
        rotated = self.vectors.astype(float) @ turn[:, :head]
        self.head = rotated
        self.rest = np.sqrt(np.maximum(0.0, self.length**2 - (rotated**2).sum(1)))
        self.turn, self.width = turn, head
        self.floats = self.vectors.astype(float)
        self.small = float(np.abs(self.floats).max(initial=0)) ** 2 * vectors.shape[1] < 2**52

    def best(self, own: int, q: np.ndarray, k: int, floor: int | None, step: int = 2048) -> tuple[np.ndarray, np.ndarray]:
        size = float(np.linalg.norm(q.astype(float)))
        head = q.astype(float) @ self.turn[:, : self.width]
        rest = float(np.sqrt(max(0.0, size**2 - (head**2).sum())))
        have_s, have_i = np.empty(0, np.int64), np.empty(0, np.int64)
        for at in range(0, len(self.ids), step):
            need = floor
            if len(have_s) >= k:
                need = int(have_s[k - 1]) if need is None else max(need, int(have_s[k - 1]))
            slack = 1e-9 * size * self.length[at] + 1e-6
            if need is not None and size * self.length[at] + slack < need:
                break  # every later vector is shorter
            part = slice(at, at + step)
            live = np.arange(at, min(at + step, len(self.ids)))
            if need is not None:
                live = live[self.head[part] @ head + self.rest[part] * rest + slack >= need]
            live = live[self.ids[live] != own]
            if not len(live):
                continue
            if self.small and float(np.abs(q).max(initial=0)) * float(np.abs(self.floats[live]).max(initial=0)) * len(q) < 2**52:
                score = (self.floats[live] @ q.astype(float)).astype(np.int64)  # every partial sum is an exact integer
            else:
                score = self.vectors[live] @ q
            have_s, have_i = np.concatenate([have_s, score]), np.concatenate([have_i, self.ids[live]])
            order = np.lexsort((have_i, -have_s))[:k]
            have_s, have_i = have_s[order], have_i[order]
        return have_i, have_s


def bounds_of(frame: DataFrame, column: str, pieces: int) -> np.ndarray:
    """Descending lower ends of about equally large ranges of a column; the last range has no lower end."""
    if pieces < 2:
        return np.empty(0)
    cuts = frame.select(F.percentile_approx(column, [i / pieces for i in range(1, pieces)], 100_000).alias("x")).first()["x"]
    return np.unique(np.array(cuts, float))[::-1]


def top_k(candidates: DataFrame, queries: DataFrame, k: int = 5, chunk_rows: int = 16_384, block_rows: int = 1024, head_share: float = 0.5, longest: int = 2048, bounds: int = 1024) -> DataFrame:
    """(query_id, rank, vec_id, score) from `whole` candidates and queries."""
    spark = candidates.sparkSession
    scratch = Scratch(spark)
    norm = F.sqrt(F.aggregate("v", F.lit(0.0), lambda s, x: s + x.cast("double") * x.cast("double")))
    pool = scratch.store(candidates.select("vec_id", "v", norm.alias("norm")), "candidates")
    asked = scratch.store(queries.groupBy("vec_id").agg(F.min("v").alias("v")), "queries")
    facts = pool.agg(F.count("*").alias("n"), F.max(F.size("v")).alias("w")).first()
    wide = asked.agg(F.count("*").alias("n"), F.max(F.size("v")).alias("w")).first()
    if not facts["n"] or not wide["n"]:
        return spark.createDataFrame([], "query_id long, rank int, vec_id long, score long")
    width = max(facts["w"], wide["w"], 1)
    turn = np.linalg.eigh(gram(pool, width))[1][:, ::-1].copy()
    head = max(1, int(width * head_share))
    top = pool.orderBy(F.desc("norm"), "vec_id").limit(longest).select("vec_id", "v").toPandas()  # `longest` rows, a parameter
    shared = spark.sparkContext.broadcast((turn, top["vec_id"].to_numpy(np.int64), _matrix(list(top["v"]), width)))

    def floors(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        start = Chunk(*shared.value[1:], shared.value[0], head)
        for batch in batches:
            ids, vectors = batch.column(0).to_numpy(), _matrix(batch.column(1), width)
            floor, cutoff = [], []
            for own, q in zip(ids, vectors, strict=True):
                got, scores = start.best(own, q, k, None)
                # a vec_id that counts twice towards k gives no floor
                sure = len(got) >= k and len(set(got.tolist())) == len(got)
                size = float(np.linalg.norm(q.astype(float)))
                floor.append(int(scores[k - 1]) if sure else NO_FLOOR)
                cutoff.append(max(0.0, float(scores[k - 1]) / size * (1 - 1e-9) - 1e-6) if sure and size else 0.0)
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(floor, pa.int64()), pa.array(cutoff, pa.float64())], ["vec_id", "v", "floor", "cutoff"])

    asked = scratch.store(asked.select("vec_id", "v").mapInArrow(floors, "vec_id long, v array<long>, floor long, cutoff double"), "floors")
    chunks, blocks = -(-facts["n"] // chunk_rows), -(-wide["n"] // block_rows)
    ranges, bands = bounds_of(pool, "norm", min(chunks, bounds)), bounds_of(asked, "cutoff", min(blocks, bounds))
    chunk_salts, block_salts = -(-chunks // (len(ranges) + 1)), -(-blocks // (len(bands) + 1))
    # the longest vector of a range and the smallest cutoff of a band, exactly
    tallest, least = np.full(len(ranges) + 1, -np.inf), np.full(len(bands) + 1, np.inf)
    for r in pool.groupBy(numbered(F.col("norm"), ranges).alias("r")).agg(F.max("norm").alias("x")).collect():  # at most `bounds` rows
        tallest[r["r"]] = r["x"]
    for r in asked.groupBy(numbered(F.col("cutoff"), bands).alias("r")).agg(F.min("cutoff").alias("x")).collect():
        least[r["r"]] = r["x"]
    spread = lambda n, salt: F.pmod(F.xxhash64(F.col("vec_id"), F.lit(salt)), F.lit(n)).cast("int")
    # a range is needed by the bands from first[range] on, a band needs the ranges down to last[band]
    first = [int(min(np.flatnonzero(least <= t), default=len(least))) for t in tallest]
    last = [max((r for r, f in enumerate(first) if f <= b), default=-1) for b in range(len(least))]
    number = lambda values: F.element_at(F.array(*[F.lit(v) for v in values]), F.col("r") + 1)
    every = lambda n: F.explode(F.sequence(F.lit(0), F.lit(n - 1)))
    left = pool.withColumn("r", numbered(F.col("norm"), ranges)).where(number(first) < len(least))
    left = left.select("vec_id", "v", F.col("r").alias("range"), spread(chunk_salts, "c").alias("chunk"), F.explode(F.sequence(number(first), F.lit(len(least) - 1))).alias("band"))
    left = left.select("*", every(block_salts).alias("block"))
    right = asked.withColumn("r", numbered(F.col("cutoff"), bands)).where(number(last) >= 0).select("vec_id", "v", "floor", F.col("r").alias("band"), spread(block_salts, "b").alias("block"), F.explode(F.sequence(F.lit(0), number(last))).alias("range"))
    right = right.select("*", every(chunk_salts).alias("chunk"))

    def of(rows: pd.DataFrame) -> tuple[np.ndarray, np.ndarray]:
        return rows["vec_id"].to_numpy(np.int64), _matrix(list(rows["v"]), width)

    def run(key: tuple, left: pd.DataFrame, right: pd.DataFrame) -> pd.DataFrame:
        chunk = Chunk(*of(left), shared.value[0], head)
        out_q, out_i, out_s = [], [], []
        for own, q, floor in zip(*of(right), right["floor"].tolist(), strict=True):
            i, s = chunk.best(own, q, k, None if floor == NO_FLOOR else floor)
            out_q.append(np.full(len(i), own)), out_i.append(i), out_s.append(s)
        flat = lambda x: np.concatenate(x) if x else np.empty(0, np.int64)
        return pd.DataFrame({"query_id": flat(out_q), "vec_id": flat(out_i), "score": flat(out_s)})

    pair = ["range", "chunk", "band", "block"]
    each = left.groupBy(*pair).cogroup(right.groupBy(*pair)).applyInPandas(run, "query_id long, vec_id long, score long")
    return ranked(each, k)


def numbered(x: Column, lower: np.ndarray) -> Column:
    """`range_of` as an expression: the number of bounds above x, by bisection over nested conditions."""

    def cut(lo: int, hi: int) -> Column:
        if lo == hi:
            return F.lit(lo)
        mid = (lo + hi) // 2
        return F.when(x >= F.lit(float(lower[mid])), cut(lo, mid)).otherwise(cut(mid + 1, hi))

    return cut(0, len(lower))


def ranked(scores: DataFrame, k: int) -> DataFrame:
    """At most k rows a chunk come in for a query: a small window."""
    order: Column = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return scores.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
