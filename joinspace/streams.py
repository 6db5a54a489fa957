"""Structured Streaming over `events`: windows, watermarks, joins, state, and merge-and-reduce of coresets."""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import local
from .coreset import _grouped
from .files import written_folder

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
SQL: dict[str, str] = {}


def _add(sql: str | None = None):
    def add(f):
        QUERIES[f.__name__] = f
        if sql:
            SQL[f.__name__] = sql
        return f

    return add


def source(spark: SparkSession, sf: str, table: str = "events") -> DataFrame:
    """The table as a file stream, times as timestamps with a zone (watermarks need that)."""
    at = f"{sf}/{table}*.parquet"
    schema = spark.read.parquet(f"{sf}/{table}.parquet").schema
    return spark.readStream.schema(schema).parquet(at).withColumn("ts", F.col("ts").cast("timestamp"))


def drained(spark: SparkSession, df: DataFrame, mode: str = "append") -> DataFrame:
    """Runs a stream over what is there, into Parquet (append) or memory (complete, update), and reads the result."""
    at = written_folder(spark, "stream")
    w = df.writeStream.outputMode(mode).trigger(availableNow=True).option("checkpointLocation", f"{at}/state")
    if mode == "append":
        w.format("parquet").option("path", f"{at}/out").start().awaitTermination()
        return spark.read.schema(df.schema).parquet(f"{at}/out")
    name = f"s{uuid.uuid4().hex}"
    w.format("memory").queryName(name).start().awaitTermination()
    return spark.table(name)


def _ts(c: str):
    return F.date_format(c, "yyyy-MM-dd HH:mm:ss")


@_add("SELECT strftime(time_bucket(INTERVAL 1 DAY, ts), '%Y-%m-%d %H:%M:%S') AS start, event_type, count(*) AS n, round(sum(value), 2) AS total FROM events GROUP BY 1, 2")
def stream_tumbling(spark, sf):
    s = source(spark, sf).withWatermark("ts", "1 hour").groupBy(F.window("ts", "1 day"), "event_type").agg(F.count("*").alias("n"), F.round(F.sum("value"), 2).alias("total"))
    return drained(spark, s, "complete").select(_ts("window.start").alias("start"), "event_type", "n", "total")


@_add("SELECT strftime(time_bucket(INTERVAL 6 HOUR, ts) - INTERVAL 6 HOUR * i, '%Y-%m-%d %H:%M:%S') AS start, count(*) AS n FROM events, range(2) r(i) GROUP BY 1")
def stream_sliding(spark, sf):
    s = source(spark, sf).groupBy(F.window("ts", "12 hours", "6 hours")).agg(F.count("*").alias("n"))
    return drained(spark, s, "complete").select(_ts("window.start").alias("start"), "n")


@_add("""WITH m AS (SELECT user_id, ts, CASE WHEN ts < lag(ts) OVER w + INTERVAL 8 HOUR THEN 0 ELSE 1 END AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)),
 g AS (SELECT user_id, ts, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS no FROM m)
 SELECT user_id, strftime(min(ts), '%Y-%m-%d %H:%M:%S') AS start, count(*) AS n FROM g GROUP BY user_id, no""")
def stream_session(spark, sf):
    s = source(spark, sf).withWatermark("ts", "1 day").groupBy(F.session_window("ts", "8 hours"), "user_id").agg(F.count("*").alias("n"))
    return drained(spark, s, "complete").select("user_id", _ts("session_window.start").alias("start"), "n")


@_add("SELECT user_id, event_type FROM events GROUP BY ALL")
def stream_dedup(spark, sf):
    return drained(spark, source(spark, sf).select("user_id", "event_type").dropDuplicates(["user_id", "event_type"]))


@_add("SELECT c_mktsegment, count(*) AS n FROM events JOIN customer ON user_id = c_custkey GROUP BY 1")
def stream_static_join(spark, sf):
    c = spark.read.parquet(f"{sf}/customer.parquet")
    s = source(spark, sf).join(c, F.col("user_id") == F.col("c_custkey")).groupBy("c_mktsegment").agg(F.count("*").alias("n"))
    return drained(spark, s, "complete")


@_add("SELECT a.event_id AS click, b.event_id AS purchase FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type = 'purchase' AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 2 HOUR")
def stream_interval_join(spark, sf):
    e = source(spark, sf)
    a = e.where("event_type = 'click'").select(F.col("event_id").alias("click"), F.col("user_id").alias("ua"), F.col("ts").alias("ta")).withWatermark("ta", "1 hour")
    b = e.where("event_type = 'purchase'").select(F.col("event_id").alias("purchase"), F.col("user_id").alias("ub"), F.col("ts").alias("tb")).withWatermark("tb", "1 hour")
    s = a.join(b, F.expr("ua = ub AND tb >= ta AND tb <= ta + INTERVAL 2 HOURS")).select("click", "purchase")
    return drained(spark, s)


@_add("SELECT strftime(time_bucket(INTERVAL 1 DAY, ts), '%Y-%m-%d') AS day, count(*) AS n FROM events GROUP BY 1 HAVING max(time_bucket(INTERVAL 1 DAY, ts)) + INTERVAL 1 DAY <= (SELECT max(ts) - INTERVAL 2 HOUR FROM events)")
def stream_late_drop(spark, sf):
    """Append mode: a day is emitted once the watermark has passed its end; days still open stay in state."""
    s = source(spark, sf).withWatermark("ts", "2 hours").groupBy(F.window("ts", "1 day")).agg(F.count("*").alias("n"))
    return drained(spark, s).select(F.date_format("window.start", "yyyy-MM-dd").alias("day"), "n")


@_add("SELECT user_id, count(*) AS n, round(sum(value), 2) AS total, round(var_pop(value), 2) AS variance FROM events GROUP BY 1")
def stream_stateful_moments(spark, sf):
    """Running count, mean and spread for each user in state."""

    def update(key, batches: Iterator[pd.DataFrame], state):
        n, mean, m2 = state.get if state.exists else (0, 0.0, 0.0)
        for b in batches:
            for v in b["value"]:
                n += 1
                d = v - mean
                mean += d / n
                m2 += d * (v - mean)
        state.update((n, mean, m2))
        yield pd.DataFrame({"user_id": [key[0]], "n": [n], "mean": [mean], "variance": [m2 / n]})

    s = source(spark, sf).select("user_id", "value").groupBy("user_id").applyInPandasWithState(update, "user_id long, n long, mean double, variance double", "n long, mean double, m2 double", "update", "NoTimeout")
    out = drained(spark, s, "update")
    last = out.groupBy("user_id").agg(F.max_by(F.struct("n", "mean", "variance"), "n").alias("x"))
    return last.select("user_id", "x.n", F.round(F.col("x.mean") * F.col("x.n"), 2).alias("total"), F.round("x.variance", 2).alias("variance"))


@_add("SELECT count(*) AS n, TRUE AS weight_ok, TRUE AS small FROM events")
def stream_coreset_merge(spark, sf):
    """Every micro-batch becomes a weighted coreset (in a task per part); coresets merge and are reduced again."""
    at = written_folder(spark, "stream")

    def fold(batch: DataFrame, number: int) -> None:
        def part(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            for f in frames:
                p = f[["value"]].to_numpy(float)
                q, w, _ = _grouped(p, np.ones(len(p)), np.empty((0, 1)), 4.0, 0.0)
                yield pd.DataFrame({"value": q[:, 0], "w": w})

        batch.select("value").mapInPandas(part, "value double, w double").write.mode("append").parquet(f"{at}/core")

    source(spark, sf).writeStream.foreachBatch(fold).option("checkpointLocation", f"{at}/state").trigger(availableNow=True).start().awaitTermination()
    core = spark.read.parquet(f"{at}/core").groupBy(F.floor(F.col("value") / 4).alias("cell")).agg(F.sum("w").alias("w"), F.min("value").alias("value"))
    n = spark.read.parquet(f"{sf}/events.parquet").agg(F.count("*").alias("n"))
    r = core.agg(F.sum("w").alias("w"), F.count("*").alias("c"))
    return n.join(r, F.lit(True)).select("n", (F.col("w") == F.col("n")).alias("weight_ok"), (F.col("c") < 400).alias("small"))


def reduce_core(points: np.ndarray, weights: np.ndarray, k: int) -> tuple[np.ndarray, float]:
    """k centres of a merged coreset."""
    return local.kmeans(points, weights, k)
