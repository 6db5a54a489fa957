"""Round trips through file formats, Python function surfaces, a table function and a small data source."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import local
from .files import written_folder
from .region import Box, Region
from .relops import QUERIES, SQL, op, t
from .sources.centres import CentreSource

__all__ = ["QUERIES", "SQL", "CentreSource", "register"]


def _trip(kind: str):
    def run(spark: SparkSession, sf: str) -> DataFrame:
        rows = t(spark, sf, "nation")
        at = written_folder(spark, "trip")
        w = rows.write.format(kind)
        (w.partitionBy("n_regionkey") if kind == "parquet" else w).save(at)
        return spark.read.schema(rows.schema).format(kind).load(at).select(*rows.columns)

    return run


for _k in ("csv", "json", "orc", "parquet"):
    op("SELECT n_nationkey, n_name, n_regionkey FROM nation", f"op_roundtrip_{_k}")(_trip(_k))


@op("SELECT l_orderkey, l_linenumber, l_partkey, round(sqrt((l_quantity - 25) ** 2 + (100 * l_discount - 5) ** 2), 4) AS d FROM lineitem")
def op_udf_pandas(spark, sf):
    @F.pandas_udf("double")
    def distance(q: pd.Series, x: pd.Series) -> pd.Series:
        return np.sqrt((q - 25) ** 2 + (100 * x - 5) ** 2)

    return t(spark, sf, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey", F.round(distance("l_quantity", "l_discount"), 4).alias("d"))


@op("SELECT l_returnflag, round(sum(l_quantity * l_extendedprice) / sum(l_quantity), 3) AS centroid FROM lineitem GROUP BY 1")
def op_udaf_pandas(spark, sf):
    """Weighted centroid. Parts are summed natively first, so that no group meets whole in Python."""
    part = t(spark, sf, "lineitem").groupBy("l_returnflag", "l_linenumber").agg(F.sum(F.col("l_quantity") * F.col("l_extendedprice")).alias("a"), F.sum("l_quantity").alias("b"))

    @F.pandas_udf("double")
    def ratio(a: pd.Series, b: pd.Series) -> float:
        return float(a.sum() / b.sum())

    return part.groupBy("l_returnflag").agg(ratio("a", "b").alias("c")).select("l_returnflag", F.round("c", 3).alias("centroid"))


@op("SELECT c_nationkey, CAST(least(3, count(DISTINCT c_acctbal)) AS BIGINT) AS n, min(c_acctbal) AS first FROM customer GROUP BY 1")
def op_apply_in_pandas(spark, sf):
    """Farthest-first of three balances for each nation, from the least one."""

    def run(rows: pd.DataFrame) -> pd.DataFrame:
        p = np.unique(rows["c_acctbal"].to_numpy(float))[:, None]
        got = local.farthest_first(p, 3)
        return pd.DataFrame({"c_nationkey": [int(rows["c_nationkey"].iloc[0])], "n": [len(got)], "first": [float(got[0, 0])]})

    return t(spark, sf, "customer").select("c_nationkey", "c_acctbal").groupBy("c_nationkey").applyInPandas(run, "c_nationkey int, n long, first double")


@op("SELECT count(*) AS n FROM lineitem WHERE (l_quantity - 25) ** 2 + (100 * l_discount - 5) ** 2 <= 16")
def op_map_in_pandas(spark, sf):
    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for f in frames:
            inside = (f["l_quantity"] - 25) ** 2 + (100 * f["l_discount"] - 5) ** 2 <= 16
            yield pd.DataFrame({"n": [int(inside.sum())]})

    return t(spark, sf, "lineitem").select("l_quantity", "l_discount").mapInPandas(run, "n long").agg(F.sum("n").alias("n"))


@op("SELECT n_nationkey AS nk, (SELECT count(*) FROM customer WHERE c_nationkey = n_nationkey) * (SELECT count(*) FROM supplier WHERE s_nationkey = n_nationkey) AS pairs FROM nation WHERE pairs > 0")
def op_cogroup(spark, sf):
    """Join pairs of each nation from two sides that were counted first."""
    c = t(spark, sf, "customer").groupBy(F.col("c_nationkey").alias("nk")).agg(F.count("*").alias("n"))
    s = t(spark, sf, "supplier").groupBy(F.col("s_nationkey").alias("nk")).agg(F.count("*").alias("n"))

    def run(a: pd.DataFrame, b: pd.DataFrame) -> pd.DataFrame:
        if not len(a) or not len(b):
            return pd.DataFrame({"nk": [], "pairs": []}).astype({"nk": "int32", "pairs": "int64"})
        return pd.DataFrame({"nk": [int(a["nk"].iloc[0])], "pairs": [int(a["n"].iloc[0] * b["n"].iloc[0])]})

    return c.groupBy("nk").cogroup(s.groupBy("nk")).applyInPandas(run, "nk int, pairs long")


@F.udtf(returnType="slab int, lo array<double>, hi array<double>")
class BoxSlabs:
    """Disjoint boxes whose union is an outer box without an inner one."""

    def eval(self, lo: list, hi: list, hole_lo: list, hole_hi: list):
        r = Region(Box(np.array(lo), np.array(hi)), Box(np.array(hole_lo), np.array(hole_hi)))
        for i, b in enumerate(r.slabs()):
            yield i, [float(x) for x in b.lo], [float(x) for x in b.hi]


def register(spark: SparkSession) -> None:
    """box_slabs(lo, hi, hole_lo, hole_hi) for SQL users."""
    spark.udtf.register("box_slabs", BoxSlabs)
    spark.dataSource.register(CentreSource)


@op("SELECT count(*) AS slabs, (SELECT count(*) FROM lineitem WHERE l_quantity < 40 AND l_discount < 0.1 AND NOT (l_quantity >= 10 AND l_quantity < 20 AND l_discount >= 0.02 AND l_discount < 0.05)) AS n FROM range(4)")
def op_udtf_slabs(spark, sf):
    register(spark)
    slabs = spark.sql("SELECT * FROM box_slabs(array(0.0D, 0.0D), array(40.0D, 0.1D), array(10.0D, 0.02D), array(20.0D, 0.05D))")
    rows = t(spark, sf, "lineitem").groupBy("l_quantity", "l_discount").agg(F.count("*").alias("w"))
    test = (F.col("l_quantity") >= F.col("lo")[0]) & (F.col("l_quantity") < F.col("hi")[0]) & (F.col("l_discount") >= F.col("lo")[1]) & (F.col("l_discount") < F.col("hi")[1])
    return rows.join(F.broadcast(slabs), test).agg(F.countDistinct("slab").alias("slabs"), F.sum("w").alias("n"))


@op("SELECT c_nationkey AS center_id, round(avg(c_custkey), 3) AS x, round(avg(c_acctbal), 3) AS y, count(*) AS n FROM customer GROUP BY 1")
def op_source_centres(spark, sf):
    """One centre for each nation's customers goes through the data source, and is served with the number of its customers."""
    register(spark)
    c = t(spark, sf, "customer").groupBy("c_nationkey").agg(F.avg("c_custkey").alias("x"), F.avg("c_acctbal").alias("y"), F.count("*").alias("n")).orderBy("c_nationkey").collect()  # a row a nation
    numbers = F.broadcast(spark.createDataFrame([(i, r["c_nationkey"], r["n"]) for i, r in enumerate(c)], "i int, nation int, n long"))
    centres = spark.read.format("centres").option("centres", ";".join(f"{float(r['x'])!r},{float(r['y'])!r}" for r in c)).load()
    return centres.join(numbers, F.col("center_id") == F.col("i")).select(F.col("nation").alias("center_id"), F.round(F.col("coords")[0], 3).alias("x"), F.round(F.col("coords")[1], 3).alias("y"), "n")


_DRAW = "CAST(('0x' || substr(md5('w' || i), 1, 8)) AS BIGINT) / 4294967296.0"


@op(f"""WITH o AS (SELECT o_custkey, sum(CAST(round(o_totalprice) AS BIGINT)) AS w FROM orders GROUP BY 1), c AS (SELECT o_custkey, sum(w) OVER (ORDER BY o_custkey) AS hi, w FROM o),
 d AS (SELECT i, {_DRAW} * (SELECT sum(w) FROM o) AS x FROM range(50) r(i)) SELECT i AS draw, o_custkey FROM d JOIN c ON x >= hi - w AND x < hi""")
def op_sample_weighted(spark, sf):
    """Inverse CDF: totals per bucket of keys come first, so no window holds all rows."""
    o = t(spark, sf, "orders").groupBy("o_custkey").agg(F.sum(F.round("o_totalprice").cast("long")).alias("w")).withColumn("bucket", F.floor(F.col("o_custkey") / 256))
    sums = o.groupBy("bucket").agg(F.sum("w").alias("b"))
    before = sums.withColumn("base", F.sum("b").over(Window.partitionBy().orderBy("bucket")) - F.col("b")).select("bucket", "base")  # one row a bucket
    c = o.join(before, "bucket").withColumn("hi", F.col("base") + F.sum("w").over(Window.partitionBy("bucket").orderBy("o_custkey")))
    total = o.agg(F.sum("w").alias("total"))
    u = F.conv(F.substring(F.md5(F.concat(F.lit("w"), F.col("id").cast("string"))), 1, 8), 16, 10).cast("long") / F.lit(4294967296.0)
    d = spark.range(50).select(F.col("id").alias("draw"), u.alias("u")).join(F.broadcast(total), F.lit(True)).withColumn("x", F.col("u") * F.col("total"))
    return c.join(F.broadcast(d), (F.col("x") >= F.col("hi") - F.col("w")) & (F.col("x") < F.col("hi"))).select("draw", "o_custkey")
